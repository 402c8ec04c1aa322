"""Splitting texts into units that recur, so that work on a unit is done once in a worker."""

from __future__ import annotations

import re

#: ASCII white space of the word contract [^\x20\x09-\x0D]+; bytes.split() splits at just these.
WHITE = " \t\n\x0b\x0c\r"

_CUT = re.compile(r"(?<=\S)(?= )")


class Memo(dict):
    """A bounded memo in two generations: a worker's memory stays flat and what recurs stays in it."""

    def __init__(self, make, most: int = 400_000):
        super().__init__()
        self.make, self.most, self.old = make, most, {}

    def __missing__(self, key):
        if len(self) >= self.most:
            self.old = dict(self)
            self.clear()
        value = self.old[key] if key in self.old else self.make(key)
        self[key] = value
        return value


def cut_at_spaces(text: str) -> list[str]:
    """Units of a text: it is cut before each space behind a non-space.

    A piece of the byte-level pre-tokeniser never holds a space behind a non-space, so the units
    encode alone to what they encode to within the text.
    """
    return _CUT.split(text)
