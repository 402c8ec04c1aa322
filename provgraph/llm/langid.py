"""Language identification: script ranges narrow the candidates, Viterbi labels spans of mixed texts.

A word's script (of its first letter) leaves the languages seen in that script; the words get the
log-likelihood of their letter trigrams under each, and a path through the words pays a penalty for each
switch.  The best path gives the spans; the language with most letters is the document's.

The path that keeps to one language is the best one whenever no stretch of words gains more in another language than one
switch costs, nor a beginning and an end together: a path of k stretches has k - 1 switches to pay, so only one that leaves the language
out altogether has a stretch more than switches.  That is checked by sums over the words, and only other texts go through the recursion.

Fit: rows outside the held-out fold with a language, thinned by hash to about `max_train_docs` for each language;
at most `max_grams` trigrams.  Labelling covers every row and whole texts.

A word in a script that no language was learned in has no candidate: its letters count as of none.  The evidence of a text is the mean
log-likelihood of a letter on the path; a text fits its language if that is within the limit which the learned texts set.

Defined results: a text that is null or has no letter of a learned script is `und` with score 0 and no spans; so is every text if
nothing could be learned; a text with more letters of unlearned scripts than of any language is `und` with score 0; words without letters join the span around them; repeated rows get a row each.
"""

from __future__ import annotations

import math
from bisect import bisect_right
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StringType, StructField, StructType

from .runtime import Stage, fold, ship
from .units import Memo

UNKNOWN = "und"
# First code point of each range and its script (Unicode blocks, coarse).
SCRIPT_RANGES = (
    (0x0000, "Latin"), (0x0370, "Greek"), (0x0400, "Cyrillic"), (0x0530, "Armenian"), (0x0590, "Hebrew"),
    (0x0600, "Arabic"), (0x0700, "Syriac"), (0x0750, "Arabic"), (0x0780, "Thaana"), (0x07C0, "Other"),
    (0x0900, "Devanagari"), (0x0980, "Bengali"), (0x0A00, "Gurmukhi"), (0x0A80, "Gujarati"), (0x0B00, "Oriya"),
    (0x0B80, "Tamil"), (0x0C00, "Telugu"), (0x0C80, "Kannada"), (0x0D00, "Malayalam"), (0x0D80, "Sinhala"),
    (0x0E00, "Thai"), (0x0E80, "Lao"), (0x0F00, "Tibetan"), (0x1000, "Myanmar"), (0x10A0, "Georgian"),
    (0x1100, "Hangul"), (0x1200, "Ethiopic"), (0x13A0, "Other"), (0x1E00, "Latin"), (0x1F00, "Greek"),
    (0x2000, "Other"), (0x3040, "Kana"), (0x3100, "Han"), (0x3130, "Hangul"), (0x31A0, "Han"), (0x31F0, "Kana"),
    (0x3200, "Han"), (0xA4D0, "Other"), (0xAC00, "Hangul"), (0xD7B0, "Other"), (0xF900, "Han"), (0xFB00, "Latin"),
    (0xFB1D, "Hebrew"), (0xFB50, "Arabic"), (0xFE00, "Other"), (0xFF21, "Latin"), (0xFF66, "Kana"), (0xFFA0, "Hangul"),
    (0x10000, "Other"), (0x20000, "Han"), (0x323B0, "Other"),
)
_STARTS = [a for a, _ in SCRIPT_RANGES]
#: A language is a candidate in a script that holds at least this share of its letters.
LEAST_SHARE = 0.01
OUT_OF_SCRIPT = -60.0
#: The limit of evidence lies LOW_TIMES as far below the median of learned texts as their LOW quantile does.
LOW, LOW_TIMES = 0.05, 3.0
#: Different words of a language that a task holds before it counts their trigrams, and those whose scores a worker remembers.
HELD_WORDS, REMEMBERED = 100_000, 100_000


def script(c: str) -> str:
    return SCRIPT_RANGES[bisect_right(_STARTS, ord(c)) - 1][1]


def trigrams(word: str) -> list[str]:
    s = f" {word} "
    return [s[i : i + 3] for i in range(len(s) - 2)]


def words_of(text: str | None) -> list[str]:
    """Runs without white space, full stop and comma, in lower case."""
    return (text or "").lower().replace(".", " ").replace(",", " ").split()


def letters_of(token: str) -> str:
    return token if token.isalpha() else "".join(filter(str.isalpha, token))


@dataclass
class LanguageModel:
    languages: list[str] = field(default_factory=list)
    scores: dict[str, tuple] = field(default_factory=dict)
    floor: tuple = ()
    scripts: dict[str, tuple] = field(default_factory=dict)
    #: Least evidence of a text that fits the language.
    limits: dict[str, float] = field(default_factory=dict)

    @classmethod
    def fit(cls, counts: list[tuple[str, str, int]], scripts: list[tuple[str, str, int]], smoothing: float = 0.5) -> LanguageModel:
        """counts: (language, trigram, n); scripts: (language, script, letters)."""
        languages = sorted({x for x, _, _ in counts})
        k = {x: i for i, x in enumerate(languages)}
        table: dict[str, list[float]] = {}
        total = [0.0] * len(languages)
        for x, g, n in counts:
            table.setdefault(g, [0.0] * len(languages))[k[x]] += n
            total[k[x]] += n
        size = len(table) + 1
        base = [t + smoothing * size for t in total]
        scores = {g: tuple(math.log((n + smoothing) / b) for n, b in zip(row, base)) for g, row in table.items()}
        letters = Counter()
        for x, _, n in scripts:
            letters[x] += n
        known: dict[str, list[bool]] = {}
        for x, s, n in scripts:
            if x in k and n >= LEAST_SHARE * letters[x]:
                known.setdefault(s, [False] * len(languages))[k[x]] = True
        return cls(languages, scores, tuple(math.log(smoothing / b) for b in base), {s: tuple(0.0 if y else OUT_OF_SCRIPT for y in row) for s, row in known.items()})


class Labeller:
    def __init__(self, model: LanguageModel, penalty: float = 8.0):
        self.model, self.penalty = model, penalty
        self.rows = np.zeros((1024, len(model.languages)))
        self.size = np.zeros(1024, np.int64)
        self.top = np.zeros(1024)
        self.foreign = np.zeros(1024, np.int64)
        self.next = 0
        self.index = Memo(self._add, REMEMBERED)

    def _add(self, token: str) -> int:
        """Index of the token's scores and number of letters; the tables start anew together with the memo."""
        if not self.index:
            self.index.old, self.next = {}, 0
        i, self.next = self.next, self.next + 1
        if i == len(self.size):
            self.rows, self.size, self.top, self.foreign = (np.concatenate([x, np.zeros_like(x)]) for x in (self.rows, self.size, self.top, self.foreign))
        word = letters_of(token)
        narrow = self.model.scripts.get(script(word[0])) if word else None
        self.size[i], self.foreign[i] = (0, len(word)) if narrow is None else (len(word), 0)
        if narrow is None:
            self.rows[i] = self.top[i] = 0
            return i
        m, padded = self.model, f" {word} "
        get, floor = m.scores.get, m.floor
        row = [sum(c) for c in zip(*[get(padded[k : k + 3], floor) for k in range(len(word))])]
        row = [a + b for a, b in zip(row, narrow)]
        self.top[i] = top = max(row)
        self.rows[i] = [x - top for x in row]
        return i

    def path(self, scores: np.ndarray) -> np.ndarray:
        """Best language of each word."""
        best = int(scores.sum(0).argmax())
        gain = np.zeros((len(scores) + 1, scores.shape[1]))
        np.cumsum(scores - scores[:, best : best + 1], 0, out=gain[1:])
        ends = gain.max() + (gain[-1] - gain).max()
        if ends <= self.penalty and (gain - np.minimum.accumulate(gain)).max() <= self.penalty:
            return np.full(len(scores), best)
        v, tops, switched = [0.0] * scores.shape[1], [], []
        for row in scores.tolist():
            top = max(v)
            tops.append(v.index(top))
            top -= self.penalty
            switched.append([x < top for x in v])
            v = [(x if x >= top else top) + y for x, y in zip(v, row)]
        out = np.empty(len(scores), np.int64)
        x = v.index(max(v))
        for t in range(len(scores) - 1, -1, -1):
            out[t] = x
            if switched[t][x]:
                x = tops[t]
        return out

    def label(self, text: str | None) -> tuple[str, float, list[tuple[int, int, str]]]:
        """Language, share of letters in it, and spans (first word, words, language)."""
        return self.judge(text)[:3]

    def judge(self, text: str | None) -> tuple[str, float, list[tuple[int, int, str]], float | None]:
        """The label and the evidence, None where no letter has a candidate."""
        tokens = words_of(text)
        if not tokens or not self.model.languages:
            return UNKNOWN, 0.0, [], None
        if len(self.index) + len(tokens) > self.index.most:  # no renewal within a text
            self.index.clear()
            self.index.most = max(self.index.most, len(tokens) + 1)
        at = np.fromiter(map(self.index.__getitem__, tokens), np.int64, len(tokens))
        size = self.size[at]
        if not size.any():
            return UNKNOWN, 0.0, [], None
        rows = self.rows[at]
        path = self.path(rows)
        by = np.bincount(path, size, len(self.model.languages))
        best, foreign = int(by.argmax()), int(self.foreign[at].sum())
        evidence = float((self.top[at].sum() + rows[np.arange(len(path)), path].sum()) / size.sum())
        cuts = np.r_[0, np.flatnonzero(np.diff(path)) + 1, len(path)]
        spans = [(int(a), int(b - a), self.model.languages[path[a]]) for a, b in zip(cuts, cuts[1:])]
        if foreign > by[best]:
            return UNKNOWN, 0.0, spans, evidence
        return self.model.languages[best], float(by[best] / (by.sum() + foreign)), spans, evidence


def _counted(rows: DataFrame) -> DataFrame:
    """(kind, lang, item, n) of all rows (text, lang): trigrams (kind 0) and letters by script (kind 1)."""
    most = HELD_WORDS

    def run(batches):
        words: dict[str, Counter] = {}
        totals: dict[str, tuple[Counter, Counter]] = {}

        def fold_in():
            for x, tokens in words.items():
                grams, scripts = totals.setdefault(x, (Counter(), Counter()))
                for token, n in tokens.items():
                    if word := letters_of(token):
                        scripts[script(word[0])] += n * len(word)
                        for g in trigrams(word):
                            grams[g] += n
            words.clear()

        for batch in batches:
            for text, x in zip(batch.column(0), batch.column(1).to_pylist()):
                words.setdefault(x, Counter()).update(words_of(text.as_py()))
                if len(words[x]) > most:
                    fold_in()
        fold_in()
        for x, both in totals.items():
            for kind, c in enumerate(both):
                items = list(c.items())
                for i in range(0, len(items), 10_000):
                    part = items[i : i + 10_000]
                    yield pa.RecordBatch.from_arrays([pa.array([kind] * len(part), pa.int32()), pa.array([x] * len(part)), pa.array([g for g, _ in part]), pa.array([n for _, n in part], pa.int64())], names=["kind", "lang", "item", "n"])

    return rows.mapInArrow(run, "kind int, lang string, item string, n long").groupBy("kind", "lang", "item").agg(F.sum("n").alias("n"))


def _made(table: list) -> LanguageModel:
    return LanguageModel.fit([(r["lang"], r["item"], r["n"]) for r in table if r["kind"] == 0], [(r["lang"], r["item"], r["n"]) for r in table if r["kind"] == 1])


def learn(docs: DataFrame) -> LanguageModel:
    """The model of every row with a text and a language, and of every trigram; without limits of evidence."""
    ship(docs.sparkSession)
    usable = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull()).select("text", "lang")
    return _made(_counted(usable).collect())  # a row for each language and trigram


def fit(docs: DataFrame, max_train_docs: int = 2500, max_grams: int = 200_000, folds: int = 4, held: int = 2) -> LanguageModel:
    """Learn from text and lang of rows outside the held-out fold."""
    spark = docs.sparkSession
    ship(spark)
    usable = docs.where((fold("doc_id", folds) != held) & F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull())
    sizes = {r["lang"]: r["n"] for r in usable.groupBy("lang").agg(F.count("*").alias("n")).collect()}  # a row for each language
    if not sizes:
        return LanguageModel()
    steps = 1 << 30
    rate = F.broadcast(spark.createDataFrame([(x, min(steps, math.ceil(steps * max_train_docs / n))) for x, n in sizes.items()], "_l string, _rate long"))
    sample = usable.select("doc_id", "text", "lang").join(rate, F.col("lang") == F.col("_l")).where(F.pmod(F.xxhash64("doc_id"), F.lit(steps)) < F.col("_rate")).select("text", "lang")
    table = _counted(sample).orderBy(F.desc("kind"), F.desc("n"), "lang", "item").limit(max_grams).collect()
    model = _made(table)
    shared = spark.sparkContext.broadcast(model)

    def judged(batches):
        labeller = Labeller(shared.value)
        for batch in batches:
            got = [(y, e) for t, y in zip(batch.column(0), batch.column(1).to_pylist()) for x, _, _, e in [labeller.judge(t.as_py())] if x == y]
            if got:
                yield pa.RecordBatch.from_arrays([pa.array([y for y, _ in got]), pa.array([e for _, e in got], pa.float64())], names=["lang", "evidence"])

    spread = sample.mapInArrow(judged, "lang string, evidence double").groupBy("lang").agg(F.percentile("evidence", F.array(F.lit(LOW), F.lit(0.5))).alias("q"))
    model.limits = {r["lang"]: r["q"][1] - LOW_TIMES * (r["q"][1] - r["q"][0]) - 0.01 for r in spread.collect()}  # a row for each language
    return model


def label(docs: DataFrame, model: LanguageModel, penalty: float = 8.0, spans: bool = False, folds: int = 4, held: int = 2, fits: bool = False) -> DataFrame:
    """doc_id, held_out, lang_pred, score, n_spans (and spans; evidence and whether it fits) of every document."""
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kind = pa.list_(pa.struct([("first", pa.int32()), ("words", pa.int32()), ("lang", pa.string())]))

    def run(batches):
        labeller = Labeller(shared.value, penalty)
        for batch in batches:
            judged = [labeller.judge(t.as_py()) for t in batch.column(1)]
            got = [x[:3] for x in judged]
            columns = [batch.column(0), pa.array([x for x, _, _ in got], pa.string()), pa.array([s for _, s, _ in got], pa.float64()), pa.array([len(s) for _, _, s in got], pa.int32())]
            names = ["doc_id", "lang_pred", "score", "n_spans"]
            if spans:
                columns.append(pa.array([[{"first": a, "words": n, "lang": x} for a, n, x in s] for _, _, s in got], kind))
                names.append("spans")
            if fits:
                columns += [pa.array([x[3] for x in judged], pa.float64()), pa.array([x[3] is not None and x[3] >= shared.value.limits.get(x[0], math.inf) for x in judged], pa.bool_())]
                names += ["evidence", "fits"]
            yield pa.RecordBatch.from_arrays(columns, names=names)

    schema = "doc_id long, lang_pred string, score double, n_spans int" + ", spans array<struct<first:int,words:int,lang:string>>" * spans + ", evidence double, fits boolean" * fits
    out = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, schema)
    return out.select("doc_id", F.coalesce(fold("doc_id", folds) == held, F.lit(False)).alias("held_out"), *out.columns[1:])


def keep(docs: DataFrame, least_share: float, penalty: float = 8.0, text_col: str = "text") -> DataFrame:
    """The rows whose text fits its language and has `least_share` of its letters in it, with all their columns, whatever their ids.

    The model is learned from all rows with a language, and the limits of evidence (to four digits) from all of these that it labels alike.  Each text is
    judged once: the judged rows are a stage table, which the limits and the result are read from.
    """
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(learn(docs))
    names = ["_pred", "_share", "_evidence"]

    def run(batches):
        labeller = Labeller(shared.value, penalty)
        for batch in batches:
            at = batch.schema.get_field_index(text_col)
            got = [labeller.judge(t.as_py()) for t in batch.column(at)]
            more = [pa.array([x[k] for x in got], t) for k, t in ((0, pa.string()), (1, pa.float64()), (3, pa.float64()))]
            yield pa.RecordBatch.from_arrays([*batch.columns, *more], names=[*batch.schema.names, *names])

    schema = StructType([*docs.schema.fields, *(StructField(n, t) for n, t in zip(names, (StringType(), DoubleType(), DoubleType())))])
    judged = Stage(spark).table(docs.mapInArrow(run, schema), "judged")
    alike = judged.where((F.col("lang") == F.col("_pred")) & F.col("_evidence").isNotNull()).groupBy("lang", F.round("_evidence", 4).alias("e")).agg(F.count("*").alias("n"))
    q = F.percentile("e", F.array(F.lit(LOW), F.lit(0.5)), F.col("n"))
    limits = {r["lang"]: r["q"][1] - LOW_TIMES * (r["q"][1] - r["q"][0]) - 0.01 for r in alike.groupBy("lang").agg(q.alias("q")).collect()}  # a row for each language
    limit = F.broadcast(spark.createDataFrame(list(limits.items()), "_lang string, _limit double"))
    fits = judged.join(limit, F.col("_pred") == F.col("_lang")).where((F.col("_pred") != UNKNOWN) & (F.col("_share") >= least_share) & (F.col("_evidence") >= F.col("_limit")))
    return fits.select(*docs.columns)
