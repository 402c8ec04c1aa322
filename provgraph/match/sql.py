"""Pattern queries as relational SQL: a relation for each label, an equi-join for each shared term."""

from __future__ import annotations

from ..query.bgp import Const, GraphQuery


def _parts(q: GraphQuery, relation) -> tuple[list[str], list[str], dict[str, str]]:
    tables, conditions, first = [], [], {}
    for i, t in enumerate(q.body):
        tables.append(f"{relation(t)} t{i}")
        for column, x in zip(("s", "p", "o"), t.terms):
            at = f"t{i}.{column}"
            if isinstance(x, Const):
                conditions.append(f"{at} = '{x.value.replace(chr(39), chr(39) * 2)}'")
            elif x.name in first:
                conditions.append(f"{first[x.name]} = {at}")
            else:
                first[x.name] = at
    return tables, conditions, first


def to_sql(q: GraphQuery, relation=lambda t: "g", edges: bool = True, sources: list[str] | None = None) -> str:
    """SELECT of all variables (and edge ids) of the matches; `relation` names a pattern's table."""
    tables, conditions, first = _parts(q, relation)
    if sources:
        tables = [f"{s} t{i}" for i, s in enumerate(sources)]
    columns = [f"{at} AS v_{v}" for v, at in first.items()] + [f"t{i}.edge_id AS e_{i}" for i in range(len(q.body)) if edges]
    return f"SELECT {', '.join(columns)} FROM {', '.join(tables)}" + (f" WHERE {' AND '.join(conditions)}" if conditions else "")


def label_relation(t) -> str:
    """Name of the view with a label's edges."""
    return f"rel_{t.label}" if t.label else "rel_all"


def create_label_views(triples, labels) -> None:
    for label in labels:
        triples.where(triples["p"] == label).createOrReplaceTempView(f"rel_{label}")
    triples.createOrReplaceTempView("rel_all")
