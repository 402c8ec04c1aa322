"""New derivations from inserted edges.

A new match has a lowest position that a new edge fills.  It comes out at that position: the new edge there meets the annotations of the
half matches, old and new ones, in which no lower position is filled by an edge of the batch.  So each new match comes out once, also
if several new edges, or one edge in several positions, make it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..match.evaluate import derivations, evaluate, join_order, scan
from ..query.bgp import GraphQuery, Var
from ..query.subquery import Subquery
from .potential import ANNOTATED, Catalog, annotations, union_all

DERIV = "qid string, ans array<string>, mono array<bigint>, n bigint"
U, VV, P = "u", "w", "lab"


def routed(catalog: Catalog, labels: set[str]) -> list[Subquery]:
    """Subqueries whose missing pattern one of the labels can fill."""
    return [s for s in catalog.subqueries if s.exp_rel == "*" or s.exp_rel in labels]


def _head(catalog: Catalog, s: Subquery) -> list[tuple[str, int, int]]:
    """Where each head value comes from: ('b', half, place), ('u', 0, 0), ('w', ...) or ('lab', ...)."""
    out = []
    for v in s.query.head:
        place = next((("b", h.number, catalog.index(s, h, v)) for h in s.halves if v in catalog.order[s.sqid, h.number]), None)
        if place is None:
            p = s.pattern
            place = (U if p.s == Var(v) else VV if p.o == Var(v) else P, 0, 0)
        out.append(place)
    return out


def _value(item: Column, b0: Column, b1: Column) -> Column:
    safe = F.greatest(item["at"], F.lit(1))
    return (
        F.when(item["src"] == U, F.col(U)).when(item["src"] == VV, F.col(VV)).when(item["src"] == P, F.col(P))
        .when(item["half"] == 0, F.get(b0, safe - 1)).otherwise(F.get(b1, safe - 1))
    )


def single(delta: DataFrame, potential: DataFrame, old: DataFrame, new: DataFrame, catalog: Catalog, labels: set[str]) -> DataFrame:
    """All new matches of all queries: (qid, ans, mono, n).

    potential: node rows of the old graph, and the batch's with `fresh`.  The catalog's rows are a small table, so the number of joins does
    not grow with the number of queries, but for one look-up for each subquery of type II.
    """
    spark = delta.sparkSession
    subs = routed(catalog, labels)
    frames = []
    d = delta.select(F.col("edge_id").alias("new_id"), "inverse", F.col("s").alias(U), F.col("p").alias(P), F.col("o").alias(VV))
    known = [s for s in subs if s.kind in ANNOTATED and not catalog.is_wide(s)]
    if known:
        wanted = Catalog(catalog.queries, known, catalog.order, catalog.places, catalog.root, catalog.plan, catalog.number)
        ann = annotations(potential, wanted, probes_only=True)
        if "fresh" in ann.columns:
            ann = ann.where(F.col("fresh").isNull() | ~F.exists("before", lambda i: F.get(F.col("fresh"), i)))
        far = F.when(F.col("dir") == "out", F.col(VV)).otherwise(F.col(U))
        out_ = lambda side: d.withColumn("_v", F.col(U if side == "out" else VV)).withColumn("_dir", F.lit(side))
        ends = out_("out").unionByName(out_("in"))
        hit = ann.join(ends, (F.col("vertex") == F.col("_v")) & (F.col("dir") == F.col("_dir")) & F.col("exp_rel").isin(sorted(labels | {"*"})))
        hit = hit.where(((F.col("exp_rel") == F.col(P)) | (F.col("exp_rel") == "*")) & (F.col("exp_other").isNull() | (F.col("exp_other") == far)) & (F.col("other").isNull() | (F.col("other") == far)) & (F.col("p_value").isNull() | (F.col("p_value") == F.col(P))))
        loops = [s.sqid for s in known if isinstance(s.pattern.s, Var) and s.pattern.s == s.pattern.o]
        if loops:
            hit = hit.where(~F.col("sqid").isin(loops) | (F.col(U) == F.col(VV)))
        heads = spark.createDataFrame([(s.sqid, [dict(src=a, half=b, at=c or 0) for a, b, c in _head(catalog, s)]) for s in known], "head_sqid string, head array<struct<src:string,half:int,at:int>>")
        key = ["sqid", "new_id", "inverse"]
        none = lambda kind: F.array().cast(f"array<{kind}>")
        one = hit.where("kind in ('I', 'IV')").select("qid", *key, U, VV, P, F.col("binding").alias("b0"), none("string").alias("b1"), F.col("edges").alias("m0"), none("bigint").alias("m1"))
        whole = [one]
        if any(s.kind == "III" for s in known):
            three = hit.where("kind = 'III'")
            left = three.where("half = 0").select("qid", *key, U, VV, P, F.col("binding").alias("b0"), F.col("edges").alias("m0"))
            right = three.where("half = 1").select(*key, F.col("binding").alias("b1"), F.col("edges").alias("m1"))
            whole.append(left.join(right, key).select("qid", *key, U, VV, P, "b0", "b1", "m0", "m1"))
        for s in known:
            if s.kind == "II":
                whole.append(_type2(hit, old, new, catalog, s, key))
        rows = union_all(whole, spark, "").join(F.broadcast(heads), F.col("sqid") == F.col("head_sqid"))
        ans = F.transform("head", lambda h: _value(h, F.col("b0"), F.col("b1")))
        frames.append(rows.select("qid", ans.alias("ans"), F.array_sort(F.concat("m0", "m1", F.array("new_id"))).alias("mono"), F.lit(1).cast("bigint").alias("n")))
    for s in subs:
        if s.kind == "empty":
            frames.append(derivations(evaluate(delta, s.query), s.query))
        elif s.kind == "free" or catalog.is_wide(s):
            frames.append(derivations(_from(delta, old, new, s.query, s.missing), s.query))
    return union_all(frames, spark, DERIV).groupBy("qid", "ans", "mono").agg(F.sum("n").alias("n"))


def _type2(hit: DataFrame, old: DataFrame, new: DataFrame, catalog: Catalog, s: Subquery, key: list[str]) -> DataFrame:
    """The other half is one edge at the far vertex, looked up in the graph by label and vertex."""
    big = s.annotated[0]
    small = next(h for h in s.halves if h.number != big.number)
    place = small.positions[0]
    names = catalog.order[s.sqid, small.number]
    at, side = (small.out_var, U) if small.out_var else (small.in_var, VV)
    found = scan(new if place > s.missing else old, s.query.body[place], 0)
    found = found.select(F.col(f"v_{at}").alias("_far"), F.array(*(F.col(f"v_{x}") for x in names)).alias("b_small"), F.array("e_0").alias("m_small"))
    mine = hit.where((F.col("sqid") == s.sqid) & (F.col("half") == big.number)).withColumn("_far", F.col(side))
    j = mine.join(found, "_far")
    b, m = (("binding", "b_small"), ("edges", "m_small")) if big.number == 0 else (("b_small", "binding"), ("m_small", "edges"))
    return j.select("qid", *key, U, VV, P, F.col(b[0]).alias("b0"), F.col(b[1]).alias("b1"), F.col(m[0]).alias("m0"), F.col(m[1]).alias("m1"))


def _from(delta: DataFrame, old: DataFrame, new: DataFrame, q: GraphQuery, i: int) -> DataFrame:
    """Matches whose lowest new edge is at position i, joined outwards from there."""
    sources = [delta if k == i else old if k < i else new for k in range(len(q.body))]
    return evaluate(sources, q, allow_cross=True, order=join_order(list(q.body), start=i))


def telescoped(delta: DataFrame, old: DataFrame, new: DataFrame, q: GraphQuery, labels: set[str]) -> list[DataFrame]:
    """All new matches without annotations: position i on the new edges, lower ones on the old graph, higher ones on the new."""
    return [_from(delta, old, new, q, i) for i, t in enumerate(q.body) if t.label is None or t.label in labels]


__all__ = ["DERIV", "routed", "single", "telescoped"]
