"""Label properties read off the graph: which labels are functional, asymmetric, acyclic and so on."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..query.folding import Constraints


def profile(triples: DataFrame) -> DataFrame:
    """(p, edges, functional, inverse_functional, irreflexive, asymmetric, symmetric) as 0/1 columns."""
    pairs = triples.select("p", "s", "o").distinct()
    out = pairs.groupBy("p", "s").count().groupBy("p").agg(F.max("count").alias("_out"))
    inn = pairs.groupBy("p", "o").count().groupBy("p").agg(F.max("count").alias("_in"))
    loops = pairs.groupBy("p").agg(F.sum((F.col("s") == F.col("o")).cast("long")).alias("_loops"), F.count("*").alias("_pairs"))
    back = pairs.select(F.col("p").alias("bp"), F.col("o").alias("bs"), F.col("s").alias("bo"))
    mutual = pairs.join(back, (F.col("p") == F.col("bp")) & (F.col("s") == F.col("bs")) & (F.col("o") == F.col("bo")), "left_semi").groupBy("p").agg(F.count("*").alias("_mutual"))
    edges = triples.where(~F.col("inverse")).groupBy("p").agg(F.count("*").alias("edges"))
    j = edges.join(out, "p").join(inn, "p").join(loops, "p").join(mutual, "p", "left").fillna(0, ["_mutual"])
    flag = lambda c: c.cast("long")
    return j.select("p", "edges", flag(F.col("_out") == 1).alias("functional"), flag(F.col("_in") == 1).alias("inverse_functional"), flag(F.col("_loops") == 0).alias("irreflexive"), flag(F.col("_mutual") == 0).alias("asymmetric"), flag(F.col("_mutual") == F.col("_pairs")).alias("symmetric"))


def domains(triples: DataFrame) -> dict:
    """(label, end) -> vertex classes there; a row for each label and class reaches the driver."""
    out: dict = {}
    for end in ("s", "o"):
        for r in triples.select("p", F.split(end, ":")[0].alias("c")).distinct().collect():
            out.setdefault((r["p"], end), set()).add(r["c"])
    return {k: frozenset(v) for k, v in out.items()}


def constraints(triples: DataFrame, acyclic=()) -> Constraints:
    """Profiled constraints; acyclic labels are declared, or asymmetric labels whose ends have no class in common."""
    rows, dom = profile(triples).collect(), domains(triples)
    named = lambda f: frozenset(r["p"] for r in rows if r[f])
    apart = {r["p"] for r in rows if not dom.get((r["p"], "s"), set()) & dom.get((r["p"], "o"), set())}
    return Constraints(named("functional"), named("inverse_functional"), named("asymmetric") - named("symmetric"), named("irreflexive"), frozenset(acyclic) | apart, named("symmetric"), dom)


def broken_by(delta: DataFrame, triples: DataFrame, c: Constraints) -> dict:
    """Constraints that the new edges break, and classes new to a domain; reads the neighbours of the new edges only."""
    labels = {r["p"] for r in delta.select("p").distinct().collect()}  # a row for each label of the batch
    out: dict = {}
    own = delta.select("p", "s", "o").distinct()
    for name, end, other in (("functional", "s", "o"), ("inverse_functional", "o", "s")):
        if labels & getattr(c, name):
            near = triples.join(own.select("p", end).distinct(), ["p", end], "left_semi").select("p", end, other).unionByName(own.select("p", end, other)).distinct()
            out[name] = {r["p"] for r in near.groupBy("p", end).count().where("count > 1").select("p").distinct().collect()} & getattr(c, name)
    if labels & c.irreflexive:
        out["irreflexive"] = {r["p"] for r in own.where("s = o").select("p").distinct().collect()} & c.irreflexive
    if labels & c.asymmetric:
        back = own.select("p", F.col("o").alias("s"), F.col("s").alias("o"))
        both = triples.select("p", "s", "o").unionByName(own)
        out["asymmetric"] = {r["p"] for r in both.join(back, ["p", "s", "o"], "left_semi").select("p").distinct().collect()} & c.asymmetric
    # a label of which ends have no class in common stays acyclic as long as that holds; any other may have closed a cycle
    if c.domains:
        seen = own.select("p", F.lit("s").alias("end"), F.split("s", ":")[0].alias("c")).unionByName(own.select("p", F.lit("o").alias("end"), F.split("o", ":")[0].alias("c"))).distinct().collect()
        more: dict = {}
        for r in seen:
            if (r["p"], r["end"]) in c.domains and r["c"] not in c.domains[r["p"], r["end"]]:
                more.setdefault((r["p"], r["end"]), set()).add(r["c"])
        if more:
            out["domains"] = more
    wide = lambda p, e: c.domains.get((p, e), frozenset()) | out.get("domains", {}).get((p, e), set())
    out["acyclic"] = {p for p in labels & c.acyclic if not (wide(p, "s") and wide(p, "o") and not wide(p, "s") & wide(p, "o"))}
    return {k: v for k, v in out.items() if v}
