"""Baselines that recompute, and counting maintenance."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..maintain.insert import telescoped
from ..maintain.potential import union_all
from ..match.evaluate import V, derivations, evaluate, scan
from ..match.sql import create_label_views, label_relation, to_sql
from ..prov import circuit, poly
from ..query.bgp import GraphQuery, Var

DERIV = "qid string, ans array<string>, mono array<bigint>, n bigint"


def relevant(queries: list[GraphQuery], labels) -> list[GraphQuery]:
    """Queries that mention an updated label: the only ones that a baseline pays for."""
    return [q for q in queries if any(q.mentions(x) for x in labels)]


def rerun_all(triples: DataFrame, queries: list[GraphQuery], previous: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(added, removed) answers: everything evaluated anew and compared with the results before."""
    now = union_all([derivations(evaluate(triples, q, allow_cross=True), q) for q in queries], triples.sparkSession, DERIV).select("qid", "ans").distinct()
    before = previous.select("qid", "ans").distinct()
    return now.exceptAll(before), before.exceptAll(now)


def graph_recompute(triples: DataFrame, queries: list[GraphQuery]) -> DataFrame:
    """A join for each step of the traversal, in the order of the patterns, on one edge table; polynomials at the end."""
    rows = [derivations(evaluate(triples, q, order=list(range(len(q.body))), allow_cross=True), q) for q in queries]
    return poly.how(union_all(rows, triples.sparkSession, DERIV))


def rewrite_recompute(triples: DataFrame, queries: list[GraphQuery]) -> DataFrame:
    """Rewritten SQL over a relation for each label: each scan adds its edge id as a column, wide rows are nested at the end."""
    spark: SparkSession = triples.sparkSession
    create_label_views(triples, {x for q in queries for x in q.labels if x != "*"})
    rows = [derivations(spark.sql(to_sql(q, label_relation)), q) for q in queries]
    return poly.how(union_all(rows, spark, DERIV))


def circuit_recompute(triples: DataFrame, query: GraphQuery) -> tuple[DataFrame, DataFrame]:
    """(answers with their gate, circuit): joins make product gates, the projection a sum gate."""
    tables, gates = [], []
    for i, t in enumerate(query.body):
        s = scan(triples, t, i).withColumn(f"g_{i}", circuit.token(F.col(f"e_{i}")))
        gates.append(s.select(F.col(f"g_{i}").alias("gate"), F.lit("edge").alias("kind"), F.array(F.col(f"e_{i}").cast("string")).alias("children")).distinct())
        tables.append(s.drop(f"e_{i}").withColumnRenamed(f"g_{i}", "g"))

    def product(left: DataFrame, right: DataFrame) -> DataFrame:
        right = right.withColumnRenamed("g", "h")
        shared = [c for c in right.columns if c.startswith(V) and c in left.columns]
        j = left.join(right, shared) if shared else left.crossJoin(right)
        j = j.withColumn("k", circuit.times_gate(F.col("g"), F.col("h")))
        gates.append(circuit.gates(j, "k", "times", F.array("g", "h")))
        return j.drop("g", "h").withColumnRenamed("k", "g")

    from ..match.evaluate import join_order

    first, *rest = join_order(list(query.body))
    whole = reduce(lambda a, i: product(a, tables[i]), rest, tables[first])
    ans = F.array(*[F.col(V + v).cast("string") for v in query.head]) if query.head else F.array().cast("array<string>")
    top = whole.groupBy(ans.alias("ans")).agg(F.array_sort(F.collect_list("g")).alias("children"))
    top = top.withColumn("gate", circuit.plus_gate(F.col("children")))
    gates.append(top.select("gate", F.lit("plus").alias("kind"), "children").distinct())
    return top.select("ans", "gate"), union_all(gates, triples.sparkSession, "gate string, kind string, children array<string>").distinct()


def expand(answers: DataFrame, gates: DataFrame, size: int) -> DataFrame:
    """(ans, mono, n): the circuit multiplied out; the depth is at most the size of the query."""
    plus = gates.where("kind = 'plus'").select("gate", F.posexplode("children").alias("k", "open"))
    rows = answers.join(plus, "gate").select("ans", "k", F.array("open").alias("open"), F.array().cast("array<bigint>").alias("mono"))
    inner = gates.where("kind <> 'plus'").select(F.col("gate").alias("_g"), "kind", F.col("children").alias("_c"))
    for _ in range(2 * size - 1):
        rows = rows.withColumn("_head", F.get("open", F.lit(0))).join(inner, F.col("_head") == F.col("_g"), "left")
        rest = F.slice("open", F.lit(2), F.greatest(F.size("open") - 1, F.lit(0)))
        rows = rows.select("ans", "k", F.when(F.col("kind") == "times", F.concat("_c", rest)).when(F.col("kind") == "edge", rest).otherwise(F.col("open")).alias("open"), F.when(F.col("kind") == "edge", F.concat("mono", F.array(F.get("_c", F.lit(0)).cast("long")))).otherwise(F.col("mono")).alias("mono"))
    return rows.select("ans", F.array_sort("mono").alias("mono")).groupBy("ans", "mono").agg(F.count("*").alias("n"))


def counting(old: DataFrame, ins: DataFrame, dels: DataFrame, q: GraphQuery) -> DataFrame:
    """(ans, n): counts after deletes and inserts, kept up by joins with signed differences and no provenance."""
    ids = F.broadcast(dels.select("edge_id").distinct())
    lost = old.join(ids, "edge_id", "left_semi").select(*old.columns)
    rest = old.join(ids, "edge_id", "left_anti").select(*old.columns)
    new = rest.unionByName(ins.select(*old.columns))
    labels = {t.label for t in q.body if t.label} | ({"*"} if any(isinstance(t.p, Var) for t in q.body) else set())
    count = lambda m, sign: derivations(m, q).select("ans", (F.col("n") * sign).alias("n"))
    terms = [count(evaluate(old, q), 1)]
    terms += [count(m, -1) for m in telescoped(lost, rest, old, q, labels)]
    terms += [count(m, 1) for m in telescoped(ins, rest, new, q, labels)]
    return union_all(terms, old.sparkSession, "").groupBy("ans").agg(F.sum("n").alias("n")).where("n <> 0")
