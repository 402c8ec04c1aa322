"""Update streams: deterministic inserts, deletes, hold-out replay, mixes, and the stream of the events table."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..kg.build import BASE, term

NEW_IDS = 90 * BASE
#: Parts of ten that are deletes.
MIXES = {"deletion_heavy": 9, "deletion_moderate": 7, "balanced": 5, "insertion_moderate": 3, "insertion_heavy": 1}


def held_out(triples: DataFrame, keep: bool, modulo: int = 50, rest: int = 7) -> DataFrame:
    """The graph without (or only) the edges with id % modulo = rest."""
    hit = F.pmod("edge_id", F.lit(modulo)) == rest
    return triples.where(~hit if keep else hit)


def deletes(triples: DataFrame, labels, q: int = 101) -> DataFrame:
    """Ids of edges of the labels with (31 id + 7) % q = 0."""
    return triples.where(F.col("p").isin(sorted(labels)) & (F.pmod(F.col("edge_id") * 31 + 7, F.lit(q)) == 0)).select("edge_id").distinct()


def inserts(triples: DataFrame, labels, k: int, mode: str = "random") -> DataFrame:
    """k new edges between unconnected vertices.

    random: any two vertices and any label; typed: subject and object of two edges of one label.
    """
    spark, names = triples.sparkSession, sorted(labels)
    i = spark.range(k).withColumnRenamed("id", "i")
    label = F.element_at(F.array(*map(F.lit, names)), (F.pmod("i", F.lit(len(names))) + 1).cast("int"))
    own = triples.where(F.col("p").isin(names))
    ends = [own.select("p", "s").distinct(), own.select("p", "o").distinct()] if mode == "typed" else None
    if ends is None:
        v = own.select(F.col("s").alias("v")).union(own.select("o")).distinct().withColumn("p", F.lit("*"))
        ends = [v.select("p", F.col("v").alias("s")), v.select("p", F.col("v").alias("o"))]
    drawn = i.withColumn("label", label).withColumn("p", F.col("label") if mode == "typed" else F.lit("*"))
    for df, c, a, b in ((ends[0], "s", 7919, 13), (ends[1], "o", 104729, 31)):
        ranked = df.withColumn("_r", F.row_number().over(Window.partitionBy("p").orderBy(c)) - 1)
        sizes = ranked.groupBy("p").agg(F.count("*").alias("_n"))
        drawn = drawn.join(sizes, "p").withColumn("_r", F.pmod(F.col("i") * a + b, F.col("_n"))).drop("_n").join(ranked, ["p", "_r"]).drop("_r")
    drawn = drawn.select((F.lit(NEW_IDS) + F.col("i")).alias("edge_id"), "s", F.col("label").alias("p"), "o", F.lit(False).alias("inverse"))
    return drawn.join(triples.select("s", "o"), ["s", "o"], "left_anti").select("edge_id", "s", "p", "o", "inverse")


def numbered(df: DataFrame, buckets: int = 64) -> DataFrame:
    """Numbers from 0 for the edges, both rows of a symmetric edge alike: ranks within hashed buckets, shifted by the buckets before."""
    ids = df.select("edge_id").distinct().withColumn("_b", F.pmod(F.xxhash64("edge_id"), F.lit(buckets)))
    sizes = ids.groupBy("_b").agg(F.count("*").alias("_n"))
    before = F.coalesce(F.sum("_n").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # a row for each bucket
    shifts = F.broadcast(sizes.withColumn("_at", before).select("_b", "_at"))
    ranked = ids.withColumn("_r", F.row_number().over(Window.partitionBy("_b").orderBy("edge_id")) - 1).join(shifts, "_b")
    return df.join(ranked.select("edge_id", (F.col("_at") + F.col("_r")).alias("_r")), "edge_id")


def as_updates(ins: DataFrame, dels: DataFrame, deletes_of_ten: int = 5) -> DataFrame:
    """(seq, op, edge_id, s, p, o, inverse): inserts and deletes dealt in the ratio d : 10 - d."""
    a = numbered(ins).withColumn("op", F.lit("ins"))
    b = numbered(dels).withColumn("op", F.lit("del"))
    per = F.when(F.col("op") == "del", F.lit(deletes_of_ten)).otherwise(10 - deletes_of_ten)
    shift = F.when(F.col("op") == "del", F.lit(0)).otherwise(deletes_of_ten)
    both = a.unionByName(b, allowMissingColumns=True)
    return both.withColumn("seq", F.floor(F.col("_r") / per) * 10 + shift + F.pmod("_r", per)).drop("_r")


def from_events(events: DataFrame) -> DataFrame:
    """Each event inserts an edge; an error deletes the edge of the user's last other event."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") != "error", F.col("event_id")), ignorenulls=True).over(w)
    e = events.withColumn("_last", last).withColumn("seq", F.col("event_id")).withColumn("ts", F.col("ts").cast("timestamp"))
    event_id = lambda c: F.lit(14 * BASE) + F.col(c)
    ins = e.where("event_type <> 'error'").select("seq", "ts", F.lit("ins").alias("op"), event_id("event_id").alias("edge_id"), term("cust", "user_id").alias("s"), F.col("event_type").alias("p"), term("topic", F.get_json_object("props", "$.k")).alias("o"), F.lit(False).alias("inverse"))
    none = F.lit(None).cast("string")
    gone = e.where("event_type = 'error' and _last is not null").select("seq", "ts", F.lit("del").alias("op"), event_id("_last").alias("edge_id"), none.alias("s"), none.alias("p"), none.alias("o"), F.lit(False).alias("inverse"))
    return ins.unionByName(gone)


def net(updates: DataFrame) -> DataFrame:
    """(edge_id, op, s, p, o, inverse): a 'del' for each id that some update deletes, and the rows that are in afterwards.

    Those are the rows of the first insert behind the last delete; later inserts of an id that is there change nothing.
    """
    per = updates.groupBy("edge_id").agg(F.max(F.when(F.col("op") == "del", F.col("seq"))).alias("_del"))
    j = updates.join(per, "edge_id")
    ins = j.where((F.col("op") == "ins") & (F.col("_del").isNull() | (F.col("seq") > F.col("_del"))))
    first = ins.groupBy("edge_id", "inverse").agg(F.min_by(F.struct("s", "p", "o"), "seq").alias("u"), F.min("seq").alias("_seq"))
    least = first.groupBy("edge_id").agg(F.min("_seq").alias("_first"))
    rows = first.join(least, "edge_id").where(F.col("_seq") == F.col("_first")).select("edge_id", F.lit("ins").alias("op"), "u.s", "u.p", "u.o", "inverse")
    none = F.lit(None).cast("string")
    return per.where("_del is not null").select("edge_id", F.lit("del").alias("op"), none.alias("s"), none.alias("p"), none.alias("o"), F.lit(False).alias("inverse")).unionByName(rows)
