"""The given tables as a directed, labelled multigraph: rows (edge_id, s, p, o, inverse)."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

BASE = 10**15
#: Labels of each family code.
LABELS = {
    1: ("followed",), 2: ("coActive",), 3: ("locatedIn",), 4: ("locatedIn",), 5: ("locatedIn",), 6: ("inSegment",), 7: ("placedBy",),
    8: ("hasPart",), 9: ("shippedFrom",), 10: ("hasBrand",), 11: ("hasType",), 12: ("hasStatus",), 13: ("hasPriority",),
    14: ("click", "view", "purchase", "signup"), 15: ("linksTo",), 16: ("writtenIn",), 17: ("fromSource",), 18: ("judged",),
    19: ("repliesTo",), 20: ("inCluster",), 21: ("mentions",),
}
SYMMETRIC = frozenset({"coActive"})
COLUMNS = ("edge_id", "s", "p", "o", "inverse")


def term(kind: str, *parts: Column | str) -> Column:
    cols = [F.col(c) if isinstance(c, str) else c for c in parts]
    return F.concat(F.lit(f"{kind}:"), *[c.cast("string") for c in cols])


def edges(df: DataFrame, code: int, local: Column | str, s: Column, p: Column | str, o: Column) -> DataFrame:
    local = F.col(local) if isinstance(local, str) else local
    return df.select((F.lit(code * BASE) + local.cast("long")).alias("edge_id"), s.alias("s"), (F.lit(p) if isinstance(p, str) else p).alias("p"), o.alias("o"), F.lit(False).alias("inverse"))


def expand_symmetric(triples: DataFrame, labels: Iterable[str] = SYMMETRIC) -> DataFrame:
    """A second, swapped row with the same id for each edge of a symmetric label."""
    back = triples.where(F.col("p").isin(list(labels))).select("edge_id", F.col("o").alias("s"), "p", F.col("s").alias("o"), F.lit(True).alias("inverse"))
    return triples.unionByName(back)


def literal_edges(df: DataFrame, code: int, kind: str, key: str, column: str, label: str) -> DataFrame:
    """Property values as vertices."""
    return edges(df.where(F.col(column).isNotNull()), code, key, term(kind, key), label, term("lit", column))


def _previous_user(read, code: int, event: str, label: str) -> DataFrame:
    k = F.get_json_object("props", "$.k")
    e = read("events").where(F.col("event_type") == event).select("event_id", "ts", "user_id", k.alias("k"))
    e = e.withColumn("before", F.lag("user_id").over(Window.partitionBy("k").orderBy("ts", "event_id")))
    return edges(e.where(F.col("before") != F.col("user_id")), code, "event_id", term("cust", "user_id"), label, term("cust", "before"))


def numbered_lines(read) -> DataFrame:
    """lineitem rows numbered within their order by all other columns, as (order, line number) is not unique."""
    rest = ["l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
    return read("lineitem").withColumn("local", F.col("l_orderkey") * 1000 + F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*rest)))


def _links(read) -> DataFrame:
    hrefs = F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1))
    d = read("pages").select("page_id", F.posexplode(hrefs).alias("pos", "href"))
    return edges(d, 15, F.col("page_id") * 1000 + F.col("pos"), term("page", "page_id"), "linksTo", term("path", "href"))


def _replies(read) -> DataFrame:
    w = Window.partitionBy("conv_id").orderBy("turn")
    c = read("conversations").select("conv_id", "turn", F.lag("turn").over(w).alias("before"))
    return edges(c.where(F.col("before").isNotNull()), 19, F.col("conv_id") * 1000 + F.col("turn"), term("turn", "conv_id", F.lit("/"), "turn"), "repliesTo", term("turn", "conv_id", F.lit("/"), "before"))


def _mentions(read) -> DataFrame:
    # benchmark is the small, fixed side; Spark broadcasts it below its own threshold
    d = read("documents").select("doc_id", "text").join(read("benchmark").select("item_id", F.col("text").alias("passage")), F.expr("contains(text, passage)"))
    return edges(d, 21, F.col("doc_id") * 1000 + F.col("item_id"), term("doc", "doc_id"), "mentions", term("item", "item_id"))


FAMILIES = {
    1: lambda r: _previous_user(r, 1, "purchase", "followed"),
    2: lambda r: _previous_user(r, 2, "click", "coActive"),
    3: lambda r: edges(r("customer"), 3, "c_custkey", term("cust", "c_custkey"), "locatedIn", term("nation", "c_nationkey")),
    4: lambda r: edges(r("supplier"), 4, "s_suppkey", term("supp", "s_suppkey"), "locatedIn", term("nation", "s_nationkey")),
    5: lambda r: edges(r("nation"), 5, "n_nationkey", term("nation", "n_nationkey"), "locatedIn", term("region", "n_regionkey")),
    6: lambda r: literal_edges(r("customer"), 6, "cust", "c_custkey", "c_mktsegment", "inSegment"),
    7: lambda r: edges(r("orders"), 7, "o_orderkey", term("order", "o_orderkey"), "placedBy", term("cust", "o_custkey")),
    8: lambda r: edges(numbered_lines(r), 8, "local", term("order", "l_orderkey"), "hasPart", term("part", "l_partkey")),
    9: lambda r: edges(numbered_lines(r), 9, "local", term("order", "l_orderkey"), "shippedFrom", term("supp", "l_suppkey")),
    10: lambda r: literal_edges(r("part"), 10, "part", "p_partkey", "p_brand", "hasBrand"),
    11: lambda r: literal_edges(r("part"), 11, "part", "p_partkey", "p_type", "hasType"),
    12: lambda r: literal_edges(r("orders"), 12, "order", "o_orderkey", "o_orderstatus", "hasStatus"),
    13: lambda r: literal_edges(r("orders"), 13, "order", "o_orderkey", "o_orderpriority", "hasPriority"),
    14: lambda r: edges(r("events").where("event_type <> 'error'"), 14, "event_id", term("cust", "user_id"), F.col("event_type"), term("topic", F.get_json_object("props", "$.k"))),
    15: _links,
    16: lambda r: literal_edges(r("documents"), 16, "doc", "doc_id", "lang", "writtenIn"),
    17: lambda r: literal_edges(r("documents"), 17, "doc", "doc_id", "source", "fromSource"),
    18: lambda r: edges(r("labels").where("quality is not null"), 18, "doc_id", term("doc", "doc_id"), "judged", F.when(F.col("quality") == 1, F.lit("lit:good")).otherwise(F.lit("lit:bad"))),
    19: _replies,
    20: lambda r: edges(r("embeddings"), 20, "vec_id", term("vec", "vec_id"), "inCluster", term("lit", "label")),
    21: _mentions,
}


def reader(spark: SparkSession, sf_dir: str):
    return lambda name: spark.read.parquet(f"{sf_dir}/{name}.parquet")


def build_graph(read, families: Iterable[int] | None = None) -> DataFrame:
    """Triples of the given families (all by default), symmetric labels in both directions."""
    codes = sorted(FAMILIES if families is None else set(families))
    out = FAMILIES[codes[0]](read)
    for code in codes[1:]:
        out = out.unionByName(FAMILIES[code](read))
    mirrored = [x for c in codes for x in LABELS[c] if x in SYMMETRIC]
    return expand_symmetric(out, mirrored) if mirrored else out


def families_of(labels: Iterable[str]) -> list[int]:
    """Codes of all families with one of the labels; '*' means every event label."""
    wanted = set(labels)
    return [c for c, own in LABELS.items() if wanted & set(own)]


def graph_for(spark: SparkSession, sf_dir: str, labels: Iterable[str]) -> DataFrame:
    return build_graph(reader(spark, sf_dir), families_of(labels)).where(F.col("p").isin(sorted(set(labels))))
