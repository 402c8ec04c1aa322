"""Sources, state, joins, user functions, statistics, query log, and a sample of the suite against its SQL."""

import glob
import os

import pytest
from pyspark.sql import functions as F

from provgraph import suite
from provgraph.bench import measures
from provgraph.functions import udfs
from provgraph.operators import joins
from provgraph.sources import readers
from provgraph.sources.state import StateStore, terms
from provgraph.stats import labels
from provgraph.stats.cardinality import Estimator, q_error
from provgraph.workload import querylog
from provgraph.workload.queries import large_set

SCHEMA = "edge_id long, s string, p string, o string, inverse boolean"


def graph(spark, rows):
    return spark.createDataFrame([(*r, False) for r in rows], SCHEMA)


def test_state_versions(spark, tmp_path):
    store = StateStore(spark, str(tmp_path))
    a, b = graph(spark, [(1, "x", "p", "y"), (2, "x", "p", "z")]), graph(spark, [(3, "y", "q", "z")])
    assert store.commit("t", base=a, batch=0) == 0 and store.commit("t", inserts=b, batch=1) == 1
    assert store.commit("t", inserts=b, batch=1) == 1 and store.read("t").count() == 3
    store.commit("t", tombstones=spark.createDataFrame([(2,)], "edge_id long"), batch=2)
    assert {r["edge_id"] for r in store.read("t").collect()} == {1, 3} and store.read("t", version=0).count() == 2
    store.compact("t")
    assert store.read("t").count() == 2 and store.manifest()["tables"]["t"]["tombstones"] == [] and store.versions() == [0, 1, 2, 3]


def test_terms_are_one_to_one(spark):
    got = terms(graph(spark, [(1, "x", "p", "y"), (2, "y", "p", "z")])).collect()
    assert len(got) == 4 and len({r["id"] for r in got}) == 4


def test_readers(spark, tmp_path):
    (tmp_path / "a.nt").write_text('<x> <p> <y> .\n<x> <p> "v w" .\nnoise\n<x> <p> <y> .\n')
    assert {(r["s"], r["p"], r["o"]) for r in readers.triples_lines(spark, str(tmp_path / "a.nt")).collect()} == {("x", "p", "y"), ("x", "p", "lit:v w")}
    (tmp_path / "a.tsv").write_text("1\tx\tp\ty\n")
    assert readers.triples_csv(spark, str(tmp_path / "a.tsv")).first()["edge_id"] == 1
    (tmp_path / "u.json").write_text('{"seq": 1, "op": "del", "edge_id": 7}\n')
    assert readers.updates_json(spark, str(tmp_path / "u.json")).first()["op"] == "del"


def test_joins(spark):
    left = spark.createDataFrame([("a", 5, 1), ("a", 1, 2), ("b", 9, 3)], "k string, t int, i int")
    right = spark.createDataFrame([("a", 2, "x"), ("a", 5, "y"), ("b", 10, "z")], "k string, t int, v string")
    assert {r["i"]: r["v"] for r in joins.asof(left, right, "k", "t", "v").collect()} == {1: "y", 2: None, 3: None}
    points = spark.createDataFrame([(t,) for t in range(30)], "t long")
    spans = spark.createDataFrame([(1, 3, 12), (2, 12, 13)], "i int, a long, b long")
    got = {(r["i"], r["t"]) for r in joins.interval(points, spans, "t", "a", "b", 5).collect()}
    assert got == {(1, t) for t in range(3, 12)} | {(2, 12)}
    many = spark.createDataFrame([("h", i) for i in range(100)] + [("c", 1)], "k string, n int")
    assert joins.salted(many, spark.createDataFrame([("h", 1), ("c", 2)], "k string, m int"), "k", 4).count() == 101


def test_probability_and_terms(spark):
    half = lambda e: 0.5
    assert udfs.probability([(1, 2), (1, 3)], half) == pytest.approx(0.375) and udfs.probability([(1, 1)], half) == pytest.approx(0.5)
    assert udfs.probability([(i,) for i in range(20)], lambda e: 0.05) == pytest.approx(1 - 0.95**20, abs=0.02)
    d = spark.createDataFrame([("q", ["a"], [1, 2], 1), ("q", ["a"], [1, 2, 3], 2)], "qid string, ans array<string>, mono array<bigint>, n bigint")
    assert [r["witness"] for r in udfs.minimal_witnesses(d).collect()] == [[1, 2]]
    from provgraph.prov import poly

    tropical = udfs.custom_semiring(float, lambda a, b: a + b, min, float("inf"), 0.0)
    assert poly.how(d).select(tropical("poly").alias("v")).first()["v"] == 3.0


def test_label_profile_and_broken_constraints(spark):
    g = graph(spark, [(1, "c:1", "in", "n:1"), (2, "c:2", "in", "n:1"), (3, "c:1", "f", "c:2")])
    c = labels.constraints(g)
    assert c.functional == {"in", "f"} and "in" not in c.inverse_functional and "in" in c.acyclic and "f" in c.asymmetric
    broken = labels.broken_by(graph(spark, [(4, "c:1", "in", "n:2"), (5, "c:2", "f", "c:1")]), g, c)
    assert broken["functional"] == {"in"} and broken["asymmetric"] == {"f"} and "in" not in c.without(broken).functional


def test_estimates(spark):
    g = graph(spark, [(i, f"c:{i}", "in", f"n:{i % 2}") for i in range(10)] + [(20 + i, f"n:{i}", "of", "r:0") for i in range(2)] + [(30, "c:1", "x", "lit:a")])
    from provgraph.query.bgp import parse_select

    chain = parse_select("SELECT ?c { ?c in ?n . ?n of ?r }").body
    assert Estimator.build(g).estimate(chain) == 10
    star = parse_select("SELECT ?c { ?c in ?n . ?c x ?y }").body
    assert Estimator.build(g).estimate(star) == 1 and Estimator.build(g, "label_count").estimate(star) == 1 and q_error(10, 5) == 2
    m = measures.sharing(large_set(), lambda patterns: float(len(patterns)))
    assert m["queries"] == 215 and m["subqueries"] == 845 and 0.3 < m["gain"] < 1 and m["inner"] < m["nodes"]


def test_query_log(spark):
    texts = ["SELECT ?a { ?a p ?b . ?b q ?c }", "SELECT ?x { ?x p ?y . ?y q ?z }", "SELECT ?a { ?a p ?b }", "ASK { ?a p ?b }", None]
    log = spark.createDataFrame(list(enumerate(texts)), "qid long, text string")
    assert tuple(querylog.funnel(log).first()) == (5, 3, 2, 1) and [r["qid"] for r in querylog.clean(log).collect()] == [0]


@pytest.mark.parametrize("name", ["kg_label_counts", "how_s2", "ann_s2", "semiring_tropical", "b2_c4", "b3_c4", "abl_counting", "stream_tumbling", "del_changes"])
def test_suite_against_sql(spark, sf, name):
    import duckdb

    con = duckdb.connect()
    for f in glob.glob(f"{sf}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    got = suite.queries()[name](spark, sf)
    names = sorted(got.columns)
    have = sorted(tuple(map(str, r)) for r in got.select(*names).collect())
    want = sorted(tuple(map(str, r)) for r in con.sql(f"SELECT {', '.join(names)} FROM ({suite.oracle_sql()[name]})").fetchall())
    assert have == want and have


def test_no_product_of_halves_in_plans(spark, sf):
    plan = suite._deriv(spark, sf, suite.get("W-S2"))._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
    scans = [x for x in plan.split("ReadSchema: ")[1:] if "c_custkey" in x]
    assert all("c_name" not in x.splitlines()[0] for x in scans) and F is not None


def test_full_graph_entries(spark, sf):
    """All families and every label, by brute force on the collected edges."""
    from collections import Counter, defaultdict

    from provgraph import suite
    from provgraph.kg.build import BASE, LABELS

    made = suite.queries()
    rows = made["kg_edges_full"](spark, sf).collect()
    assert {r["edge_id"] // BASE for r in rows} == set(LABELS)
    out, sets = defaultdict(list), defaultdict(set)
    for r in rows:
        out[r["s"]].append(r)
        sets[r["s"]].add(r["p"])
    want = Counter(",".join(sorted(x)) for x in sets.values())
    assert {r["preds"]: r["vertices"] for r in made["charsets_full"](spark, sf).collect()} == want
    pairs = Counter((",".join(sorted(sets[r["s"]])), ",".join(sorted(sets[r["o"]])), r["p"]) for r in rows if r["o"] in sets)
    assert {tuple(r)[:3]: r["cnt"] for r in made["charpairs_full"](spark, sf).collect()} == pairs
    assert {r["p"] for r in made["label_profile_full"](spark, sf).collect()} == {x for own in LABELS.values() for x in own}
    friends = [r["o"] for r in out["cust:7"] if r["p"] == "followed"]
    ends = Counter((b["p"], b["o"]) for f in friends for b in out[f])
    got = made["bgp_varpred_full"](spark, sf)
    assert Counter(tuple(r) for r in got.select("v_l", "v_o").collect()) == ends
    both = sum((Counter((a["p"], a["o"]) for a in out[r["s"]])[b["p"], b["o"]]) for r in rows if r["p"] == "followed" for b in out[r["o"]])
    seen = made["bgp_e_full"](spark, sf).count()
    assert seen == both and made["how_e_full"](spark, sf).count() <= seen
