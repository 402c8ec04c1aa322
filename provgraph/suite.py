"""queries() and oracle_sql() of the engine: every method on the given tables, with an independent SQL form."""

from __future__ import annotations

import tempfile
from dataclasses import replace
from functools import partial

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .baselines import recompute
from .bench import measures
from .kg.build import BASE, FAMILIES, LABELS, build_graph, families_of, graph_for, reader
from .kg.sql import graph_cte
from .functions import udfs
from .maintain.maintainer import Maintainer, state_folder
from .maintain.potential import Catalog, annotation_sizes, annotations, edge_to_answer, edge_to_cp, potential_matches, union_all
from .match.evaluate import derivations, evaluate
from .match.sql import to_sql
from .operators import joins
from .plan.andor import build
from .prov import poly, semiring
from .query.bgp import GraphQuery, Var, parse_select
from .query.folding import foldable_pairs
from .query.subquery import generate
from .sources import readers
from .sources.state import StateStore
from .stats import cardinality, labels
from .streaming import standing
from .workload import querylog, updates
from .workload.queries import get, labels_of, large_set, small_set

NAMES = ("W-S1", "W-S2", "W-S3", "W-S4", "W-C4", "W-Y4", "W-K3", "W-N", "W-P", "W-R", "W-E", "W-V", "W-M")
CORE = ("W-S1", "W-S2", "W-S3", "W-S4", "W-C4", "W-Y4", "W-K3")
SMALL = (1, 2, 3, 4, 5, 6, 7, 10, 16, 17, 18, 19)
HELD = "edge_id % 50 = 7"
GONE = "(edge_id * 31 + 7) % 101 = 0"
Q: dict = {}
SQL: dict[str, str] = {}


def _key(name: str) -> str:
    return name[2:].lower()


def _graph(spark: SparkSession, d: str, q: GraphQuery) -> DataFrame:
    return graph_for(spark, d, labels_of(q))


def _cte(q: GraphQuery, where: str = "true") -> str:
    names = ", ".join(f"'{x}'" for x in sorted(labels_of(q)))
    return "WITH " + graph_cte(families_of(labels_of(q)), f"p IN ({names}) AND ({where})")


def _ans(q: GraphQuery) -> str:
    return " || '|' || ".join(f"v_{v}" for v in q.head) or "''"


def _mono(q: GraphQuery) -> str:
    return f"list_sort([{', '.join(f'e_{i}' for i in range(len(q.body)))}])"


def sql_how(q: GraphQuery, where: str = "true", graph: str | None = None) -> str:
    return f"""{graph or _cte(q, where)}, d AS (SELECT {_ans(q)} AS ans, array_to_string({_mono(q)}, '.') AS m, count(*) AS n FROM ({to_sql(q)}) GROUP BY 1, 2),
    t AS (SELECT ans, CASE WHEN n > 1 THEN n || '*' ELSE '' END || m AS term FROM d) SELECT ans, string_agg(term, ' + ' ORDER BY term) AS poly FROM t GROUP BY ans"""


def _deriv(spark: SparkSession, d: str, q: GraphQuery, by_answer: bool = False) -> DataFrame:
    return derivations(evaluate(_graph(spark, d, q), q), q, by_answer)


def register(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# graph and statistics


def _all(where: str = "true", codes=SMALL) -> str:
    return "WITH " + graph_cte(codes, where)


register("kg_edges", f"{_all()} SELECT edge_id, s, p, o, inverse FROM g")(lambda s, d: build_graph(reader(s, d), SMALL))
register("kg_label_counts", f"{_all(codes=FAMILIES)} SELECT p, count(*) AS n, count(DISTINCT s) AS subjects, count(DISTINCT o) AS objects FROM g GROUP BY p")(
    lambda s, d: build_graph(reader(s, d)).groupBy("p").agg(F.count("*").alias("n"), F.count_distinct("s").alias("subjects"), F.count_distinct("o").alias("objects"))
)
register("kg_symmetric", f"{_all(codes=(2,))} SELECT edge_id, count(*) AS n FROM g GROUP BY edge_id")(lambda s, d: build_graph(reader(s, d), (2,)).groupBy("edge_id").agg(F.count("*").alias("n")))
register(
    "label_profile",
    f"""{_all()}, u AS (SELECT DISTINCT p, s, o FROM g), a AS (SELECT p, max(k) AS k FROM (SELECT p, s, count(*) AS k FROM u GROUP BY p, s) GROUP BY p), b AS (SELECT p, max(k) AS k FROM (SELECT p, o, count(*) AS k FROM u GROUP BY p, o) GROUP BY p),
    m AS (SELECT u.p, count(*) AS k FROM u JOIN u v ON u.p = v.p AND u.s = v.o AND u.o = v.s GROUP BY u.p), e AS (SELECT p, count(*) AS n FROM g WHERE NOT inverse GROUP BY p), l AS (SELECT p, sum(CASE WHEN s = o THEN 1 ELSE 0 END) AS loops, count(*) AS pairs FROM u GROUP BY p)
    SELECT e.p, e.n AS edges, CAST(a.k = 1 AS BIGINT) AS functional, CAST(b.k = 1 AS BIGINT) AS inverse_functional, CAST(loops = 0 AS BIGINT) AS irreflexive, CAST(coalesce(m.k, 0) = 0 AS BIGINT) AS asymmetric, CAST(coalesce(m.k, 0) = pairs AS BIGINT) AS symmetric
    FROM e JOIN a USING (p) JOIN b USING (p) JOIN l USING (p) LEFT JOIN m USING (p)""",
)(lambda s, d: labels.profile(build_graph(reader(s, d), SMALL)))
_SETS = "cs AS (SELECT s AS v, array_to_string(list_sort(list(DISTINCT p)), ',') AS preds FROM g GROUP BY s)"
register("charsets", f"{_all()}, {_SETS}, k AS (SELECT preds, count(*) AS vertices FROM cs GROUP BY preds), n AS (SELECT preds, count(*) AS edges FROM cs JOIN g ON v = s GROUP BY preds) SELECT preds, vertices, edges FROM k JOIN n USING (preds)")(
    lambda s, d: cardinality.charsets(build_graph(reader(s, d), SMALL)).select(F.array_join("preds", ",").alias("preds"), "vertices", F.aggregate(F.map_values("edges"), F.lit(0).cast("long"), lambda a, x: a + x).alias("edges"))
)
register("charpairs", f"{_all()}, {_SETS} SELECT a.preds AS s_preds, b.preds AS o_preds, p, count(*) AS cnt FROM g JOIN cs a ON g.s = a.v JOIN cs b ON g.o = b.v GROUP BY 1, 2, 3")(
    lambda s, d: cardinality.charpairs(build_graph(reader(s, d), SMALL)).select(F.array_join("s_preds", ",").alias("s_preds"), F.array_join("o_preds", ",").alias("o_preds"), "p", "cnt")
)

# pattern queries and provenance


def _bgp(s, d, name):
    return evaluate(_graph(s, d, get(name)), get(name))


def _how(s, d, name):
    return poly.how_text(_deriv(s, d, get(name), by_answer=True), merged=True)


for _n in NAMES:
    register(f"bgp_{_key(_n)}", f"{_cte(get(_n))} {to_sql(get(_n))}")(partial(_bgp, name=_n))
    register(f"how_{_key(_n)}", sql_how(get(_n)))(partial(_how, name=_n))
for _n, _k in (("W-V2", "how_coeff"), ("W-K3b", "how_coeff_rotation")):
    register(_k, sql_how(get(_n)))(partial(_how, name=_n))

_SHAPES = {
    "bgp_constant": "SELECT ?o { ?o placedBy cust:7 . ?o hasStatus ?x }",
    "bgp_varpred": "SELECT ?l ?o { cust:7 followed ?f . ?f ?l ?o }",
    "bgp_selfloop": "SELECT ?x { ?x followed ?x }",
    "bgp_fold": "SELECT ?a ?b { ?a followed ?x . ?b followed ?x }",
}
for _k, _t in _SHAPES.items():
    _q = parse_select(_t, _k)
    if "*" in _q.labels:
        register(_k, f"WITH {graph_cte((1, 14))} {to_sql(_q)}")(lambda s, d, q=_q: evaluate(build_graph(reader(s, d), (1, 14)), q))
    else:
        register(_k, f"{_cte(_q)} {to_sql(_q)}")(lambda s, d, q=_q: evaluate(_graph(s, d, q), q))

# The same over all families, where a variable label means every label.  The entries without _full are cut to what their SQL covers; these
# have no SQL form and are tested by brute force.  The order puts the fixed label first, so that no join pairs all vertices of one literal.


def _full(s, d) -> DataFrame:
    return build_graph(reader(s, d))


def _full_stored(s, d) -> DataFrame:
    """The whole graph, written once where several jobs read it."""
    at = state_folder(s)
    _full(s, d).write.parquet(at)
    return s.read.parquet(at)


def _how_e_full(s, d):
    q = get("W-E")
    return poly.how_text(derivations(evaluate(_full(s, d), q, order=[2, 0, 1]), q))


register("kg_edges_full")(_full)
register("label_profile_full")(lambda s, d: labels.profile(_full(s, d)))
register("charsets_full")(
    lambda s, d: cardinality.charsets(_full(s, d)).select(F.array_join("preds", ",").alias("preds"), "vertices", F.aggregate(F.map_values("edges"), F.lit(0).cast("long"), lambda a, x: a + x).alias("edges"))
)
register("charpairs_full")(lambda s, d: cardinality.charpairs(_full(s, d)).select(F.array_join("s_preds", ",").alias("s_preds"), F.array_join("o_preds", ",").alias("o_preds"), "p", "cnt"))
register("bgp_varpred_full")(lambda s, d, q=parse_select(_SHAPES["bgp_varpred"], "bgp_varpred_full"): evaluate(_full(s, d), q))
register("bgp_e_full")(lambda s, d: evaluate(_full(s, d), get("W-E"), order=[2, 0, 1]))
register("how_e_full")(_how_e_full)
_CROSS = parse_select("SELECT ?r ?s { ?n locatedIn region:1 . ?s locatedIn nation:3 }".replace("?r ?s", "?n ?s"), "cross")
register("bgp_cross", f"{_cte(_CROSS)} {to_sql(_CROSS)}")(lambda s, d: evaluate(_graph(s, d, _CROSS), _CROSS, allow_cross=True))
register("bgp_distinct", f"{_cte(get('W-S3'))} SELECT DISTINCT v_n1 AS n1, v_n2 AS n2 FROM ({to_sql(get('W-S3'))})")(lambda s, d: evaluate(_graph(s, d, get("W-S3")), get("W-S3"), keep_edges=False).select(F.col("v_n1").alias("n1"), F.col("v_n2").alias("n2")).distinct())


def _witness_sql(q: GraphQuery) -> str:
    return f"{_cte(q)}, w AS (SELECT DISTINCT {_ans(q)} AS ans, list_sort(list_distinct({_mono(q)})) AS w FROM ({to_sql(q)}))"


def _show(df: DataFrame) -> DataFrame:
    one = lambda w: F.array_join(F.transform(w, lambda e: e.cast("string")), ".")
    return df.select(F.array_join("ans", "|").alias("ans"), F.array_join(F.array_sort(F.transform("witnesses", one)), " + ").alias("why"))


for _n in ("W-S2", "W-S4", "W-K3", "W-V2"):
    _q = get(_n)
    register(f"why_{_key(_n)}", f"{_witness_sql(_q)} SELECT ans, string_agg(array_to_string(w, '.'), ' + ' ORDER BY array_to_string(w, '.')) AS why FROM w GROUP BY ans")(lambda s, d, q=_q: _show(poly.why(_deriv(s, d, q))))
_q = get("W-S2")
register("why_minimal", f"{_witness_sql(_q)}, m AS (SELECT * FROM w WHERE NOT EXISTS (SELECT 1 FROM w x WHERE x.ans = w.ans AND x.w <> w.w AND list_has_all(w.w, x.w))) SELECT ans, string_agg(array_to_string(w, '.'), ' + ' ORDER BY array_to_string(w, '.')) AS why FROM m GROUP BY ans")(
    lambda s, d: _show(poly.why(_deriv(s, d, get("W-S2")), minimal=True))
)
register("lineage", f"{_cte(_q)}, e AS (SELECT DISTINCT {_ans(_q)} AS ans, unnest({_mono(_q)}) AS e FROM ({to_sql(_q)})) SELECT ans, string_agg(CAST(e AS VARCHAR), '.' ORDER BY e) AS edges FROM e GROUP BY ans")(
    lambda s, d: poly.lineage(_deriv(s, d, get("W-S2"))).select(F.array_join("ans", "|").alias("ans"), F.array_join(F.transform("edges", lambda e: e.cast("string")), ".").alias("edges"))
)
register("how_square", f"{_cte(_q)} SELECT {_ans(_q)} AS ans, array_to_string({_mono(_q)}, '.') AS mono, count(*) AS n FROM ({to_sql(_q)}) WHERE e_3 = e_4 GROUP BY 1, 2")(
    lambda s, d: derivations(evaluate(_graph(s, d, get("W-S2")), get("W-S2")).where("e_3 = e_4"), get("W-S2")).select(F.array_join("ans", "|").alias("ans"), F.array_join(F.transform("mono", lambda e: e.cast("string")), ".").alias("mono"), "n")
)
_W = "(e % 97)"
_RINGS = {"count": (semiring.COUNT, "count(*)"), "bool": (semiring.BOOL, "bool_or(list_min(list_transform(m, lambda e: e % 97)) > 4)"), "tropical": (semiring.TROPICAL, "CAST(min(list_sum(list_transform(m, lambda e: e % 97))) AS BIGINT)"), "fuzzy": (semiring.FUZZY, "CAST(max(list_min(list_transform(m, lambda e: e % 97))) AS BIGINT)"), "security": (semiring.SECURITY, "CAST(min(list_max(list_transform(m, lambda e: e % 97))) AS BIGINT)")}
for _k, (_ring, _expr) in _RINGS.items():
    value = {"count": lambda e: F.lit(1), "bool": lambda e: F.pmod(e, F.lit(97)) > 4}.get(_k, lambda e: F.pmod(e, F.lit(97)))
    register(f"semiring_{_k}", f"{_cte(_q)} SELECT ans, {_expr} AS value FROM (SELECT {_ans(_q)} AS ans, {_mono(_q)} AS m FROM ({to_sql(_q)})) GROUP BY ans")(
        lambda s, d, ring=_ring, value=value: semiring.evaluate(_deriv(s, d, get("W-S2")), value, ring).select(F.array_join("ans", "|").alias("ans"), "value")
    )
register("poly_zero", sql_how(_q, f"edge_id <> {3 * BASE + 1}"))(
    lambda s, d: poly.how(_deriv(s, d, get("W-S2"))).withColumn("poly", poly.zero_out("poly", F.lit(3 * BASE + 1))).where(F.size("poly") > 0).select(F.array_join("ans", "|").alias("ans"), poly.render("poly").alias("poly"))
)

# subqueries, folding, plans: driver-side algorithms against values derived by hand


def _values(rows: list[tuple], names: str) -> str:
    lit = lambda x: f"'{x}'" if isinstance(x, str) else f"CAST({x} AS BIGINT)"
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(lit, r)) + ')' for r in rows)}) t({names})"


def _with_edges(s, d, rows: list[tuple], names: str) -> DataFrame:
    """Rows (..., label), one for each pattern, summed up with the edges of the given tables that have the label."""
    counts = graph_for(s, d, {r[-1] for r in rows}).groupBy("p").agg(F.count("*").alias("n"))
    df = s.createDataFrame(rows, f"{names}, label string")
    return df.join(counts, F.col("label") == F.col("p"), "left").groupBy(*df.columns[:-1]).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("edges"))


def _edges_sql(rows: list[tuple], names: str) -> str:
    known = sorted({r[-1] for r in rows})
    return f"WITH {graph_cte(families_of(known), f'p IN ({", ".join(map(repr, known))})')}, a AS ({_values(rows, f'{names}, label')}), k AS (SELECT p, count(*) AS n FROM g GROUP BY p) SELECT {names}, CAST(coalesce(sum(n), 0) AS BIGINT) AS edges FROM a LEFT JOIN k ON p = label GROUP BY {names}"


def _patterns(rows: list[tuple]) -> list[tuple]:
    """A row (qid, ...) for each pattern of the query, with its label."""
    return [(*r, p.label) for r in rows for p in get(r[0]).body]


_TYPES = {"W-S2": "II,II,I,I,I", "W-S1": "IV,IV,IV,IV,I,I", "W-Y4": "IV,IV,IV,IV", "W-C4": "II,I,II,I", "W-S3": "III,I,I,II,I,II,I", "W-K3": "IV,IV,IV", "W-S4": "IV,IV,IV,IV,IV,IV,I"}
register("subq_catalog", _edges_sql(_patterns(list(_TYPES.items())), "qid, types"))(
    lambda s, d: _with_edges(s, d, [(n, ",".join(x.kind for x in subs), x.exp_rel) for n in _TYPES for subs in [generate(get(n))] for x in subs], "qid string, types string")
)
_FOLDS = {"W-S1": 3, "W-S2": 1, "W-S3": 1, "W-Y4": 1, "W-C4": 0, "W-K3": 3, "W-P": 1, "W-V": 1, "W-R": 1}
register("fold_catalog", _edges_sql(_patterns(list(_FOLDS.items())), "qid, pairs"))(lambda s, d: _with_edges(s, d, _patterns([(n, len(foldable_pairs(get(n)))) for n in _FOLDS]), "qid string, pairs bigint"))
_FOLDED = [("W-S1", ""), ("W-S2", "3-4"), ("W-S3", ""), ("W-Y4", ""), ("W-C4", "")]


def _profiled(s, d):
    c = labels.constraints(build_graph(reader(s, d), range(1, 14)))
    return s.createDataFrame([(n, ",".join(f"{i}-{j}" for i, j in foldable_pairs(get(n), c))) for n, _ in _FOLDED], "qid string, pairs string")


register("fold_profiled", _values(_FOLDED, "qid, pairs"))(_profiled)
_SIZES = {"W-S1": (42, 125), "W-S2": (19, 32), "W-S3": (49, 144), "W-S4": (90, 422), "W-C4": (10, 10), "W-Y4": (13, 18), "W-K3": (7, 6)}
register("andor_sizes", _edges_sql(_patterns([(n, *x) for n, x in _SIZES.items()]), "qid, or_nodes, and_nodes"))(lambda s, d: _with_edges(s, d, _patterns([(n, *build(get(n).body).sizes) for n in _SIZES]), "qid string, or_nodes bigint, and_nodes bigint"))
_SETS_OF = (("large", large_set, 215, 845), ("small", small_set, 4, 25))


def _subqueries(s, d):
    """Queries and subqueries of each set, and how often an edge of the given tables is routed to one of them."""
    made = [(n, qs, [x for q in qs for x in generate(q)]) for n, f, _, _ in _SETS_OF for qs in [f()]]
    return _with_edges(s, d, [(n, len(qs), len(subs), x.exp_rel) for n, qs, subs in made for x in subs], "query_set string, queries bigint, subqueries bigint")


register("m_subqueries", _edges_sql([(n, a, b, p.label) for n, f, a, b in _SETS_OF for q in f() for p in q.body], "query_set, queries, subqueries"))(_subqueries)


def _estimator(s, d, formula="pair_sum"):
    return cardinality.Estimator.build(build_graph(reader(s, d), range(1, 14)), formula)


def _sharing(s, d):
    est = _estimator(s, d).estimate
    rows = [{"query_set": f"size {r['size']}", **r} for r in measures.by_size(large_set(), est)] + [{"query_set": "all", **measures.sharing(large_set(), est)}]
    names = ("queries", "subqueries", "intermediate", "nodes", "leaves", "inner", "labels")
    return s.createDataFrame([(r["query_set"], *[int(r[n]) for n in names], float(r["gain"]), float(r["coverage"]), float(r["mean_affected"])) for r in rows], "query_set string, " + ", ".join(f"{n} bigint" for n in names) + ", gain double, coverage double, mean_affected double")


register("m_global_plan")(_sharing)
register("plan_choice")(lambda s, d: s.createDataFrame([(q.name, p, float(_cost(q, est, p))) for est in [_estimator(s, d).estimate] for q in small_set() for p in ("greedy", "dp")], "qid string, policy string, cost double"))


def _cost(q, est, policy):
    from .plan.andor import choose, cost

    return cost(choose(q.body, est, policy), est)


def _qerror(s, d):
    """The statistics of the whole graph, all families and all of its sets and pairs, are made once for all formulas."""
    g = _full_stored(s, d)
    names = ("W-S1", "W-S2", "W-C4", "W-Y4")
    est = cardinality.Estimator.build(g)
    rows = [(formula, n, float(replace(est, formula=formula).estimate(get(n).body))) for formula in ("pair_sum", "star", "label_count", "independence") for n in names]
    exact = s.createDataFrame([(evaluate(g, get(n), keep_edges=False).count(), n) for n in names], "exact bigint, qid string")
    e = s.createDataFrame(rows, "formula string, qid string, estimate double").join(exact, "qid")
    a, b = F.greatest("estimate", F.lit(1.0)), F.greatest("exact", F.lit(1)).cast("double")
    return e.withColumn("q_error", F.greatest(a / b, b / a))


register("card_qerror")(_qerror)

# potential matches, annotations, indexes


def _catalog(names) -> Catalog:
    c = Catalog()
    for n in names:
        c.add(get(n))
    return c


def _half_sql(q: GraphQuery) -> str:
    """Counts of each annotated end of each kept half, evaluated apart from any shared plan."""
    parts = []
    for sub in generate(q):
        if sub.kind not in ("I", "II", "III", "IV"):
            continue
        for h in sub.annotated:
            hq = GraphQuery("h", (), tuple(sub.patterns(h)))
            for direction, var in (("out", h.out_var), ("in", h.in_var)):
                if var:
                    parts.append(f"SELECT '{sub.sqid}' AS sqid, CAST({h.number} AS BIGINT) AS half, '{direction}' AS dir, v_{var} AS vertex, array_to_string(list_sort([{', '.join(f'e_{i}' for i in range(len(hq.body)))}]), '.') AS mono FROM ({to_sql(hq)})")
    return f"{_cte(q)}, a AS ({' UNION ALL '.join(parts)})"


def _ann(s, d, name):
    return annotations(potential_matches(_graph(s, d, get(name)), _catalog([name])), _catalog([name]))


for _n in ("W-S2", "W-S4", "W-Y4"):
    register(f"ann_{_key(_n)}", f"{_half_sql(get(_n))} SELECT sqid, half, dir, count(*) AS n, count(DISTINCT vertex) AS vertices FROM a GROUP BY 1, 2, 3")(
        lambda s, d, n=_n: annotation_sizes(_graph(s, d, get(n)), _catalog([n]))
    )
register("ann_rows", f"{_half_sql(get('W-S2'))} SELECT sqid, half, dir, vertex, mono, count(*) AS n FROM a GROUP BY ALL")(
    lambda s, d: _ann(s, d, "W-S2").groupBy("sqid", F.col("half").cast("long").alias("half"), "dir", "vertex", F.array_join(F.transform("mono", lambda e: e.cast("string")), ".").alias("mono")).agg(F.sum("n").alias("n"))
)
register("m_cps", f"{_half_sql(get('W-S2'))} SELECT count(DISTINCT vertex) AS vertices, count(DISTINCT (vertex, sqid, dir)) AS points FROM a")(lambda s, d: measures.connection_points(_ann(s, d, "W-S2")).select("vertices", "points"))
register("idx_answers", f"{_cte(_q)} SELECT DISTINCT unnest({_mono(_q)}) AS edge_id, {_ans(_q)} AS ans FROM ({to_sql(_q)})")(lambda s, d: edge_to_answer(_deriv(s, d, get("W-S2"))).select("edge_id", F.array_join("ans", "|").alias("ans")))
register("idx_cps", f"{_half_sql(get('W-S2'))} SELECT DISTINCT CAST(unnest(string_split(mono, '.')) AS BIGINT) AS edge_id, sqid, half, dir, vertex FROM a")(lambda s, d: edge_to_cp(_ann(s, d, "W-S2")).select("edge_id", "sqid", F.col("half").cast("long").alias("half"), "dir", "vertex"))
register("m_polysize", f"{_cte(get('W-C4'))}, d AS (SELECT v_g AS ans, {_mono(get('W-C4'))} AS m FROM ({to_sql(get('W-C4'))}) GROUP BY 1, 2), p AS (SELECT ans, count(*) AS k FROM d GROUP BY ans) SELECT count(*) AS answers, CAST(sum(k) AS BIGINT) AS monomials, max(k) AS largest FROM p")(
    lambda s, d: measures.polynomial_sizes(_deriv(s, d, get("W-C4")))
)

# maintenance: the state after updates against queries on the final graph


def _replay(s, d, name, potential="kept"):
    """Register without the held-out edges, insert them, give the polynomials; a variable label means every label of the whole graph."""
    q = get(name)
    g = _full_stored(s, d) if "*" in q.labels else _graph(s, d, q)
    m = Maintainer(updates.held_out(g, True), potential=potential).register(q)
    m.insert(updates.held_out(g, False))
    return poly.how_text(m.deriv)


for _n in (*CORE, "W-R"):
    register(f"ins_{_key(_n)}", sql_how(get(_n)))(partial(_replay, name=_n))
register("ins_e", sql_how(get("W-E"), graph=_all(codes=FAMILIES)))(partial(_replay, name="W-E"))
register("ins_lazy", sql_how(get("W-S2")))(partial(_replay, name="W-S2", potential="none"))


def _replay_annotations(s, d):
    q = get("W-S2")
    g = _graph(s, d, q)
    m = Maintainer(updates.held_out(g, True)).register(q)
    m.insert(updates.held_out(g, False))
    return m.annotation.groupBy("sqid", F.col("half").cast("long").alias("half"), "dir").agg(F.sum("n").alias("n"), F.count_distinct("vertex").alias("vertices"))


register("ins_maintain", SQL["ann_s2"])(_replay_annotations)


def _changes_sql(q: GraphQuery) -> str:
    names = ", ".join(f"'{x}'" for x in sorted(labels_of(q)))
    both = f"WITH {graph_cte(families_of(labels_of(q)), f'p IN ({names})')}"
    old = to_sql(q, sources=[f"(SELECT * FROM g WHERE NOT {HELD})"] * len(q.body))
    return f"{both}, n AS (SELECT {_ans(q)} AS ans, count(*) AS k FROM ({to_sql(q)}) GROUP BY 1), o AS (SELECT {_ans(q)} AS ans, count(*) AS k FROM ({old}) GROUP BY 1) SELECT n.ans, CASE WHEN o.k IS NULL THEN 'added' ELSE 'support_added' END AS change, n.k - coalesce(o.k, 0) AS n FROM n LEFT JOIN o USING (ans) WHERE n.k > coalesce(o.k, 0)"


def _insert_changes(s, d):
    q = get("W-S2")
    g = _graph(s, d, q)
    return Maintainer(updates.held_out(g, True)).register(q).insert(updates.held_out(g, False)).select(F.array_join("ans", "|").alias("ans"), "change", "n")


register("ins_changes", _changes_sql(get("W-S2")))(_insert_changes)


def _deleted(s, d, name, use_index=True):
    q = get(name)
    g = _graph(s, d, q)
    m = Maintainer(g).register(q)
    m.delete(updates.deletes(g, labels_of(q)), use_index)
    return poly.how_text(m.deriv)


for _n in CORE:
    register(f"del_{_key(_n)}", sql_how(get(_n), f"NOT ({GONE})"))(partial(_deleted, name=_n))
register("abl_noindex", SQL["del_s2"])(partial(_deleted, name="W-S2", use_index=False))


def _delete_changes(s, d):
    q = get("W-S2")
    g = _graph(s, d, q)
    return Maintainer(g).register(q).delete(updates.deletes(g, labels_of(q))).select(F.array_join("ans", "|").alias("ans"), "change", "n")


_LEFT = to_sql(_q, sources=[f"(SELECT * FROM g WHERE NOT ({GONE}))"] * 5)
register("del_changes", f"{_cte(_q)}, n AS (SELECT {_ans(_q)} AS ans, count(*) AS k FROM ({_LEFT}) GROUP BY 1), o AS (SELECT {_ans(_q)} AS ans, count(*) AS k FROM ({to_sql(_q)}) GROUP BY 1) SELECT o.ans, CASE WHEN n.k IS NULL THEN 'removed' ELSE 'support_lost' END AS change, o.k - coalesce(n.k, 0) AS n FROM o LEFT JOIN n USING (ans) WHERE o.k > coalesce(n.k, 0)")(_delete_changes)


def _dropped_vertex(s, d):
    q = get("W-S2")
    m = Maintainer(_graph(s, d, q)).register(q)
    m.drop_vertex("cust:7")
    return poly.how_text(m.deriv)


register("del_vertex", sql_how(_q, "s <> 'cust:7' AND o <> 'cust:7'"))(_dropped_vertex)


def _modified(s, d):
    """Held-out edges modified: deleted, then inserted again."""
    q = get("W-S4")
    g = _graph(s, d, q)
    m = Maintainer(g).register(q)
    m.replace(updates.held_out(g, False).select("edge_id"), updates.held_out(g, False))
    return poly.how_text(m.deriv)


register("upd_modify", sql_how(get("W-S4")))(_modified)


def _mix_rule(part: int, first: str) -> tuple[str, str]:
    """SQL conditions on edge_id: inserted later, deleted; of each hundred edges 10 - part and part."""
    slot = "((edge_id // 7) % 100)" if first == "sql" else "((edge_id div 7) % 100)"
    return f"{slot} < {10 - part}", f"{slot} >= {100 - part}"


def _mixed(s, d, part):
    """An interleaved stream of inserts and deletes in the mix's ratio; a tenth of the deleted ids comes back at the end."""
    q = get("W-S2")
    g = _graph(s, d, q)
    new, old = _mix_rule(part, "spark")
    m = Maintainer(g.where(f"NOT ({new})")).register(q)
    back = g.where(old).where("edge_id % 10 = 3")
    u = updates.as_updates(g.where(new), g.where(old).select("edge_id").distinct(), part)
    last = u.agg(F.max("seq").alias("_m"))
    again = back.crossJoin(F.broadcast(last)).select((F.col("_m") + 1).alias("seq"), F.lit("ins").alias("op"), "edge_id", "s", "p", "o", "inverse")  # one row on that side
    m.apply(u.select("seq", "op", "edge_id", "s", "p", "o", F.coalesce("inverse", F.lit(False)).alias("inverse")).unionByName(again))
    return poly.how_text(m.deriv)


for _m, _part in updates.MIXES.items():
    register(f"mix_{_m}", sql_how(_q, f"NOT ({_mix_rule(_part, 'sql')[1]}) OR edge_id % 10 = 3"))(partial(_mixed, part=_part))


def _event_graph(s, d):
    q = parse_select("SELECT ?u ?v { ?u purchase ?t . ?v purchase ?t . ?v click ?x }", "events")
    m = Maintainer(build_graph(reader(s, d), (14,)).where("false")).register(q)
    m.apply(updates.from_events(reader(s, d)("events")))
    return poly.how_text(m.deriv)


_EV = parse_select("SELECT ?u ?v { ?u purchase ?t . ?v purchase ?t . ?v click ?x }", "events")
_DROPPED = f"edge_id NOT IN (SELECT CAST({14 * BASE} + last_id AS BIGINT) FROM (SELECT event_type, last_value(CASE WHEN event_type <> 'error' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_id FROM events) WHERE event_type = 'error' AND last_id IS NOT NULL)"
register("mix_events", sql_how(_EV, _DROPPED))(_event_graph)


def _explained(s, d):
    """Derivations that an answer has after deletes, by the maintainer: those of the least answer from scratch."""
    q = get("W-S2")
    g = _graph(s, d, q)
    m = Maintainer(g).register(q)
    m.delete(updates.deletes(g, labels_of(q)))
    ans = m.deriv.select("ans").orderBy(F.array_join("ans", "|")).first()["ans"]
    return m.explain(q.name, ans).select(F.array_join(F.transform("mono", lambda e: e.cast("string")), ".").alias("mono"), "n")


_KEPT = f"NOT ({GONE})"
register("explain_answer", f"{_cte(_q, _KEPT)} SELECT array_to_string({_mono(_q)}, '.') AS mono, count(*) AS n FROM ({to_sql(_q)}) WHERE {_ans(_q)} = (SELECT min({_ans(_q)}) FROM ({to_sql(_q)})) GROUP BY 1")(_explained)

# baselines and ablations


def _poly_text(df: DataFrame) -> DataFrame:
    return df.select(F.array_join("ans", "|").alias("ans"), poly.render("poly").alias("poly"))


for _n in ("W-S1", "W-S2", "W-C4"):
    register(f"b1_{_key(_n)}", sql_how(get(_n)))(lambda s, d, n=_n: _poly_text(recompute.graph_recompute(_graph(s, d, get(n)), [get(n)])))
    register(f"b2_{_key(_n)}", sql_how(get(_n)))(lambda s, d, n=_n: _poly_text(recompute.rewrite_recompute(_graph(s, d, get(n)), [get(n)])))


def _circuit(s, d, name):
    ans, gates = recompute.circuit_recompute(_graph(s, d, get(name)), get(name))
    return poly.how_text(recompute.expand(ans, gates, len(get(name).body)).withColumn("qid", F.lit(name)))


register("b3_c4", sql_how(get("W-C4")))(partial(_circuit, name="W-C4"))
register("b3_k3", sql_how(get("W-K3")))(partial(_circuit, name="W-K3"))


def _rerun(s, d):
    q = get("W-S2")
    g = _graph(s, d, q)
    before = derivations(evaluate(updates.held_out(g, True), q), q)
    new, lost = recompute.rerun_all(g, [q], before)
    return new.select(F.array_join("ans", "|").alias("ans"), F.lit("added").alias("change")).unionByName(lost.select(F.array_join("ans", "|").alias("ans"), F.lit("removed").alias("change")))


register("b0_diff", f"SELECT ans, change FROM ({_changes_sql(get('W-S2'))}) WHERE change = 'added'")(_rerun)


def _counting(s, d):
    q = get("W-S2")
    g = _graph(s, d, q)
    old = updates.held_out(g, True)
    return recompute.counting(old, updates.held_out(g, False), updates.deletes(old, labels_of(q)), q).select(F.array_join("ans", "|").alias("ans"), "n")


_FINAL = f"({HELD}) OR NOT ({GONE})"
register("abl_counting", f"{_cte(_q, _FINAL)} SELECT {_ans(_q)} AS ans, count(*) AS n FROM ({to_sql(_q)}) GROUP BY 1")(_counting)


def _untracked(s, d):
    q = get("W-S2")
    g = _graph(s, d, q)
    m = Maintainer(updates.held_out(g, True), track=False).register(q)
    m.insert(updates.held_out(g, False))
    return m.answers.select(F.array_join("ans", "|").alias("ans"), "n")


register("abl_notrack", f"{_cte(_q)} SELECT {_ans(_q)} AS ans, count(*) AS n FROM ({to_sql(_q)}) GROUP BY 1")(_untracked)

# query log, streams


def _requests(s, d):
    """A request for each event: queries of two shapes of two patterns, the one with two spellings, of one pattern, questions, and broken texts."""
    e, user = reader(s, d)("events"), F.col("user_id").cast("string")
    two = F.when(F.col("event_id") % 2 == 0, F.concat(F.lit("SELECT ?x { ?x followed cust:"), user, F.lit(" . ?x locatedIn ?n }"))).otherwise(F.concat(F.lit("SELECT ?b { ?b locatedIn ?m . ?b followed cust:"), user, F.lit(" }")))
    path = F.concat(F.lit("SELECT ?w { cust:"), user, F.lit(" followed ?v . ?v followed ?w }"))
    one = F.concat(F.lit("SELECT ?a { ?a coActive cust:"), user, F.lit(" }"))
    ask, broken = F.concat(F.lit("ASK { ?a followed cust:"), user, F.lit(" }")), F.concat(F.lit("SELECT ?a { cust:"), user)
    kind = F.col("event_type")
    text = F.when(kind == "purchase", two).when(kind == "view", path).when(kind == "click", one).when(kind == "signup", ask).otherwise(broken)
    return e.select(F.col("event_id").alias("qid"), text.alias("text"))


_FUNNEL = """SELECT count(*) AS requests, count(*) FILTER (user_id IS NOT NULL AND event_type IS DISTINCT FROM 'signup') AS selects, count(*) FILTER (user_id IS NOT NULL AND event_type IN ('purchase', 'view')) AS conjunctions,
    count(DISTINCT user_id) FILTER (event_type = 'purchase') + count(DISTINCT user_id) FILTER (event_type = 'view') AS distinct_queries FROM events"""


def _log(s):
    texts = [f"SELECT * {{ {t} }}" for t in ("?a followed ?b . ?b followed ?c", "?x followed ?y . ?y followed ?z", "?a followed ?b", "?a followed ?b . ?b locatedIn ?n", "?q followed ?r . ?r locatedIn ?m")]
    texts += ["ASK { ?a followed ?b }", "SELECT ?a { ?a followed ?b } ORDER BY ?a", "SELECT (COUNT(?a) AS ?n) { ?a followed ?b . ?b followed ?c }", "SELECT ?a { { ?a followed ?b } UNION { ?b followed ?a } }", "SELECT ?a {"]
    return s.createDataFrame(list(enumerate(texts)), "qid long, text string")


register("log_funnel", _FUNNEL)(lambda s, d: querylog.funnel(_requests(s, d)))


def _stream(s, d, step, name):
    """The event updates as a file stream, through `step`, into a memory table."""
    folder = tempfile.mkdtemp(prefix="provgraph_stream_") if not s.conf.get("spark.checkpoint.dir", None) else f"{s.conf.get('spark.checkpoint.dir').rstrip('/')}/stream-{name}-{id(step)}"
    u = updates.from_events(reader(s, d)("events"))
    u.repartition(4).write.mode("overwrite").parquet(f"{folder}/in")
    live = s.readStream.schema(u.schema).option("maxFilesPerTrigger", 2).parquet(f"{folder}/in")
    step(live).writeStream.format("memory").queryName(name).outputMode("complete" if name != "stream_dedup" else "append").option("checkpointLocation", f"{folder}/cp").trigger(availableNow=True).start().awaitTermination()
    return s.table(name)


_U = "u AS (SELECT ts, CASE WHEN event_type = 'error' THEN 'del' ELSE 'ins' END AS op, 'cust:' || user_id AS s FROM (SELECT *, last_value(CASE WHEN event_type <> 'error' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_id FROM events) WHERE event_type <> 'error' OR last_id IS NOT NULL)"
register("stream_tumbling", f"WITH {_U} SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS day, op, count(*) AS n FROM u GROUP BY 1, 2")(
    lambda s, d: _stream(s, d, standing.tumbling, "stream_tumbling").select(F.unix_timestamp("w.start").alias("day"), "op", "n")
)
register("stream_sliding", f"WITH {_U}, k AS (SELECT unnest([0, 1, 2, 3]) AS k) SELECT CAST(floor(epoch(ts) / 21600) * 21600 - k * 21600 AS BIGINT) AS start, op, count(*) AS n FROM u, k GROUP BY 1, 2")(
    lambda s, d: _stream(s, d, standing.sliding, "stream_sliding").select(F.unix_timestamp("w.start").alias("start"), "op", "n")
)


def _standing(s, d):
    """A standing query over the event stream ends with the batch's answers."""
    folder = tempfile.mkdtemp(prefix="provgraph_stream_") if not s.conf.get("spark.checkpoint.dir", None) else f"{s.conf.get('spark.checkpoint.dir').rstrip('/')}/standing-{id(s)}"
    u = updates.from_events(reader(s, d)("events"))
    u.repartitionByRange(3, "seq").write.mode("overwrite").parquet(f"{folder}/in")
    m = Maintainer(build_graph(reader(s, d), (14,)).where("false")).register(_EV)
    standing.run(s.readStream.schema(u.schema).option("maxFilesPerTrigger", 3).parquet(f"{folder}/in"), m, f"{folder}/cp")
    return poly.how_text(m.deriv)


register("stream_batch_parity", SQL["mix_events"])(_standing)

# operators around the methods

_LOC = "WITH " + graph_cte((1, 3, 6, 7))


def _loc(s, d):
    return build_graph(reader(s, d), (1, 3, 6, 7))


register("op_filter", f"{_LOC} SELECT edge_id, s, p, o FROM g WHERE p IN ('locatedIn', 'followed') AND s LIKE 'cust:1%'")(lambda s, d: _loc(s, d).where(F.col("p").isin("locatedIn", "followed") & F.col("s").like("cust:1%")).select("edge_id", "s", "p", "o"))
register("op_class", f"{_LOC} SELECT p, split_part(s, ':', 1) AS sc, split_part(o, ':', 1) AS oc, count(*) AS n FROM g GROUP BY ALL")(lambda s, d: _loc(s, d).groupBy("p", F.split("s", ":")[0].alias("sc"), F.split("o", ":")[0].alias("oc")).agg(F.count("*").alias("n")))
register("join_semi", f"{_LOC} SELECT s, o FROM g WHERE p = 'placedBy' AND EXISTS (SELECT 1 FROM g h WHERE h.p = 'followed' AND h.s = g.o)")(lambda s, d: _loc(s, d).where("p = 'placedBy'").join(_loc(s, d).where("p = 'followed'").select(F.col("s").alias("x")), F.col("o") == F.col("x"), "left_semi").select("s", "o"))
register("join_anti", f"{_LOC} SELECT s, o FROM g WHERE p = 'placedBy' AND NOT EXISTS (SELECT 1 FROM g h WHERE h.p = 'followed' AND h.s = g.o)")(lambda s, d: _loc(s, d).where("p = 'placedBy'").join(_loc(s, d).where("p = 'followed'").select(F.col("s").alias("x")), F.col("o") == F.col("x"), "left_anti").select("s", "o"))
register("join_outer", f"{_LOC}, a AS (SELECT s AS v, count(*) AS n FROM g WHERE p = 'followed' GROUP BY s), b AS (SELECT o AS v, count(*) AS m FROM g WHERE p = 'followed' GROUP BY o) SELECT v, coalesce(n, 0) AS n, coalesce(m, 0) AS m FROM a FULL JOIN b USING (v)")(
    lambda s, d: (lambda g: g.groupBy(F.col("s").alias("v")).agg(F.count("*").alias("n")).join(g.groupBy(F.col("o").alias("v")).agg(F.count("*").alias("m")), "v", "full_outer").fillna(0))(_loc(s, d).where("p = 'followed'"))
)
register("agg_cube", f"{_LOC} SELECT coalesce(p, '*') AS p, coalesce(c, '*') AS c, count(*) AS n FROM (SELECT p, split_part(o, ':', 1) AS c FROM g) GROUP BY CUBE (p, c)")(lambda s, d: _loc(s, d).select("p", F.split("o", ":")[0].alias("c")).cube("p", "c").agg(F.count("*").alias("n")).select(F.coalesce("p", F.lit("*")).alias("p"), F.coalesce("c", F.lit("*")).alias("c"), "n"))
register("agg_rollup", f"{_LOC} SELECT coalesce(p, '*') AS p, coalesce(c, '*') AS c, count(*) AS n FROM (SELECT p, split_part(o, ':', 1) AS c FROM g) GROUP BY ROLLUP (p, c)")(lambda s, d: _loc(s, d).select("p", F.split("o", ":")[0].alias("c")).rollup("p", "c").agg(F.count("*").alias("n")).select(F.coalesce("p", F.lit("*")).alias("p"), F.coalesce("c", F.lit("*")).alias("c"), "n"))
register("agg_pivot", f"{_LOC} SELECT o, count(*) FILTER (p = 'locatedIn') AS located, count(*) FILTER (p = 'inSegment') AS segment FROM g WHERE p IN ('locatedIn', 'inSegment') GROUP BY o")(
    lambda s, d: _loc(s, d).where("p in ('locatedIn', 'inSegment')").groupBy("o").pivot("p", ["locatedIn", "inSegment"]).count().fillna(0).select("o", F.col("locatedIn").alias("located"), F.col("inSegment").alias("segment"))
)
register("agg_maxby", f"{_LOC} SELECT p, max_by(o, edge_id) AS last_o FROM g GROUP BY p")(lambda s, d: _loc(s, d).groupBy("p").agg(F.max_by("o", "edge_id").alias("last_o")))
register("agg_distinct", f"{_LOC} SELECT count(DISTINCT s) AS s, count(DISTINCT o) AS o FROM g")(lambda s, d: _loc(s, d).agg(F.count_distinct("s").alias("s"), F.count_distinct("o").alias("o")))
register("win_rank", f"{_LOC}, c AS (SELECT p, o, count(*) AS n FROM g GROUP BY p, o) SELECT p, o, n, rank() OVER (PARTITION BY p ORDER BY n DESC) AS r, dense_rank() OVER (PARTITION BY p ORDER BY n DESC) AS dr FROM c QUALIFY r <= 5")(
    lambda s, d: (lambda w: _loc(s, d).groupBy("p", "o").agg(F.count("*").alias("n")).withColumns({"r": F.rank().over(w), "dr": F.dense_rank().over(w)}).where("r <= 5"))(Window.partitionBy("p").orderBy(F.desc("n")))
)
register("win_running", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS n FROM events")(lambda s, d: reader(s, d)("events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)).alias("n")))
register("set_ops", f"{_LOC}, a AS (SELECT s AS v FROM g WHERE p = 'followed'), b AS (SELECT o AS v FROM g WHERE p = 'followed') SELECT 'both' AS k, v FROM (SELECT v FROM a INTERSECT SELECT v FROM b) UNION ALL SELECT 'first', v FROM (SELECT v FROM a EXCEPT SELECT v FROM b)")(
    lambda s, d: (lambda g: g.select(F.col("s").alias("v")).intersect(g.select("o")).select(F.lit("both").alias("k"), "v").union(g.select("s").subtract(g.select("o")).select(F.lit("first"), "s")))(_loc(s, d).where("p = 'followed'"))
)
register("topk_support", f"{_cte(get('W-C4'))} SELECT v_g AS ans, count(*) AS n FROM ({to_sql(get('W-C4'))}) GROUP BY 1 ORDER BY n DESC, ans LIMIT 3")(lambda s, d: poly.total(_deriv(s, d, get("W-C4"))).select(F.array_join("ans", "|").alias("ans"), "n").orderBy(F.desc("n"), "ans").limit(3))


def _asof(s, d):
    e = reader(s, d)("events")
    buys = e.where("event_type = 'purchase'").select("event_id", "user_id", F.col("ts").alias("t"))
    clicks = e.where("event_type = 'click'").select("user_id", F.col("ts").alias("t"), F.col("event_id").alias("click_id"))
    return joins.asof(buys, clicks, "user_id", "t", "click_id").select("event_id", "click_id")


register("join_asof", "SELECT event_id, click_id FROM (SELECT event_id, event_type, max(CASE WHEN event_type = 'click' THEN event_id END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS click_id FROM events) WHERE event_type = 'purchase'")(_asof)


def _interval(s, d):
    e = reader(s, d)("events").select("event_id", "event_type", F.unix_timestamp("ts").alias("t"))
    spans = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("t").alias("from_t"), (F.col("t") + 900).alias("to_t"))
    return joins.interval(e.where("event_type <> 'error'"), spans, "t", "from_t", "to_t", 900).groupBy("error_id").agg(F.count("*").alias("n"))


register("join_interval", "WITH e AS (SELECT event_id, event_type, CAST(floor(epoch(ts)) AS BIGINT) AS t FROM events) SELECT x.event_id AS error_id, count(*) AS n FROM e x JOIN e y ON y.t >= x.t AND y.t < x.t + 900 AND y.event_type <> 'error' WHERE x.event_type = 'error' GROUP BY 1")(_interval)
register("join_salted", "SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand")(
    lambda s, d: joins.salted(reader(s, d)("lineitem").withColumnRenamed("l_partkey", "k"), reader(s, d)("part").select(F.col("p_partkey").alias("k"), "p_brand"), "k").groupBy("p_brand").agg(F.count("*").alias("n"))
)


def _stored(s, d):
    """Held-out edges inserted and some deleted through versioned state, then compacted."""
    g = build_graph(reader(s, d), (1, 3, 6))
    store = StateStore(s, state_folder(s))
    store.commit("triples", base=updates.held_out(g, True))
    store.commit("triples", inserts=updates.held_out(g, False))
    store.commit("triples", tombstones=updates.deletes(g, {"followed", "locatedIn", "inSegment"}))
    store.compact("triples")
    return store.read("triples").select("edge_id", "s", "p", "o")


register("state_compact", f"WITH {graph_cte((1, 3, 6), f'NOT ({GONE})')} SELECT edge_id, s, p, o FROM g")(_stored)


def _csv(s, d):
    at = state_folder(s)
    build_graph(reader(s, d), (1, 3)).select("edge_id", "s", "p", "o").write.csv(at, sep="\t")
    return readers.triples_csv(s, at).select("edge_id", "s", "p", "o")


register("src_csv", f"WITH {graph_cte((1, 3))} SELECT edge_id, s, p, o FROM g")(_csv)


def _lines(s, d):
    at = state_folder(s)
    build_graph(reader(s, d), (3, 6)).select(F.concat(F.lit("<"), "s", F.lit("> <"), "p", F.lit("> "), F.when(F.col("o").startswith("lit:"), F.concat(F.lit('"'), F.substring("o", 5, 1000), F.lit('"'))).otherwise(F.concat(F.lit("<"), "o", F.lit(">"))), F.lit(" ."))).write.text(at)
    return readers.triples_lines(s, at).select("s", "p", "o")


register("src_lines", f"WITH {graph_cte((3, 6))} SELECT s, p, o FROM g")(_lines)
register("udf_probability")(lambda s, d: udfs.answer_probabilities(_deriv(s, d, get("W-S1")), lambda e: 0.5 + (e % 5) / 10))
register("udf_minimal", SQL["why_minimal"])(
    lambda s, d: _show(udfs.minimal_witnesses(_deriv(s, d, get("W-S2"), by_answer=True)).groupBy("qid", "ans").agg(F.collect_list("witness").alias("witnesses")))
)
register("udtf_terms", f"{_cte(_q)} SELECT {_ans(_q)} AS ans, array_to_string({_mono(_q)}, '.') AS mono, count(*) AS coef FROM ({to_sql(_q)}) GROUP BY 1, 2")(
    lambda s, d: (udfs.register_sql(s), poly.how(_deriv(s, d, get("W-S2"))).createOrReplaceTempView("how_s2"), s.sql("SELECT array_join(h.ans, '|') AS ans, array_join(transform(t.mono, e -> cast(e AS string)), '.') AS mono, t.coef FROM how_s2 h, LATERAL poly_terms(h.poly) t"))[-1]
)


def entry(spark: SparkSession, sf_dir: str = "/root/testdata/sf0.001") -> DataFrame:
    """How-provenance of the folding query after a hold-out replay."""
    return _replay(spark, sf_dir, "W-S2")


def queries() -> dict:
    return dict(Q)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)


__all__ = ["LABELS", "Var", "entry", "oracle_sql", "queries"]
