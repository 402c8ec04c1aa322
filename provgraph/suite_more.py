"""More entries of queries() and oracle_sql(): variants of the methods one by one, and the operators around them."""

from __future__ import annotations

from functools import partial
from multiprocessing.pool import ThreadPool

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .kg.build import FAMILIES, build_graph, families_of, graph_for, reader
from .kg.sql import graph_cte
from .maintain import delete as gone
from .maintain import maintainer
from .maintain.insert import routed
from .maintain.maintainer import Maintainer
from .maintain.potential import AT_ONCE, Catalog, aggregated, annotations, potential_matches
from .match.evaluate import evaluate, match_counts
from .match.sql import to_sql
from .plan.frames import Frames
from .prov import poly
from .query.bgp import GraphQuery, parse_select
from .query.folding import Constraints, foldable_pairs
from .query.subquery import generate
from .stats import cardinality, labels
from .streaming import standing
from .suite import GONE, HELD, _ann, _ans, _catalog, _cte, _edges_sql, _graph, _half_sql, _mono, _stream, _values, _with_edges, sql_how
from .workload import updates
from .workload.queries import get, labels_of, large_set, small_set

Q: dict = {}
SQL: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def _text(mono) -> F.Column:
    return F.array_join(F.transform(mono, lambda e: e.cast("string")), ".")


# subqueries and folding, case by case: values derived by hand

_CASES = {
    "subq_type1": ("SELECT ?a { ?a p ?b . ?b q c:1 }", ["I", "I"]),
    "subq_type2": ("SELECT ?a { ?a p ?b . ?b q ?c . ?c p ?d . ?d r ?e }", ["I", "II", "II", "I"]),
    "subq_type2_both": ("SELECT ?a { ?a p ?b . ?b q ?c . ?c r ?d }", ["I", "II", "I"]),
    "subq_type3": ("SELECT ?a { ?a p ?b . ?b q ?c . ?c r ?d . ?d p ?e . ?e q ?f }", ["I", "II", "III", "II", "I"]),
    "subq_type4": ("SELECT ?a { ?a p ?b . ?b q ?c . ?c r ?a }", ["IV", "IV", "IV"]),
}
for _k, (_t, _kinds) in _CASES.items():
    register(_k, _values([(i, x) for i, x in enumerate(_kinds)], "missing, kind"))(lambda s, d, t=_t: s.createDataFrame([(x.missing, x.kind) for x in generate(parse_select(t))], "missing bigint, kind string"))

_TINY = parse_select("SELECT ?a { ?a placedBy ?b }", "tiny")
register("subq_tiny", _edges_sql([(0, "empty", "placedBy")], "missing, kind"))(lambda s, d: _with_edges(s, d, [(x.missing, x.kind, x.exp_rel) for x in generate(_TINY)], "missing bigint, kind string"))


def _ruled(s, d, q, use, labels_used):
    """Foldable pairs without and with one kind of constraint, which is read off the given tables' edges of some labels."""
    g = graph_for(s, d, labels_used)
    c = labels.constraints(g)
    pairs = foldable_pairs(q, Constraints(**{k: getattr(c, k) for k in use}))
    return g.agg(F.count("*").alias("edges")).select(F.lit(len(foldable_pairs(q))).cast("long").alias("pairs_without"), F.lit(",".join(f"{i}-{j}" for i, j in pairs)).alias("pairs_with"), "edges")


def _rule(name: str, text: str, use: tuple, labels_used: set, holds: str, then: str, without: int) -> None:
    """holds: SQL that is true where the edges g keep the rule; then: the pairs left by it."""
    q = parse_select(text, name)
    free = ",".join(f"{i}-{j}" for i, j in foldable_pairs(q))
    names = ", ".join(map(repr, sorted(labels_used)))
    sql = f"WITH {graph_cte(families_of(labels_used), f'p IN ({names})')} SELECT CAST({without} AS BIGINT) AS pairs_without, CASE WHEN (SELECT count(DISTINCT p) FROM g) = {len(labels_used)} AND {holds} THEN '{then}' ELSE '{free}' END AS pairs_with, (SELECT count(*) FROM g) AS edges"
    register(name, sql)(partial(_ruled, q=q, use=use, labels_used=labels_used))


_rule("fold_rule1", "SELECT ?a { ?a followed ?b . ?b hasStatus lit:O . ?x followed ?y . ?y hasStatus lit:F . ?a coActive ?x }", ("functional",), {"hasStatus"}, "(SELECT max(k) = 1 FROM (SELECT count(DISTINCT o) AS k FROM g GROUP BY s))", "", 1)
_rule("fold_rule2", "SELECT ?a { ?a placedBy ?b . ?b placedBy ?c . ?c placedBy ?d . ?d placedBy ?e }", ("acyclic",), {"placedBy"}, "NOT EXISTS (SELECT split_part(s, ':', 1) FROM g INTERSECT SELECT split_part(o, ':', 1) FROM g)", "", 6)
_rule("fold_domain", "SELECT ?a { ?a placedBy ?b . ?c placedBy ?d . ?c inSegment ?e . ?a followed ?c }", ("domains",), {"placedBy", "inSegment"}, "NOT EXISTS (SELECT split_part(s, ':', 1) FROM g WHERE p = 'placedBy' INTERSECT SELECT split_part(s, ':', 1) FROM g WHERE p = 'inSegment')", "", 1)
# symmetric: both ways of the one edge, a loop apart; if the label is irreflexive only, no pair is left
_rule("fold_symmetric", "SELECT ?a { ?a coActive ?b . ?b coActive ?a }", ("symmetric", "irreflexive"), {"coActive"}, "NOT EXISTS (SELECT 1 FROM g WHERE s = o) AND EXISTS (SELECT s, o FROM g EXCEPT SELECT o, s FROM g)", "", 1)

# potential matches and annotations

_S3 = get("W-S3")


def _parts_sql(q: GraphQuery) -> str:
    """Annotations of a query by evaluating each half apart: with the head's values that the half holds."""
    parts = []
    for sub in generate(q):
        for h in sub.annotated if sub.kind in ("I", "II", "III", "IV") else ():
            hq = GraphQuery("h", (), tuple(sub.patterns(h)))
            held = " || ';' || ".join(f"'{k}=' || v_{v}" for k, v in enumerate(q.head) if v in hq.variables) or "''"
            for direction, var in (("out", h.out_var), ("in", h.in_var)):
                if var:
                    parts.append(f"SELECT '{sub.sqid}' AS sqid, CAST({h.number} AS BIGINT) AS half, '{direction}' AS dir, v_{var} AS vertex, {held} AS result, array_to_string(list_sort([{', '.join(f'e_{i}' for i in range(len(hq.body)))}]), '.') AS mono FROM ({to_sql(hq)})")
    return f"{_cte(q)}, a AS ({' UNION ALL '.join(parts)})"


def _results(ann: DataFrame) -> DataFrame:
    result = F.array_join(F.transform("result", lambda r: F.concat(r["pos"].cast("string"), F.lit("="), r["val"])), ";")
    return ann.select("sqid", F.col("half").cast("long").alias("half"), "dir", "vertex", result.alias("result"), "mono")


register("ann_dirs", f"{_parts_sql(_S3)} SELECT dir, count(*) AS n, count(DISTINCT vertex) AS vertices FROM a GROUP BY dir")(lambda s, d: _ann(s, d, "W-S3").groupBy("dir").agg(F.count("*").alias("n"), F.count_distinct("vertex").alias("vertices")))
register("ann_result", f"{_parts_sql(_S3)} SELECT sqid, half, dir, result, count(*) AS n FROM a GROUP BY ALL")(lambda s, d: _results(_ann(s, d, "W-S3")).groupBy("sqid", "half", "dir", "result").agg(F.count("*").alias("n")))
register("ann_poly", f"{_parts_sql(get('W-S2'))} SELECT sqid, half, dir, vertex, result, count(DISTINCT mono) AS monomials FROM a GROUP BY ALL")(
    lambda s, d: aggregated(_ann(s, d, "W-S2")).select("sqid", F.col("half").cast("long").alias("half"), "dir", "vertex", F.array_join(F.transform("result", lambda r: F.concat(r["pos"].cast("string"), F.lit("="), r["val"])), ";").alias("result"), F.size("poly").cast("long").alias("monomials"))
)
_VAR = parse_select("SELECT ?u ?t { ?u ?act ?t . ?u followed ?v . ?v inSegment ?g }", "varpred")


def _varpred(s: SparkSession, d: str) -> DataFrame:
    """Annotations for a missing edge of any label, over two families."""
    c = Catalog()
    c.add(_VAR)
    ann = annotations(potential_matches(build_graph(reader(s, d), (1, 6)), c), c)
    return ann.where("exp_rel = '*'").groupBy("exp_rel", "dir", "vertex").agg(F.count("*").alias("n"))


_HALF = GraphQuery("h", (), _VAR.body[1:])
register("ann_varpred", f"WITH {graph_cte((1, 6))} SELECT '*' AS exp_rel, 'out' AS dir, v_u AS vertex, count(*) AS n FROM ({to_sql(_HALF)}) GROUP BY v_u")(_varpred)


def _matches(s, d, name):
    c = _catalog([name])
    rows = potential_matches(_graph(s, d, get(name)), c)
    keys = s.createDataFrame([(c.number[k], sqid, half) for (sqid, half), k in c.root.items()], "node int, sqid string, half bigint")
    return rows.join(F.broadcast(keys), "node").select("sqid", "half", _text(F.array_sort("edges")).alias("mono"))  # a row for each half


def _halves_sql(q: GraphQuery) -> str:
    parts = []
    for sub in generate(q):
        for h in sub.annotated if sub.kind in ("I", "II", "III", "IV") else ():
            hq = GraphQuery("h", (), tuple(sub.patterns(h)))
            parts.append(f"SELECT '{sub.sqid}' AS sqid, CAST({h.number} AS BIGINT) AS half, array_to_string({_mono(hq)}, '.') AS mono FROM ({to_sql(hq)})")
    return f"{_cte(q)}, a AS ({' UNION ALL '.join(parts)})"


register("pm_count", f"{_halves_sql(_S3)} SELECT sqid, half, count(*) AS n FROM a GROUP BY ALL")(lambda s, d: _matches(s, d, "W-S3").groupBy("sqid", "half").agg(F.count("*").alias("n")))
register("pm_rows", f"{_halves_sql(get('W-S2'))} SELECT sqid, half, mono, count(*) AS n FROM a GROUP BY ALL")(lambda s, d: _matches(s, d, "W-S2").groupBy("sqid", "half", "mono").agg(F.count("*").alias("n")))

# cardinality estimates: the same sums in SQL

_SETS = "cs AS (SELECT s AS v, list_sort(list(DISTINCT p)) AS preds FROM g GROUP BY s)"
_PAIRS = f"{_SETS}, cp AS (SELECT a.preds AS s_preds, b.preds AS o_preds, p, count(*) AS cnt FROM g JOIN cs a ON g.s = a.v JOIN cs b ON g.o = b.v GROUP BY 1, 2, 3)"
_CHAIN = parse_select("SELECT ?or { ?or placedBy ?c . ?or hasPriority ?x . ?c inSegment ?g . ?c locatedIn ?n }", "chain")
_STAR = parse_select("SELECT ?or { ?or placedBy ?c . ?or hasPart ?p . ?or hasStatus ?x }", "star")


def _estimate(s, d, q, formula):
    est = cardinality.Estimator.build(graph_for(s, d, labels_of(q)), formula)
    return s.createDataFrame([(q.name, float(round(est.estimate(q.body))))], "qid string, estimate double")


register("card_chain", f"{_cte(_CHAIN)}, {_PAIRS} SELECT 'chain' AS qid, CAST(sum(cnt) AS DOUBLE) AS estimate FROM cp WHERE p = 'placedBy' AND list_has_all(s_preds, ['placedBy', 'hasPriority']) AND list_has_all(o_preds, ['inSegment', 'locatedIn'])")(
    partial(_estimate, q=_CHAIN, formula="pair_sum")
)
register(
    "card_star",
    f"""{_cte(_STAR)}, {_SETS}, k AS (SELECT preds, count(*) AS v FROM cs GROUP BY preds), n AS (SELECT preds, p, count(*) AS e FROM cs JOIN g ON v = s GROUP BY 1, 2),
    one AS (SELECT k.preds, k.v, product(n.e / k.v) AS m FROM k JOIN n ON k.preds = n.preds AND n.p IN ('placedBy', 'hasPart', 'hasStatus') WHERE list_has_all(k.preds, ['placedBy', 'hasPart', 'hasStatus']) GROUP BY 1, 2)
    SELECT 'star' AS qid, round(sum(v * m)) AS estimate FROM one""",
)(partial(_estimate, q=_STAR, formula="star"))

# the shared plan


_PLANNED = ("W-S1", "W-Y4", "W-C4")
_PLAN = _catalog(_PLANNED)


def _global_counts(s, d):
    """Rows of every node, each evaluated from its children; a node that stands on one too wide to be kept is counted without any of its rows.

    Nodes go level by level, so that one which turns out wide is not made for those above it.
    """
    at = maintainer.state_folder(s)
    graph_for(s, d, {x for n in _PLANNED for x in labels_of(get(n))}).write.partitionBy("p").parquet(at)  # all nodes read it
    g = s.read.parquet(at).select(*maintainer.COLUMNS)
    est, frames = cardinality.Estimator.of_labels(g), Frames(_PLAN.plan, g)
    most = max(maintainer.LEAST_WIDE, maintainer.WIDE * est.edges)
    levels: dict[int, list[str]] = {}
    for k, node in _PLAN.plan.nodes.items():
        levels.setdefault(len(node.patterns), []).append(k)
    wide = {k for k, node in _PLAN.plan.nodes.items() if est.estimate(node.patterns) > most}
    sizes: dict[str, int] = {}

    def size(k: str) -> int:
        return (match_counts(g, _PLAN.plan.nodes[k].patterns) if _PLAN._below({k}) & wide else frames.size(k)).first()["n"]

    # a job each, as one plan of all of them takes longer to plan than to run
    with ThreadPool(AT_ONCE) as pool:
        for _, level in sorted(levels.items()):
            sizes.update(zip(level, pool.map(size, level, 1)))
            wide |= {k for k in level if sizes[k] > most}
    return s.createDataFrame([(_PLAN.number[k], n) for k, n in sizes.items()], "node bigint, n bigint")


_LABELS = {x for n in _PLANNED for x in labels_of(get(n))}
_PLAN_CTE = "WITH " + graph_cte(families_of(_LABELS), f"p IN ({', '.join(repr(x) for x in sorted(_LABELS))})")
register("global_eval", f"{_PLAN_CTE} " + " UNION ALL ".join(f"SELECT CAST({_PLAN.number[k]} AS BIGINT) AS node, count(*) AS n FROM ({to_sql(GraphQuery('node', (), node.patterns))})" for k, node in _PLAN.plan.nodes.items()))(_global_counts)


def _affected_sql() -> str:
    rows = [(x, sum(any(p.label in (None, x) for p in n.patterns) for n in _PLAN.plan.nodes.values())) for x in sorted(_LABELS)]
    return f"{_PLAN_CTE}, a AS ({_values(rows, 'label, nodes')}) SELECT label, nodes, count(*) AS edges, count(DISTINCT s) AS subjects FROM g JOIN a ON p = label GROUP BY label, nodes"


def _affected(s, d):
    """Nodes that the labels of the graph's edges affect, with how many edges and subjects each label has."""
    rows = graph_for(s, d, _LABELS).groupBy("p").agg(F.count("*").alias("edges"), F.count_distinct("s").alias("subjects")).collect()  # a row for each label
    return s.createDataFrame([(r["p"], len(_PLAN.plan.affected([r["p"]])), r["edges"], r["subjects"]) for r in rows], "label string, nodes bigint, edges bigint, subjects bigint")


register("global_affected", _affected_sql())(_affected)


def _separate(s, d):
    """Halves evaluated by plans of their own: the same annotations, without sharing (ablation)."""
    m = Maintainer(_graph(s, d, get("W-S4")), share=False).register(get("W-S4"))
    return m.annotation_sizes()


register("plan_noglobal", f"{_half_sql(get('W-S4'))} SELECT sqid, half, dir, count(*) AS n, count(DISTINCT vertex) AS vertices FROM a GROUP BY 1, 2, 3")(_separate)

# registration, insertion and deletion, case by case


def _registered(s, d):
    """All four large queries registered together: derivations and answers of each."""
    qs = small_set()
    m = Maintainer(graph_for(s, d, {x for q in qs for x in labels_of(q)})).register_all(qs)
    return m.deriv.groupBy("qid").agg(F.sum("n").alias("derivations"), F.count_distinct("ans").alias("answers"))


_ALL = "WITH " + graph_cte((1, 2, 3, 4, 5, 6, 7, 8, 9, 10, 13))
register("reg_all", f"{_ALL} " + " UNION ALL ".join(f"SELECT '{q.name}' AS qid, count(*) AS derivations, count(DISTINCT {_ans(q)}) AS answers FROM ({to_sql(q)})" for q in small_set()))(_registered)


_ROUTED = {"followed", "inSegment", "hasBrand", "linksTo"}


def _routes(s, d):
    """Where the edges of some labels go: queries and subqueries of the large set, for each label that the given tables have."""
    c = Catalog()
    for q in large_set():
        c.add(q)
    batch = graph_for(s, d, _ROUTED).groupBy("p").agg(F.count_distinct("edge_id").alias("edges")).collect()  # a row for each label
    rows = [(r["p"], len({sub.query.name for sub in routed(c, {r["p"]})}), len(routed(c, {r["p"]})), r["edges"]) for r in batch]
    return s.createDataFrame(rows, "label string, queries bigint, subqueries bigint, edges bigint")


def _routes_sql() -> str:
    rows = [(x, sum(x in q.labels for q in large_set()), sum(p.label == x for q in large_set() for p in q.body)) for x in sorted(_ROUTED)]
    names = ", ".join(f"'{x}'" for x in sorted(_ROUTED))
    return f"WITH {graph_cte(families_of(_ROUTED), f'p IN ({names})')}, a AS ({_values(rows, 'label, queries, subqueries')}) SELECT label, queries, subqueries, count(DISTINCT edge_id) AS edges FROM g JOIN a ON p = label GROUP BY label, queries, subqueries"


register("ins_route", _routes_sql())(_routes)


def _inserted(s, d, q, new: str, **kw):
    """Register without the edges that `new` names, insert them, give the polynomials."""
    g = _graph(s, d, q)
    m = Maintainer(g.where(f"NOT ({new})"), **kw).register(q)
    m.insert(g.where(new))
    return poly.how_text(m.deriv)


_CONST = parse_select('SELECT ?a ?b { ?a followed ?b . ?b inSegment "BUILDING" }', "const")
_FOLDS = parse_select("SELECT ?a ?c { ?a followed ?b . ?c followed ?b . ?b locatedIn ?n }", "folds")
_CHAIN3 = parse_select("SELECT ?a ?g { ?a followed ?b . ?b coActive ?c . ?c inSegment ?g }", "chain3")
register("ins_type1_const", sql_how(_CONST))(partial(_inserted, q=_CONST, new="p = 'inSegment' AND edge_id % 3 = 0"))
register("ins_type2", sql_how(_CHAIN3))(partial(_inserted, q=_CHAIN3, new="p = 'coActive' AND edge_id % 5 = 0"))
register("ins_fold", sql_how(_FOLDS))(partial(_inserted, q=_FOLDS, new="p = 'followed' AND edge_id % 7 = 0"))
register("ins_batch", sql_how(get("W-C4")))(partial(_inserted, q=get("W-C4"), new="edge_id % 4 = 1"))
for _policy in ("roots", "shared", "none"):
    register(f"ins_policy_{_policy}", sql_how(get("W-C4")))(partial(_inserted, q=get("W-C4"), new=HELD, policy=_policy))


def _supported(s, d):
    q = get("W-C4")
    g = _graph(s, d, q)
    m = Maintainer(updates.held_out(g, True)).register(q)
    return m.insert(updates.held_out(g, False)).where("change = 'support_added'").select(F.array_join("ans", "|").alias("ans"), "n")


def _two_states(q: GraphQuery, old: str, new: str) -> str:
    one = lambda where: to_sql(q, sources=[f"(SELECT * FROM g WHERE {where})"] * len(q.body))
    return f"{_cte(q)}, n AS (SELECT {_ans(q)} AS ans, count(*) AS k FROM ({one(new)}) GROUP BY 1), o AS (SELECT {_ans(q)} AS ans, count(*) AS k FROM ({one(old)}) GROUP BY 1)"


register("ins_support", f"{_two_states(get('W-C4'), f'NOT ({HELD})', 'true')} SELECT ans, n.k - o.k AS n FROM n JOIN o USING (ans) WHERE n.k > o.k")(_supported)


def _nothing(s, d):
    """Updates of a label that no query has, and deletes of ids that are not there, change nothing."""
    q = get("W-K3")
    m = Maintainer(_graph(s, d, q)).register(q)
    other = build_graph(reader(s, d), (5,))
    a, b = m.insert(other).count(), m.delete(s.createDataFrame([(-1,)], "edge_id long")).count()
    return s.createDataFrame([(a, b, gone.touches(s.createDataFrame([(-1,)], "edge_id long"), m.edge_to_answer))], "inserted bigint, deleted bigint, touched boolean")


register("del_noop", "SELECT CAST(0 AS BIGINT) AS inserted, CAST(0 AS BIGINT) AS deleted, false AS touched")(_nothing)


def _candidates(s, d):
    q = get("W-S4")
    m = Maintainer(_graph(s, d, q)).register(q)
    ids = updates.deletes(m.triples, labels_of(q))
    return gone.candidates(ids, m.tables["index"].read()).select(F.array_join("ans", "|").alias("ans"))


_S4 = get("W-S4")
register("del_candidates", f"{_cte(_S4)}, d AS (SELECT {_ans(_S4)} AS ans, unnest({_mono(_S4)}) AS edge_id FROM ({to_sql(_S4)})) SELECT DISTINCT ans FROM d WHERE {GONE}")(_candidates)


def _points_left(s, d):
    """Connection points after deletes: those of the graph without the edges."""
    q = get("W-S4")
    g = _graph(s, d, q)
    m = Maintainer(g).register(q)
    m.delete(updates.deletes(g, labels_of(q)))
    return m.annotation_sizes()


def _kept_sql(q: GraphQuery) -> str:
    return _half_sql(q).replace(f"p IN ({', '.join(repr(x) for x in sorted(labels_of(q)))}) AND (true)", f"p IN ({', '.join(repr(x) for x in sorted(labels_of(q)))}) AND NOT ({GONE})")


register("del_cp", f"{_kept_sql(_S4)} SELECT sqid, half, dir, count(*) AS n, count(DISTINCT vertex) AS vertices FROM a GROUP BY 1, 2, 3")(_points_left)


def _index_left(s, d):
    q = get("W-S4")
    g = _graph(s, d, q)
    m = Maintainer(g).register(q)
    m.delete(updates.deletes(g, labels_of(q)))
    return m.edge_to_answer.groupBy("edge_id").agg(F.count("*").alias("n"))


_WITHOUT = f"NOT ({GONE})"
register("del_index", f"{_cte(_S4, _WITHOUT)}, d AS (SELECT DISTINCT {_ans(_S4)} AS ans, unnest({_mono(_S4)}) AS edge_id FROM ({to_sql(_S4)})) SELECT edge_id, count(*) AS n FROM d GROUP BY edge_id")(_index_left)


def _index_sizes(s, d):
    """Entries of the two inverted indexes (their bytes are in the experiments)."""
    q = get("W-S2")
    m = Maintainer(_graph(s, d, q)).register(q)
    return s.createDataFrame([(m.edge_to_answer.count(), m.edge_to_cp.count())], "to_answers bigint, to_points bigint")


_S2 = get("W-S2")
register("m_index", f"{_half_sql(_S2)}, x AS (SELECT DISTINCT {_ans(_S2)} AS ans, unnest({_mono(_S2)}) AS e FROM ({to_sql(_S2)})), y AS (SELECT DISTINCT unnest(string_split(mono, '.')) AS e, sqid, half, dir, vertex FROM a) SELECT (SELECT count(*) FROM x) AS to_answers, (SELECT count(*) FROM y) AS to_points")(_index_sizes)
register("m_dataset", f"WITH {graph_cte(FAMILIES)} SELECT count(DISTINCT edge_id) AS edges, count(DISTINCT p) AS labels, (SELECT count(DISTINCT v) FROM (SELECT s AS v FROM g UNION ALL SELECT o FROM g)) AS vertices FROM g")(
    lambda s, d: (lambda g: g.agg(F.count_distinct("edge_id").alias("edges"), F.count_distinct("p").alias("labels")).join(g.select(F.col("s").alias("v")).union(g.select("o")).agg(F.count_distinct("v").alias("vertices"))))(build_graph(reader(s, d)))
)


def _parity(s, d, what):
    """Rows that differ between maintained and fresh state after inserts and deletes, both ways."""
    q = get("W-S4")
    g = _graph(s, d, q)
    m = Maintainer(updates.held_out(g, True)).register(q)
    m.insert(updates.held_out(g, False))
    m.delete(updates.deletes(g, labels_of(q)))
    fresh = Maintainer(m.triples).register(q)
    a, b = getattr(m, what), getattr(fresh, what)
    return a.exceptAll(b).unionByName(b.exceptAll(a)).agg(F.count("*").alias("differing"))


for _what in ("deriv", "potential", "edge_to_answer", "edge_to_cp"):
    register(f"parity_{_what}", "SELECT CAST(0 AS BIGINT) AS differing")(partial(_parity, what=_what))

# streams


def _events(s, d):
    return updates.from_events(reader(s, d)("events"))


_U = "u AS (SELECT event_id AS seq, ts, CASE WHEN event_type = 'error' THEN 'del' ELSE 'ins' END AS op, 'cust:' || user_id AS s, event_type FROM (SELECT *, last_value(CASE WHEN event_type <> 'error' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_id FROM events) WHERE event_type <> 'error' OR last_id IS NOT NULL)"
register("stream_dedup", f"WITH {_U} SELECT seq, op FROM u")(lambda s, d: _stream(s, d, lambda x: standing.deduplicated(x.unionByName(x.where("seq % 3 = 0")), "3650 days"), "stream_dedup").select("seq", "op"))
register("stream_session", f"WITH {_U}, x AS (SELECT s, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY s ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM u WHERE op = 'ins'), y AS (SELECT s, ts, sum(new) OVER (PARTITION BY s ORDER BY ts) AS k FROM x) SELECT s, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, count(*) AS n FROM y GROUP BY s, k")(
    lambda s, d: _stream(s, d, lambda x: standing.sessions(x.where("op = 'ins'")), "stream_session").select("s", F.col("w.start").cast("long").alias("start"), "n")
)

# joins, aggregates, windows, filters, SQL views


def _located(s, d):
    return build_graph(reader(s, d), (3, 6))


def _strategies(s, d):
    """The same equi-join by each strategy."""
    g = _located(s, d)
    a, b = g.where("p = 'locatedIn'").select("s", F.col("o").alias("nation")), g.where("p = 'inSegment'").select("s", F.col("o").alias("segment"))
    rows = [a.join(b.hint(h), "s").groupBy("nation", "segment").agg(F.count("*").alias("n")).withColumn("strategy", F.lit(h)) for h in ("merge", "shuffle_hash")]
    return rows[0].unionByName(rows[1])


register("join_strategies", f"WITH {graph_cte((3, 6))} SELECT a.o AS nation, b.o AS segment, count(*) AS n, h AS strategy FROM g a JOIN g b ON a.s = b.s AND a.p = 'locatedIn' AND b.p = 'inSegment', (VALUES ('merge'), ('shuffle_hash')) t(h) GROUP BY ALL")(_strategies)
register("op_litfilter", "SELECT o_orderkey AS k FROM orders WHERE o_totalprice > 1000 AND o_orderpriority IN ('1-URGENT', '2-HIGH')")(
    lambda s, d: evaluate(build_graph(reader(s, d), (13,)), parse_select("SELECT ?or ?x { ?or hasPriority ?x }", "f")).where(F.substring("v_x", 5, 100).isin("1-URGENT", "2-HIGH")).select(F.split("v_or", ":")[1].cast("long").alias("k"))
    .join(reader(s, d)("orders").where("o_totalprice > 1000").select(F.col("o_orderkey").alias("k")), "k")
)
register("agg_gsets", f"WITH {graph_cte((3, 6))} SELECT p, o, count(*) AS n FROM g GROUP BY GROUPING SETS ((p), (p, o), ())")(
    lambda s, d: (_located(s, d).createOrReplaceTempView("located"), s.sql("SELECT p, o, count(*) AS n FROM located GROUP BY GROUPING SETS ((p), (p, o), ())"))[-1]
)
register("agg_pct", f"WITH {graph_cte((1,))}, k AS (SELECT s, count(*) AS n FROM g GROUP BY s) SELECT quantile_cont(n, 0.5) AS p50, quantile_cont(n, 0.9) AS p90, max(n) AS most FROM k")(
    lambda s, d: build_graph(reader(s, d), (1,)).groupBy("s").agg(F.count("*").alias("n")).agg(F.percentile("n", 0.5).alias("p50"), F.percentile("n", 0.9).alias("p90"), F.max("n").alias("most"))
)
register("agg_approx", f"WITH {graph_cte((3, 7))} SELECT p, true AS close FROM g GROUP BY p")(
    lambda s, d: build_graph(reader(s, d), (3, 7)).groupBy("p").agg((F.abs(F.approx_count_distinct("s", 0.02) / F.count_distinct("s") - 1) < 0.1).alias("close"))
)
register("win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")(
    lambda s, d: reader(s, d)("events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-3600, 0)).alias("n"))
)
register("win_lag", "SELECT event_id, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, ntile(4) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS quarter FROM events")(
    lambda s, d: (lambda w: reader(s, d)("events").select("event_id", F.lag("event_type").over(w).alias("before"), F.ntile(4).over(w).cast("long").alias("quarter")))(Window.partitionBy("user_id").orderBy("ts", "event_id"))
)


def _views(s, d):
    """The state as SQL views: answers that rest on one derivation only."""
    q = get("W-S4")
    m = Maintainer(_graph(s, d, q)).register(q)
    for name, df in (("triples", m.triples), ("derivation", m.deriv), ("annotation", m.annotation)):
        df.createOrReplaceTempView(f"provgraph_{name}")
    return s.sql("SELECT array_join(ans, '|') AS ans, sum(n) AS n FROM provgraph_derivation GROUP BY ans HAVING sum(n) = 1")


register("sql_views", f"{_cte(_S4)} SELECT {_ans(_S4)} AS ans, count(*) AS n FROM ({to_sql(_S4)}) GROUP BY 1 HAVING count(*) = 1")(_views)


def queries() -> dict:
    return dict(Q)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)

