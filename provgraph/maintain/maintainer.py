"""Standing queries kept up to date: registration, insertion, deletion, mixed updates, explanation."""

from __future__ import annotations

import atexit
import tempfile
import time
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..match.evaluate import derivations, evaluate
from ..plan.frames import Frames, Refresh
from ..query.bgp import GraphQuery
from ..query.folding import NONE, Constraints, klass
from ..stats.cardinality import Estimator
from ..stats.labels import broken_by
from ..workload.updates import net
from . import delete as gone
from . import insert as added
from .parts import MOST_PARTS, SMALL, Deleted, Parts
from .potential import NODE_SCHEMA, Catalog, annotation_sizes, annotations, as_expressions, by_shape, edge_to_answer, edge_to_cp, node_rows, union_all

COLUMNS = ["edge_id", "s", "p", "o", "inverse"]
TRIPLES = "edge_id bigint, s string, p string, o string, inverse boolean"
#: A half is kept if none of its nodes is estimated, or counted when it is first needed, above so many rows for each edge of the graph, or above the least number.
WIDE, LEAST_WIDE = 4, 1_000_000
CHANGES = "qid string, ans array<string>, change string, n bigint"


def state_folder(spark: SparkSession) -> str:
    """A new folder in the shared folder of the session (spark.checkpoint.dir), or a local one where none is set."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir() or tempfile.mkdtemp(prefix="provgraph_state_")
    return f"{root.rstrip('/')}/state-{uuid.uuid4().hex}"


class Maintainer:
    """Answers and their derivations over a changing graph.

    State is tables of parts: triples, nodes of the shared plan, derivations, the index from edges to answers, and the log of changes.  A
    batch appends what is new, a delete notes the ids, so neither rewrites what is there; lineage is cut at each part.
    potential='kept' stores matches of half queries, 'none' finds new matches by joins of the graph.  `policy` and `share` are the
    catalog's.  `estimate` (of a list of patterns) decides the plans; by default it rests on the sizes of the graph's labels, as does which halves are
    too wide to be kept.  Views have the matches of these too, evaluated when asked for.
    """

    def __init__(self, triples: DataFrame, path: str | None = None, constraints: Constraints = NONE, potential: str = "kept", track: bool = True, policy: str = "all", share: bool = True, estimate=None):
        self.spark = triples.sparkSession
        self.path, self.version = path or state_folder(self.spark), 0
        self.constraints, self.keeps, self.track = constraints, potential != "none", track
        self.catalog = Catalog(policy=policy, estimate=estimate or by_shape)
        self.measures, self.known, self.more = estimate is None and self.keeps, 0, 0  # edges when the labels were last counted, edges since
        self.catalog.plan.shared = share
        self.spans: list[tuple[str, str, float]] = []
        self.waiting: list[str] = []
        self.deleted = Deleted()
        parts = lambda name, schema, edges, array, by=None: Parts(self.spark, self.path, name, schema, edges, self.deleted, array, by)
        self.tables = {
            "triples": parts("triples", TRIPLES, "edge_id", False), "nodes": parts("nodes", NODE_SCHEMA, "edges", True), "deriv": parts("deriv", added.DERIV, "mono", True),
            "index": parts("index", "edge_id bigint, qid string, ans array<string>", "edge_id", False, ["edge_id"]),
        }
        self.log = Parts(self.spark, self.path, "log", f"{CHANGES}, version int", "version", Deleted(), False)
        self.tables["triples"].append(triples.select(*COLUMNS), 0)
        atexit.register(self._close)

    def _close(self) -> None:
        jsc = self.spark.sparkContext._jsc
        if jsc is not None:
            try:
                p = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
                p.getFileSystem(jsc.hadoopConfiguration()).delete(p, True)
            except Exception:  # noqa: BLE001 - at exit the gateway may be gone
                pass

    def _store(self, df: DataFrame, name: str) -> DataFrame:
        at = f"{self.path}/t{self.version:06d}_{name}_{uuid.uuid4().hex[:6]}"
        df.write.parquet(at)
        return self.spark.read.schema(df.schema).parquet(at)

    @contextmanager
    def _span(self, phase: str, kind: str = ""):
        start = time.perf_counter()
        yield
        self.spans.append((kind, phase, time.perf_counter() - start))

    def _measure(self, triples: DataFrame, more: int = 0) -> None:
        """Count the labels: at first, and once the graph has doubled."""
        self.more += more
        if self.measures and self.more >= self.known:
            est = Estimator.of_labels(triples)
            self.known, self.more = est.edges, 0
            if est.edges:
                self.catalog.estimate = est.estimate
                self._narrow()

    def _narrow(self) -> None:
        """Nodes of halves that became wide leave the table."""
        if self.known:
            self._dropped(self.catalog.widen(self._most))

    @property
    def _most(self) -> int:
        return max(LEAST_WIDE, WIDE * self.known)

    def _dropped(self, dropped: set[str]) -> None:
        self.waiting = [k for k in self.waiting if k not in dropped]
        if dropped and self.tables["nodes"].parts:
            self.tables["nodes"].rewrite(self.tables["nodes"].read(~F.col("node").isin([self.catalog.number[k] for k in dropped])), self.version)

    # registration

    def register_all(self, queries: list[GraphQuery]) -> Maintainer:
        """Evaluate new queries and the nodes that no earlier query has; nothing that is there is evaluated again."""
        before = set(self.catalog.stored())
        triples = self.triples
        with self._span("plan"):
            self._measure(triples)
            for q in queries:
                self.catalog.add(q)
            self._narrow()
        with self._span("evaluate"):
            rows = self._tracked(union_all([derivations(evaluate(triples, q, allow_cross=True), q) for q in queries], self.spark, added.DERIV))
            rows = self.tables["deriv"].append(rows, self.version)
            self._indexed(rows)
        if self.keeps:
            self.waiting += [k for k in self.catalog.stored() if k not in before]
        return self

    def _ready(self) -> None:
        """Nodes are evaluated when an insert or a view first asks for them, on the graph as it is then; a delete needs none."""
        if self.waiting:
            stored, keys, self.waiting = set(self.catalog.stored()), self.waiting, []
            with self._span("potential"):
                self._evaluate([k for k in keys if k in stored])

    def _evaluate(self, keys: list[str]) -> None:
        """Nodes level by level, each from its stored children; where labels are counted, a node that is in fact too large to be kept is found out before it is made."""
        sizes: dict[int, list[str]] = {}
        for k in keys:
            sizes.setdefault(len(self.catalog.plan.nodes[k].patterns), []).append(k)
        made: set[str] = set()
        for _, level in sorted(sizes.items()):
            frames = Frames(self.catalog.plan, self.triples, self._stored(without=set(keys) - made))
            level = [k for k in level if k in set(self.catalog.stored())]
            if self.known and level:
                found = union_all([frames.size(k).select(F.lit(k).alias("key"), "n") for k in level], self.spark, "").where(F.col("n") > self._most).collect()  # a row for each node at most
                self._dropped(self.catalog.drop({r["key"] for r in found}))
                level = [k for k in level if k in set(self.catalog.stored())]
            if level:
                self.tables["nodes"].append(node_rows(self.catalog, frames, level), self.version)
                made |= set(level)

    def _stored(self, without: set[str] = frozenset()):
        have = set(self.catalog.stored()) - set(without) if self.keeps else set()
        return lambda key: self._node(key) if key in have else None

    def _node(self, key: str) -> DataFrame:
        return self.tables["nodes"].read(F.col("node") == self.catalog.number[key]).select("binding", "edges")

    def _indexed(self, deriv: DataFrame) -> None:
        if self.track:
            self.tables["index"].append(edge_to_answer(deriv), self.version)

    def register(self, query: GraphQuery) -> Maintainer:
        return self.register_all([query])

    def unregister(self, qid: str) -> None:
        self.catalog.remove(qid)
        self.tables["deriv"].rewrite(self.deriv.where(F.col("qid") != qid), self.version)
        self.tables["index"].rewrite(self.tables["index"].read(F.col("qid") != qid), self.version)

    def describe(self) -> list[dict]:
        return [{"qid": q.name, "size": len(q.body), "klass": klass(q, self.constraints), "types": [s.kind for s in self.catalog.subqueries if s.query.name == q.name]} for q in self.catalog.queries.values()]

    def _tracked(self, deriv: DataFrame) -> DataFrame:
        """Without provenance only counts are kept."""
        return deriv if self.track else deriv.groupBy("qid", "ans").agg(F.sum("n").alias("n")).select("qid", "ans", F.array().cast("array<bigint>").alias("mono"), "n")

    # views

    @property
    def triples(self) -> DataFrame:
        return self.tables["triples"].read()

    @property
    def deriv(self) -> DataFrame:
        """(qid, ans, mono, n); each derivation is one row, as a batch only adds monomials that were not there."""
        d = self.tables["deriv"].read()
        return d if self.track else self._tracked(d)

    def _halves(self) -> DataFrame:
        if not self.keeps:
            return self.spark.createDataFrame([], NODE_SCHEMA)
        self._ready()
        return self._rows_of(set(self.catalog.kept()))

    def _rows_of(self, kept: set[str]) -> DataFrame:
        stored = set(self.catalog.stored())
        numbers = [self.catalog.number[k] for k in kept & stored]
        rows = self.tables["nodes"].read(F.col("node").isin(numbers))
        if kept - stored:  # policy 'none': evaluated when asked for
            rows = rows.unionByName(node_rows(self.catalog, Frames(self.catalog.plan, self.triples), sorted(kept - stored)))
        return rows

    @property
    def potential(self) -> DataFrame:
        return as_expressions(self._halves(), self.catalog)

    @property
    def annotation(self) -> DataFrame:
        return annotations(self._halves(), self.catalog)

    def annotation_sizes(self) -> DataFrame:
        """(sqid, half, dir, n, vertices) of the annotations, counted on the graph as it is without making them."""
        if not self.keeps:
            return self.annotation.groupBy("sqid", F.col("half").cast("long").alias("half"), "dir").agg(F.sum("n").alias("n"), F.count_distinct("vertex").alias("vertices"))
        return annotation_sizes(self.triples, self.catalog)

    @property
    def edge_to_answer(self) -> DataFrame:
        return edge_to_answer(self.deriv)

    @property
    def edge_to_cp(self) -> DataFrame:
        return edge_to_cp(self.annotation)

    @property
    def answers(self) -> DataFrame:
        return self.deriv.groupBy("qid", "ans").agg(F.sum("n").alias("n"))

    def _is(self, qid: str, ans: list[str]):
        return (F.col("qid") == qid) & (F.col("ans") == F.array(*map(F.lit, ans)))

    def explain(self, qid: str, ans: list[str]) -> DataFrame:
        """(mono, n): derivations of one answer; empty if it no longer holds."""
        return self.deriv.where(self._is(qid, ans)).select("mono", "n")

    def history(self, qid: str, ans: list[str]) -> DataFrame:
        """(version, change, n, causes): when an answer was added, gained or lost support or was removed since registration, and by which edges."""
        causes = self.tables_of_causes()
        return self.log.read().where(self._is(qid, ans)).join(causes, "version", "left").select("version", "change", "n", "causes")

    def tables_of_causes(self) -> DataFrame:
        rows = [(v, sorted(ids)) for v, ids in self.deleted.ids]
        deleted = self.spark.createDataFrame(rows, "version int, causes array<bigint>")
        parts = [self.spark.read.parquet(at).select(F.lit(v).alias("version"), "edge_id") for v, at in self.tables["triples"].parts if v]
        inserted = union_all(parts, self.spark, "version int, edge_id bigint").distinct().groupBy("version").agg(F.array_sort(F.collect_list("edge_id")).alias("causes"))
        return deleted.unionByName(inserted)

    # updates

    def _logged(self, changes: DataFrame) -> DataFrame:
        changes = changes.withColumn("version", F.lit(self.version))
        return self.log.append(changes, self.version).select("qid", "ans", "change", "n")

    def _touched(self, labels: set[str]) -> list[GraphQuery]:
        return [q for q in self.catalog.queries.values() if any(q.mentions(x) for x in labels)]

    def insert(self, edges: DataFrame, one_edge: bool = False) -> DataFrame:
        """Insert edges; returns (qid, ans, change, n).  Rows with an id that is there, or that come twice, change nothing."""
        self.version += 1
        new_ids = edges.select(*COLUMNS).dropDuplicates(["edge_id", "inverse"])
        old = self.triples
        delta = self._store(new_ids.join(old.select("edge_id"), "edge_id", "left_anti").select(*COLUMNS), "delta")
        seen = delta.groupBy("p").count().collect()  # a row for each label of the batch
        labels = {r["p"] for r in seen}
        if not labels:
            return self.spark.createDataFrame([], CHANGES)
        if self.constraints is not NONE:
            self.constraints = self.constraints.without(broken_by(delta, old, self.constraints))
        touched = self._touched(labels)
        if not touched:
            self.tables["triples"].append(delta, self.version)
            return self.spark.createDataFrame([], CHANGES)
        new = old.unionByName(delta)
        self._measure(new, sum(r["count"] for r in seen))
        self._ready()
        plain = one_edge and sum(r["count"] for r in seen) == 1 and all(klass(q, self.constraints) == "plain" for q in touched)
        fresh_nodes = None
        if self.keeps and not plain:
            with self._span("subquery"):
                fresh_nodes = self._refreshed(delta, old, labels)
        with self._span("response"):
            if self.keeps:
                narrow = set(self.catalog.kept()) - self.catalog.wide
                halves = self._rows_of(narrow).withColumn("fresh", F.lit(None).cast("array<boolean>"))
                kept = [self.catalog.number[k] for k in narrow]
                for level in fresh_nodes or ():
                    halves = halves.unionByName(level.where(F.col("node").isin(kept)).select(*halves.columns))
                fresh = added.single(delta, halves, old, new, self.catalog, labels)
            else:
                frames = [derivations(m, q) for q in touched for m in added.telescoped(delta, old, new, q, labels)]
                fresh = union_all(frames, self.spark, added.DERIV).groupBy("qid", "ans", "mono").agg(F.sum("n").alias("n"))
            fresh = self._store(self._tracked(fresh), "fresh")
            per = fresh.groupBy("qid", "ans").agg(F.sum("n").alias("n"))
            had = self.tables["deriv"].read().select("qid", "ans").join(per.select("qid", "ans"), ["qid", "ans"], "left_semi").distinct().withColumn("_had", F.lit(True))
            changes = per.join(had, ["qid", "ans"], "left").select("qid", "ans", F.when(F.col("_had"), "support_added").otherwise("added").alias("change"), "n")
            changes = self._logged(changes)
        with self._span("maintenance"):
            if self.keeps and plain:
                fresh_nodes = self._refreshed(delta, old, labels)
            if self.catalog.policy != "none":
                for level in fresh_nodes or ():
                    self._adopt("nodes", level)
            self._adopt("deriv", fresh)
            self._indexed(fresh)
            self._adopt("triples", delta)
            self._compact()
        return changes

    def _adopt(self, name: str, stored: DataFrame) -> None:
        """A table that is written already becomes a part."""
        self.tables[name].parts.append((self.version, stored.inputFiles()[0].rsplit("/", 1)[0] if stored.inputFiles() else self._empty(name)))

    def _empty(self, name: str) -> str:
        at = f"{self.path}/empty_{name}_{uuid.uuid4().hex[:6]}"
        self.spark.createDataFrame([], self.tables[name].schema).write.parquet(at)
        return at

    def _refreshed(self, delta: DataFrame, old: DataFrame, labels: set[str]) -> list[DataFrame]:
        """New rows of the kept nodes in which a label of the batch occurs, a table for each level."""
        plan = self.catalog.plan
        affected = set(plan.affected(labels))
        refresh = Refresh(Frames(plan, old, self._stored()), delta, affected)
        keys = [k for k in (self.catalog.stored() if self.catalog.policy != "none" else sorted(set(self.catalog.kept()) - self.catalog.wide)) if k in affected]
        sizes: dict[int, list[str]] = {}
        for k in keys:
            sizes.setdefault(len(plan.nodes[k].patterns), []).append(k)
        out = []
        for _, level in sorted(sizes.items()):  # bottom-up: the next level reads what this one wrote
            rows = [refresh.rows(k).selectExpr(f"{self.catalog.number[k]} AS node", "binding", "edges", "fresh") for k in level]
            out.append(self._store(union_all(rows, self.spark, f"{NODE_SCHEMA}, fresh array<boolean>"), "nodes"))
            for k in level:
                refresh.made[k] = out[-1].where(f"node = {self.catalog.number[k]}").select("binding", "edges", "fresh")
        return out

    def delete(self, ids: DataFrame, use_index: bool = True) -> DataFrame:
        """Delete edges by id; returns (qid, ans, change, n).  Ids that are not there change nothing."""
        if not self.track:
            raise ValueError("deletion by index needs provenance; use baselines.counting")
        self.version += 1
        ids = self._store(ids.select("edge_id").distinct().join(self.tables["triples"].read().select("edge_id"), "edge_id", "left_semi"), "gone")
        few = [r["edge_id"] for r in ids.limit(SMALL + 1).collect()]  # SMALL + 1 at most
        if not few:
            return self.spark.createDataFrame([], CHANGES)
        small = len(few) <= SMALL
        with self._span("response"):
            index = None
            if use_index:
                index = self.tables["index"].read(F.expr(f"edge_id IN ({', '.join(map(str, few))})") if small else None)
            changes = self._logged(gone.verdicts(gone.refine(self.deriv, ids, index)))
        with self._span("maintenance"):
            if small:
                self.deleted.add(self.version, few)
                self._compact()
            else:
                for t in self.tables.values():
                    t.rewrite(t.without(ids), self.version)
        return changes

    def _compact(self) -> None:
        """Write a table of many parts anew, and all tables once the noted ids are many."""
        many = self.deleted.count > SMALL
        for t in self.tables.values():
            if many or len(t.parts) > MOST_PARTS:
                t.rewrite(t.read(), self.version)
        if many:
            self.deleted.ids.clear()

    def replace(self, ids: DataFrame, edges: DataFrame) -> DataFrame:
        """Modify: delete, then insert."""
        return self.delete(ids).unionByName(self.insert(edges))

    def drop_vertex(self, vertex: str) -> DataFrame:
        return self.delete(self.triples.where((F.col("s") == vertex) | (F.col("o") == vertex)).select("edge_id"))

    def apply(self, updates: DataFrame, mode: str = "batch") -> DataFrame:
        """Mixed updates (seq, op, edge_id, s, p, o, inverse): netted by edge in a batch, or edge by edge in order.

        An id that some update deletes goes with what it was; what the first insert behind its last delete says comes in its place.
        """
        if mode == "batch":
            last = self._store(net(updates), "net")
            out = self.delete(last.where("op = 'del'").select("edge_id"))
            return out.unionByName(self.insert(last.where("op = 'ins'").select(*COLUMNS)))
        frames = []
        for r in updates.select("seq", "op", "edge_id").distinct().orderBy("seq").toLocalIterator():
            if r["op"] == "del":
                frames.append(self.delete(self.spark.createDataFrame([(r["edge_id"],)], "edge_id long")))
            else:
                frames.append(self.insert(updates.where((F.col("seq") == r["seq"]) & (F.col("op") == "ins")).select(*COLUMNS), one_edge=True))
        return union_all(frames, self.spark, CHANGES)
