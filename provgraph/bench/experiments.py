"""Experiments: statistics, sharing, sizes, registration, engine against baselines, update mixes, time split, batch sizes.

    python -m provgraph.bench.experiments NAME [SF_DIR]

prints one JSON line a row.  Times are wall seconds on the session's machine; each update batch includes answers and the upkeep of
all structures.
"""

from __future__ import annotations

import json
import sys
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import recompute
from ..kg.build import graph_for
from ..maintain.maintainer import Maintainer
from ..match.evaluate import derivations, evaluate
from ..query.folding import klass
from ..stats.cardinality import Estimator
from ..stats.labels import constraints
from ..workload import updates
from ..workload.queries import labels_of, large_set, small_set
from . import measures


def _graph(spark: SparkSession, sf: str, queries) -> DataFrame:
    return graph_for(spark, sf, {x for q in queries for x in labels_of(q)})


def _timed(f) -> float:
    start = time.perf_counter()
    out = f()
    for df in out if isinstance(out, tuple) else (out,):
        if isinstance(df, DataFrame):
            df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


def statistics(spark, sf) -> list[dict]:
    qs = small_set()
    g = _graph(spark, sf, qs)
    r = g.agg(F.count_distinct("edge_id").alias("edges"), F.count_distinct("p").alias("labels")).first()
    vertices = g.select(F.col("s").alias("v")).union(g.select("o")).distinct().count()
    return [{"edges": r["edges"], "labels": r["labels"], "vertices": vertices, "queries": len(qs), "mean_size": sum(len(q.body) for q in qs) / len(qs), "folding": sum(klass(q, constraints(g)) == "folding" for q in qs)}]


def sharing(spark, sf) -> list[dict]:
    est = Estimator.build(_graph(spark, sf, large_set())).estimate
    return [*measures.by_size(large_set(), est), {"size": "all", **measures.sharing(large_set(), est)}]


def registration(spark, sf) -> list[dict]:
    out = []
    for q in small_set():
        m = Maintainer(_graph(spark, sf, [q]))
        seconds = _timed(lambda m=m, q=q: m.register(q) and None)
        points = measures.connection_points(m.annotation).first()
        out.append({"qid": q.name, "seconds": seconds, **points.asDict(), "answer_index": m.edge_to_answer.count(), "point_index": m.edge_to_cp.count()})
    return out


def against_baselines(spark, sf, batch: int = 1000) -> list[dict]:
    """A batch of typed inserts and as many deletes: the engine against recomputing the relevant queries."""
    out = []
    for q in small_set():
        g = _graph(spark, sf, [q])
        m = Maintainer(g).register(q)
        ins = m._store(updates.inserts(m.triples, labels_of(q), batch, "typed"), "batch")
        dels = m._store(updates.deletes(m.triples, labels_of(q)).limit(batch), "batch")
        n = ins.count() + dels.count()
        engine = _timed(lambda m=m, dels=dels: m.delete(dels)) + _timed(lambda m=m, ins=ins: m.insert(ins))
        now, before = m.triples, derivations(evaluate(g, q), q)
        row = {"qid": q.name, "updates": n, "engine": engine, "graph_order": _timed(lambda now=now, q=q: recompute.graph_recompute(now, [q])), "rewritten": _timed(lambda now=now, q=q: recompute.rewrite_recompute(now, [q]))}
        row["circuit"] = _timed(lambda now=now, q=q: recompute.circuit_recompute(now, q))
        row["rerun"] = _timed(lambda now=now, q=q, before=before: recompute.rerun_all(now, [q], before))
        out.append(row)
    return out


def mixes(spark, sf, batch: int = 1000) -> list[dict]:
    out = []
    for name, part in updates.MIXES.items():
        for q in small_set():
            m = Maintainer(_graph(spark, sf, [q])).register(q)
            ins = updates.inserts(m.triples, labels_of(q), batch * (10 - part) // 10, "typed")
            dels = updates.deletes(m.triples, labels_of(q)).limit(batch * part // 10)
            u = m._store(updates.as_updates(ins, dels, part), "mix")
            n = u.select("edge_id").distinct().count()
            out.append({"mix": name, "qid": q.name, "updates": n, "seconds_per_update": _timed(lambda m=m, u=u: m.apply(u)) / max(n, 1)})
    return out


def time_split(spark, sf, batch: int = 1000) -> list[dict]:
    out = []
    for q in small_set():
        m = Maintainer(_graph(spark, sf, [q]), constraints=constraints(_graph(spark, sf, [q]))).register(q)
        m.spans.clear()
        m.insert(updates.inserts(m.triples, labels_of(q), batch, "typed"))
        m.delete(updates.deletes(m.triples, labels_of(q)).limit(batch))
        total = sum(t for _, _, t in m.spans)
        for phase in ("response", "maintenance"):
            out.append({"qid": q.name, "size": len(q.body), "klass": klass(q, m.constraints), "phase": phase, "share": sum(t for _, p, t in m.spans if p == phase) / total})
    return out


def batch_sizes(spark, sf) -> list[dict]:
    q = small_set()[1]
    out = []
    for b in (1, 10, 100, 1000, 10_000):
        m = Maintainer(_graph(spark, sf, [q])).register(q)
        ins = m._store(updates.inserts(m.triples, labels_of(q), b, "typed"), "batch")
        out.append({"qid": q.name, "batch": b, "seconds_per_update": _timed(lambda m=m, ins=ins, b=b: m.insert(ins, one_edge=b == 1)) / b})
    return out


EXPERIMENTS = {f.__name__: f for f in (statistics, sharing, registration, against_baselines, mixes, time_split, batch_sizes)}


def main() -> None:
    name, sf = sys.argv[1], sys.argv[2] if len(sys.argv) > 2 else "/root/testdata/sf0.01"
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for row in EXPERIMENTS[name](spark, sf):
        print(json.dumps(row, default=float), flush=True)


if __name__ == "__main__":
    main()
