"""Toxicity by two class-conditional Kneser-Ney models of letters within words.

Both classes have discounted counts of their own for n-grams of the full order; what the discount
frees goes to one lower-order Kneser-Ney model, whose continuation counts are shared.  A rare form
(an inflected insult, say) is so judged by its parts.  The log-likelihood ratio of a word is a sum over its letters
and depends on the word alone, so it is computed once for each form.  A document gets the ratio for each
word, that is length-normalised, over the whole text and over the windows of WINDOWS words in which it is highest; a logistic
curve turns these into a probability.  It is fitted on all labelled rows of the sample, each judged by models that counted the other folds only, so that
it sees what the models are worth on new texts; a weight below zero (a denser text being less toxic) is left out.

Fit: at most `max_train_docs` labelled rows of each class (those with the smallest hashes).  N-grams of one document only say
nothing of others and are left out (LEAST_DOCS), no other is.  Scoring covers every row.

Defined results: null and empty texts and texts without a letter have ratio 0 and get the score of that
ratio; without labels of both classes every score is 0; repeated rows get a row each; a document with several
labels counts as toxic if one says so; a null id is not held out.
"""

from __future__ import annotations

import math
import pickle
from collections import Counter, defaultdict
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import Stage, fold, ship
from .units import Memo

EDGE = "\x02"
ORDER = 8
#: Words of the windows whose highest ratio counts, besides the whole text.
WINDOWS = (1, 8, 32)
#: Documents that an n-gram has to occur in.
LEAST_DOCS = 2
#: Parts of the sample for cross-fitting.
PARTS = 3
#: A toxic row counts as so many in the logistic fit.
TOXIC_WEIGHT = 2.0


def letters(token: str) -> list[str]:
    """Lower-case words of letters in a token without white space."""
    if token.isalpha():
        return [token]
    return "".join(c if c.isalpha() else " " for c in token).split()


def grams(word: str, order: int) -> list[str]:
    s = EDGE + word + EDGE
    return [s[max(0, i - order + 1) : i + 1] for i in range(1, len(s))]


@dataclass
class KneserNeyRatio:
    """log p(letter | context, toxic) - log p(letter | context, ordinary) of each n-gram, and of each context for letters not seen after it."""

    order: int = ORDER
    seen: dict = field(default_factory=dict)
    unseen: dict = field(default_factory=dict)
    weights: tuple = (0.0,) * (2 + len(WINDOWS))
    fitted: bool = False

    @classmethod
    def fit(cls, counts: dict[str, tuple[int, int]], order: int = ORDER, discount: float = 0.75) -> KneserNeyRatio:
        shared = _shared_backoff(counts, discount)
        model = cls(order)
        total, kinds = defaultdict(lambda: [0, 0]), defaultdict(lambda: [0, 0])
        for g, by in counts.items():
            for k in (0, 1):
                total[g[:-1]][k] += by[k]
                kinds[g[:-1]][k] += by[k] > 0
        free = {h: [discount * kinds[h][k] / n[k] if n[k] else 1.0 for k in (0, 1)] for h, n in total.items()}
        for g, by in counts.items():
            h = g[:-1]
            p = [(max(by[k] - discount, 0) / total[h][k] if total[h][k] else 0.0) + free[h][k] * shared(g[1:]) for k in (0, 1)]
            model.seen[g] = math.log(p[1] / p[0])
        model.unseen = {h: math.log(f[1] / f[0]) for h, f in free.items() if f[0] != f[1]}
        return model

    def word(self, word: str) -> float:
        seen, unseen = self.seen, self.unseen
        return sum(seen[g] if g in seen else unseen.get(g[:-1], 0.0) for g in grams(word, self.order))


def _shared_backoff(counts: dict, discount: float):
    """Interpolated Kneser-Ney probabilities of the lower orders, from the n-gram types of both classes."""
    kinds_before: Counter = Counter()
    level = Counter(g[1:] for g in counts)
    while level:
        for g, n in level.items():
            kinds_before[g] += n
        level = Counter(g[1:] for g in level if len(g) > 1)
    sums: dict[str, list[int]] = {}
    for g, n in kinds_before.items():
        at = sums.setdefault(g[:-1], [0, 0])
        at[0] += n
        at[1] += 1
    alphabet = max(1, len({g[-1] for g in counts}))

    def p(g: str) -> float:
        lower = p(g[1:]) if len(g) > 1 else 1.0 / alphabet
        n, kinds = sums.get(g[:-1], (0, 0))
        if not n:
            return lower
        return max(kinds_before.get(g, 0) - discount, 0) / n + discount * kinds / n * lower

    return p


class Scorer:
    def __init__(self, model: KneserNeyRatio):
        self.model = model
        self.get = Memo(self._token).__getitem__

    def _token(self, token: str) -> float:
        return sum(map(self.model.word, letters(token)))

    def features(self, text: str | None) -> tuple[float, ...]:
        """Log-likelihood ratio for each word, of the whole text and of its highest windows."""
        tokens = (text or "").lower().split()
        if not tokens:
            return (0.0,) * (1 + len(WINDOWS))
        c = np.zeros(len(tokens) + 1)
        np.cumsum(np.fromiter(map(self.get, tokens), float, len(tokens)), out=c[1:])
        out = [float(c[-1]) / len(tokens)]
        for window in WINDOWS:
            w = min(window, len(tokens))
            out.append(float((c[w:] - c[:-w]).max()) / window)
        return tuple(out)

    def score(self, text: str | None) -> float:
        if not self.model.fitted:
            return 0.0
        b, *w = self.model.weights
        z = b + sum(x * y for x, y in zip(w, self.features(text)))
        return 1 / (1 + math.exp(-min(max(z, -500), 500)))


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-3, steps: int = 60) -> np.ndarray:
    """Weights (bias first) of a ridge-logistic fit; columns whose weight is below zero are left out."""
    use, weight = list(range(x.shape[1])), np.where(y == 1, TOXIC_WEIGHT, 1.0)
    while True:
        scale = x[:, use].std(0) + 1e-9
        a = np.column_stack([np.ones(len(x)), x[:, use] / scale])
        w = np.zeros(a.shape[1])
        for _ in range(steps):
            p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
            d = weight * p * (1 - p) + 1e-9
            g = a.T @ (weight * (p - y)) + ridge * len(y) * np.r_[0, w[1:]]
            w -= np.linalg.solve((a * d[:, None]).T @ a + ridge * len(y) * np.diag([1e-9] + [1.0] * len(use)), g)
        if not use or (w[1:] >= 0).all():
            out = np.zeros(1 + x.shape[1])
            out[0], out[1 + np.array(use, int)] = w[0], w[1:] / scale
            return out
        use.pop(int(w[1:].argmin()))


def _gram_counts(rows: DataFrame, order: int) -> DataFrame:
    """(gram, docs, n{class}{part}): occurrences by class and part of the sample; rows: (text, class, part)."""
    names = [f"n{y}{k}" for y in (0, 1) for k in range(PARTS)]

    def run(batches):
        own = Memo(lambda token: [g for w in letters(token) for g in grams(w, order)], 100_000)
        out: dict[str, list[int]] = {}
        for batch in batches:
            for text, y, part in zip(batch.column(0), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                here: Counter = Counter()
                for token, n in Counter((text.as_py() or "").lower().split()).items():
                    for g in own[token]:
                        here[g] += n
                at = 1 + y * PARTS + part
                for g, n in here.items():
                    c = out.get(g)
                    if c is None:
                        c = out[g] = [0] * (1 + 2 * PARTS)
                    c[0] += 1
                    c[at] += n
        keys = list(out)
        for i in range(0, len(keys), 50_000):
            part = keys[i : i + 50_000]
            yield pa.RecordBatch.from_arrays([pa.array(part), *(pa.array([out[g][k] for g in part], pa.int64()) for k in range(1 + len(names)))], names=["gram", "docs", *names])

    schema = "gram string, docs long, " + ", ".join(f"{n} long" for n in names)
    return rows.mapInArrow(run, schema).groupBy("gram").agg(*(F.sum(n).alias(n) for n in ("docs", *names)))


def fit(docs: DataFrame, labels: DataFrame, order: int = ORDER, max_train_docs: int = 6000, folds: int = 5) -> KneserNeyRatio:
    """Fit on labelled rows outside fold 0."""
    spark = docs.sparkSession
    ship(spark)
    known = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isin(0, 1)).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("_y"))
    known = known.where(fold("doc_id", folds) != 0).withColumn("_h", F.xxhash64("doc_id"))
    chosen = [[(r["doc_id"], r["_y"]) for r in known.where(F.col("_y") == y).orderBy("_h", "doc_id").limit(max_train_docs).collect()] for y in (0, 1)]
    if not all(chosen):
        return KneserNeyRatio(order)
    # at most 2 x max_train_docs rows; one text of an id that several rows have
    sample = F.broadcast(spark.createDataFrame(chosen[0] + chosen[1], "_id long, _y int"))
    rows = docs.select("doc_id", "text").join(sample, F.col("doc_id") == F.col("_id")).groupBy("doc_id").agg(F.min("text").alias("text"), F.max("_y").alias("_y"))
    rows = Stage(spark).table(rows.select("text", "_y", F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(PARTS)).cast("int").alias("_part")), "sample")
    counted = Stage(spark).table(_gram_counts(rows, order).where(F.col("docs") >= LEAST_DOCS), "grams")  # n-grams of the sample, which is bounded
    # part k of the sample is judged by the model of all others; k = PARTS is the model of all
    sums = [F.struct(F.lit(k).alias("k"), *(sum((F.col(f"n{y}{j}") for j in range(PARTS) if j != k), F.lit(0).cast("long")).alias(f"n{y}") for y in (0, 1))) for k in range(PARTS + 1)]
    left = counted.select("gram", F.explode(F.array(*sums)).alias("c")).select("c.k", "gram", "c.n0", "c.n1").where("n0 + n1 > 0")

    def run(key, grams_of, texts):
        k = key[0].as_py()
        empty = {"k": pa.array([], pa.int32()), "x": pa.array([], pa.list_(pa.float64())), "y": pa.array([], pa.int32()), "model": pa.array([], pa.binary())}
        if not grams_of.num_rows:
            return pa.table(empty)
        counts = dict(zip(grams_of.column("gram").to_pylist(), zip(grams_of.column("n0").to_pylist(), grams_of.column("n1").to_pylist())))
        model = KneserNeyRatio.fit(counts, order)
        del counts
        if k == PARTS:
            raw = pickle.dumps(model, 5)
            pieces = [raw[i : i + (8 << 20)] for i in range(0, len(raw), 8 << 20)]
            return pa.table({"k": pa.array([PARTS + i for i in range(len(pieces))], pa.int32()), "x": pa.nulls(len(pieces), pa.list_(pa.float64())), "y": pa.nulls(len(pieces), pa.int32()), "model": pa.array(pieces, pa.binary())})
        scorer = Scorer(model)
        x = [scorer.features(t.as_py()) for t in texts.column("text")]
        return pa.table({"k": pa.array([k] * len(x), pa.int32()), "x": pa.array(x, pa.list_(pa.float64())), "y": texts.column("_y").combine_chunks().cast(pa.int32()), "model": pa.nulls(len(x), pa.binary())})

    texts = rows.select(F.col("_part").alias("k"), "text", "_y")
    got = left.groupBy("k").cogroup(texts.groupBy("k")).applyInArrow(run, "k int, x array<double>, y int, model binary").toArrow()  # a row for each row of the sample, and the model
    whole = got.filter(pa.compute.is_valid(got["model"])).sort_by("k")
    judged = got.filter(pa.compute.is_valid(got["x"]))
    x, y = np.array(judged["x"].to_pylist()).reshape(-1, 1 + len(WINDOWS)), np.array(judged["y"].to_pylist(), int)
    if not whole.num_rows or len(set(y.tolist())) < 2:
        return KneserNeyRatio(order)
    model = pickle.loads(b"".join(whole["model"].to_pylist()))
    model.weights = tuple(logistic(x, y).tolist())
    model.fitted = True
    return model


def score(docs: DataFrame, model: KneserNeyRatio, folds: int = 5) -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        scorer = Scorer(shared.value)
        for batch in batches:
            s = np.array([scorer.score(t.as_py()) for t in batch.column(1)], float)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(s), pa.array((s >= 0.5).astype(np.int32))], names=["doc_id", "score", "predicted"])

    scored = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, score double, predicted int")
    return scored.select("doc_id", F.coalesce(fold("doc_id", folds) == 0, F.lit(False)).alias("held_out"), "score", "predicted")
