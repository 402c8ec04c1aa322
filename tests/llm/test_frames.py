"""Operators on small frames: odd rows, brute force, accuracy, the pipeline."""

import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from provgraph.llm import ann, bpe, jaccard, langid, lmscore, packing, quality, queries, tokenstore, toxicity, wordpieces
from provgraph.llm.runtime import fold

DOCS = "doc_id long, text string, lang string, source string, n_chars long, n int, key string, part int"
LONG = " ".join(f"w{i % 977} x{i}" for i in range(6000))
ROWS = [
    (0, None, None, None, None, None, None, None), (1, "", "en", "s", 0, 1, "k", 1), (2, " \n\t ", None, "s", 3, 1, "k", 1), (3, "one two", "en", None, 7, 1, "k", 1),
    (4, LONG, "en", "s", None, 1, "k", 1), (4, LONG, "en", "s", None, 1, "k", 1), (5, LONG + " tail", "en", "s", 1, 1, None, 1), (6, "ONE two", "de", "s", 1, 1, "k", 1),
    (None, "one two", "en", "s", 1, 1, "k", 1), (7, "12 34 !!", "en", "s", 1, 1, "k", 1), (8, "é ü ß " * 30, "de", "s", 1, 1, "k", 1), (9, "é ü ß " * 30, "de", "s", 1, 1, "k", 1),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ROWS, DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


def test_odd_rows_of_row_operators(odd, none):
    for f in (quality.quality, wordpieces.piece_counts, bpe.round_trip, bpe.encode_table):
        assert f(odd).count() == len(ROWS) and f(none).count() == 0
    got = {r["doc_id"]: r for r in quality.quality(odd).collect()}
    assert got[0]["n_words"] == 0 and got[0]["base_failed"] and not got[0]["kept"] and got[4]["n_words"] == 12000
    assert {r["doc_id"]: r["n_tokens"] for r in bpe.round_trip(odd).collect()}[1] == 0


def test_language(odd, none):
    model = langid.fit(odd)
    got = {r["doc_id"]: r for r in langid.label(odd, model, spans=True).collect()}
    assert len(got) == 11 and got[0]["lang_pred"] == got[7]["lang_pred"] == langid.UNKNOWN and got[8]["lang_pred"] in model.languages
    assert langid.label(odd, langid.fit(none)).where("lang_pred <> 'und'").count() == 0


def test_toxicity(spark, odd, none):
    labels = spark.createDataFrame([(i, i % 2, i % 2) for i in range(10)] + [(None, 1, 1), (3, None, None)], "doc_id long, quality int, toxic int")
    got = toxicity.score(odd, toxicity.fit(odd, labels)).collect()
    assert len(got) == len(ROWS) and all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.5) for r in got)
    assert toxicity.score(odd, toxicity.fit(none, labels)).where("score > 0").count() == 0


def test_jaccard_odd_rows(odd, none):
    got = {}
    for r in jaccard.join(odd).collect():
        got.setdefault(r["doc_id"], (r["n_shingles"], r["component_id"]))
    assert got[0] == (0, 0) and got[1] == (0, 1) and got[2] == (0, 2) and got[3] == (1, 3) and got[6] == (1, 3) and got[None] == (1, None)
    assert got[5][1] == got[4][1] == 4 and got[9][1] == 8
    assert jaccard.join(none).count() == 0


def shingles(text):
    w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").split()
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()


def test_jaccard_against_brute_force(spark):
    rnd = np.random.default_rng(7)
    rows = []
    for g in range(12):
        base = [f"t{x}" for x in rnd.integers(0, 4000, rnd.integers(4, 90))]
        for _ in range(6):
            own = list(base)
            for _ in range(rnd.integers(0, 4)):
                own[rnd.integers(0, len(own))] = f"u{rnd.integers(0, 50)}"
            rows.append((len(rows), " ".join(own)))
    sets = {i: shingles(t) for i, t in rows}
    root = {i: i for i in sets}
    for i in sets:
        for j in sets:
            if i < j and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]) and sets[i]:
                a, b = root[i], root[j]
                root = {k: min(a, b) if v in (a, b) else v for k, v in root.items()}
    got = {r["doc_id"]: r["component_id"] for r in jaccard.join(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == root and len(set(root.values())) < len(rows)


def test_jaccard_frequent_fragments_and_blocks(spark, monkeypatch):
    """Salted fragments, held-back ones and buckets of several blocks give the same components and links."""
    for name, value in (("BLOCK", 3), ("OFTEN", 4), ("LOT", 8), ("HELD", 5), ("SALTS", 3), ("ROUNDS", 1)):
        monkeypatch.setattr(jaccard, name, value)
    rnd = np.random.default_rng(23)
    passage, rows = [f"p{x}" for x in range(40)], []
    for g in range(4):
        base = [f"t{x}" for x in rnd.integers(0, 4000, 60)]
        for _ in range(14):
            own = list(base)
            for _ in range(rnd.integers(0, 3)):
                own[rnd.integers(0, len(own))] = f"u{rnd.integers(0, 50)}"
            rows.append((len(rows), " ".join(own + passage if g % 2 else own)))
    rows += [(len(rows) + k, " ".join([f"s{k}x{i}" for i in range(12)] + passage)) for k in range(20)]
    rows += [(len(rows) + k, "a b c d e f g h" + " i" * (k % 2)) for k in range(6)]
    sets = {i: shingles(t) for i, t in rows}
    want = {(i, j) for i in sets for j in sets if i < j and sets[i] != sets[j] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j])}
    root = {i: i for i in sets}
    for i, j in sorted(want | {(i, j) for i in sets for j in sets if i < j and sets[i] == sets[j]}):
        a, b = root[i], root[j]
        root = {k: min(a, b) if v in (a, b) else v for k, v in root.items()}
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert {r["doc_id"]: r["component_id"] for r in jaccard.join(docs).collect()} == root
    least = {i: min(j for j in sets if sets[j] == sets[i]) for i in sets}
    got = {(r["doc_a"], r["doc_b"]) for r in jaccard.links(docs).collect()}
    assert got == {(i, j) for i, j in want if least[i] == i and least[j] == j}


def test_jaccard_links_against_brute_force(spark):
    """All links between different texts, also those that the components don't need."""
    rnd = np.random.default_rng(11)
    rows = []
    for _ in range(5):
        base = [f"t{x}" for x in rnd.integers(0, 4000, rnd.integers(110, 160))]
        for k in range(7):
            own = list(base)
            own[5 * k] = f"u{k}"
            rows.append((len(rows), " ".join(own)))
    rows += [(len(rows), rows[0][1]), (len(rows) + 1, ""), (None, rows[1][1])]
    sets = {i: shingles(t) for i, t in rows[:35]}
    want = {(i, j, len(sets[i] & sets[j])) for i in sets for j in sets if i < j and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j])}
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = [tuple(r) for r in jaccard.links(docs).collect()]
    assert len(got) == len(want) and set(got) == want and len(want) > 35
    assert jaccard.links(docs.where("false")).count() == 0


def test_token_store(spark, odd, none, tmp_path):
    import pyarrow.orc as orc
    from tokenizers import Tokenizer

    from provgraph.llm.subwords import default_path

    library = Tokenizer.from_file(default_path())
    got = tokenstore.store(odd).orderBy("start").collect()
    start, want = 0, []
    ids_of = lambda t: library.encode(t or "", add_special_tokens=False).ids + [0]
    for i, t in sorted(((r[0], r[1]) for r in ROWS), key=lambda x: (x[0] is not None, x[0] or 0)):
        ids = ids_of(t)
        want.append((i, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    assert [tuple(r) for r in got] == want and tokenstore.store(none).count() == 0
    path = str(tmp_path / "t")
    tokenstore.write(odd, path, parts=2)
    assert sorted(len(r["ids"]) for r in tokenstore.lookup(spark, path, [4]).collect()) == [len(ids_of(LONG))] * 2
    first = orc.ORCFile(next((tmp_path / "t").glob("*.orc")))
    assert first.nstripes >= 1
    plan = tokenstore.lookup(spark, path, [4])._jdf.queryExecution().toString()
    assert "PushedFilters: [" in plan and "doc_id" in plan.split("PushedFilters")[1][:60]


def test_added_tokens_in_texts(spark):
    """op5 and op9 encode as the library does by default, where the string of an added token is that token."""
    from tokenizers import Tokenizer

    from provgraph.llm.subwords import default_path

    library = Tokenizer.from_file(default_path())
    texts = ["a <|endoftext|> b", "<|endoftext|>", "x<|endoftext|><|endoftext|> y\n <|endoftext", "plain text"]
    want = [library.encode(t, add_special_tokens=False).ids + [0] for t in texts]
    assert want[0] == [64, 220, 50256, 275, 0]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = [(r["n_tokens"], r["ids_crc32"]) for r in tokenstore.store(docs).orderBy("doc_id").collect()]
    assert got == [(len(x), zlib.crc32(np.array(x, "<u4").tobytes())) for x in want]
    lengths = {r["doc_id"]: r["n"] for r in packing.pack_documents(docs).groupBy("doc_id").agg(F.sum("length").alias("n")).collect()}
    assert lengths == {i: len(x) for i, x in enumerate(want)}


def test_packing(odd, none):
    got = packing.pack_documents(odd).collect()
    by, docs = {}, {}
    for r in got:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
        docs.setdefault(r["doc_id"], 0)
        docs[r["doc_id"]] += r["length"]
    for items in by.values():
        at = 0
        for start, n in sorted(items):
            assert start == at
            at += n
        assert at <= 2048
    assert docs[0] == docs[1] == 1 and packing.pack_documents(none).count() == 0


def cross_entropy(rows, target):
    """(id, words, target loss, background loss) by counting in dictionaries, each row's own counts left out."""
    from collections import Counter
    from math import log

    texts = [(i, t, (t or "").lower().split()) for i, t in rows]
    words, before, pairs = ([Counter(), Counter()] for _ in range(3))
    steps = lambda w: list(zip(["<s>", *w], [*w, "</s>"]))
    for i, _, w in texts:
        for k in (0, 1) if i in target else (1,):
            if w:
                words[k].update([*w, "</s>"])
                before[k].update(["<s>", *w])
                pairs[k].update(steps(w))
    size, sums = len(words[1]), [sum(c.values()) for c in words]
    out = []
    for i, _, w in texts:
        loss = [0.0, 0.0]
        own_w, own_v, own_p = Counter([*w, "</s>"]), Counter(["<s>", *w]), Counter(steps(w))
        for k, scale in ((0, 1.0), (1, min(1.0, max(sums[0], 1) / max(sums[1], 1)))):
            mine = k == 1 or i in target
            for v, x in steps(w) if w else ():
                base = (words[k][x] - mine * own_w[x] + 1) / (sums[k] - mine * (len(w) + 1) + size)
                loss[k] -= log((scale * (pairs[k][v, x] - mine * own_p[v, x]) + lmscore.MASS * base) / (scale * (before[k][v] - mine * own_v[v]) + lmscore.MASS)) / (len(w) + 1)
        out.append((i, len(w), *loss, loss[0] - loss[1]))
    return out


def test_cross_entropy_difference(spark, none, odd, monkeypatch):
    monkeypatch.setattr(lmscore, "CHUNK_WORDS", 300)
    rows = [(i, " ".join(f"{'good' if i % 2 else 'plain'}{(i * 7 + k) % 13}" for k in range(60))) for i in range(40)]
    rows += [(50, None), (51, ""), (52, "Good3 plain4"), (52, "Good3 plain4"), (53, "new words " * 400)]
    docs = spark.createDataFrame([*rows, (None, "good1 good2")], "doc_id long, text string").repartition(5)
    chosen = [i for i in range(1, 30, 2)]
    target = spark.createDataFrame([(i,) for i in [*chosen, *chosen, None, 777]], "doc_id long")
    got = sorted(tuple(r) for r in lmscore.difference(docs, target).collect() if r["doc_id"] is not None)
    want = sorted(x for x in cross_entropy([*rows, (None, "good1 good2")], set(chosen)) if x[0] is not None)
    assert [x[:2] for x in got] == [x[:2] for x in want] and np.allclose([x[2:] for x in got], [x[2:] for x in want], rtol=1e-9, atol=1e-12)
    by = {x[0]: x[4] for x in got}
    assert all(by[i] < 0 for i in range(1, 40, 2)) and all(by[i] > 0 for i in range(0, 40, 2)) and by[50] == by[51] == 0
    assert lmscore.difference(none, target).count() == 0 and lmscore.difference(docs, target.where("false")).count() == len(rows) + 1
    assert lmscore.difference(odd, odd.select("doc_id", F.lit(1).alias("text"))).count() == len(ROWS)


def test_models_are_distributions():
    """The probabilities of all words and the end after any word sum to one."""
    texts = [["a", "b", "a"], ["b", "c"], ["a"]]
    chunk = lmscore.Chunk(texts)
    keys = chunk.keys
    _, v, w = chunk.steps()
    pairs, at = np.unique(lmscore.pair_keys(keys[v], keys[w]), return_inverse=True)
    single = np.bincount(w, minlength=len(keys))
    single[0] = len(texts)
    n_pairs, size, total = np.bincount(at), len(keys) - 1, int(single[1:].sum())
    count = dict(zip(pairs.tolist(), n_pairs.tolist()))
    for x in [0, *range(2, len(keys))]:
        p = [(count.get(int(lmscore.pair_keys(keys[[x]], keys[[y]])[0]), 0) + lmscore.MASS * (single[y] + 1) / (total + size)) / (single[x] + lmscore.MASS) for y in range(1, len(keys))]
        assert abs(sum(p) - 1) < 1e-12
    x = np.sort(np.random.default_rng(3).integers(0, 1 << 63, 1000).astype(np.uint64))
    assert (lmscore.unpack(lmscore.pack(x)) == x).all() and lmscore.unpack_counts(lmscore.pack_counts(np.array([1, 70000]))).tolist() == [1, 70000]


def test_nearest(spark):
    rnd = np.random.default_rng(5)
    x = rnd.standard_normal((400, 16)).astype("float32")
    x[50:120] = x[0]
    rows = [(i, v.tolist(), 0) for i, v in enumerate(x)] + [(400, None, 0), (500, [0.0] * 16, 0), (600, [float("nan")] * 16, 0), (700, [1.0], 0), (None, x[0].tolist(), 0), (7, x[7].tolist(), 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    got: dict = {}
    for r in ann.search(df, probes=64).orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    assert sorted(got) == [0, 100, 200, 300]
    assert [v for v, _ in got[0]] == list(range(50, 60)) and [v for v, _ in got[100]] == [0, *range(50, 59)]
    for q in (200, 300):
        d = np.sqrt(((x.astype(float) - x[q].astype(float)) ** 2).sum(1))
        d[q] = np.inf
        assert [v for v, _ in got[q]] == sorted(range(400), key=lambda i: (d[i], i))[:10]
    assert ann.search(df.where("false")).count() == 0


def test_held_out_accuracy(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = queries.op2_language_id(spark, sf).join(docs, "doc_id").where("held_out")
    assert got.where("lang = lang_pred").count() >= 0.97 * got.count()
    assert queries.op2_language_id(spark, sf).where(F.col("held_out") != (fold("doc_id", 4) == 2)).count() == 0


def test_toxicity_on_held_out_rows(spark):
    """Rows that the models never saw: clean ones are left alone, most toxic ones found; ids and labels may repeat, columns clash."""
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    more = docs.unionByName(docs.limit(20)).withColumn("toxic", F.lit(1)).withColumn("_y", F.lit("x"))
    model = toxicity.fit(more, labels.unionByName(labels.limit(30)).withColumn("text", F.lit("none")))
    got = toxicity.score(more, model).join(labels, "doc_id").where("held_out").select("toxic", "predicted").collect()
    clean, toxic = ([r["predicted"] for r in got if r["toxic"] == y] for y in (0, 1))
    assert sum(clean) <= 0.05 * len(clean) and sum(toxic) >= 0.5 * len(toxic) > 0
    assert toxicity.score(docs, toxicity.fit(docs, labels.where("toxic = 0"))).where("score > 0").count() == 0


def test_language_stage_rejects_what_no_language_fits(spark, sf):
    rnd = np.random.default_rng(4)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    noise = lambda letters: " ".join("".join(rnd.choice(list(letters), 7)) for _ in range(120))
    planted = [(-1, noise("абвгдежзиклмнопрст")), (-2, noise("的一是不了人我在有他这")), (-3, noise("abcdefghijklmnopqrstuvwxyz")), (-4, noise("bcdfghjklmnpqrstvwxz"))]
    rows = spark.createDataFrame([(i, t, None, "s", len(t)) for i, t in planted], "doc_id long, text string, lang string, source string, n_chars long")
    every = docs.unionByName(rows.select(*(F.col(f.name).cast(f.dataType) for f in docs.schema)))
    got = {r["doc_id"]: r for r in langid.label(every, langid.fit(every), fits=True).collect()}
    assert got[-1]["lang_pred"] == got[-2]["lang_pred"] == langid.UNKNOWN and not got[-3]["fits"] and not got[-4]["fits"]
    kept = {r["doc_id"] for r in corpus_pipeline.language(spark, every, sf).collect()}
    clean = {r["doc_id"] for r in corpus_pipeline.quality_rules(spark, docs, sf).collect()}
    assert not kept & {-1, -2, -3, -4} and len(clean & kept) >= 0.97 * len(clean)


def test_pipeline_rows(spark, sf, odd, none):
    """Null and repeated ids, ties, extra columns: every row is judged by itself, and one of each group stays."""
    good = [r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").where("lang = 'en'").orderBy("doc_id").collect() if quality.judged(r["text"], quality._compressor(3))[-1]]
    a, b, c = good[0], good[1], good[2]
    rows = [(None, a, "en", "s", 1, 1, "k", 1), (7, b, "en", "s", 1, 2, "k", 1), (7, c, "en", "s", 1, 3, "k", 1), (7, c, "en", "s", 1, 3, "k", 1), (9, a + " tail", None, "s", 1, 4, "k", 1), (None, "", "en", "s", 0, 5, "k", 1), (3, None, None, None, None, 6, None, None), (5, a, "en", "s", 1, 7, "k", 1)]
    docs = spark.createDataFrame(rows, DOCS)
    kept = corpus_pipeline.quality_rules(spark, docs, sf)
    assert kept.columns == docs.columns and sorted(r["n"] for r in kept.collect()) == [1, 2, 3, 3, 4, 7]
    every = docs.unionByName(spark.read.parquet(f"{sf}/documents.parquet").where("doc_id > 9"), allowMissingColumns=True)
    fits = corpus_pipeline.language(spark, every, sf)
    assert fits.columns == docs.columns and sorted(r["n"] for r in fits.where("n is not null").collect()) == [1, 2, 3, 3, 4, 7]
    one = corpus_pipeline.near_copies(spark, docs, sf)
    assert one.columns == docs.columns and sorted(r["n"] for r in one.collect()) == [2, 3, 5, 6, 7]
    packed = corpus_pipeline.pack(spark, docs, sf).groupBy("doc_id").agg(F.countDistinct("start", "length", "ids_crc32").alias("n")).collect()
    assert {r["doc_id"] for r in packed} == {None, 3, 5, 7, 9}
    for _, step in corpus_pipeline.STAGES:
        assert step(spark, docs.where("false"), sf).count() == 0


def test_pipeline(spark, sf, none):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = {r["doc_id"] for r in corpus_pipeline.quality_rules(spark, docs, sf).collect()}
    assert kept == {r["doc_id"] for r in quality.quality(docs).where("kept").collect()}
    stage = corpus_pipeline.near_copies(spark, docs, sf)
    assert stage.columns == docs.columns and stage.count() == jaccard.join(docs).select("component_id").distinct().count()
    packed = corpus_pipeline.run(spark, sf)
    assert 0 < packed.select("doc_id").distinct().count() <= len(kept)
    for _, step in corpus_pipeline.STAGES:
        assert step(spark, none.select(*docs.columns), sf).count() == 0


def test_language_stage_learns_from_all_rows(spark):
    """A letter group that one row of thousands has is learned, whatever the row's id; a fold or a share of the rows would miss some."""
    rows = [(i, f"mo ni {'qxz' if i == 7 else 'vkw' if i == 8 else 'ta'} lu", "x", "s", 10) for i in range(6000)] + [(None, "zzjzz", "x", "s", 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    model = langid.learn(docs)
    assert {"qxz", "vkw", "zjz"} <= set(model.scores) and langid.Labeller(model).index.most <= 100_000
    counts = {(r["lang"], r["item"]): r["n"] for r in langid._counted(docs.select("text", "lang")).where("kind = 0").collect()}
    assert counts["x", " ta"] == 5998 and counts["x", " qx"] == 1
    assert corpus_pipeline.language(spark, docs, "").count() >= 5998
