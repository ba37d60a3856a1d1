"""Learned operators: held-out accuracy, brute force for the n-gram model and the vector graph, edge cases, the pipeline."""

import math
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from revnet.llm import cotraining, ngram_lm, toxicity_cnn, vector_graph
from revnet.llm.elias_fano import EliasFano, quantise

SF = "/root/testdata/sf0.01"


def tables(spark):
    return spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")


@pytest.mark.parametrize("n,u", [(0, 10), (1, 1), (5, 1000), (900, 1000), (1000, 10**6), (20000, 10**12)])
def test_elias_fano(n, u):
    r = np.random.default_rng(n)
    v = np.unique(r.integers(0, u, n)) if n else np.zeros(0, np.int64)
    e = EliasFano(v, u)
    assert (e.get(np.arange(len(v))) == v.astype(np.uint64)).all()
    q = np.concatenate([v, r.integers(0, u, 500)])
    want = {int(x): i for i, x in enumerate(v)}
    assert e.find(q).tolist() == [want.get(int(x), -1) for x in q]


def test_quantise_is_close():
    x = np.random.default_rng(1).normal(size=5000)
    code, book = quantise(x)
    assert np.abs(book[code] - x).mean() < 0.02


def test_packing():
    r = np.random.default_rng(2)
    for x in (r.integers(0, 5, 100), r.integers(0, 2**34, 1000), np.zeros(0, np.int64)):
        assert (ngram_lm.unpack(ngram_lm.pack(x)) == x).all()
    k = np.unique(r.integers(0, 2**62, 999).astype(np.uint64))
    assert (ngram_lm._undeltas(ngram_lm._deltas(k)) == k).all()


def brute(train, text, least=1):
    """The model's log10 probability by dictionaries, without quantisation."""
    seqs = [[b"", *ngram_lm.words_of(t.encode()), b""] for t in train]
    c = Counter(w for s in seqs for w in s[1:])
    total, kept = sum(c.values()), {w for w, n in c.items() if n >= least} | {b""}
    rare = sum(n for w, n in c.items() if w not in kept)
    rare_types = sum(w not in kept for w in c)
    m = lambda w: w if w in kept else None
    cc = Counter(c.values())
    off1 = ngram_lm.absolute_discounts(*(cc[i] for i in (1, 2, 3, 4)))
    left1 = sum(off1[min(n, 3)] for n in c.values()) / total / (len(c) + 1)
    if rare_types:
        uni = lambda w: (c[w] if w is not None else rare + 0.5) / (total + 0.5)
    else:
        uni = lambda w: ((c[w] - off1[min(c[w], 3)]) / total if w is not None else 0) + left1
    two = Counter((m(s[i]), m(s[i + 1])) for s in seqs for i in range(len(s) - 1) if m(s[i]) is not None and m(s[i + 1]) is not None)
    of = Counter(two.values())
    y = of[1] / (of[1] + 2 * of[2]) if of[1] + of[2] else 0.5
    off = [0.0] + [float(np.clip(i - (i + 1) * y * of[i + 1] / of[i] if of[i] else 0.5 * i, 0.05, i - 0.05)) for i in (1, 2, 3)]
    two = {k: n for k, n in two.items() if n >= least}
    three = Counter((m(s[i]), m(s[i + 1]), m(s[i + 2])) for s in seqs for i in range(len(s) - 2))
    three = {k: n for k, n in three.items() if n >= least and None not in k}

    def p2(b, w):
        left = max(1 - sum((n - off[min(n, 3)]) / c[b] for (x, _), n in two.items() if x == b), 1e-9) if b is not None else 1.0
        own = two.get((b, w), 0)
        return ((own - off[min(own, 3)]) / c[b] if own else 0) + left * uni(w)

    def p3(a, b, w):
        mine = {z: n for (x, y_, z), n in three.items() if (x, y_) == (a, b)}
        if not mine:
            return p2(b, w)
        all_ = two[a, b]
        left = max(1 - sum((n - off[min(n, 3)]) / all_ for n in mine.values()), 1e-9)
        return ((mine[w] - off[min(mine[w], 3)]) / all_ if w in mine else 0) + left * p2(b, w)

    s = [b"", *ngram_lm.words_of(text.encode()), b""]
    out = 0.0
    for i in range(1, len(s)):
        b, w = m(s[i - 1]), m(s[i])
        out += math.log10(p3(m(s[i - 2]), b, w) if i > 1 else p2(b, w)) - (math.log10(rare_types + 1) if w is None else 0)
    return out


def test_ngram_scores_equal_brute_force(spark):
    r = np.random.default_rng(5)
    vocab = ["the", "cat", "sat", "on", "mat", "dog", "ran", *[f"r{i}" for i in range(30)]]
    texts = [" ".join(vocab[min(int(x), len(vocab) - 1)] for x in r.exponential(4, 12)) for _ in range(60)] + ["the cat sat on the mat", "Unseen words only", ""]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    train = [t for i, t in enumerate(texts) if zlib.crc32(str(i).encode()) % 5 != 1]
    use = ngram_lm.fold(F.col("doc_id"), 5) != 1
    got = {x.doc_id: x for x in ngram_lm.score_documents(docs, use).collect()}
    other = {x.doc_id: x.score for x in ngram_lm.score_documents(docs, use, mapped_bytes=-1, bucket_tokens=50).collect()}
    rarer = {x.doc_id: x.score for x in ngram_lm.score_documents(docs, use, least=2).collect()}
    c = Counter(w for t in train for w in [*ngram_lm.words_of(t.encode()), b""])
    n, v = sum(c.values()), len(c)
    for i, t in enumerate(texts):
        words = [*ngram_lm.words_of(t.encode()), b""]
        assert got[i].base_score == pytest.approx(sum(math.log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in words))
        assert got[i].n_tokens == len(words) and got[i].n_known == sum(c[w] > 0 for w in words) and got[i].train_tokens == n
        assert got[i].score == pytest.approx(brute(train, t), abs=1e-3 * len(words)) and other[i] == pytest.approx(got[i].score)
        assert rarer[i] == pytest.approx(brute(train, t, 2), abs=1e-3 * len(words))


def test_ngram_edges(spark):
    rows = [(1, None, "x"), (2, "", "x"), (3, "a\0b c", "x"), (3, "a\0b c", "x"), (4, "w " * 20000, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, ids string")
    got = ngram_lm.score_documents(docs, F.col("doc_id") > 2).collect()
    assert len(got) == 5 and all(math.isfinite(r.score) and math.isfinite(r.base_score) for r in got)
    none = ngram_lm.score_documents(docs, F.lit(False)).collect()
    assert len(none) == 5 and all(r.train_tokens == 0 and r.n_known == 0 for r in none)
    assert ngram_lm.score_documents(docs.limit(0), F.lit(True)).count() == 0


def test_held_out_text_beats_base(spark):
    got = ngram_lm.lm_scores(spark, SF).where("held_out").toPandas()
    assert (got.score > got.base_score).mean() > 0.95


def test_toxicity_on_held_out_rows(spark):
    docs, labels = tables(spark)
    got = toxicity_cnn.toxicity(spark, SF).toPandas().merge(labels.toPandas(), on="doc_id")
    held = got[got.held_out]
    flagged = held[held.predicted == 1]
    assert (flagged.toxic == 1).mean() > 0.8 and (flagged.toxic == 1).sum() >= 0.4 * held.toxic.sum()
    model = toxicity_cnn.fit(docs, labels, toxicity_cnn.learned_rows())
    odd = spark.createDataFrame([(1, None, None), (2, "", "en"), (3, "!!!", "zz"), (4, "so " * 30000 + "idiot", "en")], "doc_id long, text string, lang string")
    s = {r.doc_id: r.score for r in toxicity_cnn.classify(odd, model).collect()}
    assert s[1] == s[2] == s[3] and all(0 <= x <= 1 for x in s.values())
    empty = toxicity_cnn.fit(docs.limit(0), labels, toxicity_cnn.learned_rows())
    assert toxicity_cnn.classify(odd, empty).count() == 4 and toxicity_cnn.classify(odd.limit(0), model).count() == 0


def test_quality_on_held_out_rows(spark):
    docs, labels = tables(spark)
    got = cotraining.quality(spark, SF).toPandas().merge(labels.toPandas(), on="doc_id")
    held = got[got.held_out]
    assert (held.keep == (held.quality == 1)).mean() > 0.95 and held[held.quality == 1].keep.mean() > 0.98
    model = cotraining.fit(docs, labels)
    odd = spark.createDataFrame([(1, None, None, None, None), (2, "", "en", "s", -3), (3, "x " * 50000, "en", "s", 9)], "doc_id long, text string, lang string, source string, n_chars long")
    assert cotraining.classify(odd, model).where("score between 0 and 1").count() == 3
    none = cotraining.fit(docs, labels.limit(0))
    assert [r.score for r in cotraining.classify(odd, none).collect()] == [0.5] * 3


def test_views_teach_each_other():
    r = np.random.default_rng(0)
    n = 1200
    y = (r.random(n) < 0.5).astype(float)
    c = (y[:, None] * 2 - 1 + r.normal(0, 0.6, (n, 4))).astype(np.float32)
    m = (y[:, None] * 2 - 1 + r.normal(0, 0.6, (n, 3))).astype(np.float32)
    got = cotraining.co_train(c[:60], m[:60], y[:60], c[60:900], m[60:900], rounds=3, most=40)
    assert len(got.log) == 3 and all(x["content_to_metadata"] > 40 and x["metadata_to_content"] > 40 for x in got.log)
    z = m[900:] @ got.metadata[0]
    assert ((got.score(c[900:], m[900:])[2] >= 0.5) == (y[900:] == 1)).mean() > 0.97
    alone = cotraining.co_train(c[:60], m[:60], y[:60], c[:0], m[:0], rounds=0)
    assert ((z > 0) == y[900:]).mean() > 0.9 and ((got.score(c[900:], m[900:])[2] > 0.5) == y[900:]).mean() >= ((alone.score(c[900:], m[900:])[2] > 0.5) == y[900:]).mean() - 0.02


def test_a_rounds_choice_equals_brute_force():
    r = np.random.default_rng(4)
    for n, most in ((0, 3), (1, 1), (50, 7), (200, 30)):
        p = r.integers(0, 20, n) / 20  # with ties
        taken = {int(i): 1.0 for i in r.integers(0, max(n, 1), n // 5)}
        got = cotraining.surest(p, taken, most)
        free = [i for i in range(n) if i not in taken]
        mean = min(max(p.mean(), 1e-6), 1 - 1e-6) if n else 0.5
        want, used = [], set()
        for label, key, own in ((1.0, lambda i: (-p[i], i), mean), (0.0, lambda i: (p[i], i), 1 - mean)):
            size = max(1, round(most * own / max(mean, 1 - mean)))
            best = [i for i in sorted(free, key=key) if i not in used][:size]
            used.update(best)
            want += [(i, label) for i in best]
        assert got == want


def vectors(spark):
    r = np.random.default_rng(3)
    x = r.normal(size=(500, 16))
    hot = r.normal(size=16) + r.normal(0, 0.05, (400, 16))
    chain = [np.eye(16)[0]]
    for i in range(12):
        a = 0.42 * i
        chain.append(np.cos(a) * np.eye(16)[1] + np.sin(a) * np.eye(16)[2])
    return np.concatenate([x, hot, np.stack(chain), x[:5], x[:5] * 3])


def test_vectors_equal_brute_force(spark):
    x = vectors(spark)
    extra = [(9000, None), (9001, [0.0] * 16), (9002, [float("nan")] + [1.0] * 15), (9003, [None] + [1.0] * 15), (9004, [])]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)] + extra, "vec_id long, embedding array<double>")
    got = vector_graph.near_vectors(df, shard_rows=150)
    u = x / np.linalg.norm(x, axis=1)[:, None]
    hit = u @ u.T >= 0.9
    comp = list(range(len(x)))
    for i in range(len(x)):
        for j in np.flatnonzero(hit[i]):
            a, b = comp[i], comp[int(j)]
            comp = [min(a, b) if c in (a, b) else c for c in comp]
    rows = {r.vec_id: r for r in got.collect()}
    assert len(rows) == len(x) + 5
    found = sum(rows[i].n_links for i in range(len(x)))
    assert found >= 0.99 * (hit.sum() - len(x)) and all(rows[i].n_links <= hit[i].sum() - 1 for i in range(len(x)))
    assert np.mean([rows[i].component_id == comp[i] for i in range(len(x))]) > 0.99
    assert all(rows[i].n_links == 0 and rows[i].kept for i in range(9000, 9005))
    audit = vector_graph.audit_recall(df, got, every=10).toPandas()
    assert audit.found.sum() >= 0.9 * audit.exact.sum()
    assert vector_graph.near_vectors(df.limit(0)).count() == 0


def test_vectors_of_one_id(spark):
    """Rows that share an id keep links of their own; a component has the smallest id of its rows."""
    r = np.random.default_rng(8)
    x = r.normal(size=(40, 16))
    x[21] = x[4] + r.normal(0, 0.02, 16)
    x[33] = x[21]
    x[39] = x[38]
    ids = [i if i < 20 else 39 - i if i < 38 else 50 for i in range(40)]  # 20..37 repeat 19..2 with other vectors; 38 and 39 are one row twice
    df = spark.createDataFrame([(i, v.tolist(), "x", 1) for i, v in zip(ids, x, strict=True)], "vec_id long, embedding array<double>, node string, id int")
    u = x / np.linalg.norm(x, axis=1)[:, None]
    hit = u @ u.T >= 0.9
    assert hit[4].sum() == 3 and hit.sum() == 40 + 6 + 2
    want = sorted((k, int(h.sum()) - 1, min(ids[j] for j in np.flatnonzero(h))) for k, h in zip(ids, hit, strict=True))
    assert sorted((r.vec_id, r.n_links, r.component_id) for r in vector_graph.near_vectors(df).collect()) == want


def test_pipeline(spark):
    import corpus_pipeline as p

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    assert [k for k, _ in p.STAGES] == ["quality classifier", "toxicity", "SimHash near-dedup", "benchmark decontamination", "SentencePiece encoding and decoding"]
    bad = spark.createDataFrame([(10**6, None, None, None, None), (10**6 + 1, "", "en", "s", 0), (0, docs.first().text, "en", "src0", 5)], docs.schema)
    clash = docs.unionByName(bad).withColumn("score", F.lit(1)).withColumn("fp", F.lit("x"))
    seen = clash
    for _, stage in p.STAGES[:-1]:
        out = stage(spark, seen, SF)
        assert out.columns == clash.columns
        out.write.mode("overwrite").parquet("/tmp/revnet-test-stage")
        n = spark.read.parquet("/tmp/revnet-test-stage").count()
        assert 0 < n <= seen.count()
        from revnet.llm._common import materialize

        seen = materialize(spark.read.parquet("/tmp/revnet-test-stage"), "t")
    assert seen.groupBy("doc_id").count().where("count > 1").isEmpty()
    last = p.STAGES[-1][1](spark, seen, SF)
    assert last.count() == seen.count() and last.where("size(ids) <> n_tokens").isEmpty()
    assert p.STAGES[2][1](spark, docs.limit(0), SF).count() == 0


def test_every_repeated_word_has_an_id(spark):
    n = (1 << 21) + 1000
    counts = spark.range(n).select(F.col("id").cast("string").cast("binary").alias("word"), F.lit(2).cast("long").alias("c"))
    v = ngram_lm.build_vocabulary(counts)
    assert (v.ids > 0).all() and v.sums.size == n + 1 and ngram_lm.plan_shards(v.sums).wide
    k = np.array([[1, 5], [1, 2**63], [2**31, 0]], np.uint64)
    assert (ngram_lm._keys_in(ngram_lm._deltas(k), True) == k).all()


@pytest.mark.parametrize("common", [0, 3])
def test_large_word_tables_are_joined(spark, monkeypatch, common):
    monkeypatch.setattr(ngram_lm.encode_by_join, "__defaults__", (common,))
    r = np.random.default_rng(6)
    texts = [" ".join(f"r{int(x)}" for x in r.exponential(5, 15)) for _ in range(50)] + ["r0 r1 r0 unseen words only unseen", "", None]
    docs = spark.createDataFrame([*enumerate(texts), (0, texts[0])], "doc_id long, text string")
    use = ngram_lm.fold(F.col("doc_id"), 5) != 1
    want = sorted(tuple(x) for x in ngram_lm.score_documents(docs, use).collect())
    for limit in (400_000_000, -1):
        got = sorted(tuple(x) for x in ngram_lm.score_documents(docs, use, broadcast_words=2, mapped_bytes=limit, narrow=0).collect())
        assert len(got) == len(want) and all(x == pytest.approx(y) for x, y in zip(got, want, strict=True))
    none = ngram_lm.score_documents(docs, F.lit(False), broadcast_words=-1).collect()
    assert len(none) == len(texts) + 1 and all(x.n_known == 0 and x.train_tokens == 0 for x in none)


def test_links_across_many_shards(spark):
    r = np.random.default_rng(8)
    x = r.normal(size=(1000, 64))
    x /= np.linalg.norm(x, axis=1)[:, None]
    side = r.normal(size=x.shape)
    side -= (side * x).sum(1)[:, None] * x
    side /= np.linalg.norm(side, axis=1)[:, None]
    both = np.concatenate([x, 0.905 * x + np.sqrt(1 - 0.905**2) * side])
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(both)], "vec_id long, embedding array<double>")
    got = vector_graph.near_vectors(df, shard_rows=20, sample_rows=800).where("n_links > 0").count()
    assert got >= 0.99 * len(both)
    cents, link = vector_graph.centroids(both[::2][:800], 100), np.arccos(0.9)
    i, shard = vector_graph.probed_shards(both, np.zeros(len(both)), cents, link, 2)
    probed, near = set(zip(i.tolist(), shard.tolist(), strict=True)), (both @ cents.T).argmax(1)
    assert all((a, near[a + 1000]) in probed or (a + 1000, near[a]) in probed for a in range(1000))


def test_searches_of_a_shard_take_steps_together(monkeypatch):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(1500, 24))
    x[1000:1060] = x[5] + 0.05 * rng.normal(size=(60, 24))  # more in range than a list of 16 or 24 holds
    x /= np.sqrt((x * x).sum(1))[:, None]
    rad, reach = np.where(np.arange(1500) % 7 == 0, 0.1, 0.0), np.arccos(0.9) + 0.02 * rng.random(900)
    graph, met = vector_graph.ShardGraph(x, vector_graph.build_graph(x), rad), []
    product = np.einsum
    monkeypatch.setattr(np, "einsum", lambda s, a, b: met.append(len(a)) or product(s, a, b))
    q = np.concatenate([x[600:1050], x[600:1050] + 0.02 * rng.normal(size=(450, 24))])
    q /= np.sqrt((q * q).sum(1))[:, None]
    for own, width in ((np.where(np.arange(900) < 450, np.arange(600, 1500), -1), 16), (np.full(900, -1), 24)):
        row, node, angle = graph.search(q, reach, own, width)
        true = np.arccos(np.clip(q @ x.T, -1, 1))
        want = true <= reach[:, None] + rad[None, :]
        got = np.zeros_like(want)
        got[row, node] = True
        assert len(row) == got.sum() and not (got & ~want).any() and (got & want).sum() >= 0.99 * want.sum()
        assert np.allclose(angle, true[row, node], atol=1e-6)
        assert len(met) < 900 and sum(met) < 900 * 1500  # far fewer products than searches, and not all nodes are met
        met.clear()
    assert [len(c) for c in graph.search(q[:0], reach[:0], np.zeros(0, np.int64), 16)] == [0, 0, 0]
    lone = vector_graph.ShardGraph(x[:1], [[]], rad[:1])
    assert [c.tolist() for c in lone.search(x[:1], reach[:1], np.array([-1]), 24)[:2]] == [[0], [0]]


def test_searches_grow_no_faster_than_vectors(spark):
    r = np.random.default_rng(9)
    link, per = np.arccos(0.9), []
    for n in (2000, 16000):
        x = r.normal(size=(n, 64))
        x /= np.linalg.norm(x, axis=1)[:, None]
        fitted, apart = x[: 3 * n // 4], x[3 * n // 4 :]
        cents = vector_graph.centroids(fitted, n // 100)
        band = vector_graph.border_band(fitted, apart, cents, link, 2, draws=4000)
        assert band < link / 2
        per.append(len(vector_graph.probed_shards(x[-500:], np.zeros(500), cents, link, 2, band)[0]) / 500)
        side = r.normal(size=x.shape)
        side -= (side * x).sum(1)[:, None] * x
        y = 0.9 * x + np.sqrt(1 - 0.81) * side / np.linalg.norm(side, axis=1)[:, None]
        held = [np.argsort(-z @ cents.T, axis=1)[:, :2] for z in (x, y)]
        asked = [set(zip(*(a.tolist() for a in vector_graph.probed_shards(z, np.zeros(n), cents, link, 2, band)), strict=True)) for z in (x, y)]
        met = [any((i, h) in asked[0] for h in held[1][i].tolist()) or any((i, h) in asked[1] for h in held[0][i].tolist()) for i in range(n)]
        assert sum(met) >= 0.998 * n
    assert per[1] < 2 * per[0]  # eight times the shards


def test_toxicity_adds_the_new_words_of_a_text_at_once(monkeypatch):
    rng = np.random.default_rng(3)
    texts = [" ".join(f"w{i}" for i in rng.integers(0, 40, 12)) for _ in range(60)]
    model = toxicity_cnn.train(texts, np.arange(60) % 2.0, ["en"] * 60)
    calls, add = [], model._add
    monkeypatch.setattr(model, "_add", lambda *a: (calls.append(len(a[2])), add(*a)))
    words = toxicity_cnn.words(" ".join(f"w{i} v{i}" for i in range(5000)) + " w1 zz")
    x = model.embed(words)[toxicity_cnn.PAD : -toxicity_cnn.PAD]
    model.embed(words)
    assert calls == [10001] and len(model.vectors) >= 10001
    for i in (0, 1, 5000, 9999, 10001):
        cells = toxicity_cnn.buckets(words[i])
        own = [r for r in map(model.rows.get, cells) if r is not None]
        assert np.allclose(x[i], model.table[own].sum(0) / len(cells) if own else 0, atol=1e-6)


@pytest.mark.parametrize("limit", [400_000_000, -1])
@pytest.mark.parametrize("least", [1, 2])
def test_shards_of_common_words_lie_in_parts(spark, limit, least):
    r = np.random.default_rng(9)
    texts = [" ".join(f"r{int(x)}" if i % 2 else "the" for i, x in enumerate(r.exponential(5, 30))) for _ in range(60)] + ["the unseen the", "the the the r1", "", None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    use = ngram_lm.fold(F.col("doc_id"), 5) != 1
    want = {x.doc_id: x.score for x in ngram_lm.score_documents(docs, use, least=least).collect()}
    got = {x.doc_id: x.score for x in ngram_lm.score_documents(docs, use, least=least, mapped_bytes=limit, part_tokens=100).collect()}
    assert got == pytest.approx(want)


def test_parts_of_a_shard_bound_its_trigrams():
    n = 40_000
    plan = ngram_lm.plan_shards(ngram_lm.totals(3 * n, n + 1, 1, np.array([2 * n, 1]), np.array([1, n])), shard_tokens=1000, part_tokens=8000)
    s = int(plan.shard(np.array([1]))[0])
    a = np.arange(2, n)
    part = ngram_lm._part(a, plan.parts(s))
    assert plan.parts(s) == 11 and plan.tokens.sum() == 3 * n and np.bincount(part).max() < 1.2 * n / 11
    packed = [ngram_lm.pack(np.array(x)) for x in ([1, 200, 1 << 30], [], [5])]
    ids, many = ngram_lm.unpack_all(packed)
    assert ids.tolist() == [1, 200, 1 << 30, 5] and many.tolist() == [3, 0, 1]


def test_trigrams_of_a_context_look_it_up_once(monkeypatch):
    """A run of one context (b, a) is one search of the trie's left extensions, in any order of the runs."""
    from revnet.llm.elias_fano import TrieShard

    rng = np.random.default_rng(3)
    words, last = 60, 9
    tri = sorted({tuple(r) for r in np.stack([rng.integers(0, last + 1, 900), rng.integers(0, 25, 900), rng.integers(0, words, 900)], 1).tolist()})  # (b, a, c)
    big = sorted({(b, c) for b, _, c in tri} | {(3, 59), (4, 58)})
    nodes = sorted({(b, a) for b, a, _ in tri})
    where, of = {x: i for i, x in enumerate(big)}, {x: i for i, x in enumerate(nodes)}
    p2, weight, p3, gamma = (-rng.random(n) for n in (len(big), len(nodes), len(tri), last + 1))
    order = sorted(range(len(tri)), key=lambda i: (of[tri[i][:2]], where[tri[i][0], tri[i][2]]))
    cols = np.array([(of[tri[i][:2]], where[tri[i][0], tri[i][2]]) for i in order], np.int64).T
    shard = TrieShard(0, last, words, (*np.array(big, np.int64).T, p2), (*np.array(nodes, np.int64).T, weight), (*cols, p3[order]), gamma)
    prob = {t: p3[i] for i, t in enumerate(tri)}

    def want(b, a, c):
        low = p2[where[b, c]] if (b, c) in where else gamma[b] - 1.5
        return prob.get((b, a, c), low + (weight[of[b, a]] if (b, a) in of else 0))

    asked, find = [], shard.left.find
    monkeypatch.setattr(shard.left, "find", lambda v: asked.append(len(v)) or find(v))
    every = np.array([(b, a, c) for b in range(last + 1) for a in range(30) for c in range(words)], np.int64)
    for q in (every, rng.permutation(every)):
        b, a, c = q.T
        got = shard.log_prob(a, b, c, np.full(len(q), -1.5))
        assert np.allclose(got, [want(*r) for r in q.tolist()], atol=1e-6)
    assert asked[0] == (last + 1) * 30
    assert len(shard.log_prob(a[:0], b[:0], c[:0], np.zeros(0))) == 0
