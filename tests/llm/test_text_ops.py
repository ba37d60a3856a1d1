"""Text operators against brute force, the libraries they must equal, and defined edge cases."""

import hashlib
import json
import math
import random
import zlib
from pathlib import Path

import duckdb
import numpy as np
import pandas as pd
import pyarrow.parquet as pq
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st

from revnet.llm import decontaminate, histogram_shards, licences, sentencepiece_bpe, simhash, site_style_tree
from revnet.llm._common import connected_components

LONG = "wort " * 30_000
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, fp long, score double, shard int, keep boolean"
EDGE = [
    (1, None, None, None, None, 1, 0.5, 3, True), (2, "", "en", "s", 0, 1, 0.5, 3, True), (3, " \n\t ", "en", "s", 4, 1, 0.5, 3, True),
    (4, LONG, "de", "s", len(LONG), 1, 0.5, 3, True), (5, "a b c d e f", "en", None, 11, None, None, None, None),
    (6, "a b c d e f", "en", "s", 11, 1, 0.5, 3, True), (6, "a b c d e f", "en", "s", 11, 1, 0.5, 3, True), (7, "A B\tC  d e f", "en", "s", 11, 1, 0.5, 3, True),
]


@pytest.fixture(scope="module")
def edge(spark):
    return spark.createDataFrame(EDGE, SCHEMA)


# --- connected components, SimHash ---


@pytest.mark.parametrize("edges", [[], [(1, 2)], [(i, i + 1) for i in range(40)], [(0, i) for i in range(1, 60)], [(5, 5), (2, 1), (1, 2), (3, 9), (9, 2)]])
def test_components(spark, edges):
    root = {}
    find = lambda x: x if root.setdefault(x, x) == x else find(root[x])
    for a, b in edges:
        a, b = sorted((find(a), find(b)))
        root[b] = a
    want = {x: find(x) for e in edges if e[0] != e[1] for x in e}
    got = connected_components(spark.createDataFrame(edges, "u long, v long"))
    assert {r.node: r.component for r in got.collect()} == want


def slow_fingerprint(text):
    words = (text or "").encode().lower().split()
    sh = [b" ".join(words[i : i + 3]) for i in range(len(words) - 2)] if len(words) >= 3 else [b" ".join(words)] if words else []
    h = [xxhash.xxh64_intdigest(s, 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


@given(st.text(alphabet="abAB é\n\t\x85", max_size=40))
@settings(max_examples=200, deadline=None)
def test_fingerprints(text):
    assert simhash.fingerprint(text.encode()) == slow_fingerprint(text)


def test_xxhash_is_sparks(spark):
    got = spark.sql("select xxhash64('a b c') h").first().h
    assert got % 2**64 == xxhash.xxh64_intdigest(b"a b c", 42)


@pytest.mark.parametrize("parts", [2, 3, 4])
def test_links_equal_brute_force(spark, parts):
    r = random.Random(parts)
    base = [r.getrandbits(64) for _ in range(60)]
    fps = set(base)
    for b in base[:30]:
        for _ in range(12):
            x = b
            for _ in range(r.randint(1, 3)):
                x ^= 1 << r.randrange(64)
            fps.add(x)
    fps |= {base[0] ^ (1 << i) for i in range(64)}  # a dense ball
    arr = np.array(sorted(fps), np.uint64)
    df = spark.createDataFrame(pd.DataFrame({"fp": arr.view(np.int64)}))
    index = {int(x): i for i, x in enumerate(arr.view(np.int64))}
    for heavy in (4096, 8):
        parent = list(range(len(arr)))

        def find(x, parent=parent):
            while parent[x] != x:
                x = parent[x]
            return x

        for row in simhash.link_forest(df, 3, parts, heavy).collect():
            a, b = index[row.fa], index[row.fb]
            assert bin((row.fa ^ row.fb) & (2**64 - 1)).count("1") <= 3
            parent[find(a)] = find(b)
        want = list(range(len(arr)))
        for i in range(len(arr)):
            for j in np.flatnonzero(np.bitwise_count(arr[i + 1 :] ^ arr[i]) <= 3):
                want[find(i, want)] = find(i + 1 + int(j), want)
        got = pd.Series([find(i) for i in range(len(arr))])
        exp = pd.Series([find(i, want) for i in range(len(arr))])
        assert (got.groupby(exp).nunique() == 1).all() and got.nunique() == exp.nunique()


def test_allocation_is_optimal():
    r = np.random.default_rng(0)
    costs = [r.random((20, 4)) * 10 for _ in range(4)]
    got = simhash.allocate(costs, 0)
    assert (got.sum(1) == 0).all()
    import itertools

    for row in range(20):
        best = min(sum(c[row, t + 1] for c, t in zip(costs, ts)) for ts in itertools.product(range(-1, 3), repeat=4) if sum(ts) == 0)
        assert sum(c[row, t + 1] for c, t in zip(costs, got[row])) == pytest.approx(best)


def test_simhash_edges(spark, edge):
    got = simhash.simhash_components(edge).collect()
    assert len(got) == len(EDGE)
    comp = {}
    for r in got:
        comp.setdefault(r.doc_id, set()).add(r.component_id)
    assert comp[1] == comp[2] == comp[3] == {1} and comp[5] == comp[6] == comp[7] == {5}
    assert simhash.simhash_components(edge.limit(0)).count() == 0


# --- sharding ---


def test_shards(spark):
    r = random.Random(2)
    rows = [(i, "x" * r.randint(0, 4000)) for i in range(3000)] + [(10_000 + i, "copy" * 50) for i in range(1500)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = histogram_shards.histogram_shards(docs, 12, tolerance=0.01, tile_bytes=100_000).toPandas()
    per = got.groupby("shard")["size"].sum()
    assert len(got) == len(rows) and per.max() - per.min() <= 0.03 * per.mean() + 5000
    for _, g in got.groupby("shard"):
        assert sorted(g.slot) == list(range(len(g)))
    assert (got["size"] == got.text.str.len() + 8).all()


def test_shards_keep_small_groups_whole(spark):
    rows = [(i, f"text {i // 3} " * 20) for i in range(6000)]
    got = histogram_shards.histogram_shards(spark.createDataFrame(rows, "doc_id long, text string"), 4, tolerance=0.02).toPandas()
    assert (got.groupby("text").shard.nunique() == 1).all()


def test_shards_edges(spark, edge):
    got = histogram_shards.histogram_shards(edge, 3).toPandas()
    assert len(got) == len(EDGE) and sorted(got.columns) == sorted([*edge.columns, "size", "slot"])
    assert histogram_shards.histogram_shards(edge.limit(0), 3).count() == 0
    many = histogram_shards.find_splitters(edge.selectExpr("doc_id * 1000003 as key", "8L as size"), 300)[0]
    import pyspark.sql.functions as F

    k = edge.select(F.col("doc_id"), histogram_shards.range_of(F.col("doc_id") * 1000003, many).alias("t")).collect()
    assert all(r.t == int((many <= r.doc_id * 1000003).sum()) for r in k)


# --- decontamination ---


def test_contamination_matches_sql_on_fixtures(spark, tmp_path):
    w = [f"w{i}" for i in range(40)]
    items = [(1, " ".join(w[:20])), (2, "kurz und gut"), (3, ""), (4, None), (5, " ".join(w[10:30]).upper()), (6, "Émile É-é x1")]
    docs = [
        (1, " ".join(w)), (2, "a " * 100 + " ".join(w[3:16])), (3, None), (4, ""), (5, "KURZ, und-gut!"), (6, " ".join(w[:12])), (7, "x " + " ".join(w[5:25]) + " y " + " ".join(w[5:25])),
        (8, "émile é é x1"), (9, "Émile É é X1 kurz und gut"), (9, "Émile É é X1 kurz und gut"), (10, "the " * 500 + "kurz und gut"),
        (11, "kurz und gut"), (11, "lang und gut " * 9), (11, None), (None, "kurz und gut"), (None, "ganz ohne " + " ".join(w[:13])), (None, "nichts"), (None, None),
    ]
    d, b = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    pq.write_table(d.toArrow(), tmp_path / "documents.parquet")
    b.toPandas().to_parquet(tmp_path / "benchmark.parquet")
    con = duckdb.connect()
    for t in ("documents", "benchmark"):
        con.sql(f"create view {t} as select * from read_parquet('{tmp_path}/{t}.parquet')")
    got = decontaminate.decontamination(spark, str(tmp_path)).toPandas()
    want = con.sql(decontaminate.SQL).df()
    key = lambda x: sorted(map(tuple, x[sorted(x.columns)].astype({"doc_id": "Int64"}).astype(str).values.tolist()))
    assert key(got) == key(want)
    assert got.set_index("doc_id").contaminated.loc[5] and not got.set_index("doc_id").contaminated.loc[10]
    assert got[got.doc_id == 11].contaminated.sum() == 1 and got[got.doc_id.isna()].contaminated.sum() == 2


def test_contamination_edges(spark, edge):
    items = spark.createDataFrame([(1, "a b c")], "item_id long, text string")
    assert decontaminate.contamination(edge, items).count() == len(EDGE)
    assert decontaminate.contamination(edge.limit(0), items).count() == 0
    none = decontaminate.contamination(edge, items.limit(0)).collect()
    assert len(none) == len(EDGE) and not any(r.contaminated for r in none)


def test_proximity(spark):
    docs = spark.createDataFrame([(1, "alpha x x beta x gamma"), (2, "alpha" + " x" * 30 + " beta gamma"), (3, "gamma beta alpha")], "doc_id long, text string")
    items = spark.createDataFrame([(1, "alpha beta gamma")], "item_id long, text string")
    vocab = decontaminate.vocabulary(items)
    index = decontaminate.build_index(docs, vocab)
    q = vocab.selectExpr("1 as qid", "term_id")
    assert {r.doc_id for r in decontaminate.proximity_matches(index, q, slop=6).collect()} == {1, 3}


# --- SentencePiece ---


@pytest.fixture(scope="module")
def bpe():
    import sentencepiece

    path = sentencepiece_bpe.default_model()
    return sentencepiece_bpe.Bpe(path), sentencepiece.SentencePieceProcessor(model_file=path)


@given(st.text(alphabet=st.one_of(st.sampled_from(" \n▁aeinrst'.<>/0x"), st.characters(exclude_categories=["Cs"])), max_size=60))
@settings(max_examples=400, deadline=None)
def test_bpe_equals_library(bpe, text):
    own, lib = bpe
    ids = own.encode(text)
    assert ids == lib.encode(text) and own.decode(ids) == lib.decode(ids)
    assert own.encode_joined(text) == (",".join(map(str, ids)), lib.decode(ids))


def test_bpe_decodes_any_bytes(bpe):
    own, lib = bpe
    r = random.Random(1)
    for _ in range(300):
        ids = [r.choice([3 + r.randrange(256), r.randrange(3, 32000)]) for _ in range(6)]
        assert own.decode(ids) == lib.decode(ids)


def test_encoding_query(spark, edge, bpe):
    out = sentencepiece_bpe.encode_documents(edge, outputs=("ids", "decoded", "ids_sha256", "decoded_sha256"), store=2).collect()
    assert len(out) == len(EDGE)
    texts = {r[0]: r[1] or "" for r in EDGE}
    for r in out:
        want = bpe[1].encode(texts[r.doc_id])
        assert r.ids == want and r.n_tokens == len(want) and r.decoded == texts[r.doc_id]
        assert r.ids_sha256 == hashlib.sha256(",".join(map(str, want)).encode()).hexdigest()


# --- licences, HTML ---


def test_licences(spark, edge):
    mit = next(t for k, kind, t in licences.KNOWN if k == "MIT" and kind == "text")
    docs = spark.createDataFrame(
        [(1, "Copyright (c) 2020 Somebody\n\n" + mit.replace("sublicense", "sub-licence").upper()), (2, "prose\n  Released under the MIT Licence!\nmore"), (3, "Released under no licence"), (4, None), (5, mit + " extra")],
        "doc_id long, text string",
    )
    got = {r.doc_id: (r.whole_licence, r.licences, r.n_lines) for r in licences.scan(docs).collect()}
    assert got[1][0] == "MIT" and got[2] == (None, ["MIT"], 1) and got[3] == got[4] == (None, [], 0) and got[5][0] is None
    assert licences.scan(edge).count() == len(EDGE) and licences.scan(edge.limit(0)).count() == 0
    again = docs.union(docs.where("doc_id = 2")).union(spark.createDataFrame([(None, "Released under the MIT License.")], "doc_id long, text string"))
    more = [(r.doc_id, r.whole_licence, r.n_lines) for r in licences.scan(again, broadcast_rows=0).collect()]
    assert more.count((2, None, 1)) == 2 and more.count((None, "MIT", 1)) == 1
    two = spark.createDataFrame([(d, x) for d, _, _ in licences.known_digests([("A", "text", "shared words")]) for x in ("B", "A")], "digest string, licence string")
    assert licences.scan(spark.createDataFrame([(1, "Shared, words\nother")], "doc_id long, text string"), two).first().licences == ["A", "B"]


def test_full_licence_texts(spark):
    folder = Path("/usr/share/common-licenses")
    if not (folder / "GPL-3").exists():
        pytest.skip("no licence texts here")
    texts = [(i, (folder / f).read_text(encoding="utf-8")) for i, f in enumerate(("GPL-3", "Apache-2.0", "MPL-2.0", "LGPL-2.1"))]
    odd = [(i, "Copyright 2020 Somebody\n" + t.upper().replace(",", " ;")) for i, t in texts]
    got = {r.doc_id: r.whole_licence for r in licences.scan(spark.createDataFrame(odd, "doc_id long, text string")).collect()}
    assert got == {0: "GPL-3.0", 1: "Apache-2.0", 2: "MPL-2.0", 3: "LGPL-2.1"}


PAGE = (
    "<!doctype html><html><head><title>t</title><script>var a='<p>no</p>'</script></head><body><nav><ul><li>menu</ul></nav><div class='ad'>buy</div>"
    "<article><h1>Head&amp;line</h1><p>One <b>bold\n word<br>next<p>Two&nbsp;x &lt;3</p><div class='comments'>first!</div><ul><li>a<li>b</ul></article><footer>foot</footer></body></html>"
)


def test_main_text():
    assert site_style_tree.main_text(PAGE) == "Head&line\nOne bold word next\nTwo x <3\na\nb"
    assert site_style_tree.main_text(None) == site_style_tree.main_text("") == ""
    assert site_style_tree.main_text("<div>plain <i>text</i></div><form>f</form>") == "plain text"


def test_repeated_branches_go(spark):
    pages = [(i, f"http://h.org/{i}", f"<body><div class='x{j}'><section>Same words on all pages.</section><div><p>Own words {i} and {i * 7}, quite some of them.</p></div></div></body>") for i in range(20) for j in (1,)]
    pages += [(100, "http://other.org/", pages[0][2]), (101, None, None), (102, "http://h.org/z", "")]
    got = {r.page_id: r.text for r in site_style_tree.extract(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert got[3] == "Own words 3 and 21, quite some of them." and got[100].startswith("Same words") and got[101] == got[102] == ""
    copies = spark.createDataFrame([(i, "http://c.org/", "<article><p>A whole page copied.</p></article>") for i in range(30)], "page_id long, url string, html string")
    assert {r.text for r in site_style_tree.extract(copies).collect()} == {"A whole page copied."}


def test_importances_equal_brute_force(spark):
    r = random.Random(3)
    body = lambda i: "<body>" + "".join(f"<div class='{c}'>{t}</div>" for c, t in (("a", "<ul>" + "<li>one</li><li>two</li>" * r.randint(1, 2) + "</ul>"), ("b", r.choice(["x", "y"])), ("c", f"<p>own {i}</p><p>{r.choice('uv')}</p>tail"))[: r.randint(1, 3)]) + "</body>"
    pages = sorted({body(i) for i in range(24)})  # copies would count as one
    seen: dict = {}
    for page in pages:
        for x in {(k, p, v, t) for k, p, _, v, t in site_style_tree.merged_places(site_style_tree.parse(page))}:
            seen[x] = seen.get(x, 0) + 1

    def value(place):
        m = math.log(next(n for (k, p, _, _), n in seen.items() if (k, p) == ("n", place)) + site_style_tree.PRIOR)
        own = [n for (k, p, _, _), n in seen.items() if (k, p) == ("c", place)]
        leaf = 1 - (sum(n * math.log(n) for n in own) / sum(own) if own else 0) / m
        styles = {v: n for (k, p, v, _), n in seen.items() if (k, p) == ("s", place)}
        if not styles:
            return leaf
        total, mean = sum(styles.values()), 0.0
        for style, n in styles.items():
            kids = {p for (k, p, v, _) in seen if k == "n" and v == style}
            mean += n / total * (sum(map(value, kids)) / len(kids) if kids else leaf)
        g = site_style_tree.GAMMA ** len(styles)
        return (1 - g) * (-sum(n / total * math.log(n / total) for n in styles.values()) / m) + g * mean

    df = spark.createDataFrame([(f"http://h.org/{i}", x) for i, x in enumerate(pages)], "url string, html string")
    got = {x.place: x.importance for x in site_style_tree.importances(site_style_tree.style_trees(df)).collect()}
    assert len(got) > 8 and all(got[p] == pytest.approx(value(p), abs=1e-5) for p in got)


def test_pages_of_any_shape(spark):
    deep = "<div>" * 100_000 + "<p>far down</p>" + "</div>" * 100_000
    long_ = "<article>" + "<p>some words</p>" * 20_000 + "</article>"
    rows = [(1, "http://h.org/1", deep, "a", "b", 7), (2, "http://h.org/2", long_, "a", "b", 7), (2, "http://h.org/2", long_, "a", "b", 7), (3, None, None, None, None, None)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, host string, drop string, n long")
    got = sorted(site_style_tree.extract(df).collect(), key=lambda r: r.page_id)
    assert [r.text for r in got] == ["far down", "\n".join(["some words"] * 20_000), "\n".join(["some words"] * 20_000), ""]
    assert got[0].host == "a" and got[0].drop == "b" and got[0].n == 7 and got[3].n_chars == 0
    assert site_style_tree.extract(df.limit(0)).count() == 0


def test_repeated_lines_go_and_headlines_stay(spark):
    page = lambda i: f"<body><div class='top'>Notice: <div>we use things</div></div><div class='m'><a>Home</a> <ul><li>News</li><li>Mail</li></ul></div><article><h1>Same head</h1><p>text {i} of its own</p><div>Read all about it</div></article></body>"
    rows = [(i, f"http://h.org/{i}", page(i)) for i in range(30)] + [(99, "http://lone.org/", page(99))]
    got = {r.page_id: r.text for r in site_style_tree.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[4] == "Same head\ntext 4 of its own" and got[99] == "Same head\ntext 99 of its own\nRead all about it"
    plain = [(i, f"http://p.org/{i}", f"<body><div class='x'>Notice: <div>we use things</div></div><div><p>text {i}</p></div></body>") for i in range(30)]
    got = {r.page_id: r.text for r in site_style_tree.extract(spark.createDataFrame(plain, "page_id long, url string, html string")).collect()}
    assert got[4] == "text 4"


def test_tables_have_integer_ids(spark):
    assert json.dumps(zlib.crc32(b"1")) == str(spark.sql("select crc32(cast('1' as binary)) c").first().c)
