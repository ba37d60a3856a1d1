"""Benchmark decontamination over a distributed positional inverted index, with DataFrame operators only.

The index holds one row per posting, ``(doc_id, pos, term_id)``, for the terms of the test items,
and one closing row per document whose position is its number of words. Phrases are found by
intersecting offset-adjusted posting lists, beginning with the rarest terms of a test window.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import materialize

SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
END = -1  # term_id of a document's closing row


def words_of(text: Column) -> Column:
    """Words of a text: only A-Z change case; every ASCII character but 0-9 and a-z separates. Null has none."""
    lower = F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(F.translate(text, _UPPER, _LOWER))
    return F.array_remove(F.split(F.coalesce(lower, F.lit("")), SEPARATORS), "")


def _small(df: DataFrame, limit: int) -> bool:
    """Whether ``df`` has at most ``limit`` rows; looks at no more than that."""
    return df.limit(limit + 1).count() <= limit


def _sized(df: DataFrame, limit: int) -> DataFrame:
    """``df`` with a broadcast hint if its row count is proven small; else as it is, for a shuffled join."""
    return F.broadcast(df) if _small(df, limit) else df


def vocabulary(items: DataFrame, text_col: str = "text") -> DataFrame:
    """Distinct terms of the items with numbers from 0, ``(term, term_id INT)``."""
    terms = items.select(F.explode(words_of(F.col(text_col))).alias("term")).distinct()
    return terms.selectExpr("term", "cast(row_number() over (order by term) - 1 as int) term_id")


def build_index(docs: DataFrame, vocab: DataFrame, id_col: str = "doc_id", text_col: str = "text", broadcast_rows: int = 1_000_000, carry: str | None = None) -> DataFrame:
    """Positional postings of the vocabulary's terms in all documents, stored: ``(doc_id, pos, term_id)``.

    Each row of ``docs`` adds a closing row with ``term_id`` -1 and its number of words as position.
    The closing rows keep the column named by ``carry`` as ``carried``; it is null in the others.
    """
    kept = [] if carry is None else [F.col(carry).alias("carried")]
    lookup = vocab.unionByName(vocab.sparkSession.createDataFrame([("", END)], "term string, term_id int"))
    tokens = docs.select(F.col(id_col).alias("doc_id"), *kept, F.posexplode(F.concat(words_of(F.col(text_col)), F.array(F.lit("")))).alias("pos", "term"))
    only = [F.when(F.col("term_id") == END, F.col("carried")).alias("carried")] if kept else []
    return materialize(tokens.join(_sized(lookup, broadcast_rows), "term").select("doc_id", "pos", "term_id", *only), "postings")


def item_windows(items: DataFrame, vocab: DataFrame, width: int = 13, id_col: str = "item_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """Windows of the items: terms by offset ``(wid, off, term_id, len)``, and owners ``(wid, item_id)``.

    An item of fewer words than ``width``, but not none, is one window. Equal windows are one.
    """
    w = items.select(F.col(id_col).alias("item_id"), words_of(F.col(text_col)).alias("w")).where(F.size("w") > 0)
    s = w.select("item_id", F.explode(F.sequence(F.lit(0), F.greatest(F.size("w") - width, F.lit(0)))).alias("s"), "w")
    s = s.select("item_id", F.slice("w", F.col("s") + 1, width).alias("t"))
    s = s.withColumn("wid", F.xxhash64(F.concat_ws(" ", "t"))).cache()
    terms = s.select("wid", "t").distinct().select("wid", F.size("t").alias("len"), F.posexplode("t").alias("off", "term"))
    return terms.join(vocab, "term").select("wid", "off", "term_id", "len"), s.select("wid", "item_id").distinct()


def phrase_matches(index: DataFrame, windows: DataFrame, rarest: int = 3, broadcast_rows: int = 1_000_000) -> DataFrame:
    """Exact occurrences ``(doc_id, wid, start, len)`` of the windows in the indexed documents."""
    windows = windows.cache()
    freq = index.where(f"term_id <> {END}").groupBy("term_id").agg(F.count(F.lit(1)).alias("freq"))
    # a window with a term that no document has can't occur
    ranked = windows.join(freq, "term_id").selectExpr("*", "row_number() over (partition by wid order by freq, off) rk", "count(*) over (partition by wid) present")
    ranked = ranked.where("present = len").select("wid", "off", "term_id", "len", "rk").cache()
    first = ranked.where(F.col("rk") <= rarest).select("wid", "off", "term_id", "len")
    lists = index.join(_sized(first, broadcast_rows), "term_id").select("doc_id", "wid", (F.col("pos") - F.col("off")).alias("start"), "len")
    # repeated ids repeat their postings, so this count only preselects: every offset is verified below
    met = lists.where("start >= 0").groupBy("doc_id", "wid", "start").agg(F.count(F.lit(1)).alias("n"), F.first("len").alias("len"))
    met = materialize(met.where(F.col("n") >= F.least("len", F.lit(rarest))).select("doc_id", "wid", "start", "len"), "phrase-candidates")
    need = met.join(ranked.select("wid", "off", "term_id"), "wid").select("doc_id", "wid", "start", (F.col("start") + F.col("off")).alias("pos"), "term_id")
    want = need.select("doc_id", "pos", "term_id").distinct()
    want = F.broadcast(want) if _small(want, broadcast_rows) else want
    there = index.join(want, ["doc_id", "pos", "term_id"], "left_semi").distinct().withColumn("there", F.lit(1))
    bad = need.join(there, ["doc_id", "pos", "term_id"], "left").where("there is null").select("doc_id", "wid", "start").distinct()
    return met.join(bad, ["doc_id", "wid", "start"], "left_anti")


def proximity_matches(index: DataFrame, queries: DataFrame, slop: int = 20, broadcast_rows: int = 1_000_000) -> DataFrame:
    """Places where all terms of a query stand near its rarest term: ``(qid, doc_id, pos, first, last)``.

    ``queries(qid, term_id)``; every other term must occur within ``slop`` words of ``pos``, in any
    order. ``first`` and ``last`` span the occurrences. Positions meet by cells of ``slop`` words.
    """
    q = queries.distinct()
    freq = index.where(f"term_id <> {END}").groupBy("term_id").agg(F.count(F.lit(1)).alias("freq"))
    ranked = q.join(freq, "term_id", "left").selectExpr(
        "qid", "term_id", "row_number() over (partition by qid order by coalesce(freq, 0), term_id) rk", "count(*) over (partition by qid) n"
    ).cache()
    anchor = index.join(_sized(ranked.where("rk = 1").select("qid", "term_id", "n"), broadcast_rows), "term_id").select("qid", "doc_id", "pos", "n").distinct()
    other = index.join(_sized(ranked.where("rk > 1").select("qid", "term_id"), broadcast_rows), "term_id")
    other = other.select("qid", "doc_id", "term_id", F.col("pos").alias("at"), F.expr(f"cast(pos div {slop} as int)").alias("cell")).distinct()
    cells = anchor.withColumn("cell", F.explode(F.expr(f"sequence(cast(pos div {slop} as int) - 1, cast(pos div {slop} as int) + 1)")))
    met = cells.join(other, ["qid", "doc_id", "cell"]).where(f"abs(at - pos) <= {slop}")
    met = met.groupBy("qid", "doc_id", "pos", "n").agg(F.countDistinct("term_id").alias("m"), F.min("at").alias("lo"), F.max("at").alias("hi")).where("m = n - 1")
    alone = anchor.where("n = 1").select("qid", "doc_id", "pos", F.col("pos").alias("first"), F.col("pos").alias("last"))
    return met.select("qid", "doc_id", "pos", F.least("pos", "lo").alias("first"), F.greatest("pos", "hi").alias("last")).unionByName(alone)


def contamination(docs: DataFrame, items: DataFrame, width: int = 13, share: int = 20, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """Per row of ``docs``: words, words hit by a window's occurrence, items met, and the verdict.

    A document is contaminated if words are hit and ``share`` times their number reaches all its
    words. Null and empty texts have no words and are clean; items without words have no windows;
    every row is judged by its own text, whether its id is repeated or null; null item ids are not listed. Either
    table may be empty. Other columns are ignored.
    """
    # rows are told apart by a number of their own, which is stored with the postings it was made for
    docs = docs.select(F.monotonically_increasing_id().alias("row"), F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    items = items.select(F.col(item_col).alias("item_id"), F.col(item_text).alias("text"))
    vocab = materialize(vocabulary(items), "vocabulary")
    index = build_index(docs, vocab, "row", "text", carry="id")
    windows, owners = item_windows(items, vocab, width)
    occ = materialize(phrase_matches(index, windows), "occurrences")
    before = "max(start + len) over (partition by doc_id order by start, len, wid rows between unbounded preceding and 1 preceding)"
    fresh = occ.selectExpr("doc_id", f"greatest(0, start + len - greatest(start, coalesce({before}, 0))) fresh")
    hit = fresh.groupBy("doc_id").agg(F.sum("fresh").alias("n_hit"))
    ids = occ.select("doc_id", "wid").distinct().join(_sized(owners, 1_000_000), "wid").select("doc_id", "item_id").where("item_id is not null").distinct()
    met = ids.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n_items"), F.concat_ws(",", F.array_sort(F.collect_list(F.col("item_id").cast("string")))).alias("items"))
    rows = index.where(f"term_id = {END}").select("doc_id", "carried", F.col("pos").cast("long").alias("n_words"))
    found = hit.join(met, "doc_id", "left")
    out = rows.join(_sized(found, 1_000_000), "doc_id", "left")
    n_hit = F.coalesce("n_hit", F.lit(0)).cast("long")
    return out.select(
        F.col("carried").alias(id_col), "n_words", n_hit.alias("n_hit"), F.coalesce("n_items", F.lit(0)).cast("long").alias("n_items"),
        F.coalesce("items", F.lit("")).alias("items"), ((n_hit > 0) & (share * n_hit >= F.col("n_words"))).alias("contaminated"),
    )


def decontamination(spark, sf_dir: str) -> DataFrame:
    """Query op4: contamination of every document by the benchmark."""
    out = contamination(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
    return out.select("doc_id", "n_words", "n_hit", "n_items", F.sha2(F.col("items").cast("binary"), 256).alias("items_sha256"), "contaminated")


SQL = rf"""
WITH d AS (
  SELECT doc_id, row_number() OVER () AS rid,
         regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM documents),
b AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w
  FROM benchmark),
bs AS (SELECT item_id, w, unnest(generate_series(0, greatest(len(w) - 13, 0))) AS s FROM b WHERE len(w) > 0),
bw AS (SELECT DISTINCT item_id, least(len(w), 13) AS l, array_to_string(w[s + 1 : s + 13], ' ') AS t FROM bs),
ls AS (SELECT DISTINCT l FROM bw),
ds AS (SELECT rid, l, w, unnest(generate_series(0, len(w) - l)) AS p FROM d, ls WHERE len(w) >= l),
dw AS (SELECT rid, l, p, array_to_string(w[p + 1 : p + l], ' ') AS t FROM ds),
occ AS (SELECT DISTINCT rid, p, dw.l AS l, item_id FROM dw JOIN bw ON dw.l = bw.l AND dw.t = bw.t),
hp AS (SELECT DISTINCT rid, unnest(generate_series(p, p + l - 1)) AS x FROM occ),
h AS (SELECT rid, count(*) AS n_hit FROM hp GROUP BY rid),
i AS (SELECT rid, count(*) AS n_items, string_agg(k, ',' ORDER BY k) AS ids
      FROM (SELECT DISTINCT rid, CAST(item_id AS VARCHAR) AS k FROM occ) GROUP BY rid)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit,
       CAST(coalesce(n_items, 0) AS BIGINT) AS n_items, sha256(coalesce(ids, '')) AS items_sha256,
       coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
FROM d LEFT JOIN h USING (rid) LEFT JOIN i USING (rid)
"""
