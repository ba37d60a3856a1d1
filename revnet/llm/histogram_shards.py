"""Sharding by histogram sort: exact byte counts below candidate keys fix the splitters before one exchange.

Every row has a 63-bit sort key: 32 bits hashed from its text, 31 from its id. The bytes of all rows
are counted by key prefix; only prefixes in which a splitter still lies are counted again, with more
bits, until each splitter's deviation is within the tolerance. Splitters that settle within the
first 32 bits never part equal texts; larger groups of equal texts are parted by id.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import materialize

KEY_BITS = 63
GROUP_BITS = 32
OVERHEAD = 8  # bytes a row costs beside its text


def sort_key(id_col: Column, text_col: Column) -> Column:
    """Non-negative LONG: hash of the text in the high bits, hash of the id in the low ones."""
    high = F.shiftrightunsigned(F.xxhash64(text_col), 32)
    low = F.shiftrightunsigned(F.xxhash64(F.lit("id"), id_col), 33)
    return F.shiftleft(high, 31).bitwiseOR(low)


def find_splitters(keys: DataFrame, shards: int, tiles: int = 1, tolerance: float = 0.002) -> tuple[np.ndarray, list[dict]]:
    """Splitters of ``keys(key, size)`` into ``shards * tiles`` ranges, and a log of the rounds.

    Row ``k`` belongs to range r if exactly r splitters are <= k. Every ``tiles``-th splitter
    borders a shard and must be within ``tolerance`` of an even shard; the others within half a tile.
    A round's result on the driver is bounded by splitters times probes, whatever the row count.
    """
    parts = shards * tiles
    first = max(12, int(np.ceil(np.log2(8 * parts))))
    got = keys.groupBy(F.shiftright("key", KEY_BITS - first).alias("b")).agg(F.sum("size").alias("bytes")).toArrow().to_pandas().sort_values("b")
    total = int(got["bytes"].sum())
    target = total * np.arange(1, parts) / parts
    border = np.arange(1, parts) % tiles == 0
    allowed = np.where(border, tolerance * total / shards, 0.5 * total / parts)
    lo_key = np.zeros(parts - 1, np.int64)  # best border so far
    error = np.full(parts - 1, np.inf)
    below = np.zeros(parts - 1)  # bytes below the prefix that is being divided
    prefix = np.zeros(parts - 1, np.int64)
    depth, log = 0, []
    bits = first
    while True:
        depth += bits
        shift = KEY_BITS - depth
        open_ = np.flatnonzero(error > allowed)
        b, size = got["b"].to_numpy(np.int64), got["bytes"].to_numpy(np.float64)
        for i in open_:
            at, stop = np.searchsorted(b, prefix[i] << bits), np.searchsorted(b, (prefix[i] + 1) << bits)
            if at == stop:
                error[i] = min(error[i], abs(below[i] - target[i]))
                allowed[i] = np.inf
                continue
            ends = below[i] + np.cumsum(size[at:stop])
            j = min(int(np.searchsorted(ends, target[i], side="left")), stop - at - 1)
            start = ends[j] - size[at + j]
            for bytes_below, key in ((start, b[at + j] << shift), (ends[j], (b[at + j] + 1) << shift)):
                if abs(bytes_below - target[i]) < error[i]:
                    error[i], lo_key[i] = abs(bytes_below - target[i]), min(key, np.iinfo(np.int64).max)
            prefix[i], below[i] = b[at + j], start
        left = np.flatnonzero(error > allowed)
        log.append({"bits": depth, "open": len(left), "worst": float(error.max(initial=0))})
        if not len(left) or depth >= KEY_BITS:
            break
        bits = min(12, (GROUP_BITS if depth < GROUP_BITS else KEY_BITS) - depth)
        wanted = [int(x) for x in np.unique(prefix[left])]
        got = (
            keys.where(F.shiftright("key", shift).isin(wanted))
            .groupBy(F.shiftright("key", shift - bits).alias("b")).agg(F.sum("size").alias("bytes")).toArrow().to_pandas().sort_values("b")
        )
    return np.maximum.accumulate(lo_key), log


def range_of(key: Column, splitters: np.ndarray) -> Column:
    """Number of splitters <= key: a balanced tree of comparisons, or a binary search in Arrow batches if there are many."""
    if len(splitters) > 255:
        return F.pandas_udf(lambda k: pd.Series(np.searchsorted(splitters, k.to_numpy(), side="right").astype(np.int32)), "int")(key)

    def node(a: int, z: int) -> Column:
        if a == z:
            return F.lit(a)
        m = (a + z) // 2
        return F.when(key >= F.lit(int(splitters[m])), node(m + 1, z)).otherwise(node(a, m))

    return node(0, len(splitters))


def histogram_shards(docs: DataFrame, shards: int = 24, id_col: str = "doc_id", text_col: str = "text", tolerance: float = 0.002, tile_bytes: int = 16 << 20, max_tiles: int = 2048) -> DataFrame:
    """All rows and columns of ``docs`` with ``size``, ``shard`` and ``slot`` (gapless from 0 in each shard).

    Size is the text's UTF-8 bytes (null: none) plus 8. Shards are ranges of the sort key of nearly
    equal bytes; equal texts stay together unless their group is larger than the tolerance allows.
    Ties (repeated rows) are in any order; an empty table gives an empty result. Columns named
    size, shard or slot are replaced. Each shard is sorted in tiles of about ``tile_bytes`` (larger
    ones where more than ``max_tiles`` would be needed), whose row counts give the first slots, so that no task ever holds a whole shard.
    """
    size = F.coalesce(F.octet_length(text_col), F.lit(0)).cast("long") + OVERHEAD
    key = sort_key(F.col(id_col), F.col(text_col))
    keys = materialize(docs.select(key.alias("key"), size.alias("size")), "shard-keys")
    total = keys.agg(F.sum("size").alias("s")).first().s or 0
    tiles = min(max_tiles, max(1, -(-total // (shards * tile_bytes))))
    splitters, _ = find_splitters(keys, shards, tiles, tolerance)
    rows = dict(keys.groupBy(range_of(F.col("key"), splitters).alias("t")).agg(F.count(F.lit(1)).alias("n")).toArrow().to_pandas().itertuples(index=False))
    counts = np.array([rows.get(t, 0) for t in range(shards * tiles)]).reshape(shards, tiles)
    first = (np.cumsum(counts, 1) - counts).ravel()
    tile = range_of(F.col("_key"), splitters)
    out = docs.drop("size", "shard", "slot").withColumns({"size": size, "_key": key}).withColumn("_tile", tile)
    base = F.lit(first.tolist())[F.col("_tile")]
    order = F.expr(f"row_number() over (partition by _tile order by _key, `{id_col}`) - 1")
    return out.withColumn("_row", order).withColumns({"shard": (F.col("_tile") / tiles).cast("int"), "slot": (base + F.col("_row")).cast("long")}).drop("_key", "_tile", "_row")


def sharded(spark, sf_dir: str) -> DataFrame:
    """Query op1: all documents in 24 shards of near-equal bytes."""
    out = histogram_shards(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
    return out.select(
        "doc_id", "size", F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32"), F.lit("bytes").alias("law"),
        "shard", "slot", F.lit(None).cast("int").alias("grown_shard"),
    )
