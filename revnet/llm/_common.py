"""Shared helpers of the corpus operators: written tables in the shared folder and connected components."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share.

    Where none is set, a folder of our own if all tasks run in this process (as in tests); on a
    cluster, whose executors could not read it, an error.
    """
    given = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not given:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        given = tempfile.mkdtemp(prefix="revnet-shared-")
        spark.sparkContext.setCheckpointDir(given)
    return given.rstrip("/")


def materialize(df: DataFrame, label: str, by: str | None = None) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder, in folders by a column if one is named, and read it back.

    Lineage ends at the written table, so a lost executor costs at most the tasks that it ran.
    Shuffle files of this execution are not used again and are removed when it ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    before = spark.conf.get(_CLEANUP, "false")
    try:
        spark.conf.set(_CLEANUP, "true")
        (df.write.partitionBy(by) if by else df.write).parquet(path)
    finally:
        spark.conf.set(_CLEANUP, before)
    out = spark.read.schema(df.schema).parquet(path)
    out._revnet_path = path
    return out


def discard(df: DataFrame, part: str = "") -> None:
    """Delete the table behind a frame that ``materialize`` returned, or one folder of it, once it is no longer read."""
    path = getattr(df, "_revnet_path", None)
    if path:
        path = f"{path}/{part}" if part else path
        spark = df.sparkSession
        jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
        jpath.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jpath, True)


def append_columns(docs: DataFrame, inputs: list[Column], fn: Callable[[], Callable[..., dict[str, pa.Array]]], schema: str, keep: list[str] | None = None, rows: int = 256) -> DataFrame:
    """``docs`` (or its columns ``keep``) with columns that Python computes from the ``inputs`` of each row.

    ``fn`` makes, once per task, a function of lists of input values that returns the new columns.
    Rows pass in slices of at most ``rows``, so that few Python objects are alive at a time.
    """
    keep = docs.columns if keep is None else keep
    n = len(inputs)
    slim = docs.select(*keep, *(c.alias(f"_in{i}") for i, c in enumerate(inputs)))
    out = StructType([*(slim.schema[c] for c in keep), *StructType.fromDDL(schema)])
    names = out.fieldNames()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = fn()
        for b in batches:
            for at in range(0, b.num_rows, rows):
                s = b.slice(at, rows)
                new = work(*(s.column(len(keep) + i).to_pylist() for i in range(n)))
                yield pa.RecordBatch.from_arrays([*(s.column(i) for i in range(len(keep))), *(new[x] for x in names[len(keep) :])], names=names)

    return slim.mapInArrow(run, out)


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Smallest node reachable from each node of ``edges(u, v)``: returns ``(node, component)``.

    Every round hooks each node below its smallest neighbour, follows the new parents until they
    are roots, then contracts the edges to roots and drops loops and repeats. Only minima are
    aggregated, so a node with very many neighbours is combined before the shuffle. Nulls are not
    allowed; nodes without an edge do not appear; no edges give an empty table.
    """
    e = edges.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).where("u < v").distinct()
    e = materialize(e, "cc-edges")
    labels = None
    for _ in range(max_rounds):
        if e.isEmpty():
            break
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        hook = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("x"), F.least("u", "m").alias("p"))
        hook = materialize(hook, "cc-hook")
        # parents are always smaller or the node itself, so following them ends at a root
        while True:
            up = hook.select(F.col("x").alias("p"), F.col("p").alias("pp"))
            jumped = materialize(hook.join(up, "p").select("x", F.col("pp").alias("p"), (F.col("pp") != F.col("p")).alias("moved")), "cc-jump")
            moved = not jumped.where("moved").isEmpty()
            discard(hook)
            hook = jumped.select("x", "p")
            hook._revnet_path = jumped._revnet_path
            if not moved:
                break
        left = hook.select(F.col("x").alias("u"), F.col("p").alias("pu"))
        right = hook.select(F.col("x").alias("v"), F.col("p").alias("pv"))
        contracted = (
            e.join(left, "u").join(right, "v")
            .select(F.least("pu", "pv").alias("u"), F.greatest("pu", "pv").alias("v"))
            .where("u < v").distinct()
        )
        contracted = materialize(contracted, "cc-edges")
        if labels is None:
            new = hook.select(F.col("x").alias("node"), F.col("p").alias("component"))
        else:
            step = hook.select(F.col("x").alias("component"), F.col("p").alias("root"))
            new = labels.join(step, "component", "left").select("node", F.coalesce("root", "component").alias("component"))
        old = labels
        labels = materialize(new, "cc-labels")
        for x in (old, e, hook):
            if x is not None:
                discard(x)
        e = contracted
    else:
        raise RuntimeError("connected components did not settle")
    if labels is None:
        return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).where("1 = 0")
    return labels
