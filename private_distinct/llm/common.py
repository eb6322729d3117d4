"""Helpers shared by the training-data operators: shared scratch tables, components, row numbers."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Only a local session (one machine, as in tests) may go without the setting.
    """
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    made = f"file://{tempfile.mkdtemp(prefix='shared-')}"
    spark.conf.set("spark.checkpoint.dir", made)
    return made


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(folder)  # what no step discards goes with the driver
    return spark.read.schema(df.schema).parquet(path)


def discard(*tables: DataFrame) -> None:
    """Delete materialised tables that no later plan reads."""
    for table in tables:
        jvm, sc = table.sparkSession.sparkContext._jvm, table.sparkSession.sparkContext
        for f in table.inputFiles()[:1]:
            folder = jvm.org.apache.hadoop.fs.Path(f).getParent()
            folder.getFileSystem(sc._jsc.hadoopConfiguration()).delete(folder, True)


def free_shuffles(spark: SparkSession) -> None:
    """Let the driver's collector free shuffle files that nothing refers to, before the next large step."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def give_back_memory() -> None:
    """Return to the system what a reused worker holds of earlier tasks' freed memory."""
    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of glibc only
    if trim:
        trim(0)


@contextmanager
def small_batches(spark: SparkSession, rows: int):
    """Batches of at most ``rows`` rows between JVM and Python, for what is run inside: whole texts make large ones."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(min(rows, int(before)) if int(before) > 0 else rows))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def numbered(df: DataFrame, group: list[str], order: list[str], name: str) -> DataFrame:
    """Gapless numbers from 0 within ``group``, without putting a whole group into one task.

    Rows are dealt over (group, bucket); a small table of counts gives each bucket its first number.
    ``df`` should be a materialised table, as it is read twice.
    """
    spark = df.sparkSession
    buckets = max(16, partitions(spark))
    df = df.withColumn("_bucket", F.pmod(F.xxhash64(*order), F.lit(buckets)))
    keys = [*group, "_bucket"]
    before = Window.partitionBy(*group).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    first = df.groupBy(*keys).agg(F.count(F.lit(1)).alias("_n"))
    first = first.select(*keys, F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_first"))
    inner = F.row_number().over(Window.partitionBy(*keys).orderBy(*order))
    return (
        df.withColumn("_row", inner)
        .join(first, keys)
        .withColumn(name, F.col("_first") + F.col("_row") - F.lit(1))
        .drop("_bucket", "_row", "_first")
    )


def connected_components(edges: DataFrame, tag: str = "cc") -> DataFrame:
    """(node, root) of every node of ``edges(a, b)``; root is the least node reachable.

    Alternating large-star and small-star rounds.  Only joins and combinable minima: no adjacency list is ever
    gathered.  Minima are written before they are joined, so that both sides of a join are plain exchanges and a
    hub's rows can be split over tasks.
    """
    e = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct()
    e = materialise(e, tag)
    mark = None
    while True:
        now = tuple(e.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v"))).first())
        if now == mark or now[0] == 0:
            out = materialise(e.select(F.col("u").alias("node"), F.col("v").alias("root")).union(e.select("v", "v")).distinct(), tag)
            discard(e)
            return out
        mark = now
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = materialise(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m")), tag)
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        again = materialise(large.groupBy("u").agg(F.min("v").alias("m")), tag)
        small = large.join(again, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        new = materialise(small.union(again).where("u <> v").distinct(), tag)
        discard(e, least, again)
        e = new


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, least node of its component) for the linked pairs (a, b), roots left out."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    i, j = at[: len(a)], at[len(a) :]
    label = np.arange(len(nodes))
    while True:
        least = np.minimum(label[i], label[j])
        new = label.copy()
        np.minimum.at(new, i, least)
        np.minimum.at(new, j, least)
        new = new[new]
        if (new == label).all():
            break
        label = new
    away = label != np.arange(len(nodes))
    return nodes[away], nodes[label[away]]


def slices(n: int, step: int) -> Iterator[slice]:
    return (slice(i, min(n, i + step)) for i in range(0, n, step))
