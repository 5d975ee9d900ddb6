"""Helpers of the training-data operators: shared tables, bounded broadcasts, components, Arrow views."""

from __future__ import annotations

import ctypes
import gc
import sys
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of a key list (one or two longs each) that may be broadcast; beyond it a shuffle join is used.
BROADCAST_ROWS = 2_000_000


def ship(name: str) -> None:
    """Pickle a module's functions by value, so executors need no copy of the repository."""
    cloudpickle.register_pickle_by_value(sys.modules[name])


def shared_dir(spark: SparkSession) -> str:
    """The folder all machines share, from ``spark.checkpoint.dir``; in local mode one of its own where none is set."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="featgreedy")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def stored(df: DataFrame, note: str = "t", partitions: int | None = None) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/featgreedy/{note}-{uuid.uuid4().hex}"
    (df.coalesce(partitions) if partitions else df).write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.stored_path = path
    return out


def forget(df: DataFrame) -> None:
    """Delete a table of :func:`stored` that nothing reads any more."""
    path = getattr(df, "stored_path", None)
    if path:
        jvm, spark = df.sparkSession._jvm, df.sparkSession
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """A broadcast hint when a stored key list is counted to be within ``rows``; else the plain frame."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def components(edges: DataFrame, a: str, b: str) -> DataFrame:
    """Connected components by alternating large-star and small-star joins.

    ``edges`` has two long columns. Returns ``node, component`` (smallest node reached) for every
    node with an edge. Each round is aggregates with partial sums and joins that AQE may split, so a
    hub of any degree is never gathered into one task. Rounds stop when the edge set stays the same.
    """
    star = stored(
        edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).filter("u <> v").distinct(), "edges"
    )
    seen = None
    while True:
        both = star.select("u", "v").union(star.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        large = both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.filter("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        new = (
            large.join(least, "u")
            .select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e"))
            .select("e.u", "e.v").filter("u <> v").distinct()
        )
        new = stored(new, "edges")
        mark = new.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        forget(star)
        star = new
        if mark == seen:
            break
        seen = mark
    nodes = star.groupBy("u").agg(F.min("v").alias("component")).withColumnRenamed("u", "node")
    roots = star.select(F.col("v").alias("node")).distinct().withColumn("component", F.col("node"))
    # a root's own smallest reach is itself; every other node keeps its root
    both = nodes.union(roots).groupBy("node").agg(F.min("component").alias("component"))
    return stored(both, "components")


def tidied(fn):
    """``fn`` of batches, after whose last batch the worker gives its free memory back: workers outlive their tasks."""

    def run(batches):
        yield from fn(batches)
        gc.collect()
        pa.default_memory_pool().release_unused()
        try:
            ctypes.CDLL(None).malloc_trim(0)
        except (OSError, AttributeError):  # another C library
            pass

    return run


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of a string column and its offsets (nulls are empty), without copying."""
    column = column.cast(pa.large_binary()) if not pa.types.is_large_binary(column.type) else column
    if column.null_count:
        column = column.fill_null(b"")
    at = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    data = column.buffers()[2]
    whole = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return whole, at


def slices(at: np.ndarray, most: int = 2_000_000):
    """Ranges of rows whose bytes together stay near ``most`` (one long row may exceed it)."""
    i, n = 0, len(at) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(at, at[i] + most, "right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


ship(__name__)
