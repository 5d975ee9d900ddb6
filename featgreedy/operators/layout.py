"""Layouts: wide rows, cells, blocks of columns by row segment, and response segments.

``wide``: ``t`` (0, 1, ...), ``f`` array<double>, ``y`` array<double>.
``cells``: ``t, j, l, v``.
``blocks``: ``j, h, t0, n_h, q, x`` with ``x`` column-major, the engine's layout.
``segments``: ``h, t0, n_h, d, y`` with ``y`` row-major.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from featgreedy.session import ship, stored

BLOCKS = "j int, h int, t0 long, n_h int, q int, x array<double>"
SEGMENTS = "h int, t0 long, n_h int, d int, y array<double>"
#: Bytes of all columns of a row segment, which one task packs or multiplies.
SEGMENT_BYTES = 128_000_000
NULL_POLICIES = ("error", "drop_row", "zero", "mean")


class BlockWidthError(ValueError):
    """A row whose feature array is not as wide as the manifest says."""


def clean(wide: DataFrame, policy: str = "error") -> DataFrame:
    """Apply a null policy to ``f``: NaN counts as null."""
    if policy not in NULL_POLICIES:
        raise ValueError(f"null policy must be one of {NULL_POLICIES}")
    bad = lambda x: x.isNull() | F.isnan(x)
    if policy == "error":
        check = F.when(F.exists("f", bad), F.raise_error(F.lit("null in a feature; choose a null policy")).cast("array<double>"))
        return wide.withColumn("f", F.coalesce(check, F.col("f")))
    if policy == "drop_row":
        return wide.filter(~F.exists("f", bad))
    if policy == "zero":
        return wide.withColumn("f", F.transform("f", lambda x: F.when(bad(x), 0.0).otherwise(x)))
    means = wide.select(F.posexplode("f").alias("l", "v")).filter(~bad(F.col("v"))).groupBy("l").agg(F.avg("v").alias("m"))
    means = means.agg(F.map_from_entries(F.collect_list(F.struct("l", "m"))).alias("_m"))
    return wide.join(F.broadcast(means)).withColumn("f", F.transform("f", lambda x, i: F.when(bad(x), F.element_at("_m", i)).otherwise(x))).drop("_m")


def manifest(widths: list[int]) -> list[tuple[int, int]]:
    """Column ranges of blocks of the given widths."""
    ends = np.cumsum(widths)
    return [(int(e - w), int(e)) for w, e in zip(widths, ends, strict=True)]


def _pack(ranges, seg_rows):
    def run(key, table):
        h = key[0].as_py()
        order = np.argsort(table.column("t").to_numpy(), kind="stable")
        lists = table.column("f").combine_chunks()
        flat = lists.flatten().to_numpy(zero_copy_only=False)
        width = ranges[-1][1]
        if len(flat) != width * len(order):
            raise BlockWidthError(f"segment {h}: rows are not all {width} wide")
        x = flat.reshape(len(order), width)[order]
        cols = {k: [] for k in ("j", "h", "t0", "n_h", "q", "x")}
        for j, (a, b) in enumerate(ranges):
            for k, v in zip(cols, (j, h, h * seg_rows, len(order), b - a, x[:, a:b].T.ravel()), strict=True):
                cols[k].append(v)
        kinds = (pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.list_(pa.float64()))
        return pa.table({k: pa.array(v, t) for (k, v), t in zip(cols.items(), kinds, strict=True)})

    return run


def segment_rows(columns: int) -> int:
    """Rows of a segment of so many columns."""
    return max(1024, SEGMENT_BYTES // (8 * max(columns, 1)))


def to_blocks(wide: DataFrame, widths: list[int], seg_rows: int | None = None) -> DataFrame:
    """One shuffle by row segment; each segment, bounded in bytes unless its rows are given, is cut into all its column groups."""
    seg_rows = seg_rows or segment_rows(sum(widths))
    h = F.floor(F.col("t") / seg_rows).cast("int")
    return wide.select(h.alias("h"), "t", "f").groupBy("h").applyInArrow(_pack(manifest(widths), seg_rows), BLOCKS)


def to_segments(wide: DataFrame, seg_rows: int | None = None) -> DataFrame:
    """The response in the segments of :func:`to_blocks`."""
    if not seg_rows:
        one = wide.select(F.size("f").alias("n")).first()
        seg_rows = segment_rows(one["n"] if one else 1)
    h = F.floor(F.col("t") / seg_rows).cast("int")
    g = wide.select(h.alias("h"), F.struct("t", "y").alias("r")).groupBy("h").agg(F.sort_array(F.collect_list("r")).alias("r"))
    return g.select("h", (F.col("h").cast("long") * seg_rows).alias("t0"), F.size("r").alias("n_h"), F.size(F.col("r")[0]["y"]).alias("d"), F.flatten("r.y").alias("y"))


def to_cells(wide: DataFrame, width: int) -> DataFrame:
    e = wide.select("t", F.posexplode("f").alias("c", "v"))
    return e.select("t", F.floor(F.col("c") / width).cast("int").alias("j"), (F.col("c") % width).alias("l"), "v")


def cells_to_wide(cells: DataFrame, width: int) -> DataFrame:
    g = cells.groupBy("t").agg(F.sort_array(F.collect_list(F.struct((F.col("j") * width + F.col("l")).alias("c"), "v"))).alias("r"))
    return g.select("t", F.col("r.v").alias("f"))


def blocks_to_cells(blocks: DataFrame) -> DataFrame:
    e = blocks.select("j", "t0", "n_h", F.posexplode("x").alias("p", "v"))
    return e.select((F.col("t0") + F.col("p") % F.col("n_h")).alias("t"), "j", F.floor(F.col("p") / F.col("n_h")).cast("int").alias("l"), "v")


def numbered(df: DataFrame, *order: str) -> DataFrame:
    """``t`` = rank by ``order``, from 0, without a single-task sort: range-partition, count, then number in parts."""
    # the ranges are sampled, so the dealt rows are kept: both readings below must see the same ranges
    spread = stored(df.repartitionByRange(*order).withColumn("_p", F.spark_partition_id()), "numbered")
    spread = spread.withColumn("_r", F.row_number().over(Window.partitionBy("_p").orderBy(*order)))
    sizes = spread.groupBy("_p").agg(F.count("*").alias("_n"))
    base = sizes.withColumn("_b", F.coalesce(F.sum("_n").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return spread.join(F.broadcast(base.drop("_n")), "_p").withColumn("t", F.col("_b") + F.col("_r") - 1).drop("_p", "_r", "_b")


ship(__name__)
