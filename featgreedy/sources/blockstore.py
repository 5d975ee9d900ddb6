"""A block store on disk: Parquet partitioned by row segment and block bucket, so that screening on one segment and
refits on few blocks prune files; and a planted-data source for ``spark.read.format``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from featgreedy.session import ship

BUCKETS = 32


def write_blocks(blocks: DataFrame, path: str, buckets: int = BUCKETS) -> None:
    spread = blocks.withColumn("j_bucket", F.pmod("j", F.lit(buckets))).repartition("h", "j_bucket")
    spread.sortWithinPartitions("j").write.mode("overwrite").partitionBy("h", "j_bucket").parquet(path)


def read_blocks(spark: SparkSession, path: str, ids=None, segments=None, buckets: int = BUCKETS) -> DataFrame:
    """Blocks ``ids`` of ``segments`` (all if None), as literal filters on the partition columns and on ``j``."""
    df = spark.read.parquet(path)
    if ids is not None:
        ids = sorted({int(j) for j in ids})
        df = df.filter(F.col("j_bucket").isin(sorted({j % buckets for j in ids})) & F.col("j").isin(ids))
    if segments is not None:
        df = df.filter(F.col("h").isin([int(h) for h in segments]))
    return df.drop("j_bucket")


class _Range(InputPartition):
    def __init__(self, j: int, h: int):
        self.j, self.h = j, h


class PlantedReader(DataSourceReader):
    """Blocks of normal draws keyed by (seed, row, column), made where they are read."""

    def __init__(self, options):
        self.n, self.p, self.q = int(options.get("n", 100)), int(options.get("p", 4)), int(options.get("q", 2))
        self.seg, self.seed = int(options.get("seg_rows", 1000)), options.get("seed", "planted")

    def partitions(self):
        return [_Range(j, h) for j in range(self.p) for h in range((self.n + self.seg - 1) // self.seg)]

    def read(self, part):
        import hashlib
        import math

        def u(k):
            return (int(hashlib.md5(k.encode()).hexdigest()[:8], 16) + 0.5) / 2**32

        t0 = part.h * self.seg
        m = min(self.seg, self.n - t0)
        x = []
        for l in range(self.q):
            for t in range(t0, t0 + m):
                k = f"{self.seed}|x|{t}|{part.j * self.q + l}"
                x.append(math.sqrt(-2 * math.log(u(k + "a"))) * math.cos(2 * math.pi * u(k + "b")))
        yield (part.j, part.h, t0, m, self.q, x)


class PlantedSource(DataSource):
    """``spark.read.format("planted_blocks").option("n", ..).option("p", ..).load()``"""

    @classmethod
    def name(cls):
        return "planted_blocks"

    def schema(self):
        return "j int, h int, t0 long, n_h int, q int, x array<double>"

    def reader(self, schema):
        return PlantedReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PlantedSource)


ship(__name__)
