"""Row segments as a stream: windowed counts and moments, sessions, late rows, and arbitrary state."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from featgreedy.session import shared_dir, ship

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def split_files(events: DataFrame, note: str, files: int = 5, late_every: int = 0, late_by: int = 2) -> str:
    """Write events as files in time order, for a file stream; every ``late_every``-th row goes ``late_by`` files on."""
    import uuid

    path = f"{shared_dir(events.sparkSession)}/featgreedy/stream-{note}-{uuid.uuid4().hex}"
    span = events.agg(F.min("ts").alias("a"), F.max("ts").alias("b")).first()
    width = max((span["b"] - span["a"]).total_seconds(), 1.0) / files
    part = F.least(F.floor((F.unix_timestamp("ts") - F.lit(int(span["a"].timestamp()))) / width), F.lit(files - 1)).cast("int")
    if late_every:
        part = F.when(F.col("event_id") % late_every == 0, F.least(part + late_by, F.lit(files - 1))).otherwise(part)
    split = events.withColumn("_f", part)
    for i in range(files):
        split.filter(F.col("_f") == i).drop("_f").coalesce(1).write.mode("append").parquet(path)
    return path


def read_stream(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def drain(stream: DataFrame, name: str, mode: str) -> DataFrame:
    """Run to the end of the available files and return what the stream gave, from Parquet in the shared folder.

    Each micro-batch overwrites a folder of its own, so a repeated batch leaves nothing twice. In complete mode the last
    batch is the result, else all of them.
    """
    import uuid

    spark = stream.sparkSession
    place = f"{shared_dir(spark)}/featgreedy/streams/{name}-{uuid.uuid4().hex}"
    done: list[int] = []

    def keep(batch, i):
        batch.write.mode("overwrite").parquet(f"{place}/out/{i:06d}")
        done.append(i)

    query = stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{place}/checkpoint").trigger(availableNow=True).start()
    query.awaitTermination()
    if not done:
        return spark.createDataFrame([], stream.schema)
    batches = [max(done)] if mode == "complete" else sorted(set(done))
    return spark.read.schema(stream.schema).parquet(*[f"{place}/out/{i:06d}" for i in batches])


def tumbling(stream: DataFrame, width: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", "2 days").groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n"))


def sliding(stream: DataFrame, width: str = "2 days", step: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", "2 days").groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("n"), F.sum(F.col("value").cast("decimal(18,4)")).alias("s"))


def sessions(stream: DataFrame, gap: str = "6 hours") -> DataFrame:
    return stream.withWatermark("ts", "2 days").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))


def segment_moments(stream: DataFrame, width: str = "7 days") -> DataFrame:
    """Additive moments of (1, hour, value) by window: a row segment's inner products as a streaming aggregate."""
    h, v = F.hour("ts").cast("long"), F.col("value").cast("decimal(18,4)")
    return stream.withWatermark("ts", "2 days").groupBy(F.window("ts", width).alias("w")).agg(F.count("*").alias("n"), F.sum(h).alias("x"), F.sum(h * h).alias("xx"), F.sum(v).alias("y"), F.sum(v * h).alias("xy"))


def stateful_moments(stream: DataFrame) -> DataFrame:
    """Per event type, running moments held in arbitrary state and updated batch by batch."""

    def update(key, frames, state):
        n, x, y, xy = state.get if state.exists else (0, 0.0, 0.0, 0.0)
        for pdf in frames:
            h, v = pdf["ts"].dt.hour.to_numpy(float), pdf["value"].to_numpy(float)
            n, x, y, xy = n + len(pdf), x + h.sum(), y + v.sum(), xy + (h * v).sum()
        state.update((int(n), float(x), float(y), float(xy)))
        yield pd.DataFrame({"event_type": [key[0]], "n": [int(n)], "x": [float(x)], "y": [float(y)], "xy": [float(xy)]})

    return stream.groupBy("event_type").applyInPandasWithState(update, "event_type string, n long, x double, y double, xy double", "n long, x double, y double, xy double", "update", "NoTimeout")


def refit_each_batch(stream: DataFrame, fit, done: list) -> None:
    """``foreachBatch``: fold each micro-batch's moments into a model; ``fit(total)`` sees the sums so far."""
    import uuid

    total = np.zeros((3, 3))

    def batch(df, _):
        nonlocal total
        h, v = F.hour("ts").cast("double"), F.col("value")
        r = df.agg(F.count("*"), F.sum(h), F.sum(v), F.sum(h * h), F.sum(h * v), F.sum(v * v)).first()
        n, x, y, xx, xy, yy = (float(a or 0) for a in r)
        total = total + np.array([[n, x, y], [x, xx, xy], [y, xy, yy]])
        done.append(fit(total))

    place = f"{shared_dir(stream.sparkSession)}/featgreedy/checkpoints/{uuid.uuid4().hex}"
    stream.writeStream.foreachBatch(batch).option("checkpointLocation", place).trigger(availableNow=True).start().awaitTermination()


ship(__name__)
