"""Streams: mergeable regrid moments, incremental core refits, event axes.

State per key is a fixed number of sums (moments of a node, or the R x (R + 2) block of a
model), so it does not grow with the stream. Sums are associative: a stream gives what the
batch gives.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..operators import lstsq, regrid
from ..operators.storage import remove
from ..plans.model import FunctionalTucker
from ..schema import AxisSpec, coords


def with_watermark(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """ts as a timestamp (a watermark takes no timestamp_ntz) with the watermark on it."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def regrid_moments(points: DataFrame, axes: list[AxisSpec]) -> DataFrame:
    """Running moments of every touched node (complete or update mode)."""
    return regrid.node_moments(points, axes)


def windowed(events: DataFrame, kind: str = "tumbling", size: str = "1 day", slide: str = "12 hours", gap: str = "30 minutes", delay: str = "1 hour", watermark: bool = True) -> DataFrame:
    """Event counts and sums by tumbling, sliding or session windows (sessions by user)."""
    src = with_watermark(events, delay) if watermark else events
    if kind == "session":
        w = src.groupBy(F.session_window("ts", gap).alias("w"), "user_id")
        return w.agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "user_id", "n", "total")
    w = F.window("ts", size, slide) if kind == "sliding" else F.window("ts", size)
    return src.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "event_type", "n", "total")


def deduplicated(events: DataFrame, delay: str = "1 hour", key: str = "event_id") -> DataFrame:
    return with_watermark(events, delay).dropDuplicatesWithinWatermark([key])


def with_dictionary(events: DataFrame, dictionary: DataFrame, column: str) -> DataFrame:
    """Stream-static join with an axis dictionary (value, id), which is as small as the axis."""
    return events.join(F.broadcast(dictionary), F.col(column) == F.col("value")).drop("value").withColumnRenamed("id", f"{column}_id")


class CoreState(StatefulProcessor):
    """State of one shard of a model: the block [W'W | W'u] with the sum of squares and the row count, as bytes."""

    def __init__(self, model: FunctionalTucker):
        self.model = model

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.block = handle.getValueState("block", "data binary")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        r = self.model.R
        total = np.zeros((r + 1, r + 2))
        if self.block.exists():
            total = np.frombuffer(self.block.get()[0]).reshape(r + 1, r + 2).copy()
        for pdf in rows:
            w = np.concatenate([self.model.design([pdf[c].to_numpy() for c in coords(self.model.d)]), pdf["u"].to_numpy()[:, None]], axis=1)
            total[:, : r + 1] += w.T @ w
            total[r, r + 1] += len(w)
        self.block.update((total.tobytes(),))
        yield pd.DataFrame({"model_id": [key[0]], "shard": [int(key[1])], "n": [int(total[r, r + 1])], "block": [total.tobytes()]})

    def close(self) -> None:
        pass


def refresh_core(stream_points: DataFrame, model: FunctionalTucker, model_id: str = "m", shards: int = 32) -> DataFrame:
    """model_id, shard, n, block after each trigger; ``solve_blocks`` turns the latest blocks into the core. Points are dealt to shards by their key, so no task holds a whole model's points. Needs the RocksDB state store provider. For R beyond ``lstsq.MAX_R`` refit in batches instead."""
    if model.R > lstsq.MAX_R:
        raise ValueError(f"a core of {model.R} entries has a state that is too large")
    keyed = stream_points.select(F.lit(model_id).alias("model_id"), F.pmod(F.xxhash64("pt_key"), F.lit(shards)).cast("int").alias("shard"), *coords(model.d), "u")
    return keyed.groupBy("model_id", "shard").transformWithStateInPandas(statefulProcessor=CoreState(model), outputStructType="model_id string, shard int, n long, block binary", outputMode="Update", timeMode="None")


def solve_blocks(blocks: DataFrame, model: FunctionalTucker) -> FunctionalTucker:
    """The core from each shard's latest block (the one of most rows); as many blocks as shards reach the driver."""
    latest = blocks.groupBy("model_id", "shard").agg(F.max_by("block", "n").alias("block")).collect()
    r = model.R
    total = sum((np.frombuffer(x["block"]).reshape(r + 1, r + 2) for x in latest), np.zeros((r + 1, r + 2)))
    return model.with_core(lstsq.solve_gram(total[:r, :r], total[:r, r])[0])


def refresh_each_batch(stream_points: DataFrame, model: FunctionalTucker, sink, checkpoint: str, sums: str):
    """The same by foreachBatch: Gram sums of each micro-batch come from many tasks (no single key). The sums up to each batch are a file in the folder ``sums``, written before sink(model, n) is called: a restarted stream goes on from the batch before, a repeated batch writes its file anew. The last two files stay."""
    spark = stream_points.sparkSession
    r = model.R

    def one(batch: DataFrame, i: int) -> None:
        g, b, uu, n = lstsq.moments(batch, model)
        total = np.zeros((r + 1, r + 1))
        total[:r, :r], total[:r, r], total[r, r] = g, b, uu
        done = _sums_before(spark, sums, i)
        if done is not None:
            total, n = total + np.frombuffer(done["block"]).reshape(r + 1, r + 1), n + done["n"]
        spark.createDataFrame([(i, n, total.tobytes())], _SUMS).coalesce(1).write.mode("overwrite").parquet(f"{sums}/upto={i}")
        remove(spark, f"{sums}/upto={i - 2}")
        if n:
            sink(model.with_core(lstsq.solve_gram(total[:r, :r], total[:r, r])[0]), n)

    return stream_points.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


_SUMS = "id long, n long, block binary"


def _sums_before(spark, sums: str, i: int):
    """The sums up to the last batch before i, or None."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(sums)
    if not path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(path):
        return None
    return spark.read.schema(_SUMS).parquet(sums).where(F.col("id") < i).orderBy(F.desc("id")).first()
