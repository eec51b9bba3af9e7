"""Streaming sketches. A maximum merges in any order and any number of times, so late, repeated and replayed
rows leave a cumulative sketch unchanged. A user who moves to another cluster can't be taken out again: centers
stay fixed for an epoch, and a new epoch starts a new sketch under new keys."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from fedgrid.functions.columns import geometric_base2, md5_hash60
from fedgrid.operators.sketch import fold_minima


def cumulative(labels: DataFrame, repeats: int) -> DataFrame:
    """(a, i, alpha) over all rows so far, for update or complete mode; (id, a) may repeat."""
    keyed = labels.select("id", "a", F.explode(F.sequence(F.lit(1), F.lit(repeats))).alias("i"))
    value = geometric_base2(md5_hash60(F.concat_ws("|", F.col("id").cast("string"), F.col("i").cast("string"))))
    return keyed.groupBy("a", "i").agg(F.max(value).alias("alpha"))


def windowed(labels: DataFrame, repeats: int, length: str, slide: str | None = None, delay: str = "1 day") -> DataFrame:
    """A sketch per tumbling or sliding window of (ts, id, a), behind a watermark."""
    timed = labels.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
    keyed = timed.select("ts", "id", "a", F.explode(F.sequence(F.lit(1), F.lit(repeats))).alias("i"))
    value = geometric_base2(md5_hash60(F.concat_ws("|", F.col("id").cast("string"), F.col("i").cast("string"))))
    span = F.window("ts", length, slide) if slide else F.window("ts", length)
    out = keyed.groupBy(span.alias("w"), "a", "i").agg(F.max(value).alias("alpha"))
    return out.select(F.col("w.start").alias("start"), "a", "i", "alpha")


def sessions(events: DataFrame, user: str, gap: str = "30 minutes", delay: str = "1 day") -> DataFrame:
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
    out = timed.groupBy(F.session_window("ts", gap).alias("w"), user).agg(F.count(F.lit(1)).alias("n"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), user, "n")


def without_repeats(events: DataFrame, key: str, delay: str = "1 day") -> DataFrame:
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
    return timed.dropDuplicatesWithinWatermark([key])


def interval_join(orders: DataFrame, events: DataFrame, within: str = "7 days", delay: str = "1 day") -> DataFrame:
    """Orders with the events of the same user in the time before them; both sides watermarked."""
    o = orders.withColumn("o_ts", F.col("o_ts").cast("timestamp")).withWatermark("o_ts", delay)
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)
    near = F.expr(f"user_id = o_user AND ts <= o_ts AND ts >= o_ts - interval {within}")
    return o.join(e, near)


class MinimaState(StatefulProcessor):
    """Per (party, cluster) a state of minimum hashes; one array however many rows arrive."""

    def __init__(self, keys: np.ndarray):
        self.keys = keys

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("minima", "m binary")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        table = np.full((1, len(self.keys)), np.iinfo(np.uint64).max, np.uint64)
        if self.state.exists():
            table[0] = np.frombuffer(self.state.get()[0], np.uint64)
        for batch in rows:
            fold_minima(batch["id"].to_numpy(np.int64), np.zeros(len(batch), np.int64), self.keys, table)
        self.state.update((table[0].tobytes(),))
        yield pd.DataFrame({"a": [key[0]], "m": [table[0].tobytes()]})

    def close(self) -> None:
        pass


def stateful_minima(labels: DataFrame, keys: np.ndarray) -> DataFrame:
    """(a, m): the running minima of each cluster, kept in the state store between micro-batches."""
    return labels.groupBy("a").transformWithStateInPandas(
        MinimaState(keys), outputStructType="a int, m binary", outputMode="Update", timeMode="None"
    )


def merge_batch(path: str):
    """A foreachBatch sink: a batch's partial sketch, merged by maximum when the parts are read."""

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")  # a replay overwrites its own part

    return write
