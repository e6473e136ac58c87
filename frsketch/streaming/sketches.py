"""Sketches of streams.

Registers only grow by maximum, so replayed and duplicate rows change nothing: no deduplication state
is kept, and at-least-once delivery suffices.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from frsketch.operators.build import registers
from frsketch.params import FrsParams


def event_time(df: DataFrame, ts: str) -> DataFrame:
    """``ts`` as a timestamp in UTC; watermarks need one with a zone."""
    return df.withColumn(ts, F.to_utc_timestamp(F.col(ts).cast("timestamp"), F.current_timezone()) if dict(df.dtypes)[ts] == "timestamp_ntz" else F.col(ts))


def stream_sketch(df: DataFrame, ts: str, elements, by: list[str], params: FrsParams, window: str = "1 day", slide: str | None = None, watermark: str = "1 hour") -> DataFrame:
    """(win, by..., bucket, reg) per tumbling or sliding window; one shuffle a micro-batch, state of at most
    2**p rows a window and key. Works on batch frames alike."""
    df = event_time(df, ts)
    if df.isStreaming:
        df = df.withWatermark(ts, watermark)
    rows = registers(df, elements, [ts, *by], params)
    win = F.window(ts, window, slide) if slide else F.window(ts, window)
    return rows.groupBy(win.alias("win"), *by, "bucket").agg(F.max("reg").alias("reg")).select(F.col("win.start").alias("win"), *by, "bucket", "reg")


def merge_batch(target: str, keys: list[str]):
    """A foreachBatch function that keeps the register-wise maximum in a Parquet table: each micro-batch
    is one more folder of partial sketches, and readers take the maximum (see ``read_merged``)."""

    def write(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{target}/epoch={epoch}")

    return write


def read_merged(spark: SparkSession, target: str, keys: list[str]) -> DataFrame:
    return spark.read.parquet(target).groupBy(*keys, "bucket").agg(F.max("reg").alias("reg"))


def compact(spark: SparkSession, target: str, keys: list[str], out: str) -> None:
    """Folds all epochs into one table."""
    read_merged(spark, target, keys).write.mode("overwrite").parquet(out)


def session_sketch(df: DataFrame, ts: str, user: str, elements, params: FrsParams, gap: str = "1 hour") -> DataFrame:
    """(user, start, bucket, reg): one sketch a session. Sessions are formed a key, before the rows
    are split into buckets: each session gathers its distinct registers, then these are unfolded."""
    df = event_time(df, ts)
    rows = registers(df, elements, [ts, user], params)
    packed = F.col("bucket").cast("bigint") * (1 << 32) + F.col("reg")
    sessions = rows.groupBy(user, F.session_window(ts, gap).alias("s")).agg(F.collect_set(packed).alias("cells"))
    each = sessions.select(user, F.col("s.start").alias("start"), F.explode("cells").alias("c"))
    each = each.select(user, "start", F.shiftright("c", 32).cast("int").alias("bucket"), F.col("c").bitwiseAND(F.lit((1 << 32) - 1)).cast("int").alias("reg"))
    return each.groupBy(user, "start", "bucket").agg(F.max("reg").alias("reg"))


def packed_state_sketch(stream: DataFrame, key: str, elements, params: FrsParams) -> DataFrame:
    """(key, bucket, reg) in update mode, one packed state a key instead of a row a bucket: for streams
    of few keys and many buckets."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    import numpy as np

    kind = stream.schema[key].dataType.simpleString()
    rows = registers(stream, elements, [key], params)
    k = params.k

    def update(keys, frames, state: GroupState):
        regs = np.frombuffer(state.get[0], dtype="<i4").copy() if state.exists else np.zeros(k, dtype="<i4")
        before = regs.copy()
        for f in frames:
            np.maximum.at(regs, f["bucket"].to_numpy(), f["reg"].to_numpy())
        state.update((regs.tobytes(),))
        new = np.flatnonzero(regs != before)
        yield pd.DataFrame({key: [keys[0]] * len(new), "bucket": new.astype("int32"), "reg": regs[new]})

    return rows.groupBy(key).applyInPandasWithState(update, f"{key} {kind}, bucket int, reg int", "regs binary", "update", GroupStateTimeout.NoTimeout)


def run_to_end(stream: DataFrame, sink, checkpoint: str, mode: str = "update") -> None:
    """Runs a query over what is there, through foreachBatch, and stops."""
    q = stream.writeStream.outputMode(mode).foreachBatch(sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
