"""Structured Streaming operators: sessions, activity windows, rounds of uploads, on-line tuning and test-then-train.

Time columns must be zoned timestamps for watermarks; ``event_stream`` casts the
zone-less files and expects the session to run in UTC.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout
from pyspark.sql.types import IntegerType, StructField, StructType

from fedlake.sources.tables import load


def event_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """The events files as a stream: event_id, client_id, item_id, value, ts (zoned)."""
    schema = load(spark, folder, "events").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "events*.parquet").parquet(folder)
    return stream.select("event_id", F.col("user_id").alias("client_id"), F.concat_ws("#", "event_type", F.get_json_object("props", "$.k")).alias("item_id"), "value", F.col("ts").cast("timestamp").alias("ts"))


def sessions(stream: DataFrame, gap: str = "24 hours", delay: str = "1 hour") -> DataFrame:
    """client_id, start_ts, end_ts, n of closed sessions."""
    windowed = stream.withWatermark("ts", delay).groupBy("client_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return windowed.select("client_id", F.col("w.start").alias("start_ts"), F.col("w.end").alias("end_ts"), "n")


def activity(stream: DataFrame, width: str = "1 day", slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """client_id, w_start, n over tumbling or sliding windows."""
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    counted = stream.withWatermark("ts", delay).groupBy("client_id", window.alias("w")).agg(F.count("*").alias("n"))
    return counted.select("client_id", F.col("w.start").alias("w_start"), "n")


def rounds(deltas: DataFrame, width: str, delay: str, size: int) -> DataFrame:
    """w_start, pos, value, arrived: one tumbling window is one round; the mean divides by the fixed round size.

    Uploads later than the watermark are dropped from the mean; their privacy is
    still charged, because the client has already sent them. deltas: client_id, ts, vec.
    """
    cells = deltas.withWatermark("ts", delay).select("ts", "client_id", F.posexplode("vec").alias("pos", "x"))
    whole = F.sum((F.col("x") * float(1 << 32)).cast("long"))
    summed = cells.groupBy(F.window("ts", width).alias("w"), "pos").agg((whole / float(1 << 32) / size).alias("value"), F.count("*").alias("arrived"))
    return summed.select(F.col("w.start").alias("w_start"), "pos", "value", "arrived")


def dedup(stream: DataFrame, keys: list[str], delay: str = "1 hour") -> DataFrame:
    """One upload per key inside the watermark."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(keys)


def enrich(stream: DataFrame, items: DataFrame) -> DataFrame:
    """Stream joined with the static item table."""
    return stream.join(items, "item_id", "left")


def personalise(stream: DataFrame, theta: np.ndarray, epochs: int = 2, rate: float = 0.1, ttl_ms: int | None = None) -> DataFrame:
    """client_id, seen, w0, w1 after every micro-batch: a client's parameters of a logistic model over (1, value) step on its new events.

    The parameters are the state of the client. With ``ttl_ms`` it expires that
    long after its last event; such a query keeps ticking and suits continuous
    triggers only.
    """
    start = [float(x) for x in theta]

    def step(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        w = np.array(state.get[0] if state.exists else start)
        seen = 0
        for frame in frames:
            x = np.column_stack([np.ones(len(frame)), frame["value"].to_numpy() / 100])
            y = (frame["value"].to_numpy() > 50).astype(float)
            for _ in range(epochs):
                w = w - rate * x.T @ (1 / (1 + np.exp(-x @ w)) - y) / max(1, len(y))
            seen += len(frame)
        state.update((w.tolist(),))
        if ttl_ms:
            state.setTimeoutDuration(ttl_ms)
        yield pd.DataFrame({"client_id": [key[0]], "seen": [seen], "w0": [float(w[0])], "w1": [float(w[1])]})

    return stream.groupBy("client_id").applyInPandasWithState(step, "client_id long, seen long, w0 double, w1 double", "w array<double>", "update", GroupStateTimeout.ProcessingTimeTimeout if ttl_ms else GroupStateTimeout.NoTimeout)


def prequential(stream: DataFrame, score: Callable[[DataFrame], DataFrame], sink: list, ks: tuple[int, ...] = (5, 10)):
    """Test-then-train: every micro-batch is ranked before it may train. ``score(batch)`` gives (client_id, item_id, rank); one summary row a batch goes to ``sink``."""
    from fedlake.operators.metrics import per_user

    def on_batch(batch: DataFrame, number: int) -> None:
        users = per_user(score(batch), ks)
        for r in users.groupBy("k").agg(F.avg("hits").alias("hits"), F.count("*").alias("users")).collect():
            sink.append({"batch": number, "k": r.k, "hits": r.hits, "users": r.users})

    return stream.writeStream.foreachBatch(on_batch)


def run_once(frame: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Everything available through the query once, into Parquet files of that name beside the query's state.

    Every micro-batch overwrites a folder of its own, so a batch that runs again
    after a failure counts once; in complete mode the last batch is the result.
    """
    rows = f"{checkpoint}/{name}-rows"

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{rows}/batch={0 if mode == 'complete' else number}")

    query = frame.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{checkpoint}/{name}-state").trigger(availableNow=True).start()
    query.awaitTermination()
    schema = StructType([*frame.schema.fields, StructField("batch", IntegerType())])
    spark = frame.sparkSession
    spark.createDataFrame([], frame.schema).write.mode("overwrite").parquet(f"{rows}/batch=-1")  # there may be no batch
    return spark.read.schema(schema).parquet(rows).drop("batch")
