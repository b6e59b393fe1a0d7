"""Streaming views of the same state (ST1-ST8)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_batch: int | None = None) -> DataFrame:
    """ST1: events from Parquet files with a declared schema; event time with zone for watermarks."""
    reader = spark.readStream.schema(EVENTS)
    reader = reader.option("maxFilesPerTrigger", files_per_batch) if files_per_batch else reader
    return reader.parquet(path).withColumn("at", F.col("ts").cast("timestamp"))


def activity(events: DataFrame, size: str = "1 day", slide: str | None = None, late: str = "1 day", gap: str | None = None) -> DataFrame:
    """ST2, ST3: events per user in tumbling, sliding or session windows, late rows dropped by the
    watermark. The same plan runs on a batch frame, where the watermark has no effect."""
    own = events.withWatermark("at", late) if events.isStreaming else events
    w = F.session_window("at", gap) if gap else F.window("at", size, slide) if slide else F.window("at", size)
    return own.groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


def deduplicated(events: DataFrame, late: str = "1 day") -> DataFrame:
    """ST7."""
    return events.withWatermark("at", late).dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def enriched(events: DataFrame, customers: DataFrame) -> DataFrame:
    """ST6: stream with static: each event beside its customer."""
    return events.join(customers, events.user_id == customers.c_custkey)


def purchases_after_clicks(clicks: DataFrame, purchases: DataFrame, within: str = "1 hour", late: str = "1 day") -> DataFrame:
    """ST6: stream with stream: purchases of a user at most ``within`` after a click."""
    a = clicks.select(F.col("user_id").alias("u"), F.col("event_id").alias("click_id"), F.col("at").alias("click_at"))
    b = purchases.select("user_id", F.col("event_id").alias("purchase_id"), F.col("at").alias("purchase_at"))
    if clicks.isStreaming:
        a, b = a.withWatermark("click_at", late), b.withWatermark("purchase_at", late)
    return a.join(b, F.expr(f"u = user_id AND purchase_at > click_at AND purchase_at <= click_at + INTERVAL {within}")).select("click_id", "purchase_id")


def latest_k(events: DataFrame, k: int) -> DataFrame:
    """ST4: after each batch, the k latest events of each user seen so far (key, state in arrays)."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def update(key, frames, state):
        held = list(zip(*state.get)) if state.exists else []
        for pdf in frames:
            held += list(zip(pdf["ts_us"].tolist(), pdf["event_id"].tolist()))
        held = sorted(set(held), key=lambda x: (-x[0], x[1]))[:k]
        state.update(([x for x, _ in held], [y for _, y in held]))
        yield pd.DataFrame({"user_id": [key[0]], "event_ids": [[y for _, y in held]]})

    own = events.select("user_id", "event_id", F.unix_micros("at").alias("ts_us"))
    return own.groupBy("user_id").applyInPandasWithState(update, "user_id long, event_ids array<long>", "ts array<long>, ids array<long>", "update", GroupStateTimeout.NoTimeout)


def ema_state(obs: DataFrame, beta: float = 0.3) -> DataFrame:
    """ST5: the ledger's moving average as keyed state over (model_id, step, perf)."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def update(key, frames, state):
        mean = state.get[0] if state.exists else None
        rows = sorted((int(s), float(p)) for pdf in frames for s, p in zip(pdf["step"], pdf["perf"]))
        for _, x in rows:
            mean = x if mean is None else (1 - beta) * mean + beta * x
        state.update((mean,))
        yield pd.DataFrame({"model_id": [key[0]], "ema": [mean]})

    return obs.groupBy("model_id").applyInPandasWithState(update, "model_id string, ema double", "ema double", "update", GroupStateTimeout.NoTimeout)


def online_scores(stream: DataFrame, score_batch, path: str, checkpoint: str):
    """ST8: every micro-batch is scored by ``score_batch`` (a function of a DataFrame) and appended."""
    return stream.writeStream.foreachBatch(lambda df, _: score_batch(df).write.mode("append").parquet(path)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
