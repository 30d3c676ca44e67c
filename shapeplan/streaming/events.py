"""Events validated as they arrive: windowed counts of invalid events, stateful maximum counts of a user.

The same window functions serve batches and streams; a stream adds the watermark, beyond which late
rows are dropped.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

KINDS = ("click", "error", "purchase", "signup", "view")


def conforms() -> Column:
    """The intra-shape constraints of an event."""
    return F.coalesce(F.col("event_type").isin(*KINDS) & (F.col("value") >= 0) & F.col("props").isNotNull() & F.col("ts").isNotNull(), F.lit(False))


def read_events(spark: SparkSession, folder: str, files_per_batch: int = 1) -> DataFrame:
    schema = spark.read.parquet(folder).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def windowed(events: DataFrame, window: Column, watermark: str | None = None) -> DataFrame:
    rows = events.withColumn("ok", conforms())
    if watermark:
        rows = rows.withWatermark("ts", watermark)
    out = rows.groupBy(window.alias("w")).agg(
        F.count(F.lit(1)).alias("n"), F.count_if(~F.col("ok")).alias("n_invalid"), F.count_if(F.col("event_type") == "error").alias("n_errors"),
    )
    return out.select(F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), "n", "n_invalid", "n_errors")


def tumbling(events: DataFrame, width: str = "1 hour", **how) -> DataFrame:
    return windowed(events, F.window("ts", width), **how)


def sliding(events: DataFrame, width: str = "1 hour", step: str = "30 minutes", **how) -> DataFrame:
    return windowed(events, F.window("ts", width, step), **how)


def sessions(events: DataFrame, gap: str = "30 minutes", watermark: str | None = None) -> DataFrame:
    rows = events.withColumn("ok", conforms())
    if watermark:
        rows = rows.withWatermark("ts", watermark)
    out = rows.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"), F.count_if(~F.col("ok")).alias("n_invalid"))
    return out.select("user_id", F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), "n", "n_invalid")


def max_count_alerts(events: DataFrame, kind: str, most: int) -> DataFrame:
    """Users at the moment a maximum of events of a kind is passed, kept in state across batches."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        before = state.get[0] if state.exists else 0
        after = before + sum(len(b) for b in batches)
        state.update((after,))
        if before <= most < after:
            yield pd.DataFrame({"user_id": [key[0]], "n": [after]})

    hits = events.where(F.col("event_type") == kind).select("user_id", "event_id")
    return hits.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long", "n long", "append", GroupStateTimeout.NoTimeout)


def publish(verdicts: DataFrame, path: str, checkpoint: str, sink: Callable | None = None):
    """Append each micro-batch's verdicts; a batch that is run again overwrites its own folder."""

    def save(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")
        if sink:
            sink(batch, number)

    return verdicts.writeStream.option("checkpointLocation", checkpoint).foreachBatch(save)
