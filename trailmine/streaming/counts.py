"""Pattern counts over streams of events: sessions close at the watermark, and as a frequency
is a sum over sequences, the counts of closed sessions add up. No item is pruned, since one
that is rare now may become frequent; the threshold applies on reading."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.udfs import seq_outputs


def session_sequences(events: DataFrame, gap: str = "12 hours", delay: str = "1 hour") -> DataFrame:
    """``user_id, session, items`` of closed sessions; later rows are dropped and counted by Spark."""
    rows = events.withWatermark("ts", delay).groupBy("user_id", F.session_window("ts", gap).alias("session"))
    rows = rows.agg(F.sort_array(F.collect_list(F.struct("ts", "event_id", "event_type"))).alias("x"))
    return rows.select("user_id", "session", F.transform("x", lambda x: x["event_type"]).alias("items"))


def session_patterns(sequences: DataFrame, expression: str, edges=(), match: str = "anywhere") -> DataFrame:
    outputs = seq_outputs(expression, edges, match)
    return sequences.select(F.col("session.end").alias("closed"), F.explode(outputs("items")).alias("pattern"))


def windowed_counts(patterns: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    """Counts per tumbling or sliding window of the sessions' ends."""
    w = F.window("closed", width, slide) if slide else F.window("closed", width)
    return patterns.groupBy(w.alias("window"), "pattern").agg(F.count(F.lit(1)).alias("n"))


def run_counts(patterns: DataFrame, target: str, checkpoint: str):
    """Start a query that writes each batch's counts under its own batch number, so that a
    batch that is run again replaces what it wrote."""

    def save(batch: DataFrame, number: int) -> None:
        counts = batch.groupBy("pattern").agg(F.count(F.lit(1)).alias("n"))
        counts.write.mode("overwrite").parquet(f"{target}/batch={number}")

    return patterns.writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(save).trigger(availableNow=True).queryName(f"patterns-{uuid.uuid4().hex[:8]}").start()


def read_counts(spark: SparkSession, target: str, sigma: int) -> DataFrame:
    rows = spark.read.schema("pattern array<string>, n long, batch int").parquet(target)
    return rows.groupBy("pattern").agg(F.sum("n").alias("freq")).where(F.col("freq") >= sigma)
