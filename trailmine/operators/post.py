"""What users do with mined patterns; ``pattern`` is text, items apart by one space."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def top_k(patterns: DataFrame, k: int) -> DataFrame:
    return patterns.orderBy(F.desc("freq"), "pattern").limit(k)


def top_k_by_length(patterns: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("length").orderBy(F.desc("freq"), "pattern")
    return patterns.withColumn("nth", F.row_number().over(w)).where(F.col("nth") <= k).drop("nth")


def by_length(patterns: DataFrame) -> DataFrame:
    return patterns.groupBy("length").agg(F.count(F.lit(1)).alias("n_patterns"), F.max("freq").alias("max_freq"))


def _holds(long: str, short: str):
    """Whether the items of ``short`` occur in ``long`` in this order."""
    state = F.aggregate(F.split(long, " "), F.lit(0), lambda at, w: at + F.when(F.coalesce(F.get(F.split(short, " "), at) == w, F.lit(False)), 1).otherwise(0))
    return state == F.size(F.split(short, " "))


def _extended(patterns: DataFrame) -> DataFrame:
    """Pairs of a pattern and a longer one that holds it; joined on an item of both."""
    p = patterns.select("pattern", "length", "freq", F.element_at(F.split("pattern", " "), 1).alias("w"))
    longer = patterns.select(F.col("pattern").alias("p2"), F.col("length").alias("l2"), F.col("freq").alias("f2"), F.explode(F.array_distinct(F.split("pattern", " "))).alias("w"))
    return p.join(longer, "w").where((F.col("l2") > F.col("length")) & _holds("p2", "pattern"))


def maximal(patterns: DataFrame) -> DataFrame:
    """Patterns that no longer one of the result holds."""
    return patterns.join(_extended(patterns).select("pattern").distinct(), "pattern", "left_anti")


def closed(patterns: DataFrame) -> DataFrame:
    """Patterns that no longer one with the same frequency holds."""
    return patterns.join(_extended(patterns).where("f2 = freq").select("pattern").distinct(), "pattern", "left_anti")


def difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """``pattern, freq_a, freq_b`` over both results, zero where one lacks a pattern."""
    rows = a.select("pattern", F.col("freq").alias("freq_a")).join(b.select("pattern", F.col("freq").alias("freq_b")), "pattern", "full_outer")
    return rows.na.fill(0)


def disagreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows that one result has and the other has not."""
    return a.exceptAll(b).unionByName(b.exceptAll(a))
