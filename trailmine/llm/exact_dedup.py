"""Exact deduplication with a heavy-hitter split (operator 9), DataFrame functions only.

A Misra-Gries summary (Spark's ``freqItems``) names at most ``k`` candidate digests and
misses none that more than ``rows / k`` documents share. Their exact counts and winners are
aggregated, so the broadcast table has ``k`` rows at most. Losers of these groups are
recognised map-side and never shuffled; every other group has ``rows / k`` rows at most and
goes through an ordinary shuffle on the digest.

Defined cases: a null text is an empty one; of equal texts the row with the most code points
stays, then the smallest ``doc_id`` (null last); of rows that repeat the winner's id exactly
one stays; a text of any length is digested whole; an empty table gives an empty result; other
columns are ignored by ``dedup_decisions`` and carried, under any name, by ``drop_duplicates``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import SPACES, documents, materialize, whole_row, whole_text

#: Counters of the Misra-Gries summary: bound of the broadcast table.
HEAVY_SLOTS = 1024


def text_digest(text: Column | str = "text") -> Column:
    """SHA-256 of the text without white space, lowercase hex."""
    return F.sha2(F.regexp_replace(whole_text(text), SPACES, "").cast("binary"), 256)


def _keyed(id_col: str, text_col: str) -> list[Column]:
    return [
        text_digest(F.col(f"`{text_col}`")).alias("__digest"),
        F.struct(
            (-F.length(whole_text(F.col(f"`{text_col}`")))).alias("neg"),
            F.col(f"`{id_col}`").isNull().alias("none"),
            F.col(f"`{id_col}`").alias("id"),
        ).alias("__rank"),
    ]


def heavy_winners(keyed: DataFrame, slots: int = HEAVY_SLOTS) -> DataFrame:
    """``__digest, __best, __size`` of the verified heavy groups, ``slots`` rows at most."""
    names = keyed.select("__digest").freqItems(["__digest"], 1.0 / slots)
    names = names.select(F.explode("__digest_freqItems").alias("__digest"))
    exact = keyed.join(F.broadcast(names), "__digest").groupBy("__digest")
    exact = exact.agg(F.min("__rank").alias("__best"), F.count(F.lit(1)).alias("__size"))
    return materialize(exact.where("__size > 1"), "heavy")


def dedup_decisions(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", slots: int = HEAVY_SLOTS) -> DataFrame:
    """One row per document: ``doc_id, keep_id, group_size, kept, text_sha256``."""
    keyed = materialize(docs.select(*_keyed(id_col, text_col)), "digests")
    rows = keyed.join(F.broadcast(heavy_winners(keyed, slots)), "__digest", "left")
    lost = F.coalesce(F.col("__rank") != F.col("__best"), F.lit(False))
    group = Window.partitionBy("__digest")
    best = F.coalesce(F.col("__best"), F.min("__rank").over(group))
    shuffled = rows.where(~lost).select(
        "__digest",
        F.col("__rank.id").alias("doc_id"),
        best["id"].alias("keep_id"),
        F.coalesce(F.col("__size"), F.count(F.lit(1)).over(group)).alias("group_size"),
        (F.row_number().over(group.orderBy("__rank")) == 1).alias("kept"),
    )
    local = rows.where(lost).select(
        "__digest",
        F.col("__rank.id").alias("doc_id"),
        F.col("__best.id").alias("keep_id"),
        F.col("__size").alias("group_size"),
        F.lit(False).alias("kept"),
    )
    return shuffled.unionByName(local).select("doc_id", "keep_id", "group_size", "kept", F.col("__digest").alias("text_sha256"))


def drop_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", slots: int = HEAVY_SLOTS) -> DataFrame:
    """The documents that stay, with all their columns."""
    keyed = materialize(docs.select(*_keyed(id_col, text_col)), "digests")
    heavy = heavy_winners(keyed, slots)
    rows = docs.select(whole_row(docs).alias("row"), *_keyed(id_col, text_col)).join(F.broadcast(heavy), "__digest", "left")
    rows = rows.where(F.coalesce(F.col("__rank") == F.col("__best"), F.lit(True)))
    first = F.row_number().over(Window.partitionBy("__digest").orderBy("__rank"))
    return rows.withColumn("__nth", first).where("__nth = 1").select("row.*")


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_decisions(documents(spark, sf_dir))


ORACLE_SQL = r"""
WITH d AS (
  SELECT doc_id, coalesce(text, '') AS t,
         regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', '', 'g') AS norm
  FROM documents),
r AS (
  SELECT doc_id, norm, length(t) AS n,
         row_number() OVER (PARTITION BY norm ORDER BY length(t) DESC, doc_id) AS k,
         first_value(doc_id) OVER (PARTITION BY norm ORDER BY length(t) DESC, doc_id) AS keep_id,
         count(*) OVER (PARTITION BY norm) AS group_size
  FROM d)
SELECT doc_id, keep_id, group_size, k = 1 AS kept, sha256(norm) AS text_sha256 FROM r
"""
