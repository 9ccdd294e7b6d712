"""Mixing sources to target weights by a time-varying curriculum (operator 8), DataFrame
functions only.

A source's weight runs linearly over training time ``t`` in [0, 1], from ``w (1 - a)`` to
``w (1 + a)``; its integral over [0, 1] is ``w``, so the target shares follow from ``w`` alone.
Cumulative demand of a source up to ``t`` is ``target * (t + a (t^2 - t))``; inverting it at a
document's cumulative word count gives the training position of the document, and the result
is range-sorted by position. Heavier sources come earlier (``a`` falls with the weight).

Order within a source is the md5 of the id. Word counts are summed in two levels, over a
bounded number of hash buckets of a source and then within a bucket, so that a source with a
third of all rows is spread over many tasks.

``mixed_documents`` shuffles the texts once. Training time is cut into slices; from the narrow
table of sizes follows, for each source and pass, with which document each slice begins. These
beginnings are broadcast (at most ``MOST_STARTS``), every document finds its slices by bisection
where it is read and goes there, and within a slice its exact position follows from the sizes
before it. Beyond that bound documents get a key in a written table, are joined with their
positions by it and range-sorted, which shuffles the texts twice. Both ways give the same rows in
the same order.

Defined cases: null texts have size 0 and are not taken; null source is a source of its own,
last in order; rows that repeat an id, or have none, are documents of their own, ordered by
size; a text of any length counts whole; other columns are ignored by ``mix`` and carried, under
any name, by ``mixed_documents``; an empty table gives an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import documents, find_last, materialize, whole_row, words

WEIGHTS = (5.0, 2.0, 1.0)
TILTS = (-0.5, 0.0, 0.5)
MAX_EPOCHS = 3
#: Rows that one hash bucket of a source shall hold, about.
BUCKET_ROWS = 20_000
#: Beginnings of slices (source, pass, slice) that are broadcast, under 100 bytes each.
MOST_STARTS = 1 << 18


def source_targets(sizes: DataFrame, weights=WEIGHTS, tilts=TILTS, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """``__src, source_size, n_rows, target, tilt`` per source.

    The level at which capped targets add up to all words is found by one ordered pass: in
    the order of cap over weight the capped sources come first.
    """
    per = sizes.groupBy("__src").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n_rows"))
    nth = (F.row_number().over(Window.orderBy("__src")) - 1) % len(weights)
    pick = lambda xs: F.element_at(F.array(*map(F.lit, xs)), (nth + 1).cast("int"))
    per = per.select("*", pick(weights).alias("w"), pick(tilts).alias("tilt"))
    per = per.withColumn("cap", (max_epochs * F.col("source_size")).cast("double"))
    order = Window.orderBy(F.col("cap") / F.col("w"), "__src")
    everything = order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    used = F.sum("cap").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("cap")
    left = F.sum("w").over(order.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    per = per.withColumn("level", (F.sum("source_size").over(everything) - used) / left)
    open_ = F.when(F.col("level") <= F.col("cap") / F.col("w"), F.col("level"))
    per = per.withColumn("level", F.max(open_).over(everything))
    target = F.least("cap", F.col("w") * F.coalesce("level", F.lit(0.0)))
    return per.select("__src", "source_size", "n_rows", target.alias("target"), "tilt")


def _position(share: Column, tilt: Column) -> Column:
    """Inverse of t + a (t^2 - t) at ``share``."""
    b = 1 - tilt
    root = F.abs((F.sqrt(F.greatest(b * b + 4 * tilt * share, F.lit(0.0))) - b) / (2 * tilt))
    return F.when(tilt == 0, share).otherwise(root)


def _source(source_col: str) -> Column:
    return F.coalesce(F.concat(F.lit("="), F.col(f"`{source_col}`").cast("string")), F.lit("~"))


def _key(id_col: str) -> Column:
    return F.md5(F.coalesce(F.col(f"`{id_col}`").cast("string"), F.lit("")).cast("binary"))


def _size(text_col: str) -> Column:
    return F.size(words(F.col(f"`{text_col}`"))).cast("long")


def readings(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source",
             weights=WEIGHTS, tilts=TILTS, max_epochs: int = MAX_EPOCHS, carry: tuple[str, ...] = ()) -> DataFrame:
    """``doc_id, source, size, source_size, target, tilt, total, cum, taken`` of every row, and
    ``carry``: ``cum`` is what the source's rows before it hold, ``total`` its target in whole
    words. ``__src, __bucket, __key`` tell its place in the order."""
    sizes = docs.select(
        F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{source_col}`").alias("source"),
        _source(source_col).alias("__src"), _size(text_col).alias("size"), _key(id_col).alias("__key"), *carry,
    )
    sizes = materialize(sizes, "sizes")
    targets = materialize(source_targets(sizes, weights, tilts, max_epochs), "targets")
    most = targets.agg(F.max("n_rows")).first()[0] or 1
    digits = min(8, max(2, math.ceil(math.log(max(1, most / BUCKET_ROWS), 16))))
    rows = sizes.withColumn("__bucket", F.substring("__key", 1, digits))
    totals = rows.groupBy("__src", "__bucket").agg(F.sum("size").alias("__sum"))
    before = F.sum("__sum").over(Window.partitionBy("__src").orderBy("__bucket")) - F.col("__sum")
    heads = totals.select("__src", "__bucket", before.alias("__head")).join(targets, "__src")
    within = Window.partitionBy("__src", "__bucket").orderBy("__key", "doc_id", "size")
    within = within.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = rows.withColumn("__cum", F.sum("size").over(within) - F.col("size"))
    rows = rows.join(heads, ["__src", "__bucket"])
    rows = rows.withColumn("cum", F.col("__head") + F.col("__cum")).withColumn("total", F.round("target").cast("long"))
    return rows.select("doc_id", "source", "size", "source_size", "target", "tilt", "total", "cum", _taken().alias("taken"), "__src", "__bucket", "__key", *carry)


def _taken() -> Column:
    """Words that the mix takes of a row with ``size, cum, source_size, total``."""
    passes = F.when(F.col("source_size") > 0, F.floor(F.col("total") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    rest = F.col("total") - passes * F.col("source_size")
    return passes * F.col("size") + F.least(F.greatest(rest - F.col("cum"), F.lit(0)), F.col("size"))


def _copies() -> Column:
    """Whole readings: the one document at which a source's last pass ends is rounded."""
    return F.when(F.col("size") > 0, F.floor(_taken() / F.col("size") + 0.5)).otherwise(0).cast("int")


def _at() -> Column:
    """Position of reading ``nth``."""
    share = (F.col("nth") * F.col("source_size") + F.col("cum")) / F.col("total")
    return _position(F.least(share, F.lit(1.0)), F.col("tilt"))


def mix(docs: DataFrame, **params) -> DataFrame:
    """``doc_id, source, size, source_size, target, taken, position``; ``position`` is that of
    the first reading, null where nothing is taken. A source's taken words add up to its
    target, rounded: whole passes over the source, then the head of one more pass."""
    position = F.when(F.col("taken") > 0, _position(F.col("cum") / F.col("total"), F.col("tilt")))
    out = readings(docs, **params).select("doc_id", "source", "size", "source_size", "target", "taken", position.alias("position"))
    return out.orderBy(F.col("position").asc_nulls_last(), "doc_id")


def mixed_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source",
                    weights=WEIGHTS, tilts=TILTS, max_epochs: int = MAX_EPOCHS, most_starts: int = MOST_STARTS) -> DataFrame:
    """The mix as documents in the order of training: each as many times as its taken words
    make whole readings, the n-th reading at the position of the n-th pass; columns stay as they
    are."""
    how = (weights, tilts, max_epochs)
    slices = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    plan = readings(docs, id_col, text_col, source_col, *how)
    # rows that tie go to the slice of the first of them
    ties = Window.partitionBy("__src", "__bucket", "__key", "doc_id", "size")
    plan = plan.withColumn("copies", F.max(_copies()).over(ties)).withColumn("cum", F.min("cum").over(ties)).where("copies > 0")
    plan = plan.withColumn("nth", F.explode(F.sequence(F.lit(0), F.col("copies") - 1)))
    plan = plan.withColumn("slice", F.least(F.floor(_at() * slices), F.lit(slices - 1)).cast("int"))
    place = F.struct("nth", "__key", "doc_id", "size")
    starts = plan.groupBy("__src", "source_size", "total", "tilt", "nth", "slice").agg(F.min(place).alias("first"), F.max(place).alias("last"), F.min("cum").alias("cum"))
    starts = materialize(starts, "starts")
    count, most = starts.groupBy("__src").count().agg(F.coalesce(F.sum("count"), F.lit(0)), F.coalesce(F.max("count"), F.lit(1))).first()
    if count > most_starts:
        return _mixed_by_key(docs, id_col, text_col, source_col, *how)
    table = starts.groupBy("__src", "source_size", "total", "tilt").agg(F.sort_array(F.collect_list(F.struct("first", "nth", "slice", "cum", "last"))).alias("starts"))
    table = table.select("*", F.transform("starts", lambda x: x["first"]).alias("firsts"))
    rows = docs.select(whole_row(docs).alias("row"), F.col(f"`{id_col}`").alias("doc_id"), _source(source_col).alias("__src"), _key(id_col).alias("__key"), _size(text_col).alias("size"))
    rows = rows.join(F.broadcast(table), "__src")
    probe = lambda n: F.struct(n.cast("int").alias("nth"), "__key", "doc_id", "size")
    found = F.transform(F.sequence(F.lit(0), F.lit(max_epochs - 1)), lambda n: F.struct(n.alias("n"), probe(n).alias("p"), F.get("starts", find_last(F.col("firsts"), probe(n), most)).alias("s")))
    found = F.filter(found, lambda x: (x["s"]["nth"] == x["n"]) & (x["p"] <= x["s"]["last"]))
    rows = rows.select("row", "doc_id", "__src", "__key", "size", "source_size", "total", "tilt", F.explode(F.when(F.col("size") > 0, found)).alias("x"))
    rows = rows.select("*", F.col("x.n").alias("nth"), F.col("x.s.slice").alias("slice"), F.col("x.s.cum").alias("head")).drop("x")
    rows = rows.repartitionById(slices, F.col("slice"))
    order = Window.partitionBy("slice", "__src", "nth").orderBy("__key", "doc_id", "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = rows.withColumn("cum", F.col("head") + F.sum("size").over(order) - F.col("size")).where(F.col("nth") < _copies())
    return rows.withColumn("at", _at()).sortWithinPartitions("at", "doc_id", "nth").select("row.*")


def _mixed_by_key(docs: DataFrame, id_col: str, text_col: str, source_col: str, weights, tilts, max_epochs: int) -> DataFrame:
    """The same by a join of documents with their readings and a range sort."""
    rows = docs.select(whole_row(docs).alias("row"), F.monotonically_increasing_id().alias("uid"))
    rows = materialize(rows, "rows")
    narrow = rows.select(F.col(f"row.`{id_col}`").alias("i"), F.col(f"row.`{text_col}`").alias("t"), F.col(f"row.`{source_col}`").alias("s"), "uid")
    plan = readings(narrow, "i", "t", "s", weights, tilts, max_epochs, carry=("uid",))
    plan = plan.withColumn("copies", _copies()).where("copies > 0").withColumn("nth", F.explode(F.sequence(F.lit(0), F.col("copies") - 1)))
    return rows.join(plan.select("uid", "doc_id", "nth", _at().alias("at")), "uid").orderBy("at", "doc_id", "nth").select("row.*")


def op8_curriculum_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = mix(documents(spark, sf_dir))
    return rows.select("doc_id", "size", "source_size", F.round("target", 3).alias("target"), "taken", F.round("position", 9).alias("position"))


ORACLE_SQL = r"""
WITH s AS (
  SELECT doc_id, source, md5(CAST(doc_id AS VARCHAR)) AS k,
         len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS size
  FROM documents),
p AS (
  SELECT source, sum(size) AS source_size, row_number() OVER (ORDER BY source NULLS LAST) AS nth
  FROM s GROUP BY source),
w AS (
  SELECT *, CASE (nth - 1) % 3 WHEN 0 THEN 5e0 WHEN 1 THEN 2e0 ELSE 1e0 END AS w,
         CASE (nth - 1) % 3 WHEN 0 THEN -5e-1 WHEN 1 THEN 0e0 ELSE 5e-1 END AS a, 3e0 * source_size AS cap FROM p),
l AS (
  SELECT *, (sum(source_size) OVER () - coalesce(sum(cap) OVER (ORDER BY cap / w, nth ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
         / sum(w) OVER (ORDER BY cap / w, nth ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS lam FROM w),
t AS (
  SELECT source, a, CAST(source_size AS BIGINT) AS source_size,
         least(cap, w * (SELECT max(lam) FROM l WHERE lam <= cap / w)) AS target FROM l),
c AS (
  SELECT s.doc_id, s.size, t.*, CAST(round(t.target) AS BIGINT) AS total,
         CAST(coalesce(sum(s.size) OVER (PARTITION BY s.source ORDER BY s.k, s.doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS cum
  FROM s JOIN t ON s.source IS NOT DISTINCT FROM t.source),
f AS (
  SELECT *, CASE WHEN source_size > 0 THEN total // source_size ELSE 0 END AS passes FROM c),
g AS (
  SELECT *, CAST(passes * size + least(greatest(total - passes * source_size - cum, 0), size) AS BIGINT) AS taken,
         cum / total AS share FROM f)
SELECT doc_id, CAST(size AS BIGINT) AS size, source_size, round(target, 3) AS target, taken,
       CASE WHEN taken > 0 THEN round(CASE WHEN a = 0 THEN share
         ELSE abs((sqrt(greatest((1 - a) * (1 - a) + 4 * a * share, 0)) - (1 - a)) / (2 * a)) END, 9) END AS position
FROM g
"""
