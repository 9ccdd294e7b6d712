"""Connected components by alternating large and small stars; all steps are joins and
aggregates on the edges, which stay distributed."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize

#: Parts into which the edges of one node are dealt for the joins.
SALTS = 8


def _with_least(pairs: DataFrame) -> DataFrame:
    """``u, v, m`` with the least of ``u`` and its partners; the edges of a hub are salted."""
    least = pairs.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    least = least.select("u", "m", F.explode(F.array(*map(F.lit, range(SALTS)))).alias("s"))
    salted = pairs.withColumn("s", F.pmod(F.xxhash64("v"), F.lit(SALTS)).cast("int"))
    return salted.join(least, ["u", "s"]).select("u", "v", "m")


def large_star(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    return _with_least(both).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()


def small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    hung = _with_least(down)
    pairs = hung.select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e"))
    return pairs.select("e.*").where("u <> v").distinct()


def components(edges: DataFrame) -> DataFrame:
    """``node, root`` of every node on an edge but the roots; ``edges`` has ``u, v``."""
    now = materialize(edges.select("u", "v").where("u <> v").distinct(), "edges")
    mark = None
    while True:
        seen = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if seen[0] == 0 or tuple(seen) == mark:
            return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
        mark = tuple(seen)
        now = materialize(small_star(large_star(now)), "edges")
