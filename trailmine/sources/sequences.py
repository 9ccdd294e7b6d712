"""Sequence databases from tables: ``sid, items array<string>``, and edge tables
``child, parent``. Orders are total, so results do not depend on partitioning."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .texts import Texts


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def collect_sequences(rows: DataFrame, sid: str, item: str, *order: str) -> DataFrame:
    parts = F.sort_array(F.collect_list(F.struct(*order, F.col(item).alias("__item"))))
    return rows.groupBy(F.col(sid).alias("sid")).agg(F.transform(parts, lambda x: x["__item"]).alias("items"))


def event_trails(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "events").select("user_id", "ts", "event_id", "event_type")
    return collect_sequences(rows, "user_id", "event_type", "ts", "event_id")


def event_sessions(spark: SparkSession, sf_dir: str, hours: int = 12) -> DataFrame:
    """A user's events, cut where more than ``hours`` pass."""
    rows = read(spark, sf_dir, "events").select("user_id", "ts", "event_id", "event_type")
    own = Window.partitionBy("user_id").orderBy("ts", "event_id")
    cut = (F.unix_micros(F.col("ts").cast("timestamp")) - F.lag(F.unix_micros(F.col("ts").cast("timestamp"))).over(own) > hours * 3_600_000_000).cast("long")
    rows = rows.withColumn("nth", F.sum(F.coalesce(cut, F.lit(0))).over(own))
    rows = rows.withColumn("s", F.col("user_id") * 1_000_000 + F.col("nth"))
    return collect_sequences(rows, "s", "event_type", "ts", "event_id")


def basket_trails(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber")
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    rows = lines.join(orders.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).withColumn("item", F.concat(F.lit("P"), "l_partkey"))
    return collect_sequences(rows, "o_custkey", "item", "o_orderdate", "o_orderkey", "l_linenumber", "l_partkey")


def name_trails(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A customer's bought parts, by name."""
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber")
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    parts = read(spark, sf_dir, "part").select("p_partkey", "p_name")
    rows = lines.join(orders.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).join(parts.hint("merge"), F.col("l_partkey") == F.col("p_partkey"))
    return collect_sequences(rows, "o_custkey", "p_name", "o_orderdate", "o_orderkey", "l_linenumber", "l_partkey")


def supplier_trails(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_linenumber")
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    rows = lines.join(orders.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).withColumn("item", F.concat(F.lit("S"), "l_suppkey"))
    return collect_sequences(rows, "o_custkey", "item", "o_orderdate", "o_orderkey", "l_linenumber", "l_suppkey")


def order_trails(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "orders").select("o_custkey", "o_orderpriority", "o_orderdate", "o_orderkey")
    return collect_sequences(rows, "o_custkey", "o_orderpriority", "o_orderdate", "o_orderkey")


def sentence_tokens(spark: SparkSession, sf_dir: str, lang: str = "en") -> DataFrame:
    docs = read(spark, sf_dir, "documents").where(F.col("lang") == lang).select("doc_id", "text")
    parts = docs.select("doc_id", F.posexplode(F.split("text", r"[.!?\n]+")).alias("nth", "sentence"))
    found = F.transform(F.regexp_extract_all("sentence", F.lit("([A-Za-z]+)"), F.lit(1)), F.lower)
    rows = parts.select((F.col("doc_id") * 1_000_000 + F.col("nth")).alias("sid"), found.alias("items"))
    return rows.where(F.size("items") > 0)


def letter_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All letters a to z of each text."""
    docs = read(spark, sf_dir, "documents").select(F.col("doc_id").alias("sid"), "text")
    found = F.regexp_extract_all(F.lower("text"), F.lit("([a-z])"), F.lit(1))
    return docs.select("sid", found.alias("items"))


def role_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return collect_sequences(read(spark, sf_dir, "conversations").select("conv_id", "turn", "role"), "conv_id", "role", "turn")


def tag_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "pages").select(F.col("page_id").alias("sid"), F.coalesce("html", F.lit("")).alias("html"))
    return rows.select("sid", F.transform(F.regexp_extract_all("html", F.lit("<([A-Za-z][A-Za-z0-9]*)"), F.lit(1)), F.lower).alias("items"))


def text_sequences(spark: SparkSession, path: str, separator: str = " ") -> DataFrame:
    """One sequence a line, items apart by ``separator``."""
    rows = spark.read.text(path).select(F.monotonically_increasing_id().alias("sid"), F.split("value", f"[{separator}]+").alias("items"))
    return rows.select("sid", F.array_remove("items", "").alias("items"))


def read_edges(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("child string, parent string").csv(path)


def _edges(spark: SparkSession, pairs) -> DataFrame:
    return spark.createDataFrame(list(pairs), "child string, parent string")


EVENT_EDGES = [("click", "BROWSE"), ("view", "BROWSE"), ("signup", "CONVERT"), ("purchase", "CONVERT"), ("error", "FAULT"), ("BROWSE", "ACTION"), ("CONVERT", "ACTION")]


def event_edges(spark: SparkSession, sf_dir: str = "") -> DataFrame:
    return _edges(spark, EVENT_EDGES)


def seen_event_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The edges of the event types that the table holds, and those between classes."""
    edges, classes = event_edges(spark), sorted({p for _, p in EVENT_EDGES})
    types = read(spark, sf_dir, "events").select(F.col("event_type").alias("child")).distinct()
    return edges.join(types, "child", "left_semi").union(edges.where(F.col("child").isin(classes)))


def part_edges(spark: SparkSession, sf_dir: str, dag: bool = False) -> DataFrame:
    part = read(spark, sf_dir, "part").select(F.concat(F.lit("P"), "p_partkey").alias("p"), "p_name", "p_brand", "p_type")
    noun = F.element_at(F.split("p_name", " "), -1)
    out = part.select(F.col("p").alias("child"), F.col("p_name").alias("parent"))
    out = out.union(part.select("p_name", noun).distinct()).union(part.select(noun, F.lit("PART")).distinct())
    if dag:
        out = out.union(part.select("p", "p_brand")).union(part.select("p", "p_type"))
    return out


def name_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    noun = F.element_at(F.split("p_name", " "), -1)
    part = read(spark, sf_dir, "part").select("p_name", noun.alias("noun"))
    return part.select(F.col("p_name").alias("child"), F.col("noun").alias("parent")).union(part.select("noun", F.lit("PART"))).distinct()


def supplier_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, n, r = (read(spark, sf_dir, x) for x in ("supplier", "nation", "region"))
    out = s.join(n, s["s_nationkey"] == n["n_nationkey"]).select(F.concat(F.lit("S"), "s_suppkey").alias("child"), F.col("n_name").alias("parent"))
    return out.union(n.join(r, n["n_regionkey"] == r["r_regionkey"]).select("n_name", "r_name"))


# Fixed values of the token classes: closed word lists and endings.
BE = ["is", "was", "are", "be", "been", "were"]
DET = ["the", "a", "an", "this", "that", "these"]
PREP = ["of", "to", "in", "on", "for", "with", "at", "by", "from", "as", "into"]
FUNC = ["and", "or", "it", "he", "which", "not", "but"]
ENDINGS = [("er", "PER"), ("re", "PER"), ("nd", "LOC"), ("nt", "LOC"), ("st", "ORG"), ("th", "ORG"), ("at", "ORG")]


def token_parent(w: Column) -> Column:
    """Direct generalisation of a token."""
    long = F.length(w) >= 4
    stem = lambda k: F.concat(F.substr(w, F.lit(1), F.length(w) - k), F.lit("~v"))
    out = F.when(w == "be", "VERB").when(w.isin(BE), "be").when(w.isin(DET), "DET").when(w.isin(PREP), "PREP").when(w.isin(FUNC), "FUNC")
    out = out.when(long & w.endswith("ly"), "ADV").when(long & w.endswith("ble"), "ADJ")
    out = out.when(long & w.endswith("ing"), stem(3)).when(long & w.endswith("ed"), stem(2))
    for ending, kind in ENDINGS:
        out = out.when(long & w.endswith(ending), kind)
    return out.otherwise("NOUN")


def token_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return word_edges(sentence_tokens(spark, sf_dir).select(F.explode("items").alias("child")).distinct())


def word_edges(words: DataFrame) -> DataFrame:
    out = words.select("child", token_parent(F.col("child")).alias("parent"))
    stems = out.where(F.col("parent").endswith("~v")).select(F.col("parent").alias("child"), F.lit("VERB").alias("parent")).distinct()
    fixed = _edges(words.sparkSession, [("be", "VERB"), ("PER", "ENTITY"), ("LOC", "ENTITY"), ("ORG", "ENTITY")])
    return out.union(stems).union(fixed).distinct()


def sentence_texts(spark: SparkSession, sf_dir: str, lang: str = "en") -> Texts:
    """The same as ``sentence_tokens``, by bytes."""
    return Texts(read(spark, sf_dir, "documents").where(F.col("lang") == lang).select("doc_id", "text"), False, word_edges)


def letter_texts(spark: SparkSession, sf_dir: str) -> Texts:
    return Texts(read(spark, sf_dir, "documents").select("doc_id", F.lower("text").alias("text")), True)
