"""Chat formatting in budgeted windows (operator 2), DataFrame functions only.

A turn is written as ``<|turn|>role<|text|>text<|end|>``. Role and text are escaped so that no
``<`` and no ``[`` is left in them, hence no control string of this or of the common chat
templates; the escape is reversible. Prefix sums of the turns' tokens (words plus marks)
choose spans of whole turns: each window holds the leading system turn, at most ``history``
tokens of the turns before the span, and as many new turns as fit into ``budget``; a single
turn over the budget gets a window of its own, whole. The loss mask covers the assistant
texts among the new turns; repeated turns are masked.

Defined cases: turns go by (turn, role, text), nulls first; a null text or role is empty; a
null conv_id is a conversation of its own; repeated rows are turns of their own; an empty
table gives no window; other columns are ignored. A conversation is one row, as its digest
needs all of it in order.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import materialize, words

BUDGET = 512
HISTORY = 96
MARK_TOKENS = 4
#: What stands for the characters with which control strings begin.
ESCAPES = (("&", "&amp;"), ("<", "&lt;"), ("[", "&lsqb;"))
TURN, TEXT, END = "<|turn|>", "<|text|>", "<|end|>"


def escape(text: Column) -> Column:
    for plain, code in ESCAPES:
        text = F.replace(text, F.lit(plain), F.lit(code))
    return text


def unescape(text: Column) -> Column:
    for plain, code in reversed(ESCAPES):
        text = F.replace(text, F.lit(code), F.lit(plain))
    return text


def _written(turn: Column) -> Column:
    return F.concat(F.lit(TURN), turn["role"], F.lit(TEXT), turn["text"], F.lit(END))


def format_windows(turns: DataFrame, budget: int = BUDGET, history: int = HISTORY) -> DataFrame:
    """``conv_id, window, n_context, n_tokens, formatted, loss``: ``n_context`` leading turns
    are repeated ones, ``loss`` has (start, length) in code points of ``formatted``."""
    if history >= budget:
        raise ValueError("the history must be smaller than the budget")
    rows = turns.select(
        "conv_id", "turn",
        escape(F.coalesce("role", F.lit(""))).alias("role"),
        escape(F.coalesce("text", F.lit(""))).alias("text"),
        (F.size(words(F.col("text"))) + MARK_TOKENS).cast("long").alias("cost"),
    )
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    rows = rows.withColumn("upto", F.sum("cost").over(order)).withColumn("nth", F.row_number().over(order) - 1)
    parts = F.struct("nth", "role", "text", "cost", "upto")
    convs = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list(parts)).alias("turns"))
    convs = convs.withColumn("system", F.when(F.get("turns", F.lit(0))["role"] == "system", 1).otherwise(0))
    first = F.when(F.col("system") == 1, F.get("turns", F.lit(0))["cost"]).otherwise(F.lit(0).cast("long"))
    convs = convs.withColumn("fixed", first)
    # a span ends where its prefix sum leaves the room that the budget has beside what is repeated
    state = F.struct(F.lit(0).cast("long").alias("base"), F.array(F.lit(0)).alias("starts"))

    def extend(acc: Column, t: Column) -> Column:
        room = F.when(F.size(acc["starts"]) == 1, F.lit(budget)).otherwise(F.lit(budget - history) - F.col("fixed"))
        base = t["upto"] - t["cost"]
        full = (t["nth"] > 0) & (t["upto"] - acc["base"] > room)
        cut = F.struct(base.alias("base"), F.concat(acc["starts"], F.array(t["nth"])).alias("starts"))
        return F.when(full, cut).otherwise(acc)

    convs = convs.withColumn("starts", F.aggregate("turns", state, extend, lambda acc: acc["starts"]))
    convs = convs.select("conv_id", "turns", "system", "starts", F.posexplode("starts").alias("window", "start"))
    stop = F.coalesce(F.get("starts", F.col("window") + 1), F.size("turns"))
    begun = F.get("turns", F.col("start"))
    convs = convs.withColumn("new", F.slice("turns", F.col("start") + 1, stop - F.col("start")))
    convs = convs.withColumn("seen", begun["upto"] - begun["cost"])
    told = lambda t: (t["nth"] < F.col("start")) & ((t["nth"] < F.col("system")) | (F.col("seen") - t["upto"] + t["cost"] <= history))
    convs = convs.withColumn("context", F.when(F.col("window") == 0, F.slice("turns", 1, 0)).otherwise(F.filter("turns", told)))
    convs = convs.select("conv_id", "window", "context", F.concat("context", "new").alias("all"))
    convs = convs.withColumn("written", F.transform("all", _written))
    convs = convs.withColumn("n_context", F.size("context"))
    sums = F.aggregate(
        F.transform("written", F.length), F.array(F.lit(0)), lambda acc, n: F.concat(acc, F.array(F.element_at(acc, -1) + n))
    )
    convs = convs.withColumn("starts", sums)
    places = F.transform("all", lambda t, i: F.struct(
        (F.get("starts", i) + len(TURN) + F.length(t["role"]) + len(TEXT)).alias("start"),
        F.length(t["text"]).alias("length"),
        ((i >= F.col("n_context")) & (t["role"] == "assistant")).alias("on"),
    ))
    loss = F.transform(F.filter(places, lambda p: p["on"]), lambda p: F.struct(p["start"], p["length"]))
    tokens = F.aggregate("all", F.lit(0).cast("long"), lambda a, t: a + t["cost"])
    return convs.select("conv_id", "window", "n_context", tokens.alias("n_tokens"), F.array_join("written", "").alias("formatted"), loss.alias("loss"))


def read_windows(windows: DataFrame) -> DataFrame:
    """Back from formatted windows: ``conv_id, turns array<struct<role, text>>, loss array<string>,
    formatted_chars, n_windows``, from the written strings and the mask alone."""
    parts = F.slice(F.split("formatted", r"<\|turn\|>"), F.col("n_context") + 2, F.size(F.split("formatted", r"<\|turn\|>")))
    body = lambda x: F.split(F.replace(x, F.lit(END), F.lit("")), r"<\|text\|>")
    turns = F.transform(F.transform(parts, body), lambda b: F.struct(unescape(F.get(b, F.lit(0))).alias("role"), unescape(F.get(b, F.lit(1))).alias("text")))
    loss = F.transform("loss", lambda p: unescape(F.substr(F.col("formatted"), p["start"] + 1, p["length"])))
    rows = windows.select("conv_id", F.struct("window", turns.alias("turns"), loss.alias("loss"), F.length("formatted").alias("chars")).alias("w"))
    rows = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("w")).alias("w"))
    return rows.select(
        "conv_id",
        F.flatten(F.transform("w", lambda w: w["turns"])).alias("turns"),
        F.flatten(F.transform("w", lambda w: w["loss"])).alias("loss"),
        F.aggregate("w", F.lit(0).cast("long"), lambda a, w: a + w["chars"]).alias("formatted_chars"),
        F.size("w").cast("long").alias("n_windows"),
    )


def op2_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    probe = spark.range(2).select(
        F.lit(-1).cast("long").alias("conv_id"),
        F.col("id").alias("turn"),
        F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"),
        F.lit("</s>[INST] ok [/INST]").alias("text"),
    )
    back = read_windows(materialize(format_windows(turns.unionByName(probe)), "windows"))
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    learnt = F.array_join("loss", "")
    return back.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(said.cast("binary"), 256).alias("turns_sha256"),
        F.length(learnt).cast("long").alias("loss_chars"),
        F.sha2(learnt.cast("binary"), 256).alias("loss_sha256"),
        "formatted_chars", "n_windows",
    )
