"""Quality rules with cross-document line frequency (operator 3), DataFrame functions only.

Base rules look at one text. The cross-document rule normalises every line (lower case,
white space collapsed), hashes it, and counts for each host (column ``source``) the documents
that hold the line. A line is above the limit if more than ``min_docs`` documents of its host
hold it, however large the host (a ``share`` of the host's documents can be asked for besides,
but no query does); it is removed everywhere but in the document with the
smallest id, so that of a group of copies one keeps its text. A document is depleted, and
rejected, if the removed lines held more than ``depleted`` percent of its words.

Two passes over the texts. The first sends line hashes alone, counted per (host, line)
map-side before the shuffle, so neither a hot host nor a hot line gathers in one task. The
second decides each document where it is read: its host's lines above the limit come as one
sorted array by broadcast, in which every line is sought by bisection, so no text is shuffled.
Those arrays are broadcast only up to ``HOST_LINES`` lines of a host and ``ALL_LINES`` in all
(24 bytes each); beyond, rows get a key in a written table, their lines are joined with the
lines above the limit (salted, as such lines are frequent) and the verdicts joined back by key.
Both ways give the same rows. Line hashes are 64 bits wide, compared within a host.

Defined cases: a null text is empty and fails the base rules; a null source is a host of its
own; every row is decided alone, whether its id is null, its own or repeated, and is returned
once at most; a line whose holders all lack an id stays; lines without a word are never
counted; a text of any length is one row and is worked on whole; other columns are carried
under any name; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SPACES, documents, fence, find_last, materialize, whole_row, whole_text, words

MIN_WORDS = 50
MAX_REPEATED_PERCENT = 50
MIN_DOCS = 20
DEPLETED_PERCENT = 50
SYMBOLS = r"[^#*$%&|<>]+"
#: Lines above the limit that are broadcast: of one host, and of all.
HOST_LINES = 4096
ALL_LINES = 1 << 18
#: Parts into which a frequent line's holders are dealt where they are joined.
SALTS = 32


def _line_key(line: Column) -> Column:
    return F.xxhash64(F.lower(F.trim(F.regexp_replace(line, SPACES, " "))))


def _repeated(hashes: Column) -> Column:
    """Words inside 3-word windows that occur twice or more; ``hashes`` has one hash per window."""
    at = F.array_sort(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), F.lit(None)).otherwise(at)


def _lines(text: Column) -> Column:
    """Lines with a word."""
    return F.filter(F.split(text, "\n"), lambda x: F.length(F.regexp_replace(x, SPACES, "")) > 0)


def _host(host_col: str) -> Column:
    return F.coalesce(F.concat(F.lit("="), F.col(f"`{host_col}`").cast("string")), F.lit("~"))


def _measured(rows: DataFrame) -> DataFrame:
    """To ``row, id, host`` of documents with ``text``: the base measures and ``lines``, which
    has (key, words) of each line with a word."""
    step = rows.select(
        "row", "id", "host",
        words(F.col("text")).alias("w"),
        F.length(F.regexp_replace("text", SYMBOLS, "")).cast("long").alias("n_symbols"),
        _lines(F.col("text")).alias("lines"),
    )
    spots = F.sequence(F.lit(1), F.size("w") - 2)
    window = lambda i: F.xxhash64(F.get("w", i - 1), F.get("w", i), F.get("w", i + 1))
    step = step.select(
        "row", "id", "host", "n_symbols", "lines",
        F.size("w").cast("long").alias("n_words"),
        F.length(F.array_join("w", "")).cast("long").alias("word_chars"),
        F.when(F.size("w") >= 4, F.transform(spots, window)).otherwise(F.array().cast("array<long>")).alias("h"),
    )
    step = step.withColumn("s", _repeated(F.col("h")))
    same = lambda i: (F.get("s", i)["h"] == F.get("s", i + 1)["h"])
    twice = lambda x, i: F.coalesce(same(i), F.lit(False)) | F.coalesce((i > 0) & same(i - 1), F.lit(False))
    spots = F.array_sort(F.transform(F.filter("s", twice), lambda x: x["i"]))
    step = step.withColumn("p", F.when(F.col("s").isNotNull(), spots).otherwise(F.array().cast("array<int>")))
    gaps = F.transform("p", lambda x, i: F.least(F.lit(3), F.coalesce(F.get("p", i + 1) - x, F.lit(3))))
    step = step.withColumn("n_repeat_words", F.aggregate(gaps, F.lit(0).cast("long"), lambda a, x: a + x))
    keyed = F.transform("lines", lambda x: F.struct(_line_key(x).alias("key"), F.size(words(x)).alias("n")))
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEATED_PERCENT * F.col("n_words"))
    return fence(step.select(
        "row", "id", "host", "n_words", "word_chars", "n_symbols",
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        "n_repeat_words", failed.alias("base_failed"), keyed.alias("lines"),
    ))


def frequent_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", min_docs: int = MIN_DOCS, share: float = 0.0) -> DataFrame:
    """``host, key, n_docs, first_id`` of the lines above their host's limit."""
    rows = docs.select(F.col(f"`{id_col}`").alias("id"), _host(host_col).alias("host"), whole_text(F.col(f"`{text_col}`")).alias("text"))
    lines = rows.select("id", "host", F.explode(F.array_distinct(F.transform(_lines(F.col("text")), _line_key))).alias("key"))
    counts = lines.groupBy("host", "key").agg(F.count(F.lit(1)).alias("n_docs"), F.min("id").alias("first_id"))
    counts = counts.where(F.col("n_docs") > min_docs)
    if share:
        hosts = rows.groupBy("host").agg(F.count(F.lit(1)).alias("host_docs"))
        counts = counts.join(hosts, "host").where(F.col("n_docs") > share * F.col("host_docs"))
    return counts.select("host", "key", "n_docs", "first_id")


def _decided(docs: DataFrame, row: Column, id_col: str, text_col: str, host_col: str, min_docs: int, share: float, depleted: int, host_lines: int) -> DataFrame:
    """``row, id``, the measures, ``removed_keys, removed_words, removed_lines, kept``."""
    frequent = materialize(frequent_lines(docs, id_col, text_col, host_col, min_docs, share), "frequent")
    most, total = frequent.groupBy("host").count().agg(F.coalesce(F.max("count"), F.lit(0)), F.coalesce(F.sum("count"), F.lit(0))).first()
    rows = docs.select(row.alias("row"), F.col(f"`{id_col}`").alias("id"), _host(host_col).alias("host"), whole_text(F.col(f"`{text_col}`")).alias("text"))
    if most <= host_lines and total <= ALL_LINES:
        by_host = frequent.groupBy("host").agg(F.sort_array(F.collect_list(F.struct("key", "first_id"))).alias("f"))
        by_host = by_host.select("host", F.transform("f", lambda x: x["key"]).alias("keys"), F.transform("f", lambda x: x["first_id"]).alias("firsts"))
        out = _measured(rows).join(F.broadcast(by_host), "host", "left")
        at = lambda x: find_last(F.col("keys"), x["key"], max(1, most))
        gone = lambda x: (F.get("keys", at(x)) == x["key"]) & ~F.col("id").eqNullSafe(F.get("firsts", at(x)))
        none = F.array().cast(out.schema["lines"].dataType)
        out = out.withColumn("removed", F.when(F.col("keys").isNull(), none).otherwise(F.filter("lines", gone)))
    else:
        rows = materialize(rows.withColumn("uid", F.monotonically_increasing_id()), "rows")
        out = _measured(rows.select(F.struct("row", "uid").alias("row"), "id", "host", "text"))
        out = materialize(out.select("row.*", *[c for c in out.columns if c != "row"]), "measures")
        lines = out.select("uid", "host", "id", F.explode("lines").alias("l"), F.pmod(F.xxhash64("uid"), F.lit(SALTS)).cast("int").alias("salt")).select("uid", "id", "host", "l", F.col("l.key").alias("key"), "salt")
        spread = frequent.select("host", "key", "first_id", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
        hits = lines.join(spread, ["host", "key", "salt"]).where(~F.col("id").eqNullSafe(F.col("first_id")))
        hits = hits.groupBy("uid").agg(F.collect_list("l").alias("removed"))
        out = out.join(hits, "uid", "left").drop("uid")
        out = out.withColumn("removed", F.coalesce("removed", F.array().cast(out.schema["lines"].dataType)))
    out = out.withColumn("removed_keys", F.array_distinct(F.transform("removed", lambda x: x["key"])))
    out = out.withColumn("removed_words", F.aggregate("removed", F.lit(0).cast("long"), lambda a, x: a + x["n"]))
    kept = ~F.col("base_failed") & (100 * F.col("removed_words") <= depleted * F.col("n_words"))
    out = out.select("*", F.size("removed_keys").cast("long").alias("removed_lines"), kept.alias("kept"))
    return fence(out.drop("lines", "removed", "keys", "firsts", "host"))


def verdicts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source",
             min_docs: int = MIN_DOCS, share: float = 0.0, depleted: int = DEPLETED_PERCENT, host_lines: int = HOST_LINES) -> DataFrame:
    """One row per document: ``doc_id``, the measures, ``removed_keys`` (distinct lines),
    ``removed_lines``, ``removed_words``, ``kept``."""
    out = _decided(docs, F.lit(0), id_col, text_col, host_col, min_docs, share, depleted, host_lines)
    return out.withColumnRenamed("id", "doc_id").drop("row")


def clean_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source",
                    min_docs: int = MIN_DOCS, share: float = 0.0, depleted: int = DEPLETED_PERCENT, host_lines: int = HOST_LINES) -> DataFrame:
    """The documents that stay, with their columns; lines above the limit are taken out of
    their texts, and ``n_chars``, where there is such a column, is that of the new text."""
    out = _decided(docs, whole_row(docs), id_col, text_col, host_col, min_docs, share, depleted, host_lines)
    whole = out["row"][text_col]
    text = F.array_join(F.filter(F.split(whole, "\n"), lambda x: ~F.array_contains("removed_keys", _line_key(x))), "\n")
    out = out.withColumn("new", F.when(F.col("removed_lines") > 0, text))
    new = {text_col: F.coalesce("new", whole), "n_chars": F.coalesce(F.length("new"), out["row"]["n_chars"])} if "n_chars" in docs.columns else {text_col: F.coalesce("new", whole)}
    fields = [(new[c] if c in new else out["row"][c]).cast(t).alias(c) for c, t in docs.dtypes]
    # the choice of rows is made by exploding none or one, so that nothing above is computed twice for a filter
    return out.select(F.explode(F.when(F.col("kept"), F.array(F.struct(*fields)))).alias("row")).select("row.*")


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    cols = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "removed_lines", "removed_words"]
    return verdicts(documents(spark, sf_dir)).select(*cols)


ORACLE_SQL = r"""
WITH d AS (
  SELECT row_number() OVER () AS r, doc_id, coalesce('=' || source, '~') AS host, coalesce(text, '') AS t,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w,
         [x FOR x IN string_split(coalesce(text, ''), chr(10)) IF regexp_matches(x, '[^\x20\x09-\x0D]')] AS ls
  FROM documents),
grams AS (
  SELECT r, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS g FROM (SELECT r, w, unnest(range(1, len(w) - 1)) AS i FROM d)),
spots AS (
  SELECT r, i FROM (SELECT *, count(*) OVER (PARTITION BY r, g) AS n FROM grams) WHERE n > 1),
covered AS (
  SELECT r, sum(gap) AS n FROM (SELECT r, least(3, coalesce(lead(i) OVER (PARTITION BY r ORDER BY i) - i, 3)) AS gap FROM spots) GROUP BY r),
base AS (
  SELECT d.r, d.doc_id, d.host, d.ls, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars,
         length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS n_symbols,
         len(ls) - len(list_distinct(ls)) AS n_dup_lines, coalesce(c.n, 0) AS n_repeat_words
  FROM d LEFT JOIN covered c ON d.r = c.r),
lines AS (
  SELECT r, doc_id, host, lower(trim(regexp_replace(l, '[\x20\x09-\x0D]+', ' ', 'g'))) AS line,
         len(regexp_extract_all(l, '[^\x20\x09-\x0D]+')) AS n
  FROM (SELECT r, doc_id, host, unnest(ls) AS l FROM base)),
frequent AS (
  SELECT host, line, min(doc_id) AS first_id FROM lines GROUP BY host, line HAVING count(DISTINCT r) > 20),
gone AS (
  SELECT r, count(DISTINCT l.line) AS k, sum(n) AS n FROM lines l JOIN frequent f ON l.host = f.host AND l.line = f.line
  WHERE doc_id IS DISTINCT FROM first_id GROUP BY r),
out AS (
  SELECT b.*, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed,
         CAST(coalesce(g.k, 0) AS BIGINT) AS removed_lines, CAST(coalesce(g.n, 0) AS BIGINT) AS removed_words
  FROM base b LEFT JOIN gone g ON b.r = g.r)
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(word_chars AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols,
       CAST(n_dup_lines AS BIGINT) AS n_dup_lines, CAST(n_repeat_words AS BIGINT) AS n_repeat_words, base_failed,
       NOT base_failed AND 100 * removed_words <= 50 * n_words AS kept, removed_lines, removed_words
FROM out
"""
