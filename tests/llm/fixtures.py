"""Rows with nulls, empty and long texts, ties, repeats and clashing extra columns."""

from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, key string, size long, n_docs long"


def odd_rows():
    a = "the cat sat on the mat and the cat sat on the mat again " * 6
    rows = [
        (0, a, "en", "src0"), (1, a + "\n", "en", "src0"), (2, " " + a + "\n\n", "en", None), (3, None, None, None),
        (4, "", "en", "src1"), (5, " \t\n\x0b", "en", "src1"), (6, "one", "en", "src1"), (7, "one two", "en", "src2"),
        (8, "ONE two", "en", "src2"), (9, "one two three", "en", "src2"), (10, "one two # $ é 𝄞 é", "de", "src2"),
        (11, "line a\nline a\n \nline b", "en", "src0"), (12, "x y z x y z x y z q", "en", "src0"),
        (None, "null id text", "en", "src0"), (13, "w%d " * 3 % (1, 2, 3) + " ".join(f"w{i}" for i in range(20000)), "en", "src3"),
        (14, "same", "en", "src3"), (14, "same", "en", "src3"), (15, "<|endoftext|> & < [INST] </s>", "en", "src3"),
    ]
    return [(i, t, la, s, None if t is None else len(t), "k", 1, 2) for i, t, la, s in rows]


def odd(spark):
    return spark.createDataFrame(odd_rows(), SCHEMA)


def none(spark):
    return spark.createDataFrame([], SCHEMA)


def table(spark, name="documents", sf=SF):
    return spark.read.parquet(f"{sf}/{name}.parquet")


def texts(df):
    return [(r["doc_id"], r["text"] or "") for r in df.select("doc_id", F.col("text")).collect()]
