"""Language-model scores by a log-bilinear neural model (operator 7).

The model predicts a token from the one before it: ``s(q, w) = (r_q C) . o_w + b_w`` with
embeddings ``r``, ``o``, a matrix ``C`` and a bias. Its vocabulary is the text boundary (start
and end), the ``VOCAB`` most frequent words and one class for all other words. It is trained
in numpy by noise-contrastive estimation with the unigram distribution as noise: the counts of
all adjacent pairs in all training documents are gathered, so each step takes the exact
expectation of the objective over data and noise. Scores are normalised: a worker makes the
table of log-probabilities of all pairs by one matrix product and a log-sum over each row. A
word of the last class is then drawn by its smoothed count among such words.

Word counts cover all training documents. The ``HEAD`` most frequent words (no longer than
``HEAD_CHARS``) go to the workers with their counts; other words of each document are joined
with the table of counts. What is sent to workers and driver is bounded by ``HEAD`` words and
``(VOCAB + 2)^2`` pair counts.

Defined cases: a null text is empty and consists of its end; a null id counts as empty text in
the split of the documents; repeated rows are scored each; without training documents all
counts are zero; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bound_batches, documents, id_crc, materialize, whole_text
from .word_arrays import split_words, sums_by_text

VOCAB = 1022
HEAD = 1 << 18
HEAD_CHARS = 64
DIMS = 32
NOISE = 10
STEPS = 120
RATE = 0.05
#: Weight of the square of the embeddings, in observed pairs.
RIDGE = 10.0


def train(pairs: np.ndarray, dims: int = DIMS, noise: int = NOISE, steps: int = STEPS, rate: float = RATE, ridge: float = RIDGE, seed: int = 7) -> tuple:
    """(context vectors after ``C``, output vectors, biases) from counts of adjacent pairs."""
    n, rng = len(pairs), np.random.default_rng(seed)
    total = max(1.0, float(pairs.sum()))
    seen = pairs.sum(1, keepdims=True) / total
    share = (pairs.sum(0) + 0.5) / (total + 0.5 * n)
    data = (pairs / total).astype(np.float32)
    fake = (noise * seen * share).astype(np.float32)
    level = np.log(noise * share).astype(np.float32)
    params = [rng.normal(0, 0.1, (n, dims)), np.eye(dims), rng.normal(0, 0.1, (n, dims)), np.log(share)]
    params = [p.astype(np.float32) for p in params]
    first, second = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
    for t in range(1, steps + 1):
        r, c, o, b = params
        h = r @ c
        real = 1 / (1 + np.exp(np.clip(level - (h @ o.T + b), -30, 30)))
        slope = data * (1 - real) - fake * real
        back = slope @ o
        grads = [back @ c.T, r.T @ back, slope.T @ h, slope.sum(0)]
        for k in (0, 2):
            grads[k] = grads[k] - ridge / total * params[k]
        now = rate * (1 - (t - 1) / steps)
        for k, g in enumerate(grads):
            first[k] = 0.9 * first[k] + 0.1 * g
            second[k] = 0.99 * second[k] + 0.01 * g * g
            params[k] = params[k] + now * (first[k] / (1 - 0.9**t)) / (np.sqrt(second[k] / (1 - 0.99**t)) + 1e-9)
    r, c, o, b = params
    return r @ c, o, b


def log_table(model: tuple) -> np.ndarray:
    """log10 probabilities of every token after every token; each row adds up to one."""
    h, o, b = model
    s = h @ o.T + b
    top = s.max(1, keepdims=True)
    return ((s - top - np.log(np.exp(s - top).sum(1, keepdims=True))) / np.log(10)).astype(np.float32)


def _training(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    held = F.pmod(id_crc(id_col), F.lit(7)) == 2
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), held.alias("held_out"), whole_text(F.col(text_col)).alias("text"))


def word_counts(rows: DataFrame) -> DataFrame:
    """``word, c`` over the texts, in a written table."""

    def run(batches):
        held: dict[str, int] = {}

        def flush():
            out = pa.RecordBatch.from_arrays([pa.array(held.keys(), pa.string()), pa.array(held.values(), pa.int64())], names=["word", "c"])
            held.clear()
            return out

        for b in batches:
            names, at, _ = split_words(b.column(0))
            counts = np.bincount(at, minlength=len(names)).tolist()
            for w, c in zip(names, counts, strict=True):
                if c:
                    held[w] = held.get(w, 0) + c
            if len(held) > 400_000:
                yield flush()
        if held:
            yield flush()

    parts = rows.select("text").mapInArrow(run, "word string, c long")
    return materialize(parts.groupBy("word").agg(F.sum("c").alias("c")), "counts")


def _model_ids(head: list[str], vocab: int) -> dict[str, int]:
    return {w: k + 1 for k, w in enumerate(head[:vocab])}


def pair_counts(rows: DataFrame, head: list[str], vocab: int = VOCAB) -> np.ndarray:
    """How often each token follows each, over all texts of ``rows``."""
    n = vocab + 2
    ids = rows.sparkSession.sparkContext.broadcast(_model_ids(head, vocab))

    def run(batches):
        get, table = ids.value.get, np.zeros(n * n, np.int64)
        for b in batches:
            names, at, bounds = split_words(b.column(0))
            number = np.array([get(w, n - 1) for w in names] or [0], np.int64)
            at = np.insert(number[at], bounds[1:], 0)  # ends; the one before a text is its start
            if len(at):
                table += np.bincount(np.concatenate([[0], at[:-1]]) * n + at, minlength=n * n)
        cells = np.flatnonzero(table)
        for k in range(0, len(cells), 100_000):
            part = cells[k : k + 100_000]
            yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(table[part])], names=["cell", "c"])

    counted = rows.select("text").mapInArrow(run, "cell long, c long").groupBy("cell").agg(F.sum("c").alias("c")).toArrow()
    table = np.zeros(n * n)
    table[counted["cell"].to_numpy()] = counted["c"].to_numpy()
    return table.reshape(n, n)


_TABLES: dict[str, tuple] = {}


def score_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocab: int = VOCAB, head_size: int = HEAD) -> DataFrame:
    """``doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score``."""
    spark = docs.sparkSession
    bound_batches(spark, mb=16)
    rows = _training(docs, id_col, text_col)
    learn = rows.where(~F.col("held_out"))
    counts = word_counts(learn)
    ends = learn.select("doc_id").count()
    kinds, tokens = counts.agg(F.count(F.lit(1)), F.coalesce(F.sum("c"), F.lit(0))).first()
    kinds, tokens = kinds + (ends > 0), tokens + ends
    top = counts.where(F.length("word") <= HEAD_CHARS).orderBy(F.desc("c"), "word").limit(head_size).toArrow()
    head, head_counts = top["word"].to_pylist(), top["c"].to_numpy()
    model = train(pair_counts(learn, head, vocab))
    rest_tokens = tokens - ends - int(head_counts[:vocab].sum())
    rest_kinds = kinds - (ends > 0) - len(head[:vocab])
    all_log, rest_log = np.log10(tokens + kinds + 1), np.log10(rest_tokens + rest_kinds + 1)
    sent = spark.sparkContext.broadcast((head, np.log10(head_counts + 1.0), model))
    key, n, end_log = f"{id(sent)}-{spark.sparkContext.applicationId}-{sent._jbroadcast.id()}", vocab + 2, np.log10(ends + 1.0)

    def run(batches):
        if key not in _TABLES:
            _TABLES.clear()
            words, logs, trained = sent.value
            _TABLES[key] = ({w: k for k, w in enumerate(words)}, np.append(logs, 0.0), log_table(trained))
        number, logs, table = _TABLES[key]
        row = TaskContext.get().partitionId() << 40
        for b in batches:
            names, at, bounds = split_words(b.column(2))
            place = np.array([number.get(w, -1) for w in names] or [0], np.int64)
            mine = np.where((place >= 0) & (place < vocab), place + 1, n - 1)
            base = np.where(place >= 0, logs[place] - all_log, 0.0)
            rest = np.where(place >= vocab, logs[place] - rest_log, 0.0)
            size = np.diff(bounds)
            token = np.insert(mine[at], bounds[1:], 0)
            edge = bounds + np.arange(len(bounds))
            pair = table[np.concatenate([[0], token[:-1]]), token].astype(float) if len(token) else np.zeros(0)
            score = sums_by_text(pair, edge) + sums_by_text(rest[at], bounds)
            own = row + np.arange(b.num_rows)
            row += b.num_rows
            null = lambda t, m: pa.nulls(m, t)
            yield pa.RecordBatch.from_arrays(
                [pa.array(own), b.column(0), b.column(1), null(pa.string(), len(own)), pa.array(size.astype(np.int64) + 1), pa.array(sums_by_text((place >= 0)[at], bounds).astype(np.int64) + (ends > 0)),
                 pa.array(sums_by_text(base[at], bounds) + end_log - all_log), pa.array(score)],
                names=["row", "doc_id", "held_out", "word", "n", "known", "base", "score"])
            rare = np.flatnonzero(place[at] < 0)
            if len(rare):
                text = np.repeat(np.arange(b.num_rows), size)[rare]
                pairs, times = np.unique(text * len(names) + at[rare], return_counts=True)
                m = len(pairs)
                word = pa.array(names).take(pa.array(pairs % len(names)))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(own[pairs // len(names)]), null(pa.int64(), m), null(pa.bool_(), m), word, pa.array(times), null(pa.int64(), m), null(pa.float64(), m), null(pa.float64(), m)],
                    names=["row", "doc_id", "held_out", "word", "n", "known", "base", "score"])

    parts = rows.mapInArrow(run, "row long, doc_id long, held_out boolean, word string, n long, known long, base double, score double")
    parts = materialize(parts, "parts")
    rare = parts.where("word IS NOT NULL").select("row", "word", "n").join(counts, "word", "left")
    c = F.log10(F.coalesce("c", F.lit(0)) + 1.0)
    rare = rare.groupBy("row").agg(
        F.lit(None).cast("long").alias("doc_id"), F.lit(None).cast("boolean").alias("held_out"), F.lit(0).cast("long").alias("n"),
        F.sum(F.when(F.col("c") > 0, F.col("n")).otherwise(0)).alias("known"),
        F.sum(F.col("n") * (c - float(all_log))).alias("base"), F.sum(F.col("n") * (c - float(rest_log))).alias("score"),
    )
    whole = parts.where("word IS NULL").drop("word").unionByName(rare).groupBy("row").agg(
        F.max("doc_id").alias("doc_id"), F.max("held_out").alias("held_out"), F.max("n").alias("n_tokens"),
        F.sum("known").alias("n_known"), F.sum("base").alias("base_score"), F.sum("score").alias("score"),
    )
    return whole.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(tokens).cast("long").alias("train_tokens"), "base_score", "score")


def op7_neural_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_documents(documents(spark, sf_dir))
