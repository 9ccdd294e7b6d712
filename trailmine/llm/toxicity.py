"""Toxicity by multiple-instance learning (operator 4).

A document is a bag of sentences. A sentence's score is logistic in its words
and their first letters; the document's
is the noisy-or of them, ``1 - prod(1 - p)``. Only documents have labels; the sentence model
is trained through the noisy-or by gradient steps in numpy, and then also locates the
sentences that make a document toxic. Only the words of the text enter a score.

The model is fitted on a bounded sample of labelled documents: by hash of the id, at most
``SAMPLE`` of each label, none longer than ``SAMPLE_CHARS``. A sampled document weighs as many as
it stands for, so the share of toxic ones is that of all labelled documents, whatever the bound.
Scoring covers all whole texts.

Defined cases: a null or empty text has one empty sentence; a label row repeated for an id
counts once, toxic if any is; null labels are left out; with one class or no labelled
documents at all the model is its bias; an empty table gives an empty result; other columns
are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bound_batches, documents, id_crc, whole_text

SAMPLE = 2500
SAMPLE_CHARS = 100_000
LEAST_DOCS = 3
STEPS = 120
RATE = 0.15
RIDGE = 4e-4
PREFIXES = (4, 5)


def sentences(texts: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """All sentences of a batch, and the bounds of the texts."""
    parts = pc.split_pattern_regex(texts, r"[.!?\n]+")
    return parts.values, parts.offsets.to_numpy()


def words_of(parts: pa.Array) -> tuple[list[str], np.ndarray, np.ndarray]:
    """(distinct words, number of each word in order, bounds of the sentences)."""
    split = pc.split_pattern_regex(pc.utf8_lower(parts), r"[^\pL\pN]+")
    coded = split.values.dictionary_encode()
    return coded.dictionary.to_pylist(), coded.indices.to_numpy(), split.offsets.to_numpy()


def features(word: str) -> list[str]:
    """A word and its first letters, which inflected and compound words share."""
    return [word, *(f"{word[:k]}*" for k in PREFIXES if len(word) > k)] if word else []


def _owners(bounds: np.ndarray) -> np.ndarray:
    return np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))


def noisy_or(logits: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    """Sum over a document's sentences of -log(1 - p)."""
    return np.bincount(owner, np.logaddexp(0, logits), n)


def fit(texts: list[str], labels: np.ndarray, weights: np.ndarray | None = None, steps: int = STEPS, rate: float = RATE, ridge: float = RIDGE) -> dict:
    """``{"bias", "words": {word: weight}}`` from document labels; ``weights``: documents that
    each one stands for."""
    y, n = np.asarray(labels, float), len(texts)
    each = np.ones(n) if weights is None else np.asarray(weights, float)
    each = each / max(each.sum(), 1e-9)
    if n == 0 or y.min() == y.max():
        return {"bias": -20.0 if n == 0 or y.max() == 0 else 20.0, "words": {}}
    parts, doc_bounds = sentences(pa.array(texts, pa.string()))
    names, at, bounds = words_of(parts)
    sentence_doc, word_sentence = _owners(doc_bounds), _owners(bounds)
    doc_word = np.unique(sentence_doc[word_sentence].astype(np.int64) * len(names) + at)
    coded: dict[str, int] = {}
    parts_of = [[coded.setdefault(f, len(coded)) for f in features(x)] for x in names]
    sizes = np.array([len(f) for f in parts_of])
    feature, of_name = np.array([f for fs in parts_of for f in fs], np.int64), np.repeat(np.arange(len(names)), sizes)
    # documents that have a feature, over all words that have it
    spread = np.repeat(doc_word // len(names), sizes[doc_word % len(names)])
    first_of = (np.cumsum(sizes) - sizes)[doc_word % len(names)]
    inner = np.arange(len(spread)) - np.repeat(np.cumsum(sizes[doc_word % len(names)]) - sizes[doc_word % len(names)], sizes[doc_word % len(names)])
    had = feature[np.repeat(first_of, sizes[doc_word % len(names)]) + inner]
    often = np.bincount(np.unique(spread * len(coded) + had) % len(coded), minlength=len(coded)) >= LEAST_DOCS
    del doc_word, spread, first_of, inner, had
    number = np.where(often, np.cumsum(often) - 1, -1)[feature]
    feature, of_name = number[number >= 0], of_name[number >= 0]
    word, sentence, total = at, word_sentence, len(names)
    m, k = int(often.sum()), len(parts)
    w, b = np.zeros(m), float(np.log(each @ y / (each @ np.diff(doc_bounds))))
    first, second = np.zeros(m + 1), np.zeros(m + 1)
    for t in range(1, steps + 1):
        z = b + np.bincount(sentence, np.bincount(of_name, w[feature], total)[word], k)
        p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        toxic = -np.expm1(-noisy_or(z, sentence_doc, n))
        # of -log likelihood by a sentence's logit: p if the label is 0, -p (1 - P) / P if 1
        slope = np.where(y == 1, -(1 - toxic) / np.maximum(toxic, 1e-9), 1.0)
        slope = (each * slope)[sentence_doc] * p
        by_name = np.bincount(word, slope[sentence], total)
        g = np.append(np.bincount(feature, by_name[of_name], m) + ridge * w, slope.sum())
        first, second = 0.9 * first + 0.1 * g, 0.999 * second + 0.001 * g * g
        step = rate * (1 - t / (steps + 1)) * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-8)
        w, b = w - step[:-1], b - step[-1]
    kept = [x for x, o in zip(coded, often, strict=True) if o]
    return {"bias": float(b), "words": {x: float(v) for x, v in zip(kept, w, strict=True) if abs(v) > 1e-3}}


def sentence_logits(texts: pa.Array, model: dict) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """(sentences, their logits, bounds of the texts)."""
    parts, bounds = sentences(texts)
    names, at, word_bounds = words_of(parts)
    get = model["words"].get
    weight = np.array([sum([get(f, 0.0) for f in features(x)]) for x in names] or [0.0])[at]
    return parts, model["bias"] + np.bincount(_owners(word_bounds), weight, len(parts)), bounds


def training_sample(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample: int = SAMPLE) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Texts, labels and weights, at most ``sample`` of each label, of ids whose crc32 mod 5 is
    not 0. The weight is the label's documents over those sampled."""
    known = labels.where("toxic IS NOT NULL AND doc_id IS NOT NULL").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    known = known.where(F.pmod(id_crc("doc_id"), F.lit(5)) != 0)
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), whole_text(F.col(text_col)).alias("text"))
    got: list[tuple[str, int, float]] = []
    all_ = dict(known.groupBy((F.col("toxic") > 0).cast("int")).count().collect())
    for label in (1, 0):
        some = known.where((F.col("toxic") > 0) == bool(label)).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
        rows = texts.join(F.broadcast(some), "doc_id").where(F.length("text") <= SAMPLE_CHARS)
        rows = rows.orderBy("doc_id", "text").select("text").toArrow()["text"].to_pylist()
        got += [(t, label, all_.get(label, 0) / min(sample, all_.get(label, 1))) for t in rows]
    return [t for t, _, _ in got], np.array([y for _, y, _ in got]), np.array([x for _, _, x in got])


def score_documents(docs: DataFrame, model: dict, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, held_out, score, predicted, n_sentences``."""
    bound_batches(docs.sparkSession, mb=16)
    sent = docs.sparkSession.sparkContext.broadcast(model)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), (F.pmod(id_crc(id_col), F.lit(5)) == 0).alias("held_out"), whole_text(F.col(text_col)).alias("text"))

    def run(batches):
        for b in batches:
            _, z, bounds = sentence_logits(b.column(2), sent.value)
            score = -np.expm1(-noisy_or(z, _owners(bounds), b.num_rows))
            cols = [b.column(0), b.column(1), pa.array(score), pa.array((score >= 0.5).astype(np.int32)), pa.array(np.diff(bounds).astype(np.int64))]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "held_out", "score", "predicted", "n_sentences"])

    return rows.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int, n_sentences long")


def offending_sentences(docs: DataFrame, model: dict, least: float = 0.5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, nth, sentence, score`` of the sentences at or above ``least``."""
    bound_batches(docs.sparkSession, mb=16)
    sent = docs.sparkSession.sparkContext.broadcast(model)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), whole_text(F.col(text_col)).alias("text"))

    def run(batches):
        for b in batches:
            parts, z, bounds = sentence_logits(b.column(1), sent.value)
            p, owner = 1 / (1 + np.exp(-z)), _owners(bounds)
            hit = np.flatnonzero(p >= least)
            cols = [b.column(0).take(pa.array(owner[hit])), pa.array((hit - bounds[owner[hit]]).astype(np.int32)), parts.take(pa.array(hit)), pa.array(p[hit])]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "nth", "sentence", "score"])

    return rows.mapInArrow(run, "doc_id long, nth int, sentence string, score double")


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = fit(*training_sample(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return score_documents(docs, model)
