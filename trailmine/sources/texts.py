"""Letters and words of whole texts as sequences, read as bytes in the tasks: no item is a string
of its own until the dictionary is made."""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .dictionary import BATCH_BYTES, LOCAL_NAMES, LOCAL_PAIRS, Dictionary, Keyed, closed_edges, encode_local, frequencies_local, numbered, unique, written

#: Bytes of text that are taken apart at once, about (a text is never cut), and longest text.
BYTES, MOST_BYTES = 1 << 19, 1_000_000
#: Letters of a word that 64 bits hold; keys of longer words may coincide, which is checked.
EXACT = 13
#: Different words that a task holds before they leave it.
HELD = 200_000
_POWERS: list[np.ndarray] = []


def parts(batches):
    """(ids, bytes, bounds of the texts) of a few texts."""
    for batch in batches:
        sids, col = batch.column(0), batch.column(1)
        upto = np.frombuffer(col.buffers()[1], np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
        data, at = np.frombuffer(col.buffers()[2] or b"", np.uint8), 0
        while at < len(col):
            to = max(at + 1, int(np.searchsorted(upto, upto[at] + BYTES, "right")) - 1)
            yield sids.slice(at, to - at), data[upto[at] : upto[to]], upto[at : to + 1] - upto[at]
            at = to


def letter_chunks(batches):
    """Letters a to z by their codes, one sequence a text."""
    for sids, b, bounds in parts(batches):
        ok = (b - np.uint8(97)) < 26
        yield sids, b[ok].astype(np.int64), np.concatenate([[0], np.cumsum(ok)])[bounds]


def powers(n: int) -> list[np.ndarray]:
    """Powers of 27 and of its inverse, modulo 2 ** 64."""
    if not _POWERS or len(_POWERS[0]) < n:
        _POWERS[:] = [np.cumprod(np.concatenate([np.ones(1, np.uint64), np.full(max(n, BYTES), x, np.uint64)]), dtype=np.uint64) for x in (27, pow(27, -1, 1 << 64))]
    return _POWERS


def words(batches):
    """(ids of the sentences, keys of their words, bounds, bytes, starts and ends of the words).

    The key of a word is its letters as digits of base 27, modulo 2 ** 64: differences of one
    running sum."""
    for sids, b, bounds in parts(batches):
        inner = bounds[:-1][bounds[:-1] < len(b)]
        low = b | 32
        letter = (low - np.uint8(97)) < 26
        cut = (b == 46) | (b == 33) | (b == 63) | (b == 10)

        def begins(x, inner=inner):
            """Where a run begins, each text by itself."""
            out = x.copy()
            out[1:] &= ~x[:-1]
            out[inner] = x[inner]
            return out

        start = np.flatnonzero(begins(letter))
        if not len(start):
            continue
        last = letter.copy()
        last[:-1] &= ~letter[1:]
        ends = inner[inner > 0] - 1
        last[ends] = letter[ends]
        end = np.flatnonzero(last) + 1
        up, down = powers(len(b))
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(np.where(letter, low - np.uint8(96), np.uint8(0)) * up[: len(b)], dtype=np.uint64)])
        keys = ((sums[end] - sums[start]) * down[start]).view(np.int64)
        cuts = np.concatenate([[0], np.cumsum(begins(cut))])
        text = np.searchsorted(bounds, start, "right") - 1
        nth = cuts[start + 1] - cuts[bounds[text]]
        new = np.flatnonzero(np.concatenate([[True], (text[1:] != text[:-1]) | (nth[1:] != nth[:-1])]))
        ids = sids.to_numpy()[text[new]].astype(np.int64) * 1_000_000 + nth[new]
        yield pa.array(ids), keys, np.append(new, len(keys)), b, start, end


def word_chunks(batches):
    for x in words(batches):
        yield x[:3]


def spelled(keys: np.ndarray) -> list[str]:
    """Words of at most ``EXACT`` letters."""
    letters = np.zeros((len(keys), EXACT), np.uint8)
    for k in range(EXACT):
        keys, digit = np.divmod(keys, 27)
        letters[:, k] = np.where(digit > 0, digit + 96, 0)
    return letters.view(f"S{EXACT}").ravel().astype(str).tolist()


def sequences_with(keys: np.ndarray, seq: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different keys, and the sequences that have each."""
    kinds, of = np.unique(keys, return_inverse=True)
    held = np.unique(seq * len(kinds) + of)
    return kinds, np.bincount(held % max(1, len(kinds)), minlength=len(kinds))


def _rows(names: list, keys: np.ndarray, counts):
    return pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(keys, pa.int64()), pa.array(counts, pa.int64())], names=["item", "h", "n"])


def count_letters(batches):
    total = np.zeros(123, np.int64)
    for _, keys, bounds in letter_chunks(batches):
        for at, to in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            total += np.bincount(keys[at:to], minlength=len(total)) > 0
    some = np.flatnonzero(total)
    yield _rows(list(map(chr, some)), some, total[some])


def count_words(batches):
    """``item, h, n``: words, their keys, and sequences of the task that have them."""
    held, long = [], Counter()

    def added():
        keys, of = np.unique(np.concatenate([x[0] for x in held]), return_inverse=True)
        return keys, np.bincount(of, np.concatenate([x[1] for x in held]), len(keys)).astype(np.int64)

    size = 0
    for _, keys, bounds, b, start, end in words(batches):
        seq = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
        short = end - start <= EXACT
        held.append(sequences_with(keys[short], seq[short]))
        at = np.flatnonzero(~short)
        found = {(s, bytes(b[x:y] | 32), h) for s, x, y, h in zip(seq[at].tolist(), start[at].tolist(), end[at].tolist(), keys[at].tolist(), strict=True)}
        long.update((w, h) for _, w, h in found)
        size += len(held[-1][0])
        if size > HELD or len(long) > HELD:
            held = [added()]
            if (size := len(held[0][0])) > HELD // 2 or len(long) > HELD:
                yield _rows(spelled(held[0][0]), *held[0])
                yield _rows([w.decode() for w, _ in long], np.array([h for _, h in long], np.int64), list(long.values()))
                held, size = [], 0
                long.clear()
    if held:
        keys, counts = added()
        yield _rows(spelled(keys), keys, counts)
    yield _rows([w.decode() for w, _ in long], np.array([h for _, h in long], np.int64), list(long.values()))


@dataclass
class Texts:
    """``rows``: an id and a text; by letters or by words. ``edges`` of a table of words."""

    rows: DataFrame
    letters: bool
    edges: object = None

    def encoded(self) -> tuple[DataFrame, Dictionary] | None:
        """Sequences and dictionary; None where they have to be made the general way: ids are
        not unique, texts or vocabularies too large, keys that coincide."""
        spark = self.rows.sparkSession
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
        rows = self.rows.toDF("sid", "text").where("text IS NOT NULL")
        if dict(rows.dtypes)["sid"] != "bigint" or not unique(rows, "sid") or rows.where(F.octet_length("text") >= MOST_BYTES).limit(1).count():
            return None
        counted = rows.mapInArrow(count_letters if self.letters else count_words, "item string, h long, n long")
        own = written(counted.groupBy("item", "h").agg(F.sum("n").alias("freq")), "words")
        up = closed_edges(spark, self.edges(own.select(F.col("item").alias("child"))) if self.edges else None)

        def key(names: DataFrame) -> DataFrame:
            known = own.select("item", F.col("h").alias("__h"))
            return names.join(known.hint("merge"), "item", "left").withColumn("h", F.coalesce("__h", F.xxhash64("item"))).drop("__h")

        seqs = Keyed(rows, letter_chunks if self.letters else word_chunks, key)
        names = key(own.select("item").union(up.select("child")).union(up.select("anc")).distinct())
        if up.count() > LOCAL_PAIRS or own.count() > LOCAL_NAMES or not unique(names, "h"):
            return None
        freq = frequencies_local(seqs, up, own.select("item", "freq")) if self.edges else own.select("item", "freq")
        d = numbered(freq, up, 0)
        out = written(encode_local(seqs, d), "sequences")
        d.sequences = out.count()
        return out, d
