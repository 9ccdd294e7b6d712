"""Token-id files with directly addressable codes (operator 10).

An id is split into chunks of 8 bits, lowest first. Level k holds the k-th chunks of all ids
that have one, and a bitmap that tells which go on to level k + 1; a directory of ranks, one
per 512 bits of the bitmap, gives the place of an id's next chunk. So any token, or run of tokens, is read with
its bytes of each level and one block of bitmap before them, and no block of codes is decoded.

A file: fixed header (mark, numbers of documents, tokens and levels), document ids, document
starts, then for each level its length, chunks, bitmap and rank directory. Documents are
range-sorted by id (null first) and written in that order, one file for about ``FILE_TOKENS``
tokens; a manifest lists the files in order with their first token's number. Only files whose
task has finished are in it.

Defined cases: a null text is empty and yields its end id alone; rows that repeat an id follow
one another; an empty table gives no file; other columns are ignored.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import files
from .common import bound_batches, documents, materialize, scratch_dir, whole_text
from .tokens import default_path, encoder

MARK = b"DACTOK01"
HEAD = struct.Struct("<8sqqq")
RANK_BITS = 512
END_ID = 2
FILE_TOKENS = 8_000_000
#: Tokens that are read at once, about, where all documents of a file are asked for.
SPAN_TOKENS = 1 << 18
#: Stands for a null id in a file.
NO_ID = -(2**63)


def write_codes(ids: np.ndarray, doc_ids: np.ndarray, starts: np.ndarray) -> bytes:
    """A file's bytes; ``starts`` has each document's first token and, last, their number."""
    levels, now = [], ids.astype("<u4")
    while True:
        on = now > 255
        bits = np.packbits(on, bitorder="little")
        bits = np.concatenate([bits, np.zeros(-len(bits) % (RANK_BITS // 8), np.uint8)])
        ones = np.bitwise_count(bits.view("<u8")).reshape(-1, RANK_BITS // 64).sum(1, dtype="<u8")
        ranks = (np.cumsum(ones) - ones).astype("<u8")
        levels.append(struct.pack("<q", len(now)) + (now & 255).astype(np.uint8).tobytes() + bits.tobytes() + ranks.tobytes())
        if not on.any():
            break
        now = now[on] >> 8
    head = HEAD.pack(MARK, len(doc_ids), len(ids), len(levels))
    return head + doc_ids.astype("<i8").tobytes() + starts.astype("<i8").tobytes() + b"".join(levels)


class CodeFile:
    """Reads a file's tokens by place: of each level only the bytes of the tokens asked for, and
    what the rank directory and one block of the bitmap before them say of their place on the next.

    ``source`` is the file's bytes, or a function of offset and length that reads a range."""

    def __init__(self, source) -> None:
        self.read = source if callable(source) else lambda at, n: source[at : at + n]
        mark, self.docs, self.n, count = HEAD.unpack(self.read(0, HEAD.size))
        if mark != MARK:
            raise ValueError("not a token file")
        at = HEAD.size + 16 * self.docs + 8
        self.levels = []  # chunks, and where they, the bitmap and the rank directory begin
        for _ in range(count):
            (n,) = struct.unpack("<q", self.read(at, 8))
            size = -(-n // RANK_BITS)
            self.levels.append((n, at + 8, at + 8 + n, at + 8 + n + size * RANK_BITS // 8))
            at = self.levels[-1][3] + 8 * size

    def _array(self, kind, at: int, n: int) -> np.ndarray:
        return np.frombuffer(self.read(at, n * np.dtype(kind).itemsize), kind, n)

    @property
    def doc_ids(self) -> np.ndarray:
        return self._array("<i8", HEAD.size, self.docs)

    @property
    def starts(self) -> np.ndarray:
        return self._array("<i8", HEAD.size + 8 * self.docs, self.docs + 1)

    def tokens(self, low: int, high: int) -> np.ndarray:
        """Tokens ``low`` to ``high - 1``."""
        if not 0 <= low <= high <= self.n:
            raise IndexError((low, high))
        out, at = np.zeros(high - low, "<u4"), np.arange(high - low)
        for k, (_, chunks, bits, ranks) in enumerate(self.levels):
            if low == high:
                break
            out[at] |= self._array(np.uint8, chunks + low, high - low).astype("<u4") << np.uint32(8 * k)
            block = low // RANK_BITS
            first = block * RANK_BITS // 8
            on = np.unpackbits(self._array(np.uint8, bits + first, -(-high // 8) - first), bitorder="little")
            before, on = on[: low % RANK_BITS], on[low % RANK_BITS : low % RANK_BITS + high - low].astype(bool)
            at = at[on]
            low = int(self._array("<u8", ranks + 8 * block, 1)[0]) + int(before.sum())
            high = low + len(at)
        return out

    def token(self, i: int) -> int:
        if not 0 <= i < self.n:
            raise IndexError(i)
        return int(self.tokens(i, i + 1)[0])

    def ids(self) -> np.ndarray:
        return self.tokens(0, self.n)


def write_token_files(docs: DataFrame, base: str, path: str | None = None, end_id: int = END_ID, file_tokens: int = FILE_TOKENS,
                      id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Write the files into ``base``; the manifest: ``part, nth, file, n_docs, n_tokens, start``."""
    path = path or default_path()
    bound_batches(docs.sparkSession, mb=16)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), whole_text(F.col(text_col)).alias("text"))
    rows = rows.repartitionByRange("doc_id").sortWithinPartitions("doc_id")

    def run(batches):
        enc, part = encoder(path), TaskContext.get().partitionId()
        held, total, nth = [], 0, 0

        def close():
            ids = np.concatenate([x[0] for x in held])
            lengths = np.concatenate([x[1] for x in held])
            owners = np.concatenate([x[2] for x in held])
            starts = np.concatenate([[0], np.cumsum(lengths)])
            name = files.create(base, f"tokens-{part:06d}-{nth:06d}", ".dac", write_codes(ids, owners, starts))
            row = {"part": [part], "nth": [nth], "file": [name], "n_docs": [len(owners)], "n_tokens": [len(ids)]}
            return pa.RecordBatch.from_pydict(row, schema=pa.schema([("part", pa.int64()), ("nth", pa.int64()), ("file", pa.string()), ("n_docs", pa.int64()), ("n_tokens", pa.int64())]))

        for b in batches:
            ids, bounds = enc.encode(b.column(1))
            ids = np.insert(ids, bounds[1:], end_id)
            held.append((ids, np.diff(bounds) + 1, b.column(0).fill_null(NO_ID).to_numpy()))
            total += len(ids)
            if total >= file_tokens:
                yield close()
                held, total, nth = [], 0, nth + 1
        if held:
            yield close()

    made = materialize(rows.mapInArrow(run, "part long, nth long, file string, n_docs long, n_tokens long"), "manifest")
    before = F.sum("n_tokens").over(Window.orderBy("part", "nth")) - F.col("n_tokens")
    return made.withColumn("start", before)


def read_token_files(manifest: DataFrame, base: str) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` of every document in the files."""

    def run(batches):
        for b in batches:
            for name, first in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                f = CodeFile(files.read_all(base, name))
                at, crc, k = f.starts, [], 0
                while k < f.docs:  # some documents at a time, from wherever they stand
                    end = max(k + 1, int(np.searchsorted(at, at[k] + SPAN_TOKENS, "right")) - 1)
                    raw = memoryview(f.tokens(int(at[k]), int(at[end])).tobytes())
                    crc += [zlib.crc32(raw[4 * (at[j] - at[k]) : 4 * (at[j + 1] - at[k])]) for j in range(k, end)]
                    k = end
                ids = pa.array(f.doc_ids, mask=f.doc_ids == NO_ID)
                yield pa.RecordBatch.from_arrays([ids, pa.array(at[:-1] + first), pa.array(np.diff(at)), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    todo = manifest.select("file", "start").repartition(max(1, min(manifest.count(), 20_000)))
    return todo.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def random_token(manifest: DataFrame, base: str, i: int) -> int:
    """Token number ``i`` of the whole collection."""
    row = manifest.where((F.col("start") <= i) & (F.col("start") + F.col("n_tokens") > i)).first()
    if row is None:
        raise IndexError(i)
    with files.open_file(base, row["file"]) as opened:
        return CodeFile(lambda at, n: opened.read_at(n, at)).token(i - row["start"])


def op10_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    base = f"{scratch_dir(spark)}/tokens"
    return read_token_files(write_token_files(documents(spark, sf_dir), base), base)
