"""Best-fit packing after a linear grouping scheme (operator 6).

Texts are encoded, closed by an end id and cut into pieces only where they exceed a sequence.
Full pieces are sequences of their own. Pieces keep the order of their documents (files by
name, rows within): ranges of about ``SHARD_PIECES`` pieces are shards, each packed by one task,
and the sequences are numbered in that order, so a training order survives up to a shard.
Sharding costs at most one open sequence a shard. In a shard, pieces over ``capacity / SMALL`` are large: sorted and cut into ``GROUPS``
groups of equal cardinality, each rounded up to its longest. Over these few sizes the number
of sequences is optimised by column generation on configurations (a linear program whose
columns come from a knapsack over capacity units); the whole part of the solution is filled
with actual pieces, which are no longer than their rounded size; the last place of a sequence
takes the longest piece that the room left by rounding admits. What is left, the remainder
of the large pieces and all small ones, goes by decreasing length to the best-fitting open
sequence.

Defined cases: a null text is empty and yields its end id alone; repeated rows are documents
of their own; a text of any length is encoded whole and cut into pieces; an empty table gives an
empty result; other columns are ignored.
"""

from __future__ import annotations

import math
import zlib
from bisect import bisect_right
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bound_batches, documents, materialize, trimmed, whole_text
from .tokens import default_path, encoder

CAPACITY = 4096
END_ID = 1
SHARD_PIECES = 20_000
SMALL = 8
GROUPS = 96
UNIT = 8

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
#: Place of a piece in the input: file, where its split begins, task, number within the task.
ORDER = ("file", "split", "task", "nth")


def token_pieces(docs: DataFrame, path: str, capacity: int = CAPACITY, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32`` of every piece of every document, and ``ORDER``."""
    bound_batches(docs.sparkSession, mb=8)
    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), whole_text(F.col(f"`{text_col}`")).alias("text"), F.input_file_name().alias("file"), F.input_file_block_start().alias("split"))

    def run(batches):
        enc = encoder(path)
        end, task, nth = np.array([end_id], "<u4").tobytes(), TaskContext.get().partitionId(), 0
        for b in batches:
            ids, bounds = enc.encode(b.column(1))
            raw = memoryview(ids.tobytes())
            at, piece, start, length, crc = [], [], [], [], []
            for k in range(b.num_rows):
                own = bytes(raw[4 * bounds[k] : 4 * bounds[k + 1]]) + end
                for n, s in enumerate(range(0, len(own), 4 * capacity)):
                    part = own[s : s + 4 * capacity]
                    at.append(k)
                    piece.append(n)
                    start.append(s // 4)
                    length.append(len(part) // 4)
                    crc.append(zlib.crc32(part))
            own, m = pa.array(at, pa.int64()), len(at)
            cols = [b.column(0).take(own), pa.array(piece, pa.int32()), *(pa.array(x, pa.int64()) for x in (start, length, crc))]
            cols += [b.column(2).take(own), b.column(3).take(own), pa.array(np.full(m, task, np.int32)), pa.array(np.arange(nth, nth + m, dtype=np.int64))]
            nth += m
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "piece", "start", "length", "ids_crc32", *ORDER])

    return rows.mapInArrow(trimmed(run), PIECES + ", file string, split long, task int, nth long")


def configurations(sizes: list[int], demand: list[int], room: int) -> list[tuple[np.ndarray, int]]:
    """(copies of each size, how often) of a near-optimal packing of few sizes; whole numbers
    below the demand. ``sizes`` and ``room`` are in units."""
    m = len(sizes)
    sizes_, need = np.array(sizes), np.array(demand, float)
    columns = [np.eye(m)[j] * max(1, room // sizes[j]) for j in range(m)]
    basis, inverse = list(range(m)), np.diag([1 / columns[j][j] for j in range(m)])
    x = inverse @ need
    for _ in range(20 * m):
        price = inverse.sum(0)
        best, last = np.zeros(room + 1), np.full(room + 1, -1)
        for c in range(int(sizes_.min()), room + 1):
            value = np.where(sizes_ <= c, best[np.maximum(c - sizes_, 0)] + price, -1.0)
            j = int(value.argmax())
            if value[j] > best[c - 1] + 1e-12:
                best[c], last[c] = value[j], j
            else:
                best[c] = best[c - 1]
        if best[room] <= 1 + 1e-7:
            break
        column, c = np.zeros(m), room
        while c > 0:
            if last[c] < 0 or best[c] == best[c - 1]:
                c -= 1
                continue
            column[last[c]] += 1
            c -= sizes[last[c]]
        direction = inverse @ column
        up = direction > 1e-9
        ratio = np.where(up, x / np.where(up, direction, 1), np.inf)
        out = int(ratio.argmin())
        if not np.isfinite(ratio[out]):
            break
        columns.append(column)
        basis[out] = len(columns) - 1
        step = ratio[out]
        x = x - step * direction
        x[out] = step
        pivot = inverse[out] / direction[out]
        inverse = inverse - np.outer(direction, pivot)
        inverse[out] = pivot
    return [(columns[b], int(math.floor(v + 1e-9))) for b, v in zip(basis, x, strict=True) if v >= 1 - 1e-9]


def pack(lengths: np.ndarray, capacity: int = CAPACITY, groups: int = GROUPS, small: int = SMALL) -> tuple[np.ndarray, np.ndarray]:
    """(sequence, offset) of each piece; sequences are numbered from 0."""
    n = len(lengths)
    sequence, offset = np.full(n, -1, np.int64), np.zeros(n, np.int64)
    used: list[int] = []
    order = np.lexsort((np.arange(n), -lengths))
    large = [int(i) for i in order if lengths[i] * small > capacity]
    rest = [int(i) for i in order if lengths[i] * small <= capacity]

    def put(i: int, s: int) -> None:
        sequence[i], offset[i] = s, used[s]
        used[s] += int(lengths[i])

    if large:
        each = -(-len(large) // groups)
        unit = max(1, min(UNIT, capacity // 64))
        members = defaultdict(list)  # by rounded size; the longest are at the end
        for k in range(0, len(large), each):
            group = large[k : k + each]
            members[min(-(-int(lengths[group[0]]) // unit), capacity // unit)] += group[::-1]
        sizes = sorted(members, reverse=True)
        for counts, often in configurations(sizes, [len(members[s]) for s in sizes], capacity // unit):
            for _ in range(often):
                used.append(0)
                slots = [s for s, c in zip(sizes, counts, strict=True) for _ in range(int(c))]
                for s in slots[:-1]:
                    if members[s] and used[-1] + lengths[members[s][-1]] <= capacity:
                        put(members[s].pop(), len(used) - 1)
                for s in sizes:  # rounding has left room: the last slot takes the longest piece that fits
                    room = capacity - used[-1]
                    if members[s] and lengths[members[s][0]] <= room:
                        k = bisect_right(members[s], room, key=lengths.__getitem__) - 1
                        put(members[s].pop(k), len(used) - 1)
                        break
        rest = sorted((i for g in members.values() for i in g), key=lambda i: (-lengths[i], i)) + rest
    by_room: dict[int, list[int]] = defaultdict(list)
    mask = 0  # bit r: some open sequence has room for r
    for s, u in enumerate(used):
        by_room[capacity - u].append(s)
        mask |= 1 << capacity - u
    for i in rest:
        fit = mask >> int(lengths[i])
        if fit:
            r = int(lengths[i]) + (fit & -fit).bit_length() - 1
            s = by_room[r].pop()
            if not by_room[r]:
                mask &= ~(1 << r)
        else:
            s = len(used)
            used.append(0)
        put(i, s)
        r = capacity - used[s]
        by_room[r].append(s)
        mask |= 1 << r
    filled = np.unique(sequence)
    return np.searchsorted(filled, sequence), offset


def pack_pieces(pieces: DataFrame, capacity: int = CAPACITY, shard_pieces: int = SHARD_PIECES) -> DataFrame:
    """``pieces`` with ``sequence_id, offset``, without ``ORDER``."""
    shards = max(1, -(-pieces.count() // shard_pieces))
    rows = pieces.repartitionByRange(shards, *ORDER).sortWithinPartitions(*ORDER).drop(*ORDER)

    def run(batches):
        shard, held, done = TaskContext.get().partitionId() << 36, [], 0

        def flush():
            t = pa.Table.from_batches(held).combine_chunks()
            length = t["length"].to_numpy()
            whole = length == capacity
            seq, off = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            seq[~whole], off[~whole] = pack(length[~whole], capacity)
            seq[whole] = seq.max(initial=0) + 1 + np.arange(whole.sum())
            _, first, at = np.unique(seq, return_index=True, return_inverse=True)
            number = np.argsort(np.argsort(first))  # sequences go by their first piece
            t = t.append_column("sequence_id", pa.array(number[at] + shard + done)).append_column("offset", pa.array(off))
            held.clear()
            return len(first), t.to_batches()

        for b in batches:
            held.append(b)
            if sum(x.num_rows for x in held) >= 2 * shard_pieces:  # a range that came out too long
                n, out = flush()
                done += n
                yield from out
        if held:
            yield from flush()[1]

    return rows.mapInArrow(trimmed(run), f"{PIECES}, sequence_id long, offset long")


def pack_documents(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every piece of every document with its place: ``doc_id, piece, start, length, ids_crc32,
    sequence_id, offset``."""
    pieces = token_pieces(docs, path or default_path(), capacity, end_id, id_col, text_col)
    return pack_pieces(materialize(pieces, "pieces"), capacity)


def op6_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(documents(spark, sf_dir))
