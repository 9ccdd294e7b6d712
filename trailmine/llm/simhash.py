"""SimHash near-duplicates by meet-in-the-middle ball hashing (operator 5).

Two 64-bit fingerprints at distance 3 or less share a variant that is within 1 bit of one and
within 2 of the other. Every fingerprint emits its variants within 1 bit; those of even weight
emit the ones at 2 bits too (fingerprints at distance 3 differ in the parity of their weight,
so one side of such a pair is even). Variants are dealt by their leading bits: a fingerprint
goes to a cell once, however many of its variants lie there, and the task of the cell expands
them. Within a cell, a variant that lies within 1 bit of some fingerprint links all others
that emit it to that one; each such pair is verified by its distance. A variant that only
distant emitters share links nobody. So edges grow with the variants, not with the square of a
group, and no link between different fingerprints is lost: it is kept up to connectivity.

A cell with more than ``CELL_ROWS`` fingerprints is split by its next bits, again and again;
at full length a variant has at most 2081 emitters, so memory has a bound.

Defined cases: null and empty texts have fingerprint zero and link with each other; fewer
words than a shingle make one shingle; a text of any length is hashed whole; repeated rows share
fingerprint and component; a null id is never a component's name unless all its members have
none; an empty table gives an empty result; other columns are ignored by ``near_duplicates`` and
carried, under any name, by ``drop_near_duplicates``, which tells rows apart by id and text.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bound_batches, documents, materialize, text_digest, trimmed, whole_row, whole_text
from .components import components

SHINGLE = 3
SEED = 42
RADIUS = 3
CELL_ROWS = 8192
STEP_BITS = 8


def fingerprint(text: bytes, shingle: int = SHINGLE) -> int:
    """SimHash of a UTF-8 text: a bit is set if more than half of the shingles' hashes have it."""
    w = text.lower().split()
    if not w:
        return 0
    grams = [b" ".join(w)] if len(w) < shingle else list(map(b" ".join, zip(*(w[k:] for k in range(shingle)), strict=False)))
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(g, SEED) for g in grams], dtype="<u8")
    ones = np.zeros(64, np.int64)
    for k in range(0, len(hashes), 4096):
        bits = np.unpackbits(hashes[k : k + 4096].view(np.uint8), bitorder="little").reshape(-1, 64)
        ones += bits.sum(0, dtype=np.uint16)
    return int(np.packbits(ones * 2 > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """``doc_id, fp, digest``; the 64 bits as a signed long, and the text's digest."""
    bound_batches(docs.sparkSession)
    text = F.col(f"`{text_col}`")
    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), whole_text(text).cast("binary").alias("text"), text_digest(text).alias("digest"))

    def run(batches):
        for b in batches:
            fps = np.array([fingerprint(t.as_py(), shingle) for t in b.column(1)], dtype=np.uint64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view(np.int64)), b.column(2)], names=["doc_id", "fp", "digest"])

    return rows.mapInArrow(trimmed(run), "doc_id long, fp long, digest binary")


def masks(bits: int, most: int) -> list[tuple[int, int]]:
    """(mask, weight) of all masks of ``bits`` bits with weight ``most`` or less, 0 to 2."""
    out = [(0, 0)]
    if most >= 1:
        out += [(1 << i, 1) for i in range(bits)]
    if most >= 2:
        out += [(1 << i | 1 << j, 2) for i in range(bits) for j in range(i)]
    return out


def _deal(rows: DataFrame, have: int, bits: int, *more: str) -> DataFrame:
    """``fp, cell, room``: from cells of ``have`` leading bits to cells of ``bits`` more;
    ``room`` is how many bits a variant in the cell may still differ in."""
    own = F.shiftrightunsigned("fp", 64 - have - bits).bitwiseAND(F.lit((1 << bits) - 1))
    by_room = [F.array(*[F.struct(F.lit(m).cast("long").alias("m"), F.lit(w).alias("w")) for m, w in masks(bits, r)]) for r in (0, 1, 2)]
    choice = F.when(F.col("room") == 2, by_room[2]).when(F.col("room") == 1, by_room[1]).otherwise(by_room[0])
    rows = rows.select("fp", "cell", "room", *more, own.alias("own"), F.explode(choice).alias("x"))
    cell = F.shiftleft("cell", bits).bitwiseOR(F.col("own").bitwiseXOR(F.col("x.m")))
    return rows.select("fp", cell.alias("cell"), (F.col("room") - F.col("x.w")).alias("room"), *more)


def deal_variants(fps: DataFrame, count: int, cell_rows: int = CELL_ROWS) -> DataFrame:
    """``fp, room, bits, cell``: every distinct fingerprint in each cell where it has variants."""
    have = min(24, max(6, math.ceil(math.log2(max(2, count / 64)))))
    room = F.when(F.bit_count("fp") % 2 == 0, 2).otherwise(1)
    start = fps.select("fp", F.lit(0).cast("long").alias("cell"), room.alias("room"))
    # how full the cells are follows from the counts by leading bits and parity alone
    lead = F.shiftleft(F.shiftrightunsigned("fp", 64 - have), 64 - have)
    groups = start.groupBy(lead.alias("fp"), "cell", "room").agg(F.count(F.lit(1)).alias("n"))
    held = _deal(groups, 0, have, "n").groupBy("cell").agg(F.sum("n").alias("n"))
    hot = materialize(held.where(F.col("n") > cell_rows).select("cell"), "hot")
    rows, done = _deal(start, 0, have), []
    while True:
        if have + STEP_BITS > 64 or hot.isEmpty():
            done.append(rows.withColumn("bits", F.lit(have)))
            break
        done.append(rows.join(hot, "cell", "left_anti").withColumn("bits", F.lit(have)))
        rows = materialize(_deal(rows.join(hot, "cell", "left_semi"), have, STEP_BITS), "split")
        have += STEP_BITS
        hot = materialize(rows.groupBy("cell").count().where(F.col("count") > cell_rows).select("cell"), "hot")
    out = done[0]
    for x in done[1:]:
        out = out.unionByName(x)
    return out.select("fp", "room", "bits", "cell")


def _roots(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """Least index that each of ``n`` nodes reaches over the edges a-b."""
    label = np.arange(n)
    while len(a):
        x, y = label[a], label[b]
        differ = x != y
        a, b, x, y = a[differ], b[differ], x[differ], y[differ]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
    return label


def collide(fp: np.ndarray, cell: np.ndarray, room: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning forest (fingerprint, root) of the links over the variants in whole cells of
    ``bits`` leading bits. ``room``: bits of the rest in which a variant may still differ."""
    rest = np.uint64(64 - bits)
    low = np.uint64((1 << (64 - bits)) - 1) if bits < 64 else np.uint64(0)
    at = (cell << rest if bits < 64 else cell) | (fp & low)  # the nearest variant in the cell
    far = np.bitwise_count(at ^ fp)
    one = np.array([m for m, _ in masks(64 - bits, 1)], np.uint64)
    two = np.array([m for m, w in masks(64 - bits, 2) if w == 2], np.uint64)
    own = np.arange(len(fp))
    wide = own[room >= 1]
    near = far <= 1  # variants within 1 bit: the cell's own, and for far = 0 those one bit off
    inner_v = np.concatenate([at[near], (at[far == 0][:, None] ^ one[None, 1:]).ravel()])
    inner_o = np.concatenate([own[near], np.repeat(own[far == 0], len(one) - 1)])
    order = np.argsort(inner_v, kind="stable")
    inner_v, inner_o = inner_v[order], inner_o[order]
    if not len(inner_v):
        return fp[:0], fp[:0]
    first = np.flatnonzero(np.concatenate([[True], inner_v[1:] != inner_v[:-1]]))
    keys, heads = inner_v[first], inner_o[first]
    hub = np.repeat(heads, np.diff(np.append(first, len(inner_v))))
    left, right = [inner_o[inner_o != hub]], [hub[inner_o != hub]]
    slots = 1 << max(12, int(len(keys) * 16).bit_length())
    mixer = lambda v: ((v * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(65 - slots.bit_length())).astype(np.int64)
    there = np.zeros(slots, bool)
    there[mixer(keys)] = True

    def meet(v, o):
        hit = there[mixer(v)]
        v, o = v[hit], o[hit]
        k = np.minimum(np.searchsorted(keys, v), len(keys) - 1)
        hit = keys[k] == v
        left.append(o[hit])
        right.append(heads[k[hit]])

    meet(at[far == 2], own[far == 2])
    edge = own[(far == 1) & (room >= 1)]
    meet((at[edge][:, None] ^ one[None, 1:]).ravel(), np.repeat(edge, len(one) - 1))
    wide = own[(far == 0) & (room >= 2)]
    for k in range(0, len(wide), 512):
        part = wide[k : k + 512]
        meet((at[part][:, None] ^ two[None, :]).ravel(), np.repeat(part, len(two)))
    a, b = np.concatenate(left), np.concatenate(right)
    true = (np.bitwise_count(fp[a] ^ fp[b]) <= RADIUS) & (a != b)
    root = _roots(a[true], b[true], len(fp))
    some = root != own
    return fp[some], fp[root[some]]


def links(dealt: DataFrame) -> DataFrame:
    """``u, v``: links between fingerprints, enough to connect all that are linked."""
    bound_batches(dealt.sparkSession, rows=8192)
    rows = dealt.repartition("bits", "cell").sortWithinPartitions("bits", "cell")

    def run(batches):
        held = []  # rows of the cell that may go on, and of those before it

        def flush(t):
            fp, room, bits, cell = (c.to_numpy() for c in t.columns)
            for n in np.unique(bits):
                k = bits == n
                u, v = collide(fp[k].view(np.uint64), cell[k].view(np.uint64), room[k], int(n))
                if len(u):
                    yield pa.RecordBatch.from_arrays([pa.array(u.view(np.int64)), pa.array(v.view(np.int64))], names=["u", "v"])

        for batch in batches:
            held.append(batch)
            if sum(b.num_rows for b in held) < CELL_ROWS:
                continue
            t = pa.Table.from_batches(held).combine_chunks()
            bits, cell = t["bits"].to_numpy(), t["cell"].to_numpy()
            same = (bits == bits[-1]) & (cell == cell[-1])
            cut = int(len(same) - np.argmin(same[::-1])) if not same.all() else 0
            if cut:
                yield from flush(t.slice(0, cut))
            held = t.slice(cut).to_batches()
        if held:
            yield from flush(pa.Table.from_batches(held).combine_chunks())

    return rows.mapInArrow(trimmed(run), "u long, v long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, cell_rows: int = CELL_ROWS) -> DataFrame:
    """``doc_id, fp, component_id, n_linked, digest, best``: the smallest id reachable over links
    at three bits or fewer, the number of documents in the component, and the one that stands for
    it: the least id, null last, then the least digest of the text."""
    marks = materialize(fingerprints(docs, id_col, text_col, shingle), "fingerprints")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "digest"))
    fps = materialize(marks.groupBy("fp").agg(first.alias("best"), F.count(F.lit(1)).alias("n")), "distinct")
    edges = links(deal_variants(fps.select("fp"), fps.count(), cell_rows))
    trees = components(edges)
    rooted = fps.join(trees, fps["fp"] == trees["node"], "left").select("fp", "best", "n", F.coalesce("root", "fp").alias("root"))
    named = rooted.groupBy("root").agg(F.min("best").alias("best"), F.sum("n").alias("n_linked"))
    named = materialize(rooted.select("fp", "root").join(named, "root").select("fp", "best", "n_linked"), "named")
    return marks.join(named, "fp").select("doc_id", "fp", F.col("best.doc_id").alias("component_id"), "n_linked", "digest", "best")


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """One document of each component, with its columns: the one with the least id, or, where
    none has an id, with the least digest. Rows are told apart by id and text, so each of those
    without an id, or with the same, is decided alone."""
    found = near_duplicates(docs, id_col, text_col, shingle)
    other = ~(F.col("doc_id").eqNullSafe(F.col("best.doc_id")) & (F.col("digest") == F.col("best.digest")))
    lost = materialize(found.where(other).select("doc_id", "digest").distinct(), "lost")
    rows = docs.select(whole_row(docs).alias("row"), F.col(f"`{id_col}`").cast("long").alias("id"), text_digest(F.col(f"`{text_col}`")).alias("d"))
    return rows.join(lost, rows["id"].eqNullSafe(lost["doc_id"]) & (rows["d"] == lost["digest"]), "left_anti").select("row.*")


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(documents(spark, sf_dir))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "n_linked")
