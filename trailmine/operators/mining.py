"""The mining methods: generate and count, pruned count, snapshot growth, and their choice."""

from __future__ import annotations

import time
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.kernel import Ancestors, Kernel, TooManyOutputs, alike, rows_of
from ..functions.steps import Steps, give_back, in_parts, trimmed, waits
from ..plans.transducers import Transducer, compile_expression
from ..sources.dictionary import Dictionary, build_dictionary, decode, encode, written
from ..sources.texts import Texts

#: Rows of the dictionary's (item, ancestor) table that may be broadcast.
MAX_BROADCAST_PAIRS = 20_000_000
#: Surviving nodes of a level that may be broadcast; beyond, they are joined.
MAX_BROADCAST_NODES = 500_000
#: Levels of growth, and of joins, beyond which a run is an error.
MAX_LEVELS = 1000
#: Different outputs that a worker counts before they leave it, about.
HELD_OUTPUTS = 50_000
#: Positions of which all outputs are made at once, about, and sequences for each of sigma up to
#: which pruned counting looks for the patterns that can be frequent in parts of that size.
PART, SHARE = 30_000, 100
#: Child prefixes that one row of growth holds at most; those of a sequence may be in many rows.
ROW_NODES = 128
PATTERNS = "pattern array<int>, n long"


@dataclass
class Report:
    """Effort of a run: per level nodes created and expanded, snapshots, bytes, seconds."""

    levels: list[dict] = field(default_factory=list)

    @property
    def created(self) -> int:
        return 1 + sum(x["created"] for x in self.levels)

    @property
    def expanded(self) -> int:
        return 1 + sum(x["survived"] for x in self.levels)


@dataclass
class Database:
    """Encoded sequences with their dictionary; reusable, as frequencies are independent of
    the constraint."""

    seqs: DataFrame
    dictionary: Dictionary
    _n: int | None = None

    @property
    def sequences(self) -> int:
        """Sequences that are not empty."""
        if self._n is None:
            self._n = self.seqs.count()
        return self._n


def prepare(seqs: DataFrame, edges: DataFrame | None = None) -> Database:
    seqs = written(seqs.select("sid", "items"), "named")
    d = build_dictionary(seqs, edges)
    return Database(written(encode(seqs, d), "sequences"), d)


def prepare_texts(texts: Texts, seqs: DataFrame, edges: DataFrame | None = None) -> Database:
    """As ``prepare`` of ``seqs``, by bytes of the texts where that can be."""
    found = texts.encoded()
    return prepare(seqs, edges) if found is None else Database(*found)


def n_items(db: Database) -> int:
    """The greatest id of the dictionary."""
    return db.dictionary.items.agg(F.max("fid")).first()[0] or 0


class Binding:
    """A transducer with what the kernel needs of the dictionary, sent to the workers once.

    It goes in arrays. With pruning, items with the same ancestors among those that are frequent
    or that the expression names act alike, so one of them is sent for all."""

    def __init__(self, db: Database, t: Transducer, sigma: int | None = None, plain: bool = False, on_unknown: str = "error") -> None:
        give_back()
        items, pairs = db.dictionary.items, db.dictionary.pairs
        found = {r["item"]: r["fid"] for r in items.where(F.col("item").isin(sorted(t.names))).collect()}
        if (lost := t.names - set(found)) and on_unknown == "error":
            raise ValueError(f"the expression names items that are not in the dictionary: {', '.join(sorted(lost))}")
        self.last = None if sigma is None else db.dictionary.last_frequent(sigma)
        named, n = sorted(found.values()), pairs.count()
        if sigma is not None and n > MAX_BROADCAST_PAIRS:
            keep = pairs.groupBy("fid").agg(F.max((F.col("anc") <= self.last) | F.col("anc").isin(named)).alias("k"))
            pairs = pairs.join(keep.where("k").select("fid").hint("merge"), "fid", "left_semi")
            n = pairs.count()
        if n > MAX_BROADCAST_PAIRS:
            raise MemoryError(f"{n} item-ancestor pairs matter for this expression; raise sigma or MAX_BROADCAST_PAIRS")
        table = pairs.select("fid", "anc").toArrow()
        fid, anc = (table[c].to_numpy().astype(np.int32) for c in ("fid", "anc"))
        del table
        same = None
        if sigma is not None:
            matters = np.zeros(int(max(fid.max(initial=0), anc.max(initial=0), self.last)) + 1, bool)
            matters[: self.last + 1] = True
            matters[named] = True
            same = alike(fid, anc, matters)
            own = same[fid] == fid
            own &= (fid == anc) | matters[anc]
            fid, anc = fid[own], anc[own]
            same = np.concatenate([same, np.zeros(max(0, n_items(db) + 1 - len(same)), np.int32)])
        self.t, self.plain = t, plain
        self.sent = db.seqs.sparkSession.sparkContext.broadcast((t, Ancestors(fid, anc), found, self.last, plain, same))
        give_back()

    def kernel(self) -> Kernel:
        return Kernel(*self.sent.value)

    def same(self) -> np.ndarray:
        """Items as which others act, by id."""
        return self.sent.value[-1]

    def steps(self) -> Steps:
        """Made once in a worker, for all its tasks."""
        t, up, ids, last, plain, _ = self.sent.value
        if up.steps is None:
            up.steps = Steps(t, np.repeat(np.arange(len(up.starts) - 1, dtype=np.int32), np.diff(up.starts)), up.above, ids, last, plain)
        return up.steps


def combined(outputs):
    """Arrow batches of (pattern, times) from the outputs of many sequences."""
    held: Counter = Counter()

    def batch():
        got = pa.RecordBatch.from_arrays([pa.array(map(list, held), pa.list_(pa.int32())), pa.array(held.values(), pa.int64())], names=["pattern", "n"])
        held.clear()
        return got

    for found in outputs:
        held.update(found)
        if len(held) >= HELD_OUTPUTS:
            yield batch()
    if held:
        yield batch()


def counted(rows: DataFrame, sigma: int) -> DataFrame:
    """``pattern, freq`` of patterns with times."""
    return rows.groupBy("pattern").agg(F.sum("n").alias("freq")).where(F.col("freq") >= sigma)


def _counted(db: Database, b: Binding, sigma: int, limit: int | None) -> DataFrame:
    def run(batches):
        k = b.kernel()
        yield from combined(k.generate(k.known(items), limit) for batch in batches for items in rows_of(batch.column(0)))

    return counted(db.seqs.select("items").mapInArrow(run, PATTERNS), sigma)


def generate_and_count(db: Database, t: Transducer, sigma: int, limit: int | None = 1_000_000, plain: bool = False) -> DataFrame:
    """All outputs of every sequence, counted. ``limit`` guards the outputs of one sequence."""
    return _counted(db, Binding(db, t, None, plain), sigma, limit)


def pruned_count(db: Database, t: Transducer, sigma: int, limit: int | None = 1_000_000) -> DataFrame:
    """As above, but a run ends where it would yield an infrequent item.

    Outputs are made over arrays of many sequences. Where parts of the sequences are large for
    sigma, a frequent pattern is in its share of the sequences in one part at least: tasks make and
    count all outputs of each part, and patterns without their share in any are not shuffled; the
    others are then counted over all sequences."""
    b = Binding(db, t, sigma)
    if waits(t) - ({t.start} if t.anywhere else set()):
        return _counted(db, b, sigma, limit)
    n = db.sequences
    if n <= SHARE * sigma:
        rows = _made(db, b, lambda seqs: max(1, -(-sigma * seqs // n)), limit, True)
        some = rows.select("pattern").distinct().limit(MAX_BROADCAST_NODES + 1).toArrow()
        if len(some) <= MAX_BROADCAST_NODES:
            return _counted_known(db, b, sigma, list(map(tuple, some["pattern"].to_pylist())))
    return counted(_made(db, b, lambda seqs: 1, limit), sigma)


def _parts(batches, least: int):
    """(items, sizes of the sequences) of ``least`` positions, and not twice as many, about. No part
    ends with a batch: patterns would need few of its sequences."""
    from .local import chunks

    held, many = [], 0

    def joined(some):
        return tuple(map(np.concatenate, zip(*some, strict=True)))

    for batch in batches:
        for part in chunks(batch.column(0), least // 4):
            held.append(part)
            many += len(part[0])
            if many >= 2 * least:
                at = int(np.searchsorted(np.cumsum([len(x[0]) for x in held]), least)) + 1
                yield joined(held[:at])
                held = held[at:]
                many = sum(len(x[0]) for x in held)
    if held:
        yield joined(held)


def _guarded(lengths, limit: int | None):
    """``Steps.patterns``, until a sequence has too many."""
    total = 0
    for *found, own in lengths:
        total = total + own
        if limit is not None and total.max(initial=0) > limit:
            raise TooManyOutputs(f"over {limit} outputs of one sequence")
        yield *found, total


def _made(db: Database, b: Binding, least, limit: int | None, once: bool = False) -> DataFrame:
    """``pattern, n`` of the outputs that are in ``least`` (of their number) sequences of a part;
    ``once``: without regard to n, a task may leave out what it has yielded."""

    def outputs(s: Steps) -> list:
        before, out, enough = [], [], least(s.seqs)
        for parent, o, n, _ in _guarded(s.patterns(enough), limit):
            some = np.flatnonzero(n >= enough)
            at, items = parent[some], [o[some]]
            for parents, outs in reversed(before):
                items.append(outs[at])
                at = parents[at]
            before.append((parent, o))
            out.append((np.column_stack(items[::-1]).astype(np.int32), n[some]))
        return out

    def run(batches):
        s, same, had = b.steps(), b.same(), set()
        for flat, sizes in _parts(batches, PART):
            for rows, n in (x for part in in_parts(s, same[flat], sizes, outputs) for x in part):
                if once:
                    new = np.array([x not in had for x in map(tuple, rows.tolist())], bool)
                    had = set() if len(had) > HELD_OUTPUTS else had
                    had.update(map(tuple, rows[new].tolist()))
                    rows, n = rows[new], n[new]
                for at in range(0, len(n), HELD_OUTPUTS):
                    some = rows[at : at + HELD_OUTPUTS]
                    lists = pa.ListArray.from_arrays(np.arange(0, some.size + 1, some.shape[1], dtype=np.int32), pa.array(some.ravel()))
                    yield pa.RecordBatch.from_arrays([lists, pa.array(n[at : at + HELD_OUTPUTS])], names=["pattern", "n"])

    return db.seqs.select("items").mapInArrow(trimmed(run), PATTERNS)


def _counted_known(db: Database, b: Binding, sigma: int, patterns: list[tuple]) -> DataFrame:
    """``pattern, freq`` of those patterns that are frequent, few enough to be sent to all tasks."""
    from .local import lookup

    spark, width, numbers, names, tables = db.seqs.sparkSession, b.last + 1, {(): 0}, [], []
    prefixes = {p[:k] for p in patterns for k in range(1, len(p) + 1)}
    for k in range(1, max(map(len, patterns), default=0) + 1):
        names.append(sorted(x for x in prefixes if len(x) == k))
        tables.append(np.array([numbers[x[:-1]] * width + x[-1] for x in names[-1]], np.int64))
        numbers.update((x, n) for n, x in enumerate(names[-1]))
    sent = spark.sparkContext.broadcast(tables)

    def run(batches):
        s, same, tables = b.steps(), b.same(), sent.value
        counts = [np.zeros(len(x), np.int64) for x in tables]
        known = [(lookup(x, n, width), len(x)) for x, n in zip(tables, [1, *map(len, tables)], strict=False)]
        for flat, sizes in _parts(batches, PART):
            for part in in_parts(s, same[flat], sizes, lambda s: [x[2] for x in s.patterns(1, known, width)]):
                for k, n in enumerate(part):
                    counts[k] += n
        for k, n in enumerate(counts):
            some = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), k, np.int32)), pa.array(some), pa.array(n[some])], names=["length", "number", "n"])

    rows = db.seqs.select("items").mapInArrow(trimmed(run), "length int, number long, n long")
    rows = rows.groupBy("length", "number").agg(F.sum("n").alias("freq")).where(F.col("freq") >= sigma).toArrow()
    found = [(list(names[r["length"]][r["number"]]), r["freq"]) for r in rows.to_pylist()]
    return spark.createDataFrame(found, "pattern array<int>, freq long")


def plain_count(db: Database, t: Transducer, sigma: int, limit: int | None = 1_000_000) -> DataFrame:
    """All outputs of every sequence by the uncompressed form, stepped over arrays."""
    if waits(t) - ({t.start} if t.anywhere else set()):
        return generate_and_count(db, t, sigma, limit, True)
    from .local import chunks

    b = Binding(db, t, None, True)

    def outputs(s: Steps):
        """Arrow batches of (pattern, times) of the sequences loaded, each of one length."""
        out, rows, total = [], None, np.zeros(s.seqs, np.int64)
        for parent, o, _, (pat, seq) in s.levels([], s.none + 1):
            rows = o[:, None].astype(np.int32) if rows is None else np.column_stack([rows[parent], o.astype(np.int32)])
            total += np.bincount(seq, minlength=s.seqs)
            if limit is not None and total.max(initial=0) > limit:
                raise TooManyOutputs(f"over {limit} outputs of one sequence")
            n = np.bincount(pat, minlength=len(o))
            for at in range(0, len(n), HELD_OUTPUTS):
                some = at + np.flatnonzero(n[at : at + HELD_OUTPUTS])
                lists = pa.ListArray.from_arrays(np.arange(0, rows.shape[1] * len(some) + 1, rows.shape[1], dtype=np.int32), pa.array(rows[some].ravel()))
                out.append(pa.RecordBatch.from_arrays([lists, pa.array(n[some])], names=["pattern", "n"]))
        return out

    def run(batches):
        s = b.steps()
        for batch in batches:
            for flat, sizes in chunks(batch.column(0), 20_000):
                for part in in_parts(s, flat, sizes, outputs):
                    yield from part

    return counted(db.seqs.select("items").mapInArrow(trimmed(run), PATTERNS), sigma)


def snapshot_growth(db: Database, t: Transducer, sigma: int, max_level: int = MAX_LEVELS, report: Report | None = None, prune_nodes: bool = True) -> DataFrame:
    """Growth of output prefixes, level by level, over snapshots (position, state).

    Sequences never move; only counters per (prefix, item) are shuffled. A child lives on if
    ``sigma`` sequences support it as a prefix. ``prune_nodes`` off (an ablation) keeps any child.

    Snapshots are stepped in arrays (``local.grow``) where that can be and no effort is asked for.
    Else a row holds a sequence and its snapshots per live prefix (of many prefixes: some, in
    several rows, so that rows stay small)."""
    from . import local

    if report is None and prune_nodes:
        try:
            if (found := local.grow(db, t, sigma, max_level)) is not None:
                return found
        except local.TooManyPrefixes:
            pass
    spark, b = db.seqs.sparkSession, Binding(db, t, sigma)

    step_type = "sid long, items array<int>, accepts array<long>, nodes array<long>, outs array<int>, snaps array<array<int>>"
    start = t.start
    frontier = db.seqs.select("sid", "items", F.array(F.lit(0).cast("long")).alias("nodes"), F.array(F.array(F.lit(0), F.lit(start))).alias("snaps"))
    patterns = spark.range(1).select(F.col("id").alias("node"), F.array().cast("array<int>").alias("pattern"))
    results, known = [], None

    def arrow(rows):
        if rows:
            ints, longs = pa.list_(pa.int32()), pa.list_(pa.int64())
            kinds = (pa.int64(), ints, longs, longs, ints, pa.list_(ints))
            cols = [pa.array(c, kind) for c, kind in zip(zip(*rows, strict=True), kinds, strict=True)]
            yield pa.RecordBatch.from_arrays(cols, names=["sid", "items", "accepts", "nodes", "outs", "snaps"])

    def step(known, level):
        def run(batches):
            k = b.kernel()
            keep = known.value if known is not None else None
            out, held = [], 0
            for batch in batches:
                for sid, items, nodes, outs, snaps in zip(*map(rows_of, batch.columns), strict=True):
                    items = items if level > 1 else k.known(items)
                    alive, places, row = None, None, (sid, items, [], [], [], [])
                    for node, o, s in zip(nodes, outs, snaps, strict=True):
                        if keep is not None:
                            node = keep.get((node, o))
                            if node is None:
                                continue
                        alive, places = alive or k.alive(items), places or k.places(items)
                        ok, children = k.resume(items, zip(s[::2], s[1::2]), alive, places)
                        if ok and o:
                            row[2].append(node)
                        for w, at in children.items():
                            row[3].append(node)
                            row[4].append(w)
                            row[5].append([x for p in sorted(at) for x in p])
                            if len(row[3]) >= ROW_NODES:
                                out.append(row)
                                row = (sid, items, [], [], [], [])
                    if row[2] or row[3]:
                        out.append(row)
                    held += len(items) + 3 * len(nodes)
                    if len(out) >= 1000 or held >= 100_000:
                        yield from arrow(out)
                        out, held = [], 0
            yield from arrow(out)

        return run

    frontier = frontier.withColumn("outs", F.array(F.lit(0)))
    for level in range(1, max_level + 2):
        began = time.time()
        moved = frontier.select("sid", "items", "nodes", "outs", "snaps").mapInArrow(step(known, level), step_type)
        moved = written(moved, "frontier")
        if level > 1:
            hits = moved.select(F.explode("accepts").alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("freq"))
            results.append(patterns.join(hits.where(F.col("freq") >= sigma), "node").select("pattern", "freq"))
        pairs = moved.select(F.explode(F.arrays_zip("nodes", "outs")).alias("x")).groupBy(F.col("x.nodes").alias("node"), F.col("x.outs").alias("item"))
        counted = written(pairs.agg(F.count(F.lit(1)).alias("presup")), "children")
        children = counted.where(F.col("presup") >= (sigma if prune_nodes else 1))
        children = written(children.withColumn("new", F.monotonically_increasing_id()), "survivors")
        survived = children.count()
        if report is not None:
            snaps = F.aggregate("snaps", F.lit(0).cast("long"), lambda a, s: a + F.size(s))
            held = moved.agg(F.sum(snaps)).first()[0] or 0
            report.levels.append({"level": level, "created": counted.count(), "survived": survived, "snapshots": held // 2, "bytes": held * 2, "seconds": time.time() - began})
        if not survived:
            break
        if level > max_level:
            raise RuntimeError(f"patterns are longer than {max_level}")
        patterns = written(children.join(patterns, "node").select(F.col("new").alias("node"), F.concat("pattern", F.array("item")).alias("pattern")), "patterns")
        if survived <= MAX_BROADCAST_NODES:
            table = children.select("node", "item", "new").toArrow()
            ids = dict(zip(zip(table["node"].to_pylist(), table["item"].to_pylist(), strict=True), table["new"].to_pylist(), strict=True))
            known, frontier = spark.sparkContext.broadcast(ids), moved
        else:
            rows = moved.select("sid", "items", F.explode(F.arrays_zip("nodes", "outs", "snaps")).alias("x"))
            rows = rows.select("sid", "items", F.col("x.nodes").alias("node"), F.col("x.outs").alias("item"), F.col("x.snaps").alias("s"))
            rows = rows.join(children.select("node", "item", "new"), ["node", "item"]).groupBy("sid").agg(F.first("items").alias("items"), F.collect_list(F.struct("new", "item", "s")).alias("x"))
            known, frontier = None, rows.select("sid", "items", F.col("x.new").alias("nodes"), F.col("x.item").alias("outs"), F.col("x.s").alias("snaps"))

    out = spark.createDataFrame([], "pattern array<int>, freq long") if not results else results[0]
    for r in results[1:]:
        out = out.unionByName(r)
    return out


def mean_outputs(db: Database, t: Transducer, sigma: int | None, fraction: float | None = None, limit: int | None = None) -> DataFrame:
    """``n_sequences, mean_outputs, n_pairs``: outputs per sequence that has any; with
    ``sigma`` None nothing is pruned. Outputs are made over arrays of many sequences; those of a
    sample one sequence after another, as its guard is to end them early."""
    b = Binding(db, t, sigma)
    arrays = fraction is None and not waits(t) - ({t.start} if t.anywhere else set())

    def one_by_one(batches):
        k = b.kernel()
        for batch in batches:
            counts = [len(k.generate(k.known(x), limit)) for x in rows_of(batch.column(0))]
            yield pa.RecordBatch.from_arrays([pa.array(counts, pa.int64())], names=["n"])

    def sizes_of(s: Steps) -> np.ndarray:
        n = np.zeros(s.seqs, np.int64)
        for *_, n in _guarded(s.patterns(None), limit):
            pass
        return n

    def stepped(batches):
        s, same = b.steps(), b.same()
        for flat, sizes in _parts(batches, PART):
            for n in in_parts(s, flat if same is None else same[flat], sizes, sizes_of):
                yield pa.RecordBatch.from_arrays([pa.array(n)], names=["n"])

    run = trimmed(stepped) if arrays else one_by_one
    seqs = db.seqs if fraction is None else db.seqs.sample(fraction, seed=1)
    rows = seqs.select("items").mapInArrow(run, "n long").where("n > 0")
    return rows.agg(F.count(F.lit(1)).alias("n_sequences"), F.avg("n").alias("mean_outputs"), F.sum("n").alias("n_pairs"))


def choose_method(db: Database, t: Transducer, sigma: int, few: float = 20.0, sample: int = 500) -> str:
    """Pruned count where a sample of sequences has few outputs each, else growth."""
    from ..functions.kernel import TooManyOutputs

    fraction = min(1.0, sample / max(1, db.dictionary.sequences))
    try:
        r = mean_outputs(db, t, sigma, fraction, limit=10_000).first()
    except Exception as e:  # the guard's error comes wrapped by Spark
        if TooManyOutputs.__name__ in str(e):
            return "growth"
        raise
    return "pruned" if (r["mean_outputs"] or 0) <= few else "growth"


def mine(db: Database, expression, sigma: int, match: str = "anywhere", method: str = "auto", optimized: bool = True, force: bool = False, **options) -> DataFrame:
    """``pattern, length, freq`` of all patterns in at least ``sigma`` sequences.

    ``method``: "naive", "plain" (naive over the uncompressed transducer), "pruned",
    "growth", "joins" (where the expression can be said by joins on positions) or "auto": joins
    where that can be, else pruned or growth by a sample."""
    if sigma < 1 or sigma == 1 and not force and ".*" in str(expression).replace(" ", ""):
        raise ValueError("sigma must be 2 or more for free gaps, or force=True")
    from . import native

    t = compile_expression(expression, match, optimized)
    if method in ("auto", "joins"):
        if (g := native.from_transducer(t)) is not None:
            return decode(native.walk(db, g, sigma), db.dictionary)
        if method == "joins":
            raise ValueError("the expression cannot be said by joins on positions")
        method = choose_method(db, t, sigma)
    run = {"naive": generate_and_count, "plain": plain_count, "pruned": pruned_count, "growth": snapshot_growth}
    return decode(run[method](db, t, sigma, **options), db.dictionary)


def relative_sigma(sigma: int, of: int, n: int) -> int:
    """What ``sigma`` of ``of`` sequences is of ``n``, rounded up; 2 at least."""
    return max(2, -(-sigma * n // of))


def supporting_sequences(db: Database, expression, pattern: list[str], match: str = "anywhere") -> DataFrame:
    """``sid`` of the sequences that have the pattern among their outputs."""
    ids = {r["item"]: r["fid"] for r in db.dictionary.items.where(F.col("item").isin(pattern)).collect()}
    if set(pattern) - set(ids):
        return db.seqs.select("sid").limit(0)
    goal = tuple(ids[w] for w in pattern)
    b, wanted = Binding(db, compile_expression(expression, match)), {goal[:k] for k in range(1, len(goal) + 1)}

    def run(batches):
        k = b.kernel()
        for batch in batches:
            hit = [goal in k.generate(x, None, wanted) for x in rows_of(batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(hit, pa.bool_()))], names=["sid"])

    return db.seqs.select("sid", "items").mapInArrow(run, "sid long")


def pattern_support(db: Database, expression, patterns: list[list[str]], match: str = "anywhere") -> DataFrame:
    """``pattern, length, freq`` of the given patterns (a list that fits the driver), zero included."""
    names = sorted({w for p in patterns for w in p})
    ids = {r["item"]: r["fid"] for r in db.dictionary.items.where(F.col("item").isin(names)).collect()}
    goals = {tuple(ids.get(w, -1) for w in p): p for p in patterns}
    wanted = {g[:k] for g in goals for k in range(1, len(g) + 1)}
    b = Binding(db, compile_expression(expression, match))

    def run(batches):
        k = b.kernel()
        for batch in batches:
            got = [" ".join(map(str, g)) for x in rows_of(batch.column(0)) for g in k.generate(x, None, wanted) if g in goals]
            yield pa.RecordBatch.from_arrays([pa.array(got, pa.string())], names=["goal"])

    counts = db.seqs.select("items").mapInArrow(run, "goal string").groupBy("goal").agg(F.count(F.lit(1)).alias("freq"))
    table = [(" ".join(map(str, g)), " ".join(w.replace(" ", "_") for w in p), len(p)) for g, p in goals.items()]
    rows = db.seqs.sparkSession.createDataFrame(table, "goal string, pattern string, length int")
    return rows.join(counts, "goal", "left").select("pattern", "length", F.coalesce("freq", F.lit(0)).alias("freq"))
