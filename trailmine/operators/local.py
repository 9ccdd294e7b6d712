"""Joins of positions where the sequences lie: every task walks a graph over arrays of its own
sequences, and only counts of (prefix, item) leave it."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.steps import in_parts, spread, waits
from ..plans.transducers import Transducer
from .mining import MAX_BROADCAST_NODES, MAX_LEVELS, Binding, Database

#: Positions that are walked at once, about (a sequence is never cut), and counters held by a task.
CHUNK, HELD = 100_000, 200_000
#: Prefixes that may be counted without those one shorter being known to be frequent.
AHEAD = 20_000
#: Keys of a length up to which a task looks prefixes up by place.
DENSE = 4_000_000


class TooManyPrefixes(RuntimeError):
    """More prefixes are frequent than the driver should hold."""


def by_two(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """The stable order by two columns; short numbers are sorted by their digits."""

    def short(x):
        return x.astype(np.uint16) if x.max(initial=0) < 1 << 16 else x

    order = np.argsort(short(second), kind="stable")
    return order[np.argsort(short(first[order]), kind="stable")]


def slot_outputs(kernel, slot, items: int) -> tuple[np.ndarray, np.ndarray]:
    """By item: starts into the outputs of a slot; 0 stands for none."""
    test = ("any",) if slot.name is None else ("is" if slot.exact else "below", slot.name)
    out = ("const", slot.name) if slot.const else ("upto", slot.name) if slot.up and slot.name else ("up",) if slot.up else ("self",)
    sizes, outs = np.zeros(items + 1, np.int64), []
    for w in range(items + 1) if slot.name is None and not slot.captured else kernel.up:
        if kernel.matches(test, w):
            own = dict.fromkeys(kernel.outputs(out, w)) if slot.captured else (0,)
            sizes[w] = len(own)
            outs += own
    return np.concatenate([[0], np.cumsum(sizes)]), np.array(outs, np.int64)


class Walker:
    """A graph over one chunk of sequences after another. ``tables``: for each length of prefixes
    the sorted keys (prefix number * width + item) of the frequent ones, numbered in this order."""

    def __init__(self, edges, ends, slots, tables, width) -> None:
        self.edges, self.slots, self.tables, self.width = edges, slots, tables, width
        self.nodes = 1 + max(max(e[0], e[4]) for e in edges)
        inner = {e[0] for e in edges}
        self.inner = np.array([q in inner for q in range(self.nodes)])
        self.ends = np.array([q in ends for q in range(self.nodes)])
        #: of a prefix at these nodes the first place is enough: only free gaps follow, or nothing
        self.first = np.array([all(e[3] is None for e in edges if e[0] == q) for q in range(self.nodes)])

    def load(self, flat: np.ndarray, sizes: np.ndarray) -> None:
        self.flat, self.n = flat, len(flat)
        self.seq = np.repeat(np.arange(len(sizes)), sizes)
        self.begin = np.cumsum(sizes) - sizes
        self.end = self.begin + sizes
        self.hits = {}

    def hit(self, slot: int) -> dict:
        """Places and outputs of a slot, by sequence and place; by sequence, output and place."""
        if slot not in self.hits:
            starts, outs = self.slots[slot]
            at, k = spread(starts[self.flat], starts[self.flat + 1] - starts[self.flat])
            out, seq = outs[k], self.seq[at]
            order = by_two(seq, out)
            s, o, p = seq[order], out[order], at[order]
            new = np.flatnonzero(np.concatenate([[True], (s[1:] != s[:-1]) | (o[1:] != o[:-1])])) if len(s) else np.empty(0, np.int64)
            group = np.repeat(np.arange(len(new)), np.diff(np.concatenate([new, [len(s)]])))
            self.hits[slot] = {"at": at, "out": out, "by_seq": np.searchsorted(seq, np.arange(len(self.begin) + 1)), "place": group * (self.n + 1) + p, "p": p, "group_out": o[new], "groups": np.searchsorted(s[new], np.arange(len(self.begin) + 1))}
        return self.hits[slot]

    def move(self, edge, p: np.ndarray, pat: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(place, prefix, output) after an edge."""
        at, slot, low, high, to = edge
        if at == 0:  # p is the first place of each sequence
            h = self.hit(slot)
            nth = h["at"] - self.begin[self.seq[h["at"]]]
            ok = (nth >= low) & (nth <= (self.n if high is None else high))
            return h["at"][ok], np.zeros(int(ok.sum()), np.int64), h["out"][ok]
        seq = self.seq[p]
        if high is not None:
            starts, outs = self.slots[slot]
            found = []
            for d in range(low + 1, high + 2):
                rows = np.flatnonzero(p + d < self.end[seq])
                w = self.flat[p[rows] + d]
                r, k = spread(starts[w], starts[w + 1] - starts[w])
                found.append((p[rows[r]] + d, pat[rows[r]], outs[k]))
            return tuple(map(np.concatenate, zip(*found, strict=True)))
        h = self.hit(slot)
        if self.first[to]:
            r, g = spread(h["groups"][seq], h["groups"][seq + 1] - h["groups"][seq])
            k = np.searchsorted(h["place"], g * (self.n + 1) + p[r] + low + 1)
            ok = k < np.searchsorted(h["place"], (g + 1) * (self.n + 1))
            return h["p"][k[ok]], pat[r[ok]], h["group_out"][g[ok]]
        start = np.searchsorted(h["at"], p + low + 1)
        stop = np.maximum(start, h["by_seq"][seq + 1])
        r, k = spread(start, stop - start)
        return h["at"][k], pat[r], h["out"][k]

    def thin(self, p, node, pat):
        """Rows once each; of nodes where the first place is enough, that alone."""
        if not len(p):
            return p, node, pat
        p = np.where(self.inner[node], p, self.begin[self.seq[p]])
        code = np.sort(self.coded(p, node, pat))
        code = code[np.concatenate([[True], code[1:] != code[:-1]])]
        way, p = np.divmod(code, self.n)
        node = way % self.nodes
        if self.first[node].any():
            same = (way[1:] == way[:-1]) & self.first[node[1:]] & (self.seq[p[1:]] == self.seq[p[:-1]])
            ok = np.concatenate([[True], ~same])
            p, node, way = p[ok], node[ok], way[ok]
        return p, node, way // self.nodes

    def closed(self, p, node, pat, captured: list[bool]):
        """With all rows that edges without output lead to."""
        all_ = self.thin(p, node, pat)
        new, seen = all_, self.coded(*all_)
        while len(new[0]):
            moved = self.moved(*new, [e for e in self.edges if not captured[e[1]]])
            p, node, pat = self.thin(*moved[:3])
            code = self.coded(p, node, pat)
            fresh = ~np.isin(code, seen)
            new = p[fresh], node[fresh], pat[fresh]
            all_, seen = tuple(map(np.concatenate, zip(all_, new, strict=True))), np.concatenate([seen, code[fresh]])
        return all_

    def coded(self, p, node, pat):
        return (pat * self.nodes + node) * self.n + p

    def moved(self, p, node, pat, edges):
        found = [(np.empty(0, np.int64),) * 4]
        for e in edges:
            rows = np.flatnonzero(node == e[0])
            if len(rows):
                at, pats, out = self.move(e, p[rows], pat[rows])
                found.append((at, np.full(len(at), e[4]), pats, out))
        return tuple(map(np.concatenate, zip(*found, strict=True)))

    def count(self, captured: list[bool], ahead: int = 1) -> list[tuple]:
        """For each of ``ahead`` lengths behind those of the tables: keys of the prefixes (of the
        prefix one shorter * width + item), the sequences that reach each, and those that have it
        as a pattern."""
        full = np.flatnonzero(self.end > self.begin)
        rows = (self.begin[full][:1], np.zeros(min(1, len(full)), np.int64), np.zeros(min(1, len(full)), np.int64))
        counts, names = [], None
        for length in range(len(self.tables) + ahead):
            rows = self.closed(*rows, captured) if length or not all(captured) else rows
            p, node, pat, out = self.moved(*rows, [e for e in self.edges if captured[e[1]]])
            key = (pat if names is None else names[pat]) * self.width + out
            if length < len(self.tables):
                table = self.tables[length]
                pat = np.searchsorted(table, key)
                ok = table[np.minimum(pat, len(table) - 1)] == key
                rows = self.thin(p[ok], node[ok], pat[ok])
                continue
            names, pat = np.unique(key, return_inverse=True)
            rows = self.thin(p, node, pat)
            if not all(captured):
                rows = self.closed(*rows, captured)
            p, node, pat = rows
            per = lambda ok: np.bincount(np.unique(pat[ok] * len(self.begin) + self.seq[p[ok]]) // len(self.begin), minlength=len(names))  # noqa: B023, E731
            reached, done = per(np.ones(len(p), bool)), self.ends[node]
            counts.append((names, reached, reached if done.all() else per(done) if done.any() else np.zeros_like(reached)))
            rows = tuple(x[self.inner[node]] for x in rows)
        return counts


def chunks(col: pa.ListArray, some: int = CHUNK):
    """(items, sizes of the sequences) of a few sequences of a column."""
    offsets, values, at = col.offsets.to_numpy().astype(np.int64), col.values.to_numpy(), 0
    while at < len(col):
        to = max(at + 1, int(np.searchsorted(offsets, offsets[at] + some, "right")) - 1)
        yield values[offsets[at] : offsets[to]], np.diff(offsets[at : to + 1])
        at = to


def summed(parts: list) -> tuple:
    keys, reached, had = map(np.concatenate, zip(*parts, strict=True))
    keys, of = np.unique(keys, return_inverse=True)
    return keys, *(np.bincount(of, x, len(keys)).astype(np.int64) for x in (reached, had))


def lengths_ahead(edges: list, captured: list[bool], kinds: list[int], width: int, nodes: set[int], prefixes: int) -> tuple[int, list[set[int]]]:
    """How many lengths may be counted in one pass, as no more than ``AHEAD`` prefixes can come of
    those that are known (one length always), and the nodes after each; 0 if none can follow."""
    held, after, most, size = {q: prefixes for q in nodes}, [], prefixes, prefixes
    while len(after) < MAX_LEVELS:
        for _ in edges:  # tests without output lead on within a length
            for at, slot, _, _, to in edges:
                if at in held and not captured[slot]:
                    held[to] = max(held.get(to, 0), held[at])
        nxt = {}
        for at, slot, _, _, to in edges:
            if at in held and captured[slot]:
                nxt[to] = nxt.get(to, 0) + held[at] * kinds[slot]
        most, size = sum(nxt.values()), size * width
        if not nxt or after and (most > AHEAD or size >= 1 << 62):
            break
        after.append(set(nxt))
        held = nxt
    return len(after), after


def by_lengths(db: Database, sigma: int, width: int, lengths, counter, start: int = 0, most: int = MAX_LEVELS) -> DataFrame:
    """``pattern array<int>, freq``, counted by distinct sequence.

    Prefixes grow by one item a pass, or by several where few can come of it; a pass goes over all
    sequences anew along the prefixes that enough sequences reach, so nothing but counters is
    shuffled or written. ``lengths``: of nodes and a number of prefixes, as ``lengths_ahead``.
    ``counter``: makes of tables of prefixes, in a task, the items as which items act and a function
    of (items, sizes of the sequences, lengths) that lists what ``Walker.count`` does, in parts."""
    spark = db.seqs.sparkSession
    tables, patterns, found, nodes = [], [()], [], {start}
    while True:
        ahead, after = lengths(nodes, len(patterns))
        if not ahead:
            break
        sent = spark.sparkContext.broadcast(tables)

        def run(batches, sent=sent, ahead=ahead):
            same, count = counter(sent.value)
            parts, held = [[] for _ in range(ahead)], 0

            def batch_of(k, part):
                return pa.RecordBatch.from_arrays([pa.array(np.full(len(part[0]), k, np.int32)), *map(pa.array, part)], names=["ahead", "key", "reached", "had"])

            for batch in batches:
                for flat, sizes in chunks(batch.column(0)):
                    for counts in count(same[flat], sizes, ahead):
                        for k, part in enumerate(counts):
                            parts[k].append(part)
                            held += len(part[0])
                    if held > HELD:
                        parts = [[summed(x)] if x else [] for x in parts]
                        held = sum(len(x[0][0]) for x in parts if x)
                        if held > HELD // 2:
                            yield from (batch_of(k, x[0]) for k, x in enumerate(parts) if x)
                            parts, held = [[] for _ in range(ahead)], 0
            yield from (batch_of(k, summed(x)) for k, x in enumerate(parts) if x)

        rows = db.seqs.select("items").mapInArrow(run, "ahead int, key long, reached long, had long")
        rows = rows.groupBy("ahead", "key").agg(F.sum("reached").alias("reached"), F.sum("had").alias("had")).where(F.col("reached") >= sigma)
        got = rows.limit(MAX_BROADCAST_NODES + 1).toArrow()
        if len(got) > MAX_BROADCAST_NODES:
            raise TooManyPrefixes(f"over {MAX_BROADCAST_NODES} prefixes of {len(tables) + 1} items are frequent")
        places = np.arange(len(patterns))
        for k in range(ahead):
            table = got.filter(pc.equal(got["ahead"], k)).sort_by("key")
            if not len(table):
                patterns = []
                break
            if len(tables) >= most:
                raise RuntimeError(f"patterns are longer than {most} items")
            keys = table["key"].to_numpy()
            before = np.searchsorted(places, keys // width)
            patterns = [(*patterns[x], y) for x, y in zip(before.tolist(), (keys % width).tolist(), strict=True)]
            found += [(list(x), n) for x, n in zip(patterns, table["had"].to_pylist(), strict=True) if n >= sigma]
            tables.append(before * width + keys % width)
            places = keys
        if not patterns:
            break
        nodes = after[-1]
    return spark.createDataFrame(found, "pattern array<int>, freq long")


def walk(db: Database, g, sigma: int) -> DataFrame:
    """The patterns of a graph."""
    b = Binding(db, Transducer([[]], 0, frozenset(), names={s.name for s in g.slots if s.name}), sigma)
    k, number = b.kernel(), {s: n for n, s in enumerate(g.slots)}
    width = b.last + 1
    slots = [slot_outputs(k, s, len(k.alike) - 1) for s in g.slots]
    edges = [(at, number[s], low, high, to) for at, s, low, high, to in g.edges]
    captured, ends = [s.captured for s in g.slots], g.ends
    kinds = [len(np.unique(outs)) for _, outs in slots]
    fixed = db.seqs.sparkSession.sparkContext.broadcast((slots, k.alike))

    def counter(tables):
        slots, same = fixed.value
        w = Walker(edges, ends, slots, tables, width)

        def count(flat, sizes, ahead):
            w.load(flat, sizes)
            return [w.count(captured, ahead)]

        return same, count

    return by_lengths(db, sigma, width, lambda nodes, n: lengths_ahead(edges, captured, kinds, width, nodes, n), counter, most=MAX_LEVELS + 1)


def lookup(table: np.ndarray, before: int, width: int):
    """Function from keys of prefixes to their numbers, -1 of those that are not in the table."""
    if before * width <= DENSE:
        number = np.full(before * width, -1, np.int32)
        number[table] = np.arange(len(table))
        return lambda key: number[key].astype(np.int64)

    def find(key):
        at = np.minimum(np.searchsorted(table, key), len(table) - 1)
        return np.where(table[at] == key, at, -1)

    return find


def grow(db: Database, t: Transducer, sigma: int, max_level: int = MAX_LEVELS) -> DataFrame | None:
    """Growth of output prefixes over snapshots (position, state) held in arrays: those of the
    prefixes that live on are stepped anew in each pass, so that none are written. None where states
    behind the start wait for any number of items."""
    if waits(t) - ({t.start} if t.anywhere else set()):
        return None
    b = Binding(db, t, sigma)
    labels, width = list(dict.fromkeys((i, o) for ms in t.moves for i, o, _ in ms)), b.last + 1
    number, kinds = {x: n for n, x in enumerate(labels)}, b.steps().kinds
    edges = [(q, number[i, o], 0, None, to) for q, ms in enumerate(t.moves) for i, o, to in ms]
    captured, sizes = [o is not None for _, o in labels], [kinds[x] for x in labels]

    def counter(tables):
        s = b.steps()
        known = [lookup(x, n, width) for x, n in zip(tables, [1, *map(len, tables)], strict=False)]

        def levels(s, ahead):
            out, before = [], None
            for parent, o, reached, (pat, _) in s.levels(known, width, ahead):
                before = (parent if before is None else before[parent]) * width + o
                out.append((before, reached, np.bincount(pat, minlength=len(o))))
            return out

        return b.same(), lambda flat, sizes, ahead: in_parts(s, flat, sizes, lambda s: levels(s, ahead))

    return by_lengths(db, sigma, width, lambda nodes, n: lengths_ahead(edges, captured, sizes, width, nodes, n), counter, t.start, max_level)
