"""Simulation of a transducer over arrays of many encoded sequences at once; runs inside Arrow
tasks. A snapshot (prefix, position, state) is an element of three arrays."""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa

from ..plans.transducers import Transducer

#: Snapshots that one step may make of several sequences; beyond, fewer are taken at once.
MOST_SNAPSHOTS = 1_000_000
#: Different last items of patterns up to which they are held as bits of a set, and rows of such
#: sets that are counted at once.
MOST_BITS, BIT_ROWS = 1024, 50_000


class TooManySnapshots(RuntimeError):
    """The sequences of a chunk have to be taken in smaller parts."""


def spread(starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Row numbers, each as often as its size, and the indices from its start on."""
    rows = np.repeat(np.arange(len(sizes)), sizes)
    first = np.cumsum(sizes) - sizes
    return rows, np.arange(len(rows)) - np.repeat(first - starts, sizes)


def waits(t: Transducer) -> set[int]:
    """States that may skip any items."""
    return {q for q, ms in enumerate(t.moves) if any(i[0] == "any" and not o and to == q for i, o, to in ms)}


class Steps:
    """Moves of a transducer by state and item. ``items``, ``above``: the pairs of an item and an
    ancestor, itself included. ``last``: greatest frequent id, or None. ``plain``: each state has
    its own moves, one for each item and output; else states share those of a label pair."""

    def __init__(self, t: Transducer, items: np.ndarray, above: np.ndarray, ids: dict[str, int], last: int | None = None, plain: bool = False) -> None:
        self.t = t
        self.none = int(max(items.max(initial=0), above.max(initial=0))) + 1  # behind a sequence
        known, n = np.zeros(self.none, bool), self.none
        known[items] = True
        own, yields = np.flatnonzero(known).astype(np.int32), (lambda x: np.ones(len(x), bool)) if last is None else (lambda x: x <= last)

        def below(name: str) -> np.ndarray:
            out = np.zeros(n, bool)
            if name in ids:
                out[items[above == ids[name]]] = True
            return out

        def rows(i: tuple, o: tuple | None) -> tuple[np.ndarray, np.ndarray]:
            """(item, output) of a label pair; -1 is no output."""
            if i[0] == "any":
                ok = known if plain else np.ones(n, bool)
            elif i[0] == "below":
                ok = below(i[1])
            else:
                ok = np.arange(n) == ids.get(i[1], -1)
            if o is None:
                w = np.flatnonzero(ok).astype(np.int32)
                return w, np.full(len(w), -1, np.int8)
            if o[0] in ("self", "const"):
                w = own[ok[own]]
                out = w if o[0] == "self" else np.full(len(w), ids.get(o[1], -1), np.int32)
                keep = yields(out) & (out >= 0)
                return w[keep], out[keep]
            keep = ok[items] & yields(above)
            if o[0] == "upto":
                keep &= below(o[1])[above]
            return items[keep], above[keep]

        def indexed(w, *columns):
            starts = np.zeros(n + 2, np.int32)
            np.cumsum(np.bincount(w, minlength=n + 1), out=starts[1:])
            if (w[1:] < w[:-1]).any():
                order = np.argsort(w, kind="stable")
                columns = [x[order] for x in columns]
            return starts, *columns

        labels = list(dict.fromkeys((i, o) for ms in t.moves for i, o, _ in ms))
        of = {x: rows(*x) for x in labels}
        shared = {} if plain else {x: indexed(*of[x]) for x in labels}
        #: by state: (whether it yields, starts by item, outputs, next state or states)
        self.ways: list[list[tuple]] = []
        for q, ms in enumerate(t.moves):
            ms = [m for m in dict.fromkeys(ms) if not (t.anywhere and q == t.start and m[2] == q and m[1] is None)]
            ways = []
            for captured in (False, True):
                some = [(i, o, to) for i, o, to in ms if (o is not None) == captured]
                if plain and some:
                    w, out = (np.concatenate([of[i, o][k] for i, o, _ in some]) for k in (0, 1))
                    to = np.concatenate([np.full(len(of[i, o][0]), to, np.int16) for i, o, to in some])
                    ways.append((captured, *indexed(w, out, to)))
                else:
                    ways += [(captured, *shared[i, o], to) for i, o, to in some]
            self.ways.append(ways)
        self.silent = np.array([any(not x[0] for x in ways) for ways in self.ways])
        self.inner = np.array([any(x[0] for x in ways) for ways in self.ways])
        self.finals = np.array([q in t.finals for q in range(len(t.moves))])
        #: states that only end a pattern
        self.done = self.finals & np.array([t.anywhere and not ms for ms in t.moves], bool)
        self.kinds = {x: len(np.unique(of[x][1])) for x in labels}
        self._alive(labels, np.array([np.bincount(of[x][0], minlength=n + 1) > 0 for x in labels]).reshape(-1, n + 1))

    def _alive(self, labels, open_) -> None:
        """Numbers for the moves that are open to an item, and for the sets of states from which
        acceptance can be reached, by the number behind and the item."""
        code = np.zeros(self.none + 1, np.int64)
        for x in open_:
            code = np.unique(2 * code + x, return_inverse=True)[1]
        _, at, kind = np.unique(code, return_index=True, return_inverse=True)
        self.kind = kind.astype(np.int32)
        kinds = [{x for x, ok in zip(labels, open_[:, k].tolist(), strict=True) if ok} for k in at.tolist()]
        ends = frozenset(self.t.finals) if self.t.anywhere else frozenset()
        sets, todo, self.table = {frozenset(self.t.finals): 0}, [frozenset(self.t.finals)], []
        for now in todo:  # grows
            row = []
            for can in kinds:
                before = ends.union(q for q, ms in enumerate(self.t.moves) if any((i, o) in can and to in now for i, o, to in ms))
                if before not in sets:
                    sets[before] = len(sets)
                    todo.append(before)
                row.append(sets[before])
            self.table.append(row)
        self.table = np.array(self.table)
        self.live = np.array([[q in s for q in range(len(self.t.moves))] for s in sets])

    def load(self, flat: np.ndarray, sizes: np.ndarray) -> None:
        """Sequences one behind the other, each with a place behind its last item."""
        seqs = len(sizes)
        self.seq = np.repeat(np.arange(seqs), sizes + 1)
        self.begin = np.cumsum(sizes + 1) - sizes - 1
        self.end, self.n, self.seqs = self.begin + sizes, len(flat) + seqs, seqs
        self.flat = np.full(self.n, self.none, np.int64)
        self.flat[np.arange(len(flat)) + np.repeat(np.arange(seqs), sizes)] = flat
        self.alive = np.zeros(self.n, np.int64)
        long = np.argsort(-sizes, kind="stable")
        end, now, many = self.end[long], np.zeros(seqs, np.int64), np.searchsorted(-sizes[long], -np.arange(1, sizes.max(initial=0) + 1), "right")
        kind = self.kind[self.flat]
        for d, m in enumerate(many.tolist(), 1):
            at = end[:m] - d
            now = self.table[now[:m], kind[at]]
            self.alive[at] = now

    def first(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(place, state, prefix) of the empty prefix."""
        p = np.arange(self.n) if self.t.anywhere else self.begin
        p = p[(self.flat[p] < self.none) & self.live[self.alive[p], self.t.start]]
        return p, np.full(len(p), self.t.start), np.zeros(len(p), np.int64)

    def moved(self, p, q, pat, captured: bool) -> tuple:
        """(place, state, prefix, output) after one item, along moves that yield or that do not."""
        found, size = [(np.empty(0, np.int64),) * 4], 0
        for s in np.flatnonzero(np.bincount(q, minlength=len(self.ways))).tolist():
            ways = [x[1:] for x in self.ways[s] if x[0] == captured]
            if not ways:
                continue
            rows = np.flatnonzero(q == s)
            place = p[rows]
            w = self.flat[place]
            for starts, outs, to in ways:
                sizes, some = starts[w + 1] - starts[w], None
                one = isinstance(to, int)
                some = np.flatnonzero((sizes > 0) & self.live[self.alive[np.minimum(place + 1, self.n - 1)], to] if one else sizes > 0)
                size += int(sizes[some].sum())
                if size > MOST_SNAPSHOTS and self.seqs > 1:
                    raise TooManySnapshots
                r, k = spread(starts[w[some]], sizes[some])
                r = some[r]
                if one:
                    found.append((place[r] + 1, np.full(len(r), to), pat[rows[r]], outs[k]))
                else:
                    ok = self.live[self.alive[place[r] + 1], to[k]]
                    r, k = r[ok], k[ok]
                    found.append((place[r] + 1, to[k], pat[rows[r]], outs[k]))
        return tuple(np.concatenate(x).astype(np.int64, copy=False) for x in zip(*found, strict=True))

    def thin(self, p, q, pat) -> tuple:
        """Snapshots once each, by prefix and place."""
        states, code = len(self.ways), (pat * self.n + p)
        code = np.sort(code * len(self.ways) + q)
        if len(code):
            code = code[np.concatenate([[True], code[1:] != code[:-1]])]
        way, q = np.divmod(code, states)
        pat, p = np.divmod(way, self.n)
        return p, q, pat

    def closed(self, p, q, pat) -> tuple:
        """With all snapshots that moves without output lead to."""
        if not self.silent[q].any():
            return p, q, pat
        coded = lambda p, q, pat: (pat * self.n + p) * len(self.ways) + q
        all_, new, seen = [(p, q, pat)], (p, q, pat), coded(p, q, pat)
        while len(new[0]):
            new = self.thin(*self.moved(*new, False)[:3])
            code = coded(*new)
            at = np.minimum(np.searchsorted(seen, code), len(seen) - 1)
            fresh = seen[at] != code
            new = tuple(x[fresh] for x in new)
            if len(new[0]):
                all_.append(new)
                seen = np.sort(np.concatenate([seen, code[fresh]]))
        return self.thin(*map(np.concatenate, zip(*all_, strict=True))) if len(all_) > 1 else all_[0]

    def by_sequence(self, p, pat, many: int) -> tuple[np.ndarray, np.ndarray]:
        """(prefix, sequence) once each, of snapshots by prefix and place."""
        seq = self.seq[p]
        ok = np.ones(len(p), bool)
        ok[1:] = (pat[1:] != pat[:-1]) | (seq[1:] != seq[:-1])
        return pat[ok], seq[ok]

    def levels(self, known: list, width: int, ahead: int | None = None):
        """For each of ``ahead`` lengths behind those of ``known`` (None: for all): numbers of the
        prefixes one shorter, the outputs behind them, how many sequences reach each, and of which
        sequences each is a pattern, as (prefix, sequence) pairs.

        ``known``: for each length a function from keys (prefix number * width + output) to the
        numbers of the prefixes that live on, -1 for others."""
        rows, done = self.closed(*self.first()), 0
        while ahead is None or done < len(known) + ahead:
            p, q, pat, out = self.moved(*rows, True)
            key = pat * width + out
            if done < len(known):
                pat = known[done](key)
                ok = pat >= 0
                rows = self.closed(*self.thin(p[ok], q[ok], pat[ok]))
            else:
                if not len(key):
                    return
                if (int(key.max()) + 1) * self.n * len(self.ways) < 1 << 62:
                    p, q, key = self.thin(p, q, key)
                    new = np.concatenate([[True], key[1:] != key[:-1]])
                    names, pat = key[new], np.cumsum(new) - 1
                else:
                    names, pat = np.unique(key, return_inverse=True)
                    p, q, pat = self.thin(p, q, pat)
                reached = np.bincount(self.by_sequence(p, pat, len(names))[0], minlength=len(names))
                p, q, pat = self.closed(p, q, pat)
                ok = self.finals[q] & (self.t.anywhere | (self.flat[p] == self.none))
                yield *np.divmod(names, width), reached, self.by_sequence(p[ok], pat[ok], len(names))
                rows = p, q, pat
            ok = self.inner[rows[1]]
            rows = tuple(x[ok] for x in rows)
            done += 1

    def patterns(self, least: int | None = 1, known: list | None = None, width: int = 0):
        """All outputs of each sequence. For each length: numbers of the prefixes one shorter, the
        outputs behind them, of how many sequences each is a pattern, and how many patterns of this
        length each sequence has.

        What follows a place and state is found once for all prefixes that lead there. Where nothing
        can follow a length, its items are sets of bits by prefix and sequence, of which only those
        in ``least`` sequences at least are listed (None: none, they are but counted by sequence).
        ``known``: for each length a function as for ``levels`` and how many prefixes it numbers;
        only these are made and counted, and they are not listed."""
        (p, q, pat), states, length, many, parent, out = self.first(), len(self.ways), 0, 1, None, None
        while True:
            number, code = np.zeros(self.n * states, np.int32), p * states + q
            number[code] = 1
            at = np.flatnonzero(number)
            number[at] = np.arange(len(at))
            of = number[code]
            here = self.closed(*np.divmod(at, states), np.arange(len(at)))
            if length:
                ok = np.zeros(len(at), bool)
                ok[here[2][self.finals[here[1]] & (self.t.anywhere | (self.flat[here[0]] == self.none))]] = True
                ok = ok[of]
                had, seq = self.by_sequence(p[ok], pat[ok], many)
                yield parent, out, np.bincount(had, minlength=many), np.bincount(seq, minlength=self.seqs)
            if known is not None and length == len(known):
                return
            p2, q2, row, o = self.moved(*here, True)
            if not len(o):
                return
            kinds, o = np.unique(o, return_inverse=True)
            if known is None and len(kinds) <= MOST_BITS and self.done[q2].all():
                yield self._last(p, pat, of, len(at), row, o, kinds, least)
                return
            p2, q2, way = self.thin(p2, q2, row * len(kinds) + o)
            row, o = np.divmod(way, len(kinds))
            starts = np.searchsorted(row, np.arange(len(at) + 1))
            sizes = np.diff(starts)[of]
            if int(sizes.sum()) > MOST_SNAPSHOTS and self.seqs > 1:
                raise TooManySnapshots
            r, k = spread(starts[of], sizes)
            if known is None:
                p, q, pat, names = self._joined(pat[r], k, p2, q2, o, len(kinds))
                parent, out, many = names // len(kinds), kinds[names % len(kinds)], len(names)
            else:
                find, many = known[length]
                pat = find(pat[r] * width + kinds[o[k]])
                ok = pat >= 0
                p, q, pat = self.thin(p2[k[ok]], q2[k[ok]], pat[ok])
            length += 1

    def _joined(self, pat, k, p, q, o, kinds: int) -> tuple:
        """Snapshots (place, state, number of the prefix) once each, and the prefixes, of rows ``k``
        of moves behind prefixes ``pat``."""
        low, mid, top = (int(x - 1).bit_length() for x in (len(self.ways), self.n, kinds * (int(pat.max(initial=0)) + 1)))
        if low + mid + top > 62:
            names, pat = np.unique(pat * kinds + o[k], return_inverse=True)
            return *self.thin(p[k], q[k], pat), names
        code = ((o << mid | p) << low) | q
        code = np.sort(code[k] + pat * (kinds << (low + mid)))
        code = code[np.concatenate([[True], code[1:] != code[:-1]])]
        key = code >> (low + mid)
        new = np.concatenate([[True], key[1:] != key[:-1]])
        return (code >> low) & ((1 << mid) - 1), code & ((1 << low) - 1), np.cumsum(new) - 1, key[new]

    def _last(self, p, pat, of, many: int, row, o, kinds, least: int | None) -> tuple:
        """The last length, as ``patterns`` lists it: ``o`` are the items that may follow ``row``."""
        seq = self.seq[p]
        group = np.flatnonzero(np.concatenate([[True], (pat[1:] != pat[:-1]) | (seq[1:] != seq[:-1])]))
        seq, pat, words = seq[group], pat[group], -(-len(kinds) // 64)
        sets = np.zeros(words * many, np.uint64)
        np.bitwise_or.at(sets, (o >> 6) * many + row, np.uint64(1) << (o & 63).astype(np.uint64))
        sets = [np.bitwise_or.reduceat(x[of], group) for x in sets.reshape(words, many)]
        sizes = sum(np.bitwise_count(x).astype(np.int64) for x in sets)
        total = np.bincount(seq, sizes, self.seqs).astype(np.int64)
        parts = [(np.empty(0, np.int64),) * 3]
        if least is not None:
            # a pattern is in no more sequences than its prefix
            rows = np.flatnonzero((np.bincount(pat) >= least)[pat])
            first = np.flatnonzero(np.concatenate([[True], pat[rows[1:]] != pat[rows[:-1]]])) if len(rows) else rows
            ends, at = np.append(first, len(rows)), 0
            while at < len(first):
                to = max(at + 1, int(np.searchsorted(ends, ends[at] + BIT_ROWS, "right")) - 1)
                some = rows[ends[at] : ends[to]]
                for w, x in enumerate(sets):
                    bits = np.unpackbits(x[some].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
                    n = np.add.reduceat(bits, ends[at:to] - ends[at], axis=0, dtype=np.int32)
                    a, b = np.nonzero(n >= max(1, least))
                    parts.append((pat[rows[ends[at + a]]], kinds[64 * w + b], n[a, b].astype(np.int64)))
                at = to
        return *map(np.concatenate, zip(*parts, strict=True)), total


def in_parts(steps: Steps, flat: np.ndarray, sizes: np.ndarray, count):
    """``count`` after loading the sequences: all at once, or in halves where they are too many."""
    try:
        steps.load(flat, sizes)
        return [count(steps)]
    except TooManySnapshots:
        half = len(sizes) // 2
        cut = int(sizes[:half].sum())
        return in_parts(steps, flat[:cut], sizes[:half], count) + in_parts(steps, flat[cut:], sizes[half:], count)


def give_back() -> None:
    """To the system, the memory that is free: allocators keep what was used before."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def trimmed(run):
    """``run``, a function over batches, before and after which its worker gives back memory."""

    def wrapped(batches):
        give_back()
        yield from run(batches)
        give_back()

    return wrapped
