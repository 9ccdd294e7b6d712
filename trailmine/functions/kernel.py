"""Simulation of a transducer over one encoded sequence; runs inside Arrow tasks."""

from __future__ import annotations

from bisect import bisect_left

import numpy as np

from ..plans.transducers import PlainMoves, Transducer


#: Entries that a kernel remembers of each kind; items may be millions.
CACHED = 50_000


class TooManyOutputs(RuntimeError):
    """A sequence has more outputs than the guard admits; nothing is truncated."""


class Ancestors:
    """{item: its ancestors, itself first} of (item, ancestor) pairs, in two arrays of integers."""

    def __init__(self, items: np.ndarray, above: np.ndarray) -> None:
        order = np.lexsort((above, above != items, items))
        self.above = above[order].astype(np.int32)
        self.starts = np.concatenate([[0], np.cumsum(np.bincount(items))]).astype(np.int32)
        #: moves in arrays that a worker made of them
        self.steps = None

    def get(self, w: int, default: tuple = ()) -> tuple[int, ...]:
        if not 0 <= w < len(self.starts) - 1:
            return default
        return tuple(self.above[self.starts[w] : self.starts[w + 1]].tolist()) or default

    def __iter__(self):
        return iter(np.flatnonzero(np.diff(self.starts)).tolist())


def alike(items: np.ndarray, above: np.ndarray, matters: np.ndarray) -> np.ndarray:
    """For each id the least id that has the same ancestors among those that matter (itself too,
    if it matters); 0 of ids that have none."""
    n = len(matters)
    keep = matters[above]
    items, above = items[keep], above[keep]
    order = np.lexsort((above, items))
    above, sizes = above[order].astype(np.int64), np.bincount(items, minlength=n)
    starts, label, used = np.cumsum(sizes) - sizes, matters.astype(np.int64), 2
    for k in range(int(sizes.max(initial=0))):
        rows = np.flatnonzero(sizes > k)
        kinds, of = np.unique(label[rows] * n + above[starts[rows] + k], return_inverse=True)
        label[rows] = used + of
        used += len(kinds)
    _, first, of = np.unique(label, return_index=True, return_inverse=True)
    return np.where(sizes > 0, first[of], 0).astype(np.int32)


def rows_of(column, some: int = 256):
    """The lists of an Arrow column as Python lists, few at a time."""
    for at in range(0, len(column), some):
        yield from column.slice(at, some).to_pylist()


class Kernel:
    """``ancestors``: {item: its ancestors, itself first}; items not in it match wildcards and
    yield nothing. ``last``: greatest frequent id, or None to yield every item. ``alike``: items
    as which others act, by id."""

    def __init__(self, t: Transducer, ancestors: dict[int, tuple[int, ...]] | Ancestors, ids: dict[str, int], last: int | None = None, plain: bool = False, alike: np.ndarray | None = None) -> None:
        self.t, self.up, self.ids, self.last, self.alike = t, ancestors, ids, last, alike
        self.cache: dict[tuple[int, int], list[tuple]] = {}
        self.back: dict[tuple[frozenset, int], frozenset] = {}
        self.labels = list(dict.fromkeys((i, o) for ms in t.moves for i, o, _ in ms))
        self.kinds: dict[tuple, int] = {}
        self.kind_of: dict[int, int] = {}
        number = {x: k for k, x in enumerate(self.labels)}
        self.ways = [[(number[i, o], to) for i, o, to in ms] for ms in t.moves]
        self.plain = PlainMoves(t, self.matches, self.outputs, ancestors) if plain else None
        waits = {q for q, ms in enumerate(t.moves) if any(i[0] == "any" and not o and to == q for i, o, to in ms)} if t.anywhere and not plain else set()
        done = {q for q in t.finals if not t.moves[q]}
        #: States that may wait anywhere and only lead to such or to the end: of an item after
        #: them the first place does for all later ones.
        self.leaps = {q for q in waits if all(to in waits or to in done for _, _, to in t.moves[q])}

    def matches(self, label: tuple, w: int) -> bool:
        if label[0] == "any":
            return True
        named = self.ids.get(label[1])
        return named is not None and (w == named if label[0] == "is" else named in self.up.get(w, ()))

    def outputs(self, label: tuple, w: int) -> tuple[int, ...]:
        up = self.up.get(w, ())
        if label[0] == "self":
            out = up[:1]
        elif label[0] == "const":
            out = (self.ids[label[1]],) if label[1] in self.ids else ()
        elif label[0] == "up":
            out = up
        else:
            named = self.ids.get(label[1])
            out = tuple(a for a in up if named in self.up.get(a, ()))
        return out if self.last is None else tuple(a for a in out if a <= self.last)

    def step(self, q: int, w: int) -> list[tuple]:
        """(output or None, next state) of state ``q`` on item ``w``."""
        if self.plain is not None:
            return self.plain.of(q, w)
        found = self.cache.get((q, w))
        if found is None:
            found = []
            for i, o, to in self.t.moves[q]:
                if self.matches(i, w):
                    found += [(x, to) for x in self.outputs(o, w)] if o else [(None, to)]
            if len(self.cache) >= CACHED:
                self.cache.clear()
            found = self.cache[q, w] = list(dict.fromkeys(found))
        return found

    def kind(self, w: int) -> int:
        """A number for the moves that are open to an item, whatever they yield."""
        k = self.kind_of.get(w)
        if k is None:
            if len(self.kind_of) >= CACHED:
                self.kind_of.clear()
            key = tuple(self.matches(i, w) and (not o or bool(self.outputs(o, w))) for i, o in self.labels)
            k = self.kind_of[w] = self.kinds.setdefault(key, len(self.kinds))
        return k

    def known(self, items) -> list[int]:
        """A sequence by the items as which its items act."""
        return list(items) if self.alike is None else self.alike[np.asarray(items, np.int64)].tolist()

    def alive(self, items) -> list[frozenset[int]]:
        """States from which acceptance can be reached, for each position."""
        n = len(items)
        ends = frozenset(self.t.finals) if self.t.anywhere else frozenset()
        out = [frozenset(self.t.finals)] * (n + 1)
        for k in range(n - 1, -1, -1):
            key = (out[k + 1], items[k] if self.plain else self.kind(items[k]))
            now = self.back.get(key)
            if now is None:
                if self.plain:
                    now = ends.union(q for q in range(len(self.t.moves)) if any(to in key[0] for _, to in self.step(q, items[k])))
                else:
                    open_ = next(x for x, n in self.kinds.items() if n == key[1])
                    now = ends.union(q for q, ways in enumerate(self.ways) if any(open_[i] and to in key[0] for i, to in ways))
                if len(self.back) >= CACHED:
                    self.back.clear()
                self.back[key] = now
            out[k] = now
        return out

    def places(self, items) -> dict[int, list[int]]:
        """Positions of each item, where the transducer has states that leap to them."""
        out: dict[int, list[int]] = {}
        if self.leaps:
            for k, w in enumerate(items):
                out.setdefault(w, []).append(k)
        return out

    def leap(self, q: int, at: int, places) -> list[tuple]:
        """(output or None, next state, next position) from ``q``, at first places from ``at``."""
        out = []
        for w, ks in places.items():
            k = bisect_left(ks, at)
            if k < len(ks):
                out += [(o, to, ks[k] + 1) for o, to in self.step(q, w) if o is not None or to != q]
        return out

    def accepts(self, items) -> bool:
        now = {self.t.start}
        for w in items:
            if self.t.anywhere and now & self.t.finals:
                return True
            now = {to for q in now for _, to in self.step(q, w)}
        return bool(now & self.t.finals)

    def generate(self, items, limit: int | None = None, wanted: set | None = None) -> set[tuple[int, ...]]:
        """All outputs, each once, without the empty one; with ``wanted``, a set of prefixes,
        only outputs that stay within it."""
        alive, n, found = self.alive(items), len(items), set()
        places, first = self.places(items), {}
        stack, seen = [(0, self.t.start, ())], set()
        while stack:
            state = stack.pop()
            if state in seen:
                continue
            seen.add(state)
            at, q, out = state
            if q not in alive[at]:
                continue
            if out and q in self.t.finals and (self.t.anywhere or at == n):
                found.add(out)
                if limit is not None and len(found) > limit:
                    raise TooManyOutputs(f"over {limit} outputs of one sequence")
            if q in self.leaps:
                if first.get((q, out), n + 1) <= at:
                    continue
                first[q, out] = at
                steps = self.leap(q, at, places)
            else:
                steps = [(o, to, at + 1) for o, to in self.step(q, items[at])] if at < n else ()
            for o, to, k in steps:
                if to in alive[k]:
                    nxt = out if o is None else (*out, o)
                    if wanted is None or o is None or nxt in wanted:
                        stack.append((k, to, nxt))
        return found

    def resume(self, items, snapshots, alive=None, places=None) -> tuple[bool, dict[int, set[tuple[int, int]]]]:
        """From snapshots (position, state) of a prefix: whether the prefix itself is accepted,
        and the snapshots of each next output item."""
        alive, places = alive or self.alive(items), places or self.places(items)
        n, accepted, children = len(items), False, {}
        stack, seen = list(snapshots), set(snapshots)
        while stack:
            at, q = stack.pop()
            if q in self.t.finals and (self.t.anywhere or at == n):
                accepted = True
            if at == n:
                continue
            for o, to, k in self.leap(q, at, places) if q in self.leaps else [(o, to, at + 1) for o, to in self.step(q, items[at])]:
                if to not in alive[k]:
                    continue
                if o is not None:
                    children.setdefault(o, set()).add((k, to))
                elif (k, to) not in seen:
                    seen.add((k, to))
                    stack.append((k, to))
        return accepted, children
