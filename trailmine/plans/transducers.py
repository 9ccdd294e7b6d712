"""Compact transducers: position automata over labelled transitions, and their plain form."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from .expressions import Concat, Item, Repeat, Union, desugar

#: A label pair is (input, output): input ("any",), ("below", w) or ("is", w); output None,
#: ("self",), ("const", w), ("upto", w) or ("up",).


def labels(leaf: Item) -> tuple:
    if leaf.name is None:
        return ("any",), (("up",) if leaf.up else ("self",)) if leaf.captured else None
    w = leaf.name
    if leaf.up and leaf.exact:
        return ("below", w), ("const", w)
    if leaf.exact:
        return ("is", w), ("const", w) if leaf.captured else None
    return ("below", w), (("upto", w) if leaf.up else ("self",)) if leaf.captured else None


@dataclass
class Transducer:
    """``moves[q]``: list of (input, output, next state)."""

    moves: list[list[tuple]]
    start: int
    finals: frozenset[int]
    anywhere: bool = False
    names: set[str] = field(default_factory=set)

    @property
    def size(self) -> tuple[int, int]:
        return len(self.moves), sum(map(len, self.moves))


def positions(e) -> Transducer:
    """One state per leaf besides the start; no empty moves."""
    leafs: list[Item] = []
    follow: list[set[int]] = []

    def walk(x) -> tuple[bool, set[int], set[int]]:  # nullable, first, last
        if isinstance(x, Item):
            leafs.append(x)
            follow.append(set())
            return False, {len(leafs)}, {len(leafs)}
        if isinstance(x, Union):
            parts = [walk(p) for p in x.parts]
            return any(p[0] for p in parts), set().union(*(p[1] for p in parts)), set().union(*(p[2] for p in parts))
        if isinstance(x, Concat):
            null, first, last = True, set(), set()
            for p in x.parts:
                n, f, la = walk(p)
                for q in last:
                    follow[q - 1] |= f
                first = first | f if null else first
                last = last | la if n else la
                null = null and n
            return null, first, last
        n, f, la = walk(x.part)
        if x.high is None:
            for q in la:
                follow[q - 1] |= f
        return True, f, la

    null, first, last = walk(e)
    into = [(*labels(x), k + 1) for k, x in enumerate(leafs)]
    moves = [[into[q - 1] for q in sorted(first)]] + [[into[q - 1] for q in sorted(f)] for f in follow]
    return Transducer(moves, 0, frozenset(last | ({0} if null else set())), names={x.name for x in leafs if x.name})


def optimize(t: Transducer, cap: int = 4) -> Transducer:
    """Trim, determinise over label pairs unless that needs over ``cap`` times the states,
    and merge equivalent states; the outputs depend on the label-pair language only."""
    alive, grown = set(t.finals), True
    while grown:
        more = {q for q, ms in enumerate(t.moves) if any(m[2] in alive for m in ms)} - alive
        alive, grown = alive | more, bool(more)
    subsets, todo, moves, finals = {frozenset([t.start]): 0}, [frozenset([t.start])], [], set()
    while todo:
        s = todo.pop(0)
        if s & t.finals:
            finals.add(subsets[s])
        by: dict[tuple, set[int]] = {}
        for q in s:
            for i, o, to in t.moves[q]:
                if to in alive:
                    by.setdefault((i, o), set()).add(to)
        own = []
        for (i, o), to in sorted(by.items(), key=repr):
            to = frozenset(to)
            if to not in subsets:
                subsets[to] = len(subsets)
                todo.append(to)
            own.append((i, o, subsets[to]))
        moves.append(own)
        if len(subsets) > cap * len(t.moves) + 8:
            moves, finals = [[m for m in ms if m[2] in alive] for ms in t.moves], set(t.finals)
            break
    start = 0 if len(moves) == len(subsets) and not todo else t.start
    block = [int(q in finals) for q in range(len(moves))]
    while True:  # states with the same moves into blocks are one
        keys = [(block[q], frozenset((i, o, block[to]) for i, o, to in ms)) for q, ms in enumerate(moves)]
        order = {k: n for n, k in enumerate(dict.fromkeys(keys))}
        new = [order[k] for k in keys]
        if len(order) == len(set(block)):
            break
        block = new
    merged: list[list[tuple]] = [[] for _ in order]
    for q, ms in enumerate(moves):
        merged[new[q]] = sorted({(i, o, new[to]) for i, o, to in ms}, key=repr)
    return Transducer(merged, new[start], frozenset(new[q] for q in finals), t.anywhere, t.names)


def compile_expression(e, match: str = "full", optimized: bool = True) -> Transducer:
    """``match``: "full" consumes the whole sequence, "anywhere" any stretch of it."""
    if match not in ("full", "anywhere"):
        raise ValueError(match)
    t = positions(desugar(e))
    if optimized:
        t = optimize(t)
    if match == "anywhere":
        if any(to == t.start for ms in t.moves for _, _, to in ms):
            t.moves.append(list(t.moves[t.start]))
            if t.start in t.finals:
                t.finals |= {len(t.moves) - 1}
            t.start = len(t.moves) - 1
        t.moves[t.start] = t.moves[t.start] + [(("any",), None, t.start)]
        t.anywhere = True
    return t


def plain_moves(t: Transducer, matches, outputs, vocabulary) -> list[list[tuple]]:
    """Every transition per concrete item and concrete output: the uncompressed form."""
    out = []
    for ms in t.moves:
        own = []
        for i, o, to in ms:
            for w in vocabulary:
                if matches(i, w):
                    own += [(w, x, to) for x in (outputs(o, w) if o else (None,))]
        out.append(own)
    return out


class PlainMoves:
    """The plain form in arrays, where each state's moves of an item are found by its id."""

    def __init__(self, t: Transducer, matches, outputs, vocabulary) -> None:
        of, self.states = {}, []
        vocabulary = list(vocabulary)
        for label in dict.fromkeys((i, o) for ms in t.moves for i, o, _ in ms):
            i, o = label
            own = [(w, -1 if x is None else x) for w in vocabulary if matches(i, w) for x in (outputs(o, w) if o else (None,))]
            of[label] = np.array(own, np.int32).reshape(-1, 2)
        for ms in t.moves:
            rows = np.concatenate([np.empty((0, 2), np.int32), *(of[i, o] for i, o, _ in ms)])
            to = np.concatenate([np.empty(0, np.int32), *(np.full(len(of[i, o]), to, np.int32) for i, o, to in ms)])
            order = np.argsort(rows[:, 0], kind="stable")
            starts = np.concatenate([[0], np.cumsum(np.bincount(rows[:, 0]))]).astype(np.int32)
            self.states.append((starts, rows[order, 1], to[order]))

    def of(self, q: int, w: int) -> list[tuple]:
        """(output or None, next state) of a state on an item."""
        starts, outs, to = self.states[q]
        if not 0 <= w < len(starts) - 1:
            return []
        a, b = starts[w], starts[w + 1]
        return [(None if o < 0 else o, x) for o, x in zip(outs[a:b].tolist(), to[a:b].tolist(), strict=True)]


def to_dot(t: Transducer) -> str:
    show = lambda x: "-" if x is None else " ".join(x)
    lines = [f'  {q} [shape={"doublecircle" if q in t.finals else "circle"}];' for q in range(len(t.moves))]
    lines += [f'  {q} -> {to} [label="{show(i)} : {show(o)}"];' for q, ms in enumerate(t.moves) for i, o, to in ms]
    return "digraph {\n" + "\n".join([f"  begin -> {t.start};", *lines]) + "\n}"
