"""Pattern expressions: syntax tree, parser, and builders of well-known constraints.

Syntax: item ``w`` (it or anything below), ``w=`` (it alone), ``w^`` (captured: the item or
any of its generalisations up to w), ``w^=`` (captured: w whatever matched), ``.`` and ``.^``;
capture ``( )``, grouping ``[ ]``, postfix ``* + ? {n} {n,} {n,m}``, ``|``; items with blanks
in single quotes. Only captured parts yield output, the rest is context.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

MAX_LEAVES = 10_000


class ExpressionError(ValueError):
    """The text is no expression; the message has the column."""


@dataclass(frozen=True)
class Item:
    name: str | None  # None: any item
    exact: bool = False
    up: bool = False  # generalise
    captured: bool = False


@dataclass(frozen=True)
class Concat:
    parts: tuple


@dataclass(frozen=True)
class Union:
    parts: tuple


@dataclass(frozen=True)
class Repeat:
    part: object
    low: int
    high: int | None


@dataclass(frozen=True)
class Capture:
    part: object


_TOKEN = re.compile(r"\s*(?:(?P<name>'[^']*'|\.|[\w~#-]+)(?P<up>\^?)(?P<exact>=?)|(?P<rep>\{\s*\d+\s*(?:,\s*\d*\s*)?\}|[*+?])|(?P<sign>[()\[\]|]))")


def _tokens(text: str):
    at = 0
    while text[at:].strip():
        m = _TOKEN.match(text, at)
        if not m:
            raise ExpressionError(f"column {at + 1}: unexpected {text[at:].strip()[0]!r}")
        yield m, m.start() + len(m[0]) - len(m[0].lstrip()) + 1
        at = m.end()


class _Parser:
    def __init__(self, text: str) -> None:
        self.tokens, self.at, self.end = list(_tokens(text)), 0, len(text) + 1

    def sign(self) -> str | None:
        return self.tokens[self.at][0]["sign"] if self.at < len(self.tokens) else ""

    def fail(self, why: str):
        column = self.tokens[self.at][1] if self.at < len(self.tokens) else self.end
        raise ExpressionError(f"column {column}: {why}")

    def union(self, inside: bool):
        parts = [self.branch(inside)]
        while self.sign() == "|":
            self.at += 1
            parts.append(self.branch(inside))
        return parts[0] if len(parts) == 1 else Union(tuple(parts))

    def branch(self, inside: bool):
        parts = []
        while self.at < len(self.tokens) and self.sign() not in (")", "]", "|"):
            parts.append(self.piece(inside))
        return parts[0] if len(parts) == 1 else Concat(tuple(parts))

    def piece(self, inside: bool):
        m, _ = self.tokens[self.at]
        if m["rep"]:
            self.fail("nothing to repeat")
        if m["sign"]:
            close = {"(": ")", "[": "]"}[m["sign"]]
            self.at += 1
            inner = self.union(inside or m["sign"] == "(")
            if self.sign() != close:
                self.fail(f"{close!r} expected")
            out = Capture(inner) if m["sign"] == "(" else inner
        else:
            name = None if m["name"] == "." else m["name"].strip("'")
            if m["up"] and not inside:
                self.fail("^ outside a capture")
            if name is None and m["exact"]:
                self.fail("= needs an item")
            out = Item(name, bool(m["exact"]), bool(m["up"]))
        self.at += 1
        while self.at < len(self.tokens) and (rep := self.tokens[self.at][0]["rep"]):
            low, high = {"*": (0, None), "+": (1, None), "?": (0, 1)}.get(rep) or self.bounds(rep)
            out = Repeat(out, low, high)
            self.at += 1
        return out

    def bounds(self, rep: str) -> tuple[int, int | None]:
        low, comma, high = rep[1:-1].replace(" ", "").partition(",")
        top = int(high) if high else None if comma else int(low)
        if top is not None and top < int(low):
            self.fail("upper bound below lower bound")
        return int(low), top


def parse(text: str):
    p = _Parser(text)
    out = p.union(False)
    if p.at < len(p.tokens):
        p.fail("unexpected closing bracket")
    return out


def desugar(e, captured: bool = False):
    """Captures pushed down to the items, repetitions as copies with ``*`` and ``?`` only."""
    if isinstance(e, str):
        e = parse(e)
    if isinstance(e, Item):
        return Item(e.name, e.exact, e.up, captured)
    if isinstance(e, Capture):
        return desugar(e.part, True)
    if isinstance(e, (Concat, Union)):
        return type(e)(tuple(desugar(p, captured) for p in e.parts))
    part = desugar(e.part, captured)
    if (e.low, e.high) in ((0, None), (0, 1)):
        return Repeat(part, e.low, e.high)
    if max(e.low, e.high or 0) * leaves(part) > MAX_LEAVES:
        raise ExpressionError("too many copies")
    if e.high is None:
        return Concat((part,) * e.low + (Repeat(part, 0, None),))
    tail = None
    for _ in range(e.high - e.low):
        tail = Repeat(part if tail is None else Concat((part, tail)), 0, 1)
    return Concat((part,) * e.low + ((tail,) if tail else ()))


def leaves(e) -> int:
    if isinstance(e, Item):
        return 1
    return sum(map(leaves, e.parts)) if isinstance(e, (Concat, Union)) else leaves(e.part)


def items_named(e) -> set[str]:
    if isinstance(e, str):
        e = parse(e)
    if isinstance(e, Item):
        return {e.name} - {None}
    return set().union(*map(items_named, e.parts)) if isinstance(e, (Concat, Union)) else items_named(e.part)


def required_items(e) -> set[str]:
    """Items of which every matching sequence holds one at or below."""
    if isinstance(e, str):
        e = parse(e)
    if isinstance(e, Item):
        return {e.name} - {None}
    if isinstance(e, Concat):
        return set().union(*map(required_items, e.parts))
    if isinstance(e, Union):
        return set.intersection(*map(required_items, e.parts))
    if isinstance(e, Repeat):
        return required_items(e.part) if e.low else set()
    return required_items(e.part)


# builders of known constraints; all are meant for matches anywhere in a sequence


def all_subsequences() -> str:
    return "[.*(.)]+"


def bounded_length(low: int, high: int) -> str:
    return f"[.*(.)]{{{low},{high}}}"


def ngrams(low: int, high: int, up: bool = False) -> str:
    return f"(.{'^' if up else ''}){{{low},{high}}}"


def generalized_ngrams(low: int, high: int) -> str:
    return ngrams(low, high, True)


def bounded_gap(gap: int, low: int = 2, high: int | None = None, item: str = ".", up: bool = False) -> str:
    one = f"({item}{'^' if up else ''})"
    return f"{one}[.{{0,{gap}}}{one}]{{{low - 1},{'' if high is None else high - 1}}}"


def skipgrams(gap: int, high: int, up: bool = False, low: int = 2) -> str:
    return bounded_gap(gap, low, high, up=up)


def serial_episode(length: int, total_gap: int) -> str:
    """``length`` items with ``total_gap`` skipped ones at most, over all gaps together."""

    def rest(k: int, room: int) -> str:
        if k == 0:
            return ""
        ways = [". " * g + "(.)" + rest(k - 1, room - g) for g in range(room + 1)]
        return f"[{' | '.join(ways)}]"

    return "(.)" + rest(length - 1, total_gap)


def bounded_span(width: int, low: int, high: int) -> str:
    """First to last item at most ``width`` positions."""
    return " | ".join(f"[{serial_episode(k, width - k)}]" for k in range(low, min(high, width) + 1))


def regex_subsequences(slots: list[str]) -> str:
    """Each slot captured, gaps free; a slot is an expression such as ``[s|t]``."""
    return " .* ".join(f"({s})" for s in slots)


def regex_contiguous(e: str) -> str:
    return f"({e})"


def between(left: str, captured: str, right: str) -> str:
    return f"{left} ({captured}) {right}"
