"""Expressions of item tests with bounded or free gaps as joins on positions, without an automaton
at run time and all in the JVM; n-grams as slices of arrays."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.transducers import Transducer
from ..sources.dictionary import written
from .mining import MAX_LEVELS, Database


@dataclass(frozen=True)
class Slot:
    """A position: its test (``below``/``exactly`` an item, or any), and what it yields."""

    name: str | None = None
    exact: bool = False
    captured: bool = True
    up: bool = False
    const: bool = False


@dataclass(frozen=True)
class Graph:
    """``edges``: (node, slot, least and most items skipped before it (None: any number), next
    node); node 0 is the start, before the first item. A walk that reaches one of ``ends`` is a
    match."""

    edges: tuple = field(default=())
    ends: frozenset = field(default=frozenset())

    @property
    def slots(self) -> list[Slot]:
        return list(dict.fromkeys(e[1] for e in self.edges))

    @property
    def inner(self) -> set[int]:
        return {e[0] for e in self.edges}

    def captures_by_level(self) -> bool:
        """Whether all ways to a pattern agree on its prefix after any number of steps, so that
        infrequent prefixes may be dropped: unfinished walks of as many steps have captured as many
        items, and walks that finish later have captured more."""
        level, longest = {(0, 0)}, -1
        for _ in range(2 * len(self.edges) + 4):
            moved = {(to, n + s.captured) for q, n in level for at, s, _, _, to in self.edges if at == q}
            done = {n for q, n in moved if q in self.ends}
            level = {(q, n) for q, n in moved if q in self.inner}
            if len({n for _, n in level}) > 1 or done and min(done) <= longest:
                return False
            longest = max(done, default=longest)
        return True


def from_shapes(shapes: list[tuple[list[Slot], list[int | None]]]) -> Graph:
    """Shapes (slots, most items skipped between neighbours) that share their beginnings."""
    known, edges, ends = {}, [], set()
    for slots, gaps in shapes:
        at = 0
        for k, s in enumerate(slots):
            key = (at, s, 0, gaps[k - 1] if k else None)
            if key not in known:
                known[key] = len(known) + 1
                edges.append((*key, known[key]))
            at = known[key]
        ends.add(at)
    return Graph(tuple(edges), frozenset(ends))


def _slot(label: tuple, output: tuple | None) -> Slot:
    return Slot(label[1] if len(label) > 1 else None, label[0] == "is", output is not None, output is not None and output[0] in ("up", "upto"), output is not None and output[0] == "const" and label[0] == "below")


def from_transducer(t: Transducer) -> Graph | None:
    """The graph of a transducer that matches anywhere: its moves over uncaptured wildcards become
    gaps. None where the joins cannot say the same: full matches, wildcards behind the last test,
    gaps with holes in them."""
    skip = [{to for i, o, to in ms if i == ("any",) and o is None} for ms in t.moves]
    if not t.anywhere or t.start not in skip[t.start]:
        return None
    far, edges, ends, number, todo = 2 * len(t.moves) + 2, [], set(), {t.start: 0}, [t.start]
    while todo:
        q = todo.pop()
        at, reached = {q}, {}
        for d in range(far + 1):
            for r in at:
                reached.setdefault(r, []).append(d)
            at = {to for r in at for to in skip[r]}
        if any(r in t.finals and r != q for r in reached) and q not in t.finals:
            return None
        if q in t.finals:
            ends.add(number[q])
        for r, found in reached.items():
            low, high = found[0], found[-1]
            if len(found) != high - low + 1:
                return None
            for i, o, to in t.moves[r]:
                if i == ("any",) and o is None:
                    continue
                if to not in number:
                    number[to] = len(number)
                    todo.append(to)
                edges.append((number[q], _slot(i, o), low, None if high >= far else high, number[to]))
    if 0 in ends:
        return None
    return Graph(tuple(_merged(edges)), frozenset(ends))


def _merged(edges: list) -> list:
    """Neighbouring and overlapping gaps between the same nodes as one."""
    out, by = [], {}
    for at, s, low, high, to in edges:
        by.setdefault((at, s, to), []).append((low, high))
    for (at, s, to), gaps in by.items():
        gaps.sort(key=lambda g: g[0])
        now = gaps[0]
        for low, high in gaps[1:]:
            if now[1] is None or low <= now[1] + 1:
                now = (now[0], None if now[1] is None or high is None else max(now[1], high))
            else:
                out.append((at, s, *now, to))
                now = (low, high)
        out.append((at, s, *now, to))
    return out


def _hits(db: Database, slots: list[Slot], last: int, ids: dict[str, int]) -> DataFrame:
    """``sid, pos, slot, out``: where each slot's test holds, once for each of its outputs; those
    that no frequent pattern can have are left out."""
    spots, pairs = db.seqs.select("sid", F.posexplode("items").alias("pos", "item")), db.dictionary.pairs

    def below(w: str) -> DataFrame:
        return pairs.where(F.col("anc") == ids[w]).select(F.col("fid").alias("__w"))

    def rows(s: Slot, k: int) -> DataFrame:
        out = spots
        if s.name and s.exact:
            out = out.where(F.col("item") == ids[s.name])
        elif s.name:
            out = out.join(below(s.name), F.col("item") == F.col("__w"), "left_semi")
        if not s.captured:
            return out.select("sid", "pos", F.lit(k).alias("slot"), F.lit(None).cast("int").alias("out"))
        if s.const:
            out = out.select("sid", "pos", F.lit(ids[s.name]).alias("out"))
        elif s.up:
            own = pairs.where(F.col("anc") <= last)
            if s.name:
                own = own.join(below(s.name), F.col("anc") == F.col("__w"), "left_semi")
            out = out.join(own, out["item"] == own["fid"]).select("sid", "pos", F.col("anc").alias("out"))
        else:
            out = out.select("sid", "pos", F.col("item").alias("out"))
        return out.where(F.col("out") <= last).select("sid", "pos", F.lit(k).alias("slot"), "out")

    found = None
    for k, s in enumerate(slots):
        found = rows(s, k) if found is None else found.unionByName(rows(s, k))
    return found


def walk(db: Database, g: Graph, sigma: int) -> DataFrame:
    """``pattern array<int>, freq``, counted by distinct sequence: positions are joined in the
    tasks that hold the sequences, or as tables where too many prefixes are frequent for that."""
    from . import local

    try:
        return local.walk(db, g, sigma)
    except local.TooManyPrefixes:
        return walk_tables(db, g, sigma)


def walk_tables(db: Database, g: Graph, sigma: int) -> DataFrame:
    """``pattern array<int>, freq``, counted by distinct sequence.

    A level's rows (sequence, node, place, pattern so far) are joined with the hits of the next
    slots on the sequence, whatever the number of shapes. Before a free gap only the first place
    of a prefix is kept, and prefixes that too few sequences have are dropped where all ways to a
    pattern agree on its prefix. Every level is a written table."""
    names, slots = {s.name for s in g.slots if s.name}, g.slots
    ids = {r["item"]: r["fid"] for r in db.dictionary.items.where(F.col("item").isin(sorted(names))).collect()}
    if names - set(ids):
        raise ValueError(f"the expression names items that are not in the dictionary: {', '.join(sorted(names - set(ids)))}")
    spark = db.seqs.sparkSession
    hits = _hits(db, slots, db.dictionary.last_frequent(sigma), ids)
    if names or any(s.up for s in slots):  # joins with the hierarchy are made once
        hits = written(hits, "hits")
    number = {s: k for k, s in enumerate(slots)}
    free = sorted(q for q in g.inner if all(high is None for at, _, _, high, _ in g.edges if at == q))
    table = [(at, number[s], low, high, to) for at, s, low, high, to in g.edges]
    prune, results = g.captures_by_level(), None
    dead_ends = g.inner - {0}

    def moved(now: DataFrame | None, here: list) -> DataFrame:
        to = F.broadcast(spark.createDataFrame(here, "at int, slot int, low int, high int, next int"))
        if now is None:
            rows = hits.join(to, "slot").where((F.col("pos") >= F.col("low")) & (F.col("high").isNull() | (F.col("pos") <= F.col("high"))))
            before = F.array().cast("array<int>")
        else:
            ahead = hits.withColumnRenamed("pos", "hit")
            rows, before = now.join(to, now["node"] == to["at"]), F.col("pattern")
            if all(e[2] == e[3] == 0 for e in here):
                rows = rows.withColumn("hit", F.col("pos") + 1).join(ahead, ["sid", "slot", "hit"])
            else:
                gap = F.col("hit") - F.col("pos") - 1
                rows = rows.join(ahead.hint("merge"), ["sid", "slot"]).where((gap >= F.col("low")) & (F.col("high").isNull() | (gap <= F.col("high"))))
            rows = rows.drop("pos").withColumnRenamed("hit", "pos")
        grown = F.when(F.col("out").isNull(), before).otherwise(F.concat(before, F.array("out")))
        place = F.when(F.col("next").isin(sorted(dead_ends)), F.col("pos"))  # of finished walks no place is needed
        rows = rows.select("sid", F.col("next").alias("node"), place.alias("pos"), grown.alias("pattern"))
        if set(free) >= {e[4] for e in here} & dead_ends:
            return rows.groupBy("sid", "node", "pattern").agg(F.min("pos").alias("pos")).select("sid", "node", "pos", "pattern")
        return rows.distinct()

    now, nodes = None, {0}
    for level in range(MAX_LEVELS + 2):
        here = [e for e in table if e[0] in nodes]
        if not here or level > len(table) and now.isEmpty():  # only a graph with a cycle comes so far
            break
        if level > MAX_LEVELS:
            raise RuntimeError(f"matches are longer than {MAX_LEVELS} tested items")
        now = written(moved(now, here), f"level{level}")
        nodes = {e[4] for e in here}
        done = now.where(F.col("node").isin(sorted(g.ends)) & (F.size("pattern") > 0)).select("sid", "pattern")
        results = done if results is None else results.unionByName(done)
        now = now.where(F.col("node").isin(sorted(dead_ends)))
        if prune and nodes & dead_ends:
            often = now.select("sid", "pattern").distinct().groupBy("pattern").count().where(F.col("count") >= sigma)
            now = now.join(often.select("pattern"), "pattern", "left_semi").select("sid", "node", "pos", "pattern")
    return results.distinct().groupBy("pattern").agg(F.count(F.lit(1)).alias("freq")).where(F.col("freq") >= sigma)


def chain(db: Database, shapes: list[tuple[list[Slot], list[int | None]]] | Graph, sigma: int) -> DataFrame:
    """``pattern array<int>, freq`` of a graph, or of the union of shapes."""
    return walk(db, shapes if isinstance(shapes, Graph) else from_shapes(shapes), sigma)


def ngrams(db: Database, low: int, high: int, sigma: int) -> DataFrame:
    """Contiguous items by slices of the array: one pass, one shuffle of partial counts."""
    last = db.dictionary.last_frequent(sigma)
    none = F.array().cast("array<array<int>>")

    def cut(k: int) -> Column:
        spots = F.sequence(F.lit(1), F.size("items") - (k - 1))
        return F.when(F.size("items") >= k, F.transform(spots, lambda i: F.slice("items", i, F.lit(k)))).otherwise(none)

    rows = db.seqs.select(F.explode(F.array_distinct(F.flatten(F.array(*map(cut, range(low, high + 1)))))).alias("pattern"))
    rows = rows.where(F.forall("pattern", lambda w: w <= last))
    return rows.groupBy("pattern").agg(F.count(F.lit(1)).alias("freq")).where(F.col("freq") >= sigma)


def skip_shapes(gap: int | None, low: int, high: int, up: bool = False) -> list:
    return [([Slot(up=up)] * k, [gap] * (k - 1)) for k in range(low, high + 1)]
