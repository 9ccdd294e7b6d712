"""Specialised miners for comparison: vertical id-lists, prefix growth (with and without a
regular expression), enumeration over an expression's automaton, and unconstrained growth.

Tables of positions are joined by merging: their files are far smaller than their rows, so Spark
would take them for small and send them through the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.kernel import rows_of
from ..plans.transducers import compile_expression
from ..sources.dictionary import written
from . import native
from .mining import PATTERNS, Binding, Database, combined, counted


def _spots(db: Database, sigma: int, up: bool) -> DataFrame:
    """``sid, pos, item`` of frequent items; with ``up`` their frequent generalisations too."""
    last = db.dictionary.last_frequent(sigma)
    rows = db.seqs.select("sid", F.posexplode("items").alias("pos", "item"))
    if up:
        pairs = db.dictionary.pairs
        rows = rows.join(pairs.hint("merge"), rows["item"] == pairs["fid"]).select("sid", "pos", F.col("anc").alias("item"))
    return rows.where(F.col("item") <= last)


def _within(before, after, gap: int | None):
    step = F.col(after) - F.col(before)
    return step.between(1, 1 + gap) if gap is not None else step >= 1


def _count(rows: DataFrame, sigma: int) -> DataFrame:
    """Candidates with support: by distinct sequence."""
    return rows.select("sid", "pattern").distinct().groupBy("pattern").agg(F.count(F.lit(1)).alias("freq")).where(F.col("freq") >= sigma)


def vertical_mine(db: Database, sigma: int, max_len: int, max_gap: int | None, up: bool = False, min_len: int = 2, sizes: list | None = None) -> DataFrame:
    """Id-lists of patterns are joined with those of frequent pairs. ``sizes`` gets the rows of
    each level's inverted index."""
    spots = written(_spots(db, sigma, up).select("sid", "pos", "item"), "spots")
    two = spots.alias("a").join(spots.alias("b").hint("merge"), F.col("a.sid") == F.col("b.sid")).where(_within("a.pos", "b.pos", max_gap))
    two = two.select("a.sid", F.col("a.item").alias("first"), F.col("a.pos").alias("from"), F.col("b.item").alias("item"), F.col("b.pos").alias("pos"))
    good = _count(two.select("sid", F.array("first", "item").alias("pattern")), sigma)
    good = written(good, "pairs")
    two = two.withColumn("pattern", F.array("first", "item")).join(good.select("pattern"), "pattern", "left_semi")
    two = written(two.select("sid", "first", "from", "item", "pos"), "two")
    lists = two.select("sid", F.array("first", "item").alias("pattern"), "item", "pos").distinct()
    out = [good] if min_len <= 2 else []
    if min_len <= 1:
        out.insert(0, _count(spots.select("sid", F.array("item").alias("pattern")), sigma))
    for k in range(3, max_len + 1):
        lists = written(lists, f"lists{k}")
        if sizes is not None:
            sizes.append(lists.count())
        nxt = lists.alias("l").join(two.alias("t").hint("merge"), (F.col("l.sid") == F.col("t.sid")) & (F.col("l.item") == F.col("t.first")) & (F.col("l.pos") == F.col("t.from")))
        nxt = nxt.select("l.sid", F.concat("l.pattern", F.array("t.item")).alias("pattern"), F.col("t.item").alias("item"), F.col("t.pos").alias("pos")).distinct()
        nxt = written(nxt, f"candidates{k}")
        good = written(_count(nxt, sigma), f"good{k}")
        if good.isEmpty():
            break
        if k >= min_len:
            out.append(good)
        lists = nxt.join(good.select("pattern"), "pattern", "left_semi").select("sid", "pattern", "item", "pos")
    found = out[0] if out else good.limit(0)
    for x in out[1:]:
        found = found.unionByName(x)
    return found


def prefix_growth_mine(db: Database, sigma: int, max_len: int | None, max_gap: int | None, up: bool = False, min_len: int = 1, sizes: list | None = None) -> DataFrame:
    """Projected positions of each frequent prefix grow to the right; no automaton state."""
    spots = written(_spots(db, sigma, up), "spots")
    now = spots.select("sid", "pos", F.array("item").alias("pattern"))
    out, k = None, 1
    while True:
        now = written(now.distinct(), f"projected{k}")
        if sizes is not None:
            sizes.append(now.count())
        good = written(_count(now, sigma), f"good{k}")
        if good.isEmpty():
            break
        if k >= min_len:
            out = good if out is None else out.unionByName(good)
        if k == max_len:
            break
        now = now.join(good.select("pattern"), "pattern", "left_semi")
        if max_gap is None:  # with free gaps the first place of a prefix is enough
            now = now.groupBy("sid", "pattern").agg(F.min("pos").alias("pos"))
        nxt = now.alias("n").join(spots.alias("s").hint("merge"), F.col("n.sid") == F.col("s.sid")).where(_within("n.pos", "s.pos", max_gap))
        now, k = nxt.select("n.sid", "s.pos", F.concat("n.pattern", F.array("s.item")).alias("pattern")), k + 1
    return out if out is not None else good


def prefix_span(db: Database, sigma: int, max_len: int) -> DataFrame:
    return prefix_growth_mine(db, sigma, max_len, None)


def prefix_span_mllib(db: Database, sigma: int, max_len: int) -> DataFrame:
    """The library's miner on one-item sets, as an outside check."""
    from pyspark.ml.fpm import PrefixSpan

    n = db.seqs.count()
    rows = db.seqs.select(F.transform("items", lambda x: F.array(x)).alias("sequence"))
    found = PrefixSpan(minSupport=(sigma - 0.5) / n, maxPatternLength=max_len).findFrequentSequentialPatterns(rows)
    return found.select(F.flatten("sequence").alias("pattern"), "freq")


def prefix_growth_regex(db: Database, slots: str, sigma: int, contiguous: bool) -> DataFrame:
    """Growth where a prefix lives only if the expression's automaton, run over the pattern,
    can still accept. ``slots``: an expression over items without captures."""
    t, gap = compile_expression(f"({slots})"), 0 if contiguous else None
    # node 0 begins anywhere and is no state; state q is node q + 1
    moves = [(0, i, o, to) for i, o, to in t.moves[t.start]] + [(q + 1, i, o, to) for q, ms in enumerate(t.moves) for i, o, to in ms]
    edges = tuple((at, native._slot(i, o), 0, gap if at else None, to + 1) for at, i, o, to in moves)
    return native.walk(db, native.Graph(edges, frozenset(q + 1 for q in t.finals)), sigma)


def regex_enumerate(db: Database, slots: str, sigma: int, contiguous: bool = False) -> DataFrame:
    """One pass per sequence: each state of the expression's automaton holds the partial
    subsequences that lead to it; those at final states are counted."""
    b = Binding(db, compile_expression(f"({slots})"), sigma)

    def outputs(k, items):
        held = [set() for _ in k.t.moves]
        found = set()
        for w in items:
            new = [set() for _ in k.t.moves]
            for o, to in k.step(k.t.start, w):
                new[to].add((o,))
            for q, parts in enumerate(held):
                for o, to in k.step(q, w) if parts else ():
                    new[to].update(p + (o,) for p in parts)
            held = new if contiguous else [a | n for a, n in zip(held, new, strict=True)]
            found.update(*(new[q] for q in k.t.finals))
        return found

    def run(batches):
        k = b.kernel()
        for batch in batches:
            yield from combined(outputs(k, k.known(items)) for items in rows_of(batch.column(0)))

    return counted(db.seqs.select("items").mapInArrow(run, PATTERNS), sigma)
