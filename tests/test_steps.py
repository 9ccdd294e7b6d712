"""Transducers stepped over arrays of many sequences find what the kernel finds in one."""

import random
import time
from collections import Counter

import numpy as np
import pytest

from trailmine.functions import steps as st
from trailmine.functions.kernel import Kernel, alike
from trailmine.functions.steps import Steps, in_parts
from trailmine.operators import local, mining
from trailmine.plans.transducers import compile_expression

UP = {1: (1,), 2: (2, 1), 3: (3, 1), 4: (4, 2, 1), 5: (5, 2, 1), 6: (6, 3, 1), 7: (7,), 8: (8,), 9: (9, 2, 1)}
IDS = {"top": 1, "left": 2, "right": 3, "one": 4}
TEXTS = ["(.^)[.{0,1}(.^)]{1,2}", "(.^){3} left", "(.^ . .) | (. .^ .) | (. . .^)", "left (right+ top+? one?) .", "(left^ top^=) right? (one? .)", "top+ (.)", "(left^)[.{0,2}(left^)]{1,4}", ". . (.)?"]


def pairs():
    return map(np.array, zip(*[(w, a) for w, up in UP.items() for a in up], strict=True))


def patterns(s, flat, sizes):
    def count(s):
        out, before = Counter(), [()]
        for parent, o, reached, (pat, _) in s.levels([], s.none + 1):
            before = [(*before[p], x) for p, x in zip(parent.tolist(), o.tolist(), strict=True)]
            had = np.bincount(pat, minlength=len(o))
            assert (had <= reached).all()
            out.update({before[k]: int(n) for k, n in enumerate(had) if n})
        return out

    return sum(in_parts(s, flat, sizes, count), Counter())


@pytest.mark.parametrize("match", ["anywhere", "full"])
@pytest.mark.parametrize("text", TEXTS)
def test_steps_are_as_the_kernel(text, match, monkeypatch):
    """Compact, with items that act alike at any frequency limit, and plain; in parts too."""
    items, above = pairs()
    t, rng = compile_expression(text, match), random.Random(7)
    seqs = [[rng.randint(1, 9) for _ in range(rng.randint(0, 8))] for _ in range(60)]
    flat, sizes = np.array([w for x in seqs for w in x]), np.array([len(x) for x in seqs])
    for last in (None, 0, 2, 3, 9):
        k = Kernel(t, UP, IDS, last)
        want = Counter(o for x in seqs for o in k.generate(x))
        if last is None:
            cases = [(Steps(t, items, above, IDS, None, plain), flat) for plain in (True, False)]
        else:
            matters = np.arange(10) <= last
            matters[list(IDS.values())] = True
            same = alike(items, above, matters)
            own = (same[items] == items) & ((items == above) | matters[above])
            cases = [(Steps(t, items[own], above[own], IDS, last), same[flat])]
        for s, w in cases:
            for most in (3_000_000, 50):
                monkeypatch.setattr(st, "MOST_SNAPSHOTS", most)
                assert patterns(s, w, sizes) == want


def test_plain_form_of_many_items():
    """300,000 parts: their moves are made, and sequences of them stepped, without a Python step for
    each item."""
    n = 300_000
    parts = np.arange(101, n + 101)
    items, above = np.concatenate([np.arange(101), parts, parts]), np.concatenate([np.arange(101), parts, parts % 100 + 1])
    began = time.process_time()
    s = Steps(compile_expression("(top^)[.{0,2}(top^)]{1,2}", "anywhere"), items, above, {"top": 6}, None, True)
    got = patterns(s, np.array([205, 101, 305, 205]), np.array([3, 1]))
    assert got == Counter({(a, b): 1 for a in (205, 6) for b in (305, 6)}) and time.process_time() - began < 5


@pytest.fixture(scope="module")
def db(spark):
    rng = random.Random(4)
    names = ["a1", "a2", "b1", "b2", "c", "d"]
    seqs = spark.createDataFrame([(i, [rng.choice(names) for _ in range(rng.randint(1, 9))]) for i in range(60)], "sid long, items array<string>")
    return mining.prepare(seqs, spark.createDataFrame([("a1", "A"), ("a2", "A"), ("b1", "B"), ("b2", "B")], "child string, parent string"))


def found(df):
    return {(tuple(r["pattern"]), r["freq"]) for r in df.collect()}


@pytest.mark.parametrize("text", ["(.^)[.{0,1}(.^)]{1,2}", "(.^){3} B", "(.^ . .) | (. .^ .) | (. . .^)", "A (B+ .? c?) ."])
def test_growth_writes_no_snapshots(db, text, monkeypatch):
    """Nothing but counters leaves the tasks; the same patterns by rows of snapshots, and where a
    length is looked up by search."""
    names, real, t = [], mining.written, compile_expression(text, "anywhere")
    monkeypatch.setattr(mining, "written", lambda df, name: names.append(name) or real(df, name))
    got = found(mining.snapshot_growth(db, t, 2))
    assert got and not names
    monkeypatch.setattr(local, "DENSE", 0)
    assert found(mining.snapshot_growth(db, t, 2)) == got
    monkeypatch.setattr(local, "MAX_BROADCAST_NODES", 1)
    assert found(mining.snapshot_growth(db, t, 2)) == got and "frontier" in names
    with pytest.raises(RuntimeError, match="longer than 1"):
        monkeypatch.undo()
        mining.snapshot_growth(db, t, 2, max_level=1)


def test_growth_over_free_gaps_takes_rows(db):
    t = compile_expression("(A) .* (.)", "anywhere")
    assert local.grow(db, t, 2) is None and found(mining.snapshot_growth(db, t, 2))


@pytest.mark.parametrize("text", ["(A^)[.{0,2}(A^)]{1,4}", "(.^){2} B"])
def test_plain_is_stepped_in_arrays(db, text, monkeypatch):
    """No sequence is taken alone; the guard of its outputs holds."""
    t = compile_expression(text, "anywhere")
    want = {(tuple(x["pattern"]), x["freq"]) for x in mining.generate_and_count(db, t, 2).collect()}
    monkeypatch.setattr(mining, "generate_and_count", None)
    names = {r["fid"]: r["item"] for r in db.dictionary.items.collect()}
    got = mining.mine(db, text, 2, method="plain").collect()
    assert {(r["pattern"], r["freq"]) for r in got} == {(" ".join(names[w] for w in p), n) for p, n in want} != set()
    with pytest.raises(Exception, match="over 1 outputs"):
        mining.mine(db, text, 2, method="plain", limit=1).count()


@pytest.mark.parametrize("match", ["anywhere", "full"])
@pytest.mark.parametrize("text", [*TEXTS, "left (.) (.^)?", "(.^){2} . (.)"])
def test_patterns_are_as_the_kernel(text, match, monkeypatch):
    """All outputs of each sequence, in sets of bits and without, in parts, and only some of them."""
    items, above = pairs()
    t, rng = compile_expression(text, match), random.Random(7)
    seqs = [[rng.randint(1, 9) for _ in range(rng.randint(0, 8))] for _ in range(60)]
    flat, sizes = np.array([w for x in seqs for w in x]), np.array([len(x) for x in seqs])

    def of(s, least):
        out, before, own = Counter(), [()], np.zeros(s.seqs, np.int64)
        for parent, o, n, each in s.patterns(least):
            before = [(*before[p], x) for p, x in zip(parent.tolist(), o.tolist(), strict=True)]
            out.update({before[k]: x for k, x in enumerate(n.tolist()) if x >= least})
            own += each
        assert not s.seqs or sum((x[-1] for x in s.patterns(None)), np.zeros(s.seqs, np.int64)).tolist() == own.tolist()
        return out, own

    for last in (None, 0, 2, 9):
        k = Kernel(t, UP, IDS, last)
        found = [k.generate(x) for x in seqs]
        want, s = Counter(o for x in found for o in x), Steps(t, items, above, IDS, last)
        for bits, rows, most in ((1024, 50_000, 3_000_000), (1024, 3, 50), (0, 3, 3_000_000)):
            for name, x in (("MOST_BITS", bits), ("BIT_ROWS", rows), ("MOST_SNAPSHOTS", most)):
                monkeypatch.setattr(st, name, x)
            parts = in_parts(s, flat, sizes, lambda s: of(s, 1))
            assert sum((x for x, _ in parts), Counter()) == want
            assert np.concatenate([x for _, x in parts]).tolist() == list(map(len, found))
        monkeypatch.setattr(st, "MOST_SNAPSHOTS", 3_000_000)
        s.load(flat, sizes)
        assert of(s, 4)[0] == {x: n for x, n in want.items() if n >= 4}


@pytest.mark.parametrize("text", ["(.^)[.{0,1}(.^)]{1,2}", "(.^){3} B", "A (B+ .? c?) .", "(.)"])
def test_pruned_is_counted_in_arrays(db, text, monkeypatch):
    """No sequence is taken alone; tasks leave out what cannot be frequent, by parts of any size,
    and the same patterns come of all outputs; the guard holds."""
    t = compile_expression(text, "anywhere")
    want = {s: found(mining._counted(db, mining.Binding(db, t, s), s, None)) for s in (2, 5)}
    assert want[2]
    n = [len(k) for k in _outputs(db, t, 5)]
    monkeypatch.setattr(mining, "_counted", None)
    monkeypatch.setattr(mining, "rows_of", None)
    for part, share, most in ((8, 100, 500_000), (40, 0, 500_000), (40, 100, 1)):
        for name, x in (("PART", part), ("SHARE", share), ("MAX_BROADCAST_NODES", most), ("HELD_OUTPUTS", 3)):
            monkeypatch.setattr(mining, name, x)
        for s, patterns in want.items():
            assert found(mining.pruned_count(db, t, s)) == patterns
    r = mining.mean_outputs(db, t, 5).first()
    assert (r["n_sequences"], r["n_pairs"] or 0) == (sum(x > 0 for x in n), sum(n))
    with pytest.raises(Exception, match="over 1 outputs"):
        mining.pruned_count(db, t, 2, limit=1).count()


def _outputs(db, t, sigma):
    k = mining.Binding(db, t, sigma).kernel()
    return [k.generate(k.known(r["items"])) for r in db.seqs.collect()]


def test_parts_do_not_end_with_a_batch():
    import pyarrow as pa

    seqs = [list(range(k % 7 + 1)) for k in range(90)]
    batches = [pa.RecordBatch.from_arrays([pa.array(seqs[k : k + 16], pa.list_(pa.int32()))], names=["items"]) for k in range(0, 90, 16)]
    parts = list(mining._parts(iter(batches), 20))
    assert [w for flat, _ in parts for w in flat.tolist()] == [w for x in seqs for w in x]
    assert [n for _, sizes in parts for n in sizes.tolist()] == list(map(len, seqs))
    assert all(20 <= len(flat) <= 45 for flat, _ in parts) and not list(mining._parts(iter([]), 20))
