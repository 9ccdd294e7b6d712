"""Operator 5 against all pairs."""

import numpy as np
import pytest
import xxhash

from tests.llm import fixtures as fx
from trailmine.llm import simhash
from trailmine.llm.components import components


def slow_fingerprint(text):
    w = text.encode().lower().split()
    grams = [b" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [b" ".join(w)] if w else []
    hs = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def find(nodes, linked):
    root = {x: x for x in nodes}

    def up(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in linked:
        root[max(up(a), up(b))] = min(up(a), up(b))
    return {x: up(x) for x in nodes}


def close(fps):
    f = np.array(fps, np.uint64)
    for i in range(len(f)):
        for j in np.flatnonzero(np.bitwise_count(f[i + 1 :] ^ f[i]) <= 3):
            yield fps[i], fps[i + 1 + j]


@pytest.mark.parametrize("which", ["odd", "table"])
def test_documents(spark, which):
    docs = getattr(fx, which)(spark)
    want = [(i, slow_fingerprint(t)) for i, t in fx.texts(docs)]
    root = find({f for _, f in want}, close(sorted({f for _, f in want})))
    least = {}
    for i, f in want:
        if i is not None:
            least[root[f]] = min(i, least.get(root[f], i))
    got = simhash.near_duplicates(docs).collect()
    key = lambda r: (r[0] is None, r[0] or 0, r[1])
    assert sorted(((r["doc_id"], r["fp"] % 2**64, r["component_id"]) for r in got), key=key) == sorted(((i, f, least.get(root[f])) for i, f in want), key=key)
    kept = simhash.drop_near_duplicates(docs)
    assert kept.columns == docs.columns
    assert {r["doc_id"] for r in kept.collect()} >= set(least.values())


@pytest.mark.parametrize("cell_rows", [30, 8192])
def test_links_keep_every_component(spark, cell_rows):
    rng = np.random.default_rng(5)
    fps = {int(x) for x in rng.integers(0, 2**64, 1500, dtype=np.uint64)}
    for _ in range(25):  # clouds around centres, at 0 to 6 bits, and one dense cloud
        c = int(rng.integers(0, 2**64, dtype=np.uint64))
        for _ in range(40):
            fps.add(c ^ sum(1 << int(b) for b in rng.choice(64, rng.integers(0, 7), replace=False)))
    fps |= {0, 2**64 - 1, 7, 2**64 - 8, 2**63, 3} | {5 ^ (1 << i) ^ (1 << j) for i in range(30) for j in range(i)}
    fps = sorted(fps)
    want = find(fps, close(fps))
    df = spark.createDataFrame([(f - 2**64 if f >= 2**63 else f,) for f in fps], "fp long")
    pairs = simhash.links(simhash.deal_variants(df, len(fps), cell_rows))
    got = find(fps, {(r["u"] % 2**64, r["v"] % 2**64) for r in pairs.collect()})
    assert got == want
    trees = {r["node"]: r["root"] for r in components(pairs).collect()}
    signed = lambda f: f - 2**64 if f >= 2**63 else f
    groups = {}
    for f in fps:
        groups.setdefault(want[f], set()).add(trees.get(signed(f), signed(f)))
    assert all(len(g) == 1 for g in groups.values()) and len(set().union(*groups.values())) == len(groups)


def test_empty(spark):
    assert simhash.near_duplicates(fx.none(spark)).count() == 0
    assert simhash.drop_near_duplicates(fx.none(spark)).count() == 0
