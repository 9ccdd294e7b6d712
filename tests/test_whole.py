"""Workloads over whole sequences."""

import itertools
import random
import re

import pytest

from trailmine.functions.kernel import Kernel
from trailmine.operators import mining
from trailmine.plans.transducers import compile_expression
from trailmine.sources import sequences as sq
from trailmine.workloads import WORKLOADS


@pytest.fixture(scope="module")
def letters(spark, tmp_path_factory):
    rng = random.Random(3)
    texts = ["x" * 600 + "".join(rng.choice("strkdezu .") for _ in range(rng.randint(5, 60))) for _ in range(40)] + [None, "", "S1.t"]
    path = tmp_path_factory.mktemp("letters")
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{path}/documents.parquet")
    return mining.prepare(sq.letter_strings(spark, str(path))), [re.sub("[^a-z]", "", (t or "").lower()) for t in texts]


@pytest.mark.parametrize("method", ["pruned", "growth"])
@pytest.mark.parametrize("name", ["p1_letters", "p4_letters"])
def test_letters_after_the_600th(letters, name, method):
    db, texts = letters
    sigma, want = 3, {}
    ends = ("st", "de") if name == "p4_letters" else ("st", "rk")
    for t in texts:
        if name == "p1_letters":
            last = {c: max(t.rfind(c), -1) for c in ends[1]}
            found = {a + m + b for a in ends[0] if a in t for b in ends[1] for m in set(t[t.find(a) + 1 : max(last[b], 0)])}
        else:
            n = 4 if name == "p4_letters" else 3
            found = {t[i : i + n] for i in range(len(t) - n + 1) if t[i] in ends[0] and t[i + n - 1] in ends[1]}
        for p in found:
            want[" ".join(p)] = want.get(" ".join(p), 0) + 1
    got = mining.mine(db, WORKLOADS[name][1], sigma, method=method)
    assert {r["pattern"]: r["freq"] for r in got.collect()} == {p: n for p, n in want.items() if n >= sigma} != {}


@pytest.mark.parametrize("text", ["(a) .* (.) .* (b)", "(a) .* (.)", ".* (a) .* b", "(a) .* b (.) .* (a)"])
def test_first_places_do_for_free_gaps(text):
    """Outputs and grown prefixes against all choices of positions."""
    rng, ids, slots = random.Random(9), {"a": 1, "b": 2, "c": 3}, text.split()
    k = Kernel(compile_expression(text, "anywhere"), {i: (i,) for i in ids.values()}, ids)
    for _ in range(200):
        s, want = [rng.choice("abc") for _ in range(rng.randint(0, 8))], set()
        for at in itertools.product(range(len(s)), repeat=sum(x != ".*" for x in slots)):
            prev, free, out, rest = None, True, [], list(at)
            for x in slots:
                if x == ".*":
                    free = True
                    continue
                p = rest.pop(0)
                if not (prev is None or (p > prev if free else p == prev + 1)) or x.strip("()") not in (".", s[p]):
                    break
                out += [ids[s[p]]] * x.startswith("(")
                prev, free = p, False
            else:
                want.add(tuple(out))
        items = [ids[c] for c in s]
        grown, level = set(), {(): [(0, k.t.start)]}
        while level:
            nxt = {}
            for out, snaps in level.items():
                ok, children = k.resume(items, snaps)
                grown |= {out} if ok and out else set()
                nxt |= {(*out, w): sorted(c) for w, c in children.items()}
            level = nxt
        assert k.generate(items) == want == grown


@pytest.mark.parametrize("name,most", [("a1_baskets", 5), ("a2_baskets", 5), ("a3_baskets", 4), ("a4_baskets", 5), ("a1_baskets_dag", 5)])
def test_customer_workloads_have_all_lengths(name, most):
    _, expression, _, shapes = WORKLOADS[name]
    root = {"a3_baskets": "hot ring", "a4_baskets": "plate"}.get(name, "ring")
    ids = {root: 1, "x": 2}
    k = Kernel(compile_expression(expression, "anywhere"), {1: (1,), 2: (2,)}, ids)
    found = {len(p) for p in k.generate([1] * 7)}
    assert max(found) == most == max(sum(s.captured for s in slots) for slots, _ in shapes)
