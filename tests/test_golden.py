"""The worked example: dictionary, outputs, growth tree; methods against definitions."""

import itertools
import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from trailmine.functions.kernel import Kernel
from trailmine.operators import baselines, mining, native, post
from trailmine.plans import expressions as ex
from trailmine.plans.transducers import compile_expression, positions, to_dot
from trailmine.sources import dictionary as di

SEQS = ["c a1 b12 e", "a1 b2 e", "d a2 a1 a2 b11 e", "d a1 B e", "e a1 b2 d", "c a1 a1 a1 b2 e"]
EDGES = [("a1", "A"), ("a2", "A"), ("b1", "B"), ("b2", "B"), ("b11", "b1"), ("b12", "b1")]
EX = "[c|d]([A^|B^=]+)e"
WANT = {("A A A B", 2), ("A B", 2), ("A a1 A B", 2), ("a1 B", 2)}


@pytest.fixture(scope="module")
def db(spark):
    seqs = spark.createDataFrame([(i + 1, s.split()) for i, s in enumerate(SEQS)], "sid long, items array<string>")
    return mining.prepare(seqs, spark.createDataFrame(EDGES, "child string, parent string"))


def pairs(df):
    return {(r["pattern"], r["freq"]) for r in df.collect()}


def test_dictionary(db):
    got = {r["item"]: r["freq"] for r in db.dictionary.items.collect()}
    assert got == {"A": 6, "B": 6, "a1": 6, "e": 6, "d": 3, "b2": 3, "b1": 2, "c": 2, "a2": 1, "b11": 1, "b12": 1}
    ids = {r["item"]: r["fid"] for r in db.dictionary.items.collect()}
    assert all(ids[p] < ids[c] for c, p in EDGES) and db.dictionary.last_frequent(2) == 8


@pytest.mark.parametrize("method", ["naive", "plain", "pruned", "growth", "auto"])
@pytest.mark.parametrize("optimized", [True, False])
def test_example(db, method, optimized):
    assert pairs(mining.mine(db, EX, 2, "full", method, optimized)) == WANT


def test_growth_tree(db):
    report = mining.Report()
    mining.snapshot_growth(db, compile_expression(EX), 2, report=report).count()
    assert (report.created, report.expanded) == (15, 11)
    assert [x["created"] for x in report.levels] == [2, 6, 4, 2, 0]


def test_mean_outputs(db):
    t = compile_expression(EX)
    assert tuple(mining.mean_outputs(db, t, None).first()) == (4, 5.0, 20)
    assert tuple(mining.mean_outputs(db, t, 2).first()) == (4, 3.5, 14)


def test_support(db):
    got = sorted(r[0] for r in mining.supporting_sequences(db, EX, ["a1", "B"], "full").collect())
    assert got == [1, 4]
    assert pairs(mining.pattern_support(db, EX, [["A", "B"], ["A", "A", "A"]], "full")) == {("A B", 2), ("A A A", 0)}


@pytest.mark.parametrize("bad", ["A^", "(a", "[a)", "a{3,1}", "*a", ".=", "(a))", "a ]"])
def test_rejected(bad):
    with pytest.raises(ex.ExpressionError, match="column"):
        ex.parse(bad)


def test_unknown_item(db):
    with pytest.raises(ValueError, match="nowhere"):
        mining.mine(db, "(nowhere)", 2)


def test_cycle(spark):
    with pytest.raises(ValueError, match="cycle"):
        di.closure(spark.createDataFrame([("a", "b"), ("b", "c"), ("c", "a")], "child string, parent string"))


def test_diamond(spark):
    up = di.closure(spark.createDataFrame([("x", "p"), ("x", "q"), ("p", "r"), ("q", "r")], "child string, parent string"))
    assert sorted(map(tuple, up.collect())) == [("p", "r"), ("q", "r"), ("x", "p"), ("x", "q"), ("x", "r")]


def slow(e, items, up, full):
    """Outputs by the definition: recursion on the syntax tree."""

    def walk(e, at, cap):  # yields (end, output)
        if isinstance(e, ex.Capture):
            yield from walk(e.part, at, True)
        elif isinstance(e, ex.Concat):
            parts = [(at, ())]
            for p in e.parts:
                parts = {(j, o + o2) for i, o in parts for j, o2 in walk(p, i, cap)}
            yield from parts
        elif isinstance(e, ex.Union):
            for p in e.parts:
                yield from walk(p, at, cap)
        elif isinstance(e, ex.Repeat):
            done, new, k = set(), {(at, ())}, 0
            while new and (e.high is None or k <= e.high):
                if k >= e.low:
                    yield from new
                old, new, k = new, {(j, o + o2) for i, o in new for j, o2 in walk(e.part, i, cap)} - done, k + 1
                done |= old if k > e.low else set()
        elif at < len(items):
            w = items[at]
            if e.name is None or (w == e.name if e.exact and not e.up else e.name in up[w]):
                if not cap:
                    yield at + 1, ()
                elif e.up and e.exact or e.exact:
                    yield at + 1, (e.name,)
                else:
                    for a in up[w] if e.up else [w]:
                        if e.name is None or e.name in up[a]:
                            yield at + 1, (a,)

    starts = [0] if full else range(len(items) + 1)
    return {o for s in starts for j, o in walk(e, s, False) if o and (not full or j == len(items))}


@pytest.mark.parametrize("text", [EX, "(.){1,2}", "(.^)[.{0,1}(.^)]{1,2}", "[.*(.)]{1,3}", "A (B^|.^) .?", "(a1=)|(b1^) e", "c (A^=)+ [b1]? (.)", "(A? [B^ .]*)", "", "(.^= )".replace("=", "")])
@pytest.mark.parametrize("match", ["full", "anywhere"])
def test_against_definition(text, match):
    parents = {}
    for c, p in [*EDGES, ("b12", "A")]:
        parents.setdefault(c, []).append(p)
    names = sorted({x for e in EDGES for x in e} | {"c", "d", "e"})

    def anc(w):
        return {w}.union(*(anc(p) for p in parents.get(w, [])))

    ids = {w: k + 1 for k, w in enumerate(names)}
    up = {ids[w]: (ids[w], *sorted(ids[a] for a in anc(w) if a != w)) for w in names}
    tree, rng = ex.parse(text), random.Random(text + match)
    kernels = [Kernel(compile_expression(text, match, o), up, ids, plain=p) for o, p in ((True, False), (False, False), (True, True))]
    for _ in range(60):
        items = [rng.choice(names) for _ in range(rng.randint(0, 6))]
        want = {tuple(ids[w] for w in o) for o in slow(tree, items, {w: anc(w) for w in names}, match == "full")}
        for k in kernels:
            coded = [ids[w] for w in items]
            assert k.generate(coded) == want, (items, text)
            assert not want or k.accepts(coded)


def test_methods_agree_with_baselines(spark):
    rng = random.Random(3)
    names = ["a1", "a2", "b1", "b2", "b11", "c", "d"]
    data = [(i, [rng.choice(names) for _ in range(rng.randint(0, 9))]) for i in range(60)]
    seqs = spark.createDataFrame(data, "sid long, items array<string>")
    db = mining.prepare(seqs, spark.createDataFrame(EDGES, "child string, parent string"))
    show = lambda df: pairs(di.decode(df, db.dictionary))
    for up in (False, True):
        e = ex.skipgrams(1, 3, up)
        want = pairs(mining.mine(db, e, 6, method="growth"))
        assert want and want == pairs(mining.mine(db, e, 6, method="pruned"))
        assert want == show(baselines.vertical_mine(db, 6, 3, 1, up)) == show(baselines.prefix_growth_mine(db, 6, 3, 1, up, 2))
        assert want == show(native.chain(db, native.skip_shapes(1, 2, 3, up), 6))
    assert pairs(mining.mine(db, ex.ngrams(1, 3), 3)) == show(native.ngrams(db, 1, 3, 3))
    free = pairs(mining.mine(db, "[.*(.)]{1,3}", 9, method="growth"))
    assert free == show(baselines.prefix_span(db, 9, 3)) == show(baselines.prefix_span_mllib(db, 9, 3))
    for slots, contiguous in (("[a1|a2] . [c|d]", True), ("[a1|b1]+ c", True), ("[a1|a2] . [c|d]", False)):
        parts = [f"({s})" for s in ("[a1|a2]", ".", "[c|d]")]
        e = f"({slots})" if contiguous else " .* ".join(parts)
        want = pairs(mining.mine(db, e, 3, method="growth"))
        assert want == show(baselines.prefix_growth_regex(db, slots, 3, contiguous)) == show(baselines.regex_enumerate(db, slots, 3, contiguous))


@pytest.mark.parametrize("text", ["(.^)[.{0,1}(.^)]{1,2}", "[.*(.)]+", "(a1=)|(b1^) e", "c (A^=)+ [b1]? (.)", "(a1) b2 | (a1) . e", ". . (A^)", "[A (B)] | [(B^) [.*(e)]]"])
def test_joins_of_graphs(db, text):
    """Expressions with gaps, cycles, context, and ends at several levels, against the definition."""
    up = {}
    for w, a in EDGES:
        up.setdefault(w, []).append(a)
    anc = lambda w: {w}.union(*map(anc, up.get(w, [])))
    count = Counter(o for x in SEQS for o in slow(ex.parse(text), x.split(), {w: anc(w) for w in x.split() + [p for _, p in EDGES]}, False))
    assert pairs(mining.mine(db, text, 2, method="joins")) == {(" ".join(o), n) for o, n in count.items() if n >= 2}


@pytest.mark.parametrize("text,match", [(EX, "full"), ("(a) .", "anywhere"), ("(a) [. .]* (b)", "anywhere")])
def test_no_graph(text, match):
    assert native.from_transducer(compile_expression(text, match)) is None


def test_entry_has_rows(spark):
    assert mining.relative_sigma(60, 150, 15) == 6 and mining.relative_sigma(60, 150, 150) == 60
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0


def test_post(spark):
    p = spark.createDataFrame([("a", 1, 5), ("a b", 2, 5), ("b", 1, 7), ("a c b", 3, 2)], "pattern string, length int, freq long")
    assert pairs(post.maximal(p)) == {("a c b", 2)}
    assert pairs(post.closed(p)) == {("a b", 5), ("b", 7), ("a c b", 2)}
    assert [r["pattern"] for r in post.top_k(p, 2).collect()] == ["b", "a"]
    assert post.disagreement(p, p).count() == 0


def test_guards(spark, db):
    with pytest.raises(Exception, match="over 3 outputs"):
        mining.generate_and_count(db, compile_expression("(.^)*", "anywhere"), 2, limit=3).count()
    with pytest.raises(ValueError):
        mining.mine(db, ".*(.)", 1)


def test_empty_and_long(spark):
    none = spark.createDataFrame([], "sid long, items array<string>")
    assert mining.mine(mining.prepare(none), "(.)", 2, method="growth").count() == 0
    long = spark.createDataFrame([(1, ["x", "y"] * 5000), (2, [])], "sid long, items array<string>")
    got = mining.mine(mining.prepare(long), "(x) .* (y)", 1, method="growth", force=True)
    assert pairs(got) == {("x y", 1)}


def test_stats(spark):
    e = spark.createDataFrame(EDGES, "child string, parent string")
    r = di.hierarchy_stats(e).first()
    assert (r["n_items"], r["n_leaf"], r["n_inner"], r["n_root"], r["max_depth"], r["max_fan_out"]) == (8, 5, 1, 2, 3, 2)
    assert "doublecircle" in to_dot(positions(ex.desugar("(a)")))
    assert ex.required_items("a [b|c] (d)? e") == {"a", "e"}
    assert list(itertools.islice(ex.items_named(EX), 0)) == []
    assert F is not None
