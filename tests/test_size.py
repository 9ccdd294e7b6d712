"""Large dictionaries and tables of positions: small in a task, never sent through the driver."""

import random

import numpy as np
import pytest

from trailmine.functions.kernel import Ancestors, Kernel, alike
from trailmine.operators import baselines, local, mining, native
from trailmine.plans.transducers import PlainMoves, compile_expression, plain_moves
from trailmine.sources import dictionary as di

UP = {1: (1,), 2: (2, 1), 3: (3, 1), 4: (4, 2, 1), 5: (5, 2, 1), 6: (6, 3, 1), 7: (7,), 8: (8,), 9: (9, 2, 1)}
IDS = {"top": 1, "left": 2, "right": 3, "one": 4}


def arrays():
    return map(np.array, zip(*[(w, a) for w, up in UP.items() for a in up], strict=True))


@pytest.mark.parametrize("text", ["(.^)[.{0,1}(.^)]{1,2}", "(left^) . (right)", "(top^=) (.)", "(one) .* (.^)", "(.)[.{0,2}(left^)]"])
def test_items_that_act_alike(text):
    """Items stand for others only where the outputs stay the same, at any frequency limit."""
    items, above = arrays()
    for last in range(10):
        matters = np.arange(10) <= last
        matters[list(IDS.values())] = True
        same = alike(items, above, matters)
        own = (same[items] == items) & ((items == above) | matters[above])
        t = compile_expression(text, "anywhere")
        whole, few = Kernel(t, UP, IDS, last), Kernel(t, Ancestors(items[own], above[own]), IDS, last, alike=same)
        rng = random.Random(last)
        for _ in range(30):
            seq = [rng.randint(1, 9) for _ in range(rng.randint(0, 7))]
            assert few.generate(few.known(seq)) == whole.generate(seq)


def test_large_dictionary_is_small():
    n = 300_000
    parts = np.arange(101, n + 101)
    items, above = np.concatenate([np.arange(101), parts, parts]), np.concatenate([np.arange(101), parts, parts % 100 + 1])
    up = Ancestors(items, above)
    assert up.get(205) == (205, 6) and up.get(n + 101) == () and up.above.nbytes + up.starts.nbytes < 5e6
    k = Kernel(compile_expression("(.^)[.{0,1}(.^)]"), up, {})
    for w in parts[:120_000].tolist():
        k.step(0, w)
        k.kind(w)
    assert len(k.cache) <= 50_000 and len(k.kind_of) <= 50_000 and len(k.kinds) == 1


def test_plain_moves_by_item():
    t = compile_expression("(left^)[.{0,2}(right)]{1,2}", "anywhere")
    k = Kernel(t, UP, IDS)
    fast, slow = PlainMoves(t, k.matches, k.outputs, UP), plain_moves(t, k.matches, k.outputs, UP)
    for q, ms in enumerate(slow):
        for w in range(12):
            assert fast.of(q, w) == [(o, to) for i, o, to in ms if i == w]


@pytest.fixture(scope="module")
def db(spark):
    rng = random.Random(4)
    names = ["a1", "a2", "b1", "b2", "c", "d"]
    seqs = spark.createDataFrame([(i, [rng.choice(names) for _ in range(rng.randint(1, 9))]) for i in range(60)], "sid long, items array<string>")
    return mining.prepare(seqs, spark.createDataFrame([("a1", "A"), ("a2", "A"), ("b1", "B"), ("b2", "B")], "child string, parent string"))


def test_positions_are_not_broadcast(db, monkeypatch):
    """Tables of positions are small as files; only hints keep them from the driver."""
    plans, real = [], di.written

    def kept(df, name):
        plans.append((name, df._jdf.queryExecution().executedPlan().toString()))
        return real(df, name)

    monkeypatch.setattr(baselines, "written", kept)
    baselines.vertical_mine(db, 5, 2, 0, True, 1)
    assert any("SortMergeJoin" in plan for name, plan in plans if name == "pairs")


@pytest.mark.parametrize("text", ["(.^)[.{0,1}(.^)]{1,2}", "[.*(.)]{1,3}", "(A) B* (.)", ". . (A^)", "A .* (.) (B^)"])
def test_joins_in_tasks(db, text):
    """The walk inside the tasks finds what joins of tables find, and starts no shuffle of rows."""
    g = native.from_transducer(compile_expression(text, "anywhere"))
    found = lambda df: {(tuple(r["pattern"]), r["freq"]) for r in df.collect()}
    assert found(local.walk(db, g, 5)) == found(native.walk_tables(db, g, 5)) != set()


def test_event_closure_reads_events(spark, tmp_path):
    """Only the types that the table holds have ancestors, and classes."""
    import duckdb

    import __spark_entry__

    spark.createDataFrame([("click",), ("error",), ("click",)], "event_type string").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    got = sorted(map(tuple, __spark_entry__.queries()["hierarchy_closure_events"](spark, str(tmp_path)).collect()))
    assert got == [("BROWSE", "ACTION"), ("CONVERT", "ACTION"), ("click", "ACTION"), ("click", "BROWSE"), ("error", "FAULT")]
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet/*.parquet'")
    assert got == sorted(con.execute(__spark_entry__.oracle_sql()["hierarchy_closure_events"]).fetchall())


def test_items_are_looked_up_in_tasks(spark, monkeypatch):
    """Frequencies and ids are found where the sequences lie, without a shuffle of positions, as
    joins find them; nulls, empty sequences and ancestors that occur themselves included."""
    rows = [(1, ["a1", "B", None, "a1"]), (2, []), (3, None), (4, ["A", "a2", "x"]), (5, [None]), (6, ["b1", "B", "a1"])]
    seqs = spark.createDataFrame(rows, "sid long, items array<string>")
    edges = spark.createDataFrame([("a1", "A"), ("a2", "A"), ("b1", "B"), ("B", "TOP"), ("no", "TOP")], "child string, parent string")

    def prepared():
        d = di.build_dictionary(seqs, edges)
        out = di.encode(seqs, d)
        names = {r["fid"]: r["item"] for r in d.items.collect()}
        plan = out._jdf.queryExecution().executedPlan().toString()
        return d.items.orderBy("fid").collect(), {r["sid"]: [names[w] for w in r["items"]] for r in out.collect()}, plan

    items, coded, plan = prepared()
    assert coded == {1: ["a1", "B", "a1"], 4: ["A", "a2", "x"], 6: ["b1", "B", "a1"]} and "Exchange" not in plan
    assert {r["item"]: r["freq"] for r in items} == {"A": 3, "a1": 2, "a2": 1, "B": 2, "b1": 1, "TOP": 2, "x": 1, "no": 0}
    monkeypatch.setattr(di, "LOCAL_NAMES", 0)
    monkeypatch.setattr(di, "LOCAL_PAIRS", 0)
    slow = prepared()
    assert slow[:2] == (items, coded) and "Exchange" in slow[2]


def test_outputs_are_counted_before_they_leave_a_task(monkeypatch):
    monkeypatch.setattr(mining, "HELD_OUTPUTS", 2)
    got = [tuple(zip(b["pattern"].to_pylist(), b["n"].to_pylist(), strict=True)) for b in mining.combined([{(1,)}, {(1,)}, {(1,), (2, 3)}, {(1,)}])]
    assert got == [(([1], 3), ([2, 3], 1)), (([1], 1),)] or got == [(([2, 3], 1), ([1], 3)), (([1], 1),)]


TEXTS = ["The cats ran. a An", "...", ".Running fast! Running again\nand\nRe-running", "", None, "ÄÖ kKk x" + "y" * 40 + " x" + "y" * 41 + " is. on", "one" * 30 + "? two three", "z", "é.b", "A" * 13 + " " + "A" * 14]


def test_texts_by_bytes_are_as_by_expressions(spark, tmp_path):
    """Words and letters that tasks read from bytes: the same items, frequencies and sequences as by
    regular expressions, long words, word-less texts and bounds of texts included."""
    from trailmine.operators import mining
    from trailmine.sources import sequences as sq

    rows = [(k, t, "en") for k, t in enumerate(TEXTS * 3)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(2).write.parquet(f"{tmp_path}/documents.parquet")
    for name, slow, edges in (("sentence_texts", sq.sentence_tokens, sq.token_edges), ("letter_texts", sq.letter_strings, None)):
        got = getattr(sq, name)(spark, str(tmp_path)).encoded()
        assert got is not None
        want = mining.prepare(slow(spark, str(tmp_path)), edges and edges(spark, str(tmp_path)))
        for a, b in ((got[1].items, want.dictionary.items), (got[1].pairs, want.dictionary.pairs), (got[0], want.seqs)):
            assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect())) != []


def test_texts_that_share_an_id_are_prepared_the_general_way(spark):
    from trailmine.operators import mining
    from trailmine.sources.texts import Texts

    rows = spark.createDataFrame([(1, "ab"), (1, "bc")], "sid long, text string")
    assert Texts(rows, True).encoded() is None
    assert mining.prepare_texts(Texts(rows, True), spark.createDataFrame([(1, list("ab")), (1, list("bc"))], "sid long, items array<string>")).sequences == 1


def test_lengths_that_few_prefixes_have_are_counted_in_one_pass(spark):
    from trailmine.operators import local

    chain = [(k, 0, 0, None, k + 1) for k in range(4)]
    assert local.lengths_ahead(chain, [True], [3], 10, {0}, 1) == (4, [{1}, {2}, {3}, {4}])
    assert local.lengths_ahead(chain, [True], [local.AHEAD], 10, {0}, 1)[0] == 1
    assert local.lengths_ahead(chain, [True], [3], 10, {4}, 1)[0] == 0
