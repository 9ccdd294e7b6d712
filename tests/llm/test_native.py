"""Operators 2, 3, 8 and 9 against plain Python."""

import hashlib
import math
import re
from collections import Counter, defaultdict

import pytest

from tests.llm import fixtures as fx
from trailmine.llm import chat_format, exact_dedup, mixing, quality_rules

WORD = re.compile("[^\x20\x09-\x0d]+")


def rows(df):
    return [r.asDict() for r in df.collect()]


@pytest.mark.parametrize("slots", [2, 1024])
@pytest.mark.parametrize("which", ["odd", "table"])
def test_dedup(spark, which, slots):
    docs = getattr(fx, which)(spark)
    groups = defaultdict(list)
    for i, t in fx.texts(docs):
        groups[re.sub("[\x20\x09-\x0d]", "", t)].append((-len(t), i is None, i or 0, i))
    want = Counter()
    for norm, g in groups.items():
        g.sort()
        for k, x in enumerate(g):
            want[(x[3], g[0][3], len(g), k == 0, hashlib.sha256(norm.encode()).hexdigest())] += 1
    got = exact_dedup.dedup_decisions(docs, slots=slots)
    assert Counter(tuple(r) for r in got.collect()) == want
    kept = exact_dedup.drop_duplicates(docs, slots=slots)
    assert kept.columns == docs.columns
    assert Counter(r["doc_id"] for r in kept.collect()) == Counter(k[0] for k, n in want.items() if k[3])


def test_dedup_empty(spark):
    assert exact_dedup.dedup_decisions(fx.none(spark)).count() == 0
    assert exact_dedup.drop_duplicates(fx.none(spark)).count() == 0


def test_heavy_group_is_local(spark):
    docs = spark.range(3000).selectExpr("id AS doc_id", "IF(id % 3 = 0, 'copy', concat('t', id)) AS text")
    got = exact_dedup.dedup_decisions(docs, slots=16)
    assert got.where("kept").count() == 2001
    assert got.where("keep_id = 0").count() == 1000


def base(text):
    w = WORD.findall(text)
    seen = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    rep = {j for i in range(len(w) - 2) if seen[tuple(w[i : i + 3])] > 1 for j in (i, i + 1, i + 2)}
    lines = [x for x in text.split("\n") if WORD.search(x)]
    failed = len(w) < 50 or 100 * len(rep) > 50 * len(w)
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(rep), failed


@pytest.mark.parametrize("which", ["odd", "table"])
@pytest.mark.parametrize("min_docs,share", [(20, 0.05), (1, 0.0)])
def test_quality(spark, which, min_docs, share):
    docs = getattr(fx, which)(spark)
    data = [(r["doc_id"], r["text"] or "", r["source"]) for r in docs.collect()]
    norm = lambda x: re.sub("[\x20\x09-\x0d]+", " ", x).strip(" ").lower()
    holders, hosts = defaultdict(list), Counter(s for _, _, s in data)
    for i, t, s in data:
        for k in {norm(x) for x in t.split("\n") if WORD.search(x)}:
            holders[s, k].append(i)
    want = Counter()
    for i, t, s in data:
        b, gone = base(t), 0
        for x in t.split("\n"):
            h = holders.get((s, norm(x)), [])
            if len(h) > min_docs and len(h) > share * hosts[s] and min((y for y in h if y is not None), default=None) != i:
                gone += len(WORD.findall(x))
        want[(i, *b, not b[-1] and 100 * gone <= 50 * b[0])] += 1
    v = quality_rules.verdicts(docs, min_docs=min_docs, share=share)
    got = v.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
    assert Counter(tuple(r) for r in got.collect()) == want
    joined = quality_rules.verdicts(docs, min_docs=min_docs, share=share, host_lines=-1)
    assert Counter(map(tuple, joined.select(got.columns).collect())) == want
    clean = quality_rules.clean_documents(docs, min_docs=min_docs, share=share)
    assert clean.columns == docs.columns
    bag = lambda df: Counter((r["doc_id"], r["text"], r["n_chars"]) for r in df.collect())
    assert bag(clean) == bag(quality_rules.clean_documents(docs, min_docs=min_docs, share=share, host_lines=-1))
    assert Counter(r["doc_id"] for r in clean.collect()) == Counter(k[0] for k, n in want.items() for _ in range(n) if k[-1])


def test_quality_removes_shared_lines(spark):
    own = lambda i: "\n".join(" ".join(f"d{i}l{k}w{j}" for j in range(20)) for k in range(5))
    docs = [(i, own(i) + "\nSubscribe  to our letter now", "h") for i in range(40)]
    docs += [(i, "subscribe to our letter now\n" + "w " * 1 + "Subscribe to our letter now", "h") for i in range(40, 42)]
    df = spark.createDataFrame(docs, "doc_id long, text string, source string")
    out = {r["doc_id"]: r["text"] for r in quality_rules.clean_documents(df).collect()}
    assert sorted(out) == list(range(40))
    assert "Subscribe" in out[0] and all(out[i] == own(i) for i in range(1, 40))
    assert quality_rules.verdicts(fx.none(spark)).count() == 0 == quality_rules.clean_documents(fx.none(spark)).count()


@pytest.mark.parametrize("which", ["odd", "table"])
def test_mixing(spark, which):
    docs = getattr(fx, which)(spark)
    size, of = Counter(), defaultdict(int)
    for r in docs.collect():
        of[r["source"]] += len(WORD.findall(r["text"] or ""))
    order = sorted(of, key=lambda s: (s is None, (s or "").encode()))
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}
    target, free, left = {}, set(order), float(sum(of.values()))
    while True:  # reshare until none is above its cap
        total = sum(weight[s] for s in free)
        over = {s for s in free if left * weight[s] / total > 3 * of[s] + 1e-9} if total else set()
        if not over:
            target |= {s: left * weight[s] / total for s in free}
            break
        target |= {s: 3.0 * of[s] for s in over}
        left, free = left - sum(3 * of[s] for s in over), free - over
    got = rows(mixing.mix(docs))
    taken = Counter()
    for r in got:
        assert math.isclose(r["target"], target[r["source"]], rel_tol=1e-9, abs_tol=1e-6)
        assert 0 <= r["taken"] <= 3 * r["size"] and r["source_size"] == of[r["source"]]
        assert (r["position"] is None) == (r["taken"] == 0) and 0 <= (r["position"] or 0) <= 1
        taken[r["source"]] += r["taken"]
    assert all(abs(taken[s] - target[s]) <= 0.5 for s in order)
    assert got == rows(mixing.mix(docs.repartition(5)))
    spots = [r["position"] for r in got if r["position"] is not None]
    assert spots == sorted(spots)
    again = mixing.mixed_documents(docs)
    assert again.columns == docs.columns
    if which == "table":  # its ids are unique
        at = {r["doc_id"]: (r["position"], r["doc_id"]) for r in got}
        order = [r["doc_id"] for r in again.select("doc_id").collect()]
        firsts = [at[i] for i in dict.fromkeys(order)]
        assert firsts == sorted(firsts) and len(order) > len(firsts)
    assert mixing.mix(fx.none(spark)).count() == 0 == mixing.mixed_documents(fx.none(spark)).count()


def test_curriculum_is_inverse_of_integral(spark):
    for a in mixing.TILTS:
        df = spark.range(101).selectExpr("id / 100.0D AS y")
        from pyspark.sql import functions as F

        for r in df.select("y", mixing._position(F.col("y"), F.lit(a)).alias("t")).collect():
            assert math.isclose(r["t"] + a * (r["t"] ** 2 - r["t"]), r["y"], abs_tol=1e-9)


def plain_digests(turns):
    convs = defaultdict(list)
    for r in turns:
        convs[r["conv_id"]].append((r["turn"], r["role"] or "", r["text"] or ""))
    for c, ts in convs.items():
        ts.sort()
        said = "".join(f"{r}\n{t}\n" for _, r, t in ts)
        learnt = "".join(t for _, r, t in ts if r == "assistant")
        yield c, len(ts), hashlib.sha256(said.encode()).hexdigest(), len(learnt), hashlib.sha256(learnt.encode()).hexdigest()


def test_chat_query(spark):
    got = {r["conv_id"]: r for r in rows(chat_format.op2_chat_format(spark, fx.SF))}
    turns = rows(fx.table(spark, "conversations"))
    turns += [{"conv_id": -1, "turn": k, "role": r, "text": "</s>[INST] ok [/INST]"} for k, r in enumerate(("user", "assistant"))]
    want = {x[0]: x for x in plain_digests(turns)}
    assert set(got) == set(want)
    for c, r in got.items():
        assert (c, r["n_turns"], r["turns_sha256"], r["loss_chars"], r["loss_sha256"]) == want[c]


@pytest.mark.parametrize("budget,history", [(512, 96), (12, 5), (30, 0)])
def test_chat_windows(spark, budget, history):
    data = []
    for c in range(12):
        n = 0
        if c % 2:
            data.append((c, 0, "system", "be kind & <|end|> brief"))
            n = 1
        data += [(c, n + k, "user" if k % 2 == 0 else "assistant", " ".join(["&lt;", "<|turn|>", "[INST]", "w", "é𝄞"][j % 5] for j in range((7 * k + c) % 11))) for k in range(c)]
    data += [(90, 0, None, None), (90, 1, "assistant", ""), (90, 1, "assistant", ""), (None, 0, "user", "hi")]
    df = spark.createDataFrame(data, "conv_id long, turn long, role string, text string")
    w = chat_format.format_windows(df, budget, history)
    for r in rows(w):
        parts = r["formatted"].split("<|turn|>")[1:]
        assert "[" not in r["formatted"]
        assert r["n_tokens"] <= budget or len(parts) - r["n_context"] == 1
        if r["window"] and r["conv_id"] is not None and r["conv_id"] % 2 and r["conv_id"] < 90:
            assert parts[0].startswith("system<|text|>") and r["n_context"] >= 1
    got = {r["conv_id"]: r for r in rows(chat_format.read_windows(w))}
    want = {x[0]: x for x in plain_digests([dict(zip(("conv_id", "turn", "role", "text"), x)) for x in data])}
    assert set(got) == set(want)
    for c, r in got.items():
        said = "".join(f"{t['role']}\n{t['text']}\n" for t in r["turns"])
        learnt = "".join(r["loss"])
        assert (len(r["turns"]), hashlib.sha256(said.encode()).hexdigest(), len(learnt), hashlib.sha256(learnt.encode()).hexdigest()) == want[c][1:]
    assert chat_format.format_windows(df.limit(0)).count() == 0


def test_quality_limit_does_not_grow_with_the_host(spark):
    own = lambda i: "\n".join(" ".join(f"d{i}l{k}w{j}" for j in range(20)) for k in range(5))
    docs = [(i, own(i) + ("\nread more of this here" if i < 22 else ""), "hot") for i in range(600)]
    df = spark.createDataFrame(docs, "doc_id long, text string, source string")
    out = {r["doc_id"]: r["text"] for r in quality_rules.clean_documents(df).collect()}
    assert len(out) == 600 and all(out[i] == own(i) for i in range(1, 600)) and out[0] != own(0)
