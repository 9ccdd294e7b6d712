"""Operators 1, 4 and 7 against plain Python."""

import hashlib
import math
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from tests.llm import fixtures as fx
from trailmine.llm import neural_lm, toxicity, warc


@pytest.mark.parametrize("which", ["odd", "table"])
def test_warc(spark, which, tmp_path):
    if which == "table":
        pages = fx.table(spark, "pages")
    else:
        long = "é" * 60
        data = [(1, "http://a.b.org/x?q=1#f", long), (5, "http://a.b.org/x?q=1", long), (3, None, long), (2, "weird url\r\nX: y", "short"), (4, "http://b.org", "short"),
                (6, "http://é.org/ü", None), (None, "http://a.b.org/", long), (1, "http://a.b.org/again", long), (7, "HTTP://B.Org:80/", "x" * 300000)]
        pages = spark.createDataFrame([(*r, 9) for r in data], "page_id long, url string, html string, digest int")
    base = f"file://{tmp_path}/w"
    rows = [(r["page_id"], r["url"] or "", (r["html"] or "").encode()) for r in pages.collect()]
    first = {}
    for p, _, h in rows:
        if p is not None and len(h) >= 100:
            first[h] = min(p, first.get(h, p))
    want = Counter()
    for p, u, h in rows:
        to = first.get(h) if first.get(h) != p else None
        want[(p, u, len(h), hashlib.sha256(h).hexdigest(), "response" if to is None else "revisit", to)] += 1
    entries = warc.write_archives(pages, base, file_bytes=20_000)
    directory = warc.write_index(entries, base, block_entries=4)
    assert Counter(map(tuple, warc.look_up(entries.select("key"), directory, base).collect())) == want
    index = warc.CaptureIndex(directory, base)
    for u in {u for _, u, _ in rows[:40]}:
        got = index.lookup(u)
        assert Counter(r["page_id"] for r in got) == Counter(p for p, v, _ in rows if warc.url_key(v) == warc.url_key(u))
        assert Counter((r["page_id"], r["payload"]) for r in got) == Counter((p, h) for p, v, h in rows if warc.url_key(v) == warc.url_key(u))
    assert index.lookup("http://nowhere.invalid/") == []
    none = warc.write_archives(pages.limit(0), base)
    assert warc.look_up(none.select("key"), warc.write_index(none, base), base).count() == 0


def test_url_keys_sort_by_reversed_host():
    assert warc.url_key("https://m.b.example.org/x?y=1#z") == "org,example,b,m)/x?y=1"
    assert warc.url_key("http://A.com:8080") == "com,a:8080)/"
    assert warc.url_key("") == "" and warc.url_key("http://[bad") == "http://[bad"


def test_noisy_or_learns_sentences():
    rng = np.random.default_rng(0)
    good, bad = [f"good{i}" for i in range(200)], ["vile", "rotten"]
    texts, labels = [], []
    for k in range(400):
        s = [" ".join(rng.choice(good, 8)) for _ in range(6)]
        if k % 4 == 0:
            s[k % 6] += " " + bad[k % 2]
        texts.append(". ".join(s))
        labels.append(int(k % 4 == 0))
    model = toxicity.fit(texts, np.array(labels))
    parts, z, bounds = toxicity.sentence_logits(pa.array(["good1 good2. you vile thing! good3", "good4. good5", ""]), model)
    assert (z > 0).tolist() == [False, True, False, False, False, False]
    assert toxicity.fit([], np.array([]))["bias"] < 0


def test_toxicity_query(spark):
    got = {r["doc_id"]: r for r in toxicity.op4_toxicity(spark, "/root/testdata/sf0.01").collect()}
    labels = {r["doc_id"]: r["toxic"] for r in fx.table(spark, "labels", "/root/testdata/sf0.01").collect()}
    assert len(got) == fx.table(spark, sf="/root/testdata/sf0.01").count()
    held = []
    for i, r in got.items():
        assert r["held_out"] == (zlib.crc32(str(i).encode()) % 5 == 0) and 0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.5)
        if r["held_out"] and i in labels:
            held.append((r["score"], labels[i]))
    pos, neg = [s for s, y in held if y], [s for s, y in held if not y]
    assert np.mean([[(p > n) + 0.5 * (p == n) for n in neg] for p in pos]) > 0.85
    model = {"bias": -5.0, "words": {"vile": 9.0}}
    odd = fx.odd(spark).collect()
    assert toxicity.score_documents(fx.odd(spark), model).count() == len(odd)
    some = spark.createDataFrame([(1, "all fine. a vile end\nok"), (2, None)], "doc_id long, text string")
    assert [tuple(r)[:3] for r in toxicity.offending_sentences(some, model).collect()] == [(1, 1, " a vile end")]
    assert toxicity.score_documents(fx.none(spark), model).count() == 0


def plain_words(text):
    return text.encode().lower().split()


@pytest.mark.parametrize("which,vocab,head", [("odd", 3, 5), ("table", 50, 400), ("table", 1022, 1 << 18)])
def test_lm(spark, which, vocab, head):
    docs = getattr(fx, which)(spark)
    texts = fx.texts(docs)
    held = lambda i: zlib.crc32(b"" if i is None else str(i).encode()) % 7 == 2
    c, ends = Counter(), 0
    for i, t in texts:
        if not held(i):
            c.update(plain_words(t))
            ends += 1
    n, v = sum(c.values()) + ends, len(c) + 1
    got = neural_lm.score_documents(docs, vocab=vocab, head_size=head).collect()
    want = Counter()
    for i, t in texts:
        w = plain_words(t)
        base = sum(math.log10((c[x] + 1) / (n + v + 1)) for x in w) + math.log10((ends + 1) / (n + v + 1))
        want[(i, held(i), len(w) + 1, sum(c[x] > 0 for x in w) + 1, n, round(base, 4))] += 1
    assert Counter((r["doc_id"], r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 4)) for r in got) == want
    assert all(r["score"] <= 0 for r in got)
    if head > 1000:
        rest = [r for r in got if r["held_out"]]
        assert sum(r["score"] for r in rest) > sum(r["base_score"] for r in rest)
    assert neural_lm.score_documents(fx.none(spark)).count() == 0


def test_lm_is_normalised_and_learns_order():
    rng = np.random.default_rng(1)
    pairs = np.zeros((6, 6))
    for q in range(6):
        pairs[q, (q + 1) % 6] += 900
        pairs[q, rng.integers(0, 6)] += 100
    table = neural_lm.log_table(neural_lm.train(pairs, dims=6, steps=400))
    assert np.allclose((10.0**table).sum(1), 1, atol=1e-4)
    assert all(table[q].argmax() == (q + 1) % 6 for q in range(6))


def test_toxicity_sample_keeps_the_share_of_labels(spark):
    docs = spark.createDataFrame([(i, "bad words" if i % 9 == 0 else "good words") for i in range(3000)], "doc_id long, text string")
    labels = docs.selectExpr("doc_id", "cast(doc_id % 9 = 0 AS int) AS toxic", "1 AS quality")
    _, y, every = toxicity.training_sample(docs, labels)
    for sample in (20, 100, 1000):
        texts, labels_of, weights = toxicity.training_sample(docs, labels, sample=sample)
        assert max(np.bincount(labels_of)) <= sample
        assert weights @ labels_of / weights.sum() == pytest.approx(y.mean()) and weights.sum() == pytest.approx(len(y))
    assert (every == 1).all()
    # no word tells: the score is the prior, not the sample's share
    flat = toxicity.fit(["same"] * 200, np.repeat([1, 0], 100), np.repeat([1.0, 9.0], 100))
    _, z, _ = toxicity.sentence_logits(pa.array(["other"]), flat)
    assert 1 / (1 + np.exp(-z[0])) < 0.3
