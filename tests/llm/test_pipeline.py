"""The pipeline, stage by stage."""

import hashlib
import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from tests.llm import fixtures as fx
from tests.llm.test_native import WORD, base
from tests.llm.test_simhash import close, find, slow_fingerprint
from trailmine.llm import exact_dedup, mixing, packing, quality_rules, simhash, tokens
from trailmine.llm.common import materialize


def test_stages(spark):
    docs = fx.table(spark)
    names, counts = docs.columns, []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        was, docs = docs, materialize(stage(spark, docs, fx.SF), name)
        assert docs.columns == names and docs.dtypes == was.dtypes
        assert docs.join(was, "doc_id", "left_anti").count() == 0
        counts.append(docs.count())
        if name == "quality_rules":
            assert docs.count() == quality_rules.verdicts(was).where("kept").count()
            assert docs.where(F.length("text") != F.col("n_chars")).count() <= was.where(F.length("text") != F.col("n_chars")).count()
        if name == "curriculum_mixing":
            plan = {r["doc_id"]: r for r in mixing.mix(was).collect()}
            copies = Counter(r["doc_id"] for r in docs.collect())
            assert all(abs(copies[i] * r["size"] - r["taken"]) <= r["size"] / 2 for i, r in plan.items())
    assert counts[0] >= counts[1] >= counts[2] > 0
    out = corpus_pipeline.STAGES[-1][1](spark, docs, fx.SF)
    assert out.where("piece = 0").count() == counts[-1]
    assert out.groupBy("sequence_id").agg(F.sum("length").alias("n")).where("n > 4096").count() == 0


def test_rows_without_an_id_or_with_the_same_are_decided_alone(spark):
    own = lambda i: " ".join(f"d{i}w{j}" for j in range(80))
    rows = [(1, own(1)), (None, own(1)), (None, own(2)), (None, own(3)), (None, "bad"), (5, own(5)), (5, "worse"), (9, own(9)), (5, own(1)), (5, own(6))]
    docs = spark.createDataFrame([(i, t, "h") for i, t in rows], "doc_id long, text string, source string")
    bag = lambda df: Counter((r["doc_id"], r["text"]) for r in df.collect())
    good = [r for r in rows if r[1] not in ("bad", "worse")]
    assert bag(quality_rules.clean_documents(docs)) == Counter(good) == bag(quality_rules.clean_documents(docs, host_lines=-1))
    assert bag(simhash.drop_near_duplicates(docs.where("length(text) > 9"))) == Counter(r for r in good if r not in ((None, own(1)), (5, own(1))))


def plain_quality(rows):
    """(id, text, source) of what the quality stage keeps."""
    norm = lambda x: re.sub("[\x20\x09-\x0d]+", " ", x).strip(" ").lower()
    holders, out = defaultdict(list), []
    for i, t, s in rows:
        for k in {norm(x) for x in (t or "").split("\n") if WORD.search(x)}:
            holders[s, k].append(i)
    first = {k: min((i for i in v if i is not None), default=None) for k, v in holders.items() if len(v) > 20}
    for i, t, s in rows:
        gone = [x for x in (t or "").split("\n") if (s, norm(x)) in first and first[s, norm(x)] != i]
        b = base(t or "")
        if not b[-1] and 100 * sum(len(WORD.findall(x)) for x in gone) <= 50 * b[0]:
            out.append((i, "\n".join(x for x in t.split("\n") if x not in gone), s))
    return out


def plain_exact(rows):
    best = {}
    for r in rows:
        k = re.sub("[\x20\x09-\x0d]", "", r[1])
        best[k] = min(best.get(k, r), r, key=lambda x: (-len(x[1]), x[0]))
    return list(best.values())


def plain_near(rows):
    fp = {r: slow_fingerprint(r[1]) for r in rows}
    root, least = find(set(fp.values()), close(sorted(set(fp.values())))), {}
    for r, f in fp.items():
        least[root[f]] = min(least.get(root[f], r), r, key=lambda x: x[0])
    return list(least.values())


def plain_mix(rows):
    """(position, id, reading) in order."""
    size = {r: len(WORD.findall(r[1])) for r in rows}
    of = Counter()
    for r in rows:
        of[r[2]] += size[r]
    order = sorted(of, key=lambda s: (s is None, (s or "").encode()))
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}
    tilt = {s: (-0.5, 0.0, 0.5)[k % 3] for k, s in enumerate(order)}
    target, free, left = {}, set(order), float(sum(of.values()))
    while free:
        share = left / sum(weight[s] for s in free)
        over = {s for s in free if share * weight[s] > 3 * of[s] + 1e-9}
        target |= {s: 3.0 * of[s] for s in over} if over else {s: share * weight[s] for s in free}
        left, free = left - sum(3 * of[s] for s in over), free - over if over else set()
    out = []
    for s in order:
        total, cum = round(target[s]), 0
        for r in sorted((r for r in rows if r[2] == s), key=lambda r: hashlib.md5(str(r[0]).encode()).hexdigest()):
            n = size[r]
            taken = total // of[s] * n + min(max(total % of[s] - cum, 0), n)
            for k in range(math.floor(taken / n + 0.5) if n else 0):
                y, a = min(1.0, (k * of[s] + cum) / total), tilt[s]
                out.append((y if a == 0 else (math.sqrt((1 - a) ** 2 + 4 * a * y) - (1 - a)) / (2 * a), r[0], k))
            cum += n
    return sorted(out)


def test_pipeline_against_plain_python(spark):
    rows = [(r["doc_id"], r["text"], r["source"]) for r in fx.table(spark).collect()]
    rows += [(90_000 + k, f"{rows[k][1]}\nShared notice of this host" if rows[k][1] else None, "host") for k in range(40)]
    docs = fx.table(spark).select("doc_id", "text", "source").unionByName(spark.createDataFrame(rows[-40:], "doc_id long, text string, source string"))
    steps = [(quality_rules.clean_documents, plain_quality), (exact_dedup.drop_duplicates, plain_exact), (simhash.drop_near_duplicates, plain_near)]
    for stage, plain in steps:
        docs, rows = materialize(stage(docs), "stage"), plain(rows)
        assert Counter(map(tuple, docs.collect())) == Counter(rows)
    plan = plain_mix(rows)
    mixed = [r["doc_id"] for r in mixing.mixed_documents(docs).collect()]
    assert mixed == [i for _, i, _ in plan]
    text, enc = {r[0]: r[1] for r in rows}, Tokenizer.from_file(tokens.default_path())
    want = Counter()
    for _, i, _ in plan:
        ids = [*enc.encode(text[i], add_special_tokens=False).ids, 1]
        want.update((i, n, s, len(ids[s : s + 4096]), zlib.crc32(np.array(ids[s : s + 4096], "<u4").tobytes())) for n, s in enumerate(range(0, len(ids), 4096)))
    got = packing.pack_documents(materialize(mixing.mixed_documents(docs), "mixed")).collect()
    assert Counter(tuple(r)[:5] for r in got) == want
    bins = defaultdict(list)
    for r in got:
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    assert all(sum(n for _, n in b) <= 4096 and sorted(b)[0][0] == 0 for b in bins.values())


def test_pipeline_on_odd_and_no_rows(spark):
    for docs in (fx.odd(spark), fx.none(spark)):
        names = docs.columns
        for name, stage in corpus_pipeline.STAGES[:-1]:
            docs = materialize(stage(spark, docs, fx.SF), name)
            assert docs.columns == names
        corpus_pipeline.STAGES[-1][1](spark, docs, fx.SF).collect()


def test_clashing_names(spark):
    """Columns with the names that the operators use themselves are carried."""
    own = lambda i: " ".join(f"d{i}w{j}" for j in range(80))
    names = ["row", "id", "uid", "host", "key", "keys", "removed", "kept", "__h", "__keys", "__id", "__d", "__digest", "__rank", "__best", "__size", "__nth", "__src", "__key", "size", "cum", "slice", "nth", "at", "total", "fp", "best", "digest", "component_id", "file", "task", "a b.c"]
    rows = [(i, own(i % 7), "s", *(f"{n}{i}" for n in names)) for i in range(9)]
    docs = spark.createDataFrame(rows, ", ".join(f"`{n}` {t}" for n, t in [("doc_id", "long"), ("text", "string"), ("source", "string"), *((n, "string") for n in names)]))
    for stage, n in ((quality_rules.clean_documents, 9), (exact_dedup.drop_duplicates, 7), (simhash.drop_near_duplicates, 7), (mixing.mixed_documents, 9)):
        got = stage(docs).collect()
        assert len(got) == n and all(tuple(r) in rows for r in got)
    assert len(quality_rules.clean_documents(docs, host_lines=-1).collect()) == 9
    assert len(mixing.mixed_documents(docs, most_starts=0).collect()) == 9
    assert packing.pack_documents(docs).where("piece = 0").count() == 9


def test_mixing_ways_agree(spark):
    """Beginnings by broadcast against the join by key, with repeated ids and without ids."""
    docs = fx.table(spark).select("doc_id", "text", "source")
    docs = docs.unionByName(docs.limit(30)).unionByName(docs.limit(30)).unionByName(docs.limit(20).selectExpr("cast(null AS long) AS doc_id", "text", "source"))
    a, b = ([tuple(r) for r in mixing.mixed_documents(docs, **k).collect()] for k in ({}, {"most_starts": 0}))
    assert Counter(a) == Counter(b) and len(a) > 150
    taken = Counter(), Counter()
    for x, t in zip((a, b), taken, strict=True):
        for _, text, source in x:
            t[source] += len(WORD.findall(text or ""))
    assert taken[0] == taken[1]


def test_packing_keeps_the_order(spark, tmp_path):
    spark.range(3000).repartitionByRange(6, "id").selectExpr("id AS doc_id", "repeat('word ', cast(50 + id % 90 AS int)) AS text").write.parquet(f"{tmp_path}/d")
    pieces = materialize(packing.token_pieces(spark.read.parquet(f"{tmp_path}/d"), tokens.default_path()), "pieces")
    got = packing.pack_pieces(pieces, shard_pieces=300).groupBy(F.shiftright("sequence_id", 36).alias("shard")).agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).orderBy("shard").collect()
    assert len(got) >= 8 and all(a["hi"] < b["lo"] for a, b in zip(got, got[1:], strict=False))


def test_workers_give_back_free_memory():
    """A worker that waits beside the next stage holds no memory that its last task has freed."""
    import re

    import pyarrow as pa

    from trailmine.llm.common import trimmed

    def held() -> float:
        with open("/proc/self/smaps_rollup") as f:
            return sum(map(int, re.findall(r"\nPss_Anon:\s+(\d+)", f.read()))) / 1024

    def run(batches):
        for b in batches:
            some = [pa.array([k] * 2000, pa.int64()) for k in range(10_000)]
            yield pa.RecordBatch.from_arrays([pa.array([len(some)])], names=["n"])

    before, most, got = held(), 0, 0
    for b in trimmed(run)([None, None]):
        got, most = got + b["n"][0].as_py(), max(most, held())
    assert got == 20_000 and most - before > 100 and held() - before < (most - before) / 4
