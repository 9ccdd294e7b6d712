"""Operators 6 and 10 against the tokenizers library, text by text."""

import random
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from tests.llm import fixtures as fx
from trailmine.llm import packing, token_files, tokens


@pytest.fixture(scope="module")
def plain():
    t = Tokenizer.from_file(tokens.default_path())
    return lambda x: t.encode(x, add_special_tokens=False).ids


def test_chunks_are_exact(plain):
    rng = random.Random(1)
    letters = "abcXYZ'stredl019,.<|>&é É ÿÀ×ªµİΣſ́ßẞ \x1c\x0b \n\x85漢字😀"
    texts = ["<|endoftext|> x<|startoftext|>y", "", "ΟΔΟΣ don't I'LL 'Sx ½ ²"] + ["".join(rng.choices(letters, k=rng.randint(0, 60))) for _ in range(1500)]
    enc = tokens.ChunkEncoder(tokens.default_path(), keep=500)
    for k in range(0, len(texts), 200):
        ids, at = enc.encode(pa.array(texts[k : k + 200]))
        assert [ids[at[j] : at[j + 1]].tolist() for j in range(len(at) - 1)] == [plain(t) for t in texts[k : k + 200]]


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


@pytest.mark.parametrize("which,capacity", [("odd", 64), ("odd", 4096), ("table", 4096)])
def test_packing(spark, plain, which, capacity):
    docs = getattr(fx, which)(spark)
    want = []
    for i, t in fx.texts(docs):
        ids = [*plain(t), 1]
        want += [(i, n, s, len(ids[s : s + capacity]), crc(ids[s : s + capacity])) for n, s in enumerate(range(0, len(ids), capacity))]
    got = packing.pack_documents(docs, capacity=capacity).collect()
    key = lambda r: (r[0] is None, r[0] or 0, *r[1:])
    assert sorted((tuple(r)[:5] for r in got), key=key) == sorted(want, key=key)
    bins = defaultdict(list)
    for r in got:
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    for b in bins.values():
        b.sort()
        assert [o for o, _ in b] == [sum(n for _, n in b[:k]) for k in range(len(b))] and sum(n for _, n in b) <= capacity
    least = -(-sum(r[3] for r in want) // capacity)
    assert len(bins) <= least * 1.02 + 2
    assert packing.pack_documents(fx.none(spark)).count() == 0


def test_pack_is_tight():
    rng = np.random.default_rng(0)
    for sizes in (rng.lognormal(6.3, 1, 8000), rng.uniform(1, 4095, 4000), rng.uniform(1400, 2000, 3000), rng.uniform(300, 3000, 6000)):
        sizes = np.clip(sizes, 1, 4095).astype(int)
        seq, off = packing.pack(sizes)
        used = np.bincount(seq, sizes)
        assert used.max() <= 4096 and (used > 0).all()
        order, bins = np.sort(sizes)[::-1], []
        for s in order:  # best fit, decreasing
            fit = [k for k in range(len(bins)) if bins[k] >= s]
            if fit:
                k = min(fit, key=bins.__getitem__)
                bins[k] -= s
            else:
                bins.append(4096 - s)
        assert len(used) <= 1.02 * len(bins) + 2, (len(used), len(bins), sizes.sum() / 4096)


@pytest.mark.parametrize("which", ["odd", "table"])
def test_token_files(spark, plain, which, tmp_path):
    docs = getattr(fx, which)(spark)
    base = f"file://{tmp_path}/t"
    manifest = token_files.write_token_files(docs, base, file_tokens=3000)
    got = sorted(map(tuple, token_files.read_token_files(manifest, base).collect()), key=lambda r: r[1])
    lone = defaultdict(list)
    for i, t in fx.texts(docs):
        lone[i].append([*plain(t), 2])
    stream = []
    for i, start, n, c in got:
        assert start == len(stream)
        own = next(x for x in lone[i] if len(x) == n and crc(x) == c)
        lone[i].remove(own)
        stream += own
    assert not any(lone.values())
    assert [r[0] for r in got] == sorted((r[0] for r in got), key=lambda i: (i is not None, i))
    for i in random.Random(2).sample(range(len(stream)), 5):
        assert token_files.random_token(manifest, base, i) == stream[i]


def test_code_file_random_access():
    rng = np.random.default_rng(3)
    ids = np.concatenate([rng.integers(0, 2**k, 900) for k in (1, 8, 9, 16, 17, 31)]).astype(np.uint32)
    rng.shuffle(ids)
    f = token_files.CodeFile(token_files.write_codes(ids, np.array([1, 2]), np.array([0, 10, len(ids)])))
    assert (f.ids() == ids).all() and [f.token(i) for i in range(len(ids))] == ids.tolist()
    with pytest.raises(IndexError):
        f.token(len(ids))
    data, read = token_files.write_codes(np.tile(ids, 40), np.array([1, 2]), np.array([0, 10, 40 * len(ids)])), []
    g = token_files.CodeFile(lambda at, n: (read.append(n), data[at : at + n])[1])
    assert [g.token(i) for i in (0, 100_003, 40 * len(ids) - 1)] == [ids[i % len(ids)] for i in (0, 100_003, 40 * len(ids) - 1)]
    assert sum(read) < 2000 < len(data) // 100
    for a, b in ((0, 0), (511, 513), (1000, 5000)):
        assert (g.tokens(a, b) == np.tile(ids, 40)[a:b]).all()


def test_no_documents(spark, tmp_path):
    base = f"file://{tmp_path}/none"
    assert token_files.read_token_files(token_files.write_token_files(fx.none(spark), base), base).count() == 0
