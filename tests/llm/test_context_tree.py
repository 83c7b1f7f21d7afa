import math
import random
import re
import tracemalloc
from collections import Counter, defaultdict

import numpy as np
import pytest

from tests.llm.brute import crc
from wdsum.llm import context_tree as C

WORD = re.compile(rb"[^\x20\x09-\x0D]+")


def tokens(t):
    return [bytes(c + 32 if 65 <= c <= 90 else c for c in w) for w in WORD.findall((t or "").encode())]


class PlainTree:
    """The weighting by its definition, one bit and one dictionary at a time."""

    def __init__(self, texts, depth):
        self.depth = depth
        self.count = defaultdict(lambda: [0, 0])
        self.kids = defaultdict(set)
        for t in texts:
            for context, node, bit in self.bits(t):
                for d in range(depth + 1):
                    self.count[context[:d], node][bit] += 1
                    if d:
                        self.kids[context[: d - 1], node].add(context[:d])
        self.memo = {}

    def bits(self, t):
        past = [C.END] * self.depth
        for byte in b"".join(w + b" " for w in tokens(t)) + bytes([C.END]):
            node = 1
            for k in range(7, -1, -1):
                bit = byte >> k & 1
                yield tuple(past), node, bit
                node = node * 2 + bit
            past = [byte, *past[:-1]]

    def own(self, context, node):
        a, b = self.count.get((context, node), (0, 0))
        return math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.lgamma(a + b + 1) - math.log(math.pi)

    def deeper(self, context, node):
        return sum(self.weighted(c, node) for c in self.kids.get((context, node), ()))

    def weighted(self, context, node):
        if (context, node) not in self.memo:
            own = self.own(context, node)
            self.memo[context, node] = own if len(context) == self.depth else math.log(0.5 * math.exp(own) + 0.5 * math.exp(self.deeper(context, node)))
        return self.memo[context, node]

    def score(self, t):
        total = 0.0
        for context, node, bit in self.bits(t):
            p = None
            for d in range(self.depth, -1, -1):
                c = context[:d]
                n = self.count.get((c, node), (0, 0))
                kt = (n[bit] + 0.5) / (sum(n) + 1)
                if p is None:
                    p = kt
                else:
                    own, deeper = math.exp(self.own(c, node)), math.exp(self.deeper(c, node))
                    p = (own * kt + deeper * p) / (own + deeper)
            total += math.log10(p)
        return total


def texts(seed):
    rng = random.Random(seed)
    return [(i, "".join(rng.choices(["ab", "Ba ", "c ", "é\n", " "], k=rng.randint(0, 12)))) for i in range(40)] + [(77, None), (78, ""), (5, "again ab"), (None, "ab c")]


@pytest.mark.parametrize(("seed", "depth", "chunk"), [(0, 3, 1 << 20), (1, 2, 64), (2, 4, 64)])
def test_scores_equal_the_definition(spark, monkeypatch, seed, depth, chunk):
    if seed == 2:  # half of the pairs are split
        monkeypatch.setattr(C, "parts_of", lambda *a: np.random.default_rng(1).integers(1, 3, 1 << 16))
    docs = texts(seed)
    train = [t for d, t in docs if crc("" if d is None else d) % 7 != 2]
    tree = PlainTree(train, depth)
    count = Counter(w for t in train for w in [*tokens(t), None])
    n, v = sum(count.values()), len(count)
    df = spark.createDataFrame([(*d, 1) for d in docs], "doc_id long, text string, chunk int").repartition(3)
    rows = C.score_documents(df, depth=depth, chunk_bytes=chunk).collect()
    plain = [((d is not None, d or 0), sum(math.log10((count[x] + 1) / (n + v + 1)) for x in [*tokens(t), None])) for d, t in docs]
    for (i, x), (k, y) in zip(sorted(((r.doc_id is not None, r.doc_id or 0), r.base_score) for r in rows), sorted(plain), strict=True):
        assert i == k and x == pytest.approx(y, rel=1e-12)
    got = sorted((r.doc_id is not None, r.doc_id or 0, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6), round(r.score, 6), r.held_out) for r in rows)
    want = []
    for d, t in docs:
        w = [*tokens(t), None]
        want.append((d is not None, d or 0, len(w), sum(count[x] > 0 for x in w), n, round(sum(math.log10((count[x] + 1) / (n + v + 1)) for x in w), 6), round(tree.score(t), 6), crc("" if d is None else d) % 7 == 2))
    assert len(got) == len(want)
    for g, x in zip(got, sorted(want), strict=True):
        assert g == pytest.approx(x, abs=2e-6)


def test_probabilities_of_a_byte_sum_to_one():
    rng = np.random.default_rng(0)
    data = rng.integers(97, 100, 500).astype(np.uint8)
    keys = C.keys_of(data, np.array([0, 200, 500]), 3)
    tally = C.Tally()
    tally.add(keys)
    seen, counts = tally.all()
    context = keys[50] >> np.uint64(8) << np.uint64(8)
    every = np.union1d(seen, context + np.arange(256, dtype=np.uint64))
    n = np.zeros(len(every), np.int64)
    n[np.searchsorted(every, seen)] = counts
    tree = C.Subtree(every, n, 3)
    nodes, sums = tree.shallow()
    log10 = C.Shallow(nodes.astype(np.int64), sums).log10(every, tree.chance, 3)
    assert (10 ** log10[(every >> np.uint64(8) << np.uint64(8)) == context]).sum() == pytest.approx(1)


def test_packed_keys_and_log_gamma():
    keys = np.unique(np.random.default_rng(1).integers(0, 1 << 63, 1000).astype(np.uint64) * np.uint64(2))
    assert (C.unpack_keys(C.pack_keys(keys)) == keys).all() and len(C.unpack_keys(C.pack_keys(keys[:0]))) == 0
    x = np.array([0.5, 1, 2.5, 7.9, 8, 100.5, 1e9])
    assert C.log_gamma(x) == pytest.approx([math.lgamma(v) for v in x], rel=1e-12, abs=1e-12)
    assert (C.Lookup(keys)(keys[::-1]) == np.arange(len(keys))[::-1]).all()


def test_common_pairs_are_split(spark):
    df = spark.createDataFrame([(i, "aaab" * 20 + "xyz" * i) for i in range(30)], "doc_id long, text string")
    parts = C.parts_of(df, 1000, 100, 4)
    assert parts[ord("a") << 8 | ord("a")] > 1 and parts.sum() < (1 << 16) + 100
    assert (C.parts_of(df, 1000, 8, 4) == 1).all() and (C.parts_of(df.limit(0), 0, 100, 4) == 1).all()


def test_empty_table(spark):
    assert C.score_documents(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_asked_keys_take_bounded_memory():
    """Different keys of a chunk, in order, in a few times their own size."""
    rng = np.random.default_rng(1)
    parts = [rng.integers(0, 1 << 21, 1 << 17).astype(np.uint64) << np.uint64(32) for _ in range(40)]
    want = np.unique(np.concatenate(parts))
    deal = np.ones(1 << 16, np.int64)
    tracemalloc.start()
    held = C.Keys()
    for p in parts:
        held.add(p)
    rows = [(bucket, C.unpack_keys(raw)) for bucket, raw in C.packed_keys(held, C.GRAM, 64, C.DEPTH, deal)]
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert np.array_equal(np.sort(np.concatenate([k for _, k in rows])), want)
    assert all((C.bucket_of(C.GRAM, k, 64, C.DEPTH, deal) == b).all() for b, k in rows)
    assert peak < 9 * want.nbytes, peak / want.nbytes
