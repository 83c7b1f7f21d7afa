import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from tests.llm import brute
from tests.llm.test_windows import fixture
from wdsum.llm import decontamination, jaccard, suffixes


def plain_repeats(texts, least):
    """Maximal repeats by their definition."""
    at = {}
    for t, s in enumerate(texts):
        for i in range(len(s)):
            for j in range(i + least, len(s) + 1):
                at.setdefault(s[i:j], []).append((t, i))
    out = []
    for s, places in at.items():
        if len(places) > 1:
            before = {texts[t][i - 1] if i else (t, i) for t, i in places}
            after = {texts[t][i + len(s)] if i + len(s) < len(texts[t]) else (t, i) for t, i in places}
            if len(before) > 1 and len(after) > 1:
                out.append((s, sorted(places)))
    return sorted(out)


@pytest.mark.parametrize("seed", range(30))
def test_maximal_repeats_equal_their_definition(seed):
    rng = random.Random(seed)
    texts = [bytes(rng.choices(b"ab\x00\xff"[: rng.randint(1, 4)], k=rng.randint(0, 40))) for _ in range(rng.randint(0, 4))]
    least = rng.randint(1, 6)
    assert sorted(suffixes.repeats_in(texts, least)) == plain_repeats(texts, least)


def test_suffix_order_and_prefixes():
    rng = random.Random(3)
    texts = [bytes(rng.choices(b"ab", k=200)) for _ in range(5)]
    offsets = np.cumsum([0, *map(len, texts)])
    a = suffixes.SuffixArray(np.frombuffer(b"".join(texts), np.uint8), offsets)
    suffix = [texts[t][p - offsets[t] :] for p in a.order for t in [int(np.searchsorted(offsets, p, "right")) - 1]]
    assert suffix == sorted(suffix)
    for i in range(1, len(suffix)):
        x, y = suffix[i - 1], suffix[i]
        n = next((k for k in range(min(len(x), len(y))) if x[k] != y[k]), min(len(x), len(y)))
        assert a.lcp[i] == n


@pytest.mark.parametrize(("seed", "group", "batch"), [(0, 1024, 1 << 20), (1, 2, 500), (2, 5, 2000)])
def test_removal_equals_brute_force(spark, monkeypatch, seed, group, batch):
    docs = fixture(seed, count=40)
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    monkeypatch.setattr(suffixes, "GROUP", group)
    monkeypatch.setattr(suffixes, "BATCH_BYTES", batch)
    monkeypatch.setattr(suffixes.partial_repeats, "__defaults__", ((5, 1), group))
    for n, passage, k in ((40, 24, 9), (40, 40, 16)):
        rows = suffixes.remove_repeats(df, n, passage, k).collect()
        assert sorted((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in rows) == sorted(brute.byte_windows(docs, n))
        if passage < n:
            assert sorted((r.doc_id, r.n_bytes, r.passage_bytes, r.n_passages) for r in rows) == sorted(x[:4] for x in brute.byte_windows(docs, passage))


@pytest.mark.parametrize("seed", range(20))
def test_longest_repeats_of_the_places_that_count(seed):
    rng = random.Random(seed)
    texts = [bytes(rng.choices(b"ab", k=rng.randint(1, 60))) for _ in range(rng.randint(1, 5))]
    last, n = [rng.randint(0, len(t) - 1) for t in texts], rng.randint(1, 5)
    offsets = np.cumsum([0, *map(len, texts)])
    place, length = suffixes.longest(np.frombuffer(b"".join(texts), np.uint8), offsets, np.array(last), n)
    cover = lambda spans: {(t, p) for t, a, e in spans for p in range(a, e)}
    starts = [(t, i) for t, x in enumerate(texts) for i in range(last[t] + 1)]
    common = lambda x, y: next((k for k in range(min(len(x), len(y))) if x[k] != y[k]), min(len(x), len(y)))
    best = {(t, i): max([common(texts[t][i:], texts[u][j:]) for u, j in starts if (u, j) != (t, i)], default=0) for t, i in starts}
    for far in (n, n + 3):
        got = [(t, a, e) for some in [length >= far] for t, a, e in zip(*suffixes._spans(place[some], place[some] + length[some], offsets), strict=True)]
        assert cover(got) == cover([(t, i, i + x) for (t, i), x in best.items() if x >= far])


def test_edges(spark):
    assert suffixes.remove_repeats(spark.createDataFrame([], "doc_id long, text string, span long")).count() == 0
    long = "".join(chr(97 + i * i % 23) + str(i) for i in range(400))
    df = spark.createDataFrame([(None, long), (1, "x" + long), (2, None), (2, ""), (3, "a" * 401), (4, "b" * 400)], "doc_id long, text string")
    got = sorted((r.doc_id or 0, r.n_bytes, r.n_removed, r.passage_bytes) for r in suffixes.remove_repeats(df).collect())
    n = len(long)
    assert got == [(0, n, n, n), (1, n + 1, n, n), (2, 0, 0, 0), (2, 0, 0, 0), (3, 401, 401, 401), (4, 400, 0, 400)]


def test_columns_of_any_name_stay(spark):
    names = ["doc", "TAG", "spans", "_doc", "_tag", "_spans", "some", "_some", "id", "_id", "hash", "_hash", "text_", "window"]
    long = "".join(chr(97 + i * i % 23) + str(i) for i in range(400))
    df = spark.createDataFrame([(i, t, *names) for i, t in enumerate([long, "x" + long, None, "", "short text of a few words"])], "doc_id long, text string, " + ", ".join(f"`{x}` string" for x in names))
    bench = spark.createDataFrame([(1, "of a few words", "x")], "item_id long, text string, _id string")
    for out in (suffixes.cut_repeats(df, 240, 80), jaccard.keep_one(df), decontamination.clean(df, bench)):
        rows = out.collect()
        assert out.columns == df.columns and rows and all(list(r)[2:] == names for r in rows)


def test_a_text_of_more_than_16_mib(spark):
    rng = random.Random(8)
    long = rng.randbytes(1 << 23).hex() + "z" * 100  # 2**24 + 100 bytes
    df = spark.createDataFrame([(1, long), (2, "y" + long[-1100:])], "doc_id long, text string")
    got = sorted((r.doc_id, r.n_bytes, r.n_removed, r.n_spans) for r in suffixes.remove_repeats(df).collect())
    assert got == [(1, (1 << 24) + 100, 1100, 1), (2, 1101, 1100, 1)]


def test_sub_cells_meet_their_count_once(spark, monkeypatch):
    """Of equal sub-cells one goes on with its bytes; no join makes more rows than there are places that recur."""
    rows = [(7, d, 0, 5, 4, bytes([65 + d % 3] * 20)) for d in range(30)] + [(7, 99, 0, 0, 4, b"unlike any other ....")]
    df = spark.createDataFrame(rows, suffixes._CONTEXT)
    monkeypatch.setattr(suffixes, "_narrower", lambda contexts, *_: contexts)
    sent = []
    monkeypatch.setattr(suffixes, "_array_spans", lambda contexts, n, far: sent.append(contexts) or contexts.limit(0).select("doc", "tag", F.lit(0).cast("long").alias("span")))
    found = suffixes.partial_repeats(df, 17, 17, (1,), 8)
    assert "Inner" not in "".join(x for x in found._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Join" in x)
    spans = {(r.doc, r.span >> 32, r.span & 0xFFFFFFFF) for r in found.collect()}
    assert spans >= {(d, 5, 25) for d in range(30)} and not any(d == 99 and e - a > 17 for d, a, e in spans)
