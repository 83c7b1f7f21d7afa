import base64
import hashlib
import random
import re

import numpy as np
import pytest

from wdsum.llm import fingerprints as P
from wdsum.llm import textkit

MASK = (1 << 64) - 1


def pieces(texts):
    raw = [t.encode() for t in texts]
    return P.digests(np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)]))


def plain_pieces(text):
    """The pieces of a text, numbered among equal ones, by plain numbers."""

    def mixed(x):
        x = (x ^ x >> 30) * 0xBF58476D1CE4E5B9 & MASK
        x = (x ^ x >> 27) * 0x94D049BB133111EB & MASK
        return x ^ x >> 31

    out, seen = set(), {}
    for line in text.encode().split(b"\n"):
        held = []
        found = re.findall(rb"[^\x20\x09-\x0D]+", line)
        for k, w in enumerate(found):
            held.append(w)
            code = sum(mixed((c + 1) * 0x9E3779B97F4A7C15 & MASK) * pow(textkit._BASE, i, 1 << 64) for i, c in enumerate(w))
            if mixed(code + len(w) * 0x9E3779B97F4A7C15 & MASK) % (1 << P.PIECE_BITS) == 0 or k == len(found) - 1:
                piece = tuple(held)
                seen[piece] = seen.get(piece, 0) + 1
                out.add((piece, seen[piece]))
                held = []
    return out


@pytest.mark.parametrize("seed", range(5))
def test_peeling_finds_the_differing_digests(seed):
    rng = random.Random(seed)
    lines = ["".join(rng.choices("abc ", k=30)) for _ in range(400)]
    a, b = rng.sample(lines, 200), rng.sample(lines, rng.choice([0, 1, 199, 300]))
    owner, d = pieces(["\n".join(a), "\n".join(b)])
    left, right = set(d[owner == 0].tolist()), set(d[owner == 1].tolist())
    cells = 16
    while True:
        s = [P.Sketches(1, cells).add(np.zeros((owner == k).sum(), np.int64), d[owner == k]) for k in (0, 1)]
        _, found, sign, done = s[0].minus(s[1]).peel()
        if done[0]:
            break
        cells *= 2
    assert set(found[sign == 1].tolist()) == left - right and set(found[sign == -1].tolist()) == right - left
    corpus = P.Corpus(owner, d, 2)
    for most in (2, 16, 1 << 20):
        assert corpus.differences(np.array([0]), np.array([1]), np.array([most])).tolist() == [len(left ^ right)]


def test_folding_equals_fewer_cells():
    rng = np.random.default_rng(1)
    d, text = rng.integers(0, 1 << 63, 500).astype(np.uint64), rng.integers(0, 7, 500)
    large = P.Sketches(7, 64).add(text, d)
    for cells in (2, 8, 64):
        small, folded = P.Sketches(7, cells).add(text, d), large.folded(cells)
        assert all((getattr(small, x) == getattr(folded, x)).all() for x in ("count", "total", "check"))


@pytest.mark.parametrize("buckets", [1, 3, 50])
def test_versions_over_a_table(spark, monkeypatch, buckets):
    monkeypatch.setattr(P, "ROWS_AT_ONCE", 7)
    rng = random.Random(buckets)
    docs = [(i * 13 % 211, " ".join(rng.choices(["ab", "cdé", "e\nf", "😀", *map(str, range(30))], k=rng.choice([0, 1, 5, 60, 900])))) for i in range(60)]
    docs += [(500, docs[0][1]), (None, "last one"), (501, None), (502, ""), (600, docs[5][1] + " one more"), (601, docs[5][1])]
    df = spark.createDataFrame([(*d, 1) for d in docs], "doc_id long, text string, doc int").repartition(4)
    got = {r.doc_id: r for r in P.fingerprint_versions(df, buckets=buckets).collect()}
    order = sorted(docs, key=lambda d: -(d[0] if d[0] is not None else -1))
    assert len(got) == len(docs)
    prints = {}
    for (i, t), (j, x) in zip(order, order[1:] + order[:1], strict=True):
        t, x = t or "", x or ""
        h = len(t) // 2
        e = t[: len(t) - h] + x[:h]
        r = got[i]
        assert (r.n_chars, r.edited_sha256) == (len(t), hashlib.sha256(e.encode()).hexdigest())
        assert prints.setdefault(t, r.fingerprint) == r.fingerprint and prints.setdefault(e, r.edited_fingerprint) == r.edited_fingerprint
        s = [plain_pieces(v) for v in (t, e, x)]
        for near, other in ((r.near_edited, s[1]), (r.near_next, s[2])):
            assert near == pytest.approx(len(s[0] & other) / len(s[0] | other) if s[0] | other else 1)
        # the fingerprints alone tell the same
        assert r.near_edited == pytest.approx(P.likeness(r.fingerprint, r.edited_fingerprint))
        assert r.near_next == pytest.approx(P.likeness(got[j].fingerprint, r.fingerprint))
        assert len(base64.b64decode(r.fingerprint)) <= 4 + 14 * max(6, 8 * len(s[0]))


def test_one_and_no_rows(spark):
    df = spark.createDataFrame([(7, "just one text")], "doc_id long, text string")
    assert [(r.doc_id, r.near_next) for r in P.fingerprint_versions(df).collect()] == [(7, 1.0)]
    assert P.fingerprint_versions(df.limit(0)).count() == 0


def test_many_empty_texts(spark):
    df = spark.createDataFrame([(i, "") for i in range(5000)], "doc_id long, text string").coalesce(1)
    rows = P.fingerprint_versions(df, buckets=1).collect()
    assert len(rows) == 5000 and len({r.fingerprint for r in rows}) == 1 and {r.near_next for r in rows} == {1.0}
