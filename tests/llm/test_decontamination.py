import hashlib
import random
import re

from wdsum.llm import decontamination as D

WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words(t):
    return WORD.findall(bytes(c + 32 if 65 <= c <= 90 else c for c in (t or "").encode()))


def plain(docs, bench, n=13):
    windows = {}
    for item, t in bench:
        w = words(t)
        for s in range(max(len(w) - n + 1, 1) if w else 0):
            windows.setdefault(tuple(w[s : s + n]), set()).add(item)
    out = []
    for d, t in docs:
        w = words(t)
        hit, items = set(), set()
        for k in {len(x) for x in windows}:
            for s in range(len(w) - k + 1):
                if (x := tuple(w[s : s + k])) in windows:
                    hit.update(range(s, s + k))
                    items |= windows[x]
        ids = ",".join(sorted(i for i in items if i is not None))
        out.append((d, len(w), len(hit), len([i for i in items if i is not None]), hashlib.sha256(ids.encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    return sorted(out, key=repr)


def case(seed):
    rng = random.Random(seed)
    vocabulary = ["".join(rng.choices("abÉé1", k=rng.randint(1, 4))) for _ in range(60)]
    text = lambda k: "".join(w.upper() + rng.choice([" ", ", ", "\n", "--"]) if rng.random() < 0.2 and w.isascii() else w + " " for w in rng.choices(vocabulary, k=k))
    bench = [(i, text(rng.choice([0, 3, 12, 13, 14, 40]))) for i in range(25)] + [(90, None), (91, "")]
    docs = []
    for i in range(50):
        t = text(rng.randint(0, 40))
        for _ in range(rng.randint(0, 2)):
            w = rng.choice(bench)[1] or ""
            parts = w.split(" ")
            a = rng.randint(0, max(0, len(parts) - 14))
            t += " " + " ".join(parts[a : a + rng.choice([12, 13, 20])]) + " " + text(rng.randint(0, 300))
        docs.append((i, t))
    docs += [(100, None), (101, ""), (100, docs[3][1]), (3, docs[3][1]), (None, docs[4][1])]
    return docs, bench


def test_results_equal_brute_force(spark):
    for seed in range(2):
        docs, bench = case(seed)
        df = spark.createDataFrame([(*d, "x", 1) for d in docs], "doc_id long, text string, window string, start int").repartition(3)
        b = spark.createDataFrame([(*i, 0) for i in bench], "item_id long, text string, len int")
        got = sorted((tuple(r) for r in D.decontaminate(df, b).collect()), key=repr)
        assert got == plain(docs, [(str(i), t) for i, t in bench])


def test_without_broadcast_and_clean(spark, monkeypatch):
    docs, bench = case(7)
    monkeypatch.setattr(D, "BROADCAST_BYTES", 0)
    df = spark.createDataFrame([(*d, "x") for d in docs], "doc_id long, text string, window string")
    b = spark.createDataFrame(bench, "item_id long, text string")
    want = plain(docs, [(str(i), t) for i, t in bench])
    assert sorted((tuple(r) for r in D.decontaminate(df, b).collect()), key=repr) == want
    left = D.clean(df, b)
    assert left.columns == df.columns and left.count() == sum(not r[-1] for r in want)


def test_empty_tables(spark):
    df, b = spark.createDataFrame([(1, "a b")], "doc_id long, text string"), spark.createDataFrame([(1, "a b")], "item_id long, text string")
    assert D.decontaminate(df.limit(0), b).count() == 0
    assert [tuple(r)[:4] for r in D.decontaminate(df, b.limit(0)).collect()] == [(1, 2, 0, 0)]
    assert [tuple(r)[:4] for r in D.decontaminate(df, b).collect()] == [(1, 2, 2, 1)]
