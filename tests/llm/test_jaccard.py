import random
import re

import numpy as np
import pytest

from wdsum.llm import graph, jaccard

WORD = re.compile(rb"[^\x20\x09-\x0D]+")


def plain_set(t):
    w = [bytes(c + 32 if 65 <= c <= 90 else c for c in x) for x in WORD.findall((t or "").encode())]
    return frozenset([tuple(w)] if 0 < len(w) < 5 else [tuple(w[i : i + 5]) for i in range(len(w) - 4)])


def plain(docs):
    sets = [plain_set(t) for _, t in docs]
    n = len(docs)
    linked = [[j for j in range(n) if j != i and sets[i] and sets[j] and 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j])] for i in range(n)]
    out = []
    for i in range(n):
        seen, todo = {i}, [i]
        while todo:
            for j in linked[todo.pop()]:
                if j not in seen:
                    seen.add(j)
                    todo.append(j)
        key = lambda j: docs[j][0] if docs[j][0] is not None else -1
        first, copy = min(map(key, seen)), min(key(j) for j in range(n) if j == i or sets[i] and sets[j] == sets[i])
        out.append((docs[i][0], None if first == -1 else first, None if copy == -1 else copy, len(linked[i])))
    return sorted(out, key=repr)


def corpus(seed, groups=25):
    rng = random.Random(seed)
    vocabulary = ["".join(rng.choices("abcdé", k=5)) for _ in range(3000)]
    line = " ".join(rng.choices(vocabulary, k=30))
    docs = []
    for _ in range(groups):
        base = rng.choices(vocabulary, k=rng.choice([1, 4, 5, 6, 40, 200]))
        for _ in range(rng.choice([1, 2, 3, 12])):
            w = list(base)
            for _ in range(rng.randint(0, max(1, len(w) // 30))):
                w[rng.randrange(len(w))] = rng.choice(vocabulary)
            docs.append(" ".join(w).upper() if rng.random() < 0.1 else " ".join(w))
    docs += [line + " " + " ".join(rng.choices(vocabulary, k=30)) for _ in range(60)]
    return [(i * 3 % 1009, t) for i, t in enumerate(docs)] + [(2000, None), (2001, " \n"), (None, docs[0]), (2002, docs[1]), (2002, docs[1])]


@pytest.mark.parametrize("small", [False, True])
def test_classes_and_links_equal_brute_force(spark, monkeypatch, small):
    if small:
        monkeypatch.setattr(jaccard, "BUCKET", 4)
        monkeypatch.setattr(jaccard, "BLOCK_SETS", 5)
        monkeypatch.setattr(jaccard, "HELD_BLOCKS", 2)
        monkeypatch.setattr(jaccard, "TOGETHER", 7)
    docs = corpus(11)
    df = spark.createDataFrame([(*d, 1, 2, 3) for d in docs], "doc_id long, text string, node int, _Doc int, tag int").repartition(3)
    assert sorted((tuple(r) for r in jaccard.near_duplicates(df).collect()), key=repr) == plain(docs)
    if not small:
        kept = jaccard.keep_one(df)
        assert kept.columns == df.columns
        want = {r[1] for r in plain(docs)}
        rows = kept.collect()
        assert len(rows) == len(want) and {r.doc_id for r in rows} == want


def test_components(spark):
    rng = random.Random(2)
    edges = [(i, i + 1) for i in range(30)] + [(500, 500 + i) for i in range(1, 50)] + [(rng.randint(1000, 1100), rng.randint(1000, 1100)) for _ in range(70)] + [(3000, 3000), (None, 1)]
    got = {r.node: r.root for r in graph.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    parent = {}
    find = lambda x: x if parent.setdefault(x, x) == x else find(parent[x])
    for a, b in edges:
        if a is not None:
            parent[find(a)] = find(b)
    assert got.keys() == parent.keys()
    pairs = {(find(n), r) for n, r in got.items()}
    assert len(pairs) == len({a for a, _ in pairs}) == len({b for _, b in pairs})


def test_empty_and_single(spark):
    df = spark.createDataFrame([(4, "one text of six words here")], "doc_id long, text string")
    assert [tuple(r) for r in jaccard.near_duplicates(df).collect()] == [(4, 4, 4, 0)]
    assert jaccard.near_duplicates(df.limit(0)).count() == 0
    assert jaccard.keep_one(df.limit(0)).count() == 0


def test_every_split_has_orders_of_its_own():
    steps = range(len(jaccard.FORKS))
    branches = np.cumprod(jaccard.FORKS)
    used = [jaccard.order_of(r, s, b, k) for r in range(jaccard.RUNS) for s in steps for b in range(branches[s]) for k in range(jaccard.LOOKS[s])]
    assert sorted(used) == list(range(jaccard.ORDERS)) and len(set(jaccard._ORDERS.tolist())) == jaccard.ORDERS
    assert all(1 - (1 - jaccard.meet(0.8, s + 1)) ** jaccard.RUNS >= jaccard.RECALL for s in steps)


def test_labels_are_the_least_of_a_component():
    rng = np.random.default_rng(3)
    for n, m, share in ((1, 1, 0.5), (30, 20, 0.04), (40, 60, 0.01), (5, 9, 0.0)):
        linked = rng.random((n, m)) < share
        whole = np.zeros((n + m, n + m), bool)
        whole[:n, n:], whole[n:, :n] = linked, linked.T
        label = jaccard.labels(whole)
        assert all(label[i] == label[j] for i, j in zip(*np.nonzero(whole), strict=True)) and (label <= np.arange(n + m)).all()
        left, right = jaccard.side_labels(linked)
        alone = ~linked.any(axis=1)
        assert (left[~alone] == label[:n][~alone]).all() and (left[alone] == -1).all()
        assert (right[linked.any(axis=0)] == label[n:][linked.any(axis=0)]).all()


def test_threshold_pairs_meet_through_all_splits(spark, monkeypatch):
    monkeypatch.setattr(jaccard, "BUCKET", 1)  # no bucket of a pair is small, so all take every split
    pairs = 3000
    rng = random.Random(5)
    word = lambda: "%09x" % rng.getrandbits(36)
    docs = []
    for i in range(pairs):
        core = " ".join(word() for _ in range(44))  # 40 shingles of 50 in common
        docs += [(2 * i + j, " ".join([core, *(word() for _ in range(5))])) for j in (0, 1)]
    assert len(plain_set(docs[0][1]) & plain_set(docs[1][1])) * 5 == 4 * len(plain_set(docs[0][1]) | plain_set(docs[1][1]))
    sets = jaccard.shingle_sets(spark.createDataFrame([(i, 0, t) for i, t in docs], "doc long, tag int, text string").repartition(4)).cache()
    root = {r.node: r.root for r in graph.components(jaccard.candidates(sets)).collect()}
    node = {r.doc: r.node for r in sets.select("doc", "node").collect()}
    met = sum(node[2 * i] in root and root[node[2 * i]] == root.get(node[2 * i + 1]) for i in range(pairs))
    assert met >= pairs - 2
