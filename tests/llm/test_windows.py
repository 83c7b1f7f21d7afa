import random

import numpy as np
import pytest

from tests.llm import brute
from wdsum.llm import textkit, windows


def fixture(seed, count=60, vocabulary=400):
    rng = random.Random(seed)
    words = ["".join(rng.choices("abcdeé", k=rng.randint(1, 7))) for _ in range(vocabulary)]
    passages = [rng.choices(words, k=rng.randint(15, 90)) for _ in range(6)]
    docs = []
    for i in range(count):
        w = []
        for _ in range(rng.randint(0, 4)):
            if rng.random() < 0.5:
                p = rng.choice(passages)
                a = rng.randint(0, len(p) - 1)
                w += p[a : a + rng.randint(1, len(p))]
            else:
                w += rng.choices(words, k=rng.randint(0, 60))
        if rng.random() < 0.1:
            w += [rng.choice(words)] * rng.randint(10, 120)
        docs.append((i * 7 % 101, rng.choice([" ", "  ", "\n"]).join(w)))
    docs += [(500, docs[3][1]), (501, docs[3][1]), (502, ""), (503, None), (504, "x")]
    return docs


@pytest.mark.parametrize("seed", range(3))
def test_word_windows_equal_brute_force(spark, seed):
    docs = fixture(seed)
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(5)
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in windows.repeated_word_windows(df).collect()}
    assert got == brute.word_windows(docs)


def test_word_windows_on_edges(spark):
    df = spark.createDataFrame([], "doc_id long, text string, doc string, spans int")
    assert windows.repeated_word_windows(df).count() == 0
    long = " ".join(str(i) for i in range(3000))
    df = spark.createDataFrame([(None, long, "a"), (1, long, "b"), (1, long, "b"), (2, None, "c")], "doc_id long, text string, key string")
    got = sorted((r.doc_id is not None, r.doc_id or 0, r.n_words, r.n_removed) for r in windows.repeated_word_windows(df).collect())
    assert got == [(False, 0, 3000, 0), (True, 1, 3000, 3000), (True, 1, 3000, 3000), (True, 2, 0, 0)]


def test_cells_do_not_depend_on_pieces(monkeypatch):
    rng = np.random.default_rng(4)
    data = rng.integers(97, 100, 6000).astype(np.uint8)
    data[3000:3400] = data[100:500]
    data[4000:4300] = 97  # ties go to the left
    data[rng.integers(0, 6000, 600)] = 32
    offsets = np.array([0, 0, 30, 2500, 2519, 5990, 6000])
    start, end, at = textkit.words(data, offsets)
    for n, k, far in ((20, 6, None), (40, 16, None), (20, 6, 35)):
        codes = textkit.BYTE_CODES[data]
        whole, words = textkit.anchored_cells(codes, offsets, n, k, far), textkit.word_codes(data, start, end)
        for piece in (1, 41, 100, 997):
            with monkeypatch.context() as m:
                m.setattr(textkit, "PIECE", piece)
                got = textkit.anchored_cells(codes, offsets, n, k, far)
                assert all((got[x] == whole[x]).all() and len(got[x]) == len(whole[x]) for x in whole)
                assert (textkit.word_codes(data, start, end) == words).all()


def test_a_text_of_more_symbols_than_24_bits():
    size = (1 << 24) + 5000
    codes = textkit.BYTE_CODES[np.random.default_rng(5).integers(0, 256, size).astype(np.uint8)]
    codes[-3000:-1000] = codes[100:2100]
    c = textkit.anchored_cells(codes, np.array([0, size]), 400, 128)
    assert c["s0"][0] == 0 and c["s1"][-1] == size - 400 and (c["s0"][1:] == c["s1"][:-1] + 1).all()
    assert np.isin(c["print"][c["s0"] > size - 3000], c["print"][c["s0"] < 2100]).sum() > 4
