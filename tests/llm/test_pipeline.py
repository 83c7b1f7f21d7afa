import random

import corpus_pipeline
from tests.llm import brute
from tests.llm.test_decontamination import plain as hits
from tests.llm.test_jaccard import plain as classes
from wdsum.llm import quality, suffixes

VOCABULARY = [a + b + c for a in ("ba", "té", "lo", "mi") for b in ("ra", "ñu", "ke", "so") for c in ("n", "la", "ti", "po", "du", "we")]


def tables(seed):
    rng = random.Random(seed)
    text = lambda k: " ".join(rng.choices(VOCABULARY, k=k))
    bench = [(i, text(20)) for i in range(5)]
    passage = text(60)
    docs = [text(rng.randint(80, 160)) for _ in range(60)]
    docs += [docs[0], docs[1] + " more", docs[2]]
    docs += [text(50) + " " + passage + " " + text(50) for _ in range(4)] + [text(40) + " " + b[1] + " " + text(40) for b in bench]
    docs += [" ".join(w.upper() + "!!" for w in rng.choices(VOCABULARY, k=100)) for _ in range(40)]
    rows = [(i, t, "en", f"src{i % 3}", len(t)) for i, t in enumerate(docs)] + [(900, None, None, None, None), (901, "", "en", "x", 0)]
    labels = [(i, 0 if i >= len(docs) - 40 else 1, 0) for i in range(len(docs))]
    return rows, labels, bench, passage


def test_stages_equal_brute_force(spark, tmp_path):
    rows, labels, bench, passage = tables(4)
    columns = "doc_id long, text string, lang string, source string, n_chars long"
    spark.createDataFrame(rows, columns).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame(bench, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs, kept = spark.read.parquet(f"{tmp_path}/documents.parquet"), []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = [(r.doc_id, r.text) for r in docs.collect()]
        out = stage(spark, docs, str(tmp_path))
        assert out.columns == docs.columns, name
        out.write.parquet(f"{tmp_path}/{len(kept)}")
        docs = spark.read.parquet(f"{tmp_path}/{len(kept)}")
        kept.append((before, [tuple(r) for r in docs.collect()]))
    good = {d for d, q, _ in labels if q}
    assert {r[0] for r in kept[0][1]} >= good and not {r[0] for r in kept[0][1]} & {d for d, q, _ in labels if not q}
    assert {r[0] for r in kept[1][1]} == {c for _, c, _, _ in classes(kept[1][0])}
    before, after = kept[2]
    n = corpus_pipeline.PASSAGE_BYTES
    removed = {d: (size, cut) for d, size, cut, _, _ in brute.byte_windows(before, n)}
    for d, t, _, _, chars in after:
        size, cut = removed[d]
        assert (t is None) == (chars is None) and passage not in (t or "")
        assert t is None or len(t) == chars and size - cut <= len(t.encode()) <= size - cut + 8
    before, after = kept[3]
    bad = {d for d, *_, contaminated in hits(before, [(str(i), t) for i, t in bench]) if contaminated}
    assert bad and {r[0] for r in after} == {d for d, _ in before} - bad
    pieces = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert {p.doc_id for p in pieces} == {r[0] for r in after}


def test_quality_of_held_out_documents(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    rows = quality.score_documents(docs, labels).join(labels, "doc_id").where("held_out").collect()
    assert all(0 <= r.score <= 1 and (r.predicted == 1) == (r.score >= 0.5) for r in rows)
    good, bad = ([r for r in rows if r.quality == q] for q in (1, 0))
    assert sum(r.predicted for r in good) > 0.99 * len(good) and sum(r.predicted for r in bad) < 0.15 * len(bad)


def test_quality_edges(spark):
    docs = spark.createDataFrame([(1, None, 5), (2, "", 6), (None, "a b", 7), (3, "x" * 100_000, 8), (3, "x" * 100_000, 8)], "doc_id long, text string, score int")
    labels = spark.createDataFrame([], "doc_id long, quality int")
    assert sorted(r.score for r in quality.score_documents(docs, labels).collect())[0] >= 0
    assert quality.score_documents(docs.limit(0), labels).count() == 0
    one = spark.createDataFrame([(2, 1), (9, 0), (None, 1), (4, None)], "doc_id long, quality int")
    assert quality.score_documents(docs, one).count() == 5 and quality.reject_bad(docs, one).columns == docs.columns


def test_cut_keeps_whole_characters(spark):
    long = "é" * 5 + "".join(chr(0x4E00 + i) for i in range(200)) + "é" * 5
    df = spark.createDataFrame([(1, "aé" + long + "b", 1, "x"), (2, "cè" + long + "d", 1, "y"), (3, None, None, "z")], "doc_id long, text string, n_chars int, spans string")
    got = {r.doc_id: (r.text, r.n_chars) for r in suffixes.cut_repeats(df).collect()}
    assert got == {1: ("aéb", 3), 2: ("cèd", 3), 3: (None, None)}
