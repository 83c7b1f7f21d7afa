import random
import zlib

import numpy as np

from wdsum.llm import packing


def test_pieces_cover_every_id_without_padding(spark):
    rng = random.Random(5)
    texts = [" ".join(rng.choices(["alpha", "Beta,", "gamma.", "délta", "it's", "x1", "!!", "<|endoftext|>"], k=rng.choice([0, 1, 5, 300, 4000]))) for _ in range(60)]
    docs = [(i, t, 1) for i, t in enumerate(texts)] + [(60, None, 1), (61, "", 1), (62, "a b c ́d ΣΣ", 1), (62, "a b c ́d ΣΣ", 1), (None, "null id", 1)]
    df = spark.createDataFrame(docs, "doc_id long, text string, length int").repartition(3)
    rows = packing.pack_documents(df).collect()
    tok = packing.encoder(packing.tokenizer_path()).tokenizer
    want = {d: tok.encode(t or "", add_special_tokens=False).ids + [1] for d, t, _ in docs}
    by, seq = {}, {}
    for r in rows:
        by.setdefault(r.doc_id, []).append(r)
        seq.setdefault(r.sequence_id, []).append(r)
    assert by.keys() == want.keys()
    for d, ids in want.items():
        copies = 2 if d == 62 else 1
        assert sum(r.length for r in by[d]) == copies * len(ids)
        for r in by[d]:
            raw = np.array(ids[r.start : r.start + r.length], "<u4").tobytes()
            assert (r.doc_tokens, r.ids_crc32) == (len(ids), zlib.crc32(raw)) and r.length > 0
        if copies == 1:
            at = 0
            for r in sorted(by[d], key=lambda r: r.start):
                assert r.start == at
                at += r.length
    for rs in seq.values():
        at = 0
        for r in sorted(rs, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 2048 and at & (at - 1) == 0


def test_ids_equal_the_tokenizers():
    encode = packing.encoder(packing.tokenizer_path())
    rng = random.Random(9)
    parts = ["<|endoftext|>", "<|startoftext|>", "<|ENDOFTEXT|>", "<|EndOfText|>", "<|", "|>", "<", "x", "Y", "Word", "DON'T", "\u03a3", "\u0130", "é", "É", " ", "  ", "\n", "\t", "12", "!?", "'s", "'LL", "\u00a0", "\u0301", "ﬁ", "中文"]
    texts = ["".join(rng.choices(parts, k=rng.randint(0, 12))) for _ in range(4000)] + ["x <|ENDOFTEXT|> y", "x<|endoftext|>Y <|STARTOFTEXT|>"]
    for t, got in zip(texts, encode(texts), strict=True):
        assert np.frombuffer(got, "<u4").tolist() == encode.tokenizer.encode(t, add_special_tokens=False).ids, t


def test_empty_table(spark):
    assert packing.pack_documents(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_whole_examples_hold_all_limits():
    rng = random.Random(1)
    limits = packing.Limits(tokens=100, segments=5, loss=40)
    items = [(i, n := rng.randint(0, 100), rng.randint(0, min(40, n))) for i in range(400)]
    sequences = packing.pack_lengths(items, limits)
    size = {i: (n, x) for i, n, x in items}
    assert sorted(k for s in sequences for k in s) == list(range(400))
    for s in sequences:
        assert len(s) <= 5 and sum(size[k][0] for k in s) <= 100 and sum(size[k][1] for k in s) <= 40
    bound = max(sum(n for _, n, _ in items) / 100, sum(x for _, _, x in items) / 40, len(items) / 5)
    assert len(sequences) <= 1.1 * bound + 1


def test_conversations_pack_whole(spark):
    turns = [(1, 0, "user", "hello there"), (1, 1, "assistant", "general answer " * 30), (2, 0, "user", None), (2, 1, "assistant", "")]
    df = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string")
    sizes = packing.conversation_sizes(df, max_tokens=40)
    rows = sizes.collect()
    assert all(0 < r.tokens <= 40 and r.loss_tokens <= r.tokens for r in rows)
    packed = packing.pack_examples(sizes, "id", "tokens", "loss_tokens", packing.Limits(40, 8, 40)).collect()
    assert sorted(r.id for r in packed) == sorted(r.id for r in rows)


def test_long_turns_before_short_ones_stay_within_a_sequence(spark):
    turns = [(1, 0, "user", "a b " * 50), (1, 1, "assistant", "general answer " * 2000), (1, 2, "user", "c d " * 450), (2, 0, "assistant", "x " * 5000)]
    df = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string")
    sizes = packing.conversation_sizes(df)
    rows = sizes.collect()
    encode = packing.encoder(packing.tokenizer_path())
    assert sum(r.tokens for r in rows) == sum(len(x) // 4 + 1 for x in encode([t[3] for t in turns]))
    assert all(0 < r.tokens <= 2048 and r.loss_tokens <= r.tokens for r in rows)
    packed = packing.pack_examples(sizes, "id", "tokens", "loss_tokens").collect()
    assert sorted(r.id for r in packed) == sorted(r.id for r in rows)
