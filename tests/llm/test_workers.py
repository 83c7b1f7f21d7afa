import re
from pathlib import Path

import numpy as np
import pyarrow as pa

from wdsum.llm import jaccard, packing, suffixes


def kernels_of(monkeypatch, spark, make):
    """The functions that ``make`` gives to mapInArrow."""
    found, frame = [], type(spark.range(0))
    plain = frame.mapInArrow
    monkeypatch.setattr(frame, "mapInArrow", lambda self, func, *a, **b: found.append(func) or plain(self, func, *a, **b))
    make()
    monkeypatch.undo()
    return found


def encoders():
    import gc

    return sum(isinstance(x, packing.WordEncoder) for x in gc.get_objects())


def test_other_kernels_drop_the_encoder(monkeypatch, spark):
    docs = spark.createDataFrame([(1, "a b c"), (2, None)], "doc_id long, text string")
    empty = pa.record_batch({"doc": pa.array([], pa.int64()), "tag": pa.array([], pa.int32()), "text": pa.array([], pa.string())})
    packs = kernels_of(monkeypatch, spark, lambda: packing.pack_documents(docs))
    others = kernels_of(monkeypatch, spark, lambda: (jaccard._shingled(jaccard.identified(docs, "doc_id", "text")), suffixes.cells(suffixes.identified(docs, "doc_id", "text"), "byte", 240, 80)))
    assert len(packs) == 1 and len(others) == 2
    for other in others:
        kept = packing.encoder(packing.tokenizer_path())
        del kept
        assert encoders()
        list(other(iter([empty])))
        assert not encoders()


def test_a_task_gives_free_memory_back(monkeypatch, spark):
    def anonymous():
        return sum(map(int, re.findall(r"\nPss_Anon:\s+(\d+)", Path("/proc/self/smaps_rollup").read_text()))) / 1024

    docs = spark.createDataFrame([(1, "a b c")], "doc_id long, text string")
    kernel = kernels_of(monkeypatch, spark, lambda: suffixes.cells(suffixes.identified(docs, "doc_id", "text"), "byte", 240, 80))[0]
    batch = lambda: pa.record_batch({"doc": pa.array([1]), "tag": pa.array([1], pa.int32()), "text": pa.array(["a b c"])})
    list(kernel(iter([batch()])))
    before = anonymous()

    def batches():
        # the heap keeps what lies between arrays that live on
        small = [np.ones(12_000) for _ in range(1500)]
        pinned.extend(small[::50])
        del small
        assert anonymous() > before + 100
        yield batch()

    pinned = []
    list(kernel(batches()))
    assert anonymous() < before + 30
