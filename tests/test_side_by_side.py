"""Kernels that do many elements or streams at once give what one at a time gives."""

import hashlib
import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from wdsum.functions import estimators as E
from wdsum.functions import kernels as K
from wdsum.functions.md5 import bits52
from wdsum.operators import experiments, live
from wdsum.operators import sketches as S
from wdsum.sources import weights as W
from wdsum.spec import SketchSpec

P = SketchSpec(m=16, hash="portable")


def streams(spark, n=600):
    rng = random.Random(3)
    words = ["a", "", "é中", "x" * 55, "y" * 70, "z" * 200, *(str(i) for i in range(60))]
    rows = [(rng.choice([None, 1, 2, 3, 70]), rng.choice([*words, None]), rng.choice([None, 0.0, 1e-30, 0.5, 3.0, 1e12])) for _ in range(n)]
    return spark.createDataFrame(rows, "stream long, x string, w double")


def rows(df):
    return sorted(map(tuple, df.collect()), key=str)


def test_bits_are_those_of_md5():
    rng = random.Random(1)
    texts = ["".join(rng.choice("abé中") for _ in range(n)) for n in [*range(70), 110, 119, 130, 180, 181, 400] * 2]
    tails = [b":%d" % j for j in (1, 9, 10, 64, 4096)] + [b""]
    want = [[int(hashlib.md5(b"0:" + x.encode() + t).hexdigest()[:13], 16) for t in tails] for x in texts]
    assert bits52(pa.array(texts), b"0:", tails).tolist() == want
    assert bits52(pa.array(texts).slice(3, 9), b"0:", tails).tolist() == want[3:12]
    assert bits52(pa.array([], pa.string()), b"0:", tails).shape == (0, 6)


@pytest.mark.parametrize("at_once", [1 << 22, 40])
def test_kept_minima_are_the_registers(spark, monkeypatch, at_once):
    monkeypatch.setattr(S, "AT_ONCE", at_once)  # parts of 40 numbers cut streams
    df = streams(spark).repartition(3, "stream")
    minima = S.stream_minima(df, P, "stream").cache()
    assert minima.count() == 5
    for m in (16, 5):
        spec = SketchSpec(m=m, hash="portable")
        key = lambda d: {(r[0], r[1]): r[2] for r in d.collect()}
        got, want = key(S.dense_registers(df, spec, ["stream"], minima=minima)), key(S.dense_registers(df, spec, ["stream"]))
        assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k], rel=1e-14) for k in want)
        assert rows(S.integer_registers(df, spec, ["stream"], minima=minima)) == rows(S.integer_registers(df, spec, ["stream"]))
    minima.unpersist()


def test_columns_place_arrivals_alike(spark):
    df = streams(spark)
    assert rows(live.placed(df, ["x"], P, ["stream"], columns=True).select("stream", "s", "j", "y", "w", "x")) == rows(live.placed(df, ["x"], P, ["stream"]).select("stream", "s", "j", "y", "w", "x"))


@pytest.mark.parametrize("timing", ["pre", "post"])
@pytest.mark.parametrize("begin", ["full", "zero"])
def test_rises_side_by_side_are_the_sketch(timing, begin):
    rng, size, y, before, w, want = random.Random(2), [], [], [], [], []
    for arrivals in (0, 1, 300, 40):
        sketch, found = K.LiveSketch(8, -7, 7, timing, begin), 0
        for _ in range(arrivals):
            j, v, weight = rng.randrange(8), min(7, int(rng.expovariate(0.5)) - 4), rng.random() + 0.1
            old = sketch.registers.get(j, -7)
            if sketch.add(j, v, weight):
                found += 1
                y, before, w = [*y, v], [*before, old], [*w, weight]
                want.append((sketch.last_q, sketch.est, sketch.var, sketch.rises, [{"y": a, "n": n} for a, n in sketch.histogram()]))
        size.append(found)
    got = K.fold_rises(*map(np.array, (size, y, before, w)), 8, -7, 7, timing, begin, True)
    for c, values in zip(("q", "est", "var", "rise"), list(zip(*want, strict=True))[:4], strict=True):
        assert got[c].tolist() == pytest.approx(list(values), rel=1e-12)
    assert got["hist"] == [x[4] for x in want]


@pytest.mark.parametrize("b", [4, 8, None])
def test_likelihood_side_by_side(spark, b):
    spec, rng = SketchSpec(m=16, b=b), random.Random(4)
    hists = [[(spec.low, 16)], [(spec.high, 16)], [(spec.low, 3), (1, 6), (2, 7)], *([(y, n) for y, n in zip(sorted(rng.sample(range(-6, 7), 4)), (1, 4, 6, 5), strict=True)] for _ in range(30))]
    df = spark.createDataFrame([(h,) for h in (hists if b else hists[2:])], "h array<struct<y:int,n:bigint>>")
    for one, many in df.select(E.mle(F.col("h"), spec), E.mle_columns(F.col("h"), spec)).collect():
        assert one == pytest.approx(many, rel=1e-9) if one is not None else many is None


def test_streams_are_not_expanded_for_each_method(spark):
    """Every method drew its own m numbers of each element by the JVM's md5, and a stream was folded by a call of its own."""
    df = streams(spark).where("stream > 0 and w > 0 and x is not null").groupBy("stream", "x").agg(F.max("w").alias("w"))
    out = experiments.by_stream(df, ("dense_exp", "logbucket", "logbucket_live"), (4, 16), P, order_by=["x"])
    plan = out._jdf.queryExecution().toString()
    assert "md5(" not in plan and "FlatMapGroupsIn" not in plan
    assert out.count() == 6 * 4


def test_texts_are_cut_once(spark):
    """Terms' counts and the number of their texts come from one shuffle."""
    df = spark.createDataFrame([(1, "a b b"), (2, "b c"), (3, "")], "d long, t string")
    out = W.tfidf(df, "d", "t")
    assert {(r.d, r.x): round(r.w, 6) for r in out.collect()} == {(1, "a"): 1.098612, (1, "b"): 0.81093, (2, "b"): 0.405465, (2, "c"): 1.098612}
    with_plan = W.tfidf(df, "d", "t")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        assert "ReusedExchange" in with_plan._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", "true")


def test_streams_are_made_once(spark):
    made = spark.sparkContext.accumulator(0)

    def seen(batches):
        for b in batches:
            made.add(b.num_rows)
            yield b

    df = spark.createDataFrame([(i % 3, str(i), 1.0 + i) for i in range(30)], "stream long, x string, w double").mapInArrow(seen, "stream long, x string, w double")
    assert experiments.by_stream(df, ("dense_exp", "logbucket_live"), (4, 8), P, order_by=["x"]).count() == 12
    assert made.value == 30
