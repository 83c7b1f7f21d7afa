"""Hand-computed anchors of the likelihood, its start, its curvature and the running fold."""

import math

import pytest
from pyspark.sql import functions as F

from wdsum.functions import estimators as E
from wdsum.functions import kernels as K
from wdsum.spec import SketchSpec

ANCHORS = [
    (8, [0, 0, 0, 0], 0.75, 1.38629436112, 0.5),
    (8, [2, 3, 3, 5], 5.64705882353, 10.5823120698, 29.5281539212),
    (8, [10, 11, 12, 11, 9, 13, 11, 10], 1220.08510638, 1977.77052662, 519643.735004),
    (4, [2, 3, 7, 7], 7.68, 15.0641529827, 61.7100221926),
    (4, [2, 3, 3, 5, -7, -7], 0.015592642222, 0.031153041993, 2.4262812253e-4),
]


def hist_of(spark, b, registers):
    from wdsum.functions.registers import histogram

    spec = SketchSpec(m=len(registers), b=b)
    rows = spark.createDataFrame([(j + 1, y) for j, y in enumerate(registers) if y > spec.low], "j int, y int")
    return histogram(rows, [], spec), spec


@pytest.mark.parametrize(("b", "registers", "start", "c", "var"), ANCHORS)
def test_likelihood_anchors(spark, b, registers, start, c, var):
    hist, spec = hist_of(spark, b, registers)
    h = F.col("hist")
    row = hist.select(E.start(h, spec).alias("start"), E.mle(h, spec).alias("c"), E.mle_var(h, E.mle(h, spec), spec).alias("var"), E.score(h, E.mle(h, spec), spec).alias("score"), E.newton(h, spec)["iterations"].alias("n")).first()
    assert (row.start, row.c, row.var) == pytest.approx((start, c, var), rel=1e-9)
    assert abs(row.score) * math.sqrt(row.var) < 1e-6 and row.n <= 20


def test_all_at_one_end(spark):
    for registers, status, c in (([-7, -7], "all_low", None), ([7, 7], "all_high", math.inf)):
        spec = SketchSpec(m=2, b=4)
        h = F.array(F.struct(F.lit(registers[0]).alias("y"), F.lit(2).cast("long").alias("n")))
        row = spark.range(1).select(E.status(h, spec).alias("s"), E.mle(h, spec).alias("c")).first()
        assert row.s == status and row.c == (0.0 if c is None else c)


def test_cells_sum_to_one(spark):
    spec = SketchSpec(m=2, b=5)
    ys = spark.range(spec.low, spec.high + 1)
    for c in (0.001, 1.0, 40.0):
        assert ys.agg(F.sum(E.cell_prob(F.col("id").cast("int"), F.lit(c), spec))).first()[0] == pytest.approx(1, abs=1e-12)


def test_range_and_bits():
    low, high = E.range_bound(8)
    assert low == pytest.approx(8.1e-38, rel=0.01) and high == pytest.approx(1.7e35, rel=0.01)
    assert E.range_bound(8, censored_at="above_max")[1] == pytest.approx(3.4e35, rel=0.01)
    assert E.choose_bits(1, 9e6) == 7 and E.choose_bits(0.01, 30) == 5
    assert E.predicted_error("logbucket", 256) == pytest.approx(0.0648, abs=1e-4) and E.predicted_error("logbucket_live", 256) == pytest.approx(0.0520, abs=1e-4)
    assert E.memory_bits("dense_exp", 256) == 8 * E.memory_bits("logbucket", 256)
    with pytest.raises(ValueError):
        E.inverse_mean_var(2)


STEPS = [(1, 0, 1.0, 1, 0), (2, 1, 0.5, 1.81886721359, 0.261109906693), (1, 0, 1.0, 1.81886721359, 0.261109906693), (1, 3, 2.0, 5.71906163189, 7.67223757065), (2, 1, 4.0, 5.71906163189, 7.67223757065), (2, 2, 1.5, 13.1780305927, 52.1200020881)]


def test_running_fold_anchors():
    s = K.LiveSketch(2, -127, 127)
    for j, y, w, est, var in STEPS:
        s.add(j, y, w)
        assert (s.est, s.var) == pytest.approx((est, var), rel=1e-9)
    s = K.LiveSketch(2, -7, 7)
    for j, y, w, est in [(1, 7, 0.01, 0.0211547275919), (1, 7, 0.01, 0.0211547275919), (2, -3, 0.02, 0.0765592519878), (2, 0, 0.3, 0.935166908404)]:
        s.add(j, y, w)
        assert s.est == pytest.approx(est, rel=1e-9)


def test_one_element_is_exact():
    for w in (1e-20, 0.3, 7.0, 1e20):
        s = K.LiveSketch(64, -127, 127)
        s.add(5, 3, w)
        assert s.est == pytest.approx(w, rel=1e-12)


def test_permutation_and_ascending_values():
    for key in range(50):
        assert sorted(K.permutation(key, 17)) == list(range(1, 18))
    r = K.ascending_exponentials(12345, 2.0, 50)
    assert (r[1:] > r[:-1]).all()


@pytest.mark.parametrize("floats", [True, False])
def test_early_stop_and_lazy_tracking_change_nothing(floats):
    import numpy as np

    rng = np.random.default_rng(4)
    keys, w = rng.integers(0, 1 << 62, 600).astype(np.uint64), rng.random(600) + 0.01
    out = []
    for stop, tracking in ((False, "eager"), (True, "eager"), (True, "lazy")):
        s = K.OrderedSketch(16, -127, 127, floats, stop, tracking)
        for k in range(0, 600, 100):
            s.add(keys[k : k + 100], w[k : k + 100])
            s.add(keys[k : k + 100], w[k : k + 100])
        out.append((s.registers.tolist(), s.draws))
    assert out[0][0] == out[1][0] == out[2][0]
    assert out[0][1] == 1200 * 16 > 4 * out[1][1]
