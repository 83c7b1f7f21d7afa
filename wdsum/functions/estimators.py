"""Estimators over floats and over histograms of registers, as column expressions.

A register of value y says that its exponential variable, of rate C, lies in
(a, 2a] with a = 2 ** -(y + 1). At the lowest value it may be anything larger, at
the highest anything smaller. Histogram entries are (y, n).
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..spec import SketchSpec
from .kernels import newton_rows


def half(y: Column) -> Column:
    """Lower end of a register's cell."""
    return F.pow(F.lit(2.0), -(y + 1).cast("double"))


def inverse_mean(total: Column, m: int) -> Column:
    """Unbiased from m float minima of sum ``total``; needs two registers."""
    if m < 2:
        raise ValueError("the float estimator needs two registers")
    return (m - 1) / total


def inverse_mean_var(m: int) -> float:
    """Relative variance of ``inverse_mean``; needs three registers."""
    if m < 3:
        raise ValueError("its variance needs three registers")
    return 1 / (m - 2)


def cell_prob(y: Column, c: Column, spec: SketchSpec) -> Column:
    a = half(y)
    mid = F.exp(-c * a) - F.exp(-2 * c * a)
    if spec.b is None:
        return mid
    return F.when(y <= spec.low, F.exp(-c * a)).when(y >= spec.high, -F.expm1(-2 * c * a)).otherwise(mid)


def _sum(hist: Column, term) -> Column:
    return F.aggregate(hist, F.lit(0.0), lambda s, e: s + e["n"] * term(e["y"]))


def _cases(y: Column, spec: SketchSpec, low, mid, high) -> Column:
    if spec.b is None:
        return mid
    return F.when(y <= spec.low, low).when(y >= spec.high, high).otherwise(mid)


def loglik(hist: Column, c: Column, spec: SketchSpec) -> Column:
    def term(y: Column) -> Column:
        a = half(y)
        return _cases(y, spec, -c * a, -c * a + F.log(-F.expm1(-c * a)), F.log(-F.expm1(-2 * c * a)))

    return _sum(hist, term)


def score(hist: Column, c: Column, spec: SketchSpec) -> Column:
    """Derivative of the log-likelihood."""

    def term(y: Column) -> Column:
        a = half(y)
        return _cases(y, spec, -a, a * (F.try_divide(F.lit(1.0), F.expm1(c * a)) - 1), F.try_divide(2 * a, F.expm1(2 * c * a)))

    return _sum(hist, term)


def dscore(hist: Column, c: Column, spec: SketchSpec) -> Column:
    """Second derivative: below 0, so the likelihood has one peak."""

    def curve(a: Column) -> Column:
        x = c * a
        return F.try_divide(-a * a, F.expm1(x) * -F.expm1(-x))  # null at c = 0

    def term(y: Column) -> Column:
        a = half(y)
        return _cases(y, spec, F.lit(0.0), curve(a), curve(2 * a))

    return _sum(hist, term)


def held(hist: Column, spec: SketchSpec) -> Column:
    """Registers above the lowest value."""
    return F.aggregate(hist, F.lit(0).cast("long"), lambda s, e: s + F.when(e["y"] > spec.low, e["n"]).otherwise(0))


def total(hist: Column) -> Column:
    return F.aggregate(hist, F.lit(0).cast("long"), lambda s, e: s + e["n"])


def start(hist: Column, spec: SketchSpec) -> Column:
    """Where the iteration starts, left of the root: the float estimator on the cells' upper ends."""
    m, k = total(hist), held(hist, spec)
    upper = _sum(hist, lambda y: F.pow(F.lit(2.0), -y.cast("double")))
    return F.when(k < m, k).otherwise(F.greatest(m - 1, F.lit(1))) / upper


def plugin(hist: Column, spec: SketchSpec) -> Column:
    """The float estimator on dequantised registers; biased, kept to show why likelihood is needed."""
    return (total(hist) - 1) / _sum(hist, lambda y: F.pow(F.lit(2.0), -y.cast("double")))


def status(hist: Column, spec: SketchSpec) -> Column:
    all_low = held(hist, spec) == 0
    all_high = F.forall(hist, lambda e: e["y"] >= spec.high) if spec.b else F.lit(False)
    return F.when(all_low, "all_low").when(all_high, "all_high").otherwise("ok")


def newton(hist: Column, spec: SketchSpec, tol: float = 1e-12, max_iter: int = 40) -> Column:
    """struct(c, iterations): Newton's method folded inside the row, with no driver loop."""
    begin = F.struct(start(hist, spec).alias("c"), F.lit(0).alias("iterations"), F.lit(False).alias("done"))

    def step(s: Column, _: Column) -> Column:
        new = s["c"] - F.try_divide(score(hist, s["c"], spec), dscore(hist, s["c"], spec))
        moved = F.abs(new - s["c"]) > tol * F.abs(new)
        again = F.struct(new.alias("c"), (s["iterations"] + 1).alias("iterations"), (~moved).alias("done"))
        return F.when(s["done"], s).otherwise(again)

    return F.aggregate(F.sequence(F.lit(1), F.lit(max_iter)), begin, step)


def mle(hist: Column, spec: SketchSpec, tol: float = 1e-12, max_iter: int = 40, bias_correct: bool = False) -> Column:
    """Maximum likelihood of C; 0 or infinity where all registers are at one end."""
    c = newton(hist, spec, tol, max_iter)["c"]
    if bias_correct:
        c = c * (1 - 1 / spec.m)
    return F.when(status(hist, spec) == "all_low", 0.0).when(status(hist, spec) == "all_high", float("inf")).otherwise(c)


def mle_columns(hist: Column, spec: SketchSpec, tol: float = 1e-12, max_iter: int = 40) -> Column:
    """``mle`` for many rows: the same steps, taken for a batch of rows side by side."""
    low, high = (spec.low, spec.high) if spec.b is not None else (None, None)

    def solve(hists: pa.Array, begin: pa.Array) -> pa.Array:
        size = np.diff(hists.offsets.to_numpy())
        entries = hists.flatten()
        y, n = (entries.field(i).to_numpy() for i in (0, 1))
        c = newton_rows(np.repeat(np.arange(len(size)), size), y, n, begin.to_numpy(zero_copy_only=False).astype(float), low, high, tol, max_iter)
        return pa.array(c, pa.float64(), from_pandas=True)

    c = F.arrow_udf(solve, "double").asNondeterministic()(hist, start(hist, spec))
    return F.when(status(hist, spec) == "all_low", 0.0).when(status(hist, spec) == "all_high", float("inf")).otherwise(c)


def mle_var(hist: Column, c: Column, spec: SketchSpec) -> Column:
    return F.try_divide(F.lit(-1.0), dscore(hist, c, spec))


#: normal quantiles of the usual two-sided levels
QUANTILE = {0.9: 1.6448536269514722, 0.95: 1.959963984540054, 0.99: 2.5758293035489004}


def interval(c: Column, var: Column, level: float = 0.95) -> tuple[Column, Column]:
    q = QUANTILE[level]
    return F.greatest(c - q * F.sqrt(var), F.lit(0.0)), c + q * F.sqrt(var)


def reached(hist: Column, spec: SketchSpec) -> Column:
    """The histogram without registers at the lowest value."""
    return F.filter(hist, lambda e: e["y"] > spec.low)


def mle_routed(hist: Column, spec: SketchSpec, **options) -> Column:
    """From registers that each saw a part of the stream: the rate of one times those that saw any.

    A register that no element was routed to has no weight; to take it for one
    that saw only large values would drag the estimate to 0.
    """
    return held(hist, spec) * mle(reached(hist, spec), spec, **options)


def range_bound(b: int, eps: float = 0.001, censored_at: str = "at_max", m: int = 1) -> tuple[float, float]:
    """C for which a register is truncated with a probability of 2 eps at most.

    ``censored_at``: whether a register at its highest value counts as truncated
    ("at_max") or only one that would lie above ("above_max"). ``m``: parts that
    the stream is routed to.
    """
    low, high = -(1 << (b - 1)) + 1, (1 << (b - 1)) - 1
    top = high + (censored_at == "above_max")
    return -(2.0 ** (low + 1)) * math.log(eps) * m, -(2.0**top) * math.log1p(-eps) * m


def choose_bits(least: float, most: float, eps: float = 0.001, m: int = 1) -> int:
    """The fewest bits whose range has both ends."""
    for b in range(3, 17):
        lo, hi = range_bound(b, eps, m=m)
        if lo <= least and most <= hi:
            return b
    raise ValueError("no register of 16 bits or fewer has this range")


def fewest_bits(least: Column, most: Column, eps: float = 0.001, m: int = 1) -> Column:
    """``choose_bits`` of columns; an error where no register has the range."""
    out = F.raise_error(F.lit("no register has this range")).cast("int")
    for b in range(11, 2, -1):  # eleven bits reach as far as doubles do
        lo, hi = range_bound(b, eps, m=m)
        out = F.when((least >= lo) & (most <= hi), F.lit(b)).otherwise(out)
    return out


#: asymptotic relative errors times the square root of m
STATIC_FACTOR = math.sqrt(math.log(2) / (math.pi**2 / 6 - 1))
LIVE_FACTOR = math.sqrt(math.log(2))


def predicted_error(method: str, m: int) -> float:
    """Asymptotic relative root mean square error of a method."""
    if method in ("dense_exp", "ordered_exp", "ordered_exp_lazy"):
        return math.sqrt(inverse_mean_var(m))
    return (STATIC_FACTOR if method == "logbucket" else LIVE_FACTOR) / math.sqrt(m)


def memory_bits(method: str, m: int, b: int = 8) -> int:
    """Bits of one sketch; the running method has counters of the register values too."""
    if method in ("dense_exp", "ordered_exp", "ordered_exp_lazy"):
        return 64 * m
    return m * b + (0 if method == "logbucket" else (1 << b) * math.ceil(math.log2(m)) if m > 1 else 1 << b)
