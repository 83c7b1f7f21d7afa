"""The sketches' functions in SQL: inlined expressions, and Arrow functions where state is needed."""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .kernels import OrderedSketch

_EXPRESSIONS = (
    "wds_uniform(x STRING, j INT, seed INT) RETURNS DOUBLE RETURN (CAST(conv(substr(md5(CAST(concat_ws(':', seed, x, j) AS BINARY)), 1, 13), 16, 10) AS BIGINT) + 0.5) / 4503599627370496D",
    "wds_route(x STRING, m INT, seed INT) RETURNS INT RETURN CAST(CAST(conv(substr(md5(CAST(concat('g', seed, ':', x) AS BINARY)), 1, 13), 16, 10) AS BIGINT) % m + 1 AS INT)",
    "wds_bucket(x STRING, w DOUBLE, j INT, seed INT, b INT) RETURNS INT RETURN CAST(least(greatest(floor(-log2(-ln((CAST(conv(substr(md5(CAST(concat_ws(':', seed, x, j) AS BINARY)), 1, 13), 16, 10) AS BIGINT) + 0.5) / 4503599627370496D) / w)), 1 - (1 << (b - 1))), (1 << (b - 1)) - 1) AS INT)",
)


def _struct(**fields: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(k, t) for k, t in fields.items()])


def likelihood(registers: np.ndarray, b: int) -> tuple[float, float, str]:
    """(estimate, variance, status) of one sketch, in numpy: the column expressions' twin."""
    low, high = -(1 << (b - 1)) + 1, (1 << (b - 1)) - 1
    y, n = np.unique(np.asarray(registers, int), return_counts=True)
    if (y <= low).all():
        return 0.0, float("nan"), "all_low"
    if (y >= high).all():
        return float("inf"), float("nan"), "all_high"
    k = n[y > low].sum()
    c = (k if k < n.sum() else max(n.sum() - 1, 1)) / (n * 2.0**-y).sum()
    a = 2.0 ** -(y + 1)
    mid, top = (y > low) & (y < high), y >= high
    with np.errstate(over="ignore"):
        for _ in range(60):
            score = np.where(mid, a * (1 / np.expm1(c * a) - 1), np.where(top, 2 * a / np.expm1(2 * c * a), -a))
            v = np.where(top, 2 * a, a)
            curve = np.where(mid | top, -v * v / (np.expm1(c * v) * -np.expm1(-c * v)), 0.0)
            step = (n * score).sum() / (n * curve).sum()
            c -= step
            if abs(step) <= 1e-12 * abs(c):
                break
    return float(c), float(-1 / (n * curve).sum()), "ok"


@F.pandas_udf(_struct(est=T.DoubleType(), var=T.DoubleType(), status=T.StringType()))
def wds_estimate(registers: pd.Series, b: pd.Series) -> pd.DataFrame:
    return pd.DataFrame([likelihood(r, int(k)) for r, k in zip(registers, b, strict=True)], columns=["est", "var", "status"])


@F.pandas_udf(T.ArrayType(T.IntegerType()))
def wds_sketch(key: pd.Series, w: pd.Series) -> list:
    """A sketch of 64 registers of 8 bits of one group, from ``xxhash64(x)`` and weights: for small groups, since it has no partial form."""
    s = OrderedSketch(64, -127, 127, floats=False)
    s.add(key.to_numpy(np.int64).view(np.uint64), w.to_numpy(float))
    return s.registers.tolist()


def hash_of(x: str) -> int:
    """A 64-bit number of one element's text that doesn't depend on the process."""
    return int.from_bytes(hashlib.blake2b(str(x).encode(), digest_size=8).digest(), "little")


@F.udtf(returnType=_struct(j=T.IntegerType(), y=T.IntegerType()))
class wds_registers:  # noqa: N801
    """Rows (j, y) of an array of registers."""

    def eval(self, registers: list[int]):
        for j, y in enumerate(registers or [], 1):
            yield j, y


@F.udtf(returnType=_struct(k=T.IntegerType(), j=T.IntegerType(), r=T.DoubleType()))
class wds_values:  # noqa: N801
    """The ascending variables (k, j, r) of an element, up to a bound."""

    def eval(self, x: str, w: float, m: int, bound: float):
        from .kernels import ascending_exponentials, permutation

        key = hash_of(x)
        for k, (j, r) in enumerate(zip(permutation(key, m), ascending_exponentials(key, w, m).tolist(), strict=True), 1):
            if r > bound:
                return
            yield k, j, r


def register(spark: SparkSession) -> None:
    """Makes all of them known to the session's SQL."""
    for e in _EXPRESSIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {e}")
    spark.udf.register("wds_estimate", wds_estimate)
    spark.udf.register("wds_sketch", wds_sketch)
    spark.udtf.register("wds_registers", wds_registers)
    spark.udtf.register("wds_values", wds_values)
