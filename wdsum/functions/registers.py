"""Registers: buckets of exponential variables, truncation, packing, merging."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..spec import SketchSpec


def bucket(r: Column) -> Column:
    """The integer that stands for r: larger for smaller r."""
    return F.floor(-F.log2(r)).cast("int")


def truncate(y: Column, spec: SketchSpec) -> Column:
    return y if spec.b is None else F.least(F.greatest(y, F.lit(spec.low)), F.lit(spec.high))


def dense_array(rows: DataFrame, by: list[str], spec: SketchSpec, value: str = "y") -> DataFrame:
    """(by, registers): long rows (by, j, y) as one array of m; missing registers are at the lowest."""
    pairs = rows.groupBy(*by).agg(F.map_from_entries(F.collect_list(F.struct("j", value))).alias("_m"))
    return pairs.select(*by, F.transform(F.sequence(F.lit(1), F.lit(spec.m)), lambda j: F.coalesce(F.element_at("_m", j), F.lit(spec.low))).alias("registers"))


def per_word(b: int) -> int:
    """Registers in a 32-bit word."""
    return 32 // b


def pack(registers: Column, spec: SketchSpec) -> Column:
    """An array of registers in 32-bit words (array of int), the first in the lowest bits."""
    b, k = spec.b, per_word(spec.b)
    words = -(-spec.m // k)
    offset = lambda y: (y - spec.low).cast("long")
    word = lambda i: F.aggregate(F.sequence(F.lit(0), F.lit(k - 1)), F.lit(0).cast("long"), lambda a, s: a.bitwiseOR(F.call_function("shiftleft", F.coalesce(offset(F.get(registers, i * k + s)), F.lit(0).cast("long")), (s * b).cast("int"))))
    signed = lambda v: F.when(v >= 1 << 31, v - (1 << 32)).otherwise(v).cast("int")
    return F.transform(F.sequence(F.lit(0), F.lit(words - 1)), lambda i: signed(word(i)))


def unpack(words: Column, spec: SketchSpec) -> Column:
    b, k, mask = spec.b, per_word(spec.b), (1 << spec.b) - 1
    wide = lambda v: v.cast("long").bitwiseAND(0xFFFFFFFF)
    one = lambda i: F.call_function("shiftright", wide(F.get(words, F.floor(i / k).cast("int"))), (i % k * b).cast("int")).bitwiseAND(mask).cast("int") + spec.low
    return F.transform(F.sequence(F.lit(0), F.lit(spec.m - 1)), one)


def merge(a: Column, b: Column) -> Column:
    """The sketch of two streams' union: register by register the larger."""
    return F.zip_with(a, b, lambda x, y: F.greatest(x, y))


def merge_rows(rows: DataFrame, by: list[str], value: str = "y") -> DataFrame:
    """Long rows (by, j, y) of partial sketches merged; the shuffle carries a row for each task, stream and register at most."""
    return rows.groupBy(*by, "j").agg(F.max(value).alias(value))


def histogram(rows: DataFrame, by: list[str], spec: SketchSpec, value: str = "y") -> DataFrame:
    """(by, hist): how many registers hold each value; registers without a row hold the lowest."""
    low = F.lit(spec.low)
    counts = rows.groupBy(*by, F.col(value).alias("y")).agg(F.count(F.lit(1)).cast("long").alias("n"))
    whole = counts.groupBy(*by).agg(F.collect_list(F.struct("y", "n")).alias("_h"), F.coalesce(F.sum("n"), F.lit(0)).alias("_s"))
    missing = F.when(F.col("_s") < spec.m, F.array(F.struct(low.alias("y"), (spec.m - F.col("_s")).alias("n")))).otherwise(F.array().cast("array<struct<y:int,n:bigint>>"))
    return whole.select(*by, F.array_sort(F.concat(F.transform("_h", lambda e: F.struct(e["y"].cast("int").alias("y"), e["n"].alias("n"))), missing)).alias("hist"))
