"""Joins and set measures that weighted streams need and Spark has no operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.registers import merge_rows


def interval_join(points: DataFrame, spans: DataFrame, at: str, start: str, end: str, width: float) -> DataFrame:
    """Points with the spans [start, end) that hold them, over numbers.

    Both are cut into cells of ``width``: a span goes to each cell it touches and
    a point to one, so cells are joined by equality, not all points with all spans.
    """
    cell = lambda c: F.floor(c / width)
    cut = spans.where(F.col(start) < F.col(end)).withColumn("_cell", F.explode(F.sequence(cell(F.col(start)), cell(F.col(end)))))
    return points.withColumn("_cell", cell(F.col(at))).join(cut, "_cell").where((F.col(at) >= F.col(start)) & (F.col(at) < F.col(end))).drop("_cell")


def asof_join(left: DataFrame, right: DataFrame, on: list[str], at: str, since: str, value: str) -> DataFrame:
    """left with right's last ``value`` at or before its time; null where there is none. One shuffle, no range join."""
    l = left.withColumns({"_t": F.col(at), "_side": F.lit(1), "_v": F.lit(None).cast(right.schema[value].dataType), "_row": F.struct(*left.columns)})
    r = right.select(*on, F.col(since).alias("_t"), F.lit(0).alias("_side"), F.col(value).alias("_v"), F.lit(None).cast(l.schema["_row"].dataType).alias("_row"))
    order = Window.partitionBy(*on).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = l.select(*on, "_t", "_side", "_v", "_row").unionByName(r).withColumn("_v", F.last("_v", True).over(order))
    return both.where("_side = 1").select("_row.*", F.col("_v").alias(value))


def semi(df: DataFrame, keys: DataFrame, on: list[str], anti: bool = False) -> DataFrame:
    return df.join(keys, on, "left_anti" if anti else "left_semi")


def union_registers(parts: list[DataFrame], by: list[str]) -> DataFrame:
    """Registers of the union of streams, from theirs."""
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return merge_rows(out, by)


def overlap(a: Column, b: Column, union: Column) -> Column:
    """Weight of the intersection by inclusion and exclusion; never below 0."""
    return F.greatest(a + b - union, F.lit(0.0))
