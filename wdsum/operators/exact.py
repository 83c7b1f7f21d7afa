"""Exact weighted distinct sums."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import linear
from ..sources.weights import clean, resolve
from ..spec import SketchSpec


def weighted_distinct(df: DataFrame, x: str = "x", w: str = "w", by: list[str] | None = None, on_conflict: str = "max", order_by: list[str] | None = None) -> DataFrame:
    """(by, exact, n): the sum of the weights of the distinct elements, and how many there are.

    Two aggregations: elements within a task meet before they are shuffled, and
    of the sums a row for each task and stream is shuffled.
    """
    once = resolve(clean(df, w), x, w, on_conflict, by, order_by)
    return once.groupBy(*(by or [])).agg(F.coalesce(F.sum(w), F.lit(0.0)).alias("exact"), F.count(F.lit(1)).alias("n"))


#: ranges of the order into which a running sum without streams is cut
RANGES = 64


def running(df: DataFrame, order_by: list[str], x: str = "x", w: str = "w", by: list[str] | None = None, spec: SketchSpec = SketchSpec(), every: bool = False) -> DataFrame:
    """df with ``exact``, the sum over the distinct elements of its stream so far; an element counts at its first row.

    Rows of bad weight go, unless ``every`` row is to stay: then an element whose
    first row has none, or one of 0, has that one too.

    Streams run apart from each other. A single one is cut into ranges of the
    order's first column, if it is a number, date or time: each sums its own rows
    and starts from the total of all ranges before it.
    """
    by = by or []
    rows = df.withColumn(w, F.coalesce(F.col(w).cast("double"), F.lit(0.0))) if every else clean(df, w, spec)
    first = F.row_number().over(Window.partitionBy(*by, x).orderBy(*order_by)) == 1
    new = rows.withColumn("_new", F.when(first, F.col(w)).otherwise(0.0))
    at = linear(df, order_by[0])
    whole = lambda *keys: F.sum("_new").over(Window.partitionBy(*keys).orderBy(*order_by).rowsBetween(Window.unboundedPreceding, 0))
    if by or at is None:
        return new.withColumn("exact", whole(*by)).drop("_new")
    cuts = df.agg(F.percentile_approx(at, [k / RANGES for k in range(1, RANGES)], 100 * RANGES)).first()[0] or []
    # nulls come first in the order; rows that tie in the first column share a range
    ranged = new.withColumn("_range", F.coalesce(F.size(F.filter(F.array(*map(F.lit, sorted(set(cuts)))), lambda c: c <= at)), F.lit(0)) if cuts else F.lit(0))
    totals = ranged.groupBy("_range").agg(F.sum("_new").alias("_total"))
    before = totals.select("_range", F.coalesce(F.sum("_total").over(Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)).alias("_before"))
    # one row, not a join on _range: from such a join Spark infers a filter on the totals that asks for the order's column
    start = before.agg(F.map_from_entries(F.collect_list(F.struct("_range", "_before"))).alias("_start"))
    return ranged.crossJoin(F.broadcast(start)).withColumn("exact", whole("_range") + F.element_at("_start", F.col("_range"))).drop("_new", "_range", "_start")
