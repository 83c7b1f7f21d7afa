"""The running estimate: one register for each arrival, and an answer at all times.

An element can only raise the one register it is routed to. When it does, its
weight divided by the chance that such an element raises some register joins the
total, which is unbiased. Rises are few, so nearly all rows are dropped before
anything is shuffled. First in the JVM: stretches of time, each as long as all
before it, have floors, what a share of the arrivals before the stretch has
raised each register to, and a row that stays below its floor is no rise. Then a
task keeps a row only if it rises among the task's own rows, which every true
rise does. The fold over what is left runs by stream and shard.

The order of arrivals matters for the value, so it must be total up to equal
elements. Totals of overlapping streams don't merge; their registers do, see
``sketches.routed_registers``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import SCALE, drawn, exponential, linear, route, shard, tail
from ..functions.kernels import fold_rises
from ..functions.registers import bucket, truncate
from ..plans.shared import small
from ..sources.weights import clean, first_arrivals
from ..spec import SketchSpec


def placed(df: DataFrame, order_by: list[str], spec: SketchSpec = SketchSpec(), by: list[str] | None = None, x: str = "x", w: str = "w", shards: int = 1, columns: bool = False) -> DataFrame:
    """(by, s, j, y, w, order_by): each arrival's shard, register and bucket, also those that no register can show.

    ``columns``: the portable hash is worked out for whole columns, with the same
    result, which takes a fraction of the time where all rows are needed.
    """
    per = spec.m // shards
    if per * shards != spec.m:
        raise ValueError("the shards must divide the registers")
    s = shard(F.col(x), shards, spec.seed, spec.hash) if shards > 1 else F.lit(0)
    kept = [F.col(w).alias("w"), *(c for c in order_by if c not in (by or []))]
    if columns and spec.hash == "portable":
        rows = clean(df, w, spec).select(*(by or []), s.alias("s"), drawn(per, spec.seed)(tail(F.col(x))).alias("_d"), *kept)
        y = truncate(bucket(-F.log((F.col("_d.bits") + 0.5) / SCALE) / F.col("w")), spec)
        return rows.select(*(by or []), "s", F.col("_d.j").alias("j"), "w", *(c for c in order_by if c not in (by or [])), y.alias("y"))
    rows = clean(df, w, spec).select(*(by or []), s.alias("s"), route(F.col(x), per, spec.seed, spec.hash).alias("j"), F.col(x).alias("_x"), *kept)
    y = truncate(bucket(exponential(F.col("_x"), F.col("w"), F.col("j"), spec.seed, spec.hash)), spec)
    return rows.withColumn("y", y).drop("_x")


def project(df: DataFrame, order_by: list[str], spec: SketchSpec = SketchSpec(), by: list[str] | None = None, x: str = "x", w: str = "w", shards: int = 1, columns: bool = False) -> DataFrame:
    """Those arrivals of ``placed`` that lie above the lowest value: no other can be a rise."""
    return placed(df, order_by, spec, by, x, w, shards, columns).where(F.col("y") > spec.low)


#: stretches of time that have floors of their own, and the share of arrivals that these come from
STRETCHES, SHARE = 11, 1 / 8


def above_floors(rows: DataFrame, df: DataFrame, order_by: list[str], by: list[str] | None = None) -> DataFrame:
    """Rows of ``project`` that reach above the floor of their stretch: every rise does.

    ``df`` is what they were made from, of which only the first column of the
    order is read. That column must be a number, date or time; otherwise, and
    with too many streams to broadcast floors of, all rows stay.
    """
    at = linear(df, order_by[0])
    if at is None:
        return rows
    lo, hi = df.agg(F.min(at), F.max(at)).first()
    if lo is None or not lo < hi:
        return rows
    keys = [*(by or []), "s", "j"]
    dated = rows.withColumn("_at", F.floor(F.log2((linear(rows, order_by[0]) - lo) / (hi - lo) * (2 ** (STRETCHES - 1) - 1) + 1)).cast("int"))
    # any arrivals do for a lower bound, so it doesn't matter which ones the draw takes
    top = dated.where(F.rand(1) < SHARE).groupBy(*keys, "_at").agg(F.max("y").alias("_y"))
    floors = top.groupBy(*keys).agg(F.array(*(F.max(F.when(F.col("_at") < k, F.col("_y"))) for k in range(STRETCHES + 1))).alias("_floors"))
    floors = small(floors) if by else F.broadcast(floors)  # without streams a row for each register
    if floors is None:
        return rows
    known = dated.join(floors, keys, "left")
    return known.where(F.coalesce(F.col("y") > F.get("_floors", "_at"), F.lit(True))).select(*rows.columns)


#: rows that a task compares with each other before it passes on those that rise
PRUNE_ROWS = 1 << 20


def local_rises(rows: DataFrame, order_by: list[str], by: list[str] | None = None) -> DataFrame:
    """Rows that rise among a part of their own task's rows: none of the others can be a rise."""
    keys = [*(by or []), "s", "j"]

    def prune(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(held)
        code = np.zeros(len(t), np.int64)
        for k in keys:
            one, names = pd.factorize(t.column(k).to_pandas(), use_na_sentinel=False)
            code = code * len(names) + one
        y = t.column("y").to_numpy()
        code = pd.factorize(code)[0]
        order = np.lexsort([*(pd.factorize(t.column(c).to_pandas(), sort=True)[0] if pa.types.is_string(t.schema.field(c).type) else t.column(c).to_numpy() for c in reversed(order_by)), code])
        # groups follow each other, so one running maximum serves all of them
        rank = code[order] * (1 << 24) + y[order] + (1 << 23)
        reach = np.maximum.accumulate(rank)
        up = np.ones(len(rank), bool)
        up[1:] = rank[1:] > reach[:-1]
        yield from t.take(pa.array(np.sort(order[up]))).to_batches()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        size = 0
        for b in batches:
            held.append(b)
            size += b.num_rows
            if size >= PRUNE_ROWS:
                yield from prune(held)
                held, size = [], 0
        if held:
            yield from prune(held)

    return rows.mapInArrow(run, rows.schema)


def rises(rows: DataFrame, order_by: list[str], spec: SketchSpec, by: list[str] | None = None) -> DataFrame:
    """(by, s, j, y, w, order_by, before): arrivals that raise their register, and its value until then."""
    own = Window.partitionBy(*(by or []), "s", "j").orderBy(*order_by, F.desc("y")).rowsBetween(Window.unboundedPreceding, -1)
    known = rows.withColumn("before", F.coalesce(F.max("y").over(own), F.lit(spec.low)))
    return known.where(F.col("y") > F.col("before"))


def trajectory(df: DataFrame, order_by: list[str], spec: SketchSpec = SketchSpec(), by: list[str] | None = None, x: str = "x", w: str = "w", shards: int = 1, timing: str = "pre", begin: str = "full", prune: bool = True, histograms: bool = False, final: bool = False) -> DataFrame:
    """(by, s, order_by, j, y, w, q, est, var, rise[, hist]): the shard's estimate after each rise, and the registers' histogram.

    A shard's rises, some for each register, are one row; the fold goes through
    the shards of a batch side by side. ``final``: only (by, s, est, var, rise) of
    the last rise.
    """
    by = by or []
    rows = project(df, order_by, spec, by, x, w, shards, columns=not prune)
    if by and not prune:
        rows = rows.repartition(*by)  # one shuffle for the window and the fold
    found = rises(local_rises(above_floors(rows, df, order_by, by), order_by, by) if prune else rows, order_by, spec, by)
    per, low, high = spec.m // shards, spec.low, spec.high
    own = [*(c for c in order_by if c not in by), "j", "y", "w"]
    told = {"q": "double", "est": "double", "var": "double", "rise": "long"} | ({"hist": "array<struct<y:int,n:bigint>>"} if histograms else {})
    last = {c: told[c] for c in ("est", "var", "rise")}
    one = lambda fields: f"struct<{','.join(f'{c}:{t}' for c, t in fields.items())}>"

    def fold(y: pa.Array, before: pa.Array, w: pa.Array) -> pa.Array:
        size = np.diff(y.offsets.to_numpy())
        steps = fold_rises(size, *(c.flatten().to_numpy() for c in (y, before, w)), per, low, high, timing, begin, histograms and not final)
        if final:
            at = np.cumsum(size) - 1
            return pa.StructArray.from_arrays([pa.array(steps[c][at]) for c in last], list(last))
        kinds = {"hist": pa.list_(pa.struct([("y", pa.int32()), ("n", pa.int64())]))}
        values = pa.StructArray.from_arrays([pa.array(steps[c], kinds.get(c)) for c in told], list(told))
        return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(size)]).astype(np.int32)), values)

    together = found.groupBy(*by, "s").agg(F.sort_array(F.collect_list(F.struct(*own, "before"))).alias("_r"))
    folded = together.withColumn("_f", F.arrow_udf(fold, one(last) if final else f"array<{one(told)}>")("_r.y", "_r.before", "_r.w"))
    if final:
        return folded.select(*by, "s", *(f"_f.{c}" for c in last))
    return folded.select(*by, "s", F.inline(F.arrays_zip("_r", "_f"))).select(*by, "s", *(f"_r.{c}" for c in own), *(f"_f.{c}" for c in told))


def estimate(df: DataFrame, order_by: list[str], spec: SketchSpec = SketchSpec(), by: list[str] | None = None, x: str = "x", w: str = "w", shards: int = 1, **options) -> DataFrame:
    """(by, est, var, rises): the estimate at the end; shards are disjoint streams whose estimates add up."""
    steps = trajectory(df, order_by, spec, by, x, w, shards, final=True, **options)
    last = steps.groupBy(*(by or []), "s").agg(F.max("est").alias("est"), F.max("var").alias("var"), F.max("rise").alias("rises"))
    if by:
        return last.groupBy(*by).agg(*(F.sum(c).alias(c) for c in ("est", "var", "rises")))
    return last.agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("est", "var", "rises")))


def as_of(steps: DataFrame, times: DataFrame, at: str, time: str, by: list[str] | None = None) -> DataFrame:
    """(times' columns, est): the estimate at asked times, the last rise at or before each; 0 before the first.

    ``steps``: a trajectory of one shard with the time column ``at``.
    """
    keys = by or []
    last = Window.partitionBy(*keys).orderBy("_t", "_asked", "_rise").rowsBetween(Window.unboundedPreceding, 0)
    known = steps.select(*keys, F.col(at).alias("_t"), F.lit(0).alias("_asked"), F.col("rise").alias("_rise"), "est")
    asked = times.select(*keys, F.col(time).alias("_t"), F.lit(1).alias("_asked"), F.lit(0).cast("long").alias("_rise"), F.lit(None).cast("double").alias("est"))
    both = known.unionByName(asked).withColumn("est", F.last("est", True).over(last))
    return both.where("_asked = 1").select(*keys, F.col("_t").alias(time), F.coalesce("est", F.lit(0.0)).alias("est"))


def var_from_trace(df: DataFrame, order_by: list[str], spec: SketchSpec = SketchSpec(), by: list[str] | None = None, x: str = "x", w: str = "w") -> DataFrame:
    """(by, var): the estimate's variance by its theory, summed over first arrivals.

    Each first arrival, whether it rises or not, adds w^2 (1 - q) / q with the
    chance q of a rise just before it: what the running variance estimates from
    rises alone. The state before an arrival is that of the last rise before it,
    so arrivals and rises are joined by its number; within a stream arrivals
    are put in order by one task, so this is a measure for experiments.
    """
    keys = by or []
    first = first_arrivals(clean(df, w, spec), x, w, order_by, keys).withColumnRenamed(w, "_w")
    steps = trajectory(df, order_by, spec, by, x, w, histograms=True)
    own = Window.partitionBy(*keys).orderBy(*order_by, "_kind").rowsBetween(Window.unboundedPreceding, 0)
    # a rise is a first arrival too: it comes after itself
    marks = first.select(*keys, *order_by, "_w", F.lit(0).alias("_kind"), F.lit(None).cast("long").alias("rise")).unionByName(steps.select(*keys, *order_by, F.lit(None).cast("double").alias("_w"), F.lit(1).alias("_kind"), "rise"))
    asked = marks.withColumn("rise", F.coalesce(F.last("rise", True).over(own), F.lit(0).cast("long"))).where("_kind = 0").select(*keys, "_w", "rise")
    begin = F.array(F.struct(F.lit(spec.low).alias("y"), F.lit(spec.m).cast("long").alias("n")))
    held = asked.join(steps.select(*keys, "rise", "hist"), [*keys, "rise"], "left").withColumn("hist", F.coalesce("hist", begin))
    q = rise_prob_hist(F.col("hist"), F.col("_w"), spec.m, spec.high)
    return held.select(*keys, (F.col("_w") * F.col("_w") * (1 - q) / q).alias("var")).groupBy(*keys).agg(F.sum("var").alias("var"))


def rise_prob_registers(registers, w, m: int, high: int):
    """The chance of a rise from the registers themselves, as a column: work of m."""
    miss = F.aggregate(registers, F.lit(0.0), lambda s, y: s + F.when(y < high, -F.expm1(-w * F.pow(F.lit(2.0), -(y + 1).cast("double")))).otherwise(0.0))
    return miss / m


def rise_prob_hist(hist, w, m: int, high: int):
    """The same from the histogram (y, n): work of its different values."""
    up = F.aggregate(hist, F.lit(0.0), lambda s, e: s + F.when(e["y"] < high, e["n"] * -F.expm1(-w * F.pow(F.lit(2.0), -(e["y"] + 1).cast("double")))).otherwise(0.0))
    return up / m


def states(found: DataFrame, order_by: list[str], spec: SketchSpec, by: list[str] | None = None) -> DataFrame:
    """Each rise with all m registers just before it: for small sketches, to compare with the fold."""
    by = by or []
    numbered = found.withColumn("rise", F.row_number().over(Window.partitionBy(*by).orderBy(*order_by)))
    after = numbered.select(*(F.col(c).alias(f"_{c}") for c in by), F.col("j").alias("_j"), F.col("y").alias("_y"), F.col("rise").alias("_r"))
    same = [F.col(c).eqNullSafe(F.col(f"_{c}")) for c in by] + [F.col("_r") < F.col("rise")]
    on = same[0]
    for c in same[1:]:
        on = on & c
    level = numbered.join(after, on, "left").groupBy(*by, "rise", "_j").agg(F.max("_y").alias("_y"), F.first("w").alias("w"))
    held = level.groupBy(*by, "rise").agg(F.first("w").alias("w"), F.map_from_entries(F.collect_list(F.when(F.col("_j").isNotNull(), F.struct("_j", "_y")))).alias("_m"))
    return held.select(*by, F.col("rise").cast("long").alias("rise"), "w", F.transform(F.sequence(F.lit(1), F.lit(spec.m)), lambda j: F.coalesce(F.element_at("_m", j), F.lit(spec.low))).alias("registers"))


__all__ = ["placed", "project", "local_rises", "rises", "trajectory", "estimate", "as_of", "above_floors", "var_from_trace", "rise_prob_registers", "rise_prob_hist", "states"]
