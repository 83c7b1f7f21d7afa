"""Float and integer sketches that merge: dense, ordered with early stop, threshold and routed plans.

Long rows (by, j, r) or (by, j, y) are the common form. Whatever the plan, tasks
first reduce their own rows, so a merge shuffles at most a row for each task,
stream and register.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import estimators
from ..functions.hashing import SCALE, bits, exponential, route, tail, uniform
from ..functions.kernels import OrderedSketch
from ..functions.md5 import bits52
from ..functions.registers import bucket, histogram, merge_rows, truncate
from ..plans.shared import kept, small
from ..sources.weights import clean
from ..spec import SketchSpec


def _expanded(df: DataFrame, w: str, spec: SketchSpec) -> DataFrame:
    return clean(df, w, spec).withColumn("j", F.explode(F.sequence(F.lit(1), F.lit(spec.m))))


#: numbers of elements and registers that a task has at once in ``stream_minima``
AT_ONCE = 1 << 22


def stream_minima(df: DataFrame, spec: SketchSpec, key: str, x: str = "x", w: str = "w") -> DataFrame:
    """(key, minima): the registers of ``dense_registers`` as an array of m for each stream, portable hash.

    A stream's rows must be in one task. They are sorted by stream there, so that
    a task holds one stream's registers besides those of a part of its rows. A
    part's numbers are drawn once for each of its different elements.

    One hash serves all methods that take m variables of an element: fewer
    registers are the first ones, and a register's largest bucket is that of its
    smallest variable, as buckets fall where variables grow.
    """
    rows = clean(df, w, spec).select(key, tail(F.col(x)).alias("x"), F.col(w).alias("w")).sortWithinPartitions(key)
    m, head = spec.m, str(spec.seed).encode()
    ends = [b":%d" % j for j in range(1, m + 1)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: tuple[pa.Array, np.ndarray] | None = None

        def part(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            nonlocal last
            t = pa.Table.from_batches(held).combine_chunks()
            streams, names = (t.column(i).combine_chunks().dictionary_encode("encode") for i in (0, 1))
            logs = np.log((bits52(names.dictionary, head, ends) + 0.5) / SCALE)
            values = logs[names.indices.to_numpy()]
            values /= -t.column(2).to_numpy()[:, None]
            stream = streams.indices.to_numpy()
            edge = np.flatnonzero(np.diff(stream, prepend=-1))
            least, label = np.minimum.reduceat(values, edge, axis=0), streams.dictionary.take(pa.array(stream[edge]))
            if last is not None:
                if last[0].equals(label[:1]):
                    np.minimum(least[0], last[1], out=least[0])
                else:
                    yield told(last[0], last[1][None])
            if len(edge) > 1:
                yield told(label[:-1], least[:-1])
            last = label[-1:], least[-1].copy()

        def told(label: pa.Array, least: np.ndarray) -> pa.RecordBatch:
            return pa.record_batch([label, pa.ListArray.from_arrays(pa.array(np.arange(len(label) + 1, dtype=np.int32) * m), pa.array(least.ravel()))], names=[key, "minima"])

        held: list[pa.RecordBatch] = []
        size = 0
        for b in batches:
            # a batch may be longer than a part
            for i in range(0, b.num_rows, step := max(1, AT_ONCE // m)):
                some = b.slice(i, step)
                if size and size + some.num_rows > step:
                    yield from part(held)
                    held, size = [], 0
                held.append(some)
                size += some.num_rows
        if size:
            yield from part(held)
        if last is not None:
            yield told(last[0], last[1][None])

    return rows.mapInArrow(run, f"{key} {rows.schema[key].dataType.simpleString()}, minima array<double>")


def _first_minima(minima: DataFrame, spec: SketchSpec, by: list[str]) -> DataFrame:
    """(by, j, r) of the first m registers of ``stream_minima``."""
    return minima.select(*by, F.posexplode(F.slice("minima", 1, spec.m)).alias("_i", "r")).select(*by, (F.col("_i") + 1).alias("j"), "r")


def dense_registers(df: DataFrame, spec: SketchSpec = SketchSpec(), by: list[str] | None = None, x: str = "x", w: str = "w", minima: DataFrame | None = None) -> DataFrame:
    """(by, j, r): m independent exponentials for each element, smallest kept; m times the arrivals in work.

    ``minima``: the stream's ``stream_minima`` of m registers or more, if worked out already.
    """
    if minima is not None:
        return _first_minima(minima, spec, by or [])
    rows = _expanded(df, w, spec).select(*(by or []), "j", exponential(F.col(x), F.col(w), F.col("j"), spec.seed, spec.hash).alias("r"))
    return rows.groupBy(*(by or []), "j").agg(F.min("r").alias("r"))


def float_estimate(registers: DataFrame, spec: SketchSpec, by: list[str] | None = None) -> DataFrame:
    """(by, est, rel_var) from float registers, all of which an element has reached."""
    return registers.groupBy(*(by or [])).agg(estimators.inverse_mean(F.sum("r"), spec.m).alias("est")).withColumn("rel_var", F.lit(estimators.inverse_mean_var(spec.m) if spec.m > 2 else None).cast("double"))


def ordered_rows_sql(df: DataFrame, spec: SketchSpec, x: str = "x", w: str = "w", by: list[str] | None = None) -> DataFrame:
    """(by, x, w, k, r, j): all ascending variables of each element by windows.

    The k-th is the (k-1)-th and a spacing of rate (m - k + 1) w; registers come
    in the order of a second hash. The law of ``dense_registers``, other values.
    """
    by = by or []
    rows = clean(df, w, spec).select(*by, F.col(x).alias("x"), F.col(w).alias("w")).withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(spec.m))))
    own = Window.partitionBy(*by, "x", "w")
    spacing = -F.log(uniform(F.col("x"), F.col("k"), spec.seed + 1, spec.hash)) / (F.col("w") * (spec.m - F.col("k") + 1))
    place = bits(spec.hash, spec.seed, "p", F.col("x"), F.col("k"))
    shuffled = rows.withColumns({"_s": spacing, "_p": place})
    values = shuffled.withColumn("r", F.sum("_s").over(own.orderBy("k").rowsBetween(Window.unboundedPreceding, 0)))
    # k-th value to the register of the k-th smallest hash
    slots = shuffled.select(*by, "x", "w", F.col("k").alias("j"), F.row_number().over(own.orderBy("_p", "k")).alias("k"))
    return values.select(*by, "x", "w", "k", "r").join(slots, [*by, "x", "w", "k"])


def ordered_registers_sql(df: DataFrame, spec: SketchSpec, x: str = "x", w: str = "w", by: list[str] | None = None) -> DataFrame:
    once = clean(df, w, spec).groupBy(*(by or []), F.col(x).alias("x")).agg(F.max(w).alias("w"))
    return ordered_rows_sql(once, spec, "x", "w", by).groupBy(*(by or []), "j").agg(F.min("r").alias("r"))


#: registers of all streams that a task holds before it passes them on
HELD_REGISTERS = 1 << 22
#: one element in so many is looked at for the level that the threshold plan starts from
SAMPLED = 64


def first_variable(x, w, spec: SketchSpec):
    """The smallest of an element's m variables in the ordered plans: one draw, in the JVM."""
    return -F.log((bits("fast", spec.seed, "o", x) + 0.5) / float(1 << 52)) / (w * spec.m)


def _drawn(df: DataFrame, spec: SketchSpec, x: str, w: str, by: list[str]) -> DataFrame:
    """(by, key, w, first): what the ordered kernels need of each arrival."""
    text = F.col(x).cast("string")
    return clean(df, w, spec).select(*by, F.xxhash64(F.lit(spec.seed), text).alias("key"), F.col(w).alias("w")).withColumn("first", first_variable(F.col("key"), F.col("w"), spec))


def _partials(drawn: DataFrame, spec: SketchSpec, by: list[str], floats: bool, early_stop: bool, tracking: str, counters: bool) -> DataFrame:
    """One sketch for each task and stream, as long rows; or the kernels' counters. From (by, key, w, first).

    A task that holds many registers passes its sketches on and begins anew: they
    merge all the same.
    """
    # several columns make one name; a single one is its own
    name = F.to_json(F.struct(*by)) if len(by) > 1 else F.col(by[0]) if by else F.lit(0)
    rows = drawn.select(name.alias("by"), "key", "w", "first")
    kind = rows.schema["by"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sketches: dict[object, OrderedSketch] = {}
        stream = None

        def flush() -> Iterator[pa.RecordBatch]:
            label = lambda values: pa.array(values, stream)
            if counters:
                held = list(sketches.values())
                yield pa.record_batch([label(list(sketches)), *(pa.array([getattr(s, c) for s in held], pa.int64()) for c in ("arrivals", "draws", "refreshes"))], names=["by", "arrivals", "draws", "refreshes"])
            else:
                for k, s in sketches.items():
                    reached = np.flatnonzero(np.isfinite(s.registers) if floats else s.registers > spec.low)
                    values = pa.array(s.registers[reached]) if floats else pa.array(s.registers[reached].astype(np.int32))
                    yield pa.record_batch([label([k] * len(reached)), pa.array((reached + 1).astype(np.int32)), values], names=["by", "j", "r" if floats else "y"])
            sketches.clear()

        for b in batches:
            stream = b.schema.field(0).type
            key, weight, first = b.column(1).to_numpy().view(np.uint64), b.column(2).to_numpy(), b.column(3).to_numpy()
            groups = b.column(0).dictionary_encode()
            at, names = groups.indices.to_numpy(zero_copy_only=False), groups.dictionary.to_pylist()
            if groups.null_count:
                names = [*names, None]
                at = np.where(np.isnan(at.astype(float)), len(names) - 1, np.nan_to_num(at)).astype(np.int64)
            order = np.argsort(at, kind="stable")
            edge = np.searchsorted(at[order], np.arange(len(names) + 1))
            for g, label in enumerate(names):
                part = order[edge[g] : edge[g + 1]]
                if label not in sketches:
                    sketches[label] = OrderedSketch(spec.m, spec.low, spec.high, floats, early_stop, tracking)
                sketches[label].add(key[part], weight[part], first[part])
                if len(sketches) * spec.m >= HELD_REGISTERS:
                    yield from flush()
        if stream is not None:
            yield from flush()

    schema = f"by {kind}, arrivals long, draws long, refreshes long" if counters else f"by {kind}, j int, {'r double' if floats else 'y int'}"
    out = rows.mapInArrow(run, schema)
    if not by:
        return out.drop("by")
    if len(by) == 1:
        return out.withColumnRenamed("by", by[0])
    kinds = ", ".join(f"{c} {drawn.schema[c].dataType.simpleString()}" for c in by)
    return out.withColumn("_k", F.from_json("by", kinds)).select(*(F.col(f"_k.{c}").alias(c) for c in by), *(c for c in out.columns if c != "by"))


def _above_level(drawn: DataFrame, spec: SketchSpec, by: list[str]) -> tuple[DataFrame, DataFrame]:
    """(arrivals whose first variable can still raise a register, integer registers of some elements).

    A register only rises, so what some elements have raised all registers to is
    a lower bound at the end. Streams of too many to broadcast keep all arrivals.
    """
    some = kept(merge_rows(_partials(drawn.where(F.pmod("key", F.lit(SAMPLED)) == 0), spec, by, False, True, "eager", False), by))
    level = some.groupBy(*by).agg(F.when(F.count(F.lit(1)) == spec.m, F.min("y")).alias("_level"))
    if by:
        level = small(level.where("_level is not null"))
        if level is None:
            return drawn, some
    known = drawn.join(level, by, "left") if by else drawn.crossJoin(F.broadcast(level))  # without streams the level is one row
    first = truncate(bucket(F.col("first")), spec)
    return known.where(F.col("_level").isNull() | (first > F.col("_level"))).drop("_level"), some


def ordered_registers(df: DataFrame, spec: SketchSpec = SketchSpec(), by: list[str] | None = None, x: str = "x", w: str = "w", early_stop: bool = True, max_tracking: str = "eager") -> DataFrame:
    """(by, j, r): float registers from ascending variables, stopped once none can change."""
    return _partials(_drawn(df, spec, x, w, by or []), spec, by or [], True, early_stop, max_tracking, False).groupBy(*(by or []), "j").agg(F.min("r").alias("r"))


def work_counters(df: DataFrame, spec: SketchSpec = SketchSpec(), x: str = "x", w: str = "w", floats: bool = False, early_stop: bool = True, max_tracking: str = "eager") -> DataFrame:
    """(arrivals, draws, refreshes) of the ordered kernels, summed over tasks."""
    each = _partials(_drawn(df, spec, x, w, []), spec, [], floats, early_stop, max_tracking, True)
    return each.agg(*(F.sum(c).alias(c) for c in ("arrivals", "draws", "refreshes")))


def integer_registers(df: DataFrame, spec: SketchSpec = SketchSpec(), by: list[str] | None = None, x: str = "x", w: str = "w", plan: str = "dense", minima: DataFrame | None = None) -> DataFrame:
    """(by, j, y): integer registers; those at the lowest value have no row.

    ``plan``: "dense" computes all m variables of each element in the JVM,
    "ordered" runs the early-stopping kernel (other values, same law),
    "threshold" finds a level that every register passes from a share of the
    elements, and lets only those reach the kernel whose first variable, drawn in
    the JVM, can pass it (the values of "ordered"). ``minima``: as for
    ``dense_registers``, for the dense plan.
    """
    by = by or []
    if plan == "dense" and minima is not None:
        return _first_minima(minima, spec, by).select(*by, "j", truncate(bucket(F.col("r")), spec).alias("y")).where(F.col("y") > spec.low)
    if plan == "dense":
        value = truncate(bucket(exponential(F.col(x), F.col(w), F.col("j"), spec.seed, spec.hash)), spec)
        rows = _expanded(df, w, spec).select(*by, "j", value.alias("y"))
        return merge_rows(rows, by).where(F.col("y") > spec.low)
    if plan not in ("ordered", "threshold"):
        raise ValueError(f"unknown plan {plan}")
    drawn = _drawn(df, spec, x, w, by)
    if plan == "ordered":
        return merge_rows(_partials(drawn, spec, by, False, True, "eager", False), by)
    rest, some = _above_level(drawn, spec, by)
    return merge_rows(_partials(rest, spec, by, False, True, "eager", False).unionByName(some), by)


def routed_registers(df: DataFrame, spec: SketchSpec = SketchSpec(), by: list[str] | None = None, x: str = "x", w: str = "w") -> DataFrame:
    """(by, j, y): each element reaches one register only: one value for each arrival, nothing expanded."""
    j = route(F.col(x), spec.m, spec.seed, spec.hash)
    rows = clean(df, w, spec).select(*(by or []), j.alias("j"), x, w)
    rows = rows.select(*(by or []), "j", truncate(bucket(exponential(F.col(x), F.col(w), F.col("j"), spec.seed, spec.hash)), spec).alias("y"))
    return merge_rows(rows, by or []).where(F.col("y") > spec.low)


def integer_estimate(registers: DataFrame, spec: SketchSpec, by: list[str] | None = None, routed: bool = False, level: float = 0.95, many: bool = False) -> DataFrame:
    """(by, hist, est, var, lo, hi, status) by maximum likelihood from integer registers; ``many`` streams are solved side by side."""
    hist = histogram(registers, by or [], spec)
    used = estimators.reached(F.col("hist"), spec) if routed else F.col("hist")
    scale = estimators.held(F.col("hist"), spec) if routed else F.lit(1)
    out = hist.withColumns({"_h": used, "_k": scale, "status": estimators.status(F.col("hist"), spec)}).withColumn("_c", (estimators.mle_columns if many else estimators.mle)(F.col("_h"), spec))
    out = out.withColumns({"est": F.col("_k") * F.col("_c"), "var": F.col("_k") * F.col("_k") * estimators.mle_var(F.col("_h"), F.col("_c"), spec)})
    lo, hi = estimators.interval(F.col("est"), F.col("var"), level)
    return out.withColumns({"lo": lo, "hi": hi}).select(*(by or []), "hist", "est", "var", "lo", "hi", "status")
