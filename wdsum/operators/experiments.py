"""Runs of every method over one stream or many, as the experiments compare them."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.shared import kept
from ..spec import SketchSpec
from . import live
from . import sketches as S
from .exact import weighted_distinct
from .metrics import replicates

METHODS = ("dense_exp", "ordered_exp", "ordered_exp_lazy", "logbucket", "logbucket_ordered", "logbucket_live", "logbucket_routed")


def estimates(df: DataFrame, method: str, spec: SketchSpec, by: list[str], order_by: list[str] | None = None, together: bool = False, minima: DataFrame | None = None) -> DataFrame:
    """(by, est) of a method for each stream; integer methods also lo and hi.

    ``together``: a stream's rows are in one task already; ``minima``: its registers
    from ``stream_minima``, which dense plans start from.
    """
    if method == "dense_exp":
        return S.float_estimate(S.dense_registers(df, spec, by, minima=minima), spec, by).select(*by, "est")
    if method in ("ordered_exp", "ordered_exp_lazy"):
        return S.float_estimate(S.ordered_registers(df, spec, by, max_tracking="lazy" if method.endswith("lazy") else "eager"), spec, by).select(*by, "est")
    if method in ("logbucket", "logbucket_ordered"):
        return S.integer_estimate(S.integer_registers(df, spec, by, plan="ordered" if method.endswith("ordered") else "dense", minima=minima), spec, by, many=together).select(*by, "est", "lo", "hi")
    if method == "logbucket_routed":
        return S.integer_estimate(S.routed_registers(df, spec, by), spec, by, routed=True).select(*by, "est", "lo", "hi")
    if method == "logbucket_live":
        return live.estimate(df, order_by, spec, by, prune=not together).select(*by, "est")
    raise ValueError(f"unknown method {method}")


def runs(df: DataFrame, methods: Iterable[str], sizes: Iterable[int], seeds: Iterable[int], spec: SketchSpec = SketchSpec(), order_by: list[str] | None = None) -> DataFrame:
    """(method, m, seed, est, exact) over one stream without conflicts, every run in one job."""
    seeds = list(seeds)
    truth = weighted_distinct(df).select("exact")
    many = replicates(df, seeds)
    asked = df.sparkSession.range(1).select(F.explode(F.array(*map(F.lit, seeds))).alias("seed"))
    out: DataFrame | None = None
    for method in methods:
        for m in sizes:
            one = estimates(many, method, SketchSpec(m, spec.b, spec.seed, spec.hash), ["seed"], order_by)
            one = one.select(F.lit(method).alias("method"), F.lit(m).alias("m"), "seed", "est", *(F.col(c) if c in one.columns else F.lit(None).cast("double").alias(c) for c in ("lo", "hi")))
            # a run whose registers all stay at the lowest value has no rows: its estimate is 0
            one = asked.join(one, "seed", "left").withColumns({"method": F.lit(method), "m": F.lit(m), "est": F.coalesce("est", F.lit(0.0))})
            out = one if out is None else out.unionByName(one)
    return out.crossJoin(F.broadcast(truth))


def by_stream(df: DataFrame, methods: Iterable[str], sizes: Iterable[int], spec: SketchSpec = SketchSpec(), key: str = "stream", order_by: list[str] | None = None, together: bool = False) -> DataFrame:
    """(method, m, key, est, exact) over many streams.

    Streams are short, so a task's partial sketches would be about m times its
    rows. A stream's rows are brought together once instead, for all methods, and
    no register travels; ``together``: they are dealt by stream already. Methods
    that take m variables of each element share these, drawn once for the largest
    m and kept: m numbers a stream. Rows that are not dealt yet are kept too, as
    what they are made from, such as tf-idf, is the larger part of the work.
    """
    methods, sizes = list(methods), list(sizes)
    if not together:
        df = kept(df, "streams").repartition(key)
    minima = kept(S.stream_minima(df, SketchSpec(max(sizes), spec.b, spec.seed, spec.hash), key)) if spec.hash == "portable" and {"dense_exp", "logbucket"} & set(methods) else None
    truth = weighted_distinct(df, by=[key]).select(key, "exact")
    out: DataFrame | None = None
    for method in methods:
        for m in sizes:
            one = estimates(df, method, SketchSpec(m, spec.b, spec.seed, spec.hash), [key], order_by, True, minima).select(F.lit(method).alias("method"), F.lit(m).alias("m"), key, "est")
            out = one if out is None else out.unionByName(one)
    # one join for all methods: a few rows a stream, where the truth takes all of its rows
    return out.join(truth, key)
