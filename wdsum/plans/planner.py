"""Which plan a sketch of some stream should take."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.sketches import integer_registers, routed_registers
from ..spec import SketchSpec


@dataclass(frozen=True)
class Stats:
    arrivals: int
    streams: int
    tasks: int


def stats(df: DataFrame, by: list[str] | None = None) -> Stats:
    """One pass over the stream's keys."""
    row = df.agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct(F.struct(*by)).alias("s") if by else F.lit(1).alias("s")).first()
    return Stats(row.n, max(row.s, 1), int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def choose_plan(spec: SketchSpec, s: Stats) -> str:
    """ "dense" while the expansion is small, "by_stream" where streams are short, else "routed".

    A task's partial sketches take up to m rows for each stream it meets. Where
    that is more than its arrivals, bringing streams together first moves less.
    """
    per_task = s.arrivals / max(s.tasks, 1)
    met = min(s.streams, per_task)
    if s.arrivals * spec.m <= 1 << 22:
        return "dense"
    return "by_stream" if met * spec.m > per_task else "routed"


def registers(df: DataFrame, spec: SketchSpec, by: list[str] | None = None, plan: str | None = None) -> tuple[DataFrame, str]:
    """Integer registers by the plan that suits; (rows, plan). Routed ones need ``routed=True`` when estimated."""
    plan = plan or choose_plan(spec, stats(df, by))
    if plan == "routed":
        return routed_registers(df, spec, by), plan
    if plan == "by_stream" and by:
        return integer_registers(df.repartition(*by), spec, by), plan
    return integer_registers(df, spec, by), plan
