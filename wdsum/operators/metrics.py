"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.estimators import memory_bits, predicted_error


def rrmse(df: DataFrame, by: list[str] | None = None, est: str = "est", truth: str = "exact") -> DataFrame:
    """(by, rrmse) over runs of one stream: root mean squared error as a part of the truth."""
    return df.groupBy(*(by or [])).agg((F.sqrt(F.avg(F.pow(F.col(est) - F.col(truth), 2))) / F.avg(truth)).alias("rrmse"))


def aare(df: DataFrame, by: list[str] | None = None, est: str = "est", truth: str = "exact") -> DataFrame:
    """(by, aare) over streams: mean of the errors' absolute parts of the truths."""
    return df.groupBy(*(by or [])).agg(F.avg(F.abs(F.col(est) - F.col(truth)) / F.abs(F.col(truth))).alias("aare"))


def bias(df: DataFrame, by: list[str] | None = None, est: str = "est", truth: str = "exact") -> DataFrame:
    """(by, bias, bias_se) relative to the truth, with its standard error over runs."""
    rel = (F.col(est) - F.col(truth)) / F.col(truth)
    return df.groupBy(*(by or [])).agg(F.avg(rel).alias("bias"), (F.stddev_samp(rel) / F.sqrt(F.count(F.lit(1)))).alias("bias_se"))


def coverage(df: DataFrame, by: list[str] | None = None, truth: str = "exact", lo: str = "lo", hi: str = "hi") -> DataFrame:
    """(by, coverage): how often the interval holds the truth."""
    return df.groupBy(*(by or [])).agg(F.avg(F.col(truth).between(F.col(lo), F.col(hi)).cast("double")).alias("coverage"))


def truncation_rate(registers: DataFrame, low: int, high: int, m: int, by: list[str] | None = None) -> DataFrame:
    """(by, truncated): the share of the m registers at either end; registers without a row are at the lowest."""
    inner = F.sum(F.when((F.col("y") > low) & (F.col("y") < high), 1).otherwise(0))
    return registers.groupBy(*(by or [])).agg((1 - inner / m).alias("truncated"))


def theory_ratio(df: DataFrame, method: str, m: int, error: str = "rrmse") -> DataFrame:
    return df.withColumn("ratio", F.col(error) / predicted_error(method, m))


def replicates(df: DataFrame, seeds: Iterable[int]) -> DataFrame:
    """df once for each seed, in one job; elements get the seed in front so that every run hashes anew."""
    seeds = list(seeds)
    return df.withColumn("seed", F.explode(F.array(*map(F.lit, seeds)))).withColumn("x", F.concat(F.col("seed").cast("string"), F.lit("/"), F.col("x")))


def throughput(run: Callable[[], DataFrame], n: int) -> float:
    """Millions of arrivals a second, up to and with the sketch."""
    begin = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return n / (time.perf_counter() - begin) / 1e6


def estimation_time(run: Callable[[], DataFrame]) -> float:
    """Seconds from stored sketches to answers."""
    begin = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - begin


__all__ = ["rrmse", "aare", "bias", "coverage", "truncation_rate", "theory_ratio", "replicates", "throughput", "estimation_time", "memory_bits", "predicted_error"]
