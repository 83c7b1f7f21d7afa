"""Weights: checks, conflicts, synthetic laws and tf-idf."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..spec import SketchSpec


def clean(df: DataFrame, w: str, spec: SketchSpec = SketchSpec()) -> DataFrame:
    """Rows whose weight, cast to double, is a positive number; others are dropped or an error."""
    weight = F.col(w).cast("double")
    good = weight.isNotNull() & ~F.isnan(weight) & (weight > 0)
    if spec.on_bad_weight == "error":
        return df.withColumn(w, F.when(good, weight).otherwise(F.raise_error(F.concat(F.lit(f"weight {w} must be a positive number, not "), F.coalesce(weight.cast("string"), F.lit("null")))).cast("double")))
    return df.where(good).withColumn(w, weight)


def resolve(df: DataFrame, x: str, w: str, how: str = "max", by: list[str] | None = None, order_by: list[str] | None = None) -> DataFrame:
    """One row (by, x, w) for each element: which weight it has where it comes with several."""
    keys = [*(by or []), x]
    if how in ("max", "min"):
        return df.groupBy(*keys).agg(getattr(F, how)(w).alias(w))
    if how == "first":
        if not order_by:
            raise ValueError("the first weight needs an order")
        return df.groupBy(*keys).agg(F.min_by(w, F.struct(*order_by, w)).alias(w))
    if how != "error":
        raise ValueError(f"unknown rule {how}")
    same = df.groupBy(*keys).agg(F.min(w).alias(w), F.max(w).alias("_most"))
    said = F.raise_error(F.concat(F.lit("an element has two weights: "), F.col(x).cast("string"))).cast("double")
    return same.withColumn(w, F.when(F.col(w) == F.col("_most"), F.col(w).cast("double")).otherwise(said)).drop("_most")


def law(kind: str, x: Column, scale: float = 1.0, seed: int = 0, hash: str = "portable") -> Column:
    """A weight drawn for element x: uniform(0, 1), gauss(mean 1, variance 0.1) or gamma(shape 1, scale 2), times ``scale``.

    A Gauss weight of 0 or less is drawn again; after eight draws it is the mean.
    """
    u = lambda k: uniform(x, F.lit(k), seed + 7919, hash)
    if kind == "uniform":
        return u(1) * scale
    if kind == "gamma":
        return -2.0 * F.log(u(1)) * scale
    if kind != "gauss":
        raise ValueError(f"unknown law {kind}")
    draw = lambda k: 1 + math.sqrt(0.1) * F.sqrt(-2 * F.log(u(2 * k + 1))) * F.cos(2 * math.pi * u(2 * k + 2))
    out = F.lit(1.0)
    for k in reversed(range(8)):
        out = F.when(draw(k) > 0, draw(k)).otherwise(out)
    return out * scale


def tokens(text: Column) -> Column:
    """Runs of a-z of the lower-cased text."""
    return F.regexp_extract_all(F.lower(text), F.lit("[a-z]+"), F.lit(0))


def tfidf(df: DataFrame, key: str, text: str) -> DataFrame:
    """(key, x, w): term counts times ln(documents / documents with the term), above 0.

    Terms are counted before they are shuffled by term; only then is the
    number of documents, one row, met.
    """
    said = df.select(F.col(key), F.explode(tokens(F.col(text))).alias("x"))
    tf = said.groupBy(key, "x").agg(F.count(F.lit(1)).alias("tf"))
    # asks for tf, of which all are above 0, so that both sides of the join read one shuffle and texts are cut once
    df_ = tf.groupBy("x").agg(F.count(F.when(F.col("tf") > 0, 1)).alias("df"))
    docs = df.agg(F.count(F.lit(1)).alias("docs"))
    return tf.join(df_, "x").crossJoin(F.broadcast(docs)).where("df < docs").select(key, "x", (F.col("tf") * F.log(F.col("docs") / F.col("df"))).alias("w"))


def first_arrivals(df: DataFrame, x: str, w: str, order_by: list[str], by: list[str] | None = None) -> DataFrame:
    """The earliest row (by, x, w, order_by) of each element; a row for each element and task is shuffled."""
    keys = [*(by or []), x]
    first = df.groupBy(*keys).agg(F.min(F.struct(*order_by, w)).alias("_f"))
    return first.select(*keys, *(F.col(f"_f.{c}").alias(c) for c in [*order_by, w]))


__all__ = ["clean", "resolve", "law", "tokens", "tfidf", "first_arrivals", "Window"]
