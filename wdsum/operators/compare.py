"""Built-in unweighted sketches beside ours, for streams of weight 1."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..spec import SketchSpec
from .sketches import integer_estimate, routed_registers


def builtin_distinct(df: DataFrame, x: str = "x", spec: SketchSpec = SketchSpec(m=256)) -> DataFrame:
    """(exact, hll_plus, hll, theta, routed): distinct elements by each."""
    own = integer_estimate(routed_registers(df.withColumn("_one", F.lit(1.0)), spec, x=x, w="_one"), spec, routed=True).select(F.col("est").alias("routed"))
    built = df.agg(F.count_distinct(x).alias("exact"), F.approx_count_distinct(x, 0.05).alias("hll_plus"), F.hll_sketch_estimate(F.hll_sketch_agg(F.col(x).cast("string"), F.lit(8))).alias("hll"), F.theta_sketch_estimate(F.theta_sketch_agg(F.col(x).cast("string"))).alias("theta"))
    return built.crossJoin(F.broadcast(own))
