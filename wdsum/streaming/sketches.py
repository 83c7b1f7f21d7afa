"""Sketches of unbounded streams.

Register maxima don't depend on order, so windows of them are ordinary
aggregations with watermarks. The running estimate keeps its registers and
histogram in keyed state, by stream and shard.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState

from ..functions.hashing import exponential, route
from ..functions.kernels import LiveSketch
from ..functions.registers import bucket, truncate
from ..operators.live import project
from ..plans.shared import fresh_path
from ..sources.weights import clean, law
from ..spec import SketchSpec


def read(spark: SparkSession, sf_dir: str, name: str = "events", time: str = "ts") -> DataFrame:
    """A table's files as a stream, its time column as the timestamp that watermarks need."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    s = spark.readStream.schema(schema).parquet(f"{sf_dir}/{name}*.parquet")
    return s.withColumn(time, F.col(time).cast("timestamp"))


def routed_rows(stream: DataFrame, spec: SketchSpec, keep: list[str], x: str = "x", w: str = "w") -> DataFrame:
    """(keep, j, y): the one register of each arrival and its bucket; stateless."""
    rows = clean(stream, w, spec).withColumn("j", route(F.col(x), spec.m, spec.seed, spec.hash))
    return rows.select(*keep, "j", truncate(bucket(exponential(F.col(x), F.col(w), F.col("j"), spec.seed, spec.hash)), spec).alias("y"))


def windowed_registers(rows: DataFrame, window: Column, by: list[str] | None = None) -> DataFrame:
    """(window, by, j, y): the largest bucket of each window and register."""
    return rows.groupBy(window.alias("window"), *(by or []), "j").agg(F.max("y").alias("y"))


#: a sketch in keyed state: the registers that were reached, two sums and a count
_STATE = "j array<int>, y array<int>, est double, var double, rises long"


def live_stream(stream: DataFrame, order_by: list[str], spec: SketchSpec = SketchSpec(), by: str = "stream", shards: int = 1, ttl_ms: int | None = None) -> DataFrame:
    """(by, s, est, var, rises, expired) after each micro-batch, for the streams and shards that it had rows of.

    Rows of a micro-batch are taken in order; over micro-batches the order of
    arrival rules. State is the registers that were reached, from which the
    histogram follows, and two sums. With ``ttl_ms`` a stream that had no rows for
    so long gives its estimate once more, marked expired, and is forgotten; such a
    stream needs a trigger by processing time, since one that ends when all data
    is read (as in ``run``) would wait for the silence of every stream.
    """
    rows = project(stream, order_by, spec, [by], shards=shards)
    per, low, high = spec.m // shards, spec.low, spec.high
    kind = stream.schema[by].dataType.simpleString()

    def known(state: GroupState) -> LiveSketch:
        sketch = LiveSketch(per, low, high)
        if state.exists:
            j, y, sketch.est, sketch.var, sketch.rises = state.get
            sketch.registers = dict(zip(j, y, strict=True))
            counts = Counter(y)
            counts[low] += per - len(y)
            sketch.count = {v: n for v, n in counts.items() if n}
        return sketch

    def update(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        sketch, expired = known(state), state.hasTimedOut
        if expired:
            state.remove()
        else:
            # a micro-batch in order: each of its parts is a part of this group alone
            p = pd.concat(list(parts)).sort_values(order_by, kind="stable")
            for j, y, w in zip(p["j"].tolist(), p["y"].tolist(), p["w"].tolist(), strict=True):
                sketch.add(j, y, w)
            state.update((list(sketch.registers), list(sketch.registers.values()), sketch.est, sketch.var, sketch.rises))
            if ttl_ms is not None:
                state.setTimeoutDuration(ttl_ms)
        yield pd.DataFrame({by: [key[0]], "s": [key[1]], "est": [sketch.est], "var": [sketch.var], "rises": [sketch.rises], "expired": [expired]})

    return rows.groupBy(by, "s").applyInPandasWithState(update, f"{by} {kind}, s int, est double, var double, rises long, expired boolean", _STATE, "update", "NoTimeout" if ttl_ms is None else "ProcessingTimeTimeout")


def run(stream: DataFrame, mode: str = "complete", checkpoint: str | None = None) -> DataFrame:
    """Runs a stream over all that is there now into Parquet in the shared folder, and reads that.

    A micro-batch that is done again replaces what it wrote; in complete mode the last one stands.
    """
    spark, path = stream.sparkSession, fresh_path(stream.sparkSession, "stream")

    def put(rows: DataFrame, batch: int) -> None:
        rows.write.mode("overwrite").parquet(path if mode == "complete" else f"{path}/batch={batch}")

    writer = stream.writeStream.foreachBatch(put).outputMode(mode).trigger(availableNow=True)
    writer.option("checkpointLocation", checkpoint or fresh_path(spark, "progress")).start().awaitTermination()
    try:
        return spark.read.schema(stream.schema).parquet(path).select(*stream.columns)
    except AnalysisException:  # no micro-batch, no files
        return spark.createDataFrame([], stream.schema)


def rate(spark: SparkSession, per_batch: int = 1000, batches_apart_ms: int = 1000) -> DataFrame:
    """A made-up stream (x, w, ts), the same in every run: ``per_batch`` new elements in each micro-batch."""
    s = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", per_batch).option("advanceMillisPerBatch", batches_apart_ms).option("startTimestamp", 1_704_067_200_000).load()
    x = F.col("value").cast("string")
    return s.select(x.alias("x"), law("uniform", x).alias("w"), F.col("timestamp").alias("ts"))


def to_store(stream: DataFrame, path: str, checkpoint: str, mode: str = "append") -> None:
    """Runs a stream over all that is there now, into a Parquet sketch store."""
    stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
