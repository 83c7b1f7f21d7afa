"""Queries of the streaming forms and of the SQL functions."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import sqlfuncs
from ..operators import sketches as S
from ..plans.shared import fresh_path
from ..sources import workloads as W
from ..sources.tables import table
from ..sources.weights import law, resolve
from ..streaming import sketches as T
from . import registry as Q
from .core import M16, M
from .registry import query

_Y = Q.bucket(Q.value("event_id", "value", "j"), M16)
_J = Q.route("event_id", 16)
_EVENTS = f"(SELECT *, {_Y} AS y FROM (SELECT *, {_J}::INT AS j FROM events))"


def _rows(spark, d, keep=("ts",)):
    s = T.read(spark, d).select(F.col("event_id").cast("string").alias("x"), F.col("value").alias("w"), *keep)
    return T.routed_rows(s, M16, list(keep))


def _shown(df):
    return df.select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("start"), "j", "y")


@query(f"SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M') AS start, j, max(y) AS y FROM {_EVENTS} GROUP BY ALL")
def stream_tumbling(spark, d):
    return _shown(T.run(T.windowed_registers(_rows(spark, d), F.window("ts", "1 day"))))


@query(f"SELECT strftime(time_bucket(INTERVAL 15 MINUTE, ts) - k * INTERVAL 15 MINUTE, '%Y-%m-%d %H:%M') AS start, j, max(y) AS y FROM {_EVENTS}, (SELECT unnest([0, 1, 2, 3]) AS k) GROUP BY ALL")
def stream_sliding(spark, d):
    return _shown(T.run(T.windowed_registers(_rows(spark, d), F.window("ts", "1 hour", "15 minutes"))))


@query("""WITH g AS (SELECT user_id, ts, value, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
  s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
  SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, max(value) AS most FROM s GROUP BY user_id, k""")
def stream_session(spark, d):
    s = T.read(spark, d).groupBy(F.session_window("ts", "30 minutes").alias("window"), "user_id").agg(F.count(F.lit(1)).alias("n"), F.max("value").alias("most"))
    return T.run(s).select("user_id", F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n", "most")


@query("SELECT DISTINCT user_id FROM events")
def stream_dedupe(spark, d):
    """First arrivals within a horizon longer than the stream."""
    s = T.read(spark, d).withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["user_id"]).select("user_id")
    return T.run(s, "append")


@query(f"SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M') AS start, j, max({Q.bucket(Q.value('user_id', 'c_acctbal', 'j'), M16)}) AS y FROM (SELECT *, {Q.route('user_id', 16)}::INT AS j FROM events JOIN customer ON user_id = c_custkey WHERE c_acctbal > 0) GROUP BY ALL")
def stream_static_join(spark, d):
    """Daily users with their balance from a table."""
    s = T.read(spark, d).join(table(spark, d, "customer"), F.col("user_id") == F.col("c_custkey")).select(F.col("user_id").cast("string").alias("x"), F.col("c_acctbal").alias("w"), "ts")
    return _shown(T.run(T.windowed_registers(T.routed_rows(s, M16, ["ts"]), F.window("ts", "1 day"))))


@query(f"SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M') AS start, j, max(y) AS y FROM {_EVENTS} GROUP BY ALL")
def stream_late(spark, d):
    """The month's second half arrives first; within the watermark the first half still joins its windows."""
    path = fresh_path(spark, "late")
    e = table(spark, d, "events")
    for half in ("day(ts) > 15", "day(ts) <= 15"):
        e.where(half).coalesce(1).write.mode("append").parquet(path)
    s = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(path).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "60 days")
    rows = T.routed_rows(s.select(F.col("event_id").cast("string").alias("x"), F.col("value").alias("w"), "ts"), M16, ["ts"])
    return _shown(T.run(T.windowed_registers(rows, F.window("ts", "1 day")), "update")).groupBy("start", "j").agg(F.max("y").alias("y"))


_TYPES = Q.live_steps(Q.MONITORING, "ts, event_id", M16, "stream")


@query(f"SELECT stream, round(max(est), 2) AS est, max(rise)::BIGINT AS rises FROM {_TYPES} GROUP BY stream")
def stream_live(spark, d):
    """The running estimate by event type, in keyed state."""
    s = T.read(spark, d).select(F.col("event_type").alias("stream"), F.col("event_id").cast("string").alias("x"), F.col("value").alias("w"), "ts", "event_id")
    out = T.run(T.live_stream(s, ["ts", "event_id"], M16), "update")
    return out.groupBy("stream").agg(F.round(F.max("est"), 2).alias("est"), F.max("rises").alias("rises"))


@query(f"SELECT j, max({Q.bucket(Q.value('x', 'w', 'j'), M16)}) AS y FROM (SELECT event_id::VARCHAR AS x, {Q.LAWS['uniform']} AS w, {Q.route('event_id', 16)}::INT AS j FROM events) GROUP BY j")
def stream_rate(spark, d):
    """Registers of a stream of events whose weights are drawn as they arrive."""
    x = F.col("event_id").cast("string")
    rows = T.routed_rows(T.read(spark, d).select(x.alias("x"), law("uniform", x).alias("w")), M16, [])
    return T.run(rows.groupBy("j").agg(F.max("y").alias("y")))


# SQL -----------------------------------------------------------------------------


def _view(spark, d, name: str) -> str:
    view = f"wds_{name}"
    resolve(W.parts(spark, d), "x", "w").createOrReplaceTempView(view)
    return view


@query(f"SELECT j, y FROM {Q.routed(Q.PARTS, M)}")
def sql_bucket_udf(spark, d):
    sqlfuncs.register(spark)
    v = _view(spark, d, "bucket")
    return spark.sql(f"SELECT j, max(wds_bucket(x, w, j, 0, 8)) AS y FROM (SELECT x, w, wds_route(x, 64, 0) AS j FROM {v}) GROUP BY j")


def _registers(spark, d, name: str) -> str:
    view = f"wds_{name}"
    rows = S.integer_registers(resolve(W.parts(spark, d), "x", "w"), M)
    rows.agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "y"))), lambda e: e["y"]).alias("registers")).createOrReplaceTempView(view)
    return view


@query(f"SELECT round(c, 1) AS est, 'ok' AS status FROM {Q.mle(Q.hist(Q.integers(Q.PARTS, M), M), M)}")
def sql_estimate_udf(spark, d):
    sqlfuncs.register(spark)
    return spark.sql(f"SELECT round(e.est, 1) AS est, e.status FROM (SELECT wds_estimate(registers, 8) AS e FROM {_registers(spark, d, 'estimate')})")


@query(f"SELECT j, y FROM {Q.integers(Q.PARTS, M)}")
def udtf_registers(spark, d):
    sqlfuncs.register(spark)
    return spark.sql(f"SELECT t.j, t.y FROM {_registers(spark, d, 'unnested')}, LATERAL wds_registers(registers) t")


@query("SELECT o_orderpriority AS stream, true AS close FROM orders GROUP BY 1")
def udaf_sketch(spark, d):
    """One sketch for each option by an aggregate function; whether its estimate is within five errors."""
    sqlfuncs.register(spark)
    W.votes(spark, d).distinct().createOrReplaceTempView("wds_votes")
    sketch = spark.sql("SELECT stream, sum(w) AS exact, count(*) AS n FROM wds_votes GROUP BY stream").join(spark.sql("SELECT stream, wds_sketch(xxhash64(x), w) AS registers FROM wds_votes GROUP BY stream"), "stream")
    est = sketch.withColumn("e", sqlfuncs.wds_estimate("registers", F.lit(8)))
    return est.select("stream", (F.abs(F.col("e.est") / F.col("exact") - 1) < 5 * 0.13).alias("close"))


@query("SELECT user_id, 64::BIGINT AS registers, true AS ascending FROM events WHERE value > 0 GROUP BY user_id")
def udtf_values(spark, d):
    """All ascending variables of each user, weighed by the largest value: every register once."""
    sqlfuncs.register(spark)
    users = table(spark, d, "events").where("value > 0").groupBy("user_id").agg(F.max("value").alias("w"))
    users.createOrReplaceTempView("wds_users")
    rows = "SELECT user_id, t.k, t.j, t.r, lag(t.r) OVER (PARTITION BY user_id ORDER BY t.k) AS before FROM wds_users, LATERAL wds_values(CAST(user_id AS STRING), w, 64, 1e300D) t"
    return spark.sql(f"SELECT user_id, count(DISTINCT j) AS registers, bool_and(r > before OR k = 1) AS ascending FROM ({rows}) GROUP BY user_id")
