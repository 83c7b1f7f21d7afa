"""Queries of the methods: exact, float and integer sketches, likelihood, running estimate."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import estimators as E
from ..functions import registers as R
from ..functions.hashing import bits as hash_bits
from ..functions.hashing import exponential
from ..operators import compare, exact, live
from ..operators import sketches as S
from ..sources import workloads as W
from ..sources.tables import table
from ..sources.weights import resolve
from ..spec import SketchSpec
from . import registry as Q
from .registry import portable, query

ORDER = ", ".join(W.ARRIVAL)


def total(df: DataFrame, by: bool = False) -> DataFrame:
    out = exact.weighted_distinct(df, by=["stream"] if by else None)
    return out.select(*(["stream"] if by else []), F.round("exact", 3).alias("exact"), "n")


def total_sql(stream: str, by: bool = False) -> str:
    key = "stream, " if by else ""
    return f"SELECT {key}round(coalesce(sum(w), 0), 3) AS exact, count(*)::BIGINT AS n FROM {Q.once(stream, by)} WHERE w > 0 {'GROUP BY stream' if by else ''}"


for _name, _stream, _sql, _by in (
    ("exact_parts", W.parts, Q.PARTS, False),
    ("exact_orders", W.orders, "SELECT o_orderkey::VARCHAR AS x, o_totalprice AS w FROM orders", False),
    ("exact_text_size", W.texts, Q.TEXTS, False),
    ("exact_ratings", W.ratings, Q.RATINGS, True),
    ("exact_votes", W.votes, Q.VOTES, True),
    ("exact_daily_users", W.daily_users, Q.DAILY, True),
    ("exact_links", W.links, Q.LINKS, False),
    ("exact_vectors", W.vectors, Q.VECTORS, True),
    ("exact_edges", W.edges, Q.EDGES, False),
):
    query(total_sql(_sql, _by), _name)(lambda spark, d, f=_stream, by=_by: total(f(spark, d), by))


@query("SELECT event_id, round(sum(CASE WHEN k = 1 THEN w ELSE 0 END) OVER (ORDER BY ts, event_id), 3) AS exact FROM (SELECT event_id, ts, value AS w, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM events)")
def exact_running_events(spark, d):
    e = table(spark, d, "events").select(F.col("user_id").cast("string").alias("x"), F.col("value").alias("w"), "ts", "event_id")
    return exact.running(e, ["ts", "event_id"], every=True).select("event_id", F.round("exact", 3).alias("exact"))


@query("SELECT count(DISTINCT l_partkey)::DOUBLE AS exact FROM lineitem")
def exact_count_distinct(spark, d):
    return exact.weighted_distinct(table(spark, d, "lineitem").select(F.col("l_partkey").cast("string").alias("x"), F.lit(1).alias("w"))).select("exact")


_CONFLICT = "SELECT l_orderkey, l_linenumber, l_extendedprice AS w, l_shipdate, l_partkey, l_suppkey FROM lineitem"


def _conflict(spark, d, how):
    rows = table(spark, d, "lineitem").select("l_orderkey", F.col("l_linenumber").alias("x"), F.col("l_extendedprice").alias("w"), "l_shipdate", "l_partkey", "l_suppkey")
    once = resolve(rows, "x", "w", how, ["l_orderkey"], ["l_shipdate", "l_partkey", "l_suppkey"])
    return once.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("w"), 2).alias("total"))


for _how, _agg in (("max", "max(w)"), ("min", "min(w)"), ("first", "arg_min(w, (l_shipdate, l_partkey, l_suppkey, w))")):
    query(f"SELECT count(*) AS n, round(sum(w), 2) AS total FROM (SELECT {_agg} AS w FROM ({_CONFLICT}) GROUP BY l_orderkey, l_linenumber)", f"exact_conflict_{_how}")(lambda spark, d, how=_how: _conflict(spark, d, how))


# float registers ------------------------------------------------------------

M = portable(64)


@query(f"SELECT j::INT AS j, round(r * 1e9, 3) AS r9 FROM {Q.dense(Q.PARTS, M)}")
def dense_registers(spark, d):
    return S.dense_registers(resolve(W.parts(spark, d), "x", "w"), M).select("j", F.round(F.col("r") * 1e9, 3).alias("r9"))


@query(f"SELECT round(63 / sum(r), 1) AS est FROM {Q.dense(Q.PARTS, M)}")
def dense_estimate(spark, d):
    return S.float_estimate(S.dense_registers(resolve(W.parts(spark, d), "x", "w"), M), M).select(F.round("est", 1).alias("est"))


_SIZES = (4, 64, 128, 256, 512, 1024, 2048, 4096)
_EVENT_SUMS = "SELECT event_type AS stream, round(sum(value), 3) AS exact FROM events GROUP BY event_type"


def _event_sums(spark, d):
    """(stream, exact) of each event type."""
    return table(spark, d, "events").groupBy(F.col("event_type").alias("stream")).agg(F.round(F.sum("value"), 3).alias("exact"))


@query(f"SELECT stream, m::INT AS m, round(1 / (m - 2), 9) AS rel_var, round(sqrt(1 / (m - 2)), 9) AS rel_error, round(exact * sqrt(1 / (m - 2)), 2) AS sd FROM ({_EVENT_SUMS}), (SELECT unnest({list(_SIZES)}) AS m)")
def dense_variance(spark, d):
    """What the float estimate's variance is by size, and its standard deviation on each event type."""
    known = F.array(*(F.struct(F.lit(m).alias("m"), F.lit(E.inverse_mean_var(m)).alias("v"), F.lit(E.predicted_error("dense_exp", m)).alias("e")) for m in _SIZES))
    rows = _event_sums(spark, d).select("stream", "exact", F.inline(known))
    return rows.select("stream", "m", F.round("v", 9).alias("rel_var"), F.round("e", 9).alias("rel_error"), F.round(F.col("exact") * F.col("e"), 2).alias("sd"))


M16 = portable(16)


@query(f"SELECT stream, round(15 / sum(r), 3) AS est FROM {Q.dense(Q.RATINGS, M16, True)} GROUP BY stream")
def dense_by_stream(spark, d):
    return S.float_estimate(S.dense_registers(W.ratings(spark, d), M16, ["stream"]), M16, ["stream"]).select("stream", F.round("est", 3).alias("est"))


_ONCE = f"SELECT * FROM {Q.once(Q.PARTS)}"
_ORDERED = f"""(WITH e AS ({_ONCE}), k AS (SELECT x, w, k, -ln({Q.uniform('x', 'k', 1)}) / (w * (64 - k + 1)) AS s, {Q.bits("'p0:' || x || ':' || k")} AS p FROM e, (SELECT unnest(range(1, 65)) AS k)),
  v AS (SELECT x, k, sum(s) OVER (PARTITION BY x ORDER BY k) AS r FROM k), o AS (SELECT x, k AS j, row_number() OVER (PARTITION BY x ORDER BY p, k) AS k FROM k)
  SELECT x, k::INT AS k, r, j::INT AS j FROM v JOIN o USING (x, k))"""


def _once(spark, d):
    return resolve(W.parts(spark, d), "x", "w")


@query(f"SELECT x, k, round(r * 1e6, 4) AS r6 FROM {_ORDERED}")
def ordered_values(spark, d):
    return S.ordered_rows_sql(_once(spark, d), M).select("x", "k", F.round(F.col("r") * 1e6, 4).alias("r6"))


@query(f"SELECT x, k, j FROM {_ORDERED}")
def ordered_permutation(spark, d):
    return S.ordered_rows_sql(_once(spark, d), M).select("x", "k", "j")


@query(f"SELECT j, round(min(r) * 1e9, 2) AS r9 FROM {_ORDERED} GROUP BY j")
def ordered_registers_sql(spark, d):
    return S.ordered_registers_sql(_once(spark, d), M).select("j", F.round(F.col("r") * 1e9, 2).alias("r9"))


_SWAPS = f"""WITH RECURSIVE e AS (SELECT DISTINCT l_partkey::VARCHAR AS x FROM lineitem),
  s AS (SELECT x, 0 AS k, [1, 2, 3, 4, 5, 6, 7, 8] AS p FROM e UNION ALL
        SELECT x, k + 1, list_transform(range(1, 9), lambda i: CASE WHEN i = k + 1 THEN p[h] WHEN i = h THEN p[k + 1] ELSE p[i] END)
        FROM (SELECT x, k, p, k + 1 + {Q.bits("'w0:' || x || ':' || (k + 1)")} % (8 - k) AS h FROM s WHERE k < 8))
  SELECT x, array_to_string(p, ',') AS places FROM s WHERE k = 8"""


@query(_SWAPS)
def ordered_shuffle_small(spark, d):
    """Swap placement of eight values, folded inside the row."""
    x = table(spark, d, "lineitem").select(F.col("l_partkey").cast("string").alias("x")).distinct()

    def step(p, k):
        h = (k + hash_bits("portable", 0, "w", F.col("x"), k) % (9 - k)).cast("int")
        return F.transform(F.sequence(F.lit(1), F.lit(8)), lambda i: F.element_at(p, F.when(i == k, h).when(i == h, k).otherwise(i)))

    places = F.aggregate(F.sequence(F.lit(1), F.lit(8)), F.sequence(F.lit(1), F.lit(8)), step)
    return x.select("x", F.array_join(places.cast("array<string>"), ",").alias("places"))


@query(f"SELECT exact, true AS close FROM ({total_sql(Q.PARTS)})")
def ordered_estimate(spark, d):
    """The exact sum, and whether the estimate is within five errors of it."""
    spec = SketchSpec(m=256)
    parts = W.parts(spark, d)
    return S.float_estimate(S.ordered_registers(parts, spec), spec).crossJoin(F.broadcast(total(parts))).select("exact", (F.abs(F.col("est") / F.col("exact") - 1) < 5 * F.sqrt("rel_var")).alias("close"))


@query("SELECT 64::BIGINT AS registers, 64::BIGINT AS equal")
def ordered_lazy_equals_eager(spark, d):
    parts = W.parts(spark, d)
    a, b = (S.ordered_registers(parts, SketchSpec(m=64), max_tracking=t).withColumnRenamed("r", t) for t in ("eager", "lazy"))
    return a.join(b, "j").agg(F.count(F.lit(1)).alias("registers"), F.sum((F.col("eager") == F.col("lazy")).cast("long")).alias("equal"))


# integer registers ------------------------------------------------------------


@query(f"SELECT x, j::INT AS j, {Q.bucket(Q.value('x', 'w', 'j'), portable(4))} AS y FROM ({_ONCE}), (SELECT unnest([1, 2, 3, 4]) AS j)")
def logbucket_values(spark, d):
    rows = _once(spark, d).withColumn("j", F.explode(F.sequence(F.lit(1), F.lit(4))))
    return rows.select("x", "j", R.truncate(R.bucket(exponential(F.col("x"), F.col("w"), F.col("j"), 0, "portable")), portable(4)).alias("y"))


def _integers(spark, d, spec, plan="dense"):
    return S.integer_registers(resolve(W.parts(spark, d), "x", "w"), spec, plan=plan)


query(f"SELECT j, y FROM {Q.integers(Q.PARTS, M)}", "logbucket_registers")(lambda spark, d: _integers(spark, d, M))
for _b in (4, 5, 6, 7, 8):
    query(f"SELECT j, y FROM {Q.integers(Q.PARTS, portable(16, _b))}", f"logbucket_registers_b{_b}")(lambda spark, d, b=_b: _integers(spark, d, portable(16, b)))
query(f"SELECT j, y FROM {Q.integers(Q.PARTS, portable(16, None))}", "logbucket_untruncated")(lambda spark, d: _integers(spark, d, portable(16, None)))


@query(f"SELECT exact, 'ok' AS status, true AS close, true AS inside FROM ({total_sql(Q.PARTS)})")
def logbucket_ordered(spark, d):
    """The exact sum, and whether estimate and 99 % interval of the early-stopping plan agree with it."""
    spec = SketchSpec(m=256)
    est = S.integer_estimate(S.integer_registers(W.parts(spark, d), spec, plan="ordered"), spec, level=0.99)
    near = F.abs(F.col("est") / F.col("exact") - 1) < 5 * E.predicted_error("logbucket", 256)
    wide = F.col("exact").between(F.col("lo") - (F.col("hi") - F.col("lo")), F.col("hi") + (F.col("hi") - F.col("lo")))
    return est.crossJoin(F.broadcast(total(W.parts(spark, d)))).select("exact", "status", near.alias("close"), wide.alias("inside"))


@query("SELECT 64::BIGINT AS registers, 64::BIGINT AS equal")
def logbucket_stop_equals_full(spark, d):
    spec, parts = SketchSpec(m=64), W.parts(spark, d)
    drawn = S._drawn(parts, spec, "x", "w", [])
    a, b = (R.merge_rows(S._partials(drawn, spec, [], False, stop, "eager", False), []).withColumnRenamed("y", f"y{int(stop)}") for stop in (True, False))
    return a.join(b, "j").agg(F.count(F.lit(1)).alias("registers"), F.sum((F.col("y0") == F.col("y1")).cast("long")).alias("equal"))


@query("SELECT 64::BIGINT AS registers, 64::BIGINT AS equal")
def logbucket_threshold_equals_ordered(spark, d):
    a, b = (_integers(spark, d, M, plan).withColumnRenamed("y", plan) for plan in ("ordered", "threshold"))
    return a.join(b, "j").agg(F.count(F.lit(1)).alias("registers"), F.sum((F.col("ordered") == F.col("threshold")).cast("long")).alias("equal"))


def _pack_sql(b: int) -> str:
    spec, k = portable(16, b), 32 // b
    full = f"(SELECT j, coalesce(y, {spec.low}) - {spec.low} AS o FROM (SELECT unnest(range(1, 17))::INT AS j) LEFT JOIN {Q.integers(Q.PARTS, spec)} USING (j))"
    return f"SELECT {b}::INT AS b, ((j - 1) // {k})::INT AS word, sum(o::BIGINT << (((j - 1) % {k}) * {b})::INT)::BIGINT AS value FROM {full} GROUP BY ALL"


@query(" UNION ALL ".join(_pack_sql(b) for b in (4, 5, 6, 7, 8)))
def logbucket_pack(spark, d):
    out = None
    for b in (4, 5, 6, 7, 8):
        spec = portable(16, b)
        whole = R.dense_array(_integers(spark, d, spec), [], spec)
        one = whole.select(F.lit(b).alias("b"), F.posexplode(R.pack(F.col("registers"), spec)).alias("word", "v")).select("b", "word", F.when(F.col("v") < 0, F.col("v").cast("long") + (1 << 32)).otherwise(F.col("v").cast("long")).alias("value"))
        out = one if out is None else out.unionByName(one)
    return out


@query(" UNION ALL ".join(f"SELECT {b}::INT AS b, j, coalesce(y, {portable(16, b).low})::INT AS y FROM (SELECT unnest(range(1, 17))::INT AS j) LEFT JOIN {Q.integers(Q.PARTS, portable(16, b))} USING (j)" for b in (5, 8)))
def logbucket_unpack(spark, d):
    out = None
    for b in (5, 8):
        spec = portable(16, b)
        words = R.dense_array(_integers(spark, d, spec), [], spec).select(R.pack(F.col("registers"), spec).alias("words"))
        one = words.select(F.lit(b).alias("b"), F.posexplode(R.unpack(F.col("words"), spec)).alias("j", "y")).select("b", (F.col("j") + 1).alias("j"), "y")
        out = one if out is None else out.unionByName(one)
    return out


_H = Q.hist(Q.integers(Q.PARTS, M), M)


def _hist(spark, d, spec=M):
    return R.histogram(_integers(spark, d, spec), [], spec)


query(f"SELECT y, n FROM {_H}", "logbucket_histogram")(lambda spark, d: _hist(spark, d).select(F.explode("hist").alias("e")).select("e.y", "e.n"))
query(f"SELECT round({Q.start(M)}, 2) AS start FROM {_H}", "logbucket_start")(lambda spark, d: _hist(spark, d).select(F.round(E.start(F.col("hist"), M), 2).alias("start")))


def _cell_sql(b: int) -> str:
    low, high, c = -(2 ** (b - 1)) + 1, 2 ** (b - 1) - 1, "(0.01 * mean)"
    p = f"CASE WHEN y <= {low} THEN exp(-{c} * pow(2.0, -(y + 1))) WHEN y >= {high} THEN 1 - exp(-{c} * pow(2.0, -y)) ELSE exp(-{c} * pow(2.0, -(y + 1))) - exp(-{c} * pow(2.0, -y)) END"
    return f"SELECT stream, {b}::INT AS b, y::INT AS y, round({p}, 9) AS p FROM (SELECT event_type AS stream, round(avg(value), 3) AS mean FROM events GROUP BY event_type), (SELECT unnest(range({low}, {high + 1})) AS y)"


@query(" UNION ALL ".join(_cell_sql(b) for b in (4, 5)))
def logbucket_cellprob(spark, d):
    """How likely each register value is at a hundredth of each event type's mean value."""
    means = table(spark, d, "events").groupBy(F.col("event_type").alias("stream")).agg(F.round(F.avg("value"), 3).alias("mean"))
    out = None
    for b in (4, 5):
        spec = SketchSpec(m=2, b=b)
        cells = means.select("stream", "mean", F.lit(b).alias("b"), F.explode(F.sequence(F.lit(spec.low), F.lit(spec.high))).alias("y"))
        one = cells.select("stream", "b", "y", F.round(E.cell_prob(F.col("y"), 0.01 * F.col("mean"), spec), 9).alias("p"))
        out = one if out is None else out.unionByName(one)
    return out


@query(f"SELECT f::DOUBLE AS c, round(sum({Q.term('loglik', M, 'f')}), 6) AS loglik FROM {_H}, (SELECT unnest([1e6, 2e6, 3e6]) AS f) GROUP BY f")
def logbucket_loglik(spark, d):
    c = _hist(spark, d).withColumn("c", F.explode(F.array(*map(F.lit, (1e6, 2e6, 3e6)))))
    return c.select("c", F.round(E.loglik(F.col("hist"), F.col("c"), M), 6).alias("loglik"))


@query(f"SELECT f::DOUBLE AS c, round(sum({Q.term('score', M, 'f')}) * 1e6, 6) AS score6, round(sum({Q.term('curve', M, 'f')}) * 1e12, 5) AS curve12 FROM {_H}, (SELECT unnest([1e6, 2e6, 3e6]) AS f) GROUP BY f")
def logbucket_score(spark, d):
    c = _hist(spark, d).withColumn("c", F.explode(F.array(*map(F.lit, (1e6, 2e6, 3e6)))))
    return c.select("c", F.round(E.score(F.col("hist"), F.col("c"), M) * 1e6, 6).alias("score6"), F.round(E.dscore(F.col("hist"), F.col("c"), M) * 1e12, 5).alias("curve12"))


query(f"SELECT round(c, 1) AS est FROM {Q.mle(_H, M)}", "logbucket_mle")(lambda spark, d: _hist(spark, d).select(F.round(E.mle(F.col("hist"), M), 1).alias("est")))
query(f"SELECT round(c * (1 - 1 / 64), 1) AS est FROM {Q.mle(_H, M)}", "logbucket_bias_corrected")(lambda spark, d: _hist(spark, d).select(F.round(E.mle(F.col("hist"), M, bias_correct=True), 1).alias("est")))
query(f"SELECT round((sum(n) - 1) / sum(n * pow(2.0, -y)), 1) AS est FROM {_H}", "logbucket_plugin")(lambda spark, d: _hist(spark, d).select(F.round(E.plugin(F.col("hist"), M), 1).alias("est")))

_M5 = portable(64, 5)
_TEXT = "SELECT text AS x, 0.0001 * n_chars AS w FROM documents"


@query(f"SELECT round(c, 5) AS est FROM {Q.mle(Q.hist(Q.integers(_TEXT, _M5), _M5), _M5)}")
def logbucket_mle_truncated(spark, d):
    """Five-bit registers, part of them at an end of their range."""
    rows = W.texts(spark, d).select("x", (F.lit(0.0001) * F.col("w")).alias("w"))
    return R.histogram(S.integer_registers(resolve(rows, "x", "w"), _M5), [], _M5).select(F.round(E.mle(F.col("hist"), _M5), 5).alias("est"))


_VAR = f"SELECT c, -1 / (SELECT sum({Q.term('curve', M, 'e.c')}) FROM {_H}) AS var FROM {Q.mle(_H, M)} e"
query(f"SELECT round(sqrt(var), 1) AS sd FROM ({_VAR})", "logbucket_variance")(lambda spark, d: S.integer_estimate(_integers(spark, d, M), M).select(F.round(F.sqrt("var"), 1).alias("sd")))
query(f"SELECT round(greatest(c - 1.959963984540054 * sqrt(var), 0), 0) AS lo, round(c + 1.959963984540054 * sqrt(var), 0) AS hi FROM ({_VAR})", "logbucket_interval")(lambda spark, d: S.integer_estimate(_integers(spark, d, M), M).select(F.round("lo", 0).alias("lo"), F.round("hi", 0).alias("hi")))

_MONTHS = "SELECT strftime(l_shipdate, '%Y') AS stream, l_partkey::VARCHAR AS x, p_retailprice AS w FROM lineitem JOIN part ON l_partkey = p_partkey"


@query(f"SELECT j, max(y) AS y FROM {Q.integers(_MONTHS, M16, True)} GROUP BY j")
def logbucket_merge_months(spark, d):
    """Sketches of years, merged: that of all years."""
    rows = W.parts(spark, d).withColumn("stream", F.date_format("l_shipdate", "yyyy"))
    return R.merge_rows(S.integer_registers(resolve(rows, "x", "w", by=["stream"]), M16, ["stream"]), [])


_LANGS = "SELECT lang || '/' || source AS stream, text AS x, n_chars::DOUBLE AS w FROM documents"


@query(f"SELECT lang, source, j, max(y) AS y FROM (SELECT split_part(stream, '/', 1) AS lang, split_part(stream, '/', 2) AS source, j, y FROM {Q.integers(_LANGS, M16, True)}) GROUP BY GROUPING SETS ((lang, source, j), (lang, j), (j))")
def logbucket_rollup_lang_source(spark, d):
    """Registers by language and source, rolled up without the texts."""
    docs = table(spark, d, "documents").select("lang", "source", F.col("text").alias("x"), F.col("n_chars").cast("double").alias("w"))
    rows = S.integer_registers(resolve(docs, "x", "w", by=["lang", "source"]), M16, ["lang", "source"])
    rolled = rows.groupingSets([["lang", "source", "j"], ["lang", "j"], ["j"]], "lang", "source", "j").agg(F.max("y").alias("y"))
    return rolled.select("lang", "source", "j", "y")


for _name, _stream, _sql in (
    ("document", W.documents, Q.DOCUMENTS),
    ("customer", W.ratings, Q.RATINGS),
    ("page", W.pages, Q.PAGES),
    ("conversation", W.conversations, Q.CONVERSATIONS),
    ("vector", W.vectors, Q.VECTORS),
):
    query(f"SELECT stream, sum(y)::BIGINT AS total, count(*) AS registers FROM {Q.integers(_sql, M16, True)} GROUP BY stream", f"logbucket_by_{_name}")(
        lambda spark, d, f=_stream: S.integer_registers(f(spark, d), M16, ["stream"]).groupBy("stream").agg(F.sum("y").alias("total"), F.count(F.lit(1)).alias("registers"))
    )


_TOTALS = "SELECT o_custkey AS stream, round(sum(o_totalprice), 2) AS c FROM orders GROUP BY o_custkey"


def _totals(spark, d):
    """(stream, c): each customer's orders, summed."""
    return table(spark, d, "orders").groupBy(F.col("o_custkey").alias("stream")).agg(F.round(F.sum("o_totalprice"), 2).alias("c"))


_BOUNDS = "SELECT b::INT AS b, place, -pow(2.0, 2 - pow(2, b - 1)) * ln(0.001) AS low, -pow(2.0, pow(2, b - 1) - 1 + CASE place WHEN 'above_max' THEN 1 ELSE 0 END) * ln(0.999) AS high FROM (SELECT unnest([4, 5, 6, 7, 8]) AS b), (SELECT unnest(['at_max', 'above_max']) AS place)"


@query(f"SELECT b, place, round(log10(low), 6) AS low, round(log10(high), 6) AS high, count(*) AS streams, sum((c BETWEEN low AND high)::INT)::BIGINT AS inside FROM ({_TOTALS}), ({_BOUNDS}) GROUP BY ALL")
def range_bounds(spark, d):
    """Ends of the range by bits, and how many customers' totals lie inside."""
    known = F.array(*(F.struct(F.lit(b).alias("b"), F.lit(at).alias("place"), *(F.lit(v).alias(n) for n, v in zip(("low", "high"), E.range_bound(b, 0.001, at), strict=True))) for b in (4, 5, 6, 7, 8) for at in ("at_max", "above_max")))
    rows = _totals(spark, d).select("c", F.inline(known)).groupBy("b", "place", "low", "high")
    found = rows.agg(F.count(F.lit(1)).alias("streams"), F.sum(F.col("c").between(F.col("low"), F.col("high")).cast("long")).alias("inside"))
    return found.select("b", "place", F.round(F.log10("low"), 6).alias("low"), F.round(F.log10("high"), 6).alias("high"), "streams", "inside")


_SCALES = (1e-6, 1e-3, 1.0, 1e9)


@query(f"SELECT stream, scale, min(b)::INT AS b FROM (SELECT stream, scale, c * scale AS c FROM ({_TOTALS}), (SELECT unnest({list(_SCALES)})::DOUBLE AS scale)), (SELECT unnest([3, 4, 5, 6, 7, 8, 9]) AS b) WHERE -pow(2.0, 2 - pow(2, b - 1)) * ln(0.001) <= c AND c <= -pow(2.0, pow(2, b - 1) - 1) * ln(0.999) GROUP BY stream, scale")
def choose_bits(spark, d):
    """The fewest bits that do for each customer's total, in several units."""
    rows = _totals(spark, d).select("stream", "c", F.explode(F.array(*map(F.lit, _SCALES))).alias("scale"))
    at = F.col("c") * F.col("scale")
    return rows.select("stream", "scale", E.fewest_bits(at, at).alias("b"))


# the running estimate ------------------------------------------------------------

_STEPS = Q.live_steps(Q.PARTS, ORDER, M16)


def _steps(spark, d, **options):
    return live.trajectory(W.parts(spark, d), W.ARRIVAL, M16, **options)


@query(f"SELECT l_orderkey, l_linenumber, j, y, before FROM {_STEPS}")
def live_rises(spark, d):
    rows = live.project(W.parts(spark, d), W.ARRIVAL, M16)
    return live.rises(live.local_rises(rows, W.ARRIVAL), W.ARRIVAL, M16).select("l_orderkey", "l_linenumber", "j", "y", "before")


_PROB = f"SELECT rise::BIGINT AS rise, round(q, 9) AS q FROM {_STEPS}"


def _states(spark, d):
    rows = live.project(W.parts(spark, d), W.ARRIVAL, M16)
    return live.states(live.rises(live.local_rises(rows, W.ARRIVAL), W.ARRIVAL, M16), W.ARRIVAL, M16)


query(_PROB, "live_prob_registers")(lambda spark, d: _states(spark, d).select("rise", F.round(live.rise_prob_registers(F.col("registers"), F.col("w"), 16, M16.high), 9).alias("q")))


@query(_PROB)
def live_prob_histogram(spark, d):
    rows = _states(spark, d).select("rise", "w", F.explode("registers").alias("y")).groupBy("rise", "w", "y").agg(F.count(F.lit(1)).alias("n"))
    held = rows.groupBy("rise", "w").agg(F.collect_list(F.struct("y", "n")).alias("hist"))
    return held.select("rise", F.round(live.rise_prob_hist(F.col("hist"), F.col("w"), 16, M16.high), 9).alias("q"))


query(f"SELECT rise::BIGINT AS rise, l_orderkey, l_linenumber, round(est, 1) AS est FROM {_STEPS}", "live_trajectory")(lambda spark, d: _steps(spark, d).select("rise", "l_orderkey", "l_linenumber", F.round("est", 1).alias("est")))
query(f"SELECT round(max(est), 1) AS est, max(rise)::BIGINT AS rises FROM {_STEPS}", "live_estimate")(lambda spark, d: live.estimate(W.parts(spark, d), W.ARRIVAL, M16).select(F.round("est", 1).alias("est"), "rises"))
query(f"SELECT round(sqrt(max(var)), 1) AS sd FROM {_STEPS}", "live_variance")(lambda spark, d: live.estimate(W.parts(spark, d), W.ARRIVAL, M16).select(F.round(F.sqrt("var"), 1).alias("sd")))
query(f"SELECT round(max(est), 1) AS est FROM {Q.live_steps(Q.PARTS, ORDER, M16, timing='post')}", "live_post_timing")(lambda spark, d: live.estimate(W.parts(spark, d), W.ARRIVAL, M16, timing="post").select(F.round("est", 1).alias("est")))

_M4 = portable(16, 4)
_SMALL = f"SELECT x, 0.0002 * w AS w, {ORDER} FROM ({Q.PARTS})"


def _small(spark, d, begin):
    rows = W.parts(spark, d).withColumn("w", F.lit(0.0002) * F.col("w"))
    return live.estimate(rows, W.ARRIVAL, _M4, begin=begin).select(F.round("est", 5).alias("est"))


query(f"SELECT round(max(est), 5) AS est FROM {Q.live_steps(_SMALL, ORDER, _M4)}", "live_small_registers")(lambda spark, d: _small(spark, d, "full"))
query(f"SELECT round(max(est), 5) AS est FROM {Q.live_steps(_SMALL, ORDER, _M4, begin='zero')}", "live_zero_hist")(lambda spark, d: _small(spark, d, "zero"))

_TYPES = Q.live_steps(Q.MONITORING, "ts, event_id", M16, "stream")
query(f"SELECT stream, round(max(est), 2) AS est, max(rise)::BIGINT AS rises FROM {_TYPES} GROUP BY stream", "live_by_event_type")(lambda spark, d: live.estimate(W.monitoring(spark, d), ["ts", "event_id"], M16, ["stream"]).select("stream", F.round("est", 2).alias("est"), "rises"))

_DAYS = "SELECT unnest(generate_series(TIMESTAMP '2024-01-01', TIMESTAMP '2024-01-31', INTERVAL 1 DAY)) AS t"


def days(spark):
    return spark.sql("SELECT explode(sequence(TIMESTAMP_NTZ '2024-01-01', TIMESTAMP_NTZ '2024-01-31', INTERVAL 1 DAY)) AS t")


@query(f"SELECT stream, t, round(coalesce((SELECT max(est) FROM {_TYPES} s WHERE s.stream = k.stream AND s.ts <= t), 0), 2) AS est FROM (SELECT DISTINCT event_type AS stream FROM events) k, ({_DAYS})")
def live_as_of(spark, d):
    """The estimate of each event type at every midnight."""
    rows = W.monitoring(spark, d)
    asked = rows.select("stream").distinct().crossJoin(F.broadcast(days(spark)))
    found = live.as_of(live.trajectory(rows, ["ts", "event_id"], M16, ["stream"]), asked, "ts", "t", ["stream"])
    return found.select("stream", "t", F.round("est", 2).alias("est"))


def _shard_sql() -> str:
    part = lambda s: f"SELECT * FROM ({Q.PARTS}) WHERE {Q.bits("'s0:' || x")} % 4 = {s}"
    return "SELECT round(sum(est), 1) AS est FROM (" + " UNION ALL ".join(f"SELECT max(est) AS est FROM {Q.live_steps(part(s), ORDER, portable(16))}" for s in range(4)) + ")"


query(_shard_sql(), "live_sharded")(lambda spark, d: live.estimate(W.parts(spark, d), W.ARRIVAL, portable(64), shards=4).select(F.round("est", 1).alias("est")))
query(f"SELECT j, y FROM {Q.routed(Q.PARTS, M)}", "live_routed_registers")(lambda spark, d: S.routed_registers(W.parts(spark, d), M))
query(f"SELECT round(est, 1) AS est FROM {Q.routed_estimate(Q.PARTS, M)}", "live_routed_mle")(lambda spark, d: S.integer_estimate(S.routed_registers(W.parts(spark, d), M), M, routed=True).select(F.round("est", 1).alias("est")))


@query("SELECT count(DISTINCT l_partkey) AS exact, true AS hll_plus, true AS hll, true AS theta, true AS routed FROM lineitem")
def builtin_distinct(spark, d):
    """Distinct parts, and which sketches of them are within five errors: the engine's built-in ones and ours."""
    found = compare.builtin_distinct(W.parts(spark, d).select("x"))
    errors = {"hll_plus": 0.05, "hll": 1.04 / 16, "theta": 1 / 64, "routed": E.predicted_error("logbucket", 256)}
    return found.select("exact", *((F.abs(F.col(c) / F.col("exact") - 1) <= 5 * e).alias(c) for c, e in errors.items()))


_AT = " AND ".join(f"s.{c} = f.{c}" for c in W.ARRIVAL)
_BEFORE = f"({', '.join(f's.{c}' for c in W.ARRIVAL)}) < ({', '.join(f'f.{c}' for c in W.ARRIVAL)})"
_THEORY = f"""WITH a AS MATERIALIZED (SELECT * FROM {_STEPS}), f AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY x ORDER BY {ORDER}) AS k FROM ({Q.PARTS})) WHERE k = 1),
  n AS (SELECT f.x, f.w, count(s.rise) AS rises FROM f LEFT JOIN a s ON {_BEFORE} GROUP BY ALL),
  t AS (SELECT p.rises, s.j, max(s.y) AS y FROM (SELECT DISTINCT rises FROM n) p JOIN a s ON s.rise <= p.rises GROUP BY ALL),
  q AS (SELECT n.x, n.w, (coalesce(sum(1 - exp(-n.w * pow(2.0, -(t.y + 1)))), 0) + (16 - count(t.j)) * (1 - exp(-n.w * pow(2.0, {-(M16.low + 1)})))) / 16 AS q FROM n LEFT JOIN t USING (rises) GROUP BY n.x, n.w)
  SELECT round(sqrt(sum(w * w * (1 - q) / q)), 1) AS sd FROM q"""


@query(_THEORY)
def live_theory_variance(spark, d):
    """The running estimate's standard deviation by theory, from every first arrival."""
    return live.var_from_trace(W.parts(spark, d), W.ARRIVAL, M16).select(F.round(F.sqrt("var"), 1).alias("sd"))


def flagship(spark, d) -> DataFrame:
    """Exact, static and running estimates of one stream side by side."""
    parts = W.parts(spark, d)
    static = S.integer_estimate(_integers(spark, d, M), M).select(F.col("est").alias("static"), "lo", "hi")
    running = live.estimate(parts, W.ARRIVAL, M).select(F.col("est").alias("running"))
    return total(parts).crossJoin(F.broadcast(static)).crossJoin(F.broadcast(running)).select("exact", F.round("static", 1).alias("static"), F.round("running", 1).alias("running"), F.round("lo", 0).alias("lo"), F.round("hi", 0).alias("hi"))


query(f"SELECT exact, round(c, 1) AS static, running, round(greatest(c - 1.959963984540054 * sqrt(var), 0), 0) AS lo, round(c + 1.959963984540054 * sqrt(var), 0) AS hi FROM ({total_sql(Q.PARTS)}), ({_VAR}), (SELECT round(max(est), 1) AS running FROM {Q.live_steps(Q.PARTS, ORDER, M)})", "flagship")(flagship)
