"""Queries of the relational operators around the methods."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.hashing import element_key
from ..functions.registers import merge_rows
from ..operators import exact, relational
from ..operators import sketches as S
from ..plans.shared import fresh_path
from ..sources import workloads as W
from ..sources.tables import read_csv, read_json, table, write_sketches
from ..sources.weights import clean, law, resolve
from . import registry as Q
from .core import M16, days
from .registry import portable, query


@query("SELECT count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_quantity < 10")
def op_scan_prune(spark, d):
    rows = table(spark, d, "lineitem").where((F.col("l_shipdate") >= F.lit("1996-01-01").cast("timestamp_ntz")) & (F.col("l_quantity") < 10))
    return rows.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"))


@query("SELECT event_type, round(sum(w), 1) AS exact FROM (SELECT event_type, user_id, max(CAST(json_extract_string(props, '$.k') AS DOUBLE)) AS w FROM events GROUP BY ALL) WHERE w > 0 GROUP BY event_type")
def op_json_prop(spark, d):
    """A weight out of JSON."""
    e = table(spark, d, "events").select("event_type", F.col("user_id").cast("string").alias("x"), F.get_json_object("props", "$.k").cast("double").alias("w"))
    return exact.weighted_distinct(e, by=["event_type"]).select("event_type", F.round("exact", 1).alias("exact"))


@query("SELECT count(*) AS n, round(sum(c_acctbal), 2) AS total FROM customer WHERE c_acctbal > 0")
def op_filter_weight(spark, d):
    return clean(table(spark, d, "customer"), "c_acctbal").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("c_acctbal"), 2).alias("total"))


_NATIONS = "SELECT n_name, count(*) AS n, round(sum(c_acctbal), 2) AS total FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name"


@query(_NATIONS)
def op_join_broadcast(spark, d):
    """A dimension of a bounded size (25 nations) is broadcast."""
    j = table(spark, d, "customer").join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return j.groupBy("n_name").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("c_acctbal"), 2).alias("total"))


@query("SELECT o_orderpriority, count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
def op_join_merge(spark, d):
    j = table(spark, d, "orders").hint("merge").join(table(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"))


@query("SELECT coalesce(c.c_nationkey, s.s_nationkey) AS nation, coalesce(c.n, 0) AS customers, coalesce(s.n, 0) AS suppliers FROM (SELECT c_nationkey, count(*) AS n FROM customer WHERE c_acctbal > 5000 GROUP BY 1) c FULL JOIN (SELECT s_nationkey, count(*) AS n FROM supplier WHERE s_acctbal > 5000 GROUP BY 1) s ON c_nationkey = s_nationkey")
def op_join_outer(spark, d):
    c = table(spark, d, "customer").where("c_acctbal > 5000").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("customers"))
    s = table(spark, d, "supplier").where("s_acctbal > 5000").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("suppliers"))
    return c.join(s, "nation", "full_outer").fillna(0, ["customers", "suppliers"])


for _anti, _not in ((False, ""), (True, "NOT ")):
    query(f"SELECT count(*) AS n, round(sum(p_retailprice), 2) AS total FROM part WHERE {_not}EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 49)", "op_anti" if _anti else "op_semi")(
        lambda spark, d, anti=_anti: relational.semi(table(spark, d, "part"), table(spark, d, "lineitem").where("l_quantity > 49").select(F.col("l_partkey").alias("p_partkey")), ["p_partkey"], anti).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("p_retailprice"), 2).alias("total"))
    )


@query(f"SELECT j::INT AS j, count(*) AS n, round(min({Q.uniform('s_suppkey', 'j')}), 9) AS least FROM supplier, (SELECT unnest(range(1, 9)) AS j) GROUP BY j")
def op_cross(spark, d):
    """Elements by registers: the one crossing that the dense plan needs, with a broadcast range of m."""
    from ..functions.hashing import uniform

    j = spark.range(1, 9).select(F.col("id").cast("int").alias("j"))
    rows = table(spark, d, "supplier").crossJoin(F.broadcast(j))
    return rows.groupBy("j").agg(F.count(F.lit(1)).alias("n"), F.round(F.min(uniform(F.col("s_suppkey"), F.col("j"), 0, "portable")), 9).alias("least"))


@query("SELECT b::INT AS band, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN (SELECT unnest(range(0, 10)) AS b) ON o_totalprice >= b * 50000 AND o_totalprice < (b + 1) * 50000 GROUP BY b")
def op_range_join(spark, d):
    bands = spark.range(10).select(F.col("id").cast("int").alias("band"), (F.col("id") * 50000.0).alias("lo"), ((F.col("id") + 1) * 50000.0).alias("hi"))
    return relational.interval_join(table(spark, d, "orders"), bands, "o_totalprice", "lo", "hi", 50000.0).groupBy("band").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


@query("SELECT t, count(DISTINCT user_id) AS users, count(*) AS events FROM (SELECT unnest(generate_series(TIMESTAMP '2024-01-01', TIMESTAMP '2024-01-31', INTERVAL 1 DAY)) AS t) JOIN events ON ts >= t - INTERVAL 6 HOUR AND ts < t GROUP BY t")
def op_interval_join(spark, d):
    """Arrivals in the six hours before each midnight."""
    spans = days(spark).select("t", (F.unix_seconds(F.col("t").cast("timestamp")) - 6 * 3600).cast("double").alias("a"), F.unix_seconds(F.col("t").cast("timestamp")).cast("double").alias("b"))
    events = table(spark, d, "events").select("user_id", (F.unix_micros(F.col("ts").cast("timestamp")) / 1e6).alias("s"))
    return relational.interval_join(events, spans, "s", "a", "b", 86400.0).groupBy("t").agg(F.count_distinct("user_id").alias("users"), F.count(F.lit(1)).alias("events"))


@query("SELECT k.event_type, t, (SELECT arg_max(value, (ts, event_id)) FROM events e WHERE e.event_type = k.event_type AND ts <= t) AS last_value FROM (SELECT DISTINCT event_type FROM events) k, (SELECT unnest(generate_series(TIMESTAMP '2024-01-01', TIMESTAMP '2024-01-31', INTERVAL 1 DAY)) AS t)")
def op_asof(spark, d):
    e = table(spark, d, "events")
    last = e.groupBy("event_type", "ts").agg(F.max_by("value", "event_id").alias("last_value"))
    asked = e.select("event_type").distinct().crossJoin(F.broadcast(days(spark)))
    return relational.asof_join(asked, last, ["event_type"], "t", "ts", "last_value")


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, min(l_extendedprice) AS least, max(l_extendedprice) AS most, round(sum(l_quantity), 1) AS quantity FROM lineitem GROUP BY ALL")
def op_hash_agg(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.min("l_extendedprice").alias("least"), F.max("l_extendedprice").alias("most"), F.round(F.sum("l_quantity"), 1).alias("quantity"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def op_distinct_agg(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


_SIZES = "(SELECT lang, source, text, max(n_chars)::DOUBLE AS w FROM documents GROUP BY ALL)"


def _sizes(spark, d):
    return resolve(table(spark, d, "documents"), "text", "n_chars", by=["lang", "source"]).withColumn("w", F.col("n_chars").cast("double"))


for _name, _sql in (("op_grouping_sets", "GROUPING SETS ((lang), (source))"), ("op_cube", "CUBE (lang, source)"), ("op_rollup", "ROLLUP (lang, source)")):

    def _grouped(spark, d, kind=_name):
        rows = _sizes(spark, d)
        grouped = rows.groupingSets([["lang"], ["source"]], "lang", "source") if kind == "op_grouping_sets" else getattr(rows, kind[3:])("lang", "source")
        return grouped.agg(F.count(F.lit(1)).alias("n"), F.sum("w").alias("total"))

    query(f"SELECT lang, source, count(*) AS n, sum(w) AS total FROM {_SIZES} GROUP BY {_sql}", _name)(_grouped)


@query("SELECT c_nationkey, c_custkey, r::INT AS r FROM (SELECT c_nationkey, c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) WHERE r <= 3")
def op_rank(spark, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return table(spark, d, "customer").withColumn("r", F.row_number().over(w)).where("r <= 3").select("c_nationkey", "c_custkey", "r")


@query("SELECT event_id, max(value) OVER (PARTITION BY event_type ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before FROM events")
def op_running_max(spark, d):
    w = Window.partitionBy("event_type").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return table(spark, d, "events").select("event_id", F.max("value").over(w).alias("before"))


@query("SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS last FROM events")
def op_lag(spark, d):
    return table(spark, d, "events").select("event_id", F.lag("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("last"))


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY event_type ORDER BY ts, event_id ROWS BETWEEN 9 PRECEDING AND CURRENT ROW), 3) AS ten FROM events")
def op_rows_frame(spark, d):
    w = Window.partitionBy("event_type").orderBy("ts", "event_id").rowsBetween(-9, 0)
    return table(spark, d, "events").select("event_id", F.round(F.sum("value").over(w), 3).alias("ten"))


@query("SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS hour FROM (SELECT *, epoch(ts)::BIGINT AS s FROM (SELECT event_id, event_type, date_trunc('second', ts) AS ts FROM events))")
def op_range_frame(spark, d):
    s = table(spark, d, "events").withColumn("s", F.unix_seconds(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("event_type").orderBy("s").rangeBetween(-3600, 0)
    return s.select("event_id", F.count(F.lit(1)).over(w).alias("hour"))


@query("SELECT o_custkey, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY 1 ORDER BY total DESC, o_custkey LIMIT 10")
def op_topk(spark, d):
    return table(spark, d, "orders").groupBy("o_custkey").agg(F.round(F.sum("o_totalprice"), 2).alias("total")).orderBy(F.desc("total"), "o_custkey").limit(10)


_HALVES = ("SELECT l_partkey::VARCHAR AS x, p_retailprice AS w FROM lineitem JOIN part ON l_partkey = p_partkey WHERE l_quantity <= 5", "SELECT l_partkey::VARCHAR AS x, p_retailprice AS w FROM lineitem JOIN part ON l_partkey = p_partkey WHERE l_quantity >= 48")


def _halves(spark, d):
    rows = table(spark, d, "lineitem").join(table(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey")).select(F.col("l_partkey").cast("string").alias("x"), F.col("p_retailprice").alias("w"), "l_quantity")
    return [rows.where(c).select("x", "w").distinct() for c in ("l_quantity <= 5", "l_quantity >= 48")]


@query(f"SELECT j, max(y) AS y FROM (SELECT * FROM {Q.integers(_HALVES[0], M16)} UNION ALL SELECT * FROM {Q.integers(_HALVES[1], M16)}) GROUP BY j")
def op_union(spark, d):
    """The sketch of a union, from two sketches."""
    return relational.union_registers([S.integer_registers(h, M16) for h in _halves(spark, d)], [])


for _name in ("intersect", "except"):
    query(f"SELECT count(*) AS n, round(sum(w), 2) AS total FROM ({_HALVES[0]} {_name.upper()} {_HALVES[1]})", f"op_{_name}")(
        lambda spark, d, op=_name: (lambda a, b: a.intersect(b) if op == "intersect" else a.subtract(b))(*_halves(spark, d)).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("w"), 2).alias("total"))
    )

_M = portable(64)


@query(f"SELECT round(greatest(a.c + b.c - u.c, 0), 0) AS shared FROM {Q.mle(Q.hist(Q.integers(_HALVES[0], _M), _M), _M)} a, {Q.mle(Q.hist(Q.integers(_HALVES[1], _M), _M), _M)} b, {Q.mle(Q.hist(Q.integers(f'{_HALVES[0]} UNION ALL {_HALVES[1]}', _M), _M), _M)} u")
def op_inclusion_exclusion(spark, d):
    halves = [S.integer_registers(h, _M) for h in _halves(spark, d)]
    est = lambda r, name: S.integer_estimate(r, _M).select(F.col("est").alias(name))
    all_three = est(halves[0], "a").crossJoin(F.broadcast(est(halves[1], "b"))).crossJoin(F.broadcast(est(relational.union_registers(halves, []), "u")))
    return all_three.select(F.round(relational.overlap(F.col("a"), F.col("b"), F.col("u")), 0).alias("shared"))


@query(f"SELECT doc_id, length(text) AS chars, octet_length(encode(text))::BIGINT AS bytes, md5(lower(lang)) AS lang, len(regexp_extract_all(lower(text), '[a-z]+'))::BIGINT AS words, {Q.element('lang', 'source')} AS key FROM documents")
def op_string(spark, d):
    t = F.col("text")
    return table(spark, d, "documents").select("doc_id", F.length(t).cast("long").alias("chars"), F.octet_length(t).cast("long").alias("bytes"), F.md5(F.lower("lang").cast("binary")).alias("lang"), F.size(F.regexp_extract_all(F.lower(t), F.lit("[a-z]+"), F.lit(0))).cast("long").alias("words"), element_key("lang", "source").alias("key"))


@query("SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS host, length(regexp_replace(html, '<[^>]*>', ' ', 'g')) AS chars FROM pages")
def op_url_and_tags(spark, d):
    return table(spark, d, "pages").select("page_id", F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"), F.length(F.regexp_replace("html", "<[^>]*>", " ")).cast("long").alias("chars"))


@query("SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS n, count(DISTINCT extract('dow' FROM o_orderdate)) AS weekdays, strftime(min(o_orderdate + INTERVAL 30 DAY), '%Y-%m-%d') AS due FROM orders GROUP BY 1")
def op_date(spark, d):
    o = table(spark, d, "orders")
    return o.groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month")).agg(F.count(F.lit(1)).alias("n"), F.count_distinct(F.dayofweek("o_orderdate")).alias("weekdays"), F.date_format(F.min(F.col("o_orderdate") + F.expr("INTERVAL 30 DAYS")), "yyyy-MM-dd").alias("due"))


@query("SELECT s_suppkey, round(ln(abs(s_acctbal) + 1), 9) AS ln, floor(log2(abs(s_acctbal) + 1))::BIGINT AS y, round(exp(-s_acctbal / 1e4), 9) AS e, round(sqrt(abs(s_acctbal)), 9) AS s, least(greatest(s_acctbal, 0), 5000) AS clamped, (s_suppkey << 3) & 255 AS bits FROM supplier")
def op_math(spark, d):
    a = F.col("s_acctbal")
    return table(spark, d, "supplier").select(
        "s_suppkey", F.round(F.log(F.abs(a) + 1), 9).alias("ln"), F.floor(F.log2(F.abs(a) + 1)).alias("y"), F.round(F.expm1(-a / 1e4) + 1, 9).alias("e"), F.round(F.sqrt(F.abs(a)), 9).alias("s"),
        F.least(F.greatest(a, F.lit(0.0)), F.lit(5000.0)).alias("clamped"), F.shiftleft("s_suppkey", 3).bitwiseAND(255).alias("bits"),
    )


@query("SELECT label, round(sum(list_sum(list_filter(embedding, lambda v: v > 0))), 3) AS positive, count(*) AS n, max(len(embedding))::INT AS dims FROM embeddings GROUP BY label")
def op_array(spark, d):
    positive = F.aggregate(F.filter("embedding", lambda v: v > 0), F.lit(0.0), lambda s, v: s + v.cast("double"))
    return table(spark, d, "embeddings").groupBy("label").agg(F.round(F.sum(positive), 3).alias("positive"), F.count(F.lit(1)).alias("n"), F.max(F.size("embedding")).alias("dims"))


@query("SELECT y, sum(n)::BIGINT AS n FROM (SELECT y, count(*) AS n FROM " + Q.integers(_HALVES[0], M16) + " GROUP BY y UNION ALL SELECT y, count(*) AS n FROM " + Q.integers(_HALVES[1], M16) + " GROUP BY y) GROUP BY y")
def op_map(spark, d):
    """Histograms of two sketches, added as maps."""
    maps = []
    for k, half in enumerate(_halves(spark, d)):
        counts = S.integer_registers(half, M16).groupBy("y").agg(F.count(F.lit(1)).alias("n"))
        maps.append(counts.agg(F.map_from_entries(F.collect_list(F.struct("y", "n"))).alias(f"m{k}")))
    both = maps[0].crossJoin(F.broadcast(maps[1]))
    added = F.map_zip_with("m0", "m1", lambda k, a, b: F.coalesce(a, F.lit(0)) + F.coalesce(b, F.lit(0)))
    return both.select(F.explode(F.transform_values(added, lambda k, v: v.cast("long"))).alias("y", "n"))


@query("SELECT stream, method, total FROM (SELECT stream, 'logbucket' AS method, sum(y)::BIGINT AS total FROM " + Q.integers(Q.VOTES, M16, True) + " GROUP BY stream)")
def op_struct(spark, d):
    """A sketch as one nested row, by way of JSON."""
    rows = S.integer_registers(resolve(W.votes(spark, d), "x", "w", by=["stream"]), M16, ["stream"])
    sketch = rows.groupBy("stream").agg(F.struct(F.lit("logbucket").alias("method"), F.lit(16).alias("m"), F.array_sort(F.collect_list("y")).alias("registers")).alias("sketch"))
    back = sketch.withColumn("sketch", F.from_json(F.to_json("sketch"), "method string, m int, registers array<int>"))
    return back.select("stream", F.col("sketch.method").alias("method"), F.aggregate("sketch.registers", F.lit(0).cast("long"), lambda s, y: s + y).alias("total"))


# inputs -----------------------------------------------------------------------


for _kind, _sql in Q.LAWS.items():
    query(f"SELECT event_id, round({_sql}, 9) AS w FROM events", f"synth_{_kind}")(lambda spark, d, kind=_kind: table(spark, d, "events").select("event_id", F.round(law(kind, F.col("event_id").cast("string")), 9).alias("w")))
for _name, _sql, _key, _text in (("documents", Q.DOCUMENTS, "doc_id", "text"), ("pages", Q.PAGES, None, None), ("conversations", Q.CONVERSATIONS, None, None)):
    query(f"SELECT stream, count(*) AS words, round(sum(w), 3) AS total FROM {_sql} GROUP BY stream", f"tfidf_{_name}")(lambda spark, d, f=getattr(W, _name): f(spark, d).groupBy("stream").agg(F.count(F.lit(1)).alias("words"), F.round(F.sum("w"), 3).alias("total")))



# sources and stores ---------------------------------------------------------------


@query("SELECT event_type, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY event_type")
def op_source_json(spark, d):
    """Events written as lines of JSON, and read back with their schema."""
    path = fresh_path(spark, "json")
    table(spark, d, "events").select("event_id", "event_type", "value").write.json(path)
    back = read_json(spark, path, "event_id long, event_type string, value double")
    return back.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 2).alias("total"))


@query("SELECT c_mktsegment, count(*) AS n, round(sum(c_acctbal), 2) AS total FROM customer GROUP BY c_mktsegment")
def op_source_csv(spark, d):
    """Customers written as CSV with a header, and read back with their schema."""
    path = fresh_path(spark, "csv")
    table(spark, d, "customer").select("c_custkey", "c_mktsegment", "c_acctbal").write.csv(path, header=True)
    back = read_csv(spark, path, "c_custkey long, c_mktsegment string, c_acctbal double")
    return back.groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("c_acctbal"), 2).alias("total"))


_DAYS = f"SELECT strftime(ts, '%Y-%m-%d') AS day, j, max({Q.bucket(Q.value('user_id', 'c_acctbal', 'j'), M16)}) AS y FROM (SELECT *, {Q.route('user_id', 16)}::INT AS j FROM events JOIN customer ON user_id = c_custkey WHERE c_acctbal > 0) GROUP BY ALL"


@query(f"SELECT j, max(y) AS y FROM ({_DAYS}) WHERE day BETWEEN '2024-01-08' AND '2024-01-14' GROUP BY j")
def op_sketch_store(spark, d):
    """A store of daily sketches; a week's sketch reads that week's folders only."""
    path = fresh_path(spark, "store")
    rows = W.daily_users(spark, d)
    write_sketches(S.routed_registers(rows, M16, ["stream"]).withColumnRenamed("stream", "day"), path, ["day"])
    week = spark.read.schema("j int, y int, day string").parquet(path).where(F.col("day").between("2024-01-08", "2024-01-14"))
    return merge_rows(week, [])
