"""Laws, invariants, accuracy and plans of the sketches."""

import math
import random
import time

import pytest
from pyspark.sql import functions as F

from wdsum.functions import kernels as K
from wdsum.functions import registers as R
from wdsum.operators import exact, experiments, live, metrics, relational
from wdsum.operators import sketches as S
from wdsum.plans import planner
from wdsum.sources import weights as W
from wdsum.sources import workloads
from wdsum.spec import SketchSpec
from wdsum.streaming import sketches as T

P = SketchSpec(m=16, hash="portable")


def stream(spark, n=300, seed=1, repeats=2):
    rng = random.Random(seed)
    rows = [(str(i), rng.random() + 0.01) for i in range(n)] * repeats
    rng.shuffle(rows)
    return spark.createDataFrame([(x, w, k) for k, (x, w) in enumerate(rows)], "x string, w double, event_id long").repartition(4)


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.mark.parametrize("registers", [S.integer_registers, S.routed_registers, lambda d, s: S.integer_registers(d, s, plan="ordered"), lambda d, s: S.integer_registers(d, s, plan="threshold")])
def test_repeats_and_merging_change_nothing(spark, registers):
    df = stream(spark)
    whole = rows(registers(df, P))
    assert rows(registers(df.dropDuplicates(["x"]), P)) == whole
    parts = [registers(df.where(c), P) for c in ("event_id % 3 = 0", "event_id % 3 > 0")]
    assert rows(relational.union_registers(parts, [])) == whole


def test_threshold_plan_equals_ordered_with_streams(spark, monkeypatch):
    df = stream(spark, 3000).withColumns({"s": F.col("x").cast("int") % 3, "t": F.when(F.col("x").cast("int") % 2 == 0, "a")})
    for by in ([], ["s"], ["s", "t"], ["t"]):
        whole = rows(S.integer_registers(df, P, by, plan="ordered").select(*by, "j", "y").fillna("-"))
        assert rows(S.integer_registers(df, P, by, plan="threshold").select(*by, "j", "y").fillna("-")) == whole
        rest, _ = S._above_level(S._drawn(df, P, "x", "w", by), P, by)
        assert rest.count() < df.count()
    monkeypatch.setattr(S, "HELD_REGISTERS", 20)  # sketches are passed on again and again
    assert rows(S.integer_registers(df, P, ["s", "t"], plan="ordered").select("s", "t", "j", "y").fillna("-")) == rows(S.integer_registers(df, P, ["s", "t"], plan="threshold").select("s", "t", "j", "y").fillna("-"))


def test_floors_keep_every_rise(spark):
    df = stream(spark, 3000).withColumns({"s0": F.col("x").cast("int") % 3, "day": F.date_add(F.lit("2024-01-01"), (F.col("event_id") / 100).cast("int")), "ntz": F.col("event_id").cast("timestamp").cast("timestamp_ntz"), "name": F.format_string("%09d", "event_id")})
    for order, by in ((["event_id"], None), (["day", "event_id"], ["s0"]), (["ntz", "event_id"], None), (["name"], None)):
        projected = live.project(df, order, P, by)
        some = live.above_floors(projected, df, order, by)
        assert some.columns == projected.columns and (order == ["name"] or some.count() < projected.count() / 4)
        assert rows(live.rises(some, order, P, by)) == rows(live.rises(projected, order, P, by))
    late = df.where("event_id = 5")
    assert live.above_floors(live.project(late, ["event_id"], P), late, ["event_id"]).count() == 1


def test_theory_of_the_running_variance(spark):
    df = workloads.generated(spark, 1000, partitions=2)
    many = metrics.replicates(df, range(60))
    spec = SketchSpec(32)
    theory = live.var_from_trace(many, ["event_id"], spec, ["seed"]).agg(F.avg("var")).first()[0]
    found = live.estimate(many, ["event_id"], spec, ["seed"])
    running, spread = found.agg(F.avg("var"), F.var_samp("est")).first()
    assert running == pytest.approx(theory, rel=0.1) and spread == pytest.approx(theory, rel=0.5)
    # by a loop
    projected = {r.event_id: r for r in live.project(df, ["event_id"], P).collect()}
    sketch, total = K.LiveSketch(16, P.low, P.high), 0.0
    for r in sorted(df.collect(), key=lambda r: r.event_id):
        q = sketch.chance(r.w)
        total += r.w**2 * (1 - q) / q
        if (p := projected.get(r.event_id)) is not None:
            sketch.add(p.j, p.y, p.w)
    assert live.var_from_trace(df, ["event_id"], P).first().var == pytest.approx(total, rel=1e-9)


def test_kernels_keep_streams_apart(spark):
    df = stream(spark, 200).withColumns({"a": F.col("x").cast("int") % 2, "b": F.lit(None).cast("string")})
    for plan in ("ordered", "dense"):
        got = rows(S.integer_registers(df, P, ["a", "b"], plan=plan).where("a = 1").select("j", "y"))
        assert got == rows(S.integer_registers(df.where("a = 1"), P, plan=plan).select("j", "y"))


def test_scaling_shifts_registers(spark):
    df, spec = stream(spark), SketchSpec(m=16, b=None, hash="portable")
    base = {r.j: r.y for r in S.integer_registers(df, spec).collect()}
    assert {r.j: r.y for r in S.integer_registers(df.withColumn("w", F.col("w") * 1024), spec).collect()} == {j: y + 10 for j, y in base.items()}


@pytest.mark.parametrize("b", [4, 5, 6, 7, 8])
def test_packing_round_trip(spark, b):
    spec = SketchSpec(m=13, b=b)
    values = [[random.Random(b).randint(spec.low, spec.high) for _ in range(13)], [spec.low] * 13, [spec.high] * 13]
    df = spark.createDataFrame([(v,) for v in values], "r array<int>")
    out = df.select("r", R.pack(F.col("r"), spec).alias("p")).select("r", "p", R.unpack(F.col("p"), spec).alias("u")).collect()
    assert all(r.r == r.u and len(r.p) == -(-13 // (32 // b)) for r in out)


def test_running_estimate_equals_a_loop(spark):
    df = stream(spark, 400, 5)
    for timing, begin, shards in (("pre", "full", 1), ("post", "full", 1), ("pre", "zero", 1), ("pre", "full", 4)):
        projected = live.project(df, ["event_id"], P, shards=shards).orderBy("event_id").collect()
        loops = {}
        for r in projected:
            loops.setdefault(r.s, K.LiveSketch(16 // shards, P.low, P.high, timing, begin)).add(r.j, r.y, r.w)
        for prune in (True, False):
            got = live.estimate(df, ["event_id"], P, shards=shards, timing=timing, begin=begin, prune=prune).first()
            assert got.est == pytest.approx(sum(s.est for s in loops.values()), rel=1e-9)
            assert got.rises == sum(s.rises for s in loops.values())


def test_arrivals_of_tiny_weight_are_looked_at_too(spark):
    """Those that no register can show are no rises, but each was looked at."""
    df = spark.range(500).select(F.col("id").cast("string").alias("x"), F.when(F.col("id") % 5 == 0, 1e-60).otherwise(1.0).alias("w"), F.col("id").alias("event_id"))
    assert live.placed(df, ["event_id"], P).count() == 500
    assert live.project(df, ["event_id"], P).count() == 400


@pytest.mark.parametrize("by", [None, ["stream"]])
def test_running_sum_keeps_every_row_if_asked(spark, by):
    """An element whose first row weighs nothing counts nothing later."""
    rows = [(i, f"e{i % 7}", i % 2, None if i == 3 else 0.0 if i < 3 else float(i)) for i in range(200)]
    df = spark.createDataFrame(rows, "event_id long, x string, stream int, w double")
    seen, total, want = set(), {}, {}
    for i, x, s, w in rows:
        key = (s if by else 0, x)
        total[key[0]] = total.get(key[0], 0.0) + (0.0 if key in seen else w or 0.0)
        seen.add(key)
        want[i] = total[key[0]]
    got = {r.event_id: r.exact for r in exact.running(df, ["event_id"], by=by, every=True).collect()}
    assert got == want
    assert exact.running(df, ["event_id"], by=by).count() == 196


def test_replay_does_not_raise_the_running_estimate(spark):
    df = stream(spark, 200, repeats=1)
    twice = df.unionByName(df.withColumn("event_id", F.col("event_id") + 1000))
    assert live.estimate(twice, ["event_id"], P).first().est == pytest.approx(live.estimate(df, ["event_id"], P).first().est, rel=1e-12)


def test_keyed_state_goes_on_in_the_next_micro_batch(spark, tmp_path):
    df = stream(spark, 400, 5).withColumn("stream", F.col("x").cast("int") % 2)
    for half in ("event_id < 350", "event_id >= 350"):
        df.where(half).coalesce(1).write.mode("append").parquet(str(tmp_path))
        time.sleep(1.1)  # files are taken in order of their time
    s = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path))
    out = T.run(T.live_stream(s, ["event_id"], P), "update")
    got = {r.stream: (r.est, r.rises) for r in out.groupBy("stream").agg(F.max("est").alias("est"), F.max("rises").alias("rises")).collect()}
    want = {r.stream: (r.est, r.rises) for r in live.estimate(df, ["event_id"], P, ["stream"]).collect()}
    assert out.where("expired").count() == 0 and got == {k: (pytest.approx(e, rel=1e-12), n) for k, (e, n) in want.items()}


def test_histogram_and_register_chances_agree(spark):
    s = K.LiveSketch(8, -127, 127)
    rng = random.Random(0)
    for _ in range(200):
        w = rng.random()
        by_register = sum(-math.expm1(-w * 2.0 ** -(s.registers.get(j, s.low) + 1)) for j in range(1, 9)) / 8
        assert s.chance(w) == pytest.approx(by_register, rel=1e-9) and sum(s.count.values()) == 8
        s.add(rng.randint(1, 8), rng.randint(-3, 12), w)


def test_bad_weights_and_conflicts(spark):
    df = spark.createDataFrame([("a", 1.0, 1), ("a", 3.0, 2), ("b", None, 3), ("c", float("nan"), 4), ("d", 0.0, 5), ("e", -2.0, 6), (None, 5.0, 7)], "x string, w double, t int")
    total = lambda how: exact.weighted_distinct(df, on_conflict=how, order_by=["t"]).first().exact
    assert (total("max"), total("min"), total("first")) == (8.0, 6.0, 6.0)
    for broken in (lambda: total("error"), lambda: W.clean(df, "w", SketchSpec(on_bad_weight="error")).collect()):
        with pytest.raises(Exception, match="two weights|positive number"):
            broken()


def test_empty_streams(spark):
    df = stream(spark).limit(0)
    assert exact.weighted_distinct(df).first().exact == 0
    assert live.estimate(df, ["event_id"], P).first().est == 0
    none = S.integer_estimate(S.integer_registers(df, P, plan="ordered"), P).first()
    assert (none.est, none.status) == (0, "all_low")
    assert S.integer_registers(df, P, plan="threshold").count() == 0


def test_one_element_one_register(spark):
    one = spark.createDataFrame([("a", 3.0, 0)], "x string, w double, event_id long")
    assert live.estimate(one, ["event_id"], SketchSpec(m=1)).first().est == pytest.approx(3.0)
    assert S.routed_registers(one, SketchSpec(m=1)).count() == 1
    for bad in (dict(m=0), dict(b=1), dict(hash="x"), dict(on_conflict="x")):
        with pytest.raises(ValueError):
            SketchSpec(**bad)
    with pytest.raises(ValueError):
        live.project(one, ["event_id"], SketchSpec(m=10), shards=3)


def test_routed_estimate_of_few_elements(spark):
    """Registers that nothing reached don't drag the estimate to 0."""
    df = spark.createDataFrame([(str(i), 2.0) for i in range(100)], "x string, w double")
    r = S.integer_estimate(S.routed_registers(df, SketchSpec(64)), SketchSpec(64), routed=True).first()
    assert 0.5 * 200 < r.est < 2 * 200


METHODS = ("dense_exp", "ordered_exp", "logbucket", "logbucket_ordered", "logbucket_live", "logbucket_routed")


@pytest.fixture(scope="module")
def accuracy(spark):
    df = workloads.generated(spark, 2000, partitions=4).cache()
    r = experiments.runs(df, METHODS, (64,), range(100), SketchSpec(64), ["event_id"]).cache()
    return r, {x.method: x.rrmse for x in metrics.rrmse(r, ["method"]).collect()}, {x.method: x for x in metrics.bias(r, ["method"]).collect()}


def test_registers_of_many_streams_do_not_travel(spark):
    """A stream's rows are brought together once; no shuffle has rows by register."""
    df = stream(spark, 200).withColumn("stream", F.col("x").cast("int") % 7)
    found = experiments.by_stream(df, ("dense_exp", "logbucket"), (16,), P, order_by=["x"])
    plan = found._jdf.queryExecution().executedPlan().toString()
    dealt = [line for line in plan.splitlines() if "Exchange hashpartitioning" in line]
    assert dealt and all("REPARTITION_BY_COL" in line for line in dealt)
    assert found.count() == 14


def test_errors_follow_theory(accuracy):
    _, error, bias = accuracy
    kind = {"logbucket_ordered": "logbucket", "logbucket_routed": "logbucket"}
    for m in METHODS:
        assert error[m] == pytest.approx(metrics.predicted_error(kind.get(m, m), 64), rel=0.3), m
        assert abs(bias[m].bias) < 4 * bias[m].bias_se + 1 / 64, m


def test_running_estimate_is_the_best(accuracy):
    _, error, _ = accuracy
    assert error["logbucket_live"] == min(error.values())
    assert error["logbucket"] == pytest.approx(error["dense_exp"], rel=0.3)


def test_intervals_cover(accuracy):
    r, _, _ = accuracy
    got = {x.method: x.coverage for x in metrics.coverage(r.where("lo is not null"), ["method"]).collect()}
    assert all(0.85 <= c <= 1 for c in got.values())


def test_small_registers_fail_outside_their_range(spark):
    df = workloads.generated(spark, 1000, partitions=2)
    error = lambda b, scale: metrics.rrmse(experiments.runs(df.withColumn("w", F.col("w") * scale), ("logbucket_routed",), (64,), range(8), SketchSpec(64, b)), []).first().rrmse
    assert error(8, 1e-10) < 0.4 and error(8, 1e10) < 0.4 and error(6, 1.0) < 0.4
    assert not error(4, 1e10) < 0.9 and not error(5, 1e-10) < 0.9


def test_work(spark):
    df = workloads.generated(spark, 4000, partitions=1)
    few, many = (S.work_counters(df, SketchSpec(m)).first() for m in (16, 256))
    assert few.arrivals == many.arrivals == 4000 and 1 <= few.draws / 4000 < 2 and many.draws / 4000 < 256 / 8


def test_plans(spark):
    df = workloads.parts(spark, "/root/testdata/sf0.001").select("x", "w")
    plan = S.routed_registers(df, P)._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    assert "Python" not in plan and "Arrow" not in plan
    assert "ReadSchema: struct<l_partkey:bigint>" in plan and "ReadSchema: struct<p_partkey:bigint,p_retailprice:double>" in plan
    assert plan.split("Subqueries")[0].count("hashpartitioning(j") <= 2
    assert planner.choose_plan(SketchSpec(16), planner.Stats(1000, 1, 8)) == "dense"
    assert planner.choose_plan(SketchSpec(1024), planner.Stats(10**9, 1, 8)) == "routed"
    assert planner.choose_plan(SketchSpec(1024), planner.Stats(10**9, 10**8, 8)) == "by_stream"
    got, name = planner.registers(df, SketchSpec(64), plan="by_stream")
    assert name == "by_stream" and got.count() == 64


def events(spark, path, rows):
    spark.createDataFrame(rows, "event_id long, ts timestamp, value double, event_type string").coalesce(1).write.mode("append").parquet(path)


def test_streaming_state_survives_a_restart_and_late_rows_merge(spark, tmp_path):
    from datetime import datetime, timedelta

    base = datetime(2024, 1, 1)
    every = [(i, base + timedelta(minutes=i), 1.0 + i % 7, "ab"[i % 2]) for i in range(600)]
    path, check, out = (str(tmp_path / x) for x in ("events.parquet", "check", "out"))
    source = lambda: spark.readStream.schema("event_id long, ts timestamp, value double, event_type string").parquet(path).select(F.col("event_id").cast("string").alias("x"), F.col("value").alias("w"), F.col("event_type").alias("stream"), "ts", "event_id")
    got = {}

    def keep(batch, _):
        got.update({r.stream: (r.est, r.rises) for r in batch.collect()})

    for part in (every[:250], every[250:]):
        events(spark, path, part)
        q = T.live_stream(source(), ["ts", "event_id"], P).writeStream.foreachBatch(keep).option("checkpointLocation", check).outputMode("update").trigger(availableNow=True).start()
        q.awaitTermination()
    df = spark.read.parquet(path).select(F.col("event_id").cast("string").alias("x"), F.col("value").alias("w"), F.col("event_type").alias("stream"), "ts", "event_id")
    want = {r.stream: (r.est, r.rises) for r in live.estimate(df, ["ts", "event_id"], P, ["stream"]).collect()}
    assert got.keys() == want.keys() and all(got[k][0] == pytest.approx(want[k][0], rel=1e-9) and got[k][1] == want[k][1] for k in want)
    # rows within the watermark join their window though they come late; the last window is still open
    late = [(1000, base + timedelta(minutes=550), 9.0, "a")]
    windows = lambda: T.windowed_registers(T.routed_rows(source(), P, ["ts"]).withWatermark("ts", "2 hours"), F.window("ts", "1 hour"))
    T.to_store(windows(), out, str(tmp_path / "check2"))
    events(spark, path, late)
    events(spark, path, [(2000, base + timedelta(days=2), 1.0, "a")])
    T.to_store(windows(), out, str(tmp_path / "check2"))
    stored = {(r.window.start, r.j): r.y for r in spark.read.parquet(out).collect()}
    batch = T.routed_rows(spark.read.parquet(path).where("event_id < 2000").select(F.col("event_id").cast("string").alias("x"), F.col("value").alias("w"), "ts"), P, ["ts"])
    direct = {(r.window.start, r.j): r.y for r in T.windowed_registers(batch, F.window("ts", "1 hour")).collect()}
    assert stored == direct
