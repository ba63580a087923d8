import math

from pyspark.sql import functions as F

from exactsum.operators import joins as J
from exactsum.operators import mapreduce as M
from exactsum.operators import windows as Wi
from exactsum.plans import planner
from exactsum.sources import io
from exactsum.sources import workloads as Wl
from exactsum.streaming import sums as S

SF = "/root/testdata/sf0.001"


def test_workloads(spark):
    from exactsum.plans import metrics as C

    for delta in (10, 500):
        w = Wl.make_workload(spark, "positive", SF, delta)
        assert C.condition_number(w, "x").first()[0] == 1.0 and w.where("x <= 0").count() == 0
        assert C.exponent_range(w, "x").first()[0] == delta - 1
        assert M.exact_sum(Wl.make_workload(spark, "zero", SF, delta), "x").first()[0] == 0
        assert M.exact_sum(Wl.make_workload(spark, "near_zero", SF, delta), "x").first()[0] == 2.0 ** (-delta // 2)
        m = Wl.make_workload(spark, "mixed", SF, delta)
        xs = [r.x for r in m.collect()]
        assert M.exact_sum(m, "x").first()[0] == math.fsum(xs) and min(xs) < 0 < max(xs)
    assert C.exponent_range(Wl.make_workload(spark, "centred", SF, 2000), "x").first()[0] < 80


def test_data_source(spark):
    Wl.register_source(spark)
    d = spark.read.format("exact_workload").options(n="1000", delta="100", kind="zero", partitions="3").load()
    assert d.count() == 1000 and M.exact_sum(d, "x").first()[0] == 0


def test_round_trips(spark, tmp_path):
    d = spark.read.parquet(f"{SF}/customer.parquet").select("c_custkey", F.col("c_acctbal").alias("x"), (F.col("c_acctbal") / 3).alias("y"))
    want = sorted(map(tuple, d.collect()))
    for fmt in ("parquet", "orc", "csv", "json", "text"):
        io.save(d, f"{tmp_path}/{fmt}", fmt)
        back = io.read(spark, f"{tmp_path}/{fmt}", "c_custkey bigint, x double, y double", fmt)
        assert sorted(map(tuple, back.select("c_custkey", "x", "y").collect())) == want


def test_windows(spark):
    rows = [(i % 3, i, (-1) ** i * 0.1 * i + 1e10 * (i % 7 == 0)) for i in range(120)]
    d = spark.createDataFrame(rows, "g int, i int, x double")
    by = {g: [x for h, _, x in rows if h == g] for g in range(3)}
    for r in Wi.exact_running_sum(d, "x", ["g"], ["i"]).collect():
        assert r.value == math.fsum(by[r.g][: r.i // 3 + 1])
    for r in Wi.exact_sliding_sum(d, "x", ["g"], ["i"], 5).collect():
        k = r.i // 3
        assert r.value == math.fsum(by[r.g][max(0, k - 4) : k + 1])


def test_window_special_values_and_levels(spark):
    nan, inf = math.nan, math.inf
    v = [None, 1.0, inf, 2.0, -inf, 1.0, None]
    d = spark.createDataFrame(list(enumerate(v)), "i int, x double")
    assert repr([r.value for r in Wi.exact_running_sum(d, "x", [], ["i"]).orderBy("i").collect()]) == repr([None, 1.0, inf, inf, nan, nan, nan])
    assert repr([r.value for r in Wi.exact_sliding_sum(d, "x", [], ["i"], 2).orderBy("i").collect()]) == repr([None, 1.0, inf, inf, -inf, -inf, 1.0])
    zeros = spark.createDataFrame([(0, -0.0), (1, -0.0), (2, 0.0)], "i int, x double")
    assert [math.copysign(1, r.value) for r in Wi.exact_running_sum(zeros, "x", [], ["i"]).orderBy("i").collect()] == [-1, -1, 1]
    rows = [(k % 2, (k * 37) % 50, k, (-1) ** k * 0.1 * k + 1e12 * (k % 7 == 0) - 1e-9) for k in range(400)]
    e = spark.createDataFrame([*rows, (1, None, 400, 5.0)], "g int, t int, k int, x double").repartition(3)
    order = lambda r: (r[1] is not None, r[1] or 0, r[2])
    for keys in ([], ["g"]):
        got = {r.k: r.value for r in Wi.exact_running_sum(e, "x", keys, ["t", "k"], buckets=9).collect()}
        assert len(got) == 401
        for g in (0, 1):
            mine = sorted(((*r,) for r in [*rows, (1, None, 400, 5.0)] if not keys or r[0] == g), key=order)
            for n in range(len(mine)):
                assert got[mine[n][2]] == math.fsum(r[3] for r in mine[: n + 1])
    near = {r.k: r.value for r in Wi.exact_range_sum(e, "x", ["g"], "t", 5, 3).collect()}
    for g, t, k, _ in rows:
        assert near[k] == math.fsum(x for h, u, _, x in rows if h == g and t - 5 <= u <= t + 3)


def test_streams_fail_loudly_and_keep_custom_state(spark, tmp_path):
    import pytest

    spark.createDataFrame([("2024-01-01 00:00:00", "a", 1.0, 1), ("2024-01-01 01:00:00", "a", 1e300, 2), ("2024-01-01 01:00:00", "a", 1e300, 2)], "ts string, k string, x double, id int").coalesce(1).write.parquet(f"{tmp_path}/one")
    read = lambda: spark.readStream.schema("ts string, k string, x double, id int").parquet(f"{tmp_path}/one")
    with pytest.raises(Exception, match="outside the limbs"):
        S.run_once(S.stream_exact_sum(read(), "x", "ts", ["k"], limb_range=(-4, 2)), spark, "narrow_sums").collect()
    assert S.run_once(S.stream_exact_sum(read(), "x", "ts", ["k"]), spark, "wide_sums").first().value == 2e300
    once = S.stream_deduplicated(read(), ["id"], "ts")
    assert S.run_once(once, spark, "once", "append").count() == 2
    state = S.run_once(S.stream_running_sum(read(), "x", "k"), spark, "state_sums", "update").collect()
    assert [(r.key, r.n, r.value) for r in state] == [("a", 3, 2e300)]
    pairs = S.stream_interval_join(read(), read(), "k", "ts", "ts", 7200)
    assert S.run_once(pairs, spark, "pairs", "append").count() == 1 + 2 * 3


def test_late_rows_are_left_out_and_counted(spark, tmp_path):
    """Rows older than the watermark change no window that was closed; they are the difference to the batch."""
    path = f"{tmp_path}/late"
    times = ["2024-01-05 00:00:00", "2024-01-20 00:00:00", "2024-01-21 00:00:00", "2024-01-05 01:00:00", "2024-01-20 01:00:00"]
    for i, t in enumerate(times):
        spark.createDataFrame([(t, float(2**i))], "ts string, x double").coalesce(1).write.mode("append").parquet(path)
        import time

        time.sleep(0.02)
    stream = spark.readStream.schema("ts string, x double").option("maxFilesPerTrigger", 1).parquet(path)
    out = S.run_once(S.stream_exact_sum(stream, "x", "ts", watermark="2 days"), spark, "late_sums", "append")
    assert {str(r.start)[:10]: r.value for r in out.collect()} == {"2024-01-05": 1.0}


def test_costs_of_a_plan(spark):
    from exactsum.plans import metrics as C

    d = spark.read.parquet(f"{SF}/lineitem.parquet")
    cost = C.spark_cost(M.exact_sum(d, "l_tax", ["l_returnflag"]))
    assert cost["rows_read"] == d.count() and 0 < cost["shuffle_bytes"] < cost["bytes_read"] and cost["spill_bytes"] == 0
    assert 0 < cost["shuffle_rows"] < 200


def test_joins(spark):
    e = spark.read.parquet(f"{SF}/events.parquet")
    a, b = e.where("event_type = 'purchase'"), e.where("event_type = 'view'")
    views = {}
    for r in b.orderBy("ts").collect():
        views.setdefault(r.user_id, []).append((r.ts, r.value))
    for r in J.asof(a, b, "user_id", "ts", "ts", "value", "viewed").collect():
        before = [v for t, v in views.get(r.user_id, []) if t <= r.ts]
        assert r.viewed == (before[-1] if before else None)
    got = J.interval_join(a, b, "user_id", "ts", "ts", 36000).count()
    assert got == sum(0 <= int(r.ts.timestamp()) - int(t.timestamp()) < 36000 for r in a.collect() for t, _ in views.get(r.user_id, []))
    o = spark.read.parquet(f"{SF}/orders.parquet")
    assert J.salted(o, o.select("o_orderkey", F.lit(1).alias("one")), "o_orderkey").count() == o.count()


def test_stream_equals_batch_and_survives_restart(spark, tmp_path):
    e = spark.read.parquet(f"{SF}/events.parquet").orderBy(F.rand(3))
    e.repartition(3).write.parquet(f"{tmp_path}/events")
    stream = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/events")
    got = S.run_once(S.stream_exact_sum(stream, "value", "ts", ["event_type"], watermark="100 days"), spark, "sums_test")
    batch = M.exact_sum(e.withColumn("start", F.window(F.col("ts").cast("timestamp"), "1 day")["start"]), "value", ["start", "event_type"])
    assert sorted((r.start, r.event_type, r.value) for r in got.collect()) == sorted((r.start, r.event_type, r.value) for r in batch.collect())
    for _ in range(2):  # the second run finds nothing new
        S.accumulate(stream, "value", ["event_type"], f"{tmp_path}/acc", f"{tmp_path}/ck")
    total = io.merge_acc(spark.read.parquet(f"{tmp_path}/acc"), ["event_type"])
    assert {r.event_type: r.value for r in total.collect()} == {r.event_type: r.value for r in M.exact_sum(e, "value", ["event_type"]).collect()}


def test_planner():
    assert planner.choose_external(70, 1 << 20) == "scan" and planner.choose_external(10**9, 1 << 30) == "sort"
    assert not planner.needs_wide(1 << 30) and planner.needs_wide(1 << 31)
