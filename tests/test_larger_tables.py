"""What larger tables and odd rows asked for."""

from __future__ import annotations

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from exactsum.operators import baselines as B
from exactsum.operators import joins as J
from exactsum.operators import kernels as K
from exactsum.operators import mapreduce as M
from exactsum.sources import workloads as Wl

SF = "/root/testdata/sf0.001"


def test_salted_join_never_broadcasts_the_repeated_side(spark):
    o = spark.read.parquet(f"{SF}/orders.parquet")
    j = J.salted(o, o.select("o_orderkey", F.lit(1).alias("one")), "o_orderkey")
    assert "Broadcast" not in j._jdf.queryExecution().executedPlan().toString()
    assert j.count() == o.count()


@pytest.mark.parametrize("method", K.METHODS)
def test_methods_on_blocks(method):
    rng = random.Random(21)
    plain = [round(rng.uniform(800, 500_000), 2) for _ in range(1000)]
    mixed = [rng.choice([-1, 1]) * rng.random() * 2.0 ** rng.randint(-200, 200) for _ in range(999)]
    for v in (plain, [-x for x in plain], mixed, [*mixed, *[-x for x in mixed]], [0.0] * 100):
        if method == "doubly_compensated":
            v = sorted(v, key=abs, reverse=True)
        if method == "by_exponent":
            v = sorted(v, key=lambda x: -math.frexp(x)[1])
        arrays = [np.array(v[a : a + 70]) for a in range(0, len(v), 70)]
        value, counter = K.run_blocks(method, K.dealt_blocks(arrays, 64))
        want, counted = K.METHODS[method](v)
        assert value == want, method
        if method in ("pairwise", "compensated", "doubly_compensated", "superacc_carry", "expansion", "fixed", "bucketed"):
            assert counter == counted
    if method in ("distill", "expansion", "refine", "accurate"):
        with pytest.raises(OverflowError):
            K.run_blocks(method, K.dealt_blocks([np.array([1.7e308] * 4)], 2))


def test_sequential_has_no_limit_of_rows(spark):
    x = (F.pmod(F.col("id") * 7919, F.lit(1000)) / 8).alias("x")
    d = spark.range(0, 5_000_100, 1, 4).select("id", x)
    for method in ("reference", "distill", "naive"):
        assert B.sequential(d, "x", method).first().value == d.agg(F.sum("x")).first()[0], method


def test_sequential_keeps_order_over_blocks(spark):
    rng = random.Random(22)
    data = [(k % 3 if k % 5 else None, k, rng.choice([-1, 1]) * rng.random() * 2.0 ** rng.randint(-60, 60)) for k in range(3000)]
    d = spark.createDataFrame(data, "g int, i int, x double").repartition(4)
    for method in K.METHODS:
        want = {g: K.METHODS[method]([x for k, _, x in data if k == g])[0] for g in (0, 1, 2, None)}
        got = B.sequential(d, "x", method, ["g"], ["i"], block=64).collect()
        assert {r.g: r.value for r in got} == want, method
        assert B.sequential(d, "x", method, order=["i"], block=64).first().value == K.METHODS[method]([x for _, _, x in data])[0], method
    assert B.sequential(d.limit(0), "x", "naive").count() == 0


@pytest.mark.parametrize("kind", ["positive", "mixed"])
def test_distill_over_blocks_of_wide_workloads(spark, kind):
    w = Wl.make_workload(spark, kind, SF, 500)
    assert B.sequential(w, "x", "distill", block=256).select("value").first() == M.exact_sum(w, "x").first()


@pytest.mark.parametrize("kind", ["positive", "mixed"])
def test_distill_queries_shuffle_lists_only(spark, kind):
    """What a partition sends to the one task doesn't grow with its rows."""
    from exactsum import queries as Q

    d = Q.QUERIES[f"q_w_{kind}_500_distill"](spark, SF)
    plan = d._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInPandas") == 2 and plan.index("MapInPandas") < plan.index("Exchange") < plan.rindex("MapInPandas")
    w = Wl.make_workload(spark, kind, SF, 500)
    want = M.exact_sum(w, "x").first()
    assert d.first() == want
    assert B.sum_distill(w.repartition(5), "x", block=64).select("value").first() == want
    assert B.sum_distill(w.limit(0), "x").count() == 0
    assert B.sum_distill(spark.createDataFrame([(0.0,), (None,), (-0.0,)], "x double"), "x").first().value == 0.0


@pytest.mark.parametrize("name", ["q_tree_levels", "q_tree_cost", "q_tree_exponents", "q_tree_links"])
def test_trees_of_odd_keys(spark, tmp_path, name):
    """Keys below zero, none, beyond 32 bits; balances that cancel, none, beyond half a digit."""
    import duckdb

    from exactsum import queries as Q

    rng = random.Random(24)
    keys = [*range(-40, 40), None, None, -(2**40) - 5, 2**40 + 3]
    rows = [(k, rng.choice([None, 0.0, -0.01, 0.25, -7.5, 2.0**31, -(2.0**31), 3e9 + 0.1])) for k in keys for _ in range(3)]
    spark.createDataFrame(rows, "c_custkey long, c_acctbal double").coalesce(1).write.parquet(f"{tmp_path}/customer.parquet")
    with duckdb.connect() as c:
        c.execute(f"CREATE VIEW customer AS SELECT * FROM '{tmp_path}/customer.parquet/*.parquet'")
        want = c.execute(Q.ORACLES[name]).fetchall()
    assert sorted(map(repr, map(tuple, Q.QUERIES[name](spark, str(tmp_path)).collect()))) == sorted(map(repr, want))


def test_running_sums_of_odd_rows(spark, tmp_path):
    """Nulls in every column that a running sum is kept by, is in the order of, or adds: last, as in its SQL."""
    import datetime

    import duckdb

    from exactsum import queries as Q

    rng = random.Random(26)
    day = datetime.datetime(2024, 1, 1)
    pick = lambda *v: rng.choice([None, *v])
    rows = [(pick(2, 7, 50, 51, -50), pick(1, 2), pick(1, 2, 3), pick(1, 2), day + datetime.timedelta(days=i), 0.5 + i, pick(1.0, 2.0, 30.0)) for i in range(400)]
    rows = [(*r[:4], rng.choice([None, r[4]]) if r[2] == 3 else r[4], *r[5:]) for r in rows]
    d = spark.createDataFrame(rows, "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_shipdate timestamp_ntz, l_extendedprice double, l_quantity double")
    d.coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    with duckdb.connect() as c:
        c.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet/*.parquet'")
        want = c.execute(Q.ORACLES["q_running_special"]).fetchall()
    assert sorted(map(repr, map(tuple, Q.QUERIES["q_running_special"](spark, str(tmp_path)).collect()))) == sorted(map(repr, want))


def test_moments_of_repeated_pairs(spark):
    """Equal pairs are taken once with their number, whatever they are."""
    rng = random.Random(23)
    pairs = [(g, rng.choice([None, 0.1, -3.7e-5, 1e300 if g == 1 else 2.5, math.nan if g == 2 else 7.0]), rng.choice([0.3, 1e-7, -0.0, 0.0, None])) for g in range(3) for _ in range(400)]
    many = spark.createDataFrame(pairs, "g int, x double, y double")
    one = many.withColumn("g", F.struct("g", F.monotonically_increasing_id().alias("i")))  # each row a group: nothing to combine
    assert "times__" in M._pairs(many, "x", "y", ["g"]).columns and "times__" not in M._pairs(one, "x", "y", ["g"]).columns
    for run in (M.exact_cov, M.exact_corr, M.exact_weighted_avg):
        got = {r.g: r.value for r in run(many, "x", "y", ["g"]).collect()}
        plain = M._pairs
        try:
            M._pairs = lambda df, a, b, keys: df.select(*keys, F.col(a).alias("a__"), F.col(b).alias("b__")).where("a__ is not null and b__ is not null")
            want = {r.g: r.value for r in run(many, "x", "y", ["g"]).collect()}
        finally:
            M._pairs = plain
        assert {g: repr(v) for g, v in got.items()} == {g: repr(v) for g, v in want.items()}, run


def test_interval_rounds_seconds_as_its_sql(spark, tmp_path):
    import duckdb

    from exactsum import queries as Q

    cases = [(0.4, 3599.6), (0.6, 3599.4), (0.5, 3600.5), (1.5, 3600.5), (0.5, 3599.5), (0.6, 0.4), (0.4, 0.45), (0.55, 0.5)]  # view and purchase, in seconds
    rows = [(2 * u + k, 1.7e9 + t, u, kind, 0.25 + u) for u, (b, a) in enumerate(cases) for k, (t, kind) in enumerate([(b, "view"), (a, "purchase")])]
    e = spark.createDataFrame(rows, "event_id long, t double, user_id long, event_type string, value double")
    e.select("event_id", F.timestamp_seconds("t").cast("timestamp_ntz").alias("ts"), "user_id", "event_type", "value").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    with duckdb.connect() as c:
        c.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/events.parquet/*.parquet'")
        want = dict(c.execute(Q.ORACLES["q_interval"]).fetchall())
    assert {r.user_id: r.value for r in Q.QUERIES["q_interval"](spark, str(tmp_path)).collect()} == want


def test_deduplicated_stream_goes_around_the_driver(spark):
    from exactsum import queries as Q

    got = {r.event_type: r.value for r in Q.QUERIES["q_stream_deduplicated"](spark, SF).collect()}
    assert not [t.name for t in spark.catalog.listTables() if t.name.startswith("deduplicated_")]  # no memory table
    e = spark.read.parquet(f"{SF}/events.parquet").groupBy("user_id", "event_type").agg(F.max("value").alias("value"))
    assert got == {r.event_type: r.value for r in M.exact_sum(e, "value", ["event_type"]).collect()}
