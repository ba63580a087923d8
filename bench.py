"""Headline queries and the sweeps of the experiments; prints one JSON line.

BENCH_SF_DIR (default /root/testdata/sf0.1), BENCH_CPUS (default 8), BENCH_FULL=1 for all exponent ranges
and larger sizes.  The sequential competitor runs on all values, on one core.
Inputs are cached before a method is timed, results go to a sink that keeps nothing.
"""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

CPUS, SF = os.environ.get("BENCH_CPUS", "8"), os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
FULL = bool(os.environ.get("BENCH_FULL"))


def session(cpus: str) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main() -> None:
    from exactsum import queries as q
    from exactsum.operators import baselines as B
    from exactsum.operators import mapreduce as M
    from exactsum.operators import tree as T
    from exactsum.plans.metrics import timed
    from exactsum.sources import workloads as Wl

    spark = session(CPUS)
    times: dict[str, float] = {}

    def run(name, df, runs=2):
        times[name] = round(timed(df, runs), 3)

    for name in ("q_sum_by_flag_status", "q_sum_by_priority", "q_revenue_by_nation", "q_preagg_join", "q_rollup_exact", "q_topk_exact", "q_running_exact", "q_exact_dot", "q_range_join", "q_adaptive_cut_certified"):
        started = time.perf_counter()
        run(name, q.QUERIES[name](spark, SF))
        if time.perf_counter() - started > 120:
            break
    methods = {
        "sparse": lambda d: M.exact_sum(d, "x"),
        "dense": lambda d: M.sum_mapreduce(d, "x", acc="dense"),
        "distill": lambda d: B.sequential(d, "x", "distill"),
        "tree": lambda d: T.sum_tree(d, "x"),
        "plain_sum": lambda d: B.sum_naive(d, "x"),
    }
    sizes: dict[str, int] = {}
    relations: dict[str, float] = {}

    def compare(name, w, which, runs=2):
        n = w.count()
        for m in which:
            run(f"{name}_{m}", methods[m](w), 1 if m == "distill" else runs)
        t = {m: times[f"{name}_{m}"] for m in which}
        best = min(t["sparse"], t["dense"])
        relations[f"{name}_values_per_second"] = round(n / best)
        if "distill" in t:
            relations[f"{name}_speedup_over_distill"] = round(t["distill"] / best, 2)
        return n

    # the four distributions, exponent ranges at a fixed size, all three algorithms on the same values
    for kind in ("positive", "mixed", "centred", "zero"):
        for delta in Wl.DELTAS if FULL else (10, 2000) if kind in ("positive", "zero") else (2000,):
            w = Wl.make_workload(spark, kind, SF, delta).select("x").cache()
            sizes[kind] = compare(f"w_{kind}_{delta}", w, ("sparse", "dense", "distill", *(("tree", "plain_sum") if delta == 2000 else ())))
            w.unpersist()
    # sizes: one core's distillation against all cores
    for k in (4, 16, 64) if FULL else (4, 16):
        w = Wl.make_workload(spark, "positive", SF, 2000, k).select("x").cache()
        n = w.count()
        sizes[f"positive x {k}"] = compare(f"n_{n}", w, ("sparse", "dense", "plain_sum", *(("distill",) if n <= 5_000_000 else ())))
        w.unpersist()
    spark.stop()
    for c in [c for c in ("1", "2", "4", "8") if int(c) <= int(CPUS)]:
        spark = session(c)
        w = Wl.make_workload(spark, "positive", SF, 2000, 8).select("x").repartition(16).cache()
        w.agg(F.count("x")).first()
        for m in ("sparse", "dense"):
            run(f"cores_{c}_{m}", methods[m](w))
            relations[f"cores_{c}_{m}_efficiency"] = round(times[f"cores_1_{m}"] / times[f"cores_{c}_{m}"] / int(c), 2)
        spark.stop()
    print(json.dumps({"metric": "total_seconds", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": SF.rsplit("sf", 1)[-1], "rows": sizes, "relations": relations, "cpus": CPUS}))


if __name__ == "__main__":
    main()
