"""Cost and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.decompose import exponent
from ..operators import accumulator as A
from ..operators.baselines import sum_naive
from ..operators.mapreduce import as_column, exact_sum, packed_sums, with_values


def condition_number(df: DataFrame, col: str | Column, keys: Sequence[str] = (), name: str = "condition") -> DataFrame:
    """sum |x| / |sum x|, both sums exact and rounded once; null where the sum is zero, NaN where it has special values."""
    x = as_column(col).cast("double")
    p = with_values(packed_sums(df, keys, {"a": F.abs(x), "s": x}))
    of = lambda m: F.max(F.when(F.col("m") == m, F.col("value")))
    return p.groupBy(*keys).agg(of("a").alias("a"), F.abs(of("s")).alias("s")).select(*keys, F.when(F.col("s") != 0, F.col("a") / F.col("s")).alias(name))


def log2_condition(df: DataFrame, col: str | Column, keys: Sequence[str] = (), name: str = "bits") -> DataFrame:
    """Places between the top bits of the two sums."""
    x = as_column(col).cast("double")
    p = packed_sums(df, keys, {"a": F.abs(x), "s": x})
    top = F.when(F.size("acc.digits") > 0, 32 * (F.col("acc.low") + F.size("acc.digits") - 1) + F.length(F.bin(F.element_at("acc.digits", -1))))
    of = lambda m: F.max(F.when(F.col("m") == m, top))
    return p.groupBy(*keys).agg((of("a") - of("s")).alias(name))


def exponent_range(df: DataFrame, col: str | Column, keys: Sequence[str] = (), name: str = "delta") -> DataFrame:
    e = exponent(as_column(col).cast("double"))
    return df.groupBy(*keys).agg((F.max(e) - F.min(e)).alias(name))


def sigma(df: DataFrame, col: str | Column, keys: Sequence[str] = ()) -> DataFrame:
    """Active limbs: indexes that any value touched with a digit other than zero."""
    rows = A.limb_rows(df, keys, {"v": as_column(col)})
    digits = F.array(*[F.when(F.col(f"d{i}") != 0, F.col("top") - i) for i in range(3)])
    return rows.select(*keys, F.explode(digits).alias("idx")).where("idx is not null").groupBy(*keys).agg(F.countDistinct("idx").alias("sigma"))


def acc_ulps(acc: Column, y: Column) -> Column:
    """|y - exact| in units in the last place of the correctly rounded value."""
    from ..functions.decompose import ulp

    error = A.acc_round(A.acc_sub(A.acc_of(y), acc))
    return F.abs(error) / ulp(A.acc_round(acc))


def ulp_error(df: DataFrame, col: str | Column, keys: Sequence[str] = (), approx: Callable[..., DataFrame] = sum_naive) -> DataFrame:
    """(keys, value, exact, ulps, relative): how far an inexact sum is from the exact one."""
    exact = exact_sum(df, col, keys, detail=True, name="exact")
    near = approx(df, col, keys).select(*keys, "value")
    both = near.join(exact, list(keys)) if keys else near.join(exact, F.lit(True))
    d = both.withColumn("error", F.abs(A.acc_round(A.acc_sub(A.acc_of(F.col("value")), F.col("acc")))))
    from ..functions.decompose import ulp

    return d.select(*keys, "value", "exact", (F.col("error") / ulp(F.col("exact"))).alias("ulps"), F.when(F.col("exact") != 0, F.col("error") / F.abs("exact")).alias("relative"))


def is_correct(acc: Column, y: Column) -> Column:
    return A.acc_round(acc) == y


def is_faithful(acc: Column, y: Column) -> Column:
    """No double lies strictly between y and the exact value."""
    from ..functions.decompose import next_down, next_up

    sides = F.array(*[A.acc_compare(A.acc_of(x), acc) for x in (y, next_up(y), next_down(y))])
    return A.let(sides, lambda s: (s[0] == 0) | ((s[0] < 0) & (s[1] > 0)) | ((s[0] > 0) & (s[2] < 0)))


def reproducibility(df: DataFrame, col: str | Column, partitions: Sequence[int] = (1, 2, 7, 64), exact: bool = True) -> DataFrame:
    """(partitions, value): one row for each partitioning; equal values mean equal bits."""
    out = None
    for p in partitions:
        d = df.select(as_column(col).alias("x")).repartition(p)
        one = (exact_sum(d, "x") if exact else sum_naive(d, "x")).select(F.lit(p).alias("partitions"), "value")
        out = one if out is None else out.unionByName(one)
    return out


def balance(df: DataFrame, salt: Column, keys: Sequence[str] = ()) -> DataFrame:
    """Largest and mean number of values per reducer."""
    n = df.groupBy(*keys, salt.alias("reducer")).agg(F.count("*").alias("n"))
    return n.groupBy(*keys).agg(F.max("n").alias("most"), F.avg("n").alias("mean"), F.count("*").alias("reducers"))


def carry_stats(df: DataFrame, col: str | Column, keys: Sequence[str] = ()) -> DataFrame:
    """Longest run of limbs of the sum that a carry could travel through (all ones), and the number of limbs."""
    p = packed_sums(df, keys, {"v": as_column(col)})
    start = F.struct(F.lit(0).alias("run"), F.lit(0).alias("most"))
    step = lambda a, d: A.let(F.when(d == (1 << 32) - 1, a["run"] + 1).otherwise(0), lambda r: F.struct(r.cast("int").alias("run"), F.greatest(a["most"], r).cast("int").alias("most")))
    return p.select(*keys, (F.aggregate("acc.digits", start, step, lambda a: a["most"]) + 1).alias("longest_chain"), F.size("acc.digits").alias("limbs"))


def trace_cost(trace: DataFrame) -> DataFrame:
    """Rows and nodes of each level of a traced tree: its depth and its component operations."""
    return trace.groupBy("level").agg(F.count("*").alias("components"), F.countDistinct("node").alias("nodes"))


def timed(df: DataFrame, runs: int = 1) -> float:
    """Least seconds to compute a DataFrame into a sink that keeps nothing."""
    best = float("inf")
    for _ in range(runs):
        t = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        best = min(best, time.perf_counter() - t)
    return best


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


#: Metrics of the executed plan that spark_cost sums, by what they are called there.
COSTS = {"bytes_read": "size of files read", "rows_read": "number of output rows", "shuffle_bytes": "shuffle bytes written", "shuffle_rows": "shuffle records written", "spill_bytes": "spill size"}


def spark_cost(df: DataFrame) -> dict[str, int]:
    """Bytes and rows read by scans, shuffled, and spilled, from the SQL metrics of one run of df."""
    df.collect()
    out = dict.fromkeys(COSTS, 0)

    def walk(node) -> None:
        name = node.nodeName()
        metrics = node.metrics()
        for key, label in COSTS.items():
            it = metrics.valuesIterator()
            while it.hasNext():
                m = it.next()
                if m.name().isDefined() and m.name().get() == label and (key != "rows_read" or "Scan" in name):
                    out[key] += max(0, m.value())
        inner = [node.executedPlan()] if name == "AdaptiveSparkPlan" else [node.plan()] if hasattr(node, "plan") and "QueryStage" in name else []
        children = node.children()
        for child in [*inner, *[children.apply(i) for i in range(children.size())]]:
            walk(child)

    walk(df._jdf.queryExecution().executedPlan())
    return out
