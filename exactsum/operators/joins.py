"""Joins around exact sums."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import accumulator as A
from .mapreduce import as_column, exact_sum, packed_sums, with_values


def exact_sum_join(left: DataFrame, right: DataFrame, on, col: str | Column, keys: Sequence[str], how: str = "inner", hint: str | None = None, name: str = "value") -> DataFrame:
    return exact_sum(left.join(right.hint(hint) if hint else right, on, how), col, keys, name=name)


def preagg_join(facts: DataFrame, col: str | Column, fact_key: str, dims: DataFrame, dim_key: str, keys: Sequence[str], name: str = "value", combine: bool | None = None) -> DataFrame:
    """Sums the facts' digits per join key first: a key's few limb rows are joined, not every fact.

    Where almost every fact has a key of its own (`combine` None: counted first) that saves nothing,
    and the facts are joined as they are.
    """
    from ..plans.planner import choose_combine

    named = dims.select(F.col(dim_key).alias(fact_key), *keys)
    if not (choose_combine(facts, [fact_key], facts.count()) if combine is None else combine):
        return exact_sum_join(facts, named, fact_key, col, keys, name=name)
    sums = A.limb_sums(A.limb_rows(facts, [fact_key], {name: as_column(col)}), [fact_key])
    joined = sums.join(named, fact_key).groupBy(*keys, "m", "top").agg(*[F.sum(s).alias(s) for s in (*A.SUMS, *A.FLAGS)])
    return with_values(A.pack(joined, keys)).select(*keys, F.col("value").alias(name))


def range_join(points: DataFrame, x: str, bands: DataFrame, low: str, high: str, width: float) -> DataFrame:
    """Points within [low, high): an equi join on buckets of `width` and a residual, not a nested loop."""
    bucket = lambda c: F.floor(F.col(c) / width)
    b = bands.withColumn("bucket__", F.explode(F.sequence(bucket(low), bucket(high))))
    p = points.withColumn("bucket__", bucket(x))
    return p.join(b, "bucket__").where((F.col(x) >= F.col(low)) & (F.col(x) < F.col(high))).drop("bucket__")


def asof(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, value: str, name: str) -> DataFrame:
    """For each left row the latest right value of its key at or before its time; one shuffle by key."""
    none = F.lit(None).cast(right.schema[value].dataType)
    a = left.select(F.col(key).alias("k__"), F.col(left_time).alias("t__"), F.lit(1).alias("side__"), none.alias("v__"), F.struct(*left.columns).alias("row__"))
    b = right.select(F.col(key).alias("k__"), F.col(right_time).alias("t__"), F.lit(0).alias("side__"), F.col(value).alias("v__"), F.lit(None).cast(a.schema["row__"].dataType).alias("row__"))
    w = W.partitionBy("k__").orderBy("t__", "side__").rowsBetween(W.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("last__", F.last("v__", ignorenulls=True).over(w))
    return both.where("side__ = 1").select("row__.*", F.col("last__").alias(name))


def interval_join(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, seconds: int) -> DataFrame:
    """Pairs of one key with right_time in (left_time - seconds, left_time]; time buckets bound the candidates.

    Columns of the right side get the prefix r_.
    """
    unix = lambda c: F.unix_timestamp(F.col(c).cast("timestamp"))
    r = right.select(*[F.col(c).alias(f"r_{c}") for c in right.columns])
    r = r.withColumn("b__", F.floor(unix(f"r_{right_time}") / seconds)).withColumn("b__", F.explode(F.array(F.col("b__"), F.col("b__") + 1)))
    a = left.withColumn("b__", F.floor(unix(left_time) / seconds))
    j = a.join(r, (a[key] == r[f"r_{key}"]) & (a["b__"] == r["b__"])).drop("b__")
    gap = unix(left_time) - unix(f"r_{right_time}")
    return j.where((gap >= 0) & (gap < seconds))


def salted(facts: DataFrame, dims: DataFrame, key: str, salts: int = 8) -> DataFrame:
    """Equi join whose hot keys are spread over `salts` tasks; the small side is repeated for each salt.

    Both sides are shuffled: the planner takes the repeated side for as small as it was before, and
    would broadcast all copies by way of the driver.
    """
    f = facts.withColumn("salt__", F.pmod(F.xxhash64(*facts.columns), F.lit(salts)).cast("int"))
    d = dims.withColumn("salt__", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return f.join(d.hint("merge"), [key, "salt__"]).drop("salt__")


def topk_exact(df: DataFrame, col: str | Column, keys: Sequence[str], k: int, name: str = "value") -> DataFrame:
    """The k keys with the largest exact sums, ties by key."""
    return exact_sum(df, col, keys, name=name).orderBy(F.desc(name), *keys).limit(k)


def delta(df: DataFrame, col: str | Column, keys: Sequence[str], order: str, name: str = "delta") -> DataFrame:
    """Exact change of a key's sum against the preceding one in `order`: accumulators are subtracted, then rounded."""
    p = packed_sums(df, [*keys, order], {"v": as_column(col)})
    before = F.lag("acc").over(W.partitionBy(*keys).orderBy(order))
    d = p.withColumn("before__", before)
    return d.select(*keys, order, F.when(F.col("before__").isNotNull(), A.acc_round(A.acc_sub(F.col("acc"), F.col("before__")))).alias(name))
