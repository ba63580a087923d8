"""Exact running, sliding and range sums: limb sums over a window frame, rounded row by row."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as Wd
from pyspark.sql import functions as F

from ..functions.decompose import limbs
from . import accumulator as A
from .mapreduce import as_column


def active_limbs(df: DataFrame, col: str | Column) -> tuple[int, int]:
    """Least and greatest limb index with a digit that isn't zero; one small aggregate."""
    d = df.select(limbs(as_column(col).cast("double")).alias("l")).select("l.*")
    least = F.when(F.col("d2") != 0, F.col("top") - 2).when(F.col("d1") != 0, F.col("top") - 1).otherwise(F.col("top"))
    low, high = d.agg(F.min(least), F.max("top")).first()
    return (0, 0) if low is None else (low, high)


def _digits(df: DataFrame, col: str | Column) -> tuple[DataFrame, list[str], int]:
    """df with one column for each active limb and the flags of its value; their names and the least index."""
    low, high = active_limbs(df, col)
    d = df.withColumn("x", as_column(col).cast("double")) if "x" not in df.columns else df.withColumnRenamed("x", "own_x__").withColumn("x", _renamed(col).cast("double"))
    d = d.withColumn("l__", limbs(F.col("x")))
    zero = F.lit(0).cast("bigint")
    digit = lambda k: F.coalesce(F.when(F.col("l__.top") == k, F.col("l__.d0")).when(F.col("l__.top") == k + 1, F.col("l__.d1")).when(F.col("l__.top") == k + 2, F.col("l__.d2")), zero)
    names = [f"w{k - low}__" for k in range(low, high + 1)]
    d = d.withColumns({n: digit(k) for n, k in zip(names, range(low, high + 1), strict=True)} | A.flag_values()).drop("x", "l__")
    return d.withColumnRenamed("own_x__", "x"), names, low


def _renamed(col: str | Column) -> Column:
    if isinstance(col, str):
        return F.col("own_x__" if col == "x" else col)
    raise ValueError("give the name of the column where the frame has one named x")


def _rounded(d: DataFrame, names: Sequence[str], low: int, keep: Sequence[str], name: str) -> DataFrame:
    d = A.rounded_digits(d, names, low, "finite__")
    return d.withColumn("out__", A.finished(None, F.col("finite__"))).select(*keep, F.col("out__").alias(name))


def exact_over(df: DataFrame, col: str | Column, window, name: str = "value") -> DataFrame:
    """Adds the exact sum of `col` over a window (any frame): null over nulls only, NaN and infinities as in IEEE sums.

    Exact sums don't drift as frames slide.  df has no columns named like the flags (n, n_nan, ...).
    """
    d, names, low = _digits(df, col)
    d = d.withColumns({c: F.sum(c).over(window) for c in [*names, *A.FLAGS]})
    return _rounded(d, names, low, df.columns, name)


def exact_running_sum(df: DataFrame, col: str | Column, keys: Sequence[str], order: Sequence[str | Column], name: str = "value", buckets: int = 0) -> DataFrame:
    """Exact sum from the first row of `keys` in `order` (names: nulls first; or ordered columns, without buckets) up to each row.

    With `buckets` the sum is taken in two levels: rows are dealt to about that many ranges of the
    first order column (a number, date or time; nulls first), a range's totals run over the ranges,
    and rows run within their range.  So no task holds all rows of a key, or of a frame without keys.
    """
    if not buckets:
        return exact_over(df, col, Wd.partitionBy(*keys).orderBy(*order).rowsBetween(Wd.unboundedPreceding, 0), name)
    by = F.col(order[0])
    place = by.cast("timestamp").cast("double") if df.schema[order[0]].dataType.typeName() in ("date", "timestamp", "timestamp_ntz") else by.cast("double")
    cuts = sorted(set(df.select(place.alias("p")).approxQuantile("p", [k / buckets for k in range(1, buckets)], 0.25 / buckets)))
    d, names, low = _digits(df, col)
    given = F.array(*[F.lit(c) for c in cuts]) if cuts else F.array().cast("array<double>")
    # equal values of the first order column share a range, so the order of ranges is that of the rows
    d = d.withColumn("range__", F.when(place.isNull(), F.lit(-1)).otherwise(F.size(F.filter(given, lambda c: c <= place))))
    sums = [*names, *A.FLAGS]
    totals = d.groupBy(*keys, "range__").agg(*[F.sum(c).alias(c) for c in sums])
    earlier = Wd.partitionBy(*keys).orderBy("range__").rowsBetween(Wd.unboundedPreceding, -1)
    zero = F.lit(0).cast("bigint")
    base = totals.select(*[F.col(k).alias(f"{k}_key__") for k in keys], F.col("range__").alias("range_"), *[F.coalesce(F.sum(c).over(earlier), zero).alias(f"{c}base") for c in sums])
    inside = Wd.partitionBy(*keys, "range__").orderBy(*order).rowsBetween(Wd.unboundedPreceding, 0)
    d = d.withColumns({c: F.sum(c).over(inside) for c in sums})
    on = F.col("range__") == F.col("range_")
    for k in keys:
        on = on & F.col(k).eqNullSafe(F.col(f"{k}_key__"))
    d = d.join(base, on).withColumns({c: F.col(c) + F.col(f"{c}base") for c in sums})
    return _rounded(d, names, low, df.columns, name)


def exact_sliding_sum(df: DataFrame, col: str | Column, keys: Sequence[str], order: Sequence[str], rows: int, name: str = "value") -> DataFrame:
    return exact_over(df, col, Wd.partitionBy(*keys).orderBy(*order).rowsBetween(-(rows - 1), 0), name)


def exact_range_sum(df: DataFrame, col: str | Column, keys: Sequence[str], order: str, before: int, after: int = 0, name: str = "value") -> DataFrame:
    """Exact sum over rows whose `order` value lies within [own - before, own + after]."""
    return exact_over(df, col, Wd.partitionBy(*keys).orderBy(order).rangeBetween(-before, after), name)
