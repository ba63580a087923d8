"""External-memory sums by sorting, set equality by summation, and helpers on counts."""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.formats import FORMATS, R, W, FloatFormat
from . import accumulator as A
from .mapreduce import as_column, sum_scan, with_values


def sum_sorted(df: DataFrame, col: str | Column, keys: Sequence[str] = (), partitions: int | None = None, name: str = "value") -> DataFrame:
    """Sort-based sum: digits are dealt to ranges of (limb index, salt), sorted, and swept once.

    The salt numbers rows, so equal values go to different ranges.  The sweep is the sorted partial
    aggregation of each range; an index whose rows span range borders leaves several partial digits,
    which a small second shuffle adds.  Special values and counts travel with the digits: one scan.
    """
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    long = digit_rows(A.limb_rows(df, keys, {name: as_column(col)}), keys)
    order = [*keys, "idx"]
    ranged = long.withColumn("salt__", F.xxhash64(F.monotonically_increasing_id())).repartitionByRange(n, *order, "salt__").sortWithinPartitions(*order)
    sums = ranged.groupBy(*order).agg(F.sum("digit").alias("s0"), *[F.sum(f).alias(f) for f in A.FLAGS])
    zero = F.lit(0).cast("bigint")
    sums = sums.select(*keys, F.lit(name).alias("m"), F.col("idx").alias("top"), "s0", zero.alias("s1"), zero.alias("s2"), *A.FLAGS)
    return with_values(A.pack(sums, keys)).select(*keys, F.col("value").alias(name))


def digit_rows(rows: DataFrame, keys: Sequence[str]) -> DataFrame:
    """(keys, idx, digit, flags): a row for each digit that isn't zero, and one without index that counts the value."""
    zero = F.lit(0).cast("bigint")
    flag = {f: c.cast("bigint") for f, c in A.flag_values().items()}
    own = F.struct(F.lit(None).cast("int").alias("idx"), zero.alias("digit"), *[c.alias(f) for f, c in flag.items()])
    digits = [F.struct((F.col("top") - i).alias("idx"), F.col(f"d{i}").alias("digit"), *[zero.alias(f) for f in A.FLAGS]) for i in range(3)]
    return rows.select(*keys, F.inline(F.array(own, *digits))).where("digit <> 0 or idx is null")


def multiset_equal(a: DataFrame, x: str, b: DataFrame, y: str, bits: int = 40) -> DataFrame:
    """One row (equal, limbs_left): do integer columns x of a and y of b hold the same values equally often?

    Value v of a adds 2^(bits v), of b subtracts it.  With fewer than 2^(bits-1) rows, which is
    checked, no value's copies reach the next value's bits, so the sum is zero for equal multisets
    and for no others.  Exponents are unbounded: limb indexes are DECIMAL, whatever a double's range.
    A sum that isn't zero has a digit that isn't zero however its carries stand, so none is settled.
    Nulls are equal to each other, as in EXCEPT ALL.
    """
    period = W // math.gcd(bits, W)  # values after which a limb's border is met again
    v = F.col("v")
    low = F.pmod(v, F.lit(period).cast("bigint"))
    whole = (v.cast("decimal(38,0)") - low) / F.lit(period).cast("decimal(10,0)")
    index = (whole.cast("decimal(38,0)") * F.lit(bits * period // W).cast("decimal(10,0)")).cast("decimal(38,0)") + F.floor(low * bits / W).cast("decimal(10,0)")
    digit = F.call_function("shiftleft", F.lit(1).cast("bigint"), F.pmod(low * bits, F.lit(W)).cast("int"))
    split = lambda d, c, sign: d.select(F.col(c).cast("bigint").alias("v")).select(F.when(v.isNotNull(), index.cast("decimal(38,0)")).alias("idx"), F.coalesce(digit, F.lit(1).cast("bigint")).alias("d"), F.lit(sign).alias("sign"))
    both = split(a, x, 1).unionByName(split(b, y, -1))
    # at most 2^32 in a digit of one row, so 2^31 rows of an index can be added; decimal sums can't overflow
    sums = both.groupBy("idx").agg(F.sum((F.col("d") * F.col("sign")).cast("decimal(20,0)")).alias("p"), F.count("*").alias("rows"))
    left = sums.agg(F.count(F.when(F.col("p") != 0, 1)).alias("limbs_left"), F.coalesce(F.sum("rows"), F.lit(0)).alias("rows"))
    fits = F.when(F.col("rows") >= F.lit(1 << (bits - 1)), F.raise_error(F.lit(f"2^{bits - 1} rows or more; give more bits")).cast("boolean"))
    return left.select(F.coalesce(fits, F.col("limbs_left") == 0).alias("equal"), "limbs_left")


def sum_external(df: DataFrame, col: str | Column, keys: Sequence[str] = (), memory_bytes: int = 1 << 26, name: str = "value") -> DataFrame:
    """Scan-based where an accumulator of the active limbs fits a task's memory, else sort-based."""
    from ..plans.metrics import sigma
    from ..plans.planner import choose_external

    most = sigma(df, col, keys).agg(F.max("sigma")).first()[0] or 0
    run = sum_scan if choose_external(most, memory_bytes) == "scan" else sum_sorted
    return run(df, col, keys, name=name)


def count_as_floats(n: int, fmt: str | FloatFormat = "single") -> list[float]:
    """n as an exact sum of a few numbers of a format."""
    fmt = FORMATS[fmt] if isinstance(fmt, str) else fmt
    out = []
    while n:
        drop = max(0, n.bit_length() - fmt.precision)
        part = (n >> drop) << drop
        out.append(float(part))
        n -= part
    return out


def is_regular(rows: DataFrame) -> DataFrame:
    """Digits that break |digit| <= R - 1; empty for a regularised accumulator."""
    return rows.where(F.abs("digit") > R - 1)


def add_digits(y: np.ndarray, z: np.ndarray, radix: int) -> np.ndarray:
    """Carry-free sum of two digit vectors with |digit| <= radix - 1, in numpy: each carry moves one place."""
    p = np.append(y + z, 0)
    c = np.where(p >= radix - 1, 1, np.where(p <= 1 - radix, -1, 0))
    w = p - c * radix
    w[1:] += c[:-1]
    return w
