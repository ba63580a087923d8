"""Exact sums in one round of map, combine and reduce, and everything that rests on them."""

from __future__ import annotations

import math
from collections.abc import Sequence
from fractions import Fraction
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.decompose import is_negative_zero, is_special, limbs, scaled_limbs, two_prod, unit_parts
from ..functions.formats import DOUBLE, HIGHEST, LOWEST, W, round_integer
from ..plans.planner import choose_combine, needs_wide
from . import accumulator as A
from . import kernels


def as_column(x: str | Column) -> Column:
    return F.col(x) if isinstance(x, str) else x


def packed_sums(df: DataFrame, keys: Sequence[str], measures: dict[str, Column], wide: bool = False) -> DataFrame:
    """(keys, m, acc, sigma, flags): two small shuffles whatever the number of rows."""
    return A.pack(A.limb_sums(A.limb_rows(df, keys, measures), keys, wide), keys)


def with_values(packed: DataFrame, fmt: str = "double", mode: str = "nearest_even") -> DataFrame:
    return packed.withColumn("value", A.finished(F.col("acc"), A.acc_round(F.col("acc"), fmt, mode)))


def exact_sum(df: DataFrame, col: str | Column, keys: Sequence[str] = (), *, wide: bool | None = False, fmt: str = "double", mode: str = "nearest_even", detail: bool = False, name: str = "value") -> DataFrame:
    """Correctly rounded sum per key; with `detail` also acc, sigma, n and the special-value flags.

    `wide=None` counts the rows first and chooses the split that cannot overflow.  Without keys an
    empty input gives one null row, as SQL's sum does.
    """
    if wide is None:
        wide = needs_wide(df.count())
    packed = packed_sums(df, keys, {name: as_column(col)}, wide)
    out = with_values(packed, fmt, mode)
    if not keys:
        base = df.sparkSession.range(1).select()
        out = base.join(out, F.lit(True), "left")
    cols = [*keys, F.col("value").alias(name)]
    return out.select(*cols, *([F.col(c) for c in ("acc", "sigma", *A.FLAGS)] if detail else []))


def exact_agg(df: DataFrame, keys: Sequence[str] = (), wide: bool = False, **measures: str | Column) -> DataFrame:
    """Several exact sums in one pass, one output column for each."""
    packed = with_values(packed_sums(df, keys, {n: as_column(c) for n, c in measures.items()}, wide))
    return packed.groupBy(*keys).agg(*[F.max(F.when(F.col("m") == n, F.col("value"))).alias(n) for n in measures])


def exact_grouping_sets(df: DataFrame, col: str | Column, keys: Sequence[str], kind: str = "rollup", name: str = "value") -> DataFrame:
    """rollup or cube of exact sums with grouping_id; the limb bucket is in every grouping set."""
    rows = A.limb_rows(df, keys, {name: as_column(col)})
    sums = A.limb_sums(rows, keys)
    sets = [keys[:k] for k in range(len(keys), -1, -1)] if kind == "rollup" else [[k for i, k in enumerate(keys) if s >> i & 1] for s in range(1 << len(keys))]
    # expanding the limb sums, not the rows: each set adds a few dozen rows for each group
    wide = sums.withColumnsRenamed({k: f"{k}__" for k in keys})
    kept = F.array(*[F.struct(*[(F.col(f"{k}__") if k in s else F.lit(None).cast(df.schema[k].dataType)).alias(k) for k in keys], F.lit(sum((k not in s) << (len(keys) - 1 - i) for i, k in enumerate(keys))).alias("gid")) for s in sets])
    flat = wide.select("m", "top", *A.SUMS, *A.FLAGS, F.inline(kept))
    again = flat.groupBy(*keys, "gid", "m", "top").agg(*[F.sum(s).alias(s) for s in A.SUMS], *[F.sum(f).alias(f) for f in A.FLAGS])
    return with_values(A.pack(again, [*keys, "gid"])).select(*keys, "gid", F.col("value").alias(name))


def exact_sum_distinct(df: DataFrame, col: str | Column, keys: Sequence[str] = (), name: str = "value") -> DataFrame:
    x = as_column(col).cast("double")
    return exact_sum(df.select(*keys, (x + 0.0).alias("x")).distinct(), "x", keys, name=name)


def exact_avg(df: DataFrame, col: str | Column, keys: Sequence[str] = (), name: str = "value") -> DataFrame:
    """The exact mean rounded once.  The quotient of two integers is rounded in an Arrow UDF over one row per key."""
    packed = packed_sums(df, keys, {name: as_column(col)})

    @F.pandas_udf("double")
    def quotient(text: pd.Series, n: pd.Series) -> pd.Series:
        return pd.Series([_ratio(*A.parsed(t), k, 1, 0) if k else None for t, k in zip(text, n, strict=True)])

    mean = A.finished(F.col("acc"), quotient(A.hex_text(F.col("acc")), F.col("n")))
    return packed.select(*keys, mean.alias(name))


def _ratio(total: int, scale: int, over: int, sign: int = 1, over_scale: int = 0) -> float:
    """total * 2^scale / (over * 2^over_scale), correctly rounded."""
    q = Fraction(total) / Fraction(over)
    shift = scale - over_scale
    # 200 bits of quotient, and a sticky bit
    k = 200 - (abs(q.numerator).bit_length() - q.denominator.bit_length())
    n = q.numerator << k if k >= 0 else q.numerator
    d = q.denominator if k >= 0 else q.denominator << -k
    whole, rest = divmod(abs(n), d)
    whole = (whole << 1) | (rest != 0)
    r = round_integer(-whole if n < 0 else whole, shift - k - 1, DOUBLE)
    return float(r) if isinstance(r, str) else math.ldexp(float(r[0]), r[1])


def product_rows(df: DataFrame, keys: Sequence[str], products: dict[str, tuple[Column, Column]]) -> DataFrame:
    """Like limb_rows, for the exact products of pairs of doubles: two rows for each, of the rounded
    product and of its error, both taken from mantissas, so neither over- nor underflows.

    x is null in the second row; in the first it has the class and sign of the product.
    """
    each = F.array(*[F.struct(F.lit(m).alias("m"), a.cast("double").alias("a"), b.cast("double").alias("b")) for m, (a, b) in products.items()])
    d = df.select(*keys, F.inline(each)) if len(products) > 1 else df.select(*keys, *[v for m, (a, b) in products.items() for v in (F.lit(m).alias("m"), a.cast("double").alias("a"), b.cast("double").alias("b"))])
    a, b = F.col("a"), F.col("b")
    plain = ~is_special(a) & ~is_special(b) & (a != 0) & (b != 0)
    d = d.withColumn("x", F.when(plain, F.lit(1.0)).otherwise(a * b)).withColumns({"u": unit_parts(a), "v": unit_parts(b)})
    d = d.withColumn("p", two_prod(F.col("u.m"), F.col("v.m"))).withColumn("k", F.col("u.e") + F.col("v.e"))
    rows = F.array(F.struct(F.col("x"), F.col("p.p").alias("y")), F.struct(F.lit(None).cast("double").alias("x"), F.col("p.e").alias("y")))
    d = d.select(*keys, "m", F.when(plain, F.col("k")).alias("k"), F.inline(rows))
    limb = scaled_limbs(F.col("y"), F.col("k"))
    d = d.withColumn("l", F.when(F.col("k").isNotNull(), limb)).where("x is not null or l is not null or k is null")
    return d.select(*keys, "m", "x", "l.top", "l.d0", "l.d1", "l.d2")


def _moments(df: DataFrame, keys: Sequence[str], sums: dict[str, Column], products: dict[str, tuple[Column, Column]]) -> DataFrame:
    """(keys, n, special, one hexadecimal text for each exact sum); n counts the first of `sums`.

    A row with a column times__ stands for that many equal ones.
    """
    own = [*keys, *[c for c in df.columns if c == "times__"]]
    rows = A.limb_rows(df, own, sums).unionByName(product_rows(df, own, products))
    total = A.counted_limb_sums(rows, keys, "times__") if len(own) > len(keys) else A.limb_sums(rows, keys)
    packed = A.pack(total, keys).withColumn("t", A.hex_text(F.col("acc")))
    of = lambda m, c: F.max(F.when(F.col("m") == m, F.col(c)))
    special = F.max((F.col("n_nan") > 0) | (F.col("n_pinf") > 0) | (F.col("n_ninf") > 0))
    return packed.groupBy(*keys).agg(of(next(iter(sums)), "n").alias("n"), special.alias("special"), *[of(m, "t").alias(m) for m in (*sums, *products)])


def _rational(names: Sequence[str], form) -> Column:
    """A double from exact sums: form(n, *sums) gives a Fraction, a (sign, Fraction) whose root is meant, or None.

    An Arrow UDF over one row per key.  NaN where special values took part.
    """

    @F.pandas_udf("string")  # a pandas result can't tell NaN from null
    def run(row: pd.DataFrame) -> pd.Series:
        out = []
        for r in row.itertuples(index=False):
            got = None if r.n is None or r.n != r.n else form(int(r.n), *[_fraction(getattr(r, m)) for m in names])
            out.append(None if got is None else "NaN" if r.special else repr(_root(*got) if isinstance(got, tuple) else _nearest(got)))
        return pd.Series(out, dtype=object)

    return run(F.struct("n", "special", *names)).cast("double")


def _fraction(text: str) -> Fraction:
    n, exp = A.parsed(text)
    return Fraction(n) * Fraction(2) ** exp


def _nearest(q: Fraction) -> float:
    return _ratio(q.numerator, 0, q.denominator)


def _root(sign: int, q: Fraction) -> float:
    """sign * sqrt(q), correctly rounded: 120 bits of the root and a sticky bit."""
    k = max(0, 120 - (q.numerator.bit_length() - q.denominator.bit_length()) // 2)
    whole, rest = divmod(q.numerator << (2 * k), q.denominator)
    root = math.isqrt(whole)
    sticky = (root << 1) | (rest != 0 or root * root != whole)
    r = round_integer(sign * sticky, -k - 1, DOUBLE)
    return float(r) if isinstance(r, str) else math.ldexp(float(r[0]), r[1])


def _spread(n: int, sx: Fraction, sy: Fraction, sxy: Fraction) -> Fraction:
    return (n * sxy - sx * sy) / (n * (n - 1))


def exact_var(df: DataFrame, col: str | Column, keys: Sequence[str] = (), name: str = "value", root: bool = False) -> DataFrame:
    """Sample variance (n sum x^2 - (sum x)^2) / (n (n - 1)), or its root: exact inside, one rounding.

    Null for fewer than two values, NaN where a value is NaN or infinite.
    """
    x = as_column(col).cast("double")
    g = _moments(df, keys, {"x": x}, {"p": (x, x)})
    q = lambda n, sx, sp: None if n < 2 else (1, _spread(n, sx, sx, sp)) if root else _spread(n, sx, sx, sp)
    return g.select(*keys, _rational(["x", "p"], q).alias(name))


def exact_std(df: DataFrame, col: str | Column, keys: Sequence[str] = (), name: str = "value") -> DataFrame:
    return exact_var(df, col, keys, name, root=True)


def _pairs(df: DataFrame, a: str | Column, b: str | Column, keys: Sequence[str]) -> DataFrame:
    """(keys, a__, b__) where both are given; equal pairs as one row with their number times__ where that at least halves the rows."""
    d = df.select(*keys, as_column(a).cast("double").alias("a__"), as_column(b).cast("double").alias("b__")).where("a__ is not null and b__ is not null")
    own = [*keys, "a__", "b__"]
    return d.groupBy(*own).agg(F.count("*").alias("times__")) if choose_combine(d, own, d.count()) else d


def exact_cov(df: DataFrame, a: str | Column, b: str | Column, keys: Sequence[str] = (), name: str = "value") -> DataFrame:
    """Sample covariance over rows where both are given."""
    x, y = F.col("a__"), F.col("b__")
    g = _moments(_pairs(df, a, b, keys), keys, {"x": x, "y": y}, {"p": (x, y)})
    return g.select(*keys, _rational(["x", "y", "p"], lambda n, sx, sy, sp: None if n < 2 else _spread(n, sx, sy, sp)).alias(name))


def exact_corr(df: DataFrame, a: str | Column, b: str | Column, keys: Sequence[str] = (), name: str = "value") -> DataFrame:
    """Pearson's correlation; null where a column doesn't vary."""
    x, y = F.col("a__"), F.col("b__")
    g = _moments(_pairs(df, a, b, keys), keys, {"x": x, "y": y}, {"p": (x, y), "xx": (x, x), "yy": (y, y)})

    def form(n, sx, sy, sp, sxx, syy):
        u, v, w = n * sxx - sx * sx, n * syy - sy * sy, n * sp - sx * sy
        return None if not u or not v else ((w > 0) - (w < 0), w * w / (u * v))

    return g.select(*keys, _rational(["x", "y", "p", "xx", "yy"], form).alias(name))


def exact_weighted_avg(df: DataFrame, col: str | Column, weight: str | Column, keys: Sequence[str] = (), name: str = "value") -> DataFrame:
    """sum w x / sum w over rows where both are given; null where the weights add up to zero."""
    x, w = F.col("a__"), F.col("b__")
    g = _moments(_pairs(df, col, weight, keys), keys, {"w": w}, {"p": (x, w)})
    return g.select(*keys, _rational(["w", "p"], lambda n, sw, sp: sp / sw if sw else None).alias(name))


def exact_dot(df: DataFrame, a: str | Column, b: str | Column, keys: Sequence[str] = (), name: str = "value") -> DataFrame:
    """Sum of products of two double columns, each product split without error whatever its size."""
    rows = product_rows(df, keys, {name: (as_column(a), as_column(b))})
    out = with_values(A.pack(A.limb_sums(rows, keys), keys))
    if not keys:
        out = df.sparkSession.range(1).select().join(out, F.lit(True), "left")
    return out.select(*keys, F.col("value").alias(name))


def array_exact_sum(xs: Column) -> Column:
    """Exact sum of the elements of an array column, without any shuffle.

    Null for a null array and for one without values; NaN, infinities and negative zeros as in IEEE sums.
    """

    def total(v):
        finite = F.filter(v, lambda x: (x != 0) & ~is_special(x))
        entries = F.transform(finite, lambda x: A.let(limbs(x), lambda l: F.struct(l["top"].alias("top"), l["d0"].alias("s0"), l["d1"].alias("s1"), l["d2"].alias("s2"))))
        up, down = F.exists(v, lambda x: x == float("inf")), F.exists(v, lambda x: x == float("-inf"))
        return (
            F.when(F.size(v) == 0, F.lit(None).cast("double"))
            .when(F.exists(v, F.isnan) | (up & down), F.lit(float("nan")))
            .when(up, F.lit(float("inf")))
            .when(down, F.lit(float("-inf")))
            .when(F.forall(v, is_negative_zero), F.lit(-0.0))
            .otherwise(A.hex_text(A.canonical(entries)).cast("double"))
        )

    given = F.transform(F.filter(xs, lambda x: x.isNotNull()), lambda x: x.cast("double"))
    return F.when(xs.isNotNull(), A.let(given, total))


def array_exact_dot(a: Column, b: Column) -> Column:
    """Exact dot product of FLOAT arrays: products of two singles are exact doubles."""
    return array_exact_sum(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")))


def array_exact_norm(a: Column) -> Column:
    return F.sqrt(array_exact_dot(a, a))


def sum_mapreduce(df: DataFrame, col: str | Column, keys: Sequence[str] = (), *, p: int = 8, placement: str = "salt", acc: str = "sparse", combine: bool = True, finalize: str = "executor", name: str = "value") -> DataFrame:
    """The one-round method with its choices spelt out.

    placement  which reducer gets a value or a block's accumulator: 'salt' (any, by the row's number),
               'hash:c' (hash of column c), 'range:idx' (by range of limb index) or 'partition' (by block)
    combine    True: one accumulator for each block is sent; False: every value is
    acc        'sparse' (active limbs as rows), 'dense' (all limbs in one array of a block, see sum_scan)
               or 'dense_sql' (all limbs as columns of a SQL aggregation)
    finalize   'executor' merges the p accumulators in a second aggregation; 'driver' collects them
    """
    x = as_column(col).cast("double")
    if acc == "dense" and combine:
        return sum_scan(df, col, keys, name)
    rows = A.limb_rows(df.withColumn("salt__", _salt(placement, p)), [*keys, "salt__"], {name: x})
    if placement == "range:idx":
        rows = rows.withColumn("salt__", F.floor((F.coalesce("top", F.lit(0)) - LOWEST) * p / (HIGHEST - LOWEST + 1)).cast("int"))
    if not combine:
        rows = rows.repartition(p, "salt__", *keys)
    if acc != "sparse":
        return _dense(rows, keys, name)
    sums = A.limb_sums(rows, [*keys, "salt__"])
    if finalize == "driver":
        return _on_driver(A.pack(sums, [*keys, "salt__"]), keys, name)
    again = sums.groupBy(*keys, "m", "top").agg(*[F.sum(s).alias(s) for s in A.SUMS], *[F.sum(f).alias(f) for f in A.FLAGS])
    return with_values(A.pack(again, keys)).select(*keys, F.col("value").alias(name))


def _salt(placement: str, p: int) -> Column:
    if placement == "partition":
        return F.pmod(F.spark_partition_id(), F.lit(p)).cast("int")
    source = F.col(placement.partition(":")[2]) if placement.startswith("hash:") else F.monotonically_increasing_id()
    return F.pmod(F.xxhash64(source), F.lit(p)).cast("int")


def dense_sums(lowest: int = LOWEST, highest: int = LOWEST + 68) -> list[Column]:
    """One sum for each limb index."""
    zero = F.lit(0).cast("bigint")
    each = lambda k: reduce(lambda a, i: a.when(F.col("top") == k + i, F.col(f"d{i}")), (1, 2), F.when(F.col("top") == k, F.col("d0")))
    return [F.coalesce(F.sum(each(k)), zero).alias(f"limb{k - lowest}") for k in range(lowest, highest + 1)]


def dense_entries(lowest: int = LOWEST, highest: int = LOWEST + 68) -> Column:
    zero = F.lit(0).cast("bigint")
    return F.array(*[F.struct(F.lit(k).alias("top"), F.col(f"limb{k - lowest}").alias("s0"), zero.alias("s1"), zero.alias("s2")) for k in range(lowest, highest + 1)])


def _dense(rows: DataFrame, keys: Sequence[str], name: str) -> DataFrame:
    g = rows.groupBy(*keys, "salt__").agg(*dense_sums(), *A.flag_sums())
    limb = [c for c in g.columns if c.startswith("limb")]
    g = g.groupBy(*keys).agg(*[F.sum(c).alias(c) for c in limb], *[F.sum(f).alias(f) for f in A.FLAGS])
    acc = A.canonical(dense_entries())
    return g.withColumn("acc", acc).select(*keys, A.finished(F.col("acc"), A.acc_round(F.col("acc"))).alias(name))


def _on_driver(packed: DataFrame, keys: Sequence[str], name: str) -> DataFrame:
    """p accumulators for each key come to the driver; for few keys."""
    totals: dict[tuple, list] = {}
    for r in packed.select(*keys, A.hex_text(F.col("acc")).alias("t"), *A.FLAGS).toLocalIterator():
        v = totals.setdefault(tuple(r[k] for k in keys), [0, *[0] * len(A.FLAGS)])
        i, s = A.parsed(r["t"])
        v[0] += i << (s - LOWEST * W)
        for k, f in enumerate(A.FLAGS):
            v[k + 1] += r[f]
    schema = ", ".join([*[f"`{k}` {packed.schema[k].dataType.simpleString()}" for k in keys], f"`{name}` double"])
    out = []
    for key, (total, n, nan, pinf, ninf, nonneg) in totals.items():
        r = round_integer(total, LOWEST * W)
        x = float(r) if isinstance(r, str) else math.ldexp(float(r[0]), r[1])
        x = None if n == 0 else math.nan if nan or (pinf and ninf) else math.inf if pinf else -math.inf if ninf else -0.0 if nonneg == 0 else x
        out.append((*key, x))
    return packed.sparkSession.createDataFrame(out, schema)


def sum_scan(df: DataFrame, col: str | Column, keys: Sequence[str] = (), name: str = "value") -> DataFrame:
    """Scan-based external sum: each block keeps one dense accumulator in memory and sends what is active.

    A numpy kernel over Arrow batches; with keys a block keeps one accumulator for each key it meets.
    """
    rows = df.select(*keys, as_column(col).cast("double").alias("x"))
    schema = ", ".join([*[f"`{k}` {rows.schema[k].dataType.simpleString()}" for k in keys], "top int, s0 bigint, s1 bigint, s2 bigint", *[f"{f} bigint" for f in A.FLAGS]])

    def block(batches):
        held: dict[tuple, kernels.BlockSum] = {}
        for b in batches:
            x = b.column("x").to_numpy(zero_copy_only=False)
            valid = np.asarray(b.column("x").is_valid()) if b.column("x").null_count else np.ones(len(x), bool)
            if not keys:
                held.setdefault((), kernels.BlockSum()).add(x[valid])
                continue
            t = pa.Table.from_batches([b]).select(list(keys)).to_pandas()
            for key, at in t.groupby(list(keys), dropna=False, sort=False).indices.items():
                key = key if isinstance(key, tuple) else (key,)
                held.setdefault(tuple(None if isinstance(k, float) and k != k else k for k in key), kernels.BlockSum()).add(x[at][valid[at]])
        out = []
        for key, s in held.items():
            out += [(*key, *r) for r in s.rows()]
        names = [*keys, "top", *A.SUMS, *A.FLAGS]
        cols = list(zip(*out, strict=True)) if out else [[] for _ in names]
        yield pa.RecordBatch.from_arrays([pa.array(c, type=b_type) for c, b_type in zip(cols, types, strict=True)], names=names)

    from pyspark.sql.pandas.types import to_arrow_type

    types = [*[to_arrow_type(rows.schema[k].dataType) for k in keys], pa.int32(), *[pa.int64()] * (3 + len(A.FLAGS))]
    sent = rows.mapInArrow(block, schema).withColumn("m", F.lit(name))
    sums = sent.groupBy(*keys, "m", "top").agg(*[F.sum(s).alias(s) for s in A.SUMS], *[F.sum(f).alias(f) for f in A.FLAGS])
    return with_values(A.pack(sums, keys)).select(*keys, F.col("value").alias(name))


def decimal_sum(df: DataFrame, col: str | Column, keys: Sequence[str] = (), name: str = "value") -> DataFrame:
    """Base-10 accumulators for DECIMAL columns: limbs of nine decimal digits in BIGINT, any total width up to 10^38."""
    x = as_column(col)
    scale = df.select(x.alias("x")).schema["x"].dataType.scale
    unscaled = (x.cast("decimal(38,%d)" % scale) * F.lit(10**scale).cast("decimal(%d,0)" % (scale + 1))).cast("decimal(38,0)")
    digit = lambda k: F.expr(f"cast(sign(u) * (floor(abs(u) / {10 ** (9 * k)}BD) % 1000000000) as bigint)")
    d = df.select(*keys, unscaled.alias("u")).select(*keys, *[digit(k).alias(f"d{k}") for k in range(3)])
    g = d.groupBy(*keys).agg(*[F.sum(f"d{k}").alias(f"d{k}") for k in range(3)])
    total = reduce(lambda a, b: a + b, [F.col(f"d{k}").cast("decimal(38,0)") * F.lit(10 ** (9 * k)).cast("decimal(19,0)") for k in range(3)])
    return g.select(*keys, (total.cast("decimal(38,0)") / F.lit(10**scale).cast("decimal(19,0)")).cast(f"decimal(38,{scale})").alias(name))
