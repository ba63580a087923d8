"""Superaccumulators: limb sums as rows, packed accumulators as structs, and what can be done with them.

Long form: rows (keys..., top, s0, s1, s2) of lazily added digits; partial and final aggregation add
them without any carry.  Packed form: struct(neg, low, digits), the value being
(-1)^neg * sum digits[i] * R^(low + i) with 0 <= digits[i] < R, no zero limb at either end.  It is
unique for a value, so equal sums have equal packed forms.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.decompose import is_negative_zero, is_special, limbs
from ..functions.formats import DOUBLE, FORMATS, HIGHEST, LOWEST, R, W, FloatFormat, round_integer

SUMS = ("s0", "s1", "s2")
FLAGS = ("n", "n_nan", "n_pinf", "n_ninf", "n_nonnegzero")
PACKED = "struct<neg:boolean,low:int,digits:array<bigint>>"


def let(value: Column, use) -> Column:
    return F.get(F.transform(F.array(value), use), 0)


def limb_rows(df: DataFrame, keys: Sequence[str], measures: dict[str, Column]) -> DataFrame:
    """One row per value: keys, m (measure), x, top, d0, d1, d2."""
    if len(measures) == 1:
        ((name, x),) = measures.items()
        d = df.select(*keys, F.lit(name).alias("m"), x.cast("double").alias("x"))
    else:
        each = F.array(*[F.struct(F.lit(n).alias("m"), x.cast("double").alias("x")) for n, x in measures.items()])
        d = df.select(*keys, F.inline(each))
    return with_limbs(d).select(*keys, "m", "x", "top", "d0", "d1", "d2")


def with_limbs(d: DataFrame) -> DataFrame:
    """Adds top, d0, d1, d2 of column x: the split of functions.decompose.limbs, one step per projection.

    Steps that use an earlier one twice stay separate projections of one generated stage, so each is
    computed once; the power of two is looked up instead of raised.
    """
    x = F.col("x")
    powers = F.array(*[F.lit(2.0 ** (-16 * k)) for k in range(LOWEST, HIGHEST + 1)])
    d = d.withColumn("top", F.when((x != 0) & ~is_special(x), F.floor((F.floor(F.log2(F.abs(x))) + 1) / W).cast("int")))
    d = d.withColumn("p__", F.get(powers, F.col("top") - LOWEST))
    d = d.withColumn("m__", x * F.col("p__") * F.col("p__"))
    d = d.withColumn("d0", F.col("m__").cast("bigint")).withColumn("r__", (F.col("m__") - F.col("d0")) * float(R))
    d = d.withColumn("d1", F.col("r__").cast("bigint"))
    return d.withColumn("d2", ((F.col("r__") - F.col("d1")) * float(R)).cast("bigint"))


def flag_values() -> dict[str, Column]:
    """What each value of column x adds to the counts that decide special results."""
    x = F.col("x")
    one = lambda c: F.when(c, 1).otherwise(0)
    return {
        "n": one(x.isNotNull()),
        "n_nan": one(F.isnan(x)),
        "n_pinf": one(x == float("inf")),
        "n_ninf": one(x == float("-inf")),
        "n_nonnegzero": one(x.isNotNull() & ~is_negative_zero(x)),
    }


def flag_sums(times: Column | None = None) -> list[Column]:
    return [F.sum(c if times is None else c * times).alias(f) for f, c in flag_values().items()]


def counted_limb_sums(rows: DataFrame, keys: Sequence[str], times: str) -> DataFrame:
    """limb_sums of rows that each stand for `times` equal ones; all together are below 2^31, as there."""
    n = F.col(times).cast("bigint")
    return rows.groupBy(*keys, "m", "top").agg(*[F.sum(F.col(f"d{i}") * n).alias(f"s{i}") for i in range(3)], *flag_sums(n))


def limb_sums(rows: DataFrame, keys: Sequence[str], wide: bool = False) -> DataFrame:
    """Lazy digit sums by (keys, m, top): the map-side combine and the reduce are Spark's partial and final aggregation.

    A digit is below 2^32, so 2^31 values can be added.  `wide` adds both 16-bit halves of each
    digit by themselves, which allows 2^46 values, and then carries between limbs as R5 does.
    """
    if not wide:
        return rows.groupBy(*keys, "m", "top").agg(*[F.sum(f"d{i}").alias(f"s{i}") for i in range(3)], *flag_sums())
    half = [F.sum(F.shiftright(f"d{i}", 16)).alias(f"h{i}") for i in range(3)]
    low = [F.sum(F.col(f"d{i}").bitwiseAND(F.lit(0xFFFF))).alias(f"l{i}") for i in range(3)]
    g = rows.groupBy(*keys, "m", "top").agg(*half, *low, *flag_sums())
    # h * 2^16 + l = (h div 2^16) * R + (h mod 2^16) * 2^16 + l: the quotient belongs to the limb above
    up = lambda i: F.shiftright(f"h{i}", 16)
    here = lambda i: F.col(f"h{i}").bitwiseAND(F.lit(0xFFFF)) * 65536 + F.col(f"l{i}")
    zero = F.lit(0).cast("bigint")
    flags = [F.col(f) for f in FLAGS]
    parts = F.array(
        F.struct(F.col("top").alias("top"), here(0).alias("s0"), here(1).alias("s1"), here(2).alias("s2"), *flags),
        F.struct((F.col("top") + 1).alias("top"), up(0).alias("s0"), up(1).alias("s1"), up(2).alias("s2"), *[zero.alias(f) for f in FLAGS]),
    )
    return g.select(*keys, "m", F.inline(parts))


def canonical(lists: Column) -> Column:
    """Packed form of array<struct<top,s0,s1,s2>> (at most one entry for each top and merge operand).

    Each sum is first cut into its digit and one local carry to the limb above, so nothing
    overflows; then one pass from the low end makes the digits unique, for the value and for its
    negation, and the one without a final borrow is the magnitude.
    """

    def cut(entries):
        def pieces(e):
            out = []
            for i in range(3):
                s = F.coalesce(e[f"s{i}"], F.lit(0).cast("bigint"))
                out += [F.struct((e["top"] - i).alias("i"), s.bitwiseAND(F.lit(R - 1)).alias("d")), F.struct((e["top"] - i + 1).alias("i"), F.shiftright(s, W).alias("d"))]
            return F.array(*out)

        return F.flatten(F.transform(F.filter(entries, lambda e: e["top"].isNotNull()), pieces))

    def dense(pieces):
        low, high = F.array_min(F.transform(pieces, lambda p: p["i"])), F.array_max(F.transform(pieces, lambda p: p["i"]))
        add = lambda i: F.aggregate(F.filter(pieces, lambda p: p["i"] == i), F.lit(0).cast("bigint"), lambda a, p: a + p["d"])
        return F.when(F.size(pieces) > 0, F.struct(low.alias("low"), F.transform(F.sequence(low, high + 1), add).alias("digits")))

    return let(dense_guard(let(cut(lists), dense)), packed_of)


def dense_guard(x: Column) -> Column:
    empty = F.struct(F.lit(0).alias("low"), F.array(F.lit(0).cast("bigint")).alias("digits"))
    return F.coalesce(x, empty)


def packed_of(dense: Column) -> Column:
    """Packed form of struct(low, digits) whose digits may have any sign below 2^62."""

    def carried(sign: int) -> Column:
        start = F.struct(F.lit(0).cast("bigint").alias("c"), F.array().cast("array<bigint>").alias("out"))

        def step(a, d):
            v = d * sign + a["c"]
            return F.struct(F.shiftright(v, W).alias("c"), F.concat(a["out"], F.array(v.bitwiseAND(F.lit(R - 1)))).alias("out"))

        return F.aggregate(dense["digits"], start, step)

    def trimmed(neg: Column, out: Column) -> Column:
        used = F.filter(F.transform(out, lambda d, i: F.when(d != 0, i)), lambda i: i.isNotNull())
        first, last = F.array_min(used), F.array_max(used)
        zero = F.struct(F.lit(False).alias("neg"), F.lit(0).alias("low"), F.array().cast("array<bigint>").alias("digits"))
        some = F.struct(neg.alias("neg"), (dense["low"] + first).cast("int").alias("low"), F.slice(out, first + 1, last - first + 1).alias("digits"))
        return F.when(F.size(used) > 0, some).otherwise(zero)

    plus, minus = carried(1), carried(-1)
    return let(plus, lambda p: F.when(p["c"] >= 0, trimmed(F.lit(False), p["out"])).otherwise(let(minus, lambda q: trimmed(F.lit(True), q["out"]))))


def pack(sums: DataFrame, keys: Sequence[str], carry: Sequence[Column] = ()) -> DataFrame:
    """(keys, m, acc, sigma, flags...) from limb sums; a key has at most a few dozen rows here."""
    entries = F.collect_list(F.when(F.col("top").isNotNull(), F.struct("top", *SUMS)))
    g = sums.groupBy(*keys, "m").agg(entries.alias("entries"), *[F.sum(f).alias(f) for f in FLAGS], *carry)
    active = F.flatten(F.transform("entries", lambda e: F.filter(F.array(*[F.when(e[f"s{i}"] != 0, e["top"] - i) for i in range(3)]), lambda i: i.isNotNull())))
    return g.withColumn("acc", canonical(F.col("entries"))).withColumn("sigma", F.size(F.array_distinct(active))).drop("entries")


def hex_text(acc: Column) -> Column:
    """The exact value as a hexadecimal float literal."""

    def text(a):
        digits = F.array_join(F.transform(F.reverse(a["digits"]), lambda d: F.lpad(F.hex(d), 8, "0")), "")
        some = F.concat(F.when(a["neg"], "-0x").otherwise("0x"), digits, F.lit("p"), (a["low"] * W).cast("string"))
        return F.when(F.size(a["digits"]) == 0, F.lit("0x0p0")).otherwise(some)

    return let(acc, text)


def acc_round(acc: Column, fmt: str | FloatFormat = "double", mode: str = "nearest_even") -> Column:
    """The accumulator's value, rounded once.  Doubles, nearest even, stay in the JVM; other formats and
    modes go through exact integers in an Arrow UDF."""
    fmt = FORMATS[fmt] if isinstance(fmt, str) else fmt
    if fmt == DOUBLE and mode in ("nearest_even", "faithful"):
        return hex_text(acc).cast("double")
    @F.pandas_udf("double")
    def rounded(text: pd.Series) -> pd.Series:
        def one(t):
            if t is None:
                return None
            total, scale = parsed(t)
            r = round_integer(total, scale, fmt, mode)
            if isinstance(r, str):
                return float(r)
            return math.ldexp(r[0], r[1])

        return text.map(one)

    if fmt.mantissa > 52:
        raise ValueError("use acc_round_parts for formats wider than a double")
    return rounded(hex_text(acc))


def acc_round_parts(acc: Column, fmt: str | FloatFormat = "quad", mode: str = "nearest_even") -> Column:
    """struct(mant DECIMAL(38,0), exp INT, inf BOOLEAN) of the value rounded to any format of up to 126 bits."""
    fmt = FORMATS[fmt] if isinstance(fmt, str) else fmt
    @F.pandas_udf("struct<mant:string,exp:int,inf:boolean>")
    def rounded(text: pd.Series) -> pd.DataFrame:
        got = [round_integer(*parsed(t), fmt, mode) for t in text]
        return pd.DataFrame({"mant": [("-1" if r[0] == "-" else "1") if isinstance(r, str) else str(r[0]) for r in got], "exp": [0 if isinstance(r, str) else r[1] for r in got], "inf": [isinstance(r, str) for r in got]})

    r = rounded(hex_text(acc))
    return F.struct(r["mant"].cast("decimal(38,0)").alias("mant"), r["exp"].alias("exp"), r["inf"].alias("inf"))


def parsed(text: str) -> tuple[int, int]:
    """(integer, binary exponent) of a hexadecimal literal."""
    mant, _, exp = text.partition("p")
    return int(mant, 16), int(exp)


def acc_sign(acc: Column) -> Column:
    return let(acc, lambda a: F.when(F.size(a["digits"]) == 0, 0).when(a["neg"], -1).otherwise(1))


def dense_of(acc: Column, sign: int = 1) -> Column:
    """Packed to array<struct<top,s0,s1,s2>>, the input of `canonical`, so that operands can be concatenated."""
    zero = F.lit(0).cast("bigint")

    def entries(a):
        value = lambda d: F.when(a["neg"], -sign * d).otherwise(sign * d)
        return F.transform(a["digits"], lambda d, i: F.struct((a["low"] + i).cast("int").alias("top"), value(d).cast("bigint").alias("s0"), zero.alias("s1"), zero.alias("s2")))

    return let(acc, entries)


def acc_add(a: Column, b: Column) -> Column:
    return canonical(F.concat(dense_of(a), dense_of(b)))


def acc_sub(a: Column, b: Column) -> Column:
    return canonical(F.concat(dense_of(a), dense_of(b, -1)))


def acc_neg(a: Column) -> Column:
    return F.when(F.size(a["digits"]) == 0, a).otherwise(F.struct((~a["neg"]).alias("neg"), a["low"].alias("low"), a["digits"].alias("digits")))


def acc_compare(a: Column, b: Column) -> Column:
    """-1, 0 or 1."""
    return acc_sign(acc_sub(a, b))


def acc_scale(a: Column, k: int) -> Column:
    """k times the value, for |k| < 2^30."""
    return canonical(F.transform(dense_of(a), lambda e: F.struct(e["top"].alias("top"), (e["s0"] * k).alias("s0"), e["s1"].alias("s1"), e["s2"].alias("s2"))))


def acc_shift(a: Column, bits: int) -> Column:
    """The value times 2^bits."""
    limb, rest = divmod(bits, W)
    moved = acc_scale(a, 1 << rest) if rest < 30 else acc_scale(acc_scale(a, 1 << 16), 1 << (rest - 16))
    return let(moved, lambda m: F.struct(m["neg"].alias("neg"), (m["low"] + limb).cast("int").alias("low"), m["digits"].alias("digits")))


def acc_of(x: Column) -> Column:
    """The accumulator of one double."""
    return let(x, _acc_of)


def _acc_of(x: Column) -> Column:
    return canonical(F.filter(F.array(F.when(~is_special(x) & (x != 0), let(limbs(x), lambda v: F.struct(v["top"].alias("top"), v["d0"].alias("s0"), v["d1"].alias("s1"), v["d2"].alias("s2"))))), lambda e: e.isNotNull()))


def acc_truncate(a: Column, gamma: int) -> Column:
    """The gamma most significant active limbs: those that aren't zero, wherever they stand."""

    def cut(x):
        places = F.reverse(F.filter(F.transform(x["digits"], lambda d, i: F.when(d != 0, i)), lambda i: i.isNotNull()))
        drop = F.coalesce(F.get(places, F.lit(gamma - 1)), F.lit(0))
        return F.struct(x["neg"].alias("neg"), (x["low"] + drop).cast("int").alias("low"), F.slice(x["digits"], drop + 1, F.size(x["digits"])).alias("digits"))

    return let(a, cut)


def acc_balanced(a: Column) -> Column:
    """The other unique form: struct(low, digits) of signed digits in [-R/2, R/2), trimmed at both ends.

    One pass from the low end; a digit of R/2 or more becomes negative and carries one.
    """

    def signed(x):
        value = F.transform(x["digits"], lambda d: F.when(x["neg"], -d).otherwise(d))
        start = F.struct(F.lit(0).cast("bigint").alias("c"), F.array().cast("array<bigint>").alias("out"))

        def step(s, d):
            v = d + s["c"]
            c = F.shiftright(v + (R >> 1), W)
            return F.struct(c.alias("c"), F.concat(s["out"], F.array(v - c * R)).alias("out"))

        out = F.aggregate(value, start, step, lambda s: F.when(s["c"] != 0, F.concat(s["out"], F.array(s["c"]))).otherwise(s["out"]))
        return let(out, lambda o: trimmed(x["low"], o))

    def trimmed(low, out):
        used = F.filter(F.transform(out, lambda d, i: F.when(d != 0, i)), lambda i: i.isNotNull())
        first, last = F.array_min(used), F.array_max(used)
        some = F.struct((low + first).cast("int").alias("low"), F.slice(out, first + 1, last - first + 1).alias("digits"))
        return F.when(F.size(used) > 0, some).otherwise(F.struct(F.lit(0).alias("low"), F.array().cast("array<bigint>").alias("digits")))

    return let(a, signed)


def acc_decimal(a: Column) -> Column:
    """The exact value as a decimal text, all digits; an Arrow UDF over one row for each sum."""

    @F.pandas_udf("string")
    def text(literal: pd.Series, low: pd.Series) -> pd.Series:
        return literal.map(lambda t: None if t is None else decimal_text(*parsed(t)))

    # used twice, the accumulator stays a column of its own below the UDF
    return text(hex_text(a), a["low"])


def decimal_text(n: int, exp: int) -> str:
    """n * 2^exp with all its decimal digits."""
    while n and exp < 0 and not n & 1:
        n, exp = n >> 1, exp + 1
    if exp >= 0 or not n:
        return str(n << max(exp, 0))
    digits = str(abs(n) * 5**-exp).rjust(1 - exp, "0")
    return f"{'-' if n < 0 else ''}{digits[:exp]}.{digits[exp:]}"


def rounded_digits(d: DataFrame, digits: Sequence[str], low: int, name: str) -> DataFrame:
    """Adds the rounded value of lazily added digit columns (the first has index `low`) to every row.

    For sums that are rounded row by row: plain arithmetic of one projection for each step, with no
    array or lambda, so it stays in the generated stage.  The sign is found by one pass of carries,
    a second pass over the magnitude makes a hexadecimal literal, and the cast of that rounds once.
    """
    c, top = "c__", len(digits) - 1
    keep = [F.col(x) for x in d.columns]
    carry = F.lit(0).cast("bigint")
    for x in digits:
        d = d.withColumn(c, F.shiftright(F.col(x) + carry, W))
        carry = F.col(c)
    d = d.withColumn("sign__", F.when(F.col(c) < 0, -1).otherwise(1).cast("bigint")).withColumn(c, F.lit(0).cast("bigint"))
    for k, x in enumerate(digits):
        d = d.withColumn("v__", F.col(x) * F.col("sign__") + F.col(c))
        d = d.withColumn(f"m{k}__", F.col("v__").bitwiseAND(F.lit(R - 1))).withColumn(c, F.shiftright("v__", W))
    text = F.concat(F.when(F.col("sign__") < 0, "-0x").otherwise("0x"), F.hex(c), *[F.lpad(F.hex(f"m{k}__"), 8, "0") for k in range(top, -1, -1)], F.lit(f"p{low * W}"))
    return d.select(*keep, text.cast("double").alias(name))


def acc_map(a: Column) -> Column:
    """Sparse form: index to signed digit, non-zero digits only."""
    pairs = F.transform(a["digits"], lambda d, i: F.struct((a["low"] + i).cast("int").alias("key"), F.when(a["neg"], -d).otherwise(d).alias("value")))
    return F.map_from_entries(F.filter(pairs, lambda p: p["value"] != 0))


def sparse_add(a: Column, b: Column) -> Column:
    """Carry-free sum of two sparse accumulators with digits below R: one carry to the next limb at most.

    P = a + b; C in {-1, 0, 1} where |P| reaches R - 1; S = P - C R + C of the limb below.
    """
    zero = F.lit(0).cast("bigint")
    total = F.map_zip_with(a, b, lambda _, x, y: F.coalesce(x, zero) + F.coalesce(y, zero))
    return let(total, _carried)


def _carried(total: Column) -> Column:
    zero = F.lit(0).cast("bigint")
    carry = lambda p: F.when(p >= R - 1, 1).when(p <= 1 - R, -1).otherwise(0).cast("bigint")
    stay = F.transform_values(total, lambda _, p: p - carry(p) * F.lit(R))
    up = F.map_from_entries(F.filter(F.transform(F.map_entries(total), lambda e: F.struct((e["key"] + 1).alias("key"), carry(e["value"]).alias("value"))), lambda e: e["value"] != 0))
    return F.map_zip_with(stay, up, lambda _, s, c: F.coalesce(s, zero) + F.coalesce(c, zero))


def from_map(a: Column) -> Column:
    zero = F.lit(0).cast("bigint")
    return canonical(F.transform(F.map_entries(a), lambda e: F.struct(e["key"].alias("top"), e["value"].alias("s0"), zero.alias("s1"), zero.alias("s2"))))


def acc_to_json(acc: Column) -> Column:
    return F.to_json(acc)


def acc_from_json(text: Column) -> Column:
    return F.from_json(text, PACKED)


def finished(acc: Column | None, value: Column) -> Column:
    """SQL and IEEE semantics around the finite sum: null, NaN, infinities and the sign of zero."""
    n = F.col
    return (
        F.when(n("n") == 0, F.lit(None).cast("double"))
        .when((n("n_nan") > 0) | ((n("n_pinf") > 0) & (n("n_ninf") > 0)), F.lit(float("nan")))
        .when(n("n_pinf") > 0, F.lit(float("inf")))
        .when(n("n_ninf") > 0, F.lit(float("-inf")))
        .when(n("n_nonnegzero") == 0, F.lit(-0.0))
        .otherwise(value)
    )
