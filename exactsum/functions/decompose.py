"""Doubles as limbs of radix 2^32, and error-free arithmetic, as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .formats import R, W


def is_special(x: Column) -> Column:
    return F.isnan(x) | (F.abs(x) == float("inf"))


def is_negative_zero(x: Column) -> Column:
    return (x == 0) & (x.cast("string") == "-0.0")


def scalb(x: Column, k: Column) -> Column:
    """x * 2^k for |k| up to 2098, in two factors so that nothing overflows or underflows on the way."""
    half = F.floor(k / 2)
    return x * F.pow(F.lit(2.0), half.cast("double")) * F.pow(F.lit(2.0), (k - half).cast("double"))


def exponent(x: Column) -> Column:
    """e with 2^e <= |x| < 2^(e+1); null for zero, NaN and infinities.  log2 only guesses; the scaled value decides."""
    guess = F.floor(F.log2(F.abs(x))).cast("int")
    m = F.abs(scalb(x, -guess))
    e = guess + F.when(m >= 2, 1).when(m < 1, -1).otherwise(0)
    return F.when(~is_special(x) & (x != 0), e)


def float_parts(x: Column) -> Column:
    """struct(neg, mant, exp): x = (-1)^neg * mant * 2^exp with mant < 2^53; null where x is special."""
    e = F.greatest(F.coalesce(exponent(x), F.lit(-1022)), F.lit(-1022)) - 52
    mant = F.abs(scalb(x, -e)).cast("bigint")
    return F.when(~is_special(x), F.struct(((x < 0) | is_negative_zero(x)).alias("neg"), mant.alias("mant"), e.alias("exp")))


def limbs(x: Column) -> Column:
    """struct(top, d0, d1, d2): x = d0 R^top + d1 R^(top-1) + d2 R^(top-2); null for zero and special values.

    Every digit has the sign of x and a magnitude below R.  The bucket `top` comes from log2, and an
    off-by-one there leaves the split exact: the scaled value lies between 2^-2 and 2^32.
    """
    top = F.floor((F.floor(F.log2(F.abs(x))) + 1) / W).cast("int")
    m = x * F.pow(F.lit(2.0), -16.0 * top) * F.pow(F.lit(2.0), -16.0 * top)
    d0 = m.cast("bigint")
    m1 = (m - d0) * float(R)
    d1 = m1.cast("bigint")
    d2 = ((m1 - d1) * float(R)).cast("bigint")
    return F.when((x != 0) & ~is_special(x), F.struct(top.alias("top"), d0.alias("d0"), d1.alias("d1"), d2.alias("d2")))


def to_fixed(x: Column, lowbit: int) -> Column:
    """x / 2^lowbit as DECIMAL(38,0), for whole multiples of up to 2^126; an error for anything else."""
    p = float_parts(x)
    shift = p["exp"] - lowbit
    # 2^shift as a product of two whole numbers below 2^63
    up = F.call_function("shiftleft", F.lit(1).cast("bigint"), F.least(F.greatest(shift, F.lit(0)), F.lit(62))).cast("decimal(19,0)")
    more = F.call_function("shiftleft", F.lit(1).cast("bigint"), F.greatest(shift - 62, F.lit(0))).cast("decimal(19,0)")
    down = F.call_function("shiftright", p["mant"], F.least(F.greatest(-shift, F.lit(0)), F.lit(62)))
    back = F.call_function("shiftleft", down, F.least(F.greatest(-shift, F.lit(0)), F.lit(62)))
    size = F.when(shift >= 0, (p["mant"].cast("decimal(16,0)") * up * more).cast("decimal(38,0)")).when((back == p["mant"]) | (p["mant"] == 0), down.cast("decimal(38,0)"))
    whole = F.coalesce(size, F.raise_error(F.lit(f"not a multiple of 2^{lowbit} in range")).cast("decimal(38,0)"))
    return F.when(x.isNotNull(), F.when(p["neg"], -whole).otherwise(whole))


def two_sum(a: Column, b: Column) -> Column:
    """struct(s, e) with a + b = s + e exactly, s the rounded sum; any order."""
    s = a + b
    v = s - a
    return F.struct(s.alias("s"), ((a - (s - v)) + (b - v)).alias("e"))


def fast_two_sum(a: Column, b: Column) -> Column:
    """The same for |a| >= |b|."""
    s = a + b
    return F.struct(s.alias("s"), (b - (s - a)).alias("e"))


def halves(x: Column) -> tuple[Column, Column]:
    """High and low part of 26 bits each."""
    t = x * 134217729.0
    high = t - (t - x)
    return high, x - high


def two_prod(a: Column, b: Column) -> Column:
    """struct(p, e) with a * b = p + e exactly, barring under- and overflow."""
    p = a * b
    (ah, al), (bh, bl) = halves(a), halves(b)
    return F.struct(p.alias("p"), (((ah * bh - p) + ah * bl + al * bh) + al * bl).alias("e"))


def unit_parts(x: Column) -> Column:
    """struct(m, e) with x = m * 2^e and 1 <= |m| < 2; null for zero and special values."""
    e = exponent(x)
    return F.when(e.isNotNull(), F.struct(scalb(x, -e).alias("m"), e.alias("e")))


def scaled_limbs(x: Column, k: Column) -> Column:
    """limbs(x * 2^k) for 2^-120 <= |x| < 2^2, without ever forming the product; null for zero."""
    e = exponent(x) + k
    top = F.floor((e + 1) / W).cast("int")
    m = x * F.pow(F.lit(2.0), (k - W * top).cast("double"))
    d0 = m.cast("bigint")
    r = (m - d0) * float(R)
    d1 = r.cast("bigint")
    return F.when(x != 0, F.struct(top.alias("top"), d0.alias("d0"), d1.alias("d1"), ((r - d1) * float(R)).cast("bigint").alias("d2")))


def ulp(x: Column) -> Column:
    """Distance of the doubles at x's exponent."""
    e = F.greatest(F.coalesce(exponent(x), F.lit(-1022)), F.lit(-1022)) - 52
    return F.when(~is_special(x), scalb(F.lit(1.0), e))


def next_up(x: Column) -> Column:
    """The least double above x."""
    u = ulp(x)
    power = F.abs(scalb(F.lit(1.0), F.coalesce(exponent(x), F.lit(0)))) == F.abs(x)
    return F.when((x < 0) & power & (u > 4.9406564584124654e-324), x + u / 2).otherwise(x + u)


def next_down(x: Column) -> Column:
    return -next_up(-x)


def hexfloat(x: Column) -> Column:
    """x as text that keeps every bit, e.g. -0x1a8p-3; nulls and special values as their names."""
    p = float_parts(x)
    text = F.concat(F.when(p["neg"], "-0x").otherwise("0x"), F.lower(F.hex(p["mant"])), F.lit("p"), p["exp"].cast("string"))
    return F.when(is_special(x), x.cast("string")).otherwise(text)


def parse_hexfloat(text: Column) -> Column:
    return text.cast("double")


def is_finite(x: Column) -> Column:
    return ~is_special(x)


def magnitude_at_least(x: Column, k: int) -> Column:
    """|x| >= 2^k, as two comparisons that a Parquet scan can use."""
    return (x >= 2.0**k) | (x <= -(2.0**k))


def same_sign(x: Column, negative: bool = False) -> Column:
    return x < 0 if negative else x > 0
