import math
import random
import struct
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

from exactsum.functions import decompose as D
from exactsum.functions.formats import DOUBLE, HALF, QUAD, SINGLE, FloatFormat, round_integer
from exactsum.operators import accumulator as A
from exactsum.operators import baselines as B
from exactsum.operators import external as X
from exactsum.operators import kernels as K
from exactsum.operators import mapreduce as M
from exactsum.operators import tree as T
from exactsum.plans import metrics as C


def bits(x):
    return None if x is None else "nan" if x != x else struct.pack("d", x)


def true_sum(v):
    v = [x for x in v if x is not None]
    if not v:
        return None
    if any(x != x for x in v) or {math.inf, -math.inf} <= set(v):
        return math.nan
    if math.inf in v or -math.inf in v:
        return math.inf if math.inf in v else -math.inf
    if all(x == 0 and math.copysign(1, x) < 0 for x in v):
        return -0.0
    try:
        return float(sum(map(Fraction, v))) + 0.0
    except OverflowError:
        return math.inf if sum(map(Fraction, v)) > 0 else -math.inf


def groups():
    rng = random.Random(5)
    out = {}
    for g in range(120):
        n = rng.randint(1, 15)
        v = [math.ldexp(rng.choice([-1, 1]) * rng.random(), rng.randint(-1073, 1000) if g % 3 else rng.randint(-3, 3)) for _ in range(n)]
        out[g] = v + [-x for x in v] if g % 5 == 0 else v
    hand = [
        [1e308, 1e308, -1e308], [1.7976931348623157e308] * 2, [2.0**53, 1.0, -(2.0**53)], [1.0, 2.0**-53], [1.0, 2.0**-53, 2.0**-1074], [5e-324] * 3,
        [2.0**54, -(2.0**-20)], [2.0**54, 2 - 2.0**-52, 2 - 2.0**-52, 1 - 2.0**-53], [math.nan, 1.0], [math.inf, -math.inf], [math.inf, 1.0], [-0.0, -0.0], [0.0, -0.0], [None, None], [2.0**31, 2.0**63, -(2.0**31)],
    ]
    return out | {1000 + i: v for i, v in enumerate(hand)}


@pytest.fixture(scope="module")
def data(spark):
    rows = [(g, x) for g, v in groups().items() for x in v]
    return spark.createDataFrame(rows, "g long, x double").repartition(5).cache()


def same(df):
    want = {g: bits(true_sum(v)) for g, v in groups().items()}
    got = {r[0]: bits(r[1]) for r in df.collect()}
    assert got == want


METHODS = {
    "one round": lambda d: M.exact_sum(d, "x", ["g"]),
    "wide digits": lambda d: M.exact_sum(d, "x", ["g"], wide=True),
    "by hash of a column": lambda d: M.sum_mapreduce(d, "x", ["g"], placement="hash:g"),
    "by limb": lambda d: M.sum_mapreduce(d, "x", ["g"], placement="range:idx"),
    "by block": lambda d: M.sum_mapreduce(d, "x", ["g"], placement="partition"),
    "no combine": lambda d: M.sum_mapreduce(d, "x", ["g"], combine=False),
    "dense": lambda d: M.sum_mapreduce(d, "x", ["g"], acc="dense"),
    "on the driver": lambda d: M.sum_mapreduce(d, "x", ["g"], finalize="driver"),
    "scan": lambda d: M.sum_scan(d, "x", ["g"]),
    "tree": lambda d: T.sum_tree(d, "x", ["g"], fan_in=8, leaves=64),
    "binary tree": lambda d: T.sum_tree(d, "x", ["g"], fan_in=2, leaves=4),
    "pairwise": lambda d: T.sum_pairwise_tree(d, "x", ["g"], leaves=8),
    "sorted": lambda d: X.sum_sorted(d, "x", ["g"]),
    "adaptive cut": lambda d: T.sum_adaptive(d, "x", ["g"]).select("g", "value"),
    "adaptive tree": lambda d: T.sum_adaptive(d, "x", ["g"], variant="tree", leaves=4, fan_in=2).select("g", "value"),
    "dense columns": lambda d: M.sum_mapreduce(d, "x", ["g"], acc="dense_sql"),
    "external": lambda d: X.sum_external(d, "x", ["g"], memory_bytes=64),
    "accumulator table": lambda d: merged(d),
}


def merged(d):
    from exactsum.sources import io

    a = M.packed_sums(d.where("pmod(hash(x), 2) = 0"), ["g"], {"v": F.col("x")})
    b = M.packed_sums(d.where("pmod(hash(x), 2) = 1 or x is null"), ["g"], {"v": F.col("x")})
    return io.merge_acc(a.unionByName(b), ["g"])


@pytest.mark.parametrize("method", METHODS)
def test_every_method_gives_the_same_bits(data, method):
    same(METHODS[method](data))


def test_without_keys_and_empty(spark, data):
    finite = data.where("x is not null and x <> double('NaN') and abs(x) < double('Infinity')")
    want = true_sum([x for v in groups().values() for x in v if x is not None and math.isfinite(x)])
    for p in (1, 3, 16):
        d = finite.repartition(p)
        assert M.exact_sum(d, "x").first()[0] == want
        assert M.sum_scan(d, "x").first()[0] == want
    empty = data.limit(0)
    assert M.exact_sum(empty, "x").collect()[0][0] is None
    assert M.exact_sum(empty, "x", ["g"]).count() == 0


def test_faithful_stop_tests_are_sound(spark):
    trap = spark.createDataFrame([(2.0**54,), (2 - 2.0**-52,), (2 - 2.0**-52,), (1 - 2.0**-53,)], "x double")
    for stop in ("float", "exponent", "certified"):
        for variant in ("cut", "tree"):
            assert T.sum_adaptive(trap, "x", stop=stop, variant=variant).first().value == 2.0**54 + 4
    # zero-sum data never certifies before nothing is dropped; well-conditioned data stops at once
    rng = random.Random(2)
    v = [math.ldexp(rng.random(), rng.randint(-900, 900)) for _ in range(200)]
    for variant in ("cut", "tree"):
        zero = T.sum_adaptive(spark.createDataFrame([(s * x,) for x in v for s in (1, -1)], "x double"), "x", variant=variant).first()
        assert zero.value == 0 and zero.r == 256 and zero.accepted == "exact" and zero.certified and zero.truncations == 0
        easy = T.sum_adaptive(spark.createDataFrame([(x,) for x in v], "x double"), "x", variant=variant).first()
        assert easy.value == math.fsum(v) and easy.r <= 4 and easy.accepted == "certified" and easy.truncations > 0


def test_truncated_tree_is_not_the_row_cut(spark):
    """Leaves keep their own highest limbs, so cancelled high limbs don't hide what the row cut loses."""
    v = [2.0**200, -(2.0**200), 1.0, 2.0**-40]
    d = spark.createDataFrame([(x,) for x in v], "x double")
    cut = T.sum_adaptive(d, "x", variant="cut").first()
    tree = T.sum_adaptive(d, "x", variant="tree", leaves=1).first()
    assert cut.value == tree.value == 1 + 2.0**-40 and cut.accepted == tree.accepted == "exact"
    # limb -1 is never other than zero, so the two kept are 0 and -2, and limb -3 is cut
    w = [1.0 + 2.0**-50, 2.0**-70, 3.0]
    one = T._tree_kept(spark.createDataFrame([(x,) for x in w], "x double"), [], None, 2, 1, 2).first()
    assert [e.idx for e in one.entries] == [0, -2] and one.least == -2 and one.cuts == 1
    rows = spark.createDataFrame([(k % 7, math.ldexp(1 + k / 97, 40 - 9 * (k % 11))) for k in range(300)], "g int, x double")
    for stop in ("float", "exponent", "certified"):
        got = T.sum_adaptive(rows, "x", ["g"], stop=stop, variant="tree", leaves=8, fan_in=2).collect()
        for r in got:
            exact = sum((Fraction(x) for g, x in rows.collect() if g == r.g), Fraction(0))
            assert abs(Fraction(r.value) - exact) <= Fraction(math.ulp(float(exact)))
            assert not r.certified or r.value == float(exact)
            assert (r.truncations == 0) == (r.bound is None) == (r.accepted == "exact")


def test_limbs_and_parts_are_exact(spark):
    rng = random.Random(1)
    v = [struct.unpack("d", struct.pack("Q", rng.getrandbits(64)))[0] for _ in range(3000)]
    v += [s * math.ldexp(1, k) * f for k in range(-1074, 1024, 3) for s in (1, -1) for f in (1, 1 + 2.0**-52)]
    v = [x for x in v if math.isfinite(x) and x]
    d = spark.createDataFrame([(x,) for x in v], "x double")
    rows = d.select("x", D.limbs(F.col("x")).alias("l"), D.float_parts(F.col("x")).alias("p"), D.hexfloat(F.col("x")).cast("double").alias("h"), D.ulp(F.col("x")).alias("u"), D.exponent(F.col("x")).alias("e"), D.next_up(F.col("x")).alias("up")).collect()
    for r in rows:
        assert sum(Fraction(r.l[f"d{i}"]) * Fraction(2) ** (32 * (r.l.top - i)) for i in range(3)) == Fraction(r.x)
        assert all(abs(r.l[f"d{i}"]) < 1 << 32 for i in range(3))
        assert (-1 if r.p.neg else 1) * r.p.mant * Fraction(2) ** r.p.exp == Fraction(r.x) and r.h == r.x
        assert r.u == math.ulp(r.x) and r.e == math.frexp(r.x)[1] - 1 and r.up == math.nextafter(r.x, math.inf)


def test_rounding_modes_and_formats():
    rng = random.Random(3)
    for _ in range(4000):
        n, s = rng.getrandbits(rng.randint(1, 120)) * rng.choice([-1, 1]), rng.randint(-1140, 900)
        exact = Fraction(n) * Fraction(2) ** s
        r = round_integer(n, s)
        assert (float(r) if isinstance(r, str) else math.ldexp(r[0], r[1])) == float(exact)
        low, high = (Fraction(x[0]) * Fraction(2) ** x[1] for x in (round_integer(n, s, mode="down"), round_integer(n, s, mode="up")))
        assert low <= exact <= high and (low == high) == (low == exact)
    for x in np.random.default_rng(1).standard_normal(500) * 1e-39:
        n, d = float(x).as_integer_ratio()
        assert math.ldexp(*round_integer(n << (1100 - d.bit_length() + 1), -1100, SINGLE)) == float(np.float32(x))
    assert round_integer(65520, 0, HALF) == "inf" and round_integer(65519, 0, HALF) == (2047, 5)
    assert round_integer((1 << 113) + 1, 0, QUAD) == (1 << 112, 1)
    assert FloatFormat("own", 3, 4).bias == 7 and DOUBLE.least_bit == -1074


def test_carry_free_addition_is_regular():
    """Exhaustively for small radices: one local carry keeps digits within radix - 1."""
    for radix in (4, 8, 16):
        digits = range(1 - radix, radix)
        for y in digits:
            for z in digits:
                for below in (-2 * radix + 2, 0, 2 * radix - 2):
                    half = below // 2
                    s = K_add(np.array([half, y]), np.array([below - half, z]), radix)
                    assert all(abs(d) < radix for d in s[:-1]) and sum(int(d) * radix**i for i, d in enumerate(s)) == below + (y + z) * radix


def K_add(y, z, radix):
    return X.add_digits(y, z, radix)


def test_many_operands_need_one_carry_up_to_half_the_radix():
    for radix in (4, 8, 16, 32):
        def worst(n):
            # digit after the local carry, with the largest carry from below
            top = 0
            for p in range(-n * (radix - 1), n * (radix - 1) + 1):
                c = (p + radix // 2) // radix
                top = max(top, abs(p - c * radix) + (n * (radix - 1) + radix // 2) // radix)
            return top
        assert worst(radix // 2 - 1) <= radix - 1


def test_signed_binary():
    rng = random.Random(4)
    for _ in range(300):
        a, b = ([rng.choice([-1, 0, 1]) for _ in range(rng.randint(1, 12))] for _ in range(2))
        s = K.signed_binary_add(a, b)
        value = lambda d: sum(x << i for i, x in enumerate(d))
        assert value(s) == value(a) + value(b) and set(s) <= {-1, 0, 1}


@pytest.mark.parametrize("method", K.EXACT)
def test_exact_baselines(method):
    rng = random.Random(6)
    for n in (1, 2, 50, 400):
        v = [rng.choice([-1, 1]) * rng.random() * 2.0 ** rng.randint(-40, 40) for _ in range(n)]
        assert K.METHODS[method](v)[0] == math.fsum(v)


def test_inexact_baselines_and_measures(spark):
    rng = random.Random(8)
    v = [rng.choice([-1, 1]) * rng.random() * 2.0 ** rng.randint(-30, 30) for _ in range(400)]
    c = sum(map(abs, v)) / abs(math.fsum(v))
    for m in ("naive", "pairwise", "huffman", "by_exponent", "compensated", "doubly_compensated", "accurate", "refine"):
        assert abs(K.METHODS[m](v)[0] - math.fsum(v)) <= 400 * 2.0**-52 * c * abs(math.fsum(v))
    assert K.best_tree([1.0, 2.0**-53, 2.0**-53]) == 1 + 2.0**-52
    d = spark.createDataFrame([(1, x) for x in (1.0, 2.0, 3.0)] + [(2, 3.0), (2, -1.0), (3, 1.0), (3, -1.0)], "g int, x double")
    assert {r.g: r.condition for r in C.condition_number(d, "x", ["g"]).collect()} == {1: 1.0, 2: 2.0, 3: None}
    assert {r.g: r.delta for r in C.exponent_range(d, "x", ["g"]).collect()} == {1: 1, 2: 1, 3: 0}
    assert {r.g: r.sigma for r in C.sigma(d, "x", ["g"]).collect()} == {1: 1, 2: 1, 3: 1}
    big = spark.createDataFrame([(x,) for x in v], "x double")
    assert B.sum_accurate_passes(big, "x").first().value == math.fsum(v)
    assert B.sum_parallel_carry(big, "x").first().value == math.fsum(v)
    r = C.ulp_error(big, "x").first()
    assert r.exact == math.fsum(v)
    assert r.ulps == float(abs(Fraction(r.value) - sum(map(Fraction, v))) / Fraction(math.ulp(r.exact)))
    off = C.ulp_error(spark.createDataFrame([(1e16,), (1.0,), (-1e16,)], "x double").coalesce(1), "x").first()
    assert (off.value, off.exact, off.ulps, off.relative) == (0.0, 1.0, 2.0**52, 1.0)
    with pytest.raises(Exception, match="sequential"):
        B.sequential(big, "x", "naive", max_rows=10).collect()


def hard(rng, kind, n):
    v = [math.ldexp(rng.choice([-1, 1]) * rng.random(), rng.randint(-900, 900) if kind == "wide" else rng.randint(-20, 20)) for _ in range(n)]
    if kind in ("zero", "wide"):
        v += [-x for x in v]
        rng.shuffle(v)
    return v + [2.0**-400] if kind == "wide" else [1.0, 2.0**-53, 2.0**-120] if kind == "tie" else v


@pytest.mark.parametrize("method", ["distill", "expansion", "refine", "accurate"])
def test_exact_kernels_round_from_their_own_state(method, monkeypatch):
    """Without any help of a library sum, on hard cases."""
    monkeypatch.setattr(math, "fsum", None)
    monkeypatch.setattr(K, "exact", None)
    rng = random.Random(12)
    for kind in ("plain", "zero", "wide", "tie"):
        for n in (1, 3, 200, 1500):
            v = hard(rng, kind, n)
            assert K.METHODS[method](v)[0] == float(sum(map(Fraction, v))), (kind, n)
    assert K.METHODS[method]([])[0] == 0 and K.METHODS[method]([2.0**-1074] * 3)[0] == 3 * 2.0**-1074
    assert K.METHODS["distill"]([rng.gauss(0, 1) for _ in range(1000)])[1] <= 6
    with pytest.raises(OverflowError):
        K.METHODS["distill" if method == "expansion" else method]([1.7e308, 1.7e308, -1.7e308])


def test_rounds_over_partitions(spark):
    rng = random.Random(13)
    for kind in ("plain", "zero", "wide"):
        v = hard(rng, kind, 700)
        d = spark.createDataFrame([(x,) for x in v], "x double").repartition(5)
        for run in (B.sum_refine, B.sum_accurate_passes):
            assert run(d, "x").first().value == float(sum(map(Fraction, v))), (kind, run)
    assert B.sum_accurate_passes(d, "x").first().passes > 5
    with pytest.raises(RuntimeError, match="not settled"):
        B.sum_accurate_passes(d, "x", max_passes=2)
    assert B.sum_refine(d.limit(0), "x").first().value is None
    ordered = spark.createDataFrame([(2, 1.0), (1, 1e16), (3, -1e16)], "i int, x double").coalesce(1)
    assert B.sequential(ordered, "x", "naive").first().value == 0.0  # in the order of arrival
    assert B.sequential(ordered, "x", "naive", order=["i"]).first().value == 0.0
    assert B.sequential(ordered.orderBy(F.desc("i")).coalesce(1), "x", "naive", order=["x"]).first().value == 0.0


def test_special_values_everywhere(spark):
    nan, inf = math.nan, math.inf
    d = spark.createDataFrame([(1, [1.0, nan]), (2, [inf, 1.0]), (3, None), (4, [inf, -inf]), (5, []), (6, [None, 2.0]), (7, [-0.0, -0.0]), (8, [1e308, 1e308, -1e308]), (9, [None])], "g int, v array<double>")
    got = {r.g: bits(r.s) for r in d.select("g", M.array_exact_sum(F.col("v")).alias("s")).collect()}
    assert got == {g: bits(x) for g, x in {1: nan, 2: inf, 3: None, 4: nan, 5: None, 6: 2.0, 7: -0.0, 8: 1e308, 9: None}.items()}
    rows = spark.createDataFrame([(1, 1.0), (1, nan), (1, 3.0), (2, 1e300), (2, 2e300), (3, 1e-300), (3, 3e-300), (4, inf), (4, 1.0), (5, 2.0), (6, None), (6, None)], "g int, x double")
    var = {r.g: bits(r.value) for r in M.exact_var(rows, "x", ["g"]).collect()}
    assert var == {1: bits(nan), 2: bits(inf), 3: bits(0.0), 4: bits(nan), 5: None, 6: None}
    std = {r.g: r.value for r in M.exact_std(rows.where("g in (2, 3)"), "x", ["g"]).collect()}
    assert std[2] == float(Fraction(1e300) * 0 + abs(Fraction(2e300) - Fraction(1e300))) / 2**0.5 or math.isclose(std[2], 1e300 / 2**0.5, rel_tol=1e-15)
    pairs = spark.createDataFrame([(1, 1e200, 1e200), (1, 1.0, 1.0), *[(2, 3e-200, 3e-120)] * 4, (3, 1e200, 1e200), (3, -1e200, 1e200), (3, 5.0, 1.0), (4, nan, 1.0), (5, inf, 0.0), (6, inf, -1.0), (7, -0.0, 3.0), (8, 5e-324, 0.5), (8, 5e-324, 0.5), (9, None, 1.0)], "g int, x double, y double")
    dot = {r.g: bits(r.value) for r in M.exact_dot(pairs, "x", "y", ["g"]).collect()}
    want = {1: inf, 2: float(4 * Fraction(3e-200) * Fraction(3e-120)), 3: 5.0, 4: nan, 5: nan, 6: -inf, 7: -0.0, 8: 5e-324, 9: None}
    assert dot == {g: bits(x) for g, x in want.items()}
    assert [bits(r.condition) for r in C.condition_number(spark.createDataFrame([(1.0,), (nan,), (3.0,)], "x double"), "x").collect()] == [bits(nan)]


def test_moments_are_correctly_rounded(spark):
    rng = random.Random(14)
    v = [(k % 3, rng.uniform(-5, 5) * 2.0 ** rng.randint(-30, 30), rng.uniform(1, 2)) for k in range(90)] + [(0, None, 1.0), (0, 2.0, None)]
    d = spark.createDataFrame(v, "g int, x double, y double")
    got = {r.g: r for r in M.exact_cov(d, "x", "y", ["g"], "cov").join(M.exact_corr(d, "x", "y", ["g"], "corr"), "g").join(M.exact_weighted_avg(d, "x", "y", ["g"], "avg"), "g").join(M.exact_std(d.where("y is not null"), "x", ["g"], "std"), "g").collect()}
    for g, r in got.items():
        p = [(Fraction(x), Fraction(y)) for h, x, y in v if h == g and x is not None and y is not None]
        n, sx, sy = len(p), sum(x for x, _ in p), sum(y for _, y in p)
        c = n * sum(x * y for x, y in p) - sx * sy
        a, b = n * sum(x * x for x, _ in p) - sx * sx, n * sum(y * y for _, y in p) - sy * sy
        assert r.cov == float(c / (n * (n - 1))) and r.avg == float(sum(x * y for x, y in p) / sy)
        for y, square, sign in ((r.corr, c * c / (a * b), c), (r.std, a / (n * (n - 1)), 1)):
            assert (y < 0) == (sign < 0)
            low, high = ((Fraction(abs(y)) + s * Fraction(math.ulp(y)) / 2) ** 2 for s in (-1, 1))
            assert low <= square <= high


def test_other_forms_of_accumulators(spark):
    v = [0.1, -0.1, 1.5 + 2.0**31, 2.0**-1074, -(2.0**63) + 2.0**11, 0.0, 3.0]
    d = spark.createDataFrame([(x,) for x in v], "x double").withColumn("a", A.acc_of(F.col("x")))
    for r in d.select("x", A.acc_balanced(F.col("a")).alias("b"), A.acc_decimal(F.col("a")).alias("t"), A.acc_truncate(F.col("a"), 1).alias("one")).collect():
        assert all(-(1 << 31) <= x < 1 << 31 for x in r.b.digits) and (not r.b.digits or (r.b.digits[0] and r.b.digits[-1]))
        assert sum(Fraction(x) * Fraction(2) ** (32 * (r.b.low + i)) for i, x in enumerate(r.b.digits)) == Fraction(r.x)
        assert Fraction(r.t) == Fraction(r.x) and "e" not in r.t.lower()
        assert sum(x != 0 for x in r.one.digits) == (r.x != 0)
    whole = spark.createDataFrame([(0.75,), (-3.0,), (2.0**50,), (0.0,), (None,)], "x double").select(D.to_fixed(F.col("x"), -2).alias("k"))
    assert [None if r.k is None else int(r.k) for r in whole.collect()] == [3, -12, 2**52, 0, None]
    with pytest.raises(Exception, match="not a multiple"):
        spark.createDataFrame([(0.1,)], "x double").select(D.to_fixed(F.col("x"), -2)).collect()


def test_accumulator_algebra(spark):
    rng = random.Random(9)
    pairs = [(math.ldexp(rng.uniform(-1, 1), rng.randint(-60, 60)), math.ldexp(rng.uniform(-1, 1), rng.randint(-60, 60))) for _ in range(200)] + [(1.5, -1.5), (0.0, 2.0)]
    d = spark.createDataFrame(pairs, "a double, b double").select("a", "b", A.acc_of(F.col("a")).alias("x"), A.acc_of(F.col("b")).alias("y")).cache()
    out = d.select("a", "b", A.acc_round(A.acc_add(F.col("x"), F.col("y"))).alias("s"), A.acc_round(A.acc_sub(F.col("x"), F.col("y"))).alias("d"), A.acc_compare(F.col("x"), F.col("y")).alias("c"), A.acc_round(A.acc_shift(F.col("x"), 37)).alias("t"), A.acc_round(A.acc_scale(F.col("x"), 3)).alias("k"), A.acc_round(A.from_map(A.sparse_add(A.acc_map(F.col("x")), A.acc_map(F.col("y"))))).alias("m"), A.acc_round(A.acc_from_json(A.acc_to_json(F.col("x")))).alias("j"), A.acc_round(F.col("x"), "single").alias("f"), A.acc_sign(A.acc_neg(F.col("x"))).alias("n"))
    for r in out.collect():
        assert r.s == r.a + r.b == r.m and r.d == r.a - r.b and r.c == (r.a > r.b) - (r.a < r.b)
        assert r.t == r.a * 2**37 and r.k == r.a * 3 and r.j == r.a and r.f == float(np.float32(r.a)) and r.n == (r.a < 0) - (r.a > 0)


def test_averages_variances_and_dots(spark):
    rng = random.Random(10)
    v = [(rng.randint(0, 3), rng.uniform(-5, 5), rng.uniform(-5, 5)) for _ in range(300)]
    d = spark.createDataFrame(v, "g int, x double, y double")
    by = {g: [(x, y) for h, x, y in v if h == g] for g in range(4)}
    fr = lambda xs: sum(map(Fraction, xs))
    for g, m in M.exact_avg(d, "x", ["g"]).collect():
        assert m == float(fr(x for x, _ in by[g]) / len(by[g]))
    for g, m in M.exact_var(d, "x", ["g"]).collect():
        n, s = len(by[g]), fr(x for x, _ in by[g])
        assert m == float((n * sum(Fraction(x) ** 2 for x, _ in by[g]) - s * s) / (n * (n - 1)))
    for g, m in M.exact_dot(d, "x", "y", ["g"]).collect():
        assert m == float(sum(Fraction(x) * Fraction(y) for x, y in by[g]))


def test_set_equality_and_counts(spark):
    a = spark.createDataFrame([(i * i % 97 - 20,) for i in range(200)], "v long")
    assert X.multiset_equal(a, "v", a.orderBy(F.rand(1)), "v").first().equal
    assert not X.multiset_equal(a, "v", a.limit(199), "v").first().equal
    assert not X.multiset_equal(a, "v", a.distinct(), "v").first().equal
    def equal(a, b, **how):
        frames = [spark.createDataFrame([(v,) for v in x], "v long") for x in (a, b)]
        return X.multiset_equal(frames[0], "v", frames[1], "v", **how).first().equal

    big = [10**15, -(10**15), (1 << 63) - 1, -(1 << 63), -1, 0]
    assert equal(big, big[::-1]) and not equal(big, big[:-1]) and not equal(big, [*big[:-1], 1])
    # copies never carry into a neighbour's bits, below zero neither
    for a in (-5, -4, -3, -1, 0, 3, 4):
        for bits_ in (40, 36, 33):
            assert not equal([a], [a - 1] * 256, bits=bits_) and not equal([a] * 2, [a]) and equal([a] * 300, [a] * 300, bits=bits_)
    assert not equal([a + 1], [a] * 16, bits=8) and equal([None, 1], [1, None]) and not equal([None, 1], [1])
    with pytest.raises(Exception, match="more bits"):
        equal([1] * 8, [1] * 8, bits=5)
    assert sum(X.count_as_floats(10**13 + 7)) == 10**13 + 7 and len(X.count_as_floats(10**13 + 7)) <= 4


def test_plan_has_no_python_and_prunes(spark):
    d = spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet")
    text = C.plan_text(M.exact_sum(d, "l_tax", ["l_returnflag"]))
    assert "Python" not in text and "Pandas" not in text and "Arrow" not in text
    assert "ReadSchema: struct<l_tax:double,l_returnflag:string>" in text
