"""Numpy block accumulators and the sequential summation methods that the engine is compared with."""

from __future__ import annotations

import heapq
import itertools
import math
from collections.abc import Iterable, Iterator, Sequence

import numpy as np

from ..functions.formats import LOWEST, W, round_integer

SPAN = 72


def split(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """top and digits of finite doubles, as in functions.decompose.limbs."""
    m, e = np.frexp(x)
    top = np.floor_divide(e, W)
    m = np.ldexp(m, e - W * top)
    d0 = np.trunc(m)
    m = np.ldexp(m - d0, W)
    d1 = np.trunc(m)
    return top, d0.astype(np.int64), d1.astype(np.int64), np.trunc(np.ldexp(m - d1, W)).astype(np.int64)


class BlockSum:
    """Dense accumulator of int64 limbs for up to 2^31 values between carries."""

    def __init__(self):
        self.limbs = np.zeros(SPAN, np.int64)
        self.used = np.zeros(SPAN, bool)
        self.room = 1 << 30
        self.n = self.nan = self.pinf = self.ninf = self.nonneg = 0

    def add(self, x: np.ndarray) -> None:
        self.n += len(x)
        finite = np.isfinite(x)
        if not finite.all():
            self.nan += int(np.isnan(x).sum())
            self.pinf += int((x == np.inf).sum())
            self.ninf += int((x == -np.inf).sum())
        self.nonneg += len(x) - int(((x == 0) & np.signbit(x)).sum())
        x = x[finite & (x != 0)]
        if len(x) > self.room:
            self.carry()
        self.room -= len(x)
        top, *digits = split(x)
        for i, d in enumerate(digits):
            at = top - i - LOWEST
            # both halves are added exactly in doubles: fewer than 2^30 values of 16 bits at a time
            high, low = np.bincount(at, d >> 16, SPAN), np.bincount(at, d & 0xFFFF, SPAN)
            self.limbs += (high.astype(np.int64) << 16) + low.astype(np.int64)
            self.used |= np.bincount(at, d != 0, SPAN) > 0

    def carry(self) -> None:
        for k in range(SPAN - 1):
            c = int(self.limbs[k]) >> W
            self.limbs[k] -= c << W
            self.limbs[k + 1] += c
        self.room = 1 << 30

    def total(self) -> int:
        """The sum in units of R^LOWEST."""
        return sum(int(d) << (W * k) for k, d in enumerate(self.limbs.tolist()))

    def value(self) -> float | None:
        """The rounded sum, with SQL's null for nothing and IEEE's special values."""
        if not self.n:
            return None
        if self.nan or (self.pinf and self.ninf):
            return math.nan
        if self.pinf or self.ninf:
            return math.inf if self.pinf else -math.inf
        return rounded(self.total()) if self.nonneg else -0.0

    def saved(self) -> bytes:
        self.carry()
        return np.concatenate([self.limbs, [self.n, self.nan, self.pinf, self.ninf, self.nonneg], self.used]).astype("<i8").tobytes()

    @classmethod
    def restored(cls, held: bytes | None) -> BlockSum:
        s = cls()
        if held is not None:
            a = np.frombuffer(held, "<i8")
            s.limbs, s.used = a[:SPAN].copy(), a[SPAN + 5 :].astype(bool)
            s.n, s.nan, s.pinf, s.ninf, s.nonneg = a[SPAN : SPAN + 5].tolist()
        return s

    def rows(self):
        yield (None, None, None, None, self.n, self.nan, self.pinf, self.ninf, self.nonneg)
        for k in np.flatnonzero(self.used | (self.limbs != 0)).tolist():
            yield (k + LOWEST, int(self.limbs[k]), 0, 0, 0, 0, 0, 0, 0)


def rounded(total: int, scale: int = LOWEST * W) -> float:
    r = round_integer(total, scale)
    return float(r) if isinstance(r, str) else math.ldexp(float(r[0]), r[1])


def exact(xs: Sequence[float]) -> int:
    """Exact sum of finite doubles in units of R^LOWEST."""
    total = 0
    for x in xs:
        n, d = float(x).as_integer_ratio()
        total += (n << (-LOWEST * W)) // d
    return total


def two_sum(a: float, b: float) -> tuple[float, float]:
    s = a + b
    v = s - a
    return s, (a - (s - v)) + (b - v)


def naive(xs):
    s = 0.0
    for x in xs:
        s += x
    return s, 0


def pairwise(xs):
    v, levels = np.asarray(xs, float), 0
    while len(v) > 1:
        if len(v) % 2:
            v = np.append(v, 0.0)
        v = v[::2] + v[1::2]
        levels += 1
    return (float(v[0]) if len(v) else 0.0), levels


def huffman(xs):
    """Adds the two least magnitudes, again and again."""
    heap = [(abs(x), x) for x in xs]
    heapq.heapify(heap)
    while len(heap) > 1:
        s = heapq.heappop(heap)[1] + heapq.heappop(heap)[1]
        heapq.heappush(heap, (abs(s), s))
    return (heap[0][1] if heap else 0.0), 0


def by_exponent(xs):
    order = np.argsort(-np.frexp(np.asarray(xs, float))[1], kind="stable")
    s = np.longdouble(0)
    for x in np.asarray(xs, float)[order]:
        s += np.longdouble(x)
    return float(s), 0


def compensated(xs):
    s = c = 0.0
    for x in xs:
        s, e = two_sum(s, x)
        c += e
    return s + c, c


def doubly_compensated(xs):
    s = c = 0.0
    for x in sorted(xs, key=abs, reverse=True):
        y = c + x
        u = x - (y - c)
        t = y + s
        v = y - (t - s)
        z = u + v
        s, c = t + z, z - ((t + z) - t)
    return s, c


def grown(parts: list[float], x: float) -> list[float]:
    """A non-overlapping list of rising magnitudes, and x: their exact sum as such a list."""
    out = []
    for p in parts:
        x, e = two_sum(x, p)
        if e:
            out.append(e)
    if x - x != 0:
        raise OverflowError("a partial sum is beyond the largest double")
    return [*out, x] if x else out


def rounded_parts(parts: Sequence[float]) -> float:
    """The nearest double of a non-overlapping list of rising magnitudes.

    Adding from the large end stays exact until one addition isn't; what is left below can only
    decide a tie, by its sign.
    """
    total, k = 0.0, len(parts)
    while k:
        k -= 1
        total, error = two_sum(total, parts[k])
        if error:
            if k and (error > 0) == (parts[k - 1] > 0):
                twice = 2 * error
                away = total + twice
                if away - total == twice:
                    return away
            break
    return total


def certain(parts: list[float], rest: float) -> float | None:
    """The rounded sum of the parts, if adding or taking away up to `rest` doesn't change it."""
    y = rounded_parts(parts)
    return y if rounded_parts(grown(parts, rest)) == y == rounded_parts(grown(parts, -rest)) else None


def magnitude(v) -> float:
    """No less than the sum of magnitudes."""
    return math.nextafter(float(np.abs(np.asarray(v, float)).sum()) * (1 + len(v) * 2.0**-51), math.inf)


def distill(xs):
    """Error-free distillation: sweeps of two-sums until what is left cannot change the rounded total.

    A sweep that changes nothing leaves a non-overlapping list, which is rounded as it stands.
    """
    v, sweeps = [x for x in xs if x], 0
    while len(v) > 1:
        sweeps += 1
        left, total = [], 0.0
        for x in v:
            total, e = two_sum(total, x)
            if e:
                left.append(e)
        if total - total != 0:
            raise OverflowError("a partial sum is beyond the largest double")
        new = [*left, total] if total else left
        if not left or new == v:
            return rounded_parts(new), sweeps
        if total and (y := certain([total], magnitude(left))) is not None:
            return y, sweeps
        v = new
    return (v[0] if v else 0.0), sweeps


def superacc_carry(xs):
    """One value at a time into a non-redundant accumulator, carries propagated at once."""
    limbs, carries, longest = [0] * SPAN, 0, 0
    for x in xs:
        top, *digits = (int(v[0]) for v in split(np.array([x])))
        for i, d in enumerate(digits):
            k, chain = top - i - LOWEST, 0
            limbs[k] += d
            while not 0 <= limbs[k] < 1 << W and k < SPAN - 1:
                c = limbs[k] >> W
                limbs[k] -= c << W
                k += 1
                limbs[k] += c
                chain += 1
            carries += chain
            longest = max(longest, chain)
    return rounded(sum(d << (W * k) for k, d in enumerate(limbs))), longest


def small_acc(xs):
    s = BlockSum()
    times = 0
    for low in range(0, len(xs), 1 << 16):
        s.add(np.asarray(xs[low : low + (1 << 16)], float))
        s.carry()
        times += 1
    return rounded(s.total()), times


def expansion(xs):
    """A growing list of floats without overlap."""
    parts, longest = [], 0
    for x in xs:
        parts = grown(parts, x)
        longest = max(longest, len(parts))
    return rounded_parts(parts), longest


def two_sum_tree(v: np.ndarray) -> tuple[float, np.ndarray]:
    """The sum by pairs and all errors of its additions; nothing is lost."""
    errors = []
    while len(v) > 1:
        if len(v) % 2:
            v = np.append(v, 0.0)
        a, b = v[::2], v[1::2]
        s = a + b
        t = s - a
        e = (a - (s - t)) + (b - t)
        errors.append(e[e != 0])
        v = s
    total = float(v[0]) if len(v) else 0.0
    if not math.isfinite(total):
        raise OverflowError("a partial sum is beyond the largest double")
    return total, np.concatenate([*errors, np.zeros(0)])


def refine(xs, blocks: int = 8):
    """Rounds over blocks: each sends its block's rounded sum and keeps the errors for the next round."""
    held, passes, parts = [np.asarray(xs[b::blocks], float) for b in range(blocks)], 0, []
    while True:
        passes += 1
        for b in range(blocks):
            s, held[b] = two_sum_tree(held[b])
            parts = grown(parts, s)
        rest = sum(map(magnitude, held)) if any(map(len, held)) else 0.0
        if not rest:
            return rounded_parts(parts), passes
        if (y := certain(parts, rest * (1 + 2.0**-40))) is not None:
            return y, passes


def accurate(xs):
    """Extraction by falling powers of two; the number of passes follows the condition number."""
    v, passes, parts = np.asarray(xs, float), 0, []
    while len(v):
        passes += 1
        m = int(np.frexp(np.abs(v).max())[1]) + len(v).bit_length() + 1
        if m > 1022:
            raise OverflowError("values too large to extract from")
        sigma = math.ldexp(1.0, m)
        q = (v + sigma) - sigma
        parts = grown(parts, float(q.sum()))  # exact: the sum's bits lie between those of sigma and of its last place
        v = v - q
        v = v[v != 0]
        if len(v) and (y := certain(parts, magnitude(v))) is not None:
            return y, passes
    return rounded_parts(parts), passes


def fixed(xs):
    """One wide integer."""
    total = exact(xs)
    return rounded(total), total.bit_length()


def bucketed(xs):
    """Buckets by exponent; each takes a limited number of carry-free additions."""
    budget = 1 << 10
    sums, room, flushed = {}, {}, 0
    spill = 0
    for x in xs:
        m, e = math.frexp(x)
        sums[e] = sums.get(e, 0) + int(math.ldexp(m, 53))
        room[e] = room.get(e, budget) - 1
        if room[e] == 0:
            spill += (sums.pop(e) << (e - 53 - LOWEST * W)) if e - 53 >= LOWEST * W else 0
            room[e] = budget
            flushed += 1
    total = spill + sum(s << (e - 53 - LOWEST * W) for e, s in sums.items())
    return rounded(total), budget * 64 - flushed


def reference(xs):
    return math.fsum(xs), 0


def best_tree(xs: Sequence[float]) -> float:
    """The least error of any binary tree of float additions, by trying all; for up to seven values."""
    true = exact(xs)
    seen: set[tuple] = set()
    best = None

    def walk(items: tuple):
        nonlocal best
        if items in seen:
            return
        seen.add(items)
        if len(items) == 1:
            err = abs(exact(items) - true)
            if best is None or err < best[0]:
                best = (err, items[0])
            return
        for i in range(len(items)):
            for j in range(i):
                rest = items[:j] + items[j + 1 : i] + items[i + 1 :]
                walk(tuple(sorted((*rest, items[i] + items[j]))))

    walk(tuple(sorted(xs)))
    return best[1]


def signed_binary_add(a: Sequence[int], b: Sequence[int]) -> list[int]:
    """Carry-free sum of signed-binary digit lists (-1, 0, 1; low end first): a carry looks one place down only."""
    n = max(len(a), len(b)) + 1
    p = [(a[i] if i < len(a) else 0) + (b[i] if i < len(b) else 0) for i in range(n)]
    carry, rest = [0] * (n + 1), [0] * (n + 1)
    for i in range(n):
        below = p[i - 1] if i else 0
        if p[i] == 2 or (p[i] == 1 and below >= 0):
            carry[i + 1], rest[i] = 1, p[i] - 2
        elif p[i] == -2 or (p[i] == -1 and below < 0):
            carry[i + 1], rest[i] = -1, p[i] + 2
        else:
            rest[i] = p[i]
    return [rest[i] + carry[i] for i in range(n + 1)]


METHODS = {
    "naive": naive, "pairwise": pairwise, "huffman": huffman, "by_exponent": by_exponent, "compensated": compensated,
    "distill": distill, "superacc_carry": superacc_carry, "small_acc": small_acc, "expansion": expansion, "refine": refine,
    "accurate": accurate, "fixed": fixed, "bucketed": bucketed, "doubly_compensated": doubly_compensated, "reference": reference,
}

EXACT = ("distill", "superacc_carry", "small_acc", "expansion", "refine", "accurate", "fixed", "bucketed", "reference")


# the same methods on blocks of values, for any number of them in bounded memory (huffman: eight bytes a value)
def running(start, v: np.ndarray) -> np.ndarray:
    """start, start + v[0], ... one rounded addition after the other."""
    return np.add.accumulate(np.concatenate([np.array([start], v.dtype), v]))


def errors_of(sums: np.ndarray, v: np.ndarray) -> np.ndarray:
    """What the additions of running(start, v) = sums rounded off."""
    a, s = sums[:-1], sums[1:]
    t = s - a
    return (a - (s - t)) + (v - t)


def naive_blocks(blocks):
    s = 0.0
    for v in blocks:
        s = running(s, v)[-1]
    return float(s), 0


def pairwise_blocks(blocks):
    """All blocks but the last have one length, a power of two, so each is a whole subtree."""
    tops, levels = [], 0
    for v in blocks:
        top, own = pairwise(v)
        tops.append(top)
        levels = max(levels, own)
    top, above = pairwise(tops)
    return top, levels + above


def huffman_blocks(blocks):
    """Values of one sign are added in whole runs: no sum is below the first, so those up to it are paired as they stand."""
    v = np.concatenate([*blocks, np.zeros(0)])
    if not len(v) or not np.isfinite(v).all() or v.min() < 0 < v.max():
        return huffman(v.tolist())
    sign, v = -1.0 if v.min() < 0 else 1.0, np.sort(np.abs(v))
    while len(v) > 1:
        k = int(np.searchsorted(v, v[0] + v[1], "right")) // 2 * 2
        sums, rest = v[:k:2] + v[1:k:2], v[k:]
        near = int(np.searchsorted(rest, sums[-1], "right"))
        v = np.concatenate([np.sort(np.concatenate([sums, rest[:near]]), kind="stable"), rest[near:]])
    return sign * float(v[0]), 0


def by_exponent_blocks(blocks):
    """The values come by falling exponent."""
    s = np.longdouble(0)
    for v in blocks:
        s = running(s, v.astype(np.longdouble))[-1]
    return float(s), 0


def compensated_blocks(blocks):
    s = c = 0.0
    for v in blocks:
        sums = running(s, v)
        s, c = sums[-1], running(c, errors_of(sums, v))[-1]
    return float(s + c), float(c)


def doubly_compensated_blocks(blocks):
    """The values come by falling magnitude."""
    s = c = 0.0
    for v in blocks:
        for x in v.tolist():
            y = c + x
            u = x - (y - c)
            t = y + s
            z = u + (y - (t - s))
            s = t + z
            c = z - (s - t)
    return s, c


def distilled(blocks) -> tuple[np.ndarray, int]:
    """A list without overlap that has the blocks' sum, and the most sweeps of any block.

    Each block is swept together with what is left of those before.
    """
    held, most = np.zeros(0), 0
    for v in blocks:
        v, sweeps = np.concatenate([held, v[v != 0]]), 0
        while len(v) > 1:
            sweeps += 1
            sums = running(0.0, v)
            if not np.isfinite(sums).all():
                raise OverflowError("a partial sum is beyond the largest double")
            e = errors_of(sums, v)
            new = np.concatenate([e[e != 0], sums[-1:][sums[-1:] != 0]])
            if np.array_equal(new, v):
                break
            v = new
        held, most = v, max(most, sweeps)
    return held, most


def distill_blocks(blocks):
    held, most = distilled(blocks)
    return rounded_parts(held.tolist()), most


def superacc_carry_blocks(blocks):
    limbs, longest, top_limb = [0] * SPAN, 0, SPAN - 1
    for v in blocks:
        top, *digits = (a.tolist() for a in split(v))
        for t, *three in zip(top, *digits, strict=True):
            for k, d in zip((t - LOWEST, t - 1 - LOWEST, t - 2 - LOWEST), three, strict=True):
                if not d:
                    continue
                chain = 0
                limbs[k] += d
                while not 0 <= limbs[k] < 1 << W and k < top_limb:
                    c = limbs[k] >> W
                    limbs[k] -= c << W
                    k += 1
                    limbs[k] += c
                    chain += 1
                longest = max(longest, chain)
    return rounded(sum(d << (W * k) for k, d in enumerate(limbs))), longest


def small_acc_blocks(blocks):
    s, times = BlockSum(), 0
    for v in blocks:
        for low in range(0, len(v), 1 << 16):
            s.add(v[low : low + (1 << 16)])
            s.carry()
            times += 1
    return rounded(s.total()), times


def expansion_blocks(blocks):
    parts, longest = [], 0
    for v in blocks:
        for x in v.tolist():
            k = 0
            for p in parts:  # grown, in place
                s = x + p
                t = s - x
                e = (x - (s - t)) + (p - t)
                if e:
                    parts[k] = e
                    k += 1
                x = s
            if x - x != 0:
                raise OverflowError("a partial sum is beyond the largest double")
            parts[k:] = [x] if x else []
            if k >= longest:
                longest = max(longest, len(parts))
    return rounded_parts(parts), longest


def refine_blocks(blocks):
    """Each block's rounds go on until it has no errors left."""
    parts, most = [], 0
    for v in blocks:
        passes = 0
        while len(v):
            s, v = two_sum_tree(v)
            parts = grown(parts, s)
            passes += 1
        most = max(most, passes)
    return rounded_parts(parts), most


def accurate_blocks(blocks):
    """Each block is extracted with its own thresholds, to the end."""
    parts, most = [], 0
    for v in blocks:
        passes, v = 0, v[v != 0]
        while len(v):
            passes += 1
            m = int(np.frexp(np.abs(v).max())[1]) + len(v).bit_length() + 1
            if m > 1022:
                raise OverflowError("values too large to extract from")
            sigma = math.ldexp(1.0, m)
            q = (v + sigma) - sigma
            parts = grown(parts, float(q.sum()))
            v = v - q
            v = v[v != 0]
        most = max(most, passes)
    return rounded_parts(parts), most


def fixed_blocks(blocks):
    total = sum(exact(v.tolist()) for v in blocks)
    return rounded(total), total.bit_length()


def bucketed_blocks(blocks):
    return bucketed(itertools.chain.from_iterable(v.tolist() for v in blocks))


def reference_blocks(blocks):
    return math.fsum(itertools.chain.from_iterable(v.tolist() for v in blocks)), 0


BLOCKS = {
    "naive": naive_blocks, "pairwise": pairwise_blocks, "huffman": huffman_blocks, "by_exponent": by_exponent_blocks,
    "compensated": compensated_blocks, "distill": distill_blocks, "superacc_carry": superacc_carry_blocks, "small_acc": small_acc_blocks,
    "expansion": expansion_blocks, "refine": refine_blocks, "accurate": accurate_blocks, "fixed": fixed_blocks, "bucketed": bucketed_blocks,
    "doubly_compensated": doubly_compensated_blocks, "reference": reference_blocks,
}


def dealt_blocks(arrays: Iterable[np.ndarray], size: int) -> Iterator[np.ndarray]:
    """The values again in arrays of `size`, the last one shorter."""
    held, n = [], 0
    for a in arrays:
        held.append(a)
        n += len(a)
        if n >= size:
            v = np.concatenate(held)
            for low in range(0, n - n % size, size):
                yield v[low : low + size]
            held, n = [v[n - n % size :]], n % size
    if n:
        yield np.concatenate(held)


def run_blocks(method: str, blocks: Iterator[np.ndarray]) -> tuple[float, float]:
    """A method on all blocks; a single one is taken as a list."""
    first, second = next(blocks, np.zeros(0)), next(blocks, None)
    return METHODS[method](first.tolist()) if second is None else BLOCKS[method](itertools.chain([first, second], blocks))
