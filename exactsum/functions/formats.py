"""Number formats and the radix."""

from __future__ import annotations

from dataclasses import dataclass

#: Bits of a limb: accumulators have radix R = 2^W and limb i weighs R^i.
W = 32
R = 1 << W
#: Limbs that doubles can touch (2^-1074 .. 2^1024), with room for carries.
LOWEST, HIGHEST = -36, 34
#: Digits stay below R, so this many can be added in a BIGINT.
LAZY_ADDS = 1 << (63 - W)


@dataclass(frozen=True)
class FloatFormat:
    """`mantissa` stored bits (without the leading one) and `exponent` bits."""

    name: str
    mantissa: int
    exponent: int

    @property
    def bias(self) -> int:
        return (1 << (self.exponent - 1)) - 1

    @property
    def precision(self) -> int:
        return self.mantissa + 1

    @property
    def least_bit(self) -> int:
        """Exponent of the smallest positive number."""
        return 1 - self.bias - self.mantissa

    @property
    def overflow(self) -> int:
        """All magnitudes from 2^overflow on are infinite."""
        return self.bias + 1


HALF, SINGLE, DOUBLE, QUAD = FloatFormat("half", 10, 5), FloatFormat("single", 23, 8), FloatFormat("double", 52, 11), FloatFormat("quad", 112, 15)
FORMATS = {f.name: f for f in (HALF, SINGLE, DOUBLE, QUAD)}


def round_integer(total: int, scale: int, fmt: FloatFormat = DOUBLE, mode: str = "nearest_even") -> tuple[int, int] | str:
    """total * 2^scale in a format, as (integer, exponent), or 'inf' or '-inf'.

    Modes: nearest_even, down, up, toward_zero; faithful is nearest_even, which is faithful.
    """
    if total == 0:
        return 0, 0
    sign, size = (-1, -total) if total < 0 else (1, total)
    drop = max(size.bit_length() - fmt.precision, fmt.least_bit - scale, 0)
    kept, lost = size >> drop, size & ((1 << drop) - 1)
    half = 1 << (drop - 1) if drop else 0
    away = {"nearest_even": drop > 0 and (lost > half or (lost == half and kept & 1)), "down": sign < 0 and lost > 0, "up": sign > 0 and lost > 0, "toward_zero": False}
    kept += int(away["nearest_even" if mode == "faithful" else mode])
    exponent = scale + drop
    if kept and kept.bit_length() + exponent > fmt.overflow:
        if mode in ("nearest_even", "faithful") or away[mode] or (mode == "up") == (sign > 0) and mode != "toward_zero":
            return "inf" if sign > 0 else "-inf"
        return sign * ((1 << fmt.precision) - 1), fmt.overflow - fmt.precision
    return sign * kept, exponent
