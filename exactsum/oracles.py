"""SQL texts for DuckDB that take exact sums apart without this engine: digits from the bits of a double,
carries by recursion, one rounding at the end."""

from __future__ import annotations

#: Digits of radix 2^32 by (keys, index), added without carries.
DIGITS = """
WITH b AS (SELECT {keys} CAST(CAST(x AS DOUBLE)::BIT AS BIGINT) AS b FROM ({rows}) WHERE x <> 0),
p AS (SELECT {keys} CASE WHEN b < 0 THEN -1 ELSE 1 END AS s, ((b >> 52) & 2047)::INTEGER AS e, b & 4503599627370495 AS f FROM b),
m AS (SELECT {keys} s, (f + CASE WHEN e > 0 THEN 4503599627370496 ELSE 0 END)::HUGEINT AS m, greatest(e, 1) - 1075 AS q FROM p),
i AS (SELECT {keys} s, floor(q / 32.0)::INTEGER AS i0, m * (1::HUGEINT << (q - 32 * floor(q / 32.0)::INTEGER)) AS big FROM m),
d AS (SELECT {keys} unnest([i0, i0 + 1, i0 + 2]) AS idx, unnest([s * (big % 4294967296), s * ((big // 4294967296) % 4294967296), s * (big // 18446744073709551616)]) AS digit FROM i)
SELECT {keys} idx, CAST(sum(digit) AS BIGINT) AS digit FROM d GROUP BY {keys} idx HAVING sum(digit) <> 0
"""

#: Digits that any value has at an index, zero sums included.
TOUCHED = DIGITS.replace("SELECT {keys} idx, CAST(sum(digit) AS BIGINT) AS digit FROM d GROUP BY {keys} idx HAVING sum(digit) <> 0", "SELECT DISTINCT {keys} idx FROM d WHERE digit <> 0")


def floored(v: str) -> str:
    """v / 2^32, towards minus infinity."""
    return f"CASE WHEN {v} < 0 THEN -((-({v}) + 4294967295) // 4294967296) ELSE ({v}) // 4294967296 END"


def canonical(rows: str, tag: str = "c") -> str:
    """CTEs ending in {tag}(sgn, idx, norm): sign and unique digits of the exact sum of column x of `rows`.

    Both signs are walked from the low end; the one without a last borrow is the magnitude.
    """
    return f"""{tag}_d AS MATERIALIZED ({DIGITS.format(keys="", rows=rows)}),
{tag}_span AS (SELECT min(idx) AS low, max(idx) + 2 AS high FROM {tag}_d),
{tag}_walk(sgn, idx, norm, carry) AS (
  SELECT s.sgn, low - 1, 0::HUGEINT, 0::HUGEINT FROM {tag}_span, (VALUES (1), (-1)) s(sgn) WHERE low IS NOT NULL
  UNION ALL
  SELECT sgn, idx, v - 4294967296 * ({floored('v')}), {floored('v')} FROM (
    SELECT w.sgn, w.idx + 1 AS idx, w.carry + w.sgn * coalesce((SELECT digit FROM {tag}_d d WHERE d.idx = w.idx + 1), 0)::HUGEINT AS v
    FROM {tag}_walk w, {tag}_span WHERE w.idx < high)
),
{tag} AS MATERIALIZED (
  SELECT sgn, idx, norm FROM {tag}_walk WHERE norm <> 0
  AND sgn = (SELECT max(w.sgn) FROM {tag}_walk w, {tag}_span WHERE w.idx = high AND w.carry >= 0)
)"""


def leading(tag: str) -> str:
    """Scalar pieces of the magnitude: sign, top index, its first three digits as one number, and whether more follows."""
    return f"""{tag}_t AS (
  SELECT any_value(sgn) AS sgn, max(idx) AS top,
         sum(CASE WHEN idx > t - 3 THEN norm * (4294967296::HUGEINT ** 0)::HUGEINT * (CASE idx - t WHEN 0 THEN 18446744073709551616::HUGEINT WHEN -1 THEN 4294967296::HUGEINT ELSE 1::HUGEINT END) ELSE 0 END)::HUGEINT AS v,
         count(CASE WHEN idx <= t - 3 THEN 1 END) > 0 AS more
  FROM {tag}, (SELECT max(idx) AS t FROM {tag})
)"""


def scaled(number: str, power: str) -> str:
    """A double times a power of two that may be out of range by itself."""
    return f"({number}) * pow(2, floor(({power}) / 2.0)) * pow(2, ({power}) - floor(({power}) / 2.0))"


def exact_any(rows: str, name: str = "value") -> str:
    """The correctly rounded sum of column x of `rows`, for any normal doubles."""
    value = scaled("sgn * CAST(CAST(v * 2 + CASE WHEN more THEN 1 ELSE 0 END AS VARCHAR) AS DOUBLE)", "32 * (top - 2) - 1")
    return f"WITH RECURSIVE {canonical(rows)}, {leading('c')} SELECT coalesce({value}, 0.0)::DOUBLE AS {name} FROM c_t"


def exact_mean(rows: str, name: str = "mean") -> str:
    """The correctly rounded quotient of the exact sum and the number of rows (below 2^28)."""
    whole = "((v * 1048576) // n)"
    sticky = f"CASE WHEN more OR (v * 1048576) % n <> 0 THEN 1 ELSE 0 END"
    value = scaled(f"sgn * CAST(CAST({whole} * 2 + {sticky} AS VARCHAR) AS DOUBLE)", "32 * (top - 2) - 21")
    return f"WITH RECURSIVE {canonical(rows)}, {leading('c')} SELECT {value} AS {name} FROM c_t, (SELECT count(x) AS n FROM ({rows}))"


def quotient(number: str, over: str, power: int, bits: int = 40) -> str:
    """number * 2^-power / over as a double, rounded once, for whole numbers that leave `bits` bits of room."""
    big = f"(abs({number}) * {1 << bits}::HUGEINT)"
    whole = f"({big} // ({over}) * 2 + CASE WHEN {big} % ({over}) <> 0 THEN 1 ELSE 0 END)"
    return f"(CASE WHEN ({number}) < 0 THEN -1 ELSE 1 END * CAST(CAST({whole} AS VARCHAR) AS DOUBLE) / pow(2, {power + bits + 1}))"
