"""The engine's functions for SQL text."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..operators import kernels


def register_sql(spark: SparkSession) -> None:
    """exact_sum(x): grouped aggregate; limbs_of(x): table function; exact_hex(x): lossless text.

    The aggregate sees all rows of a group at once, so every row is shuffled: convenient on small
    data, never for scale.  `exact_sql` writes the scalable form.
    """

    @F.pandas_udf("double")
    def exact_sum(x: pd.Series) -> float:
        s = kernels.BlockSum()
        s.add(x.dropna().to_numpy(float))
        if s.n == 0:
            return None
        if s.nan or (s.pinf and s.ninf):
            return math.nan
        if s.pinf or s.ninf:
            return math.inf if s.pinf else -math.inf
        return -0.0 if s.nonneg == 0 else kernels.rounded(s.total())

    @F.udtf(returnType="idx int, digit bigint")
    class LimbsOf:
        def eval(self, x: float):
            if x is not None and math.isfinite(x) and x:
                import numpy as np

                top, *digits = (int(v[0]) for v in kernels.split(np.array([x])))
                for i, d in enumerate(digits):
                    if d:
                        yield top - i, d

    @F.udf("string")
    def exact_hex(x):
        return None if x is None else float(x).hex()

    spark.udf.register("exact_sum", exact_sum)
    spark.udf.register("exact_hex", exact_hex)
    spark.udtf.register("limbs_of", LimbsOf)


def exact_sql(view: str, col: str, keys: tuple[str, ...] = ()) -> str:
    """Plain SQL for the limb sums of a column: one partial and one final aggregation, no Python."""
    k = "".join(f"{c}, " for c in keys)
    return f"""
WITH t AS (SELECT {k}{col} AS x, CAST(floor((floor(log2(abs({col}))) + 1) / 32) AS INT) AS top FROM {view} WHERE {col} <> 0 AND abs({col}) < double('Infinity')),
m AS (SELECT {k}top, x * pow(2D, -16 * top) * pow(2D, -16 * top) AS m FROM t),
a AS (SELECT {k}top, CAST(m AS BIGINT) AS d0, (m - CAST(m AS BIGINT)) * 4294967296D AS r FROM m),
d AS (SELECT {k}top, d0, CAST(r AS BIGINT) AS d1, CAST((r - CAST(r AS BIGINT)) * 4294967296D AS BIGINT) AS d2 FROM a)
SELECT {k}top, sum(d0) AS s0, sum(d1) AS s1, sum(d2) AS s2 FROM d GROUP BY {k}top"""
