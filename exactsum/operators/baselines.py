"""The methods that the exact sums are compared with, each as one row per key: value and a counter."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from typing import Any

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.decompose import exponent
from ..sources.io import checkpointed
from . import kernels
from .mapreduce import as_column, packed_sums

#: Counter that a sequential method returns beside its value.
COUNTERS = {
    "naive": "none", "pairwise": "levels", "huffman": "none", "by_exponent": "none", "compensated": "correction", "distill": "sweeps",
    "superacc_carry": "longest_chain", "small_acc": "normalisations", "expansion": "longest", "refine": "passes", "accurate": "passes",
    "fixed": "bits", "bucketed": "budget_left", "doubly_compensated": "correction", "reference": "none",
}


def sequential(df: DataFrame, col: str | Column, method: str, keys: Sequence[str] = (), order: Sequence[str] = (), max_rows: int | None = None, block: int = 1 << 20) -> DataFrame:
    """A one-core method on each key's values, in the order of `order` or else in that of arrival (partition, row).

    These methods are sequential by nature, so one task takes all values of a key, but as blocks of
    `block` (a power of two): Spark sorts them, and only huffman holds more than a block.  A method with
    an exact value gets its values as they come to the task unless `order` is given; then its counter
    may follow the shuffle.  With more than a block the counters of distill, refine and accurate are
    the most of any block, each of which is brought to the end.  A group over `max_rows` raises, if
    that is given.  Nulls are skipped.
    """
    x = F.col("x")
    lead = {"by_exponent": -F.coalesce(exponent(x) + 1, F.lit(0)), "doubly_compensated": -F.abs(x)}
    places = [F.col(o) for o in order] or ([] if method in kernels.EXACT else [F.monotonically_increasing_id()])
    by = [f"place{k}__" for k in range(len(places))]
    rows = df.select(*keys, *[c.alias(b) for c, b in zip(places, by, strict=True)], as_column(col).cast("double").alias("x")).where("x is not null")
    if method in lead:
        rows, by = rows.withColumn("lead__", lead[method]), ["lead__", *by]
    schema = ", ".join([*[f"`{k}` {rows.schema[k].dataType.simpleString()}" for k in keys], "value double, counter double"])

    def run(batches: Iterator[pd.DataFrame]) -> tuple[int, float, float]:
        n = 0

        def arrays():
            nonlocal n
            for b in batches:
                n += len(b)
                if max_rows is not None and n > max_rows:
                    raise ValueError(f"{method} is sequential and was given {n} rows or more; the limit is {max_rows}")
                yield b["x"].to_numpy(float)

        value, counter = kernels.run_blocks(method, kernels.dealt_blocks(arrays(), block))
        return n, value, float(counter)

    def group(key: tuple[Any, ...], batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        yield pd.DataFrame([(*key, *run(batches)[1:])])

    def whole(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        n, value, counter = run(batches)
        if n:
            yield pd.DataFrame({"value": [value], "counter": [counter]})

    rows = rows.repartition(*keys) if keys else rows.repartition(1)
    rows = rows.sortWithinPartitions(*keys, *by) if by else rows
    return rows.groupBy(*keys).applyInPandas(group, schema) if keys else rows.select("x").mapInPandas(whole, schema)


def sum_distill(df: DataFrame, col: str | Column, block: int = 1 << 20) -> DataFrame:
    """Error-free distillation in two levels: (value, counter), no row without values.

    Each partition is distilled in blocks to a list without overlap; only these lists, of some tens of
    numbers, go to one task, which distils them in the same way.  The counter is the most sweeps of any block.
    """

    def lists(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        n = 0

        def arrays():
            nonlocal n
            for b in batches:
                n += len(b)
                yield b["x"].to_numpy(float)

        held, sweeps = kernels.distilled(kernels.dealt_blocks(arrays(), block))
        if n:
            yield pd.DataFrame({"x": held if len(held) else [0.0], "sweeps": sweeps})

    def whole(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        most = []

        def arrays():
            for b in batches:
                most.extend(b["sweeps"].tolist())
                yield b["x"].to_numpy(float)

        value, sweeps = kernels.distill_blocks(kernels.dealt_blocks(arrays(), block))
        if most:
            yield pd.DataFrame({"value": [value], "counter": [float(max(sweeps, *most))]})

    rows = df.select(as_column(col).cast("double").alias("x")).where("x is not null")
    return rows.mapInPandas(lists, "x double, sweeps long").repartition(1).mapInPandas(whole, "value double, counter double")


def sum_naive(df: DataFrame, col: str | Column, keys: Sequence[str] = (), name: str = "value") -> DataFrame:
    """Spark's own sum: its bits follow the partitioning."""
    return df.groupBy(*keys).agg(F.sum(as_column(col).cast("double")).alias(name))


def sum_decimal_cast(df: DataFrame, col: str | Column, keys: Sequence[str] = (), name: str = "value") -> DataFrame:
    """Through the shortest decimal text of each double: reproducible, but not the doubles' exact sum."""
    return df.groupBy(*keys).agg(F.sum(as_column(col).cast("decimal(30,10)")).cast("double").alias(name))


def sum_by_exponent(df: DataFrame, col: str | Column, keys: Sequence[str] = ()) -> DataFrame:
    return sequential(df, col, "by_exponent", keys)


def sum_accurate_passes(df: DataFrame, col: str | Column, max_passes: int = 256) -> DataFrame:
    """Extraction by falling thresholds, one aggregate per pass over the whole table: (value, passes).

    Each pass takes the part of every value above a power of two that makes the parts' sum exact in
    any order, so the aggregate is Spark's plain one.  Passes end when the rest is zero or cannot
    change the rounded value; a double's bits run out long before `max_passes`, beyond which it is an error.
    """
    import math

    x = as_column(col).cast("double")
    rows = df.select(x.alias("x")).where("x is not null")
    n, most = rows.agg(F.count("x"), F.max(F.abs("x"))).first()
    sigmas, parts, passes, value = [], [], 0, None if not n else 0.0
    while n and most:
        if passes == max_passes:
            raise RuntimeError(f"not settled after {max_passes} passes")
        m = math.frexp(most)[1] + n.bit_length() + 1
        if m > 1022:
            raise OverflowError("values too large to extract from")
        sigmas.append(math.ldexp(1.0, m))
        # what earlier passes took is taken again row by row: a loop over the thresholds, not a growing plan
        given = F.array(*[F.lit(s) for s in sigmas[:-1]]) if passes else F.array().cast("array<double>")
        left = F.aggregate(given, F.col("x"), lambda a, s: a - ((a + s) - s))
        taken = rows.select(left.alias("x")).select("x", ((F.col("x") + F.lit(sigmas[-1])) - F.lit(sigmas[-1])).alias("q"))
        s, most = taken.agg(F.sum("q"), F.max(F.abs(F.col("x") - F.col("q")))).first()
        parts = kernels.grown(parts, s)
        passes += 1
        value = kernels.rounded_parts(parts)
        if most and kernels.certain(parts, math.nextafter(most * n, math.inf)) is not None:
            break
    return df.sparkSession.createDataFrame([(value, passes)], "value double, passes int")


def sum_refine(df: DataFrame, col: str | Column) -> DataFrame:
    """Iterative refinement over partitions: (value, passes).

    In each round a partition adds its values by pairs, sends the rounded sum and keeps the errors
    of its additions as its values for the next round.  The sums sent are added without loss, and
    rounds go on until nothing is left or what is left cannot change the rounded value.
    """
    held = df.select(as_column(col).cast("double").alias("x")).where("x is not null").withColumn("sent", F.lit(False))
    n, parts, passes = held.count(), [], 0

    def sweep(batches):
        import numpy as np

        mine = [b.loc[~b["sent"], "x"].to_numpy(float) for b in batches]
        s, errors = kernels.two_sum_tree(np.concatenate([*mine, np.zeros(0)]))
        yield pd.DataFrame({"x": [s, *errors.tolist()], "sent": [True, *[False] * len(errors)]})

    while n:
        passes += 1
        held = checkpointed(held.mapInPandas(sweep, "x double, sent boolean"))
        for r in held.where("sent").toLocalIterator():  # one number for each partition
            parts = kernels.grown(parts, r["x"])
        left, rest = held.where("not sent").agg(F.count("x"), F.sum(F.abs("x"))).first()
        if not left or kernels.certain(parts, rest * (1 + left * 2.0**-50)) is not None:
            break
    return df.sparkSession.createDataFrame([(kernels.rounded_parts(parts) if n else None, passes)], "value double, passes int")


def sum_parallel_carry(df: DataFrame, col: str | Column, keys: Sequence[str] = (), blocks: int = 16) -> DataFrame:
    """Block accumulators merged with full carry propagation each time: (keys, value, longest carry chain)."""
    from ..functions.formats import LOWEST, W
    from . import accumulator as A

    d = df.withColumn("block__", F.pmod(F.xxhash64(as_column(col).cast("double")), F.lit(blocks)))
    packed = packed_sums(d, [*keys, "block__"], {"v": as_column(col)}).select(*keys, "block__", A.hex_text(F.col("acc")).alias("t"))
    schema = ", ".join([*[f"`{k}` {df.schema[k].dataType.simpleString()}" for k in keys], "value double, longest int"])

    def merge(key, f: pd.DataFrame) -> pd.DataFrame:
        total, longest = 0, 0
        for t in f.sort_values("block__")["t"]:
            i, s = A.parsed(t)
            new = total + (i << (s - LOWEST * W))
            changed, chain = abs(total ^ new) >> W, 0
            while changed:
                chain += 1
                changed >>= W
            total, longest = new, max(longest, chain)
        return pd.DataFrame([(*key, kernels.rounded(total), longest)])

    if keys:
        return packed.groupBy(*keys).applyInPandas(merge, schema)
    return packed.withColumn("all__", F.lit(1)).groupBy("all__").applyInPandas(lambda key, f: merge((), f), schema)
