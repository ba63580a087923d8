"""Workloads of the experiments on the given tables, reproducible to the bit.

All come from integers of `lineitem` by fixed integer arithmetic, so any engine with exact powers
of two can rebuild them.  Kinds: positive (condition number 1), mixed (signs by key parity), centred
(the exact mean is subtracted), zero (values and their negations, in another order), near_zero (zero and one tiny value).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.decompose import scalb
from ..operators.mapreduce import exact_avg

KINDS = ("positive", "mixed", "centred", "zero", "near_zero")
DELTAS = (10, 100, 500, 1000, 1500, 2000)


def base(spark: SparkSession, sf_dir: str, delta: int, replicate: int = 1) -> DataFrame:
    """(k, s, x): key, sign by parity, and a positive double whose exponent spans `delta` binades."""
    d = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")
    if replicate > 1:
        d = d.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(replicate - 1)))).withColumn("l_orderkey", F.col("l_orderkey") + F.col("copy") * 600_011).drop("copy")
    o, p, s, n = (F.col(c).cast("bigint") for c in ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"))
    mant = (o * 1103515245 + p * 12345 + s * 2654435761 + n * 97) % (1 << 52) + (1 << 52)
    expo = (p * 7919 + o * 31 + n) % delta - delta // 2
    x = scalb(mant.cast("double"), expo - 52)
    return d.select((o * 8 + n).alias("k"), ((o + n + p) % 2).alias("s"), x.alias("x"))


def make_workload(spark: SparkSession, kind: str, sf_dir: str, delta: int = 200, replicate: int = 1) -> DataFrame:
    """(k BIGINT, x DOUBLE)"""
    b = base(spark, sf_dir, delta, replicate)
    if kind == "positive":
        return b.select("k", "x")
    if kind == "mixed":
        return b.select("k", F.when(F.col("s") == 0, F.col("x")).otherwise(-F.col("x")).alias("x"))
    if kind == "centred":
        mean = exact_avg(b, "x", name="mean")
        return b.crossJoin(F.broadcast(mean)).select("k", (F.col("x") - F.col("mean")).alias("x"))
    if kind in ("zero", "near_zero"):
        # the negations come in an order of their own, not next to their values
        other = F.xxhash64(F.lit("negated"), "k", "x")
        signed = F.array(F.struct(F.xxhash64("k", "x").alias("at"), F.col("x").alias("x")), F.struct(other.alias("at"), (-F.col("x")).alias("x")))
        flat = b.select("k", F.inline(signed))
        both = flat.repartitionByRange(F.col("at")).sortWithinPartitions("at").select("k", "x")
        if kind == "zero":
            return both
        tiny = spark.range(1).select(F.lit(-1).cast("bigint").alias("k"), F.lit(2.0 ** max(-1022, -delta // 2)).alias("x"))
        return both.unionByName(tiny)
    raise ValueError(f"unknown workload {kind!r}; one of {KINDS}")


NATURAL = {
    "price": ("lineitem", "l_extendedprice"),
    "tax": ("lineitem", "l_tax"),
    "discount": ("lineitem", "l_discount"),
    "quantity": ("lineitem", "l_quantity"),
    "orders": ("orders", "o_totalprice"),
    "acctbal": ("customer", "c_acctbal"),
    "supplier": ("supplier", "s_acctbal"),
    "retail": ("part", "p_retailprice"),
    "events": ("events", "value"),
}


def make_natural(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    table, col = NATURAL[name]
    return spark.read.parquet(f"{sf_dir}/{table}.parquet").select(F.col(col).alias("x"))


def register_source(spark: SparkSession) -> None:
    """Python data source 'exact_workload': options n, delta, kind, seed, partitions; rows (k, x) by ranges of k."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Range(InputPartition):
        def __init__(self, low: int, high: int):
            self.low, self.high = low, high

    class Reader(DataSourceReader):
        def __init__(self, o):
            self.n, self.delta = int(o.get("n", "1000")), int(o.get("delta", "200"))
            self.kind, self.seed, self.parts = o.get("kind", "positive"), int(o.get("seed", "42")), int(o.get("partitions", "8"))
            if self.kind not in ("positive", "mixed", "zero"):
                raise ValueError(f"unknown kind {self.kind!r}; positive, mixed or zero")

        def partitions(self):
            step = -(-self.n // self.parts)
            return [Range(a, min(self.n, a + step)) for a in range(0, self.n, step)]

        def read(self, part):
            """Arrow batches made by numpy; the second half of a zero-sum set negates the first in reverse."""
            import numpy as np
            import pyarrow as pa

            for low in range(part.low, part.high, 1 << 16):
                k = np.arange(low, min(part.high, low + (1 << 16)))
                own = np.minimum(k, 2 * (self.n // 2) - 1 - k) if self.kind == "zero" else k
                h = own.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(self.seed)
                h = (h ^ (h >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
                mant = ((h & np.uint64((1 << 52) - 1)) | np.uint64(1 << 52)).astype(float)
                x = np.ldexp(mant, (h >> np.uint64(52)).astype(np.int64) % self.delta - self.delta // 2 - 52)
                if self.kind == "mixed":
                    x = np.where(h & np.uint64(1), -x, x)
                elif self.kind == "zero":
                    x = np.where(own < 0, 0.0, np.where(k >= self.n // 2, -x, x))  # an odd last one is zero
                yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(x)], names=["k", "x"])

    class Source(DataSource):
        @classmethod
        def name(cls):
            return "exact_workload"

        def schema(self):
            return "k bigint, x double"

        def reader(self, schema):
            return Reader(self.options)

    spark.dataSource.register(Source)
