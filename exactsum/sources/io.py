"""Reading and writing without losing a bit, and accumulator tables that grow by new files only."""

from __future__ import annotations

import uuid
from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from ..functions.decompose import hexfloat
from ..operators import accumulator as A
from ..operators.mapreduce import as_column, packed_sums, with_values


def shared_folder(spark: SparkSession) -> str:
    """The session's folder for checkpoints, which all executors reach; local masters may go without one."""
    if not spark.sparkContext.getCheckpointDir():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors can reach")
        spark.sparkContext.setCheckpointDir(named or f"/tmp/checkpoints/{uuid.uuid4().hex}")
    return spark.sparkContext.getCheckpointDir()


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut the lineage with a reliable checkpoint in the session's shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def save(df: DataFrame, path: str, fmt: str = "parquet", hexfloats: bool = True, partition_by: Sequence[str] = ()) -> None:
    """Text formats write doubles as hexadecimal literals, which every reader here restores exactly."""
    if fmt in ("csv", "json", "text") and hexfloats:
        df = df.select(*[hexfloat(F.col(f.name)).alias(f.name) if isinstance(f.dataType, DoubleType) else F.col(f.name) for f in df.schema])
    if fmt == "text":
        df = df.select(F.concat_ws("\t", *[F.col(c).cast("string") for c in df.columns]).alias("value"))
    w = df.write.mode("overwrite").format(fmt)
    w = w.option("header", "true") if fmt == "csv" else w
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def read(spark: SparkSession, path: str, schema: str, fmt: str = "parquet") -> DataFrame:
    if fmt in ("parquet", "orc"):
        return spark.read.format(fmt).load(path)
    want = spark.createDataFrame([], schema).schema
    if fmt == "text":
        parts = F.split("value", "\t", -1)
        return spark.read.text(path).select(*[parts[i].cast(f.dataType).alias(f.name) for i, f in enumerate(want)])
    text = ", ".join(f"`{f.name}` string" for f in want)
    d = spark.read.format(fmt).schema(text).option("header", "true").load(path)
    return d.select(*[F.col(f.name).cast(f.dataType).alias(f.name) for f in want])


def write_acc(df: DataFrame, col, keys: Sequence[str], path: str, mode: str = "append") -> None:
    """Packed accumulators of a batch; appending later batches never touches what is there."""
    packed_sums(df, keys, {"v": as_column(col)}).drop("sigma").write.mode(mode).parquet(path)


def merge_acc(accs: DataFrame, keys: Sequence[str], name: str = "value") -> DataFrame:
    """Exact totals of any union of accumulator rows."""
    zero = F.lit(0).cast("bigint")
    flat = accs.select(*keys, "m", F.explode_outer(A.dense_of(F.col("acc"))).alias("e")).select(*keys, "m", "e.*")
    sums = flat.where("top is not null").groupBy(*keys, "m", "top").agg(*[F.sum(s).alias(s) for s in A.SUMS]).withColumns({f: zero for f in A.FLAGS})
    flags = accs.groupBy(*keys, "m").agg(*[F.sum(f).alias(f) for f in A.FLAGS])
    none = {c: F.lit(None).cast(t) for c, t in (("top", "int"), ("s0", "bigint"), ("s1", "bigint"), ("s2", "bigint"))}
    both = sums.unionByName(flags.withColumns(none))
    return with_values(A.pack(both, keys)).select(*keys, F.col("value").alias(name), "acc")
