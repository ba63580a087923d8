"""Exact sums of streams: dense limb sums as state, so late rows, retries and repartitioning never change a bit."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from functools import reduce

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.decompose import limbs
from ..operators import accumulator as A
from ..operators import kernels
from ..operators.mapreduce import as_column, dense_entries, dense_sums


def stream_exact_sum(stream: DataFrame, col: str | Column, ts: str, keys: Sequence[str] = (), window: str = "1 day", slide: str | None = None, session_gap: str | None = None, watermark: str = "1 day", limb_range: tuple[int, int] | None = None, name: str = "value") -> DataFrame:
    """(start, keys, n, value) per tumbling, sliding or session window.

    One stateful aggregation holds a BIGINT for each limb of `limb_range` (all of a double's by
    default); rounding is a stateless projection behind it.  A value with a digit outside a narrower
    range fails the query, it is never left out.  NTZ times are taken in the session's zone.
    """
    d = stream.withColumn("ts__", F.col(ts).cast("timestamp")).withWatermark("ts__", watermark)
    d = d.withColumn("x", as_column(col).cast("double")).withColumn("l__", limbs(F.col("x")))
    d = d.select("ts__", *keys, "x", "l__.top", "l__.d0", "l__.d1", "l__.d2")
    w = F.session_window("ts__", session_gap) if session_gap else F.window("ts__", window, slide) if slide else F.window("ts__", window)
    low, high = limb_range or (-36, 32)
    digit = lambda i: (F.col("top") - i, F.col(f"d{i}"))
    outside = reduce(lambda a, b: a | b, [((k < low) | (k > high)) & (v != 0) for k, v in map(digit, range(3))])
    g = d.groupBy(w.alias("w__"), *keys).agg(*dense_sums(low, high), *A.flag_sums(), F.sum(F.when(outside, 1).otherwise(0)).alias("outside"))
    acc = A.canonical(dense_entries(low, high))
    fails = F.raise_error(F.lit(f"values outside the limbs {low} to {high} of this stream")).cast(A.PACKED)
    return g.withColumn("acc", F.when(F.col("outside") > 0, fails).otherwise(acc)).select(F.col("w__.start").alias("start"), *keys, "n", A.finished(F.col("acc"), A.acc_round(F.col("acc"))).alias(name))


def run_once(stream: DataFrame, spark: SparkSession, name: str, mode: str = "complete", checkpoint: str | None = None) -> DataFrame:
    """All that is there now into a memory table."""
    w = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    q = (w.option("checkpointLocation", checkpoint) if checkpoint else w).start()
    q.awaitTermination()
    return spark.table(name)


def run_to_files(stream: DataFrame, spark: SparkSession, name: str) -> DataFrame:
    """All rows that are there now as Parquet files in the session's shared folder: none goes through the driver's memory."""
    from ..sources.io import shared_folder

    path = f"{shared_folder(spark)}/streams/{name}"
    w = stream.writeStream.format("parquet").queryName(name).outputMode("append").trigger(availableNow=True)
    w.option("checkpointLocation", f"{path}/checkpoint").start(f"{path}/rows").awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


def accumulate(stream: DataFrame, col: str | Column, keys: Sequence[str], path: str, checkpoint: str) -> None:
    """foreachBatch: each micro-batch appends its packed accumulators to a table."""
    from ..sources.io import write_acc

    q = stream.writeStream.foreachBatch(lambda df, _: write_acc(df, col, keys, path)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()


def stream_deduplicated(stream: DataFrame, ids: Sequence[str], ts: str, watermark: str = "1 day") -> DataFrame:
    """Rows met again within the watermark are dropped, so redelivered events count once."""
    d = stream.withColumn("ts__", F.col(ts).cast("timestamp")).withWatermark("ts__", watermark)
    return d.dropDuplicatesWithinWatermark([*ids]).drop("ts__")


def stream_interval_join(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, seconds: int, watermark: str = "1 day") -> DataFrame:
    """Pairs of two streams of one key with right_time in (left_time - seconds, left_time]; right columns get the prefix r_.

    Both sides have watermarks, so state older than the interval is dropped.
    """
    a = left.withColumn("t__", F.col(left_time).cast("timestamp")).withWatermark("t__", watermark)
    b = right.select(*[F.col(c).alias(f"r_{c}") for c in right.columns]).withColumn("r_t__", F.col(f"r_{right_time}").cast("timestamp")).withWatermark("r_t__", watermark)
    gap = F.expr(f"r_t__ <= t__ and r_t__ > t__ - interval {seconds} seconds")
    return a.join(b, (F.col(key) == F.col(f"r_{key}")) & gap).drop("t__", "r_t__")


def stream_running_sum(stream: DataFrame, col: str | Column, key: str, name: str = "value") -> DataFrame:
    """(key, n, value) after each batch with rows of the key: custom state, one exact accumulator for each key.

    The state is the digits of a dense accumulator, about 600 bytes a key; updates may come in any order.
    """
    rows = stream.select(F.col(key).alias("key"), as_column(col).cast("double").alias("x"))

    def update(own: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        held = kernels.BlockSum.restored(state.get[0] if state.exists else None)
        for b in batches:
            held.add(b["x"].dropna().to_numpy(float))
        state.update((held.saved(),))
        yield pd.DataFrame({"key": [own[0]], "n": [held.n], name: [held.value()]})

    kind = rows.schema["key"].dataType.simpleString()
    return rows.groupBy("key").applyInPandasWithState(update, f"key {kind}, n bigint, {name} double", "held binary", "update", "NoTimeout")
