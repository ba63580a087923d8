"""Mixing sources to target weights under a time-varying curriculum, in DataFrame functions only.

Training runs over time 0..1.  Each source has a weight schedule, a piecewise linear function of
time; its integral is the source's weight in the mix, and the running integral, scaled to the
source's target, is the demand for the source's words up to a time.  The mix goes through each
source in a keyed order, again from the start where its target exceeds its size, and a document's
training position is the time at which cumulative demand reaches the document's middle word.
Sorting by position by ranges gives the training order.

Running sums of a source are taken in two levels: over hash buckets of a source, and within one
bucket.  No task holds a source, however large its share of the rows.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import n_words

Knots = Sequence[tuple[float, float]]
#: Rows that share a bucket of the running sums.
BUCKET_ROWS = 4096


def tilted(weight: int) -> Knots:
    """Weight 1 fades, 2 stays, 3 grows; each integrates to its weight."""
    tilt = {1: -0.5, 2: 0.0, 3: 0.5}[weight]
    return [(0.0, weight * (1 - tilt)), (1.0, weight * (1 + tilt))]


def cyclic_schedules(weights: Sequence[int] = (1, 2, 3)) -> Callable[[Column], Column]:
    """Schedules by the rank (from 0) of the source: the weights in turn, again and again."""
    made = [F.array(*[F.struct(F.lit(float(t)).alias("t"), F.lit(float(w)).alias("w")) for t, w in tilted(x)]) for x in weights]
    return lambda rank: F.get(F.array(*made), F.pmod(rank, F.lit(len(made))).cast("int"))


def source_targets(sized: DataFrame, schedule: Callable[[Column], Column], cap: int = 3) -> DataFrame:
    """One row per source: source, source_size, weight, target, segments of its scaled schedule.

    Targets share the sum of all sizes by weight; a target stops at cap times its source's size, and
    what it leaves is shared by the others in turn.  With sources in the order of size per weight,
    the first k are capped for the least k at which the rest's common level is below the next
    source's own, so one pass over one row per source settles all rounds of resharing: past that
    source the level only falls, so it is the greatest one that fits.
    """
    s = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    s = s.withColumn("knots", schedule(F.row_number().over(W.orderBy(F.col("source").asc_nulls_last())) - 1))
    following = F.slice("knots", 2, F.size("knots") - 1)
    segments = F.zip_with(F.slice("knots", 1, F.size("knots") - 1), following, lambda a, b: F.struct(a["t"].alias("t"), (b["t"] - a["t"]).alias("dt"), a["w"].alias("w0"), b["w"].alias("w1")))
    s = s.withColumn("parts", segments)
    s = s.withColumn("weight", F.aggregate("parts", F.lit(0.0), lambda a, x: a + x["dt"] * (x["w0"] + x["w1"]) / 2))
    order = W.orderBy(F.col("source_size") / F.col("weight"), F.col("source").asc_nulls_last())
    everything = W.partitionBy()
    capped = F.coalesce(F.sum("source_size").over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)) * cap
    level = (F.sum("source_size").over(everything) - capped) / F.sum("weight").over(order.rowsBetween(0, W.unboundedFollowing))
    s = s.withColumn("level", level).withColumn("own", F.col("source_size") * cap / F.col("weight"))
    s = s.withColumn("level", F.max(F.when(F.col("level") <= F.col("own"), F.col("level"))).over(everything))
    return s.withColumn("target", F.least((F.col("source_size") * cap).cast("double"), F.coalesce(F.col("level") * F.col("weight"), (F.col("source_size") * cap).cast("double"))))


def running(sized: DataFrame, buckets: int) -> DataFrame:
    """Adds `before`: words of the same source earlier in its keyed order."""
    digits = max(1, math.ceil(math.log(buckets, 16)))
    d = sized.withColumn("bucket__", F.substring("key__", 1, digits))
    totals = d.groupBy("source", "bucket__").agg(F.sum("weighted__").alias("words"))
    earlier = W.partitionBy("source").orderBy("bucket__").rowsBetween(W.unboundedPreceding, -1)
    totals = totals.select(F.col("source").alias("source_"), F.col("bucket__").alias("bucket_"), F.coalesce(F.sum("words").over(earlier), F.lit(0)).alias("base"))
    inside = W.partitionBy("source", "bucket__").orderBy("key__", "doc_id", "size").rowsBetween(W.unboundedPreceding, -1)
    d = d.withColumn("before", F.coalesce(F.sum("weighted__").over(inside), F.lit(0)))
    d = d.join(totals, F.col("source").eqNullSafe(F.col("source_")) & (F.col("bucket__") == F.col("bucket_")))
    return d.withColumn("before", F.col("before") + F.col("base")).drop("bucket__", "source_", "bucket_", "base")


def position(share: Column, parts: Column, weight: Column) -> Column:
    """The time at which the schedule's running integral reaches `share` of its whole."""
    start = F.struct(F.lit(0.0).alias("c"), F.lit(None).cast("double").alias("t"))

    def step(a, x):
        area = x["dt"] * (x["w0"] + x["w1"]) / 2
        c = F.greatest(F.lit(0.0), share * weight - a["c"])
        # root of w0 y + (w1 - w0) y^2 / 2 = c / dt, in the form that doesn't cancel
        per = c / x["dt"]
        y = 2 * per / (x["w0"] + F.sqrt(F.greatest(F.lit(0.0), x["w0"] * x["w0"] + 2 * (x["w1"] - x["w0"]) * per)))
        here = a["t"].isNull() & (c <= area) & (area > 0)
        return F.struct((a["c"] + area).alias("c"), F.when(here, x["t"] + F.least(F.lit(1.0), F.coalesce(y, F.lit(0.0))) * x["dt"]).otherwise(a["t"]).alias("t"))

    return F.coalesce(F.aggregate(parts, start, step, lambda a: a["t"]), F.lit(1.0))


def plan(docs: DataFrame, schedule: Callable[[Column], Column] | None = None, cap: int = 3) -> DataFrame:
    """(doc_id, source, size, rows, source_size, target, copies, taken, positions) for each distinct (doc_id, source, size).

    A source is taken whole as often as its target allows; of the rest, the documents that come first
    in the keyed order (md5 of doc_id) fill it, the last one if at least half of it fits.  `positions`
    has one training position for each copy.  A null text has size 0, a null source is a source, and
    repeated rows are planned together and get the same copies.
    """
    sized = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), n_words(F.col("text").cast("string")).alias("size"))
    sized = sized.groupBy("doc_id", "source", "size").agg(F.count("*").alias("rows"))
    buckets = max(1, math.ceil(docs.count() / BUCKET_ROWS))
    sized = sized.withColumns({"key__": F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), "weighted__": F.col("size") * F.col("rows")})
    targets = source_targets(sized.select("source", F.col("weighted__").alias("size")), schedule or cyclic_schedules(), cap)
    t = targets.select(F.col("source").alias("source_"), "source_size", "target", "parts", "weight")
    d = running(sized, buckets).join(t, F.col("source").eqNullSafe(F.col("source_")))
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0))
    d = d.withColumn("whole__", F.least(F.lit(cap), whole).cast("int"))
    rest = F.col("target") - F.col("whole__") * F.col("source_size")
    more = (F.col("whole__") < cap) & (F.col("before") + F.col("weighted__") / 2 < rest)
    d = d.withColumn("copies", F.col("whole__") + more.cast("int"))
    middle = F.col("before") + F.col("weighted__") / 2
    share = lambda j: F.least(F.lit(1.0), (j * F.col("source_size") + middle) / F.col("target"))
    times = F.transform(F.sequence(F.lit(0), F.col("copies") - 1), lambda j: position(share(j), F.col("parts"), F.col("weight")))
    d = d.withColumn("positions", F.when(F.col("copies") > 0, times).otherwise(F.array().cast("array<double>")))
    return d.withColumn("taken", F.col("size") * F.col("copies")).select("doc_id", "source", "size", "rows", "source_size", "target", "copies", "taken", "positions")


def mixed(docs: DataFrame, schedule: Callable[[Column], Column] | None = None, cap: int = 3) -> DataFrame:
    """The rows of docs, each as often as the mix takes it, in training order, with their columns."""
    p = plan(docs, schedule, cap).where("copies > 0")
    p = p.select(F.struct("doc_id", "source", "size").alias("key__"), F.col("positions").alias("positions__"))
    own = F.struct(F.col("doc_id").cast("long"), F.col("source").cast("string"), n_words(F.col("text").cast("string")))
    d = docs.withColumn("own__", own).join(p, F.col("own__").eqNullSafe(F.col("key__"))).drop("own__", "key__")
    d = d.withColumn("position__", F.explode("positions__"))
    return d.repartitionByRange(F.col("position__")).sortWithinPartitions("position__", "doc_id").select(*docs.columns)
