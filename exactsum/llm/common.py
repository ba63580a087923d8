"""Helpers shared by the training-data operators."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: One word: a longest run of anything but space, tab, line feed, vertical tab, form feed, return.
WORD = r"[^\x20\x09-\x0D]+"


def words(text: Column) -> Column:
    """All words of the whole text, in order; a null text has none."""
    return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(WORD), F.lit(0))


def n_words(text: Column) -> Column:
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD)).cast("long")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share; local masters, as in tests, may go without."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors can reach")
    return "/tmp/checkpoints"


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut the lineage with a reliable checkpoint in the shared folder of the session."""
    sc = df.sparkSession.sparkContext
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(f"{shared_folder(df.sparkSession)}/{uuid.uuid4().hex}")
    return df.checkpoint(eager=True)


#: Partitions that one shuffle is cut into at most, where their number follows the data.
MOST_PARTITIONS = 50_000
#: Stands for a null doc_id, before all others.
NO_ID = -(1 << 63)


def numbered(docs: DataFrame) -> tuple[DataFrame, DataFrame | None, bool]:
    """Rows (node, doc_id, text), the doc_id of each node where that isn't the node itself, and whether rows repeat.

    Rows of equal doc_id and text are one node, others are different ones, and nodes are in the order
    of doc_id, nulls first.  Where no doc_id has two texts, the doc_id is the node.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    h = F.xxhash64(F.coalesce("text", F.lit("")))
    seen = rows.groupBy("doc_id").agg(F.min(h).alias("a"), F.max(h).alias("b"), F.count("*").alias("n"))
    clash, most = seen.agg(F.coalesce(F.bool_or(F.col("a") != F.col("b")), F.lit(False)), F.coalesce(F.max("n"), F.lit(0))).first()
    if not clash:
        return rows.select(F.coalesce("doc_id", F.lit(NO_ID)).alias("node"), "doc_id", "text"), None, most > 1
    key = F.md5(F.coalesce("text", F.lit("")).cast("binary"))
    texts = rows.select("doc_id", key.alias("key_")).distinct().repartitionByRange("doc_id", "key_").sortWithinPartitions("doc_id", "key_")
    names = checkpointed(texts.select(F.col("doc_id").alias("id_"), "key_", F.monotonically_increasing_id().alias("node")))
    named = rows.withColumn("key__", key).join(names, F.col("doc_id").eqNullSafe(F.col("id_")) & (F.col("key__") == F.col("key_")))
    return named.select("node", "doc_id", "text"), names.select("node", F.col("id_").alias("doc_id")), most > 1


def hub_join(facts: DataFrame, sums: DataFrame, key: str, count: str, total: int) -> DataFrame:
    """facts with the row of `sums` that has their key, where sums.count says how many of `total` facts have it.

    Keys of over a thousandth of all facts are at most a thousand, whatever the size, so they are
    broadcast and their facts stay where they are; all others are shuffled.
    """
    limit = max(32, total // 1000)
    hot = F.broadcast(sums.where(F.col(count) > limit))
    rest = facts.join(hot.select(key), key, "left_anti").join(sums.where(F.col(count) <= limit), key)
    return facts.join(hot, key).unionByName(rest)


#: Bits of the filter of likely(), 8 MB whatever the data; and of each of its rows, a fixed value of Spark's bitmaps.
FILTER_BITS, BITMAP_BITS = 1 << 26, 32_768


def likely(rows: DataFrame, key: str, wanted: DataFrame, name: str) -> DataFrame:
    """rows without most of those whose key isn't among wanted.name, so that fewer are shuffled to a join with them.

    The hashes of wanted keys are set in a bitmap of fixed size, which is broadcast; keys that share
    a hash with a wanted one stay too, so more of the rest stay the fuller the bitmap is.
    """
    place = lambda c: F.pmod(F.xxhash64(F.col(c)), F.lit(FILTER_BITS))
    bits = wanted.select(place(name).alias("h")).groupBy(F.floor(F.col("h") / BITMAP_BITS).alias("word__"))
    bits = bits.agg(F.bitmap_construct_agg(F.col("h") % BITMAP_BITS).alias("bits__"))
    bit = place(key) % BITMAP_BITS
    byte = F.conv(F.hex(F.substring(F.col("bits__"), F.floor(bit / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    held = rows.withColumn("word__", F.floor(place(key) / BITMAP_BITS)).join(F.broadcast(bits), "word__")
    mask = F.call_function("shiftleft", F.lit(1), (bit % 8).cast("int"))
    return held.where(byte.bitwiseAND(mask) != 0).select(*rows.columns)


def dealt(df: DataFrame, bucket: str, buckets: int):
    """Rows grouped by bucket 0 .. buckets - 1, dealt evenly: one to each partition, or as many to each as there must be."""
    parts = min(buckets, MOST_PARTITIONS)
    return df.withColumn("part__", F.pmod(F.col(bucket), F.lit(parts)).cast("int")).repartitionById(parts, "part__").groupBy("part__", bucket)
