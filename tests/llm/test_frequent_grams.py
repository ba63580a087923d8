"""Frequent grams are counted in all texts."""

from __future__ import annotations

from pyspark.sql import functions as F

from exactsum.llm import superkmer as S


def test_every_text_is_counted(spark):
    """A gram in exactly as many documents as asked for, among 40 MB of others, is found."""
    filler = F.concat_ws(" ", F.transform(F.sequence(F.lit(1), F.lit(100)), lambda k: F.md5(F.concat_ws("-", "id", k))))
    rows = spark.range(0, 12_000, 1, 4).select(F.col("id").alias("node"), F.when(F.col("id") % 10 == 0, F.concat(filler, F.lit(" one two three"), F.lit(" "), filler)).otherwise(filler).alias("text"))
    wanted = S.gram_hashes(S.word_hashes(b"one two\tthree"), 3)
    total = rows.agg(F.sum(F.octet_length("text"))).first()[0]
    found = S.frequent_grams(rows, total, 3, 1200)
    assert wanted[0] in found and len(found) == 1
