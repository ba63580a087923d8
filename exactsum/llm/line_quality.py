"""Quality rules with cross-document line frequency, in DataFrame functions only.

Base rules look at one document: its length and the share of words in repeated 8-word windows.
The corpus rule hashes normalised lines, counts for each host in how many distinct documents a line
stands, removes lines above the host's limit, and rejects a document when too little is left.

A document is a doc_id with a text: repeated rows count once, copies under other ids count each.
Copies are folded to one row with their number before lines are exploded, so a large group of
copies costs no more than one text.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WORD, checkpointed, words

SYMBOLS = "#*$%&|<>"
WINDOW = 8


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """use(value) with `value` computed once, also where the optimizer moves the expression into a filter."""
    return F.get(F.transform(F.array(value), use), 0)


def repeat_words(found: Column) -> Column:
    """How many of the words are covered by 8-word windows that occur twice or more."""

    def windows(h):
        made = F.transform(F.sequence(F.lit(0), F.size(h) - WINDOW), lambda i: F.xxhash64(*[F.get(h, i + k) for k in range(WINDOW)]))
        return F.when(F.size(h) >= WINDOW, made).otherwise(F.array().cast("array<bigint>"))

    def placed(g):
        return F.array_sort(F.transform(g, lambda x, i: F.struct(x.alias("g"), i.alias("i"))))

    def repeated(s):
        same = lambda x, j: F.coalesce(F.get(s, j)["g"] == x["g"], F.lit(False))
        return F.array_sort(F.transform(F.filter(s, lambda x, i: same(x, i - 1) | same(x, i + 1)), lambda x: x["i"]))

    def covered(at):
        start = F.struct(F.lit(0).cast("long").alias("n"), F.lit(-WINDOW).alias("last"))
        return F.aggregate(at, start, lambda a, p: F.struct((a["n"] + F.least(F.lit(WINDOW), p - a["last"])).alias("n"), p.alias("last")), lambda a: a["n"])

    def count(g):
        return F.when(F.size(F.array_distinct(g)) < F.size(g), let(placed(g), lambda s: covered(repeated(s)))).otherwise(F.lit(0).cast("long"))

    return let(F.transform(found, lambda x: F.xxhash64(x)), lambda h: let(windows(h), count))


def base_measures(docs: DataFrame) -> DataFrame:
    """Adds n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words to (doc_id, host, text) rows."""
    text = F.coalesce("text", F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(WORD))
    of_words = let(
        words(F.col("text")),
        lambda w: F.struct(F.size(w).cast("long").alias("n_words"), F.aggregate(w, F.lit(0).cast("long"), lambda a, x: a + F.length(x)).alias("word_chars"), repeat_words(w).alias("n_repeat_words")),
    )
    d = docs.withColumns(
        {
            "w__": of_words,
            "n_symbols": (F.length(text) - F.length(F.translate(text, SYMBOLS, ""))).cast("long"),
            "n_dup_lines": let(lines, lambda x: (F.size(x) - F.size(F.array_distinct(x))).cast("long")),
        }
    )
    return d.withColumns({n: F.col(f"w__.{n}") for n in ("n_words", "word_chars", "n_repeat_words")}).drop("w__")


def line_hash(line: Column) -> Column:
    """Of the line in lower case with single spaces between its words."""
    return F.xxhash64(F.lower(F.array_join(words(line), " ")))


def line_frequency(docs: DataFrame, share: float, least: int) -> tuple[DataFrame, DataFrame]:
    """From (doc_id, host, text_id, text) rows: (host, text_id, removed words, removed lines) and (host, line, documents) above the limits.

    A line's limit in a host is `share` of its distinct documents, but at least `least`.
    """
    line = F.transform(F.filter(F.split("text", "\n"), lambda x: x.rlike(WORD)), lambda x: F.struct(line_hash(x).alias("line"), F.regexp_count(x, F.lit(WORD)).alias("n")))
    own = docs.where("text is not null").select("host", "text_id", "doc_id", line.alias("lines"))
    own = own.groupBy("host", "text_id", "doc_id").agg(F.first("lines").alias("lines"))
    texts = checkpointed(own.groupBy("host", "text_id").agg(F.first("lines").alias("lines"), F.count("*").alias("docs")))
    hosts = texts.groupBy("host").agg(F.sum("docs").alias("docs"))
    limit = F.greatest(F.lit(least).cast("double"), F.col("docs") * F.lit(share))
    hosts = hosts.select(F.col("host").alias("host_"), limit.alias("limit"))
    distinct = texts.select("host", "docs", F.explode(F.array_distinct(F.transform("lines", lambda x: x["line"]))).alias("line"))
    counts = distinct.groupBy("host", "line").agg(F.sum("docs").alias("docs")).where(F.col("docs") > least)
    often = counts.join(hosts, F.col("host").eqNullSafe(F.col("host_"))).where("docs > limit").select("host", "line", "docs")
    every = texts.select("host", "text_id", F.inline("lines"))
    o = often.select(F.col("host").alias("host_"), F.col("line").alias("line_"))
    removed = every.join(o, F.col("host").eqNullSafe(F.col("host_")) & (F.col("line") == F.col("line_")))
    removed = removed.groupBy("host", "text_id").agg(F.sum("n").cast("long").alias("n_removed"), F.collect_set("line").alias("removed_lines"))
    return removed, often


def judged(docs: DataFrame, host: str = "source", share: float = 0.02, least: int = 3, left: float = 0.3, min_words: int = 20, repeat_percent: int = 30) -> DataFrame:
    """(doc_id, host, text_id, base measures, base_failed, n_removed, removed_lines, kept) for each row.

    text_id is the text's md5.  base_failed: fewer than min_words words, or over repeat_percent % of
    them in windows found twice.  A line goes where more than `share` of its host's documents, and
    more than `least` of them, have it.  kept: not base_failed, and more than `left` of the words
    outside lines that go.  A null text has no words and fails.  A null host is a host of its own.
    Repeated rows and ids are judged row by row; other columns are ignored.
    """
    rows = docs.select(F.col("doc_id"), F.col("text").cast("string").alias("text"), F.col(host).cast("string").alias("host"))
    rows = rows.withColumn("text_id", F.unhex(F.md5("text")))
    removed, _ = line_frequency(rows, share, least)
    r = removed.withColumnsRenamed({"host": "host_", "text_id": "text_id_"})
    d = base_measures(rows).drop("text")
    d = d.join(r, F.col("host").eqNullSafe(F.col("host_")) & (F.col("text_id") == F.col("text_id_")), "left").drop("host_", "text_id_")
    gone = F.coalesce("n_removed", F.lit(0).cast("long"))
    failed = (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > repeat_percent * F.col("n_words"))
    return d.withColumns({"n_removed": gone, "base_failed": failed}).withColumn("kept", ~F.col("base_failed") & (F.col("n_words") - F.col("n_removed") > F.col("n_words") * F.lit(left)))


def without_lines(text: Column, removed: Column) -> Column:
    """The text without the lines whose hashes are given."""
    kept = F.filter(F.split(text, "\n"), lambda x: ~(x.rlike(WORD) & F.array_contains(removed, line_hash(x))))
    return F.when(removed.isNull(), text).otherwise(F.array_join(kept, "\n"))


def cleaned(docs: DataFrame, **rules) -> DataFrame:
    """The rows of docs that are kept, without their too frequent lines; n_chars follows the text."""
    key = F.struct(F.col("doc_id"), F.col("source").cast("string"), F.unhex(F.md5(F.col("text").cast("string"))))
    verdict = judged(docs, **rules).where("kept").select(F.struct("doc_id", "host", "text_id").alias("key__"), "removed_lines").dropDuplicates(["key__"])
    d = docs.withColumn("own_key__", key).join(verdict, F.col("own_key__").eqNullSafe(F.col("key__")))
    text = without_lines(F.col("text"), F.col("removed_lines"))
    out = {"text": text} | ({"n_chars": F.length(text).cast(docs.schema["n_chars"].dataType)} if "n_chars" in docs.columns else {})
    return d.withColumns(out).select(*docs.columns)
