"""Exact top-k search for binary codes by incremental multi-index hashing.

A code is cut into m segments of about log2(n) bits.  One index, built once, has an entry for each
code in each segment; its cells are a segment and the first bits of the segment's value.  If all
values within radius r of a query's segment have been looked up in every segment, every code within
Hamming distance m (r + 1) - 1 has been met: otherwise all m segments would differ in r + 1 bits or
more.  The radius grows by one from round to round.  In a round each open query is sent to the cells
whose prefix can hold a value at exactly that radius, the values are looked up there among the
cell's sorted entries, and the best k codes of all cells join those of earlier rounds.  A query is
closed, and asks no more, once its k-th verified distance is within the bound.

Equal codes are one entry with their k least ids, and equal queries are asked once, so a vector
that a third of all rows share costs no more than another.  A cell with many entries is cut into
slices by hash, and the queries of a slice into blocks, so a segment value that a third of all codes
share is spread over as many tasks as it needs.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import checkpointed, hub_join

#: Entries of an index cell's slice, and queries that are sent to it together.
CELL_CODES, QUERY_BLOCK = 32_768, 512
#: Lookups of a batch of queries in a cell at a time.
LOOKUPS = 1 << 20
BEST = "array<struct<distance:int,least:bigint,code:bigint,copies:int>>"
#: Bits of a cell's number that hold the prefix.
SPOT = 40


def sign_code(vector: Column) -> Column:
    """One bit for each of up to 64 components: set where it is above zero (a null one isn't); null for a null vector."""
    bits = F.transform(vector, lambda x, i: F.when(x > 0, F.call_function("shiftleft", F.lit(1).cast("long"), i)).otherwise(F.lit(0).cast("long")))
    code = F.aggregate(bits, F.lit(0).cast("long"), lambda a, b: a.bitwiseOR(b))
    return F.when(F.size(vector) > 64, F.raise_error(F.lit("sign codes have at most 64 components"))).otherwise(code)


def layout(bits: int, codes: int) -> list[tuple[int, int]]:
    """(shift, width) of each segment."""
    m = max(1, round(bits / max(8, min(24, math.log2(max(codes, 2))))))
    widths = [bits // m + (j < bits % m) for j in range(m)]
    return [(sum(widths[:j]), w) for j, w in enumerate(widths)]


def masks(width: int, radius: int) -> list[int]:
    """All values of `width` bits with `radius` of them set."""
    return [sum(1 << i for i in c) for c in itertools.combinations(range(width), radius)]


def _spots(code: Column, segments: list[tuple[int, int]], prefix: int) -> list[Column]:
    """For each segment the number of its cell: the segment, then the first `prefix` bits of its value."""
    cut = lambda shift, w: F.shiftrightunsigned(code, shift + w - min(prefix, w)).bitwiseAND(F.lit((1 << min(prefix, w)) - 1))
    return [cut(shift, w).bitwiseOR(F.lit(j << SPOT)) for j, (shift, w) in enumerate(segments)]


def ring(codes: np.ndarray, queries: np.ndarray, apart: np.ndarray, shift: int, free: int, radius: int, bound: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query, code, distance) of a cell's codes at segment radius `radius`; queries and codes as indexes.

    `codes` are sorted by the `free` last bits of their segment; `apart` is how many bits of the
    cell's prefix differ from each query's.  Distances over a query's bound are left out.
    """
    low = (codes >> np.uint64(shift)) & np.uint64((1 << free) - 1)
    # where each value starts: a table while it is small, else by bisection
    table = np.searchsorted(low, np.arange((1 << free) + 1, dtype=np.uint64)) if free <= 20 else None
    out = []
    for rest in np.unique(radius - apart):
        if rest > free:
            continue
        flips = np.array(masks(free, int(rest)), np.uint64)
        all_here = np.flatnonzero(radius - apart == rest)
        step = max(1, LOOKUPS // len(flips))
        for begin in range(0, len(all_here), step):
            here = all_here[begin : begin + step]
            value = (((queries[here] >> np.uint64(shift)) & np.uint64((1 << free) - 1))[:, None] ^ flips[None, :]).ravel()
            if table is None:
                first, last = np.searchsorted(low, value, "left"), np.searchsorted(low, value, "right")
            else:
                first, last = table[value], table[value + np.uint64(1)]
            count = last - first
            hit = np.flatnonzero(count)
            count, first = count[hit], first[hit]
            ends = np.cumsum(count)
            at = np.arange(ends[-1] if len(ends) else 0) + np.repeat(first - (ends - count), count)
            q = np.repeat(here[hit // len(flips)], count)
            distance = np.bitwise_count(codes[at] ^ queries[q]).astype(np.int64)
            near = distance <= bound[q]
            out.append((q[near], at[near], distance[near]))
    if not out:
        return (np.zeros(0, np.int64),) * 3
    q, at, distance = (np.concatenate(x) for x in zip(*out, strict=True))
    return q, at, distance


def best_of(q: np.ndarray, distance: np.ndarray, least: np.ndarray, k: int) -> np.ndarray:
    """Places of the k entries of each query that are least by (distance, least id)."""
    order = np.lexsort((least, distance, q))
    opens = np.ones(len(q), bool)
    opens[1:] = q[order][1:] != q[order][:-1]
    rank = np.arange(len(q)) - np.maximum.accumulate(np.where(opens, np.arange(len(q)), 0))
    return order[rank < k]


def nearest_codes(rows: DataFrame, queries: DataFrame, k: int = 10, bits: int = 64, cell_codes: int = CELL_CODES, query_block: int = QUERY_BLOCK) -> DataFrame:
    """(query_id, rank, neighbor_id, distance): the k rows nearest to each query, ties by id.

    rows and queries have (id, code).  Rows with a null id or code are left out of both; repeated
    (id, code) rows count once; fewer than k rows give fewer ranks.  A query that is itself a row
    finds itself.  Other columns are ignored.
    """
    rows = rows.select(F.col("id").cast("long").alias("id"), F.col("code").cast("long").alias("code")).dropna()
    asked = queries.select(F.col("id").cast("long").alias("query_id"), F.col("code").cast("long").alias("query")).dropna().distinct()
    codes = checkpointed(_folded(rows, k))
    n = codes.count()
    segments = layout(bits, n)
    m, widest, prefix = len(segments), max(w for _, w in segments), max(0, math.ceil(math.log2(max(1, n / cell_codes))))
    index = checkpointed(_index(codes, n, segments, prefix, cell_codes))
    sizes = index.groupBy("spot").agg(F.count("*").cast("int").alias("slices"))
    open_ = checkpointed(asked.select("query").distinct().select("query", F.lit(bits).alias("bound"), F.array().cast(BEST).alias("best")))
    closed = open_.select("query", "best").limit(0)
    for radius in range(widest + 1):
        left = open_.count()
        if not left:
            break
        met = _round(open_, left, index, sizes, segments, prefix, radius, k, query_block)
        now = checkpointed(_merged(open_, met, k, bits, n, m * (radius + 1) - 1, radius == widest))
        closed = closed.unionByName(now.where("done").select("query", "best"))
        open_ = now.where("not done").select("query", "bound", "best")
    flat = closed.select("query", F.explode("best").alias("b")).select("query", "b.distance", "b.code")
    ids = flat.join(codes.select("code", "ids"), "code").select("query", "distance", F.explode("ids").alias("id"))
    ranked = ids.withColumn("rank", F.row_number().over(W.partitionBy("query").orderBy("distance", "id"))).where(F.col("rank") <= k)
    lists = ranked.groupBy("query").agg(F.sort_array(F.collect_list(F.struct("rank", F.col("id").alias("neighbor_id"), "distance"))).alias("found"))
    return asked.join(lists, "query").select("query_id", F.inline("found"))


def _folded(rows: DataFrame, k: int) -> DataFrame:
    """(code, ids): each distinct code with its k least ids; a code that many rows share is met in parts first."""
    part = F.pmod(F.xxhash64("id"), F.lit(64)).cast("int")
    first = lambda *by: F.row_number().over(W.partitionBy(*by).orderBy("id"))
    some = rows.distinct().withColumn("part", part).withColumn("at", first("code", "part")).where(F.col("at") <= k)
    least = some.withColumn("at", first("code")).where(F.col("at") <= k)
    return least.groupBy("code").agg(F.sort_array(F.collect_list("id")).alias("ids"))


def _field(structs: str, name: str) -> Column:
    return F.transform(structs, lambda e: e[name]).alias(name)


def _flipped(spot: Column, flips: Column, apart: int) -> Column:
    return F.transform(flips, lambda x: F.struct(spot.bitwiseXOR(x).alias("spot"), F.lit(apart).alias("apart")))


def _index(codes: DataFrame, n: int, segments: list[tuple[int, int]], prefix: int, cell_codes: int) -> DataFrame:
    """(spot, slice, code, least, copies): arrays with the codes of each slice, their least ids and numbers of copies."""
    entry = F.struct("code", F.get("ids", 0).alias("least"), F.size("ids").alias("copies"))
    flat = codes.select(entry.alias("e"), F.explode(F.array(*_spots(F.col("code"), segments, prefix))).alias("spot"))
    size = flat.groupBy("spot").agg(F.count("*").alias("codes"))
    piece = F.pmod(F.xxhash64("e.code"), F.ceil(F.col("codes") / F.lit(2 * cell_codes))).cast("int")
    placed = hub_join(flat, size, "spot", "codes", n * len(segments))
    cells = placed.groupBy("spot", piece.alias("slice")).agg(F.collect_list("e").alias("e"))
    return cells.select("spot", "slice", *[_field("e", c) for c in ("code", "least", "copies")])


def _round(open_: DataFrame, left: int, index: DataFrame, sizes: DataFrame, segments: list[tuple[int, int]], prefix: int, radius: int, k: int, query_block: int) -> DataFrame:
    """(query, distance, least, code, copies) at exactly this segment radius, up to k for each query and slice."""
    flips, number = [], 0
    for spot, (_, w) in zip(_spots(F.col("query"), segments, prefix), segments, strict=True):
        p = min(prefix, w)
        for apart in range(max(0, radius - (w - p)), min(radius, p) + 1):
            values = masks(p, apart)
            number += len(values)
            literal = F.split(F.lit(",".join(map(str, values))), ",").cast("array<bigint>")  # folded to one literal
            flips.append(_flipped(spot, literal, apart))
    probes = open_.select("query", "bound", F.inline(F.flatten(F.array(*flips))))
    load = probes.groupBy("spot").agg(F.count("*").alias("asked")).join(sizes, "spot")
    probes = hub_join(probes, load, "spot", "asked", left * number)
    block = F.pmod(F.xxhash64("query"), F.ceil(F.col("asked") / F.lit(query_block))).cast("int")
    probes = probes.select("spot", "query", "bound", "apart", block.alias("block"), F.explode(F.sequence(F.lit(0), F.col("slices") - 1)).alias("slice"))
    sent = probes.groupBy("spot", "slice", "block").agg(F.collect_list(F.struct("query", "bound", "apart")).alias("q"))
    sent = sent.select("spot", "slice", *[_field("q", c) for c in ("query", "bound", "apart")])
    both = sent.join(index, ["spot", "slice"])

    def search(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for row in batch.itertuples(index=False):
                shift, width = segments[row.spot >> SPOT]
                free = width - min(prefix, width)
                code = row.code.view(np.uint64)
                order = np.argsort((code >> np.uint64(shift)) & np.uint64((1 << free) - 1), kind="stable")
                code, least, copies = code[order], row.least[order], row.copies[order]
                query = row.query.view(np.uint64)
                q, at, distance = ring(code, query, row.apart.astype(np.int64), shift, free, radius, row.bound)
                best = best_of(q, distance, least[at], k)
                q, at, distance = q[best], at[best], distance[best]
                yield pd.DataFrame({"query": query[q].view(np.int64), "distance": distance.astype("int32"), "least": least[at], "code": code[at].view(np.int64), "copies": copies[at].astype("int32")})

    return both.select("spot", "code", "least", "copies", "query", "bound", "apart").mapInPandas(search, "query long, distance int, least long, code long, copies int")


def _merged(open_: DataFrame, met: DataFrame, k: int, bits: int, codes: int, covered: int, last: bool) -> DataFrame:
    """(query, best, bound, done): the k best codes so far; done where they hold k ids within the covered distance, or are all."""
    # a code can be met in several segments of a round
    few = met.distinct().withColumn("at", F.row_number().over(W.partitionBy("query").orderBy("distance", "least"))).where(F.col("at") <= k)
    new = few.groupBy("query").agg(F.collect_list(F.struct("distance", "least", "code", "copies")).alias("new"))
    all_ = F.array_distinct(F.concat("best", F.coalesce("new", F.array().cast(BEST))))
    both = open_.join(new, "query", "left").select("query", F.slice(F.array_sort(all_), 1, k).alias("best"))
    start = F.struct(F.lit(0).alias("n"), F.lit(None).cast("int").alias("at"))
    step = lambda s, e: F.struct((s["n"] + e["copies"]).alias("n"), F.when(s["at"].isNull() & (s["n"] + e["copies"] >= k), e["distance"]).otherwise(s["at"]).alias("at"))
    both = both.withColumn("kth", F.aggregate("best", start, step, lambda s: s["at"]))
    done = F.lit(last) | (F.size("best") >= codes) | F.coalesce(F.col("kth") <= covered, F.lit(False))
    return both.select("query", "best", F.coalesce("kth", F.lit(bits)).alias("bound"), done.alias("done"))
