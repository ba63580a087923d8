"""Exact near-duplicate components under Jaccard distance, by a metric-space join.

Documents are sets of word shingles and link at similarity t = near/100 or more, that is at
Jaccard distance eps = 1 - t or less.  Jaccard distance is a metric, and the join rests on
pivots, regions around them and the triangle inequality:

1. Pivots and regions.  Almost all pairs of documents share no shingle and are at distance 1, so
   distances to a few global pivots would tell nothing apart.  Pivots are therefore taken where
   they are near: every shingle among the lowest hashes of a set (its head) names a block, and the
   least document of a block is the block's pivot.  If two sets link, each lacks at most a
   quarter of itself in the other, so their heads of a/4 + e shingles share the first min(e, e')
   common ones.  With e = a/4 + 1, a document with fewer than k = 1 + 3a/16 shared head shingles
   links with nothing, and a document goes to the regions of its most frequent pivots until the
   blocks left over are fewer than k/2: then no linked pair can miss each other (both leave over
   less than half of what they share).
2. Within a region, farther pivots are drawn, documents within eps of a pivot join its component
   outright, and the rest form Voronoi cells.  A document is copied to each cell whose pivot is
   within 2 eps of being its nearest; cells are solved the same way until they no longer shrink.
3. A small or dense cell is settled exactly: documents outside the component of the first pivot
   are compared with all that the triangle and size windows leave, and pairs already connected
   are skipped.  No result is dropped, capped or sampled.
4. Edges between regions are joined to components by alternating large-star and small-star steps.

Equal sets of a map chunk are folded before anything is sent.  A head shingle that many documents
of a chunk hold sends only its least document to the block; its other holders look the pivot up in
a join of one row for each hash and chunk.  Regions beyond `region_docs` are cut into slices.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import NO_ID, checkpointed, dealt, hub_join, likely, numbered
from .superkmer import ROOT, mixed, spread

CHUNK_BYTES, BUCKET_BYTES = 8 << 20, 16 << 20
#: Holders of a head shingle in a chunk from which it is looked up instead of sent.
HOT_IN_CHUNK = 64
UPPER = bytes(range(65, 91))
LOWER = bytes.maketrans(UPPER, UPPER.lower())


def shingle_sets(texts: list[bytes], width: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of all texts, one after the other, and how many each has."""
    split = [t.translate(LOWER).split() for t in texts]
    sizes = np.fromiter(map(len, split), np.int64, len(split))
    words = list(set().union(*split))
    index = dict(zip(words, range(len(words)), strict=True))
    at = np.fromiter(map(index.__getitem__, itertools.chain.from_iterable(split)), np.int64, int(sizes.sum()))
    value = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))[at]
    few = np.flatnonzero((sizes > 0) & (sizes < width))
    short = np.array([xxhash.xxh3_64_intdigest(b" ".join(split[i])) for i in few], np.uint64)
    del split, words, index, at  # millions of small objects
    ends = np.cumsum(sizes)
    count = np.where(sizes >= width, sizes - width + 1, 0)
    begin = spread(ends - sizes, count)
    gram = np.zeros(len(begin), np.uint64)
    for k in range(width):
        gram = mixed(gram * ROOT + value[begin + k])
    owner = np.repeat(np.arange(len(sizes)), count)
    gram, owner = np.concatenate([gram, mixed(short ^ ROOT)]), np.concatenate([owner, few])
    order = np.lexsort((gram, owner))
    gram, owner = gram[order], owner[order]
    keep = np.ones(len(gram), bool)
    keep[1:] = (gram[1:] != gram[:-1]) | (owner[1:] != owner[:-1])
    return gram[keep], np.bincount(owner[keep], minlength=len(sizes))


def head_size(n):
    """Lowest shingles of a set of n that name blocks."""
    return np.minimum(n, n // 4 + n // 4 + 1)


def _blob(*arrays: np.ndarray) -> bytes:
    return zstandard.compress(b"".join(a.astype("<i8").tobytes() for a in arrays), 3)


def _unblob(blob: bytes, columns: int) -> np.ndarray:
    return np.frombuffer(zstandard.decompress(blob), "<i8").reshape(columns, -1)


def chunk_rows(ids: list[int], texts: list[bytes], width: int, buckets: int, hot_from: int = HOT_IN_CHUNK) -> Iterator[tuple]:
    """Rows (bucket, kind, blob): documents (id, n, equal document), postings (delta hash, document,
    n, looked up) and holders to look up (hash, document, n)."""
    order = sorted(range(len(ids)), key=ids.__getitem__)
    ids_ = np.array([ids[i] for i in order], np.int64)
    gram, n = shingle_sets([texts[i] for i in order], width)
    ends = np.cumsum(n)
    same: dict[tuple, int] = {}
    lead = np.array([same.setdefault((k, gram[e - k : e].tobytes()) if k else (0, i), i) for i, (e, k) in enumerate(zip(ends.tolist(), n.tolist(), strict=True))])
    yield int(ids_[0]) % buckets, 0, _blob(ids_, n, ids_[lead])
    own = (lead == np.arange(len(ids_))) & (n > 0)
    head = np.where(own, head_size(n), 0)
    at = spread(ends - n, head)
    doc = np.repeat(np.arange(len(ids_)), head)
    hashes = gram[at]
    order = np.argsort(hashes, kind="stable")  # documents ascend within a hash
    hashes, doc = hashes[order], doc[order]
    opens = np.ones(len(hashes), bool)
    opens[1:] = hashes[1:] != hashes[:-1]
    group = np.cumsum(opens) - 1
    hot = (np.bincount(group) >= hot_from)[group] if len(group) else np.zeros(0, bool)
    if hot.any():
        yield int(hashes[hot][0] % np.uint64(buckets)), 2, _blob(hashes[hot].view(np.int64), ids_[doc[hot]], n[doc[hot]])
    keep = ~hot | opens
    hashes, doc, hot = hashes[keep], doc[keep], hot[keep]
    bucket = (mixed(hashes) % np.uint64(buckets)).astype(np.int64)
    order = np.argsort(bucket, kind="stable")
    for here in np.split(order, np.flatnonzero(np.diff(bucket[order])) + 1) if len(order) else []:
        used, local = np.unique(doc[here], return_inverse=True)
        key = np.diff(hashes[here], prepend=np.uint64(0)).astype("<u8").view(np.uint8).reshape(-1, 8).T
        body = np.array([len(here), len(used)], "<i8").tobytes() + ids_[used].astype("<i8").tobytes() + n[used].astype("<i8").tobytes()
        body += key.tobytes() + local.astype("<i4").view(np.uint8).reshape(-1, 4).T.tobytes() + hot[here].tobytes()
        yield int(bucket[here[0]]), 1, zstandard.compress(body, 3)


def _postings(blob: bytes):
    body = zstandard.decompress(blob)
    count, used = np.frombuffer(body, "<i8", 2).tolist()
    ids, n = np.frombuffer(body, "<i8", used, 16), np.frombuffer(body, "<i8", used, 16 + 8 * used)
    at = 16 + 16 * used
    key = np.cumsum(np.frombuffer(body, np.uint8, 8 * count, at).reshape(8, -1).T.copy().view("<u8")[:, 0], dtype=np.uint64)
    local = np.frombuffer(body, np.uint8, 4 * count, at + 8 * count).reshape(4, -1).T.copy().view("<i4")[:, 0]
    return key, ids[local], n[local], np.frombuffer(body, bool, count, at + 12 * count)


FOUND = "kind int, x long, n long, p long, m long, holders binary"


def bucket_rows(group: pd.DataFrame) -> pd.DataFrame:
    """kind 0: a document, its set's size, an equal document; 1: document x, size, pivot p, blocks m
    that x shares with others under p; 2: chunk x, hash p, its holders there and their sizes; 3: hash x, pivot p."""
    out = []
    for kind, blob in zip(group["kind"], group["blob"], strict=True):
        if kind == 0:
            x, n, p = _unblob(blob, 3)
            out.append(pd.DataFrame({"kind": 0, "x": x, "n": n, "p": p, "m": 0}))
        elif kind == 2:
            h, x, n = _unblob(blob, 3)
            chunk, cuts = x[0], np.flatnonzero(np.diff(h)) + 1
            rows = [_blob(a, b) for a, b in zip(np.split(x, cuts), np.split(n, cuts), strict=True)]
            out.append(pd.DataFrame({"kind": 2, "x": chunk, "n": 0, "p": h[np.append(0, cuts)], "m": 0, "holders": rows}))
    parts = [_postings(b) for k, b in zip(group["kind"], group["blob"], strict=True) if k == 1]
    if parts:
        key, x, n, hot = (np.concatenate(c) for c in zip(*parts, strict=True))
        del parts
        order = np.lexsort((x, key))
        key, x, n, hot = key[order], x[order], n[order], hot[order]
        opens = np.ones(len(key), bool)
        opens[1:] = key[1:] != key[:-1]
        first = np.flatnonzero(opens)
        size = np.diff(np.append(first, len(key)))
        looked_up = np.maximum.reduceat(hot, first)
        if looked_up.any():
            out.append(pd.DataFrame({"kind": 3, "x": key[first[looked_up]].view(np.int64), "n": 0, "p": x[first[looked_up]], "m": 0}))
        shared = np.repeat((size > 1) | looked_up, size) & ~hot
        pivot = np.repeat(x[first], size)[shared]
        x, n = x[shared], n[shared]
        order = np.lexsort((pivot, x))
        x, n, pivot = x[order], n[order], pivot[order]
        new = np.ones(len(x), bool)
        new[1:] = (x[1:] != x[:-1]) | (pivot[1:] != pivot[:-1])
        at = np.flatnonzero(new)
        out.append(pd.DataFrame({"kind": 1, "x": x[at], "n": n[at], "p": pivot[at], "m": np.diff(np.append(at, len(x)))}))
    return pd.concat([pd.DataFrame({"kind": [], "holders": []}, dtype=object), *out]).astype({k: "int64" for k in "xnpm"} | {"kind": "int32"})[["kind", "x", "n", "p", "m", "holders"]]


def looked_up_rows(chunk: pd.DataFrame) -> pd.DataFrame:
    """(x, n, p, m) of the holders of a chunk, whose hashes have been given pivots."""
    held = [_unblob(b, 2) for b in chunk["holders"]]
    x, n = (np.concatenate([h[k] for h in held]) for k in (0, 1))
    p = np.repeat(chunk["p"].to_numpy(), [h.shape[1] for h in held])
    return pd.DataFrame({"x": x, "n": n, "p": p, "m": 1}).groupby(["x", "p"], as_index=False).agg({"n": "max", "m": "sum"})[["x", "n", "p", "m"]]


class Region:
    """Documents of one region; `labels` are the indexes of their components' least documents."""

    LEAF, PIVOTS = 48, 6

    def __init__(self, sets: list[np.ndarray], near: int = 75):
        self.near, self.eps = near, 1 - near / 100
        self.size = np.fromiter(map(len, sets), np.int64, len(sets))
        _, entry = np.unique(np.concatenate(sets), return_inverse=True)
        df = np.bincount(entry)
        owner = np.repeat(np.arange(len(sets)), self.size)
        shared = df[entry] > 1
        self.entry, own = entry[shared], owner[shared]
        self.begin = np.searchsorted(own, np.arange(len(sets) + 1))
        self.holders = own[np.argsort(self.entry, kind="stable")]
        self.df = np.where(df > 1, df, 0)
        self.first = np.cumsum(self.df) - self.df
        self.parent = np.arange(len(sets))

    def root(self, i: int) -> int:
        while self.parent[i] != i:
            self.parent[i] = i = self.parent[self.parent[i]]
        return i

    def labels(self) -> np.ndarray:
        p = self.parent
        while (q := p[p]).tolist() != p.tolist():
            p = q
        self.parent = p
        return p

    def unite(self, i: int, others: np.ndarray) -> None:
        roots = {self.root(j) for j in others.tolist()} | {self.root(i)}
        least = min(roots)
        for r in roots:
            self.parent[r] = least

    def distance(self, i: int) -> np.ndarray:
        """Of document i to all; documents within eps join its component on the way."""
        e = self.entry[self.begin[i] : self.begin[i + 1]]
        common = np.bincount(self.holders[spread(self.first[e], self.df[e])], minlength=len(self.size))
        common[i] = self.size[i]
        union = self.size + self.size[i] - common
        near = np.flatnonzero(100 * common >= self.near * union)
        if len(near) > 1:
            self.unite(i, near)
        return 1 - common / union

    def solve(self, members: np.ndarray | None = None, depth: int = 0) -> None:
        members = np.arange(len(self.size)) if members is None else members
        if len(members) < 2:
            return
        far, dist, pivots = np.full(len(members), 2.0), [], []
        for _ in range(1 if len(members) <= self.LEAF else self.PIVOTS):
            best = int(np.argmax(far))
            if pivots and far[best] <= self.eps:
                break
            pivots.append(int(members[best]))
            dist.append(self.distance(pivots[-1])[members])
            far = np.minimum(far, dist[-1])
        d = np.array(dist)
        if (self.labels()[members] == self.parent[members[0]]).all():
            return
        if len(members) > self.LEAF and depth < 24:
            tiny = 1e-9
            least = d.min(0)
            # home: the nearest pivot if that is nearer than 1 - eps, else outside
            cells = [(d[q] < 1 - tiny) & (d[q] <= least + 2 * self.eps + tiny) for q in range(len(d))]
            cells.append(least >= 1 - 2 * self.eps - tiny)
            if max(c.sum() for c in cells) <= 0.75 * len(members):
                for c in cells:
                    self.solve(members[c], depth + 1)
                return
        self.settle(members, d, set(pivots))

    def settle(self, members: np.ndarray, d: np.ndarray, done: set[int]) -> None:
        while True:
            label = self.labels()[members]
            roots, counts = np.unique(label, return_counts=True)
            main = roots[np.argmax(counts)]
            left = [k for k in np.flatnonzero(label != main).tolist() if int(members[k]) not in done]
            if not left:
                return
            for k in left:
                i = int(members[k])
                root = self.root(i)
                if root == self.root(int(main)):
                    continue
                done.add(i)
                window = (np.abs(d - d[:, k : k + 1]).max(0) <= self.eps + 1e-9) & (label != label[k])
                size = self.size[members]
                window &= (100 * size >= self.near * self.size[i]) & (100 * self.size[i] >= self.near * size)
                if window.any():
                    self.distance(i)
            self.labels()


def region_links(sets: list[np.ndarray], ids: np.ndarray, near: int) -> tuple[np.ndarray, np.ndarray]:
    """(document, least document of its component) for all that aren't their component's least; ids ascend."""
    region = Region(sets, near)
    region.solve()
    label = region.labels()
    moved = np.flatnonzero(label != np.arange(len(ids)))
    return ids[moved], ids[label[moved]]


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for each node that isn't the least of its component; edges are (u, v), u > v.

    Nodes with many edges are joined by broadcast, at most a thousand of them in each step.
    """
    edges = checkpointed(edges.distinct())
    total, mark = edges.count(), None
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("degree"))
        large = hub_join(both, least, "u", "degree", 2 * total).where("v > u").select(F.col("v").alias("u"), F.least("m", "u").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("degree"))
        small = hub_join(large, least, "u", "degree", 2 * total).where("v <> m").select(F.greatest("v", "m").alias("u"), F.least("v", "m").alias("v"))
        edges = checkpointed(small.unionByName(least.select("u", F.col("m").alias("v"))).distinct())
        now = edges.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0))).first()
        if now == mark:
            return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
        total, mark = now[0], now


LINKS = "p long, slices int, out boolean, u long, v long"


def region_solver(near: int):
    def solve(key: tuple, group: pd.DataFrame) -> pd.DataFrame:
        """Links of a group, and of a slice also the documents outside its pivot's component."""
        p, slices = int(key[0]), int(key[1])
        group = group.drop_duplicates("x").sort_values("x")
        ids = group["x"].to_numpy()
        u, v = region_links([np.frombuffer(b, np.uint64) for b in group["grams"]], ids, near)
        out = pd.DataFrame({"out": False, "u": u, "v": v})
        if slices > 1:
            root = dict(zip(u.tolist(), v.tolist(), strict=True))
            home = root.get(p, p)
            far = [x for x in ids.tolist() if root.get(x, x) != home]
            out = pd.concat([out, pd.DataFrame({"out": True, "u": far, "v": far}, dtype="int64")])
        return pd.DataFrame({"p": p, "slices": slices, "out": out["out"].astype(bool), "u": out["u"].astype("int64"), "v": out["v"].astype("int64")})

    return solve


def grouped_links(rows: DataFrame, placed: DataFrame, width: int, near: int) -> DataFrame:
    """Solve the groups (p, slices, a, b) that `placed` puts documents x in."""
    by_doc = placed.groupBy("x").agg(F.collect_list(F.struct("p", "slices", "a", "b")).alias("gs"))
    members = likely(rows, "node", placed, "x").join(by_doc, F.col("node") == F.col("x")).select("node", "text", "gs")

    def sets(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for low in range(0, len(batch), 1000):
                part = batch.iloc[low : low + 1000]
                gram, n = shingle_sets([t.encode() for t in part["text"]], width)
                ends = np.cumsum(n)
                out = [(g["p"], g["slices"], g["a"], g["b"], i, gram[e - k : e].tobytes()) for i, gs, e, k in zip(part["node"], part["gs"], ends.tolist(), n.tolist(), strict=True) for g in gs]
                yield pd.DataFrame(out, columns=["p", "slices", "a", "b", "x", "grams"])

    held = members.mapInPandas(sets, "p long, slices int, a int, b int, x long, grams binary")
    return held.groupBy("p", "slices", "a", "b").applyInPandas(region_solver(near), LINKS)


def links_of_regions(rows: DataFrame, regions: DataFrame, width: int, near: int, region_docs: int) -> DataFrame:
    """(u, v) of all pairs within regions (x, p), as links that connect the same components.

    A region of up to `region_docs` documents is one group.  A larger one is cut into slices by hash,
    each with a copy of the pivot: what links to the pivot in its slice needs no further comparison
    with others that do.  Only the documents outside then go to every slice, in blocks of up to
    `region_docs`, so no group holds more than about twice that.
    """
    size = regions.groupBy("p").agg(F.count("*").alias("docs"))
    total = regions.count()
    slices = F.ceil(F.col("docs") / F.lit(region_docs)).cast("int")
    one = F.lit(0)
    cut = hub_join(regions, size, "p", "docs", total).where("docs > 1").withColumn("slices", slices)
    cut = cut.select("x", "p", "slices", F.pmod(F.xxhash64("x"), F.col("slices")).cast("int").alias("a"))
    large = size.withColumn("slices", slices).where("slices > 1")
    pivots = large.select(F.col("p").alias("x"), "p", "slices", F.explode(F.sequence(one, F.col("slices") - 1)).alias("a"))
    placed = checkpointed(cut.unionByName(pivots))
    found = checkpointed(grouped_links(rows, placed.withColumn("b", one), width, near))
    links = found.where("not out").select("u", "v")
    outside = found.where("out").select(F.col("u").alias("x"), "p", "slices").distinct()
    blocks = outside.groupBy("p").agg(F.ceil(F.count("*") / F.lit(region_docs)).cast("int").alias("blocks"))
    blocks = checkpointed(blocks)
    if blocks.isEmpty():
        return links
    # few rows: regions that are large and hold documents outside their pivot's component
    wanted = outside.join(blocks, "p").withColumn("b", F.pmod(F.xxhash64(F.lit("block"), "x"), F.col("blocks")).cast("int"))
    wanted = wanted.select("x", "p", "slices", F.explode(F.sequence(one, F.col("slices") - 1)).alias("a"), "b")
    held = placed.where("slices > 1").join(blocks, "p").select("x", "p", "slices", "a", F.explode(F.sequence(one, F.col("blocks") - 1)).alias("b"))
    again = grouped_links(rows, checkpointed(wanted.unionByName(held).distinct()), width, near)
    return links.unionByName(again.where("not out").select("u", "v"))


def near_duplicates(docs: DataFrame, width: int = 5, near: int = 75, buckets: int | None = None, region_docs: int = 1000, hot_from: int = HOT_IN_CHUNK) -> DataFrame:
    """(doc_id, n_shingles, component_id) for each row of docs.

    Null and empty texts have an empty set and link with nothing.  Rows of equal doc_id and text are
    one document; rows of one doc_id and different texts are different documents.  A null doc_id is
    kept and is less than all others.  Extra columns are ignored.  Shingles are equal when their
    64-bit hashes are.  The proof of the regions needs `near` of 75 or more.
    """
    found, names = nodes_with_components(*numbered(docs), width, near, buckets, region_docs, hot_from)
    if names is None:
        null = F.lit(NO_ID)
        return found.select(F.nullif("node", null).alias("doc_id"), F.col("n").alias("n_shingles"), F.nullif("component", null).alias("component_id"))
    own = names.select("node", "doc_id")
    least = names.select(F.col("node").alias("component"), F.col("doc_id").alias("component_id"))
    return found.join(own, "node").join(least, "component").select("doc_id", F.col("n").alias("n_shingles"), "component_id")


def nodes_with_components(rows: DataFrame, names: DataFrame | None, repeats: bool, width: int, near: int, buckets: int | None = None, region_docs: int = 1000, hot_from: int = HOT_IN_CHUNK) -> tuple[DataFrame, DataFrame | None]:
    """(node, n, component) for each of the numbered rows, and the names of nodes as given."""
    if near < 75:
        raise ValueError("similarities of 75 % or more are supported")
    if buckets is None:
        total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        buckets = max(8, math.ceil(total / BUCKET_BYTES))

    def send(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, texts, held = [], [], 0

        def out() -> pd.DataFrame:
            return pd.DataFrame(list(chunk_rows(ids, texts, width, buckets, hot_from)) if ids else [], columns=["bucket", "kind", "blob"])

        for batch in batches:
            for i, t in zip(batch["node"].tolist(), batch["text"], strict=True):
                ids.append(i)
                texts.append((t or "").encode())
                held += len(texts[-1]) + 64
                if held >= CHUNK_BYTES:
                    yield out()
                    ids, texts, held = [], [], 0
        yield out()

    sent = rows.select("node", "text").mapInPandas(send, "bucket long, kind int, blob binary")
    found = checkpointed(dealt(sent, "bucket", buckets).applyInPandas(bucket_rows, FOUND))
    documents = found.where("kind = 0").select(F.col("x").alias("node_"), "n", F.col("p").alias("lead"))
    looked_up = found.where("kind = 2").select(F.col("x").alias("chunk"), F.col("p").alias("h"), "holders")
    pivots = found.where("kind = 3").select(F.col("x").alias("h"), "p")
    looked_up = looked_up.join(pivots, "h").groupBy("chunk").applyInPandas(looked_up_rows, "x long, n long, p long, m long")
    shared = found.where("kind = 1").select("x", "n", "p", "m").unionByName(looked_up)
    shared = shared.groupBy("x", "p").agg(F.max("n").alias("n"), F.sum("m").alias("m"))
    needed = F.lit(1) + F.floor(F.col("n") * 3 / 16)
    by_x = W.partitionBy("x")
    before = F.sum("m").over(by_x.orderBy(F.desc("m"), "p").rowsBetween(W.unboundedPreceding, -1))
    regions = shared.withColumn("total", F.sum("m").over(by_x)).withColumn("rest", F.col("total") - F.coalesce(before, F.lit(0)))
    regions = checkpointed(regions.where((F.col("total") >= needed) & (2 * F.col("rest") > needed - 1)).select("x", "p"))
    once = rows.select("node", "text")
    once = once.dropDuplicates(["node"]) if repeats else once
    roots = components(links_of_regions(once, regions, width, near, region_docs))
    joined = documents.join(roots, F.col("lead") == F.col("node"), "left")
    return joined.select(F.col("node_").alias("node"), "n", F.coalesce("root", "lead").alias("component")), names


def one_of_each(docs: DataFrame, width: int = 5, near: int = 75) -> DataFrame:
    """One row of docs for each component, with all its columns: that of the least doc_id.

    Of repeated rows one stays; of different texts with one doc_id the one with the least hash stays.
    """
    rows, names, repeats = numbered(docs)
    found, _ = nodes_with_components(rows, names, repeats, width, near)
    kept = found.where("node = component").select(F.col("node").alias("kept__"))
    kept = kept.distinct() if repeats else kept
    if names is None:
        d = docs.withColumn("node__", F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)))
        d = d.dropDuplicates(["node__"]) if repeats else d
        return d.join(kept, F.col("node__") == F.col("kept__"), "left_semi").select(*docs.columns)
    text = F.md5(F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary"))
    d = docs.withColumns({"id__": F.col("doc_id").cast("long"), "text__": text}).dropDuplicates(["id__", "text__"])
    keys = names.join(kept, F.col("node") == F.col("kept__"), "left_semi")
    of = rows.select("node", F.md5(F.coalesce("text", F.lit("")).cast("binary")).alias("key_")).distinct()
    keys = keys.join(of, "node").select(F.col("doc_id").alias("kept_id__"), F.col("key_").alias("kept_text__"))
    return d.join(keys, F.col("id__").eqNullSafe(F.col("kept_id__")) & (F.col("text__") == F.col("kept_text__")), "left_semi").select(*docs.columns)
