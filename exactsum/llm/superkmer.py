"""Removal of word windows that occur earlier in the corpus, by super-k-mer partitioning.

A window is `width` consecutive words of one document.  Its minimiser is the least hash among its
`seed`-word grams; consecutive windows with the same minimiser form a super-k-mer, which travels
once, as one packed run of words, to the bucket of its minimiser.  Equal windows have equal
minimisers, so each bucket can be settled alone: its windows are sorted, and every window whose
words also start at a smaller (document, position) is reported.

Before anything is sent, a map chunk reports super-k-mers that it has already met and sends only
the first of them, so a passage that a third of all documents share reaches its bucket once per
chunk instead of once per document.  Hashes only order and group; words decide equality.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import checkpointed, dealt, numbered

#: Text that is turned into super-k-mers at a time, and text whose super-k-mers share a bucket.
CHUNK_BYTES, BUCKET_BYTES = 12 << 20, 8 << 20
#: Text, words and runs that are hashed or compared at a time.
PIECE_BYTES, PIECE_WORDS, RUNS = 1 << 20, 1 << 15, 1 << 14
ROOT = np.uint64(0x9E3779B97F4A7C15)  # odd, so powers of it can be undone modulo 2^64
UNROOT = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
#: Set in the order of frequent grams.
LATE = np.uint64(1 << 63)
#: A gram is frequent from so many occurrences on; at most so many grams are (eight bytes each, broadcast).
FREQUENT_FROM, MOST_FREQUENT = 10_000, 1 << 20


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit integers."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


#: What a byte counts for in the hash of a word.
BYTES = mixed(np.arange(1, 257, dtype=np.uint64) * ROOT)


def run_hash(values: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hashes of values[begin:end], each from two prefix sums."""
    n = len(values)
    up = np.multiply.accumulate(np.full(n + 1, ROOT)) if n else np.array([ROOT])
    down = np.multiply.accumulate(np.full(n + 1, UNROOT))
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(values * up[:n], dtype=np.uint64)])
    return mixed((sums[end] - sums[begin]) * down[begin])


def run_hashes(values: np.ndarray, begin: np.ndarray, end: np.ndarray, made=lambda v: v) -> np.ndarray:
    """run_hash of made(values) for rising begins and ends, some runs at a time, so that no prefix sums of all values are held."""
    out = np.empty(len(begin), np.uint64)
    for low in range(0, len(begin), RUNS):
        b, e = begin[low : low + RUNS], end[low : low + RUNS]
        out[low : low + RUNS] = run_hash(made(values[b[0] : e[-1]]), b - b[0], e - b[0])
    return out


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    step, out = 1, x
    while step * 2 <= width:
        out = np.minimum(out[: len(out) - step], out[step:])
        step *= 2
    rest = width - step
    return np.minimum(out[: len(out) - rest], out[rest:]) if rest else out


def spread(begin: np.ndarray, count: np.ndarray) -> np.ndarray:
    """begin[0], begin[0]+1, ... count[0] of them, then the same for the next."""
    ends = np.cumsum(count)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(begin - (ends - count), count)


def merged(doc: np.ndarray, start: np.ndarray, stop: np.ndarray) -> pd.DataFrame:
    """Spans joined where they touch; they come ordered by (doc, start)."""
    if not len(doc):
        return pd.DataFrame({"doc_id": doc, "start": start, "stop": stop})
    offset = np.cumsum(np.concatenate([[0], doc[1:] != doc[:-1]])) * np.int64(1 << 40)
    reach = np.maximum.accumulate(stop + offset)
    first = np.flatnonzero(np.concatenate([[True], (start + offset)[1:] > reach[:-1]]))
    last = np.concatenate([first[1:], [len(doc)]]) - 1
    return pd.DataFrame({"doc_id": doc[first], "start": start[first], "stop": reach[last] - offset[last]})


def packed_blob(doc, start, size, ids, words: Words) -> bytes:
    """Super-k-mers of one bucket: heads, a dictionary of their words, and the words as its entries."""
    used, local, often = np.unique(ids, return_inverse=True, return_counts=True)
    by_use = np.argsort(-often, kind="stable")  # small entries for frequent words, which compress
    rank = np.empty(len(used), np.int64)
    rank[by_use] = np.arange(len(used))
    text = words.joined(used[by_use])
    planes = 2 if len(used) < 1 << 16 else 4
    local = rank[local].astype(f"<u{planes}").view(np.uint8).reshape(-1, planes).T
    head = np.array([len(doc), len(used), len(text), planes], "<i8")
    body = b"".join([head.tobytes(), np.diff(doc, prepend=0).astype("<i8").tobytes(), start.astype("<i4").tobytes(), size.astype("<i4").tobytes(), text, local.tobytes()])
    return zstandard.ZstdCompressor(level=5).compress(body)


def unpacked_blob(blob: bytes):
    body = zstandard.ZstdDecompressor().decompress(blob)
    n, _, length, planes = np.frombuffer(body, "<i8", 4).tolist()
    at = 32
    doc = np.cumsum(np.frombuffer(body, "<i8", n, at))
    start = np.frombuffer(body, "<i4", n, at := at + 8 * n)
    size = np.frombuffer(body, "<i4", n, at := at + 4 * n)
    words = body[(at := at + 4 * n) : (at := at + length)].split(b" ")
    local = np.frombuffer(body, np.uint8, -1, at).reshape(planes, -1).T.copy().view(f"<u{planes}")[:, 0]
    return doc, start.astype(np.int64), size.astype(np.int64), words, local


def word_edges(b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where the words of a text begin and end, in order."""
    gap = np.ones(len(b) + 2, bool)
    gap[1:-1] = (b == 32) | (b - np.uint8(9) < 5)
    edges = np.flatnonzero(gap[1:] != gap[:-1])
    return edges[::2], edges[1::2]


def word_hashes(text: bytes) -> np.ndarray:
    """A hash of each word of a text, in order, without a Python object for any."""
    b = np.frombuffer(text, np.uint8)
    return run_hashes(b, *word_edges(b), BYTES.__getitem__)


def gram_hashes(value: np.ndarray, seed: int) -> np.ndarray:
    """Hashes below 2^63 of the `seed` words from each on, across the borders of texts."""
    out = np.empty(max(0, len(value) - seed + 1), np.uint64)
    for low in range(0, len(out), PIECE_WORDS):
        high = min(len(out), low + PIECE_WORDS)
        gram = value[low:high]
        for k in range(1, seed):
            gram = mixed(gram * ROOT + value[low + k : high + k])
        out[low:high] = gram & ~LATE
    return out


class Words:
    """Texts as arrays, without a Python object for any word: each word's place in `body`, its length, hash (value)
    and number (flat), one word of each number (first), and how many words each text has.

    Texts of fewer than `at_least` words are left out.  Words of one hash get one number after their bytes were compared.
    """

    def __init__(self, texts: list[bytes], at_least: int):
        text_end = np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)) + 1)
        joined = b" ".join([*texts, b""])
        self.body = np.frombuffer(joined, np.uint8)
        place = np.int32 if len(joined) < 1 << 31 else np.int64
        at, length, value, low = [], [], [], 0
        while low < len(joined):
            high = int(text_end[min(len(texts) - 1, np.searchsorted(text_end, low + PIECE_BYTES))])
            begin, end = word_edges(self.body[low:high])
            value.append(run_hashes(self.body[low:high], begin, end, BYTES.__getitem__))
            at.append((begin + low).astype(place))
            length.append((end - begin).astype(place))
            low = high
        at, length, value = (np.concatenate([np.zeros(0, t), *x]) for t, x in ((place, at), (place, length), (np.uint64, value)))
        sizes = np.diff(np.searchsorted(at, text_end), prepend=0)
        self.enough = sizes >= at_least
        self.sizes = sizes[self.enough]
        if not self.enough.all():
            held = np.repeat(self.enough, sizes)
            at, length, value = at[held], length[held], value[held]
        self.at, self.length, self.value = at, length, value
        order = np.argsort(value)
        opens = np.ones(len(order), bool)
        by_value = value[order]
        opens[1:] = by_value[1:] != by_value[:-1]
        del by_value
        self.first = order[opens]
        self.flat = np.empty(len(order), np.int32)
        self.flat[order] = np.cumsum(opens, dtype=np.int32) - 1
        del order, opens
        self._settle()

    def _settle(self) -> None:
        """Words that only share the hash of their number's first word get numbers of their own."""
        odd = []
        for low in range(0, len(self.at), PIECE_WORDS):
            here = np.arange(low, min(len(self.at), low + PIECE_WORDS))
            lead = self.first[self.flat[here]]
            here, lead = here[here != lead], lead[here != lead]
            alike = self.length[here] == self.length[lead]
            odd.append(here[~alike])
            here, lead = here[alike], lead[alike]
            length = self.length[here]
            unlike = np.flatnonzero(self.body[spread(self.at[here], length)] != self.body[spread(self.at[lead], length)])
            if len(unlike):
                odd.append(np.unique(here[np.searchsorted(np.cumsum(length), unlike, "right")]))
        odd = np.concatenate([*odd, np.zeros(0, np.int64)])
        if len(odd):
            met: dict[bytes, int] = {}
            firsts = self.first.tolist()
            for i in odd.tolist():
                number = met.setdefault(self.body[self.at[i] : self.at[i] + self.length[i]].tobytes(), len(firsts))
                if number == len(firsts):
                    firsts.append(i)
                self.flat[i] = number
            self.first = np.array(firsts)

    def joined(self, numbers: np.ndarray) -> bytes:
        """The words of these numbers, with a space between."""
        i = self.first[numbers]
        length = self.length[i] + 1  # there is a gap behind each word
        out = self.body[spread(self.at[i], length)]
        out[np.cumsum(length) - 1] = 32
        return out[:-1].tobytes()


def chunk_rows(ids: list[int], texts: list[bytes], width: int, seed: int, buckets: int, frequent: np.ndarray) -> Iterator[tuple]:
    """What a chunk sends: (bucket, spans found here or None, packed super-k-mers or None)."""
    order = sorted(range(len(ids)), key=ids.__getitem__)
    read = Words([texts[i] for i in order], width)
    if not read.enough.any():
        return
    owner = np.array([ids[i] for i in order], np.int64)[read.enough]
    flat, value, sizes = read.flat, read.value, read.sizes
    gram = gram_hashes(value, seed)
    if len(frequent):
        at = np.minimum(np.searchsorted(frequent, gram), len(frequent) - 1)
        gram[frequent[at] == gram] |= LATE
    least = sliding_min(gram, width - seed + 1)  # of the window that starts here
    ends = np.cumsum(sizes)
    del gram
    window = np.zeros(len(least) + 1, np.int8)  # does one start here?
    window[ends - sizes] += 1
    window[ends - width + 1] -= 1
    window = np.cumsum(window, dtype=np.int8)[:-1].view(bool)
    opens = window.copy()
    opens[1:] &= ~window[:-1] | (least[1:] != least[:-1])
    begin = np.flatnonzero(opens)
    least = least[begin]
    before = np.cumsum(window, dtype=np.int64 if len(window) >= 1 << 31 else np.int32)
    count = np.diff(before[begin] - 1, append=before[-1])
    del window, opens, before
    size = count + width - 1
    which = np.searchsorted(ends, begin, "right")
    doc, start = owner[which], begin - (ends - sizes)[which]
    _, first, same = np.unique(run_hashes(value, begin, begin + size), return_index=True, return_inverse=True)
    earliest = first[same]  # np.unique gives the first in (doc, start) order
    again = np.flatnonzero(earliest != np.arange(len(begin)))
    equal = [size[a] == size[b] and np.array_equal(flat[begin[a] : begin[a] + size[a]], flat[begin[b] : begin[b] + size[b]]) for a, b in zip(again, earliest[again], strict=True)]
    again = again[np.array(equal, bool)] if len(again) else again
    send = np.ones(len(begin), bool)
    send[again] = False
    later = again[(doc[again] != doc[earliest[again]]) | (start[again] != start[earliest[again]])]
    if len(later):
        found = merged(doc[later], start[later], start[later] + size[later])
        yield int(doc[later[0]]) % buckets, zstandard.compress(found.to_numpy("<i8").tobytes()), None
    bucket = (mixed(least) % np.uint64(buckets)).astype(np.int64)
    sent = np.flatnonzero(send)
    sent = sent[np.argsort(bucket[sent], kind="stable")]
    for here in np.split(sent, np.flatnonzero(np.diff(bucket[sent])) + 1):
        yield int(bucket[here[0]]), None, packed_blob(doc[here], start[here], size[here], flat[spread(begin[here], size[here])], read)


def bucket_spans(blobs: list[bytes], width: int) -> pd.DataFrame:
    """Spans of all windows of a bucket that also start earlier."""
    known: dict[bytes, int] = {}
    parts = []
    for blob in blobs:
        doc, start, size, words, local = unpacked_blob(blob)
        table = np.fromiter((known.setdefault(w, len(known)) for w in words), np.int32, len(words))
        parts.append((doc, start, size, table[local]))
    doc, start, size, flat = (np.concatenate(x) for x in zip(*parts, strict=True))
    del parts, known
    begin = np.cumsum(size) - size
    order = np.lexsort((start, doc))
    doc, start, size, begin = doc[order], start[order], size[order], begin[order]
    flat = np.concatenate([flat[spread(begin[low : low + RUNS], size[low : low + RUNS])] for low in range(0, len(begin), RUNS)])
    begin = np.cumsum(size) - size
    count = size - width + 1
    at = spread(begin, count)
    which = np.repeat(np.arange(len(doc)), count)
    place = at - begin[which] + start[which]
    key = run_hashes(flat, at, at + width, lambda v: mixed(v.astype(np.uint64) + ROOT))
    by_key = np.argsort(key, kind="stable")
    opens = np.concatenate([[True], key[by_key][1:] != key[by_key][:-1]])
    lead = by_key[np.flatnonzero(opens)[np.cumsum(opens) - 1]]
    dup = ~opens
    late, lead = by_key[dup], lead[dup]
    equal = np.ones(len(late), bool)
    for k in range(width):
        equal &= flat[at[late] + k] == flat[at[lead] + k]
    if not equal.all():  # different windows of one hash: settle those by their words
        met: dict[bytes, int] = {}
        for i in np.unique(np.concatenate([lead[~equal], late[np.isin(key[late], key[late[~equal]])]])).tolist():
            met.setdefault(flat[at[i] : at[i] + width].tobytes(), i)
        lead = np.array([met.get(flat[at[i] : at[i] + width].tobytes(), j) for i, j in zip(late.tolist(), lead.tolist(), strict=True)])
    late = late[(doc[which[late]] != doc[which[lead]]) | (place[late] != place[lead])]
    late.sort()  # windows were laid out by (doc, start)
    return merged(doc[which[late]], place[late], place[late] + width)


def frequent_grams(rows: DataFrame, total: int, seed: int, frequent_from: int = FREQUENT_FROM) -> np.ndarray:
    """Sorted hashes of the grams that occur `frequent_from` times or more in all texts, `total` bytes of them.

    Every text is counted, chunk by chunk; a chunk leaves out what it has fewer than `least` times, so some
    grams that occur less often are found as well, by up to least - 1 for each chunk.
    """
    least = max(2, int(frequent_from / (4 * (total / CHUNK_BYTES + 64))))

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        found, texts, held, counted = [], [], 0, 0

        def grams() -> np.ndarray:
            return gram_hashes(word_hashes(b" ".join(texts)), seed)

        def out() -> pd.DataFrame:
            gram, n = np.unique(np.concatenate([*found, grams()]), return_counts=True)
            often = n >= least
            return pd.DataFrame({"gram": np.append(gram[often].view(np.int64), -1), "n": np.append(n[often], 1)})

        for batch in batches:
            for t in batch["text"]:
                if t:
                    texts.append(t.encode())
                    held += len(texts[-1])
                if held >= PIECE_BYTES:
                    found.append(grams())
                    counted, texts, held = counted + held, [], 0
                if counted >= CHUNK_BYTES:
                    yield out()
                    found, counted = [], 0
        yield out()

    sums = rows.select("text").mapInPandas(count, "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n"))
    sums = checkpointed(sums)  # read twice, counted once
    chunks = sums.where("gram = -1").select(F.col("n").alias("chunks"))
    found = sums.where("gram <> -1").crossJoin(F.broadcast(chunks)).where(F.col("n") >= frequent_from - F.col("chunks") * (least - 1))
    found = found.orderBy(F.desc("n"), "gram").limit(MOST_FREQUENT)
    return np.sort(found.select("gram").toPandas()["gram"].to_numpy("int64").view(np.uint64))


def repeated_spans(rows: DataFrame, width: int = 20, seed: int = 3, buckets: int | None = None, frequent_from: int = FREQUENT_FROM) -> DataFrame:
    """Rows (node, start, stop): words [start, stop) are covered by windows that start earlier elsewhere.

    `rows` has a number `node` for each document, in their order, and its text.  Null and short
    texts have no window.  Rows with one node are copies of one document, so they don't repeat
    themselves.
    """
    total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    if buckets is None:
        buckets = max(8, math.ceil(total / BUCKET_BYTES))
    frequent = rows.sparkSession.sparkContext.broadcast(frequent_grams(rows, total, seed, frequent_from))

    def send(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ids, texts, held = [], [], 0

        def out() -> pd.DataFrame:
            return pd.DataFrame(list(chunk_rows(ids, texts, width, seed, buckets, frequent.value)), columns=["bucket", "spans", "runs"])

        for batch in batches:
            for i, t in zip(batch["node"].tolist(), batch["text"], strict=True):
                if t:
                    ids.append(i)
                    texts.append(t.encode())
                    held += len(texts[-1])
                if held >= CHUNK_BYTES:
                    yield out()
                    ids, texts, held = [], [], 0
        yield out()

    def settle(group: pd.DataFrame) -> pd.DataFrame:
        found = [np.frombuffer(zstandard.decompress(x), "<i8").reshape(-1, 3) for x in group["spans"] if x is not None]
        out = [pd.DataFrame(x, columns=["doc_id", "start", "stop"]) for x in found]
        if runs := [x for x in group["runs"] if x is not None]:
            out.append(bucket_spans(runs, width))
        return pd.concat(out).astype("int64").rename(columns={"doc_id": "node"})

    sent = rows.select("node", "text").mapInPandas(send, "bucket long, spans binary, runs binary")
    return dealt(sent, "bucket", buckets).applyInPandas(settle, "node long, start long, stop long")


def without_repeats(docs: DataFrame, width: int = 20, seed: int = 3, buckets: int | None = None, frequent_from: int = FREQUENT_FROM) -> DataFrame:
    """doc_id, n_words, n_removed, kept: the kept words joined by one space, for each row of docs.

    Rows of equal doc_id and text are one document; rows of one doc_id and different texts are
    different documents, in the order of their texts' hashes.  A null doc_id comes before all others.
    Extra columns are ignored.
    """
    rows, _, _ = numbered(docs)
    spans = repeated_spans(rows, width, seed, buckets, frequent_from).groupBy("node").agg(F.collect_list(F.struct("start", "stop")).alias("spans"))

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for low in range(0, len(batch), 512):
                out = []
                part = batch.iloc[low : low + 512]
                for text, found in zip(part["text"], part["spans"], strict=True):
                    words, removed = (text or "").encode().split(), 0
                    if found is not None and len(found):
                        gone = np.zeros(len(words) + 1, bool)
                        for s in found:
                            gone[s["start"] : s["stop"]] = True
                        removed = int(gone[: len(words)].sum())
                        kept = list(itertools.compress(words, (~gone[: len(words)]).tolist()))
                    else:
                        kept = words
                    out.append((len(words), removed, b" ".join(kept).decode()))
                frame = pd.DataFrame(out, columns=["n_words", "n_removed", "kept"])
                frame.insert(0, "doc_id", part["doc_id"].astype("Int64").to_numpy())
                yield frame

    return rows.join(spans, "node", "left").select("doc_id", "text", "spans").mapInPandas(cut, "doc_id long, n_words long, n_removed long, kept string")
