"""Best-two-fit packing of tokenised documents into fixed-length training sequences.

Documents are tokenised, closed with a separator id and, only when longer than a sequence, cut
into full-length pieces plus one remainder.  Pieces are then packed in independent groups of
thousands: a group loses at most its last, partly filled sequence, so grouping costs
well under one sequence in a thousand and needs no global state.  Within a group only the
histogram of lengths matters (at most `capacity` distinct values), so the packer works on counts
and its memory does not depend on how often a length occurs.
"""

from __future__ import annotations

import functools
import itertools
import math
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Pieces that are packed together, without and with their ids (up to 64 MB of them).
GROUP_PIECES, GROUP_PIECES_WITH_IDS = 65_536, 8192
#: Distinct words whose ids a worker remembers; beyond it those of one batch only are forgotten.
MEMO_WORDS = 500_000

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, salt__ long"


class WordMemo:
    """Token ids of whole texts, with the ids of each chunk between ASCII white space remembered.

    Valid for tokenizers whose pre-tokenizer never joins characters across white space and drops
    white space itself; `word_bpe_49k.json` is one.  Chunks that could hold part of a special
    token's string need no care: those strings have no white space.
    """

    MARK = "~"

    def __init__(self, path: str, limit: int = MEMO_WORDS):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.limit = limit
        self.clear()

    def clear(self) -> None:
        self.index: dict[bytes, int] = {}
        self.lengths, self.begins, self.used = np.zeros(1 << 16, np.int64), np.zeros(1 << 16, np.int64), 0
        self.flat = np.zeros(1 << 18, np.uint32)
        self.met = np.zeros(1 << 16, np.int32)

    def _forget(self) -> None:
        """Keep the words of two or more batches since the last time; all go if they are too many themselves."""
        words = list(self.index)
        keep = np.flatnonzero(self.met[: len(words)] > 1)
        if 2 * len(keep) > self.limit:
            return self.clear()
        lengths, begins, flat = self.lengths[keep], self.begins[keep], self.flat
        self.clear()
        ends = np.cumsum(lengths)
        ids = flat[np.arange(ends[-1] if len(ends) else 0) + np.repeat(begins - (ends - lengths), lengths)]
        self._store([words[i] for i in keep.tolist()], lengths, ids)

    def _tokens(self, new: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """How many ids each chunk has, and all ids; many chunks go in one text, each closed by a
        mark that is one token of its own."""
        mark = self.tokenizer.encode(self.MARK, add_special_tokens=False).ids
        ends = f" {self.MARK} ".encode()
        texts = [(ends.join(new[i : i + 200]) + ends).decode() for i in range(0, len(new), 200)]
        got = [e.ids for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
        ids = np.fromiter(itertools.chain.from_iterable(got), np.uint32, sum(map(len, got)))
        closes = np.flatnonzero(ids == mark[0])
        if len(mark) > 1 or len(closes) != len(new):
            raise ValueError(f"{self.MARK!r} is no token of its own in this tokenizer")
        return np.diff(closes, prepend=-1) - 1, np.delete(ids, closes)

    def _learn(self, new: list[bytes]) -> None:
        marked = [w for w in new if self.MARK.encode() in w]
        if marked:  # these can't be told apart by it
            new = [w for w in new if self.MARK.encode() not in w]
        lengths, flat = self._tokens(new) if new else (np.zeros(0, np.int64), np.zeros(0, np.uint32))
        if marked:
            got = [e.ids for e in self.tokenizer.encode_batch_fast([w.decode() for w in marked], add_special_tokens=False)]
            new, lengths = new + marked, np.append(lengths, [len(x) for x in got])
            flat = np.append(flat, np.fromiter(itertools.chain.from_iterable(got), np.uint32))
        self._store(new, lengths, flat)

    def _store(self, new: list[bytes], lengths: np.ndarray, flat: np.ndarray) -> None:
        have, end = len(self.index), self.used + len(flat)
        self.index.update(zip(new, range(have, have + len(new)), strict=True))
        while len(self.lengths) < len(self.index):
            self.lengths, self.begins, self.met = (np.concatenate([x, np.zeros_like(x)]) for x in (self.lengths, self.begins, self.met))
        while len(self.flat) < end:
            self.flat = np.concatenate([self.flat, np.zeros_like(self.flat)])
        self.lengths[have : len(self.index)] = lengths
        self.begins[have : len(self.index)] = self.used + np.cumsum(lengths) - lengths
        self.flat[self.used : end] = flat
        self.used = end

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        if len(self.index) > self.limit:
            self._forget()
        split = [t.encode().split() for t in texts]
        chunks = list(itertools.chain.from_iterable(split))
        at = np.fromiter(map(self.index.get, chunks, itertools.repeat(-1)), np.int64, len(chunks))
        missing = np.flatnonzero(at < 0).tolist()
        if missing:
            self._learn(list(dict.fromkeys([chunks[i] for i in missing])))
            at[missing] = [self.index[chunks[i]] for i in missing]
        self.met[at] += 1  # once for each batch that has the word
        lengths = self.lengths[at]
        ends = np.concatenate([[0], np.cumsum(lengths)])
        ids = self.flat[np.arange(ends[-1]) + np.repeat(self.begins[at] - ends[:-1], lengths)]
        bounds = ends[np.cumsum([0, *map(len, split)])]
        return [ids[a:b] for a, b in itertools.pairwise(bounds)]


@functools.cache
def memo_of(path: str, limit: int) -> WordMemo:
    """One memory for each Python worker, kept from task to task; about 180 bytes a word."""
    return WordMemo(path, limit)


def tokenised(docs: DataFrame, path: str, capacity: int = 2048, separator: int = 0, with_ids: bool = False, memo_words: int = MEMO_WORDS) -> DataFrame:
    """One row for each piece of each document; `with_ids` adds the piece's ids.

    A null or empty text yields the separator alone, repeated rows are kept as they are, and extra
    columns are ignored.  salt__ numbers the rows of a task, so that rows of one id can be dealt apart.
    """

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        memo = memo_of(path, memo_words)
        task, met = TaskContext.get().partitionId(), 0
        for batch in batches:
            for low in range(0, len(batch), 256):
                part, rows = batch.iloc[low : low + 256], []
                for doc_id, ids in zip(part["doc_id"], memo.encode([t or "" for t in part["text"]]), strict=True):
                    ids = np.append(ids, np.uint32(separator)).astype("<u4")
                    for piece, start in enumerate(range(0, len(ids), capacity)):
                        cut = ids[start : start + capacity]
                        row = (doc_id, piece, start, len(cut), zlib.crc32(cut.tobytes()), (task << 40) + met)
                        met += 1
                        rows.append((*row, cut.astype(np.int32)) if with_ids else row)
                names = ["doc_id", "piece", "start", "length", "ids_crc32", "salt__"] + ["ids"] * with_ids
                out = pd.DataFrame(rows, columns=names)
                out["doc_id"] = out["doc_id"].astype("Int64")
                yield out

    narrow = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return narrow.mapInPandas(run, PIECES + (", ids array<int>" if with_ids else ""))


def best_two_fit(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of each item.

    A bin takes the largest unpacked item that fits, again and again.  When nothing more fits, its
    smallest item may give way to the two unpacked items that fill the widened gap best, if
    together they are longer than it; this goes on while it helps.
    """
    lengths = np.asarray(lengths, np.int64)
    counts = np.bincount(lengths, minlength=capacity + 1)
    order = np.argsort(lengths, kind="stable")
    ends = np.cumsum(counts)
    following = (ends - counts).copy()  # next item of each length
    sizes = np.arange(capacity + 1)
    # largest available length <= x, for each x
    largest = np.maximum.accumulate(np.where(counts > 0, sizes, 0))
    largest[0] = 0
    bins, offsets = np.empty(len(lengths), np.int64), np.empty(len(lengths), np.int64)

    def change(size: int, by: int) -> None:
        counts[size] += by
        if by < 0 and counts[size] == 0:
            x = size
            below = largest[size - 1]
            stop = size + int(np.searchsorted(largest[size:], size, "right"))
            largest[x:stop] = below
        elif by > 0 and counts[size] == by:
            stop = size + int(np.searchsorted(largest[size:], size, "left"))
            largest[size:stop] = size

    left, number = len(lengths), 0
    while left:
        held: list[int] = []
        gap = capacity
        while gap and (size := int(largest[gap])):
            take = min(int(counts[size]), gap // size)
            held += [size] * take
            change(size, -take)
            gap -= take * size
        while gap and len(held) > 1 and largest[capacity]:
            small = held[-1]
            room = gap + small
            first = np.unique(largest[1 : room])
            first = first[first > 0]
            second = largest[room - first]
            alone = (second == first) & (counts[first] < 2)
            if alone.any():
                second = np.where(alone, largest[first - 1], second)
            total = np.where(second > 0, first + second, 0)
            if not len(total) or (best := int(np.argmax(total))) < 0 or total[best] <= small:
                break
            a, b = int(first[best]), int(second[best])
            held.pop()
            change(a, -1)
            change(b, -1)
            change(small, 1)
            held += sorted((a, b), reverse=True)
            held.sort(reverse=True)
            gap = room - a - b
        offset = 0
        for size in held:
            item = order[following[size]]
            following[size] += 1
            bins[item], offsets[item] = number, offset
            offset += size
        left -= len(held)
        number += 1
    return bins, offsets


def packed(pieces: DataFrame, capacity: int = 2048, groups: int = 1) -> DataFrame:
    """Adds sequence_id and offset to piece rows (doc_id, piece, length, salt__ and any others but these).

    Pieces are dealt to `groups` by a hash of (doc_id, piece, salt__), so neither a repeated nor a null id
    makes a group larger than others; ties and repeated rows are packed like any other.  A sequence's
    number is its group's number times 2^32 plus its rank there.
    """
    deal = F.pmod(F.xxhash64(F.lit("pack"), "doc_id", "piece", "salt__"), F.lit(groups)).cast("int")

    def run(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(["doc_id", "piece", "salt__"], kind="stable")
        bins, offsets = best_two_fit(group["length"].to_numpy(), capacity)
        group["sequence_id"] = group["pack_group__"].astype("int64") * (1 << 32) + bins
        group["offset"] = offsets
        return group.drop(columns=["pack_group__", "salt__"])

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in pieces.schema.fields if f.name != "salt__")
    return pieces.withColumn("pack_group__", deal).groupBy("pack_group__").applyInPandas(run, schema + ", sequence_id long, offset long")


def pack(docs: DataFrame, path: str, capacity: int = 2048, separator: int = 0, with_ids: bool = False, memo_words: int = MEMO_WORDS) -> DataFrame:
    """Tokenise and pack; `with_ids` keeps each piece's ids, so that sequences can be put together.

    The number of groups follows the largest possible number of pieces: a document has one, and one
    more for each `capacity` ids, of which it has no more than bytes.  `memo_words` trades memory of
    the Python workers for time; results don't depend on it.
    """
    rows, size = docs.agg(F.count("*"), F.coalesce(F.sum(F.octet_length(F.col("text").cast("string"))), F.lit(0))).first()
    groups = max(1, math.ceil((rows + size / capacity) / (GROUP_PIECES_WITH_IDS if with_ids else GROUP_PIECES)))
    return packed(tokenised(docs, path, capacity, separator, with_ids, memo_words), capacity, groups)
