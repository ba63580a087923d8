"""Toxicity scores by non-negative positive-unlabelled learning.

A linear model in numpy is trained from texts confirmed as toxic and from all texts as unlabelled ones.
With pi the share of toxic texts among all, the risk of calling unlabelled texts harmless is
corrected by what toxic ones among them are expected to add; where that estimate falls below zero,
the step goes back over the unlabelled part instead of overfitting it:

    risk = pi E_P[l(z)] + max(0, E_U[l(-z)] - pi E_P[l(-z)]),  l(z) = log(1 + exp(-z))

Features are the distinct words of a text, in lower case, their beginnings, and beginnings that two
or three of its words share; only those are kept that mark toxic texts: by the class prior, more than half
of all texts that hold them must be toxic.  Confirmed toxic texts are a bounded
sample (`positives`: the rows with the least hashes of doc_id).  Everything on the unlabelled side is
taken over all documents that may be learnt from: how many hold each feature, and E_U and its slope in
every step.  For that, texts are reduced once to the kept features they hold, equal reductions become
one row with their number, and each step sums its part of the gradient where those rows are.
"""

from __future__ import annotations

import itertools
import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import checkpointed

POSITIVES = 4000
STEMS = range(4, 9)
#: Features of toxic texts that are counted over all documents, and features of the model, at most.
MAX_CANDIDATES, MAX_FEATURES = 1 << 17, 4096
#: Toxic texts that a feature must be in.
LEAST_TEXTS = 3
STEPS, RATE, DECAY = 80, 0.5, 3e-4
#: Least estimated share of toxic texts among those that hold a feature, and how far apart its shares are, in deviations.
PURITY, STRENGTH = 0.55, 4
#: Blocks of reduced texts (up to an Arrow batch each) in a task of a step.
STEP_BLOCKS = 4
TOKEN = re.compile(r"\w+")


def tokens(text: str) -> set[str]:
    return set(TOKEN.findall(text.lower()))


def features(word: str) -> list[str]:
    """The word, and its beginnings marked with a trailing *."""
    return [word, *[word[:k] + "*" for k in STEMS if len(word) >= k]]


def held(words: set[str], stems_of) -> set[str]:
    """All features of a text: those of its words, and f2, f3 for a beginning f* of two, three or more of them."""
    often = Counter(itertools.chain.from_iterable(map(stems_of, words)))
    return set(often).union(f"{f}{k}" for f, n in often.items() if n > 1 for k in (2, 3) if n >= k)


class Reduced:
    """Reduced texts as sparse rows of ones, with how many confirmed and how many unlabelled texts each stands for."""

    def __init__(self, rows: np.ndarray, cols: np.ndarray, n_p: np.ndarray, n_u: np.ndarray):
        self.rows, self.cols, self.n_p, self.n_u = rows, cols, n_p, n_u

    @staticmethod
    def packed(cols: list, n_p, n_u) -> dict[str, list[bytes]]:
        count = [len(c) for c in cols]
        flat = np.fromiter(itertools.chain.from_iterable(cols), np.int64, sum(count))
        return {"rows": [np.repeat(np.arange(len(cols)), count).tobytes()], "cols": [flat.tobytes()], "n_p": [np.asarray(n_p, float).tobytes()], "n_u": [np.asarray(n_u, float).tobytes()]}

    @classmethod
    def unpacked(cls, rows: bytes, cols: bytes, n_p: bytes, n_u: bytes) -> Reduced:
        return cls(np.frombuffer(rows, np.int64), np.frombuffer(cols, np.int64), np.frombuffer(n_p), np.frombuffer(n_u))

    def sums(self, theta: np.ndarray) -> np.ndarray:
        """One flat array: sums of l(z) over confirmed texts, of l(-z) over confirmed and over unlabelled ones, then their gradients."""
        width = len(theta) - 1
        z = np.bincount(self.rows, theta[self.cols], len(self.n_p)) + theta[width]
        soft, up = np.logaddexp(0, z), 1 / (1 + np.exp(-np.clip(z, -500, 500)))  # l(-z) and its slope

        def gradient(g: np.ndarray) -> np.ndarray:
            return np.append(np.bincount(self.cols, g[self.rows], width), g.sum())

        risks = [self.n_p @ (soft - z), self.n_p @ soft, self.n_u @ soft]
        return np.concatenate([risks, gradient(self.n_p * (up - 1)), gradient(self.n_p * up), gradient(self.n_u * up)])


def risk_step(sums: np.ndarray, n_p: float, n_u: float, prior: float) -> tuple[float, np.ndarray]:
    """The estimated risk, and the direction of its step: downhill, or back over the harmless part where that is below zero."""
    risks, (toxic, excess, harmless) = sums[:3], sums[3:].reshape(3, -1)
    rest = risks[2] / n_u - prior * risks[1] / n_p
    slope = harmless / n_u - prior * excess / n_p
    if rest >= 0:
        return prior * risks[0] / n_p + rest, prior * toxic / n_p + slope
    return prior * risks[0] / n_p, -slope


def nn_pu(sums_at, width: int, n_p: float, n_u: float, prior: float, steps: int = STEPS, rate: float = RATE, decay: float = DECAY) -> np.ndarray:
    """Weights, then bias, by Adam on the non-negative PU risk; sums_at(theta) gives Reduced.sums over all rows."""
    theta, m, v = (np.zeros(width + 1) for _ in range(3))
    theta[width] = math.log(prior / (1 - prior))
    for step in range(1, steps + 1):
        _, grad = risk_step(sums_at(theta), n_p, n_u, prior)
        grad[:width] += decay * theta[:width]
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad * grad
        slower = rate * (1 - 0.9 * step / steps)
        theta = theta - slower * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return theta


def held_out(doc_id: Column) -> Column:
    """Rows that training must not see: a third, by crc32 of the id as text."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


class Stems(dict):
    """Word to those of its features that can matter; most words have none.  It forgets when it has grown large."""

    def __init__(self, wanted: set[str] | None):
        self.wanted = wanted

    def __missing__(self, word: str) -> tuple[str, ...]:
        self[word] = out = tuple(f for f in features(word) if self.wanted is None or f in self.wanted)
        return out

    def rest(self) -> None:
        if len(self) > 1_000_000:
            self.clear()


def base_names(names) -> set[str]:
    """The features f of words that names need, with f2 and f3 by f."""
    return {n[:-1] if n[-2:-1] == "*" else n for n in names}


def _feature_counts(texts: DataFrame, among: set[str] | None) -> DataFrame:
    """(feature, texts): how many rows hold each feature, or each of `among`; summed in the task first."""
    wanted = None if among is None else texts.sparkSession.sparkContext.broadcast(among)

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        stems = Stems(None if wanted is None else base_names(wanted.value))
        often: Counter[str] = Counter()

        def out() -> pd.DataFrame:
            kept = often if wanted is None else {f: n for f, n in often.items() if f in wanted.value}
            return pd.DataFrame({"feature": pd.Series(list(kept), dtype=object), "texts": pd.Series(list(kept.values()), dtype="int64")})

        for b in batches:
            for text in b["text"]:
                often.update(held(tokens(text or ""), stems.__getitem__))
            stems.rest()
            if len(often) > 1_000_000:
                yield out()
                often.clear()
        yield out()

    return texts.select("text").mapInPandas(count, "feature string, texts long").groupBy("feature").agg(F.sum("texts").alias("texts"))


def _reduced(texts: DataFrame, number: dict[str, int]) -> DataFrame:
    """(cols, n_p, n_u): equal reductions of (text, positive) rows, with the numbers of confirmed and unlabelled ones."""
    wanted = texts.sparkSession.sparkContext.broadcast(number)

    def reduce(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        place = wanted.value
        stems = Stems(base_names(place))
        for b in batches:
            out: Counter[tuple] = Counter()
            for text, p in zip(b["text"], b["positive"], strict=True):
                out[tuple(sorted(place[f] for f in held(tokens(text or ""), stems.__getitem__) if f in place)), bool(p)] += 1
            stems.rest()
            yield pd.DataFrame([(list(k), n * p, n * (not p)) for (k, p), n in out.items()], columns=["cols", "n_p", "n_u"])

    flat = texts.select("text", "positive").mapInPandas(reduce, "cols array<int>, n_p long, n_u long")
    return flat.groupBy("cols").agg(F.sum("n_p").alias("n_p"), F.sum("n_u").alias("n_u"))


def _blocks(rows: DataFrame) -> DataFrame:
    """The reduced rows of each batch as one block of bytes, ready for a step."""

    def pack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame(Reduced.packed(b["cols"].tolist(), b["n_p"], b["n_u"]))

    return rows.mapInPandas(pack, "rows binary, cols binary, n_p binary, n_u binary")


def train(docs: DataFrame, labels: DataFrame, positives: int = POSITIVES, steps: int = STEPS) -> tuple[dict[str, float], float]:
    """Model from the toxic labels (doc_id, toxic) of rows that aren't held out, and from all texts that aren't.

    The class prior is the share of toxic ones among the labelled ids.  Repeated labels count once, an
    id with contradicting labels is toxic, null ids and labels are ignored; repeated rows of an id
    count each among the unlabelled.  Without any positive the model is the prior alone.
    """
    texts = docs.select(F.col("doc_id").cast("long").alias("id"), F.col("text").cast("string").alias("text")).where(F.col("id").isNotNull() & ~held_out(F.col("id")))
    seen = labels.select(F.col("doc_id").cast("long").alias("id"), F.col("toxic").cast("int").alias("toxic")).dropna().where(~held_out(F.col("id")))
    seen = seen.groupBy("id").agg(F.max("toxic").alias("toxic"))
    n, toxic = seen.agg(F.count("*"), F.coalesce(F.sum("toxic"), F.lit(0))).first()
    prior = min(0.5, max(1e-3, toxic / n if n else 1e-3))
    bias = math.log(prior / (1 - prior))
    order = F.xxhash64(F.lit("sample"), "id")
    known = seen.where("toxic = 1").select("id").orderBy(order, "id").limit(positives)  # at most `positives` ids
    confirmed = checkpointed(texts.join(F.broadcast(known), "id").groupBy("id").agg(F.min("text").alias("text")))
    n_p, n_u = confirmed.count(), texts.count()
    if not n_p:
        return {}, bias
    often = _feature_counts(confirmed, None).where(F.col("texts") >= LEAST_TEXTS).orderBy(F.desc("texts"), "feature").limit(MAX_CANDIDATES)
    in_p = {r["feature"]: r["texts"] for r in often.collect()}
    if not in_p:
        return {}, bias
    names = sorted(in_p)
    in_u = {r["feature"]: r["texts"] for r in _feature_counts(texts, set(in_p)).collect()}  # as many as candidates
    a, b = (np.array([x.get(f, 0) for f in names], float) for x in (in_p, in_u))
    number = {names[f]: k for k, f in enumerate(telling_features(a, b, n_p, n_u, prior).tolist())}
    if not number:
        return {}, bias
    both = confirmed.select("text", F.lit(True).alias("positive")).unionByName(texts.select("text", F.lit(False).alias("positive")))
    blocks = checkpointed(_blocks(_reduced(both, number)))
    blocks = blocks.coalesce(max(1, math.ceil(blocks.count() / STEP_BLOCKS)))

    def sums_at(theta: np.ndarray) -> np.ndarray:
        def part(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            total = np.zeros(3 + 3 * len(theta))
            for b in batches:
                for row in b.itertuples(index=False):
                    total += Reduced.unpacked(row.rows, row.cols, row.n_p, row.n_u).sums(theta)
            yield pd.DataFrame({"sums": [total.tobytes()]})

        # one row for each task
        return sum((np.frombuffer(r["sums"]) for r in blocks.mapInPandas(part, "sums binary").collect()), np.zeros(3 + 3 * len(theta)))

    theta = nn_pu(sums_at, len(number), n_p, n_u, prior, steps)
    return {f: float(theta[k]) for f, k in number.items() if theta[k] != 0}, float(theta[-1])


def telling_features(in_p: np.ndarray, in_u: np.ndarray, n_p: int, n_u: int, prior: float) -> np.ndarray:
    """Indexes of the features that mark toxic texts, from the numbers of confirmed and unlabelled texts that hold them."""
    purity = prior * ((in_p + 0.1) / n_p) / ((in_u + 1) / n_u)
    # distance of the two shares, in standard deviations
    both = (in_p + in_u + 1) / (n_p + n_u)
    strength = (in_p / n_p - in_u / n_u) / np.sqrt(both * (1 - np.minimum(both, 0.999)) * (1 / n_p + 1 / n_u))
    good = np.flatnonzero((purity >= PURITY) & (strength >= STRENGTH))
    return good[np.argsort(-strength[good], kind="stable")][:MAX_FEATURES]


def scored(docs: DataFrame, model: tuple[dict[str, float], float]) -> DataFrame:
    """(doc_id, score) for each row of docs; a null or empty text gets the score of no feature at all."""
    weights, bias = model
    named = docs.sparkSession.sparkContext.broadcast(weights)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        weight = named.value
        stems = Stems(base_names(weight))

        class Told(dict):
            def __missing__(self, chunk: str) -> tuple[str, ...]:
                """The words with a feature in a stretch without white space; mostly none."""
                self[chunk] = out = tuple(w for w in TOKEN.findall(chunk) if stems[w])
                return out

        told = Told()
        for b in batches:
            out = []
            for text in b["text"]:
                words = set().union(*map(told.__getitem__, set((text or "").lower().split())))
                z = bias + (math.fsum(weight[f] for f in held(words, stems.__getitem__) if f in weight) if words else 0.0)
                out.append(1 / (1 + math.exp(-max(-50.0, min(50.0, z)))))
            stems.rest()
            if len(told) > 1_000_000:
                told.clear()
            yield pd.DataFrame({"doc_id": b["doc_id"].astype("Int64"), "score": out})

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInPandas(run, "doc_id long, score double")
