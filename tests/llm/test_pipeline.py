import hashlib
import random
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

import corpus_pipeline as P
from exactsum.llm import best_fit, curriculum, jaccard_join, line_quality, pseudonyms
from exactsum.llm.queries import PSEUDONYM_KEY, tokenizer_path
from tests.llm.test_jaccard_join import brute

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def documents():
    rng = random.Random(7)
    vocabulary = [f"w{k}" for k in range(900)]
    boiler = "Buy now and subscribe to our letter today dear reader"
    rows = []
    for i in range(160):
        lines = [" ".join(rng.choice(vocabulary) for _ in range(rng.randint(6, 14))) for _ in range(rng.randint(1, 8))]
        if i % 3 == 0:
            lines.insert(rng.randrange(len(lines)), boiler)
        if i % 9 == 0:
            lines = [boiler.upper(), "some short tail here", boiler, "xx yy zz", boiler][: rng.randint(3, 5)]
        if i % 17 == 0:
            lines += ["card 4315726095712222 and 152.143.123.131"]
        if i % 29 == 0:
            lines = ["ha ha"] * 20
        rows.append((i, "\n".join(lines), "en", ["a", "b", "c", None][i % 4]))
    for i in range(160, 200):
        text = rows[i - 150][1].split(" ")
        if i % 2 and len(text) > 60:
            text[3] = "changed"
        rows.append((i, " ".join(text), "en", "b"))
    rows += [(300, None, None, "a"), (301, "", "en", "c"), (302, "word " * 3000, "en", "c")]
    return [(i, t, lang, s, None if t is None else len(t)) for i, t, lang, s in rows]


def slow_quality(rows, share=0.02, least=3, left=0.3):
    norm = lambda line: " ".join(line.split()).lower()
    texts = defaultdict(set)
    for i, t, _, s, _ in rows:
        if t is not None:
            texts[s].add((i, t))
    often = {}
    for s, ts in texts.items():
        c = Counter(x for _, t in ts for x in {norm(line) for line in t.split("\n") if line.split()})
        often[s] = {x for x, n in c.items() if n > max(least, share * len(ts))}
    out = []
    for i, t, lang, s, _ in rows:
        w = (t or "").split()
        seen = defaultdict(list)
        for k in range(len(w) - 7):
            seen[tuple(w[k : k + 8])].append(k)
        hit = {k + d for ks in seen.values() if len(ks) > 1 for k in ks for d in range(8)}
        if len(w) < 20 or 100 * len(hit) > 30 * len(w):
            continue
        kept = [line for line in t.split("\n") if not line.split() or norm(line) not in often[s]]
        if len(" ".join(kept).split()) > left * len(w):
            out.append((i, "\n".join(kept), lang, s, len("\n".join(kept))))
    return out


def slow_copies(rows):
    """Documents' copies in the mix."""
    size = {i: len((t or "").split()) for i, t, *_ in rows}
    sources = defaultdict(list)
    for i, _, _, s, _ in rows:
        sources[s].append(i)
    names = sorted((s for s in sources if s is not None)) + [None] * (None in sources)
    weight = {s: k % 3 + 1 for k, s in enumerate(names)}
    own = {s: sum(size[i] for i in sources[s]) for s in names}
    left, free, target = sum(own.values()), set(names), {}
    while free:
        level = left / sum(weight[s] for s in free)
        full = {s for s in free if level * weight[s] > 3 * own[s]}
        for s in full or free:
            target[s] = 3 * own[s] if full else level * weight[s]
        left -= sum(target[s] for s in full)
        free = free - full if full else set()
    copies = {}
    for s in names:
        whole = min(3, int(target[s] / own[s])) if own[s] else 0
        at = 0
        for i in sorted(sources[s], key=lambda i: (hashlib.md5(str(i).encode()).hexdigest(), i)):
            copies[i] = whole + (whole < 3 and at + size[i] / 2 < target[s] - whole * own[s])
            at += size[i]
    return copies, target, size


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(documents(), SCHEMA).repartition(3)


def read(df):
    return sorted(map(tuple, df.collect()), key=repr)


def test_stages_against_brute_force(spark, docs, tmp_path):
    def again(df, name):
        df.write.parquet(f"{tmp_path}/{name}")
        return spark.read.parquet(f"{tmp_path}/{name}")

    rows = [tuple(r) for r in docs.collect()]
    one = again(P.quality(spark, docs, ""), "1")
    assert one.columns == docs.columns
    want = slow_quality(rows)
    assert read(one) == sorted(want, key=repr) and 20 < len(want) < len(rows)
    two = again(P.near_duplicates(spark, one, ""), "2")
    keep = {i for i, _, c in brute([(r[0], r[1]) for r in want]) if i == c}
    want = [r for r in want if r[0] in keep]
    assert read(two) == sorted(want, key=repr)
    three = again(P.personal_data(spark, two, ""), "3")
    assert three.columns == docs.columns and three.count() == len(want)
    assert three.where("text like '%4315726095712222%' or text like '%152.143.123.131%'").count() == 0
    rows3 = [tuple(r) for r in three.collect()]
    before = {r[0]: r for r in want}
    assert all(r == before[r[0]] for r in rows3 if "card" not in r[1])
    four = again(P.mixture(spark, three, ""), "4")
    copies, target, size = slow_copies(rows3)
    assert Counter(r.doc_id for r in four.collect()) == Counter({i: n for i, n in copies.items() if n})
    by_source = defaultdict(int)
    for r in rows3:
        by_source[r[3]] += copies[r[0]] * size[r[0]]
    assert all(abs(by_source[s] - t) <= max(size.values()) for s, t in target.items())
    five = P.packing(spark, four, "").collect()
    check_packing(four.collect(), five)


def check_packing(rows, pieces, capacity=2048):
    memo = best_fit.WordMemo(tokenizer_path())
    tokens = {r.doc_id: len(memo.tokenizer.encode(r.text or "", add_special_tokens=False).ids) + 1 for r in rows}
    times = Counter(r.doc_id for r in rows)
    got = Counter((p.doc_id, p.piece, p.start, p.length) for p in pieces)
    want = Counter()
    for i, n in tokens.items():
        for k, start in enumerate(range(0, n, capacity)):
            want[(i, k, start, min(capacity, n - start))] += times[i]
    assert got == want
    bins = defaultdict(list)
    for p in pieces:
        bins[p.sequence_id].append((p.offset, p.length))
    for b in bins.values():
        at = 0
        for offset, length in sorted(b):
            assert offset == at
            at += length
        assert at <= capacity
    assert len(bins) <= -(-sum(tokens[r.doc_id] for r in rows) // capacity) + 1


def test_run_is_its_stages(spark, tmp_path):
    spark.createDataFrame(documents(), SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    out = P.run(spark, str(tmp_path))
    assert out.count() > 0 and "sequence_id" in out.columns


def test_empty_and_odd_tables(spark, docs):
    odd = docs.withColumns({"host": F.lit("x"), "n": F.lit(1), "copies": F.lit(2), "key__x": F.lit(3)})
    for stage in (P.quality, P.near_duplicates, P.personal_data, P.mixture):
        assert stage(spark, docs.limit(0), "").count() == 0
        assert stage(spark, odd, "").columns == odd.columns
    assert P.packing(spark, docs.limit(0), "").count() == 0
    nulls = spark.createDataFrame([(None, None, None, None, None), (1, "a b", None, None, 3), (1, "a b", None, None, 3)], SCHEMA)
    assert P.quality(spark, nulls, "").count() == 0
    assert P.near_duplicates(spark, nulls, "").count() == 2  # of repeated rows one stays
    assert P.personal_data(spark, nulls, "").count() == 3
    assert P.mixture(spark, nulls, "").count() >= 2
    assert sorted(p.length for p in P.packing(spark, nulls, "").collect()) == [1, 3, 3]


def test_identical_rows_and_pseudonym_key(spark, docs):
    twice = docs.unionByName(docs)
    assert read(line_quality.cleaned(twice)) == sorted(2 * read(line_quality.cleaned(docs)), key=repr)
    plan = curriculum.plan(twice)
    assert plan.agg(F.max("rows")).first()[0] == 2 and plan.count() == docs.count()
    assert read(pseudonyms.pseudonymised(docs, PSEUDONYM_KEY)) == read(pseudonyms.pseudonymised(docs.repartition(7), PSEUDONYM_KEY))
    assert jaccard_join.near_duplicates(twice).count() == 2 * docs.count()
