import random

import pytest
from pyspark.sql import functions as F

from exactsum.llm import common, jaccard_join


def brute(rows, width=5, near=75):
    def shingles(text):
        words = (text or "").encode().translate(jaccard_join.LOWER).split()
        if not words:
            return set()
        return {tuple(words[i : i + width]) for i in range(max(1, len(words) - width + 1))}

    least = lambda i: -1 if i is None else i
    sets = {(least(i), text): shingles(text) for i, text in rows}
    ids = sorted(sets, key=lambda k: (k[0], k[1] or ""))
    parent = {i: i for i in ids}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for k, i in enumerate(ids):
        for j in ids[:k]:
            common, union = len(sets[i] & sets[j]), len(sets[i] | sets[j])
            if union and sets[i] and sets[j] and 100 * common >= near * union:
                low, high = sorted((root(i), root(j)), key=ids.index)
                parent[high] = low
    smallest = {}
    for i in ids:
        smallest.setdefault(root(i), i[0])
    named = lambda i: None if i == -1 else i
    return sorted(((i, len(sets[least(i), t]), named(smallest[root((least(i), t))])) for i, t in rows), key=repr)


def corpus(seed, n=120):
    rng = random.Random(seed)
    vocabulary = [f"w{k}" for k in range(400)] + ["Ünï", "A,", "|"]
    bases = [[rng.choice(vocabulary) for _ in range(rng.choice([3, 8, 30, 120]))] for _ in range(8)]
    shared = [rng.choice(vocabulary) for _ in range(25)]
    rows = []
    for i in range(n):
        words = list(rng.choice(bases)) if rng.random() < 0.7 else [rng.choice(vocabulary) for _ in range(40)]
        for _ in range(rng.choice([0, 0, 1, 2, 6])):
            words[rng.randrange(len(words))] = rng.choice(vocabulary)
        if rng.random() < 0.3:
            words += shared
        text = " \n".join(words)
        rows.append((i * 37 % 1009, text.upper() if rng.random() < 0.1 else text))
    return rows + [(2000, None), (2001, ""), (2002, " \t"), (2003, "one two"), (2004, "One  TWO"), rows[0], (2005, "z" * 50_000)]


@pytest.mark.parametrize(("seed", "region_docs", "hot"), [(1, 6000, 64), (2, 5, 64), (3, 6000, 3), (4, 3, 64), (5, 8, 5)])
def test_components_match_brute_force(spark, seed, region_docs, hot):
    rows = corpus(seed)
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as n", "'x' as p", "doc_id as x", "2 as component_id").repartition(3)
    got = jaccard_join.near_duplicates(docs, region_docs=region_docs, hot_from=hot)
    assert sorted(map(tuple, got.collect()), key=repr) == brute(rows)


def test_clashing_ids_are_different_documents(spark):
    rows = [(r if k % 5 else None if k % 2 else 7, t) for k, (r, t) in enumerate(corpus(11, 60))]
    rows += rows[:4]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("node", F.lit("x"))
    assert sorted(map(tuple, jaccard_join.near_duplicates(docs, region_docs=6).collect()), key=repr) == brute(rows)
    kept = jaccard_join.one_of_each(docs)
    sets = {(r.doc_id, r.text) for r in kept.collect()}
    assert kept.columns == docs.columns and kept.count() == len(sets)
    full = brute([(i, t) for i, (_, t) in enumerate(rows)])
    assert len(sets) == len({c for i, n, c in full if n}) + len({(i, t or "") for i, t in rows if not (t or "").split()})


def test_repeated_rows_leave_one(spark):
    docs = spark.createDataFrame([(1, "a b c d e f")] * 3 + [(2, "A b c d e f"), (3, "other")], "doc_id long, text string")
    assert sorted(r.doc_id for r in jaccard_join.one_of_each(docs).collect()) == [1, 3]



def test_empty_table_and_null_ids(spark):
    docs = spark.createDataFrame([], "doc_id long, text string")
    assert jaccard_join.near_duplicates(docs).count() == 0
    docs = spark.createDataFrame([(None, "a b c d e f g"), (5, "a b c d e f g"), (6, "other")], "doc_id long, text string")
    got = {(r.doc_id, r.n_shingles, r.component_id) for r in jaccard_join.near_duplicates(docs).collect()}
    assert got == {(None, 3, None), (5, 3, None), (6, 1, 6)}
    assert {r.doc_id for r in jaccard_join.one_of_each(docs).collect()} == {None, 6}


def test_low_thresholds_are_refused(spark):
    with pytest.raises(ValueError):
        jaccard_join.near_duplicates(spark.createDataFrame([(1, "a")], "doc_id long, text string"), near=60)


def test_filter_keeps_all_that_is_wanted(spark):
    rows = spark.range(-5000, 5000).withColumnRenamed("id", "node").withColumn("text", F.lit("x"))
    wanted = rows.where("node % 7 = 0").select(F.col("node").alias("x"))
    kept = common.likely(rows, "node", wanted, "x")
    assert kept.columns == rows.columns
    got = {r.node for r in kept.collect()}
    assert {r.x for r in wanted.collect()} <= got and len(got) < 1.01 * wanted.count()
    assert common.likely(rows, "node", wanted.limit(0), "x").count() == 0
