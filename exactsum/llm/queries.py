"""The opN_<name> queries: each applies its operator to the whole table it is meant for."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import best_fit, curriculum, hamming, jaccard_join, licenses, line_quality, preference, pseudonyms, pu_toxicity, superkmer
from .common import table

TOKENIZER = "word_bpe_49k.json"
PSEUDONYM_KEY = "corpus release key"


def op9_sentence_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = licenses.recognised(table(spark, sf_dir, "documents"))
    line = F.array_join(F.transform("sentence_ids", lambda i: F.concat(F.lit("<"), i, F.lit(">"))), "")
    return d.select("doc_id", F.size("sentence_ids").alias("n_sentences"), line.alias("sentence_ids"), F.array_join("licenses", "|").alias("licenses"))


def op10_nn_pu_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = pu_toxicity.train(docs, table(spark, sf_dir, "labels"))
    s = pu_toxicity.scored(docs, model)
    return s.select("doc_id", pu_toxicity.held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(TOKENIZER)


def op1_multi_index_hashing(spark: SparkSession, sf_dir: str) -> DataFrame:
    coded = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), hamming.sign_code(F.col("embedding")).alias("code"))
    return hamming.nearest_codes(coded, coded.where("id % 20 = 0"), k=10, bits=64)


OP1_SQL = """
WITH bits AS (SELECT vec_id, embedding, unnest(range(1, 65)) AS i FROM embeddings),
c AS (SELECT vec_id, string_agg(CASE WHEN embedding[i] > 0 THEN '1' ELSE '0' END, '' ORDER BY i)::BIT AS code FROM bits GROUP BY vec_id),
p AS (
  SELECT q.vec_id AS query_id, r.vec_id AS neighbor_id, bit_count(xor(q.code, r.code))::INTEGER AS distance
  FROM c q, c r WHERE q.vec_id % 20 = 0
), o AS (SELECT *, (row_number() OVER (PARTITION BY query_id ORDER BY distance, neighbor_id))::INTEGER AS rank FROM p)
SELECT query_id, rank, neighbor_id, distance FROM o WHERE rank <= 10
"""


def op2_line_frequency(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = line_quality.judged(table(spark, sf_dir, "documents"))
    return d.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_removed")


OP2_SQL = r"""
WITH d AS (
  SELECT doc_id, source AS host, text, coalesce(text, '') AS t,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w
  FROM documents
), spot AS (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM d WHERE len(w) >= 8
), gram AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, array_to_string(w[i:i + 7], ' ')) AS c FROM spot
), rep AS (SELECT doc_id, least(8, i - coalesce(lag(i) OVER (PARTITION BY doc_id ORDER BY i), -8)) AS n FROM gram WHERE c > 1
), repeated AS (SELECT doc_id, sum(n) AS n FROM rep GROUP BY doc_id
), lines AS (SELECT doc_id, host, text, unnest(string_split(t, chr(10))) AS l FROM d
), line AS (
  SELECT doc_id, host, text, l, lower(array_to_string(regexp_extract_all(l, '[^\x20\x09-\x0D]+'), ' ')) AS norm,
         len(regexp_extract_all(l, '[^\x20\x09-\x0D]+')) AS n
  FROM lines WHERE regexp_matches(l, '[^\x20\x09-\x0D]')
), dup AS (SELECT doc_id, count(*) - count(DISTINCT l) AS n FROM line GROUP BY doc_id
), hosts AS (SELECT host, count(DISTINCT doc_id) AS docs FROM d WHERE text IS NOT NULL GROUP BY host
), often AS (
  SELECT host, norm FROM (SELECT host, norm, count(DISTINCT doc_id) AS c FROM line GROUP BY host, norm)
  JOIN (SELECT host AS host_, docs FROM hosts) ON host IS NOT DISTINCT FROM host_
  WHERE c > greatest(3::DOUBLE, docs * 0.02::DOUBLE)
), gone AS (
  SELECT doc_id, sum(n) AS n FROM line JOIN (SELECT host AS host_, norm AS norm_ FROM often)
  ON host IS NOT DISTINCT FROM host_ AND norm = norm_ GROUP BY doc_id
), m AS (
  SELECT d.doc_id, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars,
         (length(t) - length(translate(t, '#*$%&|<>', '')))::BIGINT AS n_symbols,
         coalesce(dup.n, 0)::BIGINT AS n_dup_lines, coalesce(repeated.n, 0)::BIGINT AS n_repeat_words,
         coalesce(gone.n, 0)::BIGINT AS n_removed
  FROM d LEFT JOIN dup USING (doc_id) LEFT JOIN repeated USING (doc_id) LEFT JOIN gone USING (doc_id)
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       (n_words < 20 OR 100 * n_repeat_words > 30 * n_words) AS base_failed,
       (NOT (n_words < 20 OR 100 * n_repeat_words > 30 * n_words) AND n_words - n_removed > n_words * 0.3::DOUBLE) AS kept,
       n_removed
FROM m
"""


def op3_preference_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Conversations 2i and 2i + 1 stand for the chosen and the rejected side of pair i."""
    c = table(spark, sf_dir, "conversations")
    turns = c.select(F.floor(F.col("conv_id") / 2).alias("pair_id"), (F.col("conv_id") % 2 == 0).alias("chosen"), "turn", "role", "text")
    spans = lambda name: F.array_join(F.transform(name, lambda s: F.concat_ws("-", s["start"].cast("string"), s["stop"].cast("string"))), ",").alias(name)
    return preference.preference_pairs(turns).select("pair_id", "n_prompt_turns", "prompt", "chosen", "rejected", spans("chosen_spans"), spans("rejected_spans"))


OP3_SQL = """
WITH t AS (
  SELECT conv_id // 2 AS pair_id, conv_id % 2 = 0 AS chosen, coalesce(role, '') AS role, coalesce(text, '') AS text,
         row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, coalesce(role, ''), coalesce(text, '')) - 1 AS pos
  FROM conversations WHERE conv_id IS NOT NULL
), both_sides AS (SELECT pair_id FROM t GROUP BY pair_id HAVING count(DISTINCT chosen) = 2
), side AS (SELECT * FROM t JOIN both_sides USING (pair_id)
), pos AS (
  SELECT pair_id, pos, count(*) = 2 AND count(DISTINCT role) = 1 AND count(DISTINCT text) = 1 AS same FROM side GROUP BY pair_id, pos
), prefix AS (SELECT pair_id, coalesce(min(pos) FILTER (NOT same), max(pos) + 1) AS n FROM pos GROUP BY pair_id
), r AS (
  SELECT s.*, n, '<|' || role || '|>' || chr(10) AS head, text || '<|end|>' || chr(10) AS body FROM side s JOIN prefix USING (pair_id)
), o AS (
  SELECT *, coalesce(sum(length(head) + length(body)) OVER (PARTITION BY pair_id, chosen ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS at_
  FROM r WHERE pos >= n
), after AS (
  SELECT pair_id, chosen, string_agg(head || body, '' ORDER BY pos) AS text,
         string_agg((at_ + length(head))::BIGINT || '-' || (at_ + length(head) + length(body))::BIGINT, ',' ORDER BY pos) FILTER (role = 'assistant') AS spans
  FROM o GROUP BY pair_id, chosen
), prompt AS (SELECT pair_id, string_agg(head || body, '' ORDER BY pos) AS text FROM r WHERE chosen AND pos < n GROUP BY pair_id
)
SELECT p.pair_id, p.n::INTEGER AS n_prompt_turns, coalesce(prompt.text, '') AS prompt, coalesce(c.text, '') AS chosen, coalesce(j.text, '') AS rejected,
       coalesce(c.spans, '') AS chosen_spans, coalesce(j.spans, '') AS rejected_spans
FROM prefix p LEFT JOIN prompt USING (pair_id)
LEFT JOIN (SELECT * FROM after WHERE chosen) c USING (pair_id) LEFT JOIN (SELECT * FROM after WHERE NOT chosen) j USING (pair_id)
"""


def op4_feistel_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pseudonyms.pseudonymised(table(spark, sf_dir, "documents"), key=PSEUDONYM_KEY).select("doc_id", "text")


def op5_curriculum(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = curriculum.plan(table(spark, sf_dir, "documents"))
    one = p.withColumn("copy__", F.explode(F.sequence(F.lit(1), F.col("rows"))))
    return one.select("doc_id", "size", "source_size", "target", "taken", F.get("positions", 0).alias("first_position")).orderBy("first_position", "doc_id")


OP5_SQL = r"""
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::BIGINT AS size FROM documents
), s0 AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source
), s1 AS (SELECT *, ((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::DOUBLE AS weight FROM s0
), s2 AS (
  SELECT *, ((sum(source_size) OVER () - 3 * coalesce(sum(source_size) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::DOUBLE
            / sum(weight) OVER (o ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)) AS level, (source_size * 3)::DOUBLE / weight AS own
  FROM s1 WINDOW o AS (ORDER BY source_size / weight, source NULLS LAST)
), s AS (
  SELECT source AS source_, source_size, weight,
         least((source_size * 3)::DOUBLE, (max(CASE WHEN level <= own THEN level END) OVER ()) * weight) AS target
  FROM s2
), j AS (
  SELECT d.*, s.*, coalesce(sum(size) OVER (PARTITION BY source ORDER BY md5(doc_id::VARCHAR), doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before
  FROM d JOIN s ON source IS NOT DISTINCT FROM source_
), e AS (SELECT *, least(3, CASE WHEN source_size > 0 THEN floor(target / source_size) ELSE 0 END)::BIGINT AS whole FROM j
), c AS (
  SELECT *, whole + CASE WHEN whole < 3 AND before + size::DOUBLE / 2 < target - whole * source_size THEN 1 ELSE 0 END AS copies FROM e
), p AS (
  SELECT *, least(1.0::DOUBLE, (before + size::DOUBLE / 2) / target) * weight AS per,
         weight * (1 - CASE weight WHEN 1 THEN -0.5 WHEN 2 THEN 0.0 ELSE 0.5 END)::DOUBLE AS w0,
         weight * (1 + CASE weight WHEN 1 THEN -0.5 WHEN 2 THEN 0.0 ELSE 0.5 END)::DOUBLE AS w1
  FROM c
)
SELECT doc_id, size, source_size, target, size * copies AS taken,
       CASE WHEN copies > 0 THEN least(1.0::DOUBLE, 2 * per / (w0 + sqrt(greatest(0.0::DOUBLE, w0 * w0 + 2 * (w1 - w0) * per)))) END AS first_position
FROM p
"""


def op6_super_kmer(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = superkmer.without_repeats(table(spark, sf_dir, "documents"), width=20)
    return kept.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def op7_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.near_duplicates(table(spark, sf_dir, "documents"), width=5, near=75)


def op8_best_two_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return best_fit.pack(table(spark, sf_dir, "documents"), tokenizer_path(), capacity=2048, separator=0, memo_words=1_500_000)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_multi_index_hashing": op1_multi_index_hashing,
    "op2_line_frequency": op2_line_frequency,
    "op3_preference_pairs": op3_preference_pairs,
    "op4_feistel_pseudonyms": op4_feistel_pseudonyms,
    "op5_curriculum": op5_curriculum,
    "op6_super_kmer": op6_super_kmer,
    "op7_jaccard_join": op7_jaccard_join,
    "op8_best_two_fit": op8_best_two_fit,
    "op9_sentence_rules": op9_sentence_rules,
    "op10_nn_pu_toxicity": op10_nn_pu_toxicity,
}

ORACLES: dict[str, str] = {
    "op1_multi_index_hashing": OP1_SQL,
    "op3_preference_pairs": OP3_SQL,
    "op9_sentence_rules": licenses.oracle(),
    "op2_line_frequency": OP2_SQL,
    "op5_curriculum": OP5_SQL,
}
