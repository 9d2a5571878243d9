"""Queries of this subpackage and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from termatlas.llm import chat, licenses, mixing, mtree, near_dup, personal, pieces, quality, secrets, toxicity
from termatlas.llm.tables import documents, table


def op1_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces_ = chat.transcribe(table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text"))
    parsed = chat.by_row(chat.parse(pieces_, chat.fit(pieces_)))
    return parsed.select(F.col("id").alias("conv_id"), F.col("seq").alias("turn"), "recovered", "begins", "n_lines", "rendered", chat.held_out("id").alias("held_out"))


def op2_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix(documents(spark, sf_dir, "doc_id", "source", "text"))
    return mixed.select("doc_id", "size", "source_size", "target", "taken", "copies")


def op3_personal(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.digests(personal.personal(documents(spark, sf_dir, "doc_id", "text")), personal.KINDS)


def op4_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.digests(secrets.secrets(documents(spark, sf_dir, "doc_id", "text")), secrets.KINDS)


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality.quality(documents(spark, sf_dir, "doc_id", "text", "lang"), table(spark, sf_dir, "labels", "doc_id", "quality"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.array_join("failed_rules", ",").alias("failed_rules"))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = toxicity.toxicity(documents(spark, sf_dir, "doc_id", "text"), table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return scored.select("doc_id", "held_out", "score", "predicted", F.size("sentences").cast("long").alias("n_offending"))


def op7_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mtree.top_inner_products(table(spark, sf_dir, "embeddings", "vec_id", "embedding"), k=20, every=20)


def op8_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_dup.near_duplicates(documents(spark, sf_dir, "doc_id", "text"), percent=85)
    return found.select("doc_id", "n_shingles", "component_id", "kept")


def op9_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    model = public_tokenizers.path("piece_bpe_32k.model")
    return pieces.encode_decode(documents(spark, sf_dir, "doc_id", "text"), model, ("n_tokens", "ids_sha256", "decoded_sha256"))


OP7_SQL = r"""
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), scored AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id, list_dot_product(q.e, c.e)::BIGINT AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 20 = 0
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM scored
)
SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM ranked WHERE rank <= 20
"""

def op5_sql(risk: float = 0.01, delta: float = 0.1) -> str:
    """The measures, the joint levels and their binomial certificates, from the rules' table."""
    levels, names = [], list(quality.RULES)
    for rule, (over, under, high, cutoffs) in quality.RULES.items():
        row = ", ".join(f"{c if high else -c!r}::DOUBLE" for c in cutoffs)
        value = f"{'' if high else '-'}(CASE WHEN {under} > 0 THEN {over}::DOUBLE / {under} ELSE 0 END)"
        levels.append(f"(SELECT CASE WHEN n < {len(cutoffs)} THEN n ELSE {quality.LEVELS} END FROM (SELECT len(list_filter([{row}], lambda c: {value} <= c)) AS n)) AS l_{rule}")
    failed = ", ".join(f"CASE WHEN l_{r} <= c.level THEN '{r}' END" for r in names)
    return rf"""
WITH t AS (
  SELECT doc_id, lang, coalesce(text, '') AS t FROM documents
), w AS (
  SELECT *, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS w, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM t
), windows AS (
  SELECT doc_id, i, array_to_string(w[i:i + 2], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM w WHERE len(w) > 2)
), again AS (
  SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS n FROM windows) WHERE n > 1
), repeats AS (
  SELECT doc_id, count(DISTINCT spot) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS spot FROM again) GROUP BY doc_id
), m AS (
  SELECT w.doc_id, lang, len(w)::BIGINT AS n_words, length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g'))::BIGINT AS word_chars,
    length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols, length(regexp_replace(t, '[^!]', '', 'g'))::BIGINT AS n_marks,
    length(regexp_replace(t, '[^A-Z]', '', 'g'))::BIGINT AS n_capitals, len(l)::BIGINT AS n_lines, (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines,
    coalesce(r.n, 0)::BIGINT AS n_repeat_words
  FROM w LEFT JOIN repeats r USING (doc_id)
), measured AS (
  SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed, {", ".join(levels)} FROM m
), leveled AS (
  SELECT *, least({", ".join(f"l_{r}" for r in names)}) AS level FROM measured
), good AS (
  SELECT doc_id FROM labels WHERE doc_id IS NOT NULL GROUP BY doc_id HAVING avg(quality) >= 0.5
), held AS (
  SELECT lang, level FROM leveled JOIN good USING (doc_id) WHERE NOT base_failed
), trials AS (
  SELECT lang, x.n AS level, count(*) AS n, count(*) FILTER (level <= x.n) AS k FROM held, range(0, {quality.LEVELS}) x(n) GROUP BY lang, x.n
), tested AS (
  SELECT lang, level, list_sum(list_transform(range(0, k + 1), lambda i: exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln({risk}::DOUBLE) + (n - i) * ln(1 - {risk}::DOUBLE))))
    <= {delta}::DOUBLE / (SELECT count(*) FROM (SELECT DISTINCT lang FROM held)) AS fits FROM trials
), certified AS (
  SELECT lang, max(level) AS level FROM (SELECT *, bool_and(fits) OVER (PARTITION BY lang ORDER BY level) AS ok FROM tested) WHERE ok GROUP BY lang
)
SELECT d.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  NOT base_failed AND coalesce(d.level > c.level, true) AS kept, coalesce(array_to_string([{failed}], ','), '') AS failed_rules
FROM leveled d LEFT JOIN certified c ON d.lang IS NOT DISTINCT FROM c.lang
"""


OP8_SQL = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), shingles AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
    ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS s FROM words
), sizes AS (
  SELECT doc_id, count(*) AS n FROM shingles GROUP BY doc_id
), links AS (
  SELECT x.doc_id AS a, y.doc_id AS b FROM shingles x JOIN shingles y ON x.s = y.s AND x.doc_id <> y.doc_id
  JOIN sizes p ON p.doc_id = x.doc_id JOIN sizes q ON q.doc_id = y.doc_id
  GROUP BY x.doc_id, y.doc_id, p.n, q.n HAVING 100 * count(*) >= 85 * (p.n + q.n - count(*))
), reach AS (
  SELECT doc_id, doc_id AS root FROM documents
  UNION SELECT r.doc_id, l.b FROM reach r JOIN links l ON l.a = r.root
), named AS (
  SELECT doc_id, min(root) AS component_id FROM reach GROUP BY doc_id
)
SELECT d.doc_id, coalesce(z.n, 0)::BIGINT AS n_shingles, c.component_id, d.doc_id = c.component_id AS kept
FROM documents d JOIN named c USING (doc_id) LEFT JOIN sizes z USING (doc_id)
"""


def op10_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.digests(licenses.licenses(documents(spark, sf_dir, "doc_id", "text")))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_chat": op1_chat,
        "op2_mixing": op2_mixing,
        "op3_personal": op3_personal,
        "op4_secrets": op4_secrets,
        "op5_quality": op5_quality,
        "op6_toxicity": op6_toxicity,
        "op7_topk": op7_topk,
        "op8_minhash": op8_minhash,
        "op9_sentencepiece": op9_sentencepiece,
        "op10_licenses": op10_licenses,
    }


def oracle_sql() -> dict[str, str]:
    return {"op5_quality": op5_sql(), "op7_topk": OP7_SQL, "op8_minhash": OP8_SQL}
