"""Queries of the training-data operators and the SQL that checks them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ctph, exact_dedup, line_dedup, mixing, near_dedup, quality, token_output, tokenizing, wrapper
from .common import LOWER, UPPER, scratch, table, vocabulary_path

WORDS, BYTES = "word_bpe_49k.json", "byte_bpe_50k.json"


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mixing.weigh(table(spark, sf_dir, "documents"))
    tags = [F.col(f"__{c}").alias(c) for c in ("source", "lang", "topic", "tokens")]
    return out.select("doc_id", *tags, F.coalesce("__probability", F.lit(0.0)).alias("probability"), F.col("__selected").alias("selected"))


def op2_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.classes(table(spark, sf_dir, "documents"))


def op3_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenizing.round_trip(table(spark, sf_dir, "documents"), vocabulary_path(WORDS))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = line_dedup.dedup_lines(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_lines", "n_dropped", F.sha2("kept_text", 256).alias("kept_sha256"))


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.groups(table(spark, sf_dir, "documents"))


def op6_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ctph.neighbours(table(spark, sf_dir, "documents"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenizing.count_tokens(table(spark, sf_dir, "documents"), vocabulary_path(BYTES))


def op9_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch(spark, "sequences")
    token_output.write_sequences(table(spark, sf_dir, "documents"), path, vocabulary_path(WORDS))
    return token_output.read_documents(spark, path)


def op10_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wrapper.main_text(table(spark, sf_dir, "pages"))


QUERIES = {f.__name__: f for f in (op1_mixing, op2_near_dedup, op3_bpe_round_trip, op4_line_dedup, op5_exact_dedup, op6_fingerprints, op7_quality, op8_token_counts, op9_token_output, op10_main_text)}

ASCII_LOWER = f"translate({{}}, '{UPPER}', '{LOWER}')"



def _mixing_sql(share: float = 0.7, powers: tuple = (0.5, 0.7, 0.5), topics: int = 8, rounds: int = 8, steps: int = 6) -> str:
    """The raking rounds unrolled as common table expressions."""
    margins = ("source", "lang", "topic")
    ctes = [f"""d AS MATERIALIZED (SELECT doc_id, coalesce(source, '(none)') AS source, coalesce(lang, '(none)') AS lang,
        list_filter(regexp_split_to_array(coalesce(text, ''), '[ \\t\\n\\r]+'), lambda w: w <> '') AS words FROM documents),
top AS MATERIALIZED (SELECT word, n FROM (SELECT word, count(*) AS n FROM (SELECT unnest(list_distinct(list_filter(words, lambda w: length(w) BETWEEN 5 AND 7))) AS word FROM d) GROUP BY word)
        WHERE n <= 0.1::DOUBLE * (SELECT count(*) FROM d) ORDER BY n DESC, word LIMIT {topics}),
named AS MATERIALIZED (SELECT list(word ORDER BY n, word DESC) AS anchors FROM top),
t AS MATERIALIZED (SELECT doc_id, source, lang, len(words)::BIGINT AS tokens,
        coalesce(list_position(anchors, list_filter(anchors, lambda a: list_contains(words, a))[1]), 0)::INTEGER AS topic FROM d, named),
cells AS MATERIALIZED (SELECT source, lang, topic, sum(tokens)::BIGINT AS tokens FROM t GROUP BY ALL),
r0 AS MATERIALIZED (SELECT *, tokens / (SELECT greatest(sum(tokens), 1)::DOUBLE FROM cells) AS raked FROM cells)"""]
    for m, p in zip(margins, powers):
        ctes.append(f"w_{m} AS MATERIALIZED (SELECT {m}, p / sum(p) OVER () AS target FROM (SELECT {m}, pow(sum(tokens)::DOUBLE, {p}) AS p FROM cells GROUP BY {m} HAVING sum(tokens) > 0))")
    k = 0
    for _ in range(rounds):
        for m in margins:
            ctes.append(f"""r{k + 1} AS MATERIALIZED (SELECT s.source, s.lang, s.topic, s.tokens, s.raked * coalesce(f.target / nullif(f.now, 0), 0) AS raked FROM r{k} s
LEFT JOIN (SELECT a.{m}, a.now, w.target FROM (SELECT {m}, sum(raked) AS now FROM r{k} GROUP BY {m}) a JOIN w_{m} w USING ({m})) f ON s.{m} = f.{m})""")
            k += 1
    ctes.append(f"c AS MATERIALIZED (SELECT source, lang, topic, tokens, CASE WHEN tokens > 0 THEN raked / tokens ELSE 0 END AS factor FROM r{k})")
    ctes.append("s0 AS MATERIALIZED (SELECT 0.0::DOUBLE AS scale)")
    for i in range(steps):
        ctes.append(f"""s{i + 1} AS MATERIALIZED (SELECT CASE WHEN v > 0 THEN v ELSE (SELECT scale FROM s{i}) END AS scale FROM (SELECT ({share} * sum(tokens) - coalesce(sum(tokens) FILTER (factor * s >= 1), 0))
/ nullif(sum(factor * tokens) FILTER (factor * s < 1), 0) AS v FROM (SELECT c.*, (SELECT scale FROM s{i}) AS s FROM c)))""")
    return f"""WITH {", ".join(ctes)},
p AS (SELECT source, lang, topic, round(least(1.0, factor * coalesce((SELECT scale FROM s{steps}), 0)), 6) AS probability FROM c)
SELECT t.doc_id, t.source, t.lang, t.topic, t.tokens, p.probability,
       ('0x' || substr(sha256('mix:' || coalesce(t.doc_id::VARCHAR, 'null')), 1, 12))::BIGINT / 281474976710656.0::DOUBLE < p.probability AS selected
FROM t JOIN p USING (source, lang, topic)"""


ORACLES = {
    "op1_mixing": _mixing_sql(),
    "op4_line_dedup": f"""
WITH docs AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
parts AS (SELECT doc_id, string_split(text, chr(10)) AS ls FROM docs),
lines AS (SELECT doc_id, unnest(ls) AS line, unnest(range(len(ls))) AS pos FROM parts),
keyed AS (SELECT *, {ASCII_LOWER.format("trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13))")} AS k FROM lines),
shared AS (SELECT k, min(doc_id) AS holder FROM keyed WHERE length(k) >= 10 GROUP BY k HAVING count(DISTINCT doc_id) >= 2),
judged AS (SELECT l.doc_id, l.pos, l.line, s.k IS NOT NULL AND s.holder <> l.doc_id AS gone FROM keyed l LEFT JOIN shared s ON l.k = s.k)
SELECT doc_id, count(*)::BIGINT AS n_lines, (count(*) FILTER (gone))::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '')) AS kept_sha256
FROM judged GROUP BY doc_id""",
    "op5_exact_dedup": f"""
WITH t AS (SELECT doc_id, {ASCII_LOWER.format("coalesce(text, '')")} AS norm FROM documents),
g AS (SELECT norm, max(doc_id) AS keep_id, count(*)::BIGINT AS group_size FROM t GROUP BY norm)
SELECT t.doc_id, g.keep_id, g.group_size, t.doc_id = g.keep_id AS kept, sha256(t.norm) AS text_sha256
FROM t JOIN g ON t.norm = g.norm""",
}
