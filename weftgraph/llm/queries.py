"""Registered queries of this subpackage and their SQL.

Each query is thin: it applies one operator to its whole table and derives
digest columns from what the operator returns.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from weftgraph.llm.ann import nearest
from weftgraph.llm.exact_dedup import exact_dedup
from weftgraph.llm.html_text import extract_text
from weftgraph.llm.licenses import scan_licenses
from weftgraph.llm.line_dedup import line_dedup
from weftgraph.llm.mixing import SEED, mix_sources
from weftgraph.llm.near_dedup import NearDupParams, near_dup_groups
from weftgraph.llm.packing import pack_documents
from weftgraph.llm.secrets import scan_secrets
from weftgraph.llm.toxicity import score_toxicity
from weftgraph.plans.common import table


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(table(spark, sf_dir, "documents"))


def op2_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_text(table(spark, sf_dir, "pages"))


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = line_dedup(table(spark, sf_dir, "documents"))
    return cut.select("doc_id", "n_lines", "n_dropped", F.sha2("text", 256).alias("kept_sha256"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "documents").select("doc_id", "text")
    return score_toxicity(rows, table(spark, sf_dir, "labels"), carry_text=False).select("doc_id", "held_out", "score", "predicted")


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan_secrets(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "start", "length", F.sha2("candidate", 256).alias("candidate_sha256"), "score", "is_secret")


def op6_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(table(spark, sf_dir, "embeddings"), F.pmod("vec_id", F.lit(20)) == 0)


def op7_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup_groups(table(spark, sf_dir, "documents"), NearDupParams(words=3, num=85, den=100))


def op8_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))


def op9_poisson_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_sources(table(spark, sf_dir, "documents")).select("doc_id", "source", "copy", "order_key", "text")


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_exact_dedup": op1_exact_dedup,
    "op2_html_text": op2_html_text,
    "op3_line_dedup": op3_line_dedup,
    "op4_toxicity": op4_toxicity,
    "op5_secret_scan": op5_secret_scan,
    "op6_nearest": op6_nearest,
    "op7_near_dedup": op7_near_dedup,
    "op8_best_fit_packing": op8_best_fit_packing,
    "op9_poisson_mixing": op9_poisson_mixing,
    "op10_license_scan": op10_license_scan,
}

ORACLE_SQL: dict[str, str] = {
    "op1_exact_dedup": r"""
        WITH n AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents)
        SELECT doc_id, min(doc_id) OVER (PARTITION BY t) AS keep_id, count(*) OVER (PARTITION BY t) AS group_size,
               doc_id = min(doc_id) OVER (PARTITION BY t) AS kept, sha256(t) AS text_sha256
        FROM n""",
    "op3_line_dedup": r"""
        WITH l AS (SELECT doc_id, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos,
                          unnest(string_split(coalesce(text, ''), chr(10))) AS line FROM documents),
             k AS (SELECT *, translate(trim(line, E' \t\n\x0b\x0c\r'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
             s AS (SELECT key, max(doc_id) AS keep_id FROM k WHERE length(key) >= 40 GROUP BY key HAVING count(DISTINCT doc_id) >= 5),
             m AS (SELECT k.doc_id, k.pos, k.line, (s.key IS NOT NULL AND k.doc_id <> s.keep_id) AS gone FROM k LEFT JOIN s ON k.key = s.key)
        SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
               sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
        FROM m GROUP BY doc_id""",
    "op9_poisson_mixing": f"""
        WITH s AS (SELECT source, count(*) AS n FROM documents GROUP BY source),
             t AS (SELECT count(*) AS m, sum(n) AS total FROM s),
             r AS (SELECT source, 1.0::DOUBLE / m * total / n AS rate FROM s, t),
             k AS (SELECT source, unnest(range(0, ceil(rate + 9 * sqrt(rate) + 30)::BIGINT + 1)) AS k, rate FROM r),
             p AS (SELECT source, k, sum(exp(-rate + k * ln(rate) - lgamma(k + 1))) OVER (PARTITION BY source ORDER BY k) AS cdf FROM k),
             u AS (SELECT doc_id, source, text,
                          (('0x' || substr(md5('{SEED}:' || coalesce(doc_id::VARCHAR, 'null')), 1, 13))::BIGINT + 0.5::DOUBLE) / 4503599627370496.0::DOUBLE AS u FROM documents),
             c AS (SELECT u.doc_id, u.source, u.text, count(*) AS n FROM u JOIN p ON u.source = p.source AND p.cdf < u.u GROUP BY ALL)
        SELECT doc_id, source, copy::INTEGER AS copy, md5('{SEED}:' || coalesce(doc_id::VARCHAR, 'null') || ':' || copy) AS order_key, text
        FROM (SELECT doc_id, source, text, unnest(range(0, n)) AS copy FROM c)""",
}
