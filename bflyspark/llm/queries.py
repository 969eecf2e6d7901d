"""The queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .byte_bpe import op2_byte_bpe
from .decontaminate import op9_decontaminate
from .jaccard_join import op8_jaccard_join
from .license_scan import op5_license_scan
from .quality_classifier import op7_quality_classifier
from .quality_rules import op1_quality_rules
from .secret_scan import op6_secret_scan
from .shard_balance import op4_shard_balance
from .suffix_dedup import op10_suffix_dedup
from .token_files import op3_token_files


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def llm_queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_quality_rules": op1_quality_rules,
        "op2_byte_bpe": op2_byte_bpe,
        "op3_token_files": op3_token_files,
        "op4_shard_balance": op4_shard_balance,
        "op5_license_scan": op5_license_scan,
        "op6_secret_scan": op6_secret_scan,
        "op7_quality_classifier": op7_quality_classifier,
        "op8_jaccard_join": op8_jaccard_join,
        "op9_decontaminate": op9_decontaminate,
        "op10_suffix_dedup": op10_suffix_dedup,
        "pipeline": pipeline,
    }


#: Shingle sets, all pairs that share a shingle, links, and what each document reaches by links.
JACCARD_SQL = r"""
WITH RECURSIVE
w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT doc_id, CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 4 THEN [array_to_string(ws, ' ')]
      ELSE list_distinct([array_to_string(ws[i:i+3], ' ') FOR i IN range(1, len(ws) - 2)]) END AS g FROM w),
e AS (SELECT doc_id, len(g) AS n, unnest(g) AS g FROM s),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, any_value(a.n) AS na, any_value(b.n) AS nb, count(*) AS c FROM e a JOIN e b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM p WHERE 100 * c >= 85 * (na + nb - c)),
both_ways AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
reached AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, x.b FROM reached r JOIN both_ways x ON r.b = x.a),
least_of AS (SELECT a, min(b) AS component_id FROM reached GROUP BY a)
SELECT s.doc_id, CAST(len(g) AS BIGINT) AS n_shingles, component_id FROM s JOIN least_of ON s.doc_id = least_of.a
"""


def llm_oracle_sql() -> dict[str, str]:
    """The other operators have no SQL form for all their columns; tests hold them against plain versions."""
    return {"op8_jaccard_join": JACCARD_SQL}
