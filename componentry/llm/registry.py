"""The subpackage's queries, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline
from componentry.llm import jaccard, knn, licenses, lines, mixing, packing, quality, secrets, tokens, urls


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    ops = (mixing.op1_source_mix, licenses.op2_license_scans, knn.op3_voronoi_knn, jaccard.op4_jaccard_join, secrets.op5_secret_scans, packing.op6_best_fit_packing, urls.op7_url_filters, quality.op8_quality_rules, tokens.op9_token_counts, lines.op10_line_dedup)
    return {f.__name__: f for f in ops} | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    return {"op1_source_mix": mixing.OP1_SQL, "op3_voronoi_knn": knn.OP3_SQL, "op4_jaccard_join": jaccard.OP4_SQL, "op7_url_filters": urls.OP7_SQL, "op8_quality_rules": quality.OP8_SQL, "op10_line_dedup": lines.OP10_SQL}
