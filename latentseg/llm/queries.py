"""One query for each operator of this folder, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import bpe, lm_bloom, media, mixing, neardup, quality, sharding, token_counts, url_graph, warc


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_mix_sources": mixing.op1,
        "op2_stratified_shards": sharding.op2,
        "op3_warc": warc.op3,
        "op4_media_avi": media.op4,
        "op5_token_counts": token_counts.op5,
        "op6_lm_scores": lm_bloom.op6,
        "op7_url_graph": url_graph.op7,
        "op8_bpe": bpe.op8,
        "op9_quality": quality.op9,
        "op10_near_duplicates": neardup.op10,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_mix_sources": mixing.OP1_SQL, "op7_url_graph": url_graph.OP7_SQL, "op9_quality": quality.OP9_SQL, "op10_near_duplicates": neardup.OP10_SQL}
