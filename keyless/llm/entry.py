"""Queries of the training-data operators, and SQL for those that have an SQL form."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from keyless.llm import bpe, dedup, jaccard, licenses, oracle, packing, quality, resharding, tokenfiles, vafile, warc


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    functions = [
        dedup.op1_suffix_merge_dedup, warc.op2_chunked_warc, bpe.op3_chunked_bpe, jaccard.op4_adaptive_prefix_join, licenses.op5_signature_rules,
        packing.op6_pattern_packing, vafile.op7_vector_approximation, tokenfiles.op8_token_files, resharding.op9_flow_resharding, quality.op10_suffix_repetition,
    ]
    return {f.__name__: f for f in functions}


def oracle_sql() -> dict[str, str]:
    return dict(oracle.SQL)
