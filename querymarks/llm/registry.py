"""Queries of the training-data operators, by name."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline

from . import bpe, chat, decontaminate, exact_dedup, language_model, line_dedup, quality, secrets, simhash, url_filter


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "pipeline": corpus_pipeline.run,
        "op1_chat": chat.op1_chat,
        "op2_language_model": language_model.op2_language_model,
        "op3_bpe": bpe.op3_bpe,
        "op4_simhash": simhash.op4_simhash,
        "op5_secrets": secrets.op5_secrets,
        "op6_line_dedup": line_dedup.op6_line_dedup,
        "op7_url_filter": url_filter.op7_url_filter,
        "op8_decontaminate": decontaminate.op8_decontaminate,
        "op9_exact_dedup": exact_dedup.op9_exact_dedup,
        "op10_quality": quality.op10_quality,
    }


def oracle_sql() -> dict[str, str]:
    own = {"op1_chat": chat.OP1_SQL, "op7_url_filter": url_filter.OP7_SQL, "op9_exact_dedup": exact_dedup.OP9_SQL, "pipeline": corpus_pipeline.ORACLE_SQL}
    return {k: v for k, v in own.items() if v}
