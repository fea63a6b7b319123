"""Queries and DuckDB SQL of the pipeline operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import q_audio, q_html, q_jaccard, q_langid, q_lm, q_mixing, q_packing, q_pipeline, q_substring, q_token_codec, q_vectors

MODULES = (q_packing, q_token_codec, q_jaccard, q_html, q_mixing, q_vectors, q_lm, q_langid, q_audio, q_substring, q_pipeline)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {m.NAME: m.query for m in MODULES}


def oracle_sql() -> dict[str, str]:
    return {m.NAME: m.ORACLE for m in MODULES if getattr(m, "ORACLE", None)}
