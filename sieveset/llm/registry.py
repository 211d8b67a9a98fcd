"""Queries of this subpackage and the SQL that checks them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import chat, exact_dedup, images, mixing, packing, quality, repeats, sharding, simhash, url_rules

Query = Callable[[SparkSession, str], DataFrame]


def queries() -> dict[str, Query]:
    return {
        "op1_quality_rules": quality.query,
        "op2_sharding": sharding.query,
        "op3_source_mixing": mixing.query,
        "op4_exact_dedup": exact_dedup.query,
        "op5_packing": packing.query,
        "op6_repeated_passages": repeats.query,
        "op7_image_copies": images.query,
        "op8_chat_format": chat.query,
        "op9_url_filter": url_rules.query,
        "op10_simhash": simhash.query,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op3_source_mixing": mixing.oracle(),
        "op4_exact_dedup": exact_dedup.oracle(),
        "op8_chat_format": chat.oracle(),
        "op9_url_filter": url_rules.oracle(),
    }
