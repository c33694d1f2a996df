"""The subpackage's queries and their SQL, for ``__spark_entry__.py``."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import bpe, html, media, packing, pii, simhash, tokenfile, topk, toxicity, urls


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_packing": packing.op1_packing,
        "op2_tokenfile": tokenfile.op2_tokenfile,
        "op3_bpe": bpe.op3_bpe,
        "op4_urls": urls.op4_urls,
        "op5_html": html.op5_html,
        "op6_simhash": simhash.op6_simhash,
        "op7_toxicity": toxicity.op7_toxicity,
        "op8_topk": topk.op8_topk,
        "op9_pii": pii.op9_pii,
        "op10_media": media.op10_media,
    }


def oracle_sql() -> dict[str, str]:
    return {"op8_topk": topk.ORACLE}
