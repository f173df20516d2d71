"""The queries and SQL of this subpackage."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from kdforest.llm import decontaminate, fingerprint, html_text, langid, packing, quality, sharding, simhash, substring, warc


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found = [
        langid.op1_language, fingerprint.op2_sketch, substring.op3_suffix_dedup, warc.op4_warc, html_text.op5_html_text,
        quality.op6_quality, simhash.op7_simhash, sharding.op8_shard, decontaminate.op9_decontaminate, packing.op10_pack,
    ]
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return {"op3_suffix_dedup": substring.OP3_SQL, "op4_warc": warc.OP4_SQL, "op9_decontaminate": decontaminate.OP9_SQL}
