"""The corpus queries by name, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline
from slowlens.llm import ann, chat, decontaminate, linededup, minhash, mixing, pii, quality, sharding, urls

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_pii": pii.op1_pii,
    "op2_line_dedup": linededup.op2_line_dedup,
    "op3_quality_classifier": quality.op3_quality_classifier,
    "op4_mixing": mixing.op4_mixing,
    "op5_url_filters": urls.op5_url_filters,
    "op6_sharding": sharding.op6_sharding,
    "op7_minhash_dedup": minhash.op7_minhash_dedup,
    "op8_nearest_neighbours": ann.op8_nearest_neighbours,
    "op9_chat_formatting": chat.op9_chat_formatting,
    "op10_decontamination": decontaminate.op10_decontamination,
    "pipeline": corpus_pipeline.run,
}

ORACLES: dict[str, str] = {"op5_url_filters": urls.OP5_SQL, "op9_chat_formatting": chat.OP9_SQL}
