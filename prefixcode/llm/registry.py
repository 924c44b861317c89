"""The operators' queries and their SQL, for ``__spark_entry__.py``."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from prefixcode.llm import brown, chat, exthash, hdlang, icws, kneser, ogg, packing, pivotal, windows

Query = Callable[[SparkSession, str], DataFrame]


def queries() -> dict[str, Query]:
    return {
        "op1_chat_views": chat.op1,
        "op2_ogg_media": ogg.op2,
        "op3_icws_near_dedup": icws.op3,
        "op4_hyperdimensional_lang": hdlang.op4,
        "op5_extendible_hash_dedup": exthash.op5,
        "op6_brown_class_lm": brown.op6,
        "op7_kneser_ney_quality": kneser.op7,
        "op8_compact_window_passages": windows.op8,
        "op9_pivotal_mix": pivotal.op9,
        "op10_config_lp_packing": packing.op10,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_chat_views": chat.SQL, "op5_extendible_hash_dedup": exthash.SQL}
