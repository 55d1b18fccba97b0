"""The thin queries of this subpackage and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from winnow.llm import chat, embeddings, line_dedup, media, mixing, packing, secrets, sharding, simhash, toxicity


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_line_dedup": line_dedup.op1_line_dedup,
        "op2_secret_scan": secrets.op2_secret_scan,
        "op3_gif_media": media.op3_gif_media,
        "op4_simhash_near_dedup": simhash.op4_simhash_near_dedup,
        "op5_source_mixing": mixing.op5_source_mixing,
        "op6_embedding_near_dedup": embeddings.op6_embedding_near_dedup,
        "op7_toxicity": toxicity.op7_toxicity,
        "op8_chat_tree": chat.op8_chat_tree,
        "op9_sharding": sharding.op9_sharding,
        "op10_packing": packing.op10_packing,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op1_line_dedup": line_dedup.OP1_SQL,
        "op5_source_mixing": mixing.OP5_SQL,
        "op6_embedding_near_dedup": embeddings.OP6_SQL,
        "op8_chat_tree": chat.OP8_SQL,
    }
