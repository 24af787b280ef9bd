"""Token blocking: one block per token; the reference that the other methods extend."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from erblock.functions.text import WORD, tokens


def description_tokens(desc: DataFrame, pattern: str = WORD, lower: bool = True, min_len: int = 1, kinds: Sequence[str] = ("literal", "uri")) -> DataFrame:
    """collection, entity_id, attribute, token: exploded, repeated tokens of one value left out."""
    chosen = desc.where(F.col("kind").isin(*kinds)) if set(kinds) != {"literal", "uri"} else desc
    return chosen.select("collection", "entity_id", "attribute", F.explode(tokens(F.col("value"), pattern, lower, min_len)).alias("token"))


def bags(desc: DataFrame) -> DataFrame:
    """``blocks.bags`` of ``build``, without a row per token; a description without tokens has no keys, but a row."""
    found = desc.repartition("entity_id").select("collection", "entity_id", tokens(F.col("value")).alias("found"))
    return found.groupBy("collection", "entity_id").agg(F.array_distinct(F.flatten(F.collect_list("found"))).alias("keys"))


def build(desc: DataFrame, **options: object) -> DataFrame:
    """Postings (block_key, collection, entity_id) of every token; one shuffle, on the values before they are cut into tokens."""
    t = description_tokens(desc.repartition("entity_id"), **options)
    return t.select(F.col("token").alias("block_key"), "collection", "entity_id").distinct()
