"""Ground truth: pairs (left_id, right_id, link_type)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from erblock.operators.components import connected


def close(truth: DataFrame, max_rounds: int = 50) -> DataFrame:
    """All pairs implied by chains of equivalences; output left_id < right_id.

    Costs the sum of squared component sizes, as the closed truth is that large.
    """
    comp = connected(truth, "left_id", "right_id", max_rounds)
    other = comp.select(F.col("node").alias("right_id"), F.col("component").alias("c"))
    pairs = comp.join(other, comp["component"] == other["c"]).where("node < right_id")
    return pairs.select(F.col("node").alias("left_id"), "right_id", F.lit("equivalence").alias("link_type"))


def edges(desc: DataFrame) -> DataFrame:
    """src_id, dst_id: URI values that name another description."""
    ids = desc.select(F.col("entity_id").alias("dst_id")).distinct()
    out = desc.where("kind = 'uri'").select(F.col("entity_id").alias("src_id"), F.col("value").alias("dst_id")).distinct()
    return out.join(ids, "dst_id", "left_semi").where("src_id <> dst_id").select("src_id", "dst_id")
