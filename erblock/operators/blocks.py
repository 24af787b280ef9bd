"""Blocks in long form: postings (block_key, collection, entity_id), distinct.

No block is ever gathered in a row, and nothing here expands pairs: comparisons are counted from sizes.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BIG = "decimal(38,0)"


def comparisons(task: str) -> Column:
    """Comparisons of a block from n_left and n_right (all in n_left if dirty)."""
    left, right = F.col("n_left").cast(BIG), F.col("n_right").cast(BIG)
    if task == "clean":
        return (left * right).cast(BIG)
    n = (left + right).cast("decimal(20,0)")
    return ((n * (n - 1)) / 2).cast(BIG)


def summary(postings: DataFrame, task: str) -> DataFrame:
    """block_key, n_left, n_right, comparisons of every useful block.

    Useful: at least two descriptions (dirty), or both collections (clean).
    """
    right = F.col("collection") == "R" if task == "clean" else F.lit(False)
    sizes = postings.groupBy("block_key").agg(F.count_if(~right).alias("n_left"), F.count_if(right).alias("n_right"))
    sizes = sizes.where("n_left > 0 and n_right > 0" if task == "clean" else "n_left > 1")
    return sizes.withColumn("comparisons", comparisons(task))


def useful(postings: DataFrame, task: str) -> DataFrame:
    """Postings of useful blocks only."""
    return postings.join(summary(postings, task).select("block_key"), "block_key", "left_semi")


def purge(postings: DataFrame, task: str, max_comparisons: int | None = None) -> DataFrame:
    """Optional: without blocks above a number of comparisons (None: all stay)."""
    if max_comparisons is None:
        return postings
    big = summary(postings, task).where(F.col("comparisons") > max_comparisons).select("block_key")
    return postings.join(big, "block_key", "left_anti")


def hash_keys(postings: DataFrame) -> DataFrame:
    """64-bit keys instead of strings: a smaller shuffle; distinct keys may collide (p about n^2 / 2^65)."""
    return postings.withColumn("block_key", F.xxhash64("block_key")).distinct()


def bags(postings: DataFrame) -> DataFrame:
    """collection, entity_id, keys: a description's keys in one row, as long as the description itself.

    No exchange where postings are dealt by entity_id, as those of the builders are.
    """
    return postings.groupBy("collection", "entity_id").agg(F.collect_set("block_key").alias("keys"))


def unbagged(rows: DataFrame) -> DataFrame:
    """Postings of ``bags``; postings stay as they are."""
    return rows.select(F.explode("keys").alias("block_key"), "collection", "entity_id") if "keys" in rows.columns else rows


def same_block(postings: DataFrame, pairs: DataFrame) -> DataFrame:
    """Of pairs (left_id, right_id) those with a common block; joins descriptions (postings or ``bags``), expands neither pairs nor keys."""
    rows = postings if "keys" in postings.columns else bags(postings)
    keys = lambda side: rows.select(F.col("entity_id").alias(f"{side}_id"), F.col("keys").alias(f"{side}_keys"))
    both = pairs.select("left_id", "right_id").distinct().join(keys("left"), "left_id").join(keys("right"), "right_id")
    return both.where(F.arrays_overlap("left_keys", "right_keys")).select("left_id", "right_id").distinct()
