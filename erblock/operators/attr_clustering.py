"""Attribute-clustering blocking of two clean collections.

Attributes are compared by the Jaccard similarity of the gram sets of all their values.  Pairs come from a
join on grams, not from comparing every attribute with every other; each attribute links to its most
similar one on the other side, linked attributes form clusters, and a block key is (cluster, token).
Default for attributes similar to none: dropped, as their blocks would have one side only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from erblock.functions.cut import discard, written
from erblock.functions.text import grams as gram_array
from erblock.functions.text import tokens
from erblock.operators.components import connected
from erblock.operators.token_blocking import description_tokens

SEP = "\u0001"
#: Attributes up to which the clusters are broadcast (a row is two names).
BROADCAST_ATTRIBUTES = 200_000


def grams(desc: DataFrame, n: int = 3, unit: str = "token") -> DataFrame:
    """collection, attribute, gram, distinct. unit: grams inside tokens ('token'), of whole values ('value'),
    or whole words instead of grams ('word')."""
    if unit == "value":
        exploded = desc.select("collection", "attribute", F.explode(gram_array(F.lower("value"), n)).alias("gram"))
    else:
        words = desc.select("collection", "attribute", F.explode(tokens(F.col("value"))).alias("gram")).distinct()
        exploded = words if unit == "word" else words.select("collection", "attribute", F.explode(gram_array(F.col("gram"), n)).alias("gram"))
    return exploded.distinct()


def similarities(gram_rows: DataFrame) -> DataFrame:
    """left_attribute, right_attribute, inter, sim for every pair that shares a gram."""
    sizes = gram_rows.groupBy("collection", "attribute").agg(F.count(F.lit(1)).alias("size"))
    left = gram_rows.where("collection = 'L'").select("gram", F.col("attribute").alias("left_attribute"))
    right = gram_rows.where("collection = 'R'").select("gram", F.col("attribute").alias("right_attribute"))
    inter = left.join(right, "gram").groupBy("left_attribute", "right_attribute").agg(F.count(F.lit(1)).alias("inter"))
    ls = sizes.where("collection = 'L'").select(F.col("attribute").alias("left_attribute"), F.col("size").alias("ls"))
    rs = sizes.where("collection = 'R'").select(F.col("attribute").alias("right_attribute"), F.col("size").alias("rs"))
    both = inter.join(ls, "left_attribute").join(rs, "right_attribute")
    return both.select("left_attribute", "right_attribute", "inter", (F.col("inter") / (F.col("ls") + F.col("rs") - F.col("inter"))).alias("sim"))


def tiled_similarities(gram_rows: DataFrame, tiles: int = 4) -> DataFrame:
    """The same by comparing every pair of attributes, tile against tile (for few, dense attributes).

    Every attribute's gram set goes to the ``tiles`` keys of its row or column, so no task holds more than
    one tile of either side.
    """
    sets = gram_rows.groupBy("collection", "attribute").agg(F.collect_set("gram").alias("grams"))
    own = F.pmod(F.xxhash64("attribute"), F.lit(tiles))
    every = F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)))
    left = sets.where("collection = 'L'").select(own.alias("i"), every.alias("j"), F.col("attribute").alias("left_attribute"), F.col("grams").alias("lg"))
    right = sets.where("collection = 'R'").select(every.alias("i"), own.alias("j"), F.col("attribute").alias("right_attribute"), F.col("grams").alias("rg"))
    joined = left.join(right, ["i", "j"]).withColumn("inter", F.size(F.array_intersect("lg", "rg")).cast("long")).where("inter > 0")
    return joined.select("left_attribute", "right_attribute", "inter", (F.col("inter") / (F.size("lg") + F.size("rg") - F.col("inter"))).alias("sim"))


def minhash_similarities(gram_rows: DataFrame, distance: float = 0.9, tables: int = 16) -> DataFrame:
    """Approximate: pairs that a MinHash join finds below a Jaccard distance."""
    from pyspark.ml.feature import HashingTF, MinHashLSH

    sets = gram_rows.groupBy("collection", "attribute").agg(F.collect_set("gram").alias("grams"))
    vec = HashingTF(inputCol="grams", outputCol="v", binary=True, numFeatures=1 << 18).transform(sets).select("collection", "attribute", "v")
    lsh = MinHashLSH(inputCol="v", outputCol="h", numHashTables=tables, seed=7).fit(vec)
    near = lsh.approxSimilarityJoin(vec.where("collection = 'L'"), vec.where("collection = 'R'"), distance, "d")
    return near.select(F.col("datasetA.attribute").alias("left_attribute"), F.col("datasetB.attribute").alias("right_attribute"), (1 - F.col("d")).alias("sim"))


def best_match(sims: DataFrame, min_similarity: float = 0.0, ties: str = "first") -> DataFrame:
    """collection, attribute, best, sim: the most similar attribute of the other side, for both sides.

    ties: the first by name, or 'all'.  The partial aggregate is the combiner.
    """
    good = sims.where(F.col("sim") > min_similarity)
    sided = good.select(F.lit("L").alias("collection"), F.col("left_attribute").alias("attribute"), F.col("right_attribute").alias("best"), "sim").unionByName(
        good.select(F.lit("R").alias("collection"), F.col("right_attribute").alias("attribute"), F.col("left_attribute").alias("best"), "sim")
    )
    order = F.rank() if ties == "all" else F.row_number()
    by = [F.desc("sim")] if ties == "all" else [F.desc("sim"), F.asc("best")]
    w = Window.partitionBy("collection", "attribute").orderBy(*by)
    return sided.withColumn("r", order.over(w)).where("r = 1").drop("r")


def clusters(best: DataFrame, all_attributes: DataFrame | None = None, unmatched: str = "drop") -> DataFrame:
    """collection, attribute, cluster_id; unmatched='glue' puts attributes without a link in one more cluster."""
    name = lambda side, col: F.concat(F.lit(f"{side}|"), F.col(col))
    edges = best.select(
        F.when(F.col("collection") == "L", name("L", "attribute")).otherwise(name("L", "best")).alias("src"),
        F.when(F.col("collection") == "L", name("R", "best")).otherwise(name("R", "attribute")).alias("dst"),
    ).distinct()
    comp = connected(edges)
    out = comp.select(F.substring("node", 1, 1).alias("collection"), F.expr("substring(node, 3)").alias("attribute"), F.col("component").alias("cluster_id"))
    if unmatched == "glue" and all_attributes is not None:
        rest = all_attributes.select("collection", "attribute").distinct().join(out, ["collection", "attribute"], "left_anti")
        out = out.unionByName(rest.withColumn("cluster_id", F.lit("rest")))
    return out


def find_clusters(desc: DataFrame, unit: str = "token", min_similarity: float = 0.0, method: str = "exact", unmatched: str = "drop") -> DataFrame:
    g = written(grams(desc, unit=unit), "zstd")  # read for sizes and for both sides: values are cut into grams once
    sims = written({"exact": similarities, "tiled": tiled_similarities, "minhash": minhash_similarities}[method](g), "zstd")
    discard(g)
    return clusters(best_match(sims, min_similarity), desc, unmatched)


def bags(desc: DataFrame, found: DataFrame | None = None, **options: object) -> DataFrame:
    """``blocks.bags`` of ``build``, without a row per token; a description without clustered tokens has no keys, but a row."""
    found = find_clusters(desc, **options) if found is None else found
    if found.count() <= BROADCAST_ATTRIBUTES:
        found = F.broadcast(found)
    keys = F.transform(tokens(F.col("value")), lambda t: F.concat_ws(SEP, "cluster_id", t))
    keys = F.when(F.col("cluster_id").isNotNull(), keys).otherwise(F.array().cast("array<string>"))
    each = desc.repartition("entity_id").join(found, ["collection", "attribute"], "left").select("collection", "entity_id", keys.alias("found"))
    return each.groupBy("collection", "entity_id").agg(F.array_distinct(F.flatten(F.collect_list("found"))).alias("keys"))


def build(desc: DataFrame, found: DataFrame | None = None, **options: object) -> DataFrame:
    """Postings with keys (cluster, token)."""
    found = find_clusters(desc, **options) if found is None else found
    if found.count() <= BROADCAST_ATTRIBUTES:
        found = F.broadcast(found)
    t = description_tokens(desc.repartition("entity_id")).join(found, ["collection", "attribute"])
    return t.select(F.concat_ws(SEP, "cluster_id", "token").alias("block_key"), "collection", "entity_id").distinct()
