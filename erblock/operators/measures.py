"""Quality and cost of a blocking collection, and descriptive statistics.

Recall never expands pairs (truth joined with postings on both sides); comparisons are counted from block
sizes; only precision on distinct pairs asks for candidates, exactly or by sketch.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from erblock.functions.cut import discard, fits, written
from erblock.functions.text import harmonic, tokens, try_ratio
from erblock.operators import blocks, pairs

BIG = blocks.BIG


def exhaustive(desc: DataFrame, task: str) -> DataFrame:
    """n_left, n_right, exhaustive: the comparisons without blocking."""
    ids = desc.select("collection", "entity_id")
    ids = ids if "keys" in desc.columns else ids.distinct()  # bags have a row per description
    right = F.col("collection") == "R" if task == "clean" else F.lit(False)
    n = ids.agg(F.count_if(~right).alias("n_left"), F.count_if(right).alias("n_right"))
    return n.withColumn("exhaustive", blocks.comparisons(task))


def hits(postings: DataFrame, truth: DataFrame) -> DataFrame:
    """left_id, right_id, link_type, hit: whether a true pair shares a block."""
    found = blocks.same_block(postings, truth).withColumn("hit", F.lit(True))
    return truth.join(found, ["left_id", "right_id"], "left").select("left_id", "right_id", "link_type", F.coalesce("hit", F.lit(False)).alias("hit"))


def recall_by(found: DataFrame, dims: list[str], mode: str = "group") -> DataFrame:
    """links, tp, recall per combination of ``dims`` (mode: group, rollup or cube)."""
    g = {"group": found.groupBy, "rollup": found.rollup, "cube": found.cube}[mode](*dims)
    return g.agg(F.count(F.lit(1)).alias("links"), F.count_if("hit").alias("tp")).withColumn("recall", try_ratio(F.col("tp"), F.col("links")))


def quality(postings: DataFrame, desc: DataFrame, truth: DataFrame, task: str, distinct_pairs: str = "count") -> DataFrame:
    """One row: blocks, comparisons, distinct_pairs, tp, fn, fp, tn, recall, precision, precision_raw, f, rr, h3r.

    distinct_pairs: 'count' (exact, pairs inside the largest blocks by arithmetic), 'exact' and 'min_key' (all
    expanded), 'sketch' or 'none' (fp, tn, precision and f are null then).  Without truth recall is null, without candidates
    precision; a reduction ratio below 0 has no harmonic mean with recall.  ``postings`` may be ``blocks.bags``, and
    ``desc``, too, if every description has a row.
    """
    rows, postings = postings, blocks.unbagged(postings)
    numbers = None
    if distinct_pairs == "count" and "keys" in rows.columns:
        useful, numbers = pairs.numbered(rows, task)
        shared = pairs.shares_ids(rows)
        # A true pair of different ids can only meet in a useful block, unless an id stands for two descriptions.
        known = rows if shared else numbers.select("collection", "entity_id", F.col("ids").alias("keys"))
    else:
        useful, known = blocks.summary(postings, task), rows
    s = useful.agg(F.count(F.lit(1)).alias("blocks"), F.coalesce(F.sum("comparisons"), F.lit(0)).cast(BIG).alias("comparisons"))
    if distinct_pairs == "sketch":
        p = pairs.sketch(postings, task)
    elif distinct_pairs == "count":
        p = pairs.count(rows, task) if numbers is None else pairs.count_numbered(numbers, task, shared)
    elif distinct_pairs == "none":
        p = s.select(F.lit(None).cast("long").alias("distinct_pairs"))
    else:
        p = pairs.distinct(postings, task, distinct_pairs).agg(F.count(F.lit(1)).alias("distinct_pairs"))
    t = hits(known, truth).agg(F.count_if("hit").alias("tp"), F.count_if(~F.col("hit")).alias("fn"))
    if numbers is not None:  # what was shuffled for it is deleted, and what was numbered
        s, t = written(s), written(t)
        discard(useful, numbers)
    one = s.crossJoin(p).crossJoin(t).crossJoin(exhaustive(desc, task).select("exhaustive"))  # four single rows
    one = one.withColumns(
        {
            "fp": F.when(F.col("distinct_pairs").isNotNull(), F.greatest(F.col("distinct_pairs") - F.col("tp"), F.lit(0))).cast(BIG),
            "recall": try_ratio(F.col("tp"), F.col("tp") + F.col("fn")),
            "precision": try_ratio(F.col("tp"), F.col("distinct_pairs")),
            "precision_raw": try_ratio(F.col("tp"), F.col("comparisons")),
            "rr": 1 - try_ratio(F.col("comparisons"), F.col("exhaustive")),
        }
    )
    one = one.withColumns(
        {
            "tn": (F.col("exhaustive") - F.col("tp") - F.col("fp") - F.col("fn")).cast(BIG),
            "f": harmonic(F.col("precision"), F.col("recall")),
            "h3r": F.when(F.col("rr") >= 0, harmonic(F.col("rr"), F.col("recall"))),
        }
    )
    text = {c: F.col(c).cast("string") for c in ("comparisons", "exhaustive", "fp", "tn")}
    rounded = {c: F.round(c, 10) for c in ("recall", "precision", "precision_raw", "f", "rr", "h3r")}
    order = ("blocks", "comparisons", "distinct_pairs", "exhaustive", "tp", "fn", "fp", "tn", "recall", "precision", "precision_raw", "f", "rr", "h3r")
    return one.withColumns(text | rounded).select(*order)


def delta(metrics: DataFrame, base: str = "token") -> DataFrame:
    """Each method against the base on the same collection and task: recall points, misses, ratios."""
    b = metrics.where(F.col("method") == base).select("collection", "task", F.col("recall").alias("br"), F.col("precision").alias("bp"), F.col("fn").alias("bf"), F.col("comparisons").alias("bc"))
    j = metrics.where(F.col("method") != base).join(b, ["collection", "task"])
    return j.select(
        "collection",
        "task",
        "method",
        F.round((F.col("recall") - F.col("br")) * 100, 8).alias("recall_points"),
        (F.col("fn") - F.col("bf")).alias("extra_misses"),
        F.round(F.try_divide("precision", "bp"), 8).alias("precision_ratio"),
        F.round(try_ratio(F.col("comparisons"), F.col("bc")), 8).alias("comparison_ratio"),
    )


def characteristics(desc: DataFrame, truth: DataFrame | None = None, type_attribute: str = "type") -> DataFrame:
    """Per collection: triples, descriptions, pairs per description, attributes, entity types, attributes per type;
    with truth also duplicates: pairs of its descriptions that share a match."""
    is_type = F.col("attribute") == type_attribute
    c = desc.groupBy("collection").agg(
        F.count(F.lit(1)).alias("triples"),
        F.count_distinct("entity_id").alias("descriptions"),
        F.count_distinct("attribute").alias("attributes"),
        F.count_distinct(F.when(is_type, F.col("value"))).alias("types"),
    )
    c = c.withColumns({"pairs_per_description": F.round(try_ratio(F.col("triples"), F.col("descriptions")), 8), "attributes_per_type": F.round(try_ratio(F.col("attributes"), F.col("types")), 8)})
    if truth is None:
        return c
    d = duplicates(truth).unpivot([], ["L", "R"], "collection", "duplicates")
    return c.join(F.broadcast(d), "collection", "left")


def duplicates(truth: DataFrame) -> DataFrame:
    """L, R: pairs of descriptions of the left (right) collection that share a match."""
    t = truth.select("left_id", "right_id").distinct()
    n = F.count(F.lit(1))
    pairs_of = lambda c: t.groupBy(c).agg((n * (n - 1) / 2).cast("long").alias("k")).agg(F.coalesce(F.sum("k"), F.lit(0)))
    return pairs_of("right_id").toDF("L").crossJoin(pairs_of("left_id").toDF("R"))


def combined(desc: DataFrame, truth: DataFrame) -> DataFrame:
    """One row for a collection of two: sizes, matches with and without duplicates, comparisons of both tasks without
    blocking, and the ratio of matches to non-matches."""
    ids = exhaustive(desc, "clean").select("n_left", "n_right", F.col("exhaustive").alias("clean"))
    n = (F.col("n_left") + F.col("n_right")).cast("decimal(20,0)")
    d = desc.agg(F.count(F.lit(1)).alias("triples"), F.count_distinct("collection", "attribute").alias("attributes"), F.count_distinct(F.when(F.col("attribute") == "type", F.struct("collection", "value"))).alias("types"))
    m = truth.select("left_id", "right_id").distinct().agg(F.count(F.lit(1)).alias("matches"))
    one = ids.crossJoin(d).crossJoin(m).crossJoin(duplicates(truth)).withColumn("dirty", ((n * (n - 1)) / 2).cast(BIG))
    one = one.withColumns({"matches_with_duplicates": F.col("matches") + F.col("L") + F.col("R"), "pairs_per_description": F.round(try_ratio(F.col("triples"), F.col("n_left") + F.col("n_right")), 8)})
    ratio = lambda k, z: F.round(try_ratio(F.col(k), F.col(z) - F.col(k)), 12)
    return one.select(
        "n_left", "n_right", "triples", "attributes", "types", "pairs_per_description", "matches", "matches_with_duplicates",
        F.col("clean").cast("string").alias("clean"), F.col("dirty").cast("string").alias("dirty"), ratio("matches", "clean").alias("ratio_clean"), ratio("matches_with_duplicates", "dirty").alias("ratio_dirty"),
    )


#: Tasks that descriptions are dealt to for a count, so that each holds a small part in memory.
PARTS = 128


def common_tokens(desc: DataFrame, clusters: DataFrame | None = None) -> DataFrame:
    """A row per description with n: tokens that the other collection has, too (in the same cluster, if given); those
    without any count 0.

    A description goes by 96 bits of its id.  Only common tokens are shuffled, as numbers: the common vocabulary, or
    where it is too large its most frequent part, is sent to the values, and the rest joined.
    """
    found = tokens(F.col("value"))
    if clusters is not None:
        desc = desc.join(F.broadcast(clusters) if fits(clusters) else clusters, ["collection", "attribute"], "left")
        found = F.when(F.col("cluster_id").isNotNull(), F.transform(found, lambda t: F.concat(F.col("cluster_id"), F.lit("\u0001"), t)))
    name = [F.xxhash64("collection", "entity_id").alias("a"), F.hash("collection", "entity_id").alias("b")]
    ids = desc.select(*name, F.lit(None).cast("long").alias("id"))
    each = desc.select("collection", (F.col("entity_id").isNotNull()).alias("named"), *name, F.explode(found).alias("token"))
    right = F.col("collection") == "R"
    vocabulary = each.groupBy("token").agg(F.count(F.lit(1)).alias("k"), F.count_if(right).alias("r")).where("r > 0 and r < k")
    vocabulary = written(vocabulary.select("token", "k"), "zstd").withColumn("id", F.monotonically_increasing_id())
    each = each.where("named").select("a", "b", "token")
    least, frequent = 0, vocabulary
    while not fits(frequent):
        least = max(least * 10, 10)
        frequent = vocabulary.where(F.col("k") >= least)
    frequent = F.broadcast(frequent.select("token", "id"))
    common = [ids, each.join(frequent, "token").select("a", "b", "id")]
    if least:
        rare = vocabulary.where(F.col("k") < least).select("token", "id")
        common.append(written(each.join(frequent, "token", "left_anti").join(rare.hint("shuffle_hash"), "token").select("a", "b", "id"), "zstd"))
    dealt = reduce(DataFrame.unionByName, common).repartition(PARTS, "a", "b")
    return dealt.groupBy("a", "b", "id").agg(F.lit(1)).groupBy("a", "b").agg(F.count("id").alias("n")).select("n")


def histogram(common: DataFrame) -> DataFrame:
    """n, descriptions: small whole numbers, so the distribution is exact at any size."""
    return common.groupBy("n").agg(F.count(F.lit(1)).alias("descriptions"))


def median_of(common: DataFrame) -> DataFrame:
    """Exact median from the histogram: the counts are few even when descriptions aren't."""
    return histogram(common).agg(F.expr("percentile(n, 0.5, descriptions)").alias("median"))


def band_share(counts: DataFrame, lo: int, hi: int) -> DataFrame:
    """share of descriptions with lo to hi, of a ``histogram``."""
    inside = F.coalesce(F.sum(F.when(F.col("n").between(lo, hi), F.col("descriptions"))), F.lit(0))
    return counts.agg(F.round(inside / F.sum("descriptions"), 10).alias("share"))


def cluster_stats(clusters: DataFrame) -> DataFrame:
    """n_clusters, median_attributes."""
    per = clusters.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("k"))
    return per.agg(F.count(F.lit(1)).alias("n_clusters"), F.median("k").alias("median_attributes"))
