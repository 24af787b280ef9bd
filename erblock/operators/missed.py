"""Forensics of missed matches, neighbours of sampled pairs, and recall by link type."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from erblock.functions.cut import written
from erblock.operators.measures import hits

PAIR = ["left_id", "right_id"]


def _ids(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.explode(F.array("left_id", "right_id")).alias("id")).distinct()


def matching_neighbours(pairs: DataFrame, edges: DataFrame, truth: DataFrame) -> DataFrame:
    """Pairs of which some neighbour of one is a known match of some neighbour of the other."""
    near = lambda side: edges.select(F.col("src_id").alias(f"{side}_id"), F.col("dst_id").alias(f"{side}_n"))
    both = truth.select(F.col("left_id").alias("left_n"), F.col("right_id").alias("right_n"))
    both = both.unionByName(both.select(F.col("right_n").alias("left_n"), F.col("left_n").alias("right_n"))).distinct()
    first = pairs.select(*PAIR).join(near("left"), "left_id").join(both, "left_n").select(*PAIR, "right_n").distinct()
    return first.join(near("right"), ["right_id", "right_n"], "left_semi").select(*PAIR).distinct()


def common_match(pairs: DataFrame, found: DataFrame) -> DataFrame:
    """Pairs whose two descriptions were both matched with the same third one."""
    sym = found.select(F.col("left_id").alias("x"), F.col("right_id").alias("y"))
    sym = sym.unionByName(sym.select(F.col("y").alias("x"), F.col("x").alias("y"))).distinct()
    left = pairs.select(*PAIR).join(sym.select(F.col("x").alias("left_id"), "y"), "left_id")
    return left.join(sym.select(F.col("x").alias("right_id"), "y"), ["right_id", "y"], "left_semi").select(*PAIR).distinct()


def report(postings: DataFrame, truth: DataFrame, edges: DataFrame) -> DataFrame:
    """measure, numerator, denominator, pct: who the missed matches are.

    Matches and links are looked up once, in tables of the shared folder; all measures are made of these.
    """
    found = written(hits(postings, truth), "zstd")
    fn, tp = found.where(~F.col("hit")).select(*PAIR), found.where("hit").select(*PAIR)
    edges, truth = written(edges, "zstd"), found.select(*PAIR)
    lost = _ids(fn)
    reach = edges.join(lost.withColumnRenamed("id", "src_id"), "src_id", "left_semi")
    of = lambda ids: reach.join(ids.withColumnRenamed("id", "dst_id"), "dst_id", "left_semi").select("src_id").distinct()
    n_fn, n_lost = fn.agg(F.count(F.lit(1)).alias("denominator")), lost.agg(F.count(F.lit(1)).alias("denominator"))
    parts = [
        ("missed_pairs", fn, n_fn),
        ("descriptions_with_neighbours", reach.select("src_id").distinct(), n_lost),
        ("descriptions_with_neighbours_in_truth", of(_ids(truth)), n_lost),
        ("descriptions_with_matched_neighbours", of(_ids(tp)), n_lost),
        ("pairs_with_matching_neighbours", matching_neighbours(fn, edges, truth), n_fn),
        ("pairs_with_common_match", common_match(fn, tp), n_fn),
    ]
    rows = [written(df.agg(F.count(F.lit(1)).alias("numerator")).crossJoin(n).select(F.lit(name).alias("measure"), "numerator", "denominator")) for name, df, n in parts]
    return reduce(DataFrame.unionByName, rows).withColumn("pct", F.round(F.try_divide(F.col("numerator") * 100.0, "denominator"), 8))


def sample_matches(truth: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """k true pairs by the order of an md5, which any engine repeats."""
    h = F.md5(F.concat_ws("|", "left_id", "right_id", F.lit(str(seed))))
    return truth.select(*PAIR).distinct().orderBy(h, *PAIR).limit(k)


def sample_non_matches(desc: DataFrame, truth: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """k pairs of a left and a right description of the whole collections that aren't true.

    Ids of either side are put in the order of an md5 of their own and paired by rank; true pairs are left out.
    """

    def drawn(side: str, name: str) -> DataFrame:
        h = F.md5(F.concat_ws("|", name, F.lit(f"{seed}{side}")))
        ids = desc.where(F.col("collection") == side).select(F.col("entity_id").alias(name)).distinct().withColumn("h", h)
        first = ids.orderBy("h", name).limit(2 * k)
        return first.select(name, F.row_number().over(Window.orderBy("h", name)).alias("i"))  # over 2 k rows

    paired = drawn("L", "left_id").join(drawn("R", "right_id"), "i")
    return paired.join(truth.select(*PAIR).distinct(), PAIR, "left_anti").orderBy("i").limit(k).select(*PAIR)


def structural(desc: DataFrame, truth: DataFrame, edges: DataFrame, k: int = 1000, seed: int = 42) -> DataFrame:
    """kind, pairs, with_neighbours, median_neighbour_pairs, with_matching_neighbours for k matches and k non-matches."""
    deg = edges.groupBy("src_id").agg(F.count(F.lit(1)).alias("deg"))

    def one(kind: str, pairs: DataFrame) -> DataFrame:
        d = pairs.join(deg.select(F.col("src_id").alias("left_id"), F.col("deg").alias("ld")), "left_id", "left").join(deg.select(F.col("src_id").alias("right_id"), F.col("deg").alias("rd")), "right_id", "left")
        counts = d.agg(F.count(F.lit(1)).alias("pairs"), F.count_if(F.expr("ld > 0 and rd > 0")).alias("with_neighbours"), F.median(F.when(F.expr("ld > 0 and rd > 0"), F.col("ld") * F.col("rd"))).alias("median_neighbour_pairs"))
        m = matching_neighbours(pairs, edges, truth).agg(F.count(F.lit(1)).alias("with_matching_neighbours"))
        return counts.crossJoin(m).select(F.lit(kind).alias("kind"), "*")

    return one("match", sample_matches(truth, k, seed)).unionByName(one("non_match", sample_non_matches(desc, truth, k, seed)))


def split_by_clusters(token: DataFrame, attribute: DataFrame, truth: DataFrame) -> DataFrame:
    """Whether attribute clustering misses just what token blocking misses and what shares tokens in different clusters
    only: missed_token, missed_attribute, split (found by tokens, missed by clusters), missed_token_only (0)."""
    hit = lambda p, name: hits(p, truth).groupBy(*PAIR).agg(F.max("hit").alias(name))
    both = hit(token, "t").join(hit(attribute, "a"), PAIR)
    return both.agg(F.count_if(~F.col("t")).alias("missed_token"), F.count_if(~F.col("a")).alias("missed_attribute"), F.count_if(F.col("t") & ~F.col("a")).alias("split"), F.count_if(~F.col("t") & F.col("a")).alias("missed_token_only"))


def split_by_parts(literals: DataFrame, infixes: DataFrame, uri: DataFrame, truth: DataFrame) -> DataFrame:
    """Whether the URI method misses just the pairs with no common literal token and no common infix: missed_uri,
    without_token_and_infix (of those with separate key spaces), common_infix_only, common_token_only."""
    hit = lambda p, name: hits(p, truth).groupBy(*PAIR).agg(F.max("hit").alias(name))
    all_ = hit(literals, "l").join(hit(infixes, "i"), PAIR).join(hit(uri, "u"), PAIR)
    l, i = F.col("l"), F.col("i")
    return all_.agg(F.count_if(~F.col("u")).alias("missed_uri"), F.count_if(~l & ~i).alias("without_token_and_infix"), F.count_if(i & ~l).alias("common_infix_only"), F.count_if(l & ~i).alias("common_token_only"))
