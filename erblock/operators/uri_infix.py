"""Prefix-infix(-suffix) blocking: blocks from literal tokens and from the infixes of URIs.

For every URI that prefix is cut which has the most distinct next parts among the URIs of its domain; the same
on the reversed rest cuts the suffix.  Groups are (domain, prefix) and only counted, so a domain that
holds most URIs is not a task of its own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from erblock.functions.text import uri_parts
from erblock.operators.token_blocking import build as token_postings


def uris(desc: DataFrame, include_subject: bool = True, include_values: bool = True) -> DataFrame:
    """collection, entity_id, uri of subjects and URI values."""
    own = desc.select("collection", "entity_id", F.col("entity_id").alias("uri")).distinct()
    values = desc.where("kind = 'uri'").select("collection", "entity_id", F.col("value").alias("uri")).distinct()
    both = own.unionByName(values).distinct() if include_subject and include_values else own if include_subject else values
    return both.where(F.col("uri").rlike("^[A-Za-z][A-Za-z0-9+.-]*://"))


def _counts(rows: DataFrame, scope: list[str], lengths: F.Column) -> DataFrame:
    """scope, prefix, n_next: distinct next parts of every prefix (of the parts column)."""
    each = rows.select(*scope, "parts", F.explode(lengths).alias("len"))
    step = each.select(*scope, F.array_join(F.slice("parts", 1, F.col("len")), "").alias("prefix"), F.get("parts", F.col("len")).alias("next"))
    return step.distinct().groupBy(*scope, "prefix").agg(F.count(F.lit(1)).alias("n_next"))


def strip_prefix(named: DataFrame, ties: str = "longest") -> DataFrame:
    """uri, domain, prefix, rest (parts) of distinct URIs.

    Where no prefix branches the cut lies right behind the host.
    """
    u = named.select("uri").distinct().withColumn("parts", uri_parts(F.col("uri"))).where(F.size("parts") > 1)
    u = u.withColumn("domain", F.get("parts", F.lit(1)))
    # Host: parts before the first that starts with a single slash (or other path delimiter).
    host = F.greatest(F.size(F.filter("parts", lambda p, i: (i < 2) | p.startswith("."))), F.lit(1))
    u = u.withColumn("host", F.least(host, F.size("parts") - 1))
    lengths = F.sequence(F.lit(1), F.size("parts") - 1)
    n = _counts(u, ["domain"], lengths)
    each = u.select("uri", "domain", "parts", "host", F.explode(lengths).alias("len"))
    each = each.withColumn("prefix", F.array_join(F.slice("parts", 1, F.col("len")), "")).join(n, ["domain", "prefix"])
    w = Window.partitionBy("uri").orderBy(F.desc("n_next"), F.desc("len") if ties == "longest" else F.asc("len"))
    best = each.withColumn("r", F.row_number().over(w)).where("r = 1")
    cut = F.when(F.col("n_next") > 1, F.col("len")).otherwise(F.col("host"))
    best = best.withColumn("cut", cut)
    return best.select("uri", "domain", F.array_join(F.slice("parts", 1, F.col("cut")), "").alias("prefix"), F.slice("parts", F.col("cut") + 1, F.size("parts")).alias("rest"))


def strip_suffix(stripped: DataFrame, suffix_rule: str = "support", min_support: int = 3, suffix_scope: str = "all", ties: str = "longest") -> DataFrame:
    """uri, domain, prefix, infix, suffix.

    suffix_rule: 'literal' always cuts the best-branching reversed prefix; 'allow_empty' lets "nothing"
    compete; 'support' cuts only one with at least ``min_support`` distinct next parts.
    """
    if suffix_rule not in ("literal", "allow_empty", "support"):
        raise ValueError(suffix_rule)
    scope = ["domain"] if suffix_scope == "domain" else ["one"]
    r = stripped.withColumns({"parts": F.reverse("rest"), "one": F.lit(1)})
    first = 0 if suffix_rule == "allow_empty" else 1
    lengths = F.when(F.size("parts") > first, F.sequence(F.lit(first), F.size("parts") - 1)).otherwise(F.array().cast("array<int>"))
    distinct_rests = r.select(*scope, "parts").distinct()
    n = _counts(distinct_rests, scope, lengths)
    if suffix_rule == "support":
        n = n.where(F.col("n_next") >= min_support)
    each = r.select("uri", *scope, F.explode(lengths).alias("len"), "parts")
    each = each.withColumn("prefix", F.array_join(F.slice("parts", 1, F.col("len")), "")).join(n, [*scope, "prefix"])
    w = Window.partitionBy("uri").orderBy(F.desc("n_next"), F.desc("len") if ties == "longest" else F.asc("len"))
    best = each.withColumn("k", F.row_number().over(w)).where("k = 1").select("uri", F.col("len").alias("cut"))
    out = stripped.join(best, "uri", "left").withColumn("cut", F.coalesce("cut", F.lit(0)))
    keep = F.size("rest") - F.col("cut")
    return out.select("uri", "domain", "prefix", F.array_join(F.slice("rest", 1, keep), "").alias("infix"), F.array_join(F.slice("rest", keep + 1, F.size("rest")), "").alias("suffix"))


def infixes(desc: DataFrame, suffix: bool = True, ties: str = "longest", **options: object) -> DataFrame:
    """collection, entity_id, domain, infix of every URI of every description."""
    named = uris(desc)
    stripped = strip_prefix(named, ties)
    parts = strip_suffix(stripped, ties=ties, **options) if suffix else stripped.withColumn("infix", F.array_join("rest", ""))
    return named.join(parts, "uri").select("collection", "entity_id", "domain", "infix").where("infix <> ''").distinct()


def infix_postings(found: DataFrame) -> DataFrame:
    return found.select(F.col("infix").alias("block_key"), "collection", "entity_id").distinct()


def build(desc: DataFrame, shared_keys: bool = True, **options: object) -> DataFrame:
    """Postings of infixes and of tokens of literal values, in one key space or two."""
    names = infix_postings(infixes(desc, **options))
    literals = token_postings(desc, kinds=("literal",))
    if not shared_keys:
        names = names.withColumn("block_key", F.concat(F.lit("i:"), "block_key"))
        literals = literals.withColumn("block_key", F.concat(F.lit("t:"), "block_key"))
    return names.unionByName(literals).distinct()


def applicable(desc: DataFrame, min_share: float = 0.5) -> DataFrame:
    """share of descriptions whose id is a URI, and whether that is enough."""
    ids = desc.select("collection", "entity_id").distinct()
    share = F.avg(F.col("entity_id").rlike("^[A-Za-z][A-Za-z0-9+.-]*://").cast("int"))
    return ids.agg(share.alias("share")).withColumn("applicable", F.col("share") >= min_share)
