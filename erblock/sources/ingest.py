"""Triples and descriptions.

The engine's form is long: collection, entity_id, attribute, value, kind ('literal' or 'uri').  It is the
triple table itself, so building descriptions needs no shuffle; the nested form is made on request.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

COLUMNS = ("collection", "entity_id", "attribute", "value", "kind")


def descriptions(triples: DataFrame, nested: bool = False) -> DataFrame:
    """Triples (collection, subject, predicate, object, object_kind) grouped by subject."""
    t = drop_blank_nodes(triples)
    long = t.select("collection", F.col("subject").alias("entity_id"), F.col("predicate").alias("attribute"), F.col("object").alias("value"), F.col("object_kind").alias("kind"))
    return nest(long) if nested else long


def nest(desc: DataFrame) -> DataFrame:
    """One row per description, its attribute-value pairs as a set."""
    return desc.groupBy("collection", "entity_id").agg(F.array_sort(F.collect_set(F.struct("attribute", "value", "kind"))).alias("attrs"))


def drop_blank_nodes(triples: DataFrame) -> DataFrame:
    return triples.where("not startswith(subject, '_:') and not (object_kind <> 'literal' and startswith(object, '_:'))")


def hide_truth(triples: DataFrame, predicate: str, truth: DataFrame | None = None) -> DataFrame:
    """Without the triples that state the known links: all with the predicate, or, of these, the pairs of ``truth`` in
    either direction."""
    stated = F.col("predicate") == predicate
    if truth is None:
        return triples.where(~stated)
    links = truth.select(F.col("left_id").alias("subject"), F.col("right_id").alias("object"))
    links = links.unionByName(links.select(F.col("object").alias("subject"), F.col("subject").alias("object"))).distinct()
    return triples.where(~stated).unionByName(triples.where(stated).join(links, ["subject", "object"], "left_anti").select(*triples.columns))


def keep_linked(desc: DataFrame, truth: DataFrame, side: str) -> DataFrame:
    """Descriptions that the truth mentions on a side ('left' or 'right')."""
    ids = truth.select(F.col(f"{side}_id").alias("entity_id")).distinct()
    return desc.join(ids, "entity_id", "left_semi").select(*desc.columns)


def combine_dirty(a: DataFrame, b: DataFrame) -> DataFrame:
    """One collection of two; matches may lie inside either."""
    return a.unionByName(b)


def combine_clean(a: DataFrame, b: DataFrame) -> DataFrame:
    """Two duplicate-free collections, named L and R."""
    return a.withColumn("collection", F.lit("L")).unionByName(b.withColumn("collection", F.lit("R")))


def unpivot(df: DataFrame, collection: str, entity: F.Column | str, cols: Sequence[str], uri_cols: Sequence[str] = ()) -> DataFrame:
    """Any table as descriptions: a row per non-null cell of ``cols``; one scan, no shuffle."""
    cells = F.array(*[F.struct(F.lit(c).alias("attribute"), F.col(c).cast("string").alias("value"), F.lit("uri" if c in uri_cols else "literal").alias("kind")) for c in cols])
    e = F.expr(entity) if isinstance(entity, str) else entity
    return df.select(F.lit(collection).alias("collection"), e.alias("entity_id"), F.explode(cells).alias("x")).select("collection", "entity_id", "x.*").where("value is not null")


def _unescaped(literal: F.Column) -> F.Column:
    """Escapes of a literal undone: those of JSON and the single quote; one that JSON doesn't know leaves the literal as it is."""
    plain = F.regexp_replace(literal, r"(?<!\\)((?:\\\\)*)\\'", "$1'")
    parsed = F.from_json(F.concat(F.lit('["'), plain, F.lit('"]')), "array<string>", {"allowUnquotedControlChars": "true"})
    return F.when(literal.contains("\\"), F.coalesce(F.get(parsed, F.lit(0)), literal)).otherwise(literal)


def read_ntriples(spark: SparkSession, path: str, collection: str = "L") -> tuple[DataFrame, DataFrame]:
    """(triples, rejected lines) of an N-Triples text file."""
    pattern = r'^\s*(<[^>]*>|_:\S+)\s+<([^>]*)>\s+(<[^>]*>|_:\S+|"(?:[^"\\]|\\.)*"\S*)\s*\.\s*$'
    lines = spark.read.text(path).where(r"not value rlike '^\\s*(#.*)?$'")
    good = lines.where(F.col("value").rlike(pattern))
    part = lambda i: F.regexp_extract("value", pattern, i)
    obj = part(3)
    triples = good.select(
        F.lit(collection).alias("collection"),
        F.regexp_replace(part(1), "^<|>$", "").alias("subject"),
        part(2).alias("predicate"),
        F.when(obj.startswith('"'), _unescaped(F.regexp_extract(obj, r'^"((?:[^"\\]|\\.)*)"', 1))).otherwise(F.regexp_replace(obj, "^<|>$", "")).alias("object"),
        F.when(obj.startswith('"'), "literal").when(obj.startswith("_:"), "blank").otherwise("uri").alias("object_kind"),
    )
    return triples, lines.where(~F.col("value").rlike(pattern))
