"""Joins in time, sets of candidates, and a SQL surface around the blocking methods."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from erblock.operators import blocks


def _bucket(ts: str, seconds: int) -> Column:
    return F.floor(F.unix_micros(F.col(ts).cast("timestamp")) / (seconds * 1_000_000)).cast("long")


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, seconds: int = 86_400) -> DataFrame:
    """Columns of ``left`` and as_of: the latest ``ts`` of ``right`` with the same key at or before the row's.

    Keys are cut into spans of time, so a hot key is many tasks; a span takes over the latest time of the
    spans before it from a table of one row per key and span.  Null keys or times match nothing.
    """
    span = lambda df: df.withColumn("_span", _bucket(ts, seconds))
    times = span(right.select(F.col(key).alias("_key"), F.col(ts)).where(F.col(key).isNotNull() & F.col(ts).isNotNull()))
    last = times.groupBy("_key", "_span").agg(F.max(ts).alias("_last"))
    asked = span(left.withColumn("_key", F.col(key)))
    marks = last.select("_key", "_span", "_last").unionByName(asked.select("_key", "_span").distinct().withColumn("_last", F.lit(None)), allowMissingColumns=True)
    marks = marks.groupBy("_key", "_span").agg(F.max("_last").alias("_last"))
    before = Window.partitionBy("_key").orderBy("_span").rowsBetween(Window.unboundedPreceding, -1)
    carried = marks.select("_key", "_span", F.max("_last").over(before).alias("_carried"))
    rows = asked.select(*left.columns, "_key", "_span", F.col(ts).alias("_at"), F.lit(None).cast(right.schema[ts].dataType).alias("_seen"), F.lit(1).alias("_asks"))
    facts = times.select("_key", "_span", F.col(ts).alias("_at"), F.col(ts).alias("_seen"), F.lit(0).alias("_asks"))
    both = rows.unionByName(facts, allowMissingColumns=True)
    within = Window.partitionBy("_key", "_span").orderBy("_at").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    found = both.withColumn("_in", F.max("_seen").over(within)).where("_asks = 1")
    joined = found.join(carried, ["_key", "_span"], "left")
    return joined.select(*left.columns, F.coalesce("_in", "_carried").alias("as_of"))


def interval_join(left: DataFrame, right: DataFrame, key: str, ts: str, id_col: str, seconds: int) -> DataFrame:
    """left_id, right_id of rows with the same key whose times are at most ``seconds`` apart.

    An equi-join on spans of that length: a row meets the rows of its own span and of the two beside it.
    """
    a = left.select(F.col(key).alias("k"), F.col(ts).alias("at"), F.col(id_col).alias("left_id"), _bucket(ts, seconds).alias("span"))
    b = right.select(F.col(key).alias("k"), F.col(ts).alias("bt"), F.col(id_col).alias("right_id"), F.explode(F.array(*[_bucket(ts, seconds) + i for i in (-1, 0, 1)])).alias("span"))
    apart = F.abs(F.unix_micros(F.col("at").cast("timestamp")) - F.unix_micros(F.col("bt").cast("timestamp")))
    return a.join(b, ["k", "span"]).where(apart <= seconds * 1_000_000).select("left_id", "right_id")


def compare_candidates(sets: dict[str, DataFrame]) -> DataFrame:
    """a, b, both, only_a, only_b for every two candidate sets (left_id, right_id)."""
    marked = reduce(DataFrame.unionByName, [df.select("left_id", "right_id").distinct().withColumn("m", F.lit(name)) for name, df in sets.items()])
    has = marked.groupBy("left_id", "right_id").pivot("m", list(sets)).count()
    names, cells = list(sets), []
    for i, x in enumerate(names):
        for y in names[i + 1 :]:
            in_x, in_y = F.col(x).isNotNull(), F.col(y).isNotNull()
            cells.append(F.struct(F.lit(x).alias("a"), F.lit(y).alias("b"), F.count_if(in_x & in_y).alias("both"), F.count_if(in_x & ~in_y).alias("only_a"), F.count_if(~in_x & in_y).alias("only_b")))
    return has.agg(F.array(*cells).alias("cells")).select(F.explode("cells").alias("c")).select("c.*")


def top_blocks(summary: DataFrame, k: int) -> DataFrame:
    """The k blocks with most comparisons, their rank and the running sum of comparisons."""
    most = summary.orderBy(F.desc("comparisons"), "block_key").limit(k)
    w = Window.orderBy(F.desc("comparisons"), "block_key")  # over k rows
    return most.select("block_key", F.row_number().over(w).alias("rank"), F.sum("comparisons").over(w.rowsBetween(Window.unboundedPreceding, 0)).cast("string").alias("running"))


# ---------------------------------------------------------------- SQL surface


@udtf(returnType="token: string")
class TokensOf:
    """Distinct tokens of a value, a row each."""

    def eval(self, value: str) -> Iterator[tuple[str]]:
        import regex

        for t in dict.fromkeys(regex.findall(r"[\p{L}\p{N}]+", (value or "").lower())):
            yield (t,)


@udtf(returnType="part: string, place: int")
class PartsOf:
    """Parts of a URI with their place, a row each."""

    def eval(self, uri: str) -> Iterator[tuple[str, int]]:
        import re

        for i, p in enumerate(re.findall(r"[/#?&=:.]*[^/#?&=:.]+", uri or ""), 1):
            yield p, i


def surface(spark: SparkSession, desc: DataFrame, postings: DataFrame, truth: DataFrame, task: str) -> None:
    """Temporary views descriptions, postings, block_summary and truth, functions tokens_of and parts_of, for SQL users."""
    desc.createOrReplaceTempView("descriptions")
    postings.createOrReplaceTempView("postings")
    blocks.summary(postings, task).createOrReplaceTempView("block_summary")
    truth.createOrReplaceTempView("truth")
    spark.udtf.register("tokens_of", TokensOf)
    spark.udtf.register("parts_of", PartsOf)


# ---------------------------------------------------------------- sinks


def save_postings(postings: DataFrame, path: str, buckets: int = 64, mode: str = "overwrite") -> None:
    """Postings as Parquet in folders by a hash of the key, sorted by key inside: a reader of one key opens one folder."""
    b = F.pmod(F.xxhash64("block_key"), F.lit(buckets)).cast("int")
    postings.withColumn("bucket", b).repartition("bucket").sortWithinPartitions("bucket", "block_key").write.mode(mode).partitionBy("bucket").parquet(path)


def postings_of(spark: SparkSession, path: str, key: str, buckets: int = 64) -> DataFrame:
    """Postings of one key from ``save_postings``: the folder by partition pruning, the rows by a pushed filter."""
    b = spark.range(1).select(F.pmod(F.xxhash64(F.lit(key)), F.lit(buckets)).cast("int")).first()[0]
    return spark.read.parquet(path).where((F.col("bucket") == b) & (F.col("block_key") == key)).drop("bucket")


def save_table(postings: DataFrame, table: str, buckets: int = 64) -> None:
    """Postings as a bucketed table: later joins on the key need no exchange."""
    postings.write.mode("overwrite").bucketBy(buckets, "block_key").sortBy("block_key").saveAsTable(table)
