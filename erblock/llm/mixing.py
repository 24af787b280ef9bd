"""Mix sources to target weights with hash-threshold histograms (native).

1. Target of a source: its weight's share of ``share`` times all sizes, at most ``max_repeat``
   times its own size; the excess is dealt to the others by weight until none is above
   (closed form: sort by cap/weight, prefix sums).
2. Whole copies of the source fill ``floor(target / size)``; the rest is met by the documents whose
   hash lies under a threshold.  Thresholds come from histograms of summed sizes by (source,
   hash bucket): a running sum finds the bucket at the budget, and only that boundary bucket is cut
   finer, four times 12 bits.  No document is sorted, no source gathers in one task.
3. The boundary document is taken if that brings the sum nearer to the target.

Nested: as the hash of a document never changes, a larger budget keeps all that a smaller one took.

Edge cases: null text has size 0; a null source is a source of its own, ordered last; rows that
share an id share a hash, so they are taken together; a null id hashes as the word ``null``;
sources of size 0 get target 0; an empty table gives an empty result; extra columns are ignored (``repeated`` passes
columns of any name).  The table of sources, a row per source, is put in order in one task: windows spill, so that
bounds the number of sources to what one disk sorts (some 10**8), not the documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from erblock.llm.common import checkpoint, fits, row_of, words

BITS, LEVELS = 12, 4


def hashed(id_col: str = "doc_id") -> Column:
    """48 bits of the md5 of the id: the same in any engine."""
    return F.conv(F.substring(F.md5(F.coalesce(F.col(id_col).cast("string"), F.lit("null"))), 1, 12), 16, 10).cast("long")


def sizes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """doc_id, source, size (words) and h of each row."""
    return docs.select(
        F.col(id_col).alias("doc_id"),
        F.col(source_col).alias("source"),
        F.size(words(F.col(text_col))).cast("long").alias("size"),
        hashed(id_col).alias("h"),
    )


def targets(slim: DataFrame, weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, max_repeat: int = 2) -> DataFrame:
    """A row per source: source_size, weight, target, copies (whole passes) and rest."""
    per = slim.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(w) for w in weights]), F.pmod(order, F.lit(len(weights))) + 1)
    per = per.withColumn("weight", weight.cast("long"))
    per = per.withColumn("cap", F.col("source_size") * F.lit(max_repeat))
    every = Window.partitionBy()
    before = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    budget = F.lit(share) * F.sum("source_size").over(every)
    level = (budget - F.coalesce(F.sum("cap").over(before), F.lit(0))) / (F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0)))
    per = per.withColumn("level", level).withColumn("capped", F.col("cap") / F.col("weight") <= F.col("level"))
    shared = F.max(F.when(~F.col("capped"), F.col("level"))).over(every)
    per = per.withColumn("target", F.when(F.col("capped"), F.col("cap").cast("double")).otherwise(F.col("weight") * shared))
    copies = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    per = per.withColumn("copies", copies)
    return per.withColumn("rest", F.col("target") - F.col("copies") * F.col("source_size")).drop("level", "capped", "cap")


def thresholds(slim: DataFrame, tgt: DataFrame) -> DataFrame:
    """Per source the hash ``cut`` under which documents get one more copy; ``at`` says if the
    documents with that very hash do, too."""
    state = tgt.select(F.col("source").alias("s"), F.lit(0).cast("long").alias("prefix"), F.col("rest").alias("left"))
    for level in range(LEVELS):
        shift = BITS * (LEVELS - 1 - level)
        above = shift + BITS
        here = slim if level == 0 else slim.join(state, slim["source"].eqNullSafe(state["s"]) & (F.shiftright(F.col("h"), above) == F.col("prefix")), "left_semi")
        hist = here.groupBy("source", F.shiftright("h", shift).alias("bucket")).agg(F.sum("size").alias("in_bucket"))
        running = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
        hist = hist.withColumn("under", F.coalesce(F.sum("in_bucket").over(running), F.lit(0)))
        found = hist.join(state, hist["source"].eqNullSafe(state["s"])).where((F.col("under") <= F.col("left")) & (F.col("under") + F.col("in_bucket") > F.col("left")))
        state = checkpoint(found.select("s", F.col("bucket").alias("prefix"), (F.col("left") - F.col("under")).alias("left"), F.col("in_bucket").alias("last")))
    return state.select(F.col("s"), F.col("prefix").alias("cut"), (F.col("last") - F.col("left") < F.col("left")).alias("at"))


def plan(slim: DataFrame, weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, max_repeat: int = 2) -> DataFrame:
    """s (source), source_size, target, copies, cut and at: what each source gives; broadcast if its bytes are few."""
    tgt = checkpoint(targets(slim, weights, share, max_repeat))
    cut = thresholds(slim, tgt)
    out = tgt.join(cut, tgt["source"].eqNullSafe(cut["s"]), "left").select(F.col("source").alias("s"), "source_size", "target", "copies", "cut", "at")
    return F.broadcast(out) if fits(tgt) else out


def _copies(h: Column) -> Column:
    more = F.coalesce((h < F.col("cut")) | ((h == F.col("cut")) & F.col("at")), F.lit(False))
    return F.col("copies") + more.cast("long")


def mix(docs: DataFrame, weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, max_repeat: int = 2, **cols: str) -> DataFrame:
    """doc_id, source, size, source_size, target, n_copies (times the mix holds the document)."""
    slim = checkpoint(sizes(docs, **cols))
    per = plan(slim, weights, share, max_repeat)
    joined = slim.join(per, slim["source"].eqNullSafe(F.col("s")))
    return joined.select("doc_id", "source", "h", "size", "source_size", "target", _copies(F.col("h")).alias("n_copies"))


def repeated(docs: DataFrame, weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, max_repeat: int = 2, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The rows of ``docs``, each as often as the mix takes it.

    What a source gives is joined to the rows, so each row is judged by its own source and hash; texts are not exchanged
    as long as the sources' plan is broadcast.
    """
    slim = checkpoint(sizes(docs, id_col, text_col, source_col))
    per = plan(slim, weights, share, max_repeat)
    rows = docs.select(row_of(docs).alias("row"), hashed(id_col).alias("h"), F.col(source_col).alias("source"))
    taken = rows.join(per, rows["source"].eqNullSafe(F.col("s"))).select("row", _copies(F.col("h")).alias("n")).where("n > 0")
    return taken.select("row", F.explode(F.sequence(F.lit(1), F.col("n").cast("int"))).alias("i")).select("row.*")
