"""Incremental blocking over a stream of descriptions [extension].

State holds counts per key only; postings go to the sink as they come, late rows are bounded by the watermark.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erblock.functions.cut import new_path, written
from erblock.functions.text import tokens


def event_stream(spark: SparkSession, path: str) -> DataFrame:
    """The events table replayed as a file stream."""
    schema = spark.read.parquet(path).schema
    # The last character as a class makes a glob, so a single file will do as well as a folder.  Watermarks
    # need instants; results give the table's zone-less times back.
    return spark.readStream.schema(schema).parquet(f"{path[:-1]}[{path[-1]}]").withColumn("ts", F.col("ts").cast("timestamp"))


def closed(events: DataFrame) -> DataFrame:
    """The stream and a last event of no user in the year 9999: it moves the watermark past all others, so whatever was
    open when they ended is done.  Its own session is never emitted."""
    spark = events.sparkSession
    last = [F.lit("9999-01-01").cast("timestamp") if f.name == "ts" else F.lit(None).cast(f.dataType) for f in events.schema]
    end = written(spark.range(1).select(*[c.alias(f.name) for c, f in zip(last, events.schema, strict=True)]))
    return events.unionByName(spark.readStream.schema(end.schema).parquet(end.written_to))


def event_tokens(events: DataFrame, watermark: str = "10 minutes") -> DataFrame:
    """ts, entity_id, block_key: tokens of a user's event type and JSON keys."""
    keys = F.map_keys(F.from_json("props", "map<string,string>"))
    values = F.concat(F.array("event_type"), F.coalesce(keys, F.array().cast("array<string>")))
    wide = events.withWatermark("ts", watermark).select("ts", F.col("user_id").alias("entity_id"), F.explode(values).alias("value"))
    return wide.select("ts", "entity_id", F.explode(tokens(F.col("value"))).alias("block_key"))


def incremental_postings(events: DataFrame, watermark: str = "10 minutes") -> DataFrame:
    """New postings, each once."""
    return event_tokens(events, watermark).select("block_key", "entity_id").dropDuplicates(["block_key", "entity_id"])


def block_growth(events: DataFrame, window: str = "1 hour", slide: str | None = None) -> DataFrame:
    """start, block_key, n: postings per window and key."""
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    return event_tokens(events).groupBy(w.alias("w"), "block_key").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "block_key", "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """user_id, start, n: events of a user without a gap; an event exactly that long after another begins a session."""
    # A session window takes in what begins when it ends.
    s = events.withWatermark("ts", "10 minutes").groupBy(F.session_window("ts", f"{gap} -1 microseconds").alias("s"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return s.select("user_id", F.col("s.start").cast("timestamp_ntz").alias("start"), "n")


def new_candidates(events: DataFrame, postings: DataFrame) -> DataFrame:
    """block_key, entity_id (new), other: stream joined with the postings known so far."""
    known = postings.select("block_key", F.col("entity_id").alias("other"))
    return event_tokens(events).join(known, "block_key").where("entity_id <> other").select("block_key", "entity_id", "other")


def late(events: DataFrame, seconds: int = 3600, order: str = "event_id") -> DataFrame:
    """user_id, n, n_late: events that came more than ``seconds`` after a later one of the same user.

    State per user: the latest time seen and two counts.  Inside a micro-batch rows count in the order given.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key: tuple, frames: object, state: GroupState) -> object:
        pdf = pd.concat(list(frames)).sort_values("place")
        top, n, behind = state.get if state.exists else (-1, 0, 0)
        seen = pdf["at"].cummax().shift(fill_value=top).clip(lower=top)
        behind += int((pdf["at"] < seen - seconds * 1_000_000).sum())
        top, n = max(top, int(pdf["at"].max())), n + len(pdf)
        state.update((top, n, behind))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "n_late": [behind]})

    kind = events.schema["user_id"].dataType.simpleString()
    slim = events.select("user_id", F.expr(order).cast("long").alias("place"), F.unix_micros("ts").alias("at"))
    return slim.groupBy("user_id").applyInPandasWithState(step, f"user_id {kind}, n long, n_late long", "top long, n long, behind long", "update", GroupStateTimeout.NoTimeout)


def drain(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """All that a stream has now, as a table (available-now trigger).

    Appended rows go to files of the shared folder; what changes again, to the memory sink.
    """
    if mode == "append":
        spark, path = stream.sparkSession, new_path(stream.sparkSession)
        query = stream.writeStream.outputMode(mode).format("parquet").option("checkpointLocation", new_path(spark)).trigger(availableNow=True).start(path)
        query.awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    name = f"stream_{uuid.uuid4().hex}"
    query = stream.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)
