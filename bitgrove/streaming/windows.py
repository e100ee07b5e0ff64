"""Filters over streams: one per type and window, and a tree that grows with the ids that arrive."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import Spec, positions
from ..operators.filters import bit_of, word_of
from ..plans.tree import Tree, grow


def windowed_words(events: DataFrame, spec: Spec, span: Column) -> DataFrame:
    """Filter words per (event_type, window start), for a static or a streaming table with ts as timestamp. OR is idempotent,
    so a row delivered twice changes nothing; late rows beyond the watermark are dropped by the stream."""
    placed = events.filter("user_id is not null").select("event_type", span.alias("w"), F.explode(F.array(*positions(F.col("user_id"), spec))).alias("pos"))
    return placed.groupBy("event_type", "w", word_of(F.col("pos")).alias("word_no")).agg(F.bit_or(bit_of(F.col("pos"))).alias("bits")).select("event_type", F.col("w.start").alias("start"), "word_no", "bits")


def tumbling(length: str = "1 day") -> Column:
    return F.window("ts", length)


def sliding(length: str = "2 days", step: str = "1 day") -> Column:
    return F.window("ts", length, step)


def sessions(events: DataFrame, gap: str = "1 hour") -> DataFrame:
    """Per user and session, which ends after a gap without an event: user_id, start, last, n."""
    of = events.filter("user_id is not null").groupBy("user_id", F.session_window("ts", gap).alias("w"))
    return of.agg(F.count("*").alias("n"), F.max("ts").alias("last")).select("user_id", F.col("w.start").alias("start"), "last", "n")


def late_rows(query) -> int:
    """Rows that a running or ended stream dropped because they came after the watermark."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def read_events(spark, sf_dir: str, delay: str = "1 day") -> DataFrame:
    """The events table as a stream of its files, with a watermark. Its ts has no zone, so it is cast."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def without_repeats(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


class GrowingTree:
    """foreachBatch target: each micro-batch's ids are OR-ed into the tree; batches may be delivered again."""

    def __init__(self, tree: Tree):
        self.tree = tree

    def __call__(self, batch: DataFrame, _: int) -> None:
        ids = batch.select(F.col("user_id").alias("x")).distinct()
        if not ids.isEmpty():
            self.tree = grow(self.tree, ids)
