"""Helpers shared by the training-data operators."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.scratch import shared_dir, stored

__all__ = ["BROADCAST_BYTES", "SPACES", "n_words", "read", "shared_dir", "stored", "stored_in_buckets", "words"]

#: The white space that separates words, in every operator of this folder.
SPACES = r"[\x20\x09-\x0D]+"
#: What a table may take, by its rows and a bound of their size, to be sent to every task.
BROADCAST_BYTES = 32 << 20


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def stored_in_buckets(df: DataFrame, name: str, key: str, buckets: int) -> DataFrame:
    """As stored, bucketed by key: joins on key then read it in place instead of shuffling it. The table's name leaves the catalog
    again at once; its files stay, and the returned rows know where."""
    spark = df.sparkSession
    table = f"bitgrove_{name}_{uuid.uuid4().hex}"
    df.write.bucketBy(buckets, key).option("path", f"{shared_dir(spark)}/{table}").format("parquet").saveAsTable(table)
    rows = spark.table(table)
    spark.sql(f"DROP TABLE {table}")
    return rows


def words(text):
    """Words of a text column, in order (null: none)."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), SPACES, -1), lambda w: w != "")


def n_words(text):
    """Number of words, without making the words: each white-space run becomes one blank."""
    flat = F.trim(F.regexp_replace(F.coalesce(text, F.lit("")), SPACES, " "))
    return F.when(flat == "", F.lit(0)).otherwise(F.length(flat) - F.length(F.translate(flat, " ", "")) + 1).cast("long")
