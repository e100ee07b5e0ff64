"""Saving and loading filters and trees, and reading id lists."""

from __future__ import annotations

import json
from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import Spec
from ..operators.filters import same_spec
from ..plans.tree import Tree


def save_tree(tree: Tree, path: str) -> None:
    """Words partitioned by level, so that one level is one folder; nodes and format beside them."""
    tree.words.repartition("level", "idx").write.mode("overwrite").partitionBy("level").parquet(f"{path}/words")
    tree.nodes.coalesce(1).write.mode("overwrite").parquet(f"{path}/nodes")
    about = json.dumps(asdict(tree.spec) | {"domain": tree.domain, "depth": tree.depth, "cut": tree.cut})
    tree.nodes.sparkSession.createDataFrame([(about,)], "about string").coalesce(1).write.mode("overwrite").json(f"{path}/spec")


def load_tree(spark: SparkSession, path: str, spec: Spec | None = None) -> Tree:
    """A stored tree; if spec is given it must be the tree's."""
    about = json.loads(spark.read.json(f"{path}/spec").first()["about"])
    found = Spec(about["m"], about["k"], about["family"], tuple(about["a"]), tuple(about["b"]), about["p"])
    if spec is not None:
        same_spec(spec, found)
    words = spark.read.parquet(f"{path}/words").select("idx", "word_no", "bits", F.col("level").cast("int").alias("level"))
    return Tree(found, about["domain"], about["depth"], words, spark.read.parquet(f"{path}/nodes"), about["cut"])


def save_filters(words: DataFrame, path: str, fmt: str = "parquet") -> None:
    words.write.mode("overwrite").format(fmt).save(path)


def load_filters(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    return spark.read.format(fmt).schema("set_id string, word_no int, bits long").load(path)


def read_ids(spark: SparkSession, path: str, fmt: str = "csv", column: str = "x") -> DataFrame:
    """Ids of a text, CSV, JSON, ORC or Parquet file as (x); lines that are no number drop out."""
    rows = spark.read.text(path).withColumnRenamed("value", column) if fmt == "text" else spark.read.format(fmt).option("header", True).load(path)
    return rows.select(F.col(column).cast("string").try_cast("long").alias("x")).filter("x is not null")
