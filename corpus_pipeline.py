"""A corpus pipeline of five operators: quality rules, near-dedup, PII surrogates, mixing, packing."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from bitgrove.llm.common import read, stored
from bitgrove.llm.minhash import near_duplicates
from bitgrove.llm.mixing import mix
from bitgrove.llm.packing import pack_documents
from bitgrove.llm.quality import judge
from bitgrove.llm.queries import tokenizer
from bitgrove.llm.surrogate import replace_entities


def _whole(docs: DataFrame) -> Column:
    """All columns as one, so that none of them can clash with a stage's own."""
    return F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_doc")


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep, with joint cutoffs. Rows that share a doc_id stay if one of them is kept; null ids count as one."""
    kept = judge(docs, read(spark, sf_dir, "labels"), joint=True).filter("kept").select(F.col("doc_id").alias("_id")).distinct()
    held = docs.select(_whole(docs)).join(kept.hint("merge"), F.col("_doc.doc_id").eqNullSafe(F.col("_id")), "left_semi")
    return held.select("_doc.*")


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five words, 0.8): that with the smallest doc_id, one row of it. Rows without a
    doc_id stay."""
    judged = stored(near_duplicates(docs, size=5, percent=80).filter("doc_id is not null"), "judged")
    kept = judged.filter("kept").select("doc_id").distinct()
    named = docs.join(kept.hint("merge"), "doc_id", "left_semi")
    if not judged.groupBy("doc_id").count().filter("count > 1").isEmpty():
        named = named.dropDuplicates(["doc_id"])
    return named.unionByName(docs.filter("doc_id is null"))


def pii_surrogates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, with surrogates for personal data in their texts; n_chars follows the text."""
    out = replace_entities(docs.select("doc_id", "text", _whole(docs)), carry=("_doc",))
    changed = {"text": F.col("text")}
    if "n_chars" in docs.columns:
        changed["n_chars"] = F.when(F.col("n_entities") > 0, F.length("text").cast("long")).otherwise(F.col("_doc.n_chars"))
    return out.select(*(changed.get(c, F.col(f"_doc.`{c}`")).alias(c) for c in docs.columns))


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mixture: documents that the mix takes, those that it takes twice as two rows. Equal rows are taken alike."""
    parts = [F.col("doc_id"), F.col("doc_id").isNull(), F.col("text"), F.col("text").isNull(), F.col("source"), F.col("source").isNull()]
    row = F.struct(F.xxhash64(*parts).alias("a"), F.xxhash64(F.lit(1), *parts).alias("b")).alias("_row")
    taken = mix(docs.select("doc_id", "text", "source", row), carry=("_row",)).filter("n_taken > 0").groupBy("_row").agg(F.max("n_taken").alias("_turns"))
    keyed = docs.select(_whole(docs), row).join(taken.hint("merge"), "_row")
    return keyed.select("_doc", F.explode(F.sequence(F.lit(1), F.col("_turns"))).alias("_turn")).select("_doc.*")


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mixture's tokens packed into sequences: a row per piece."""
    return pack_documents(docs, tokenizer())


STAGES = [("quality_rules", quality_rules), ("minhash_near_dedup", near_dedup), ("pii_surrogates", pii_surrogates), ("source_mix", source_mix), ("packing", packing)]
#: No stage but the first can be said in SQL; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written and read again."""
    docs = read(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
