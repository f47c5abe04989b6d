"""Corpus pipeline: toxicity, exact dedup, n-gram join, source mixing, packing.

Each stage takes ``(spark, docs, sf_dir)`` and returns a frame; ``run`` writes each result as
Parquet and reads it again as the next stage's ``docs``.  All stages but the last return the
columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from canopy.llm import exact_dedup, mixing, ngram_join, packing, toxicity
from canopy.store import cut, reachable, write


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model does not reject.

    Defined results: null and empty texts score as clean and stay; repeated rows share one decision; an empty
    table stays empty; rows with a null id are scored like others, and never train.
    """
    reachable(spark)
    return toxicity.keep_clean(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def _keep_rows(docs: DataFrame, keep: DataFrame) -> DataFrame:
    """Rows of ``docs`` whose id and text hash are in ``keep(doc_id, th)``; rows with a null id stay."""
    own = docs.columns
    held = docs.filter("doc_id is null")
    one = write(keep.select(F.col("doc_id").alias("__id"), F.col("th").alias("__th")).distinct(), "keep").df.hint("merge")
    row = docs.withColumn("__h", F.xxhash64(F.col("text").cast("string")))
    kept = row.join(one, (F.col("doc_id") == F.col("__id")) & (F.col("__h") == F.col("__th")), "left_semi")
    return kept.select(*own).unionByName(held)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts: the one with the smallest id.

    Defined results: null text counts as empty, so of null and empty texts one document stays; an id with several
    texts keeps those that are the first of their group; repeated rows (same id and text) stay or go together; rows
    with a null id stay; an empty table stays empty.
    """
    g = exact_dedup.exact_groups(docs)
    return _keep_rows(docs, g.filter("kept and id is not null").select(F.col("id").alias("doc_id"), "th"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of linked texts: the one with the smallest id.

    Defined results: texts without words have no links and stay; an id with several texts keeps those whose class
    it leads; repeated rows stay or go together; rows with a null id stay; an empty table stays empty.
    """
    reachable(spark)
    j = ngram_join.similarity_join(docs)
    return _keep_rows(docs, j.filter("class_id = doc_id").select("doc_id", "th"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mixture in slot order: a document once for each epoch that takes it, a last cut copy as its first words.

    Defined results: texts without words are in no mixture; the null source is a source; repeated rows count each
    and come as copies of one of them; null ids are kept; an empty table stays empty.
    """
    return mixing.mixed_documents(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of the mixture in sequences.

    Defined results: null text is one piece with the end id; repeated rows are packed apart; null ids are kept; an
    empty table gives an empty result.
    """
    reachable(spark)
    return packing.packed_documents(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("exact_dedup", drop_copies),
    ("ngram_join", drop_near_copies),
    ("mixing", mix_sources),
    ("packing", pack_sequences),
]

#: Learned scores and genetic packing have no SQL form; tests compare the stages with plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
