"""Corpus pipeline: language ID, line dedup, n-gram Jaccard join, benchmark decontamination, piece encoding.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of
`documents`. Documents without letters are rejected by language ID; boilerplate lines are cut; one document of
each near-duplicate group (five words, similarity 0.8) stays, the one with the smallest id; contaminated
documents go; what is left is encoded into pieces.
"""

from __future__ import annotations

from functools import wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from localgraph.llm import decontaminate as decon
from localgraph.llm import language_id, line_dedup, ngram_join, pieces
from localgraph.llm.common import small_batches, stored, table

#: language ID, the first stage, and the piece vocabulary have no SQL form; tests compare with brute force
ORACLE_SQL = None


def in_small_batches(stage):
    """The stage with bounded batches; they stay set, as its result is often evaluated later."""

    @wraps(stage)
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        small_batches(spark)
        return stage(spark, docs, sf_dir)

    return run


@in_small_batches
def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents whose language cannot be told (null text, no letters); fills in missing languages."""
    prototypes = language_id.learn(docs)
    told = language_id.predict(docs, prototypes).filter("lang_pred <> 'und'")
    return told.withColumn("lang", F.coalesce("lang", "lang_pred")).select(docs.columns)


@in_small_batches
def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts lines that at least line_dedup.MIN_SITES sites share."""
    cut = line_dedup.dedup_lines(docs)
    return cut.withColumn("n_chars", F.when(F.col("n_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(docs.columns)


@in_small_batches
def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the smallest id of each near-duplicate component; rows with a null id are in none and stay."""
    found = ngram_join.near_components(docs, k=5, percent=80)
    kept = found.filter("doc_id = component_id").select("doc_id").distinct()
    return docs.join(kept, "doc_id", "left_semi").dropDuplicates(["doc_id"]).select(docs.columns).unionByName(docs.filter("doc_id is null"))


@in_small_batches
def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that contain a benchmark item."""
    return decon.decontaminate(docs, table(spark, sf_dir, "benchmark")).filter("not contaminated").select(docs.columns)


@in_small_batches
def piece_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Adds the ids of the best pieces and their score."""
    return pieces.encode(docs, pieces.Vocabulary.load())


STAGES = [
    ("language", language_stage),
    ("lines", line_stage),
    ("near duplicates", near_duplicate_stage),
    ("decontamination", decontamination_stage),
    ("pieces", piece_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written and read again before the next."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), "stage-" + name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
