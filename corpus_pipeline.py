"""A corpus pipeline: quality, repeated lines, near duplicates, the mix, and packing.

Every stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame; ``run`` writes each stage's
result as Parquet in the shared scratch folder and reads it again for the next. All stages but the
last return the columns of ``documents``, extra ones of any name included. Rows with null fields and empty texts
pass through all stages; rows with equal or near texts become one in ``near_duplicates``, whatever their ids.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphcc.llm import jaccard, lines, mixing, packing, quality
from graphcc.llm.tables import table
from graphcc.session import Kept

#: Documents at least this likely to be labelled good stay: unsure ones are kept.
LEAST_SCORE = 0.5
#: Ids of dropped documents are broadcast up to this many (8 bytes each), else joined by a shuffle.
BROADCAST_ROWS = 200_000

#: The classifier's scores have no SQL form; the stages are tested against brute force instead.
ORACLE_SQL = None


def quality_filter(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that the classifier, trained on the labelled ones outside the held-out fold, rejects."""
    weights = quality.train(docs, table(spark, sf_dir, "labels"))
    return quality.score(docs, weights, into="__score").where(F.col("__score") >= LEAST_SCORE).select(*docs.columns)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop lines that repeat an earlier line, exactly or within two edits."""
    return lines.dedup_lines(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep one row of each component of near duplicates (5 words, 0.8): the one with the smallest id, or the first of these.

    Rows are nodes of their own, known by their number in reading order, so that rows which share an id, or have none,
    stay unless their texts are alike.
    """
    rows = docs.withColumn("__row", F.monotonically_increasing_id())
    judged = jaccard.near_duplicates(rows.select(F.col("__row").alias("doc_id"), "text"), k=5, percent=80)
    judged = Kept(judged.select(F.col("doc_id").alias("__row"), "component_id"), "judged").df
    several = judged.where("__row <> component_id").select("component_id").distinct()
    members = judged.join(several, "component_id", "left_semi").join(rows.select("__row", "doc_id"), "__row")
    first = members.groupBy("component_id").agg(F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "__row")).getField("__row").alias("keep"))
    gone = Kept(members.join(first, "component_id").where("__row <> keep").select("__row"), "gone").df
    few = gone.count() <= BROADCAST_ROWS
    return rows.join(F.broadcast(gone) if few else gone, "__row", "left_anti").select(*docs.columns)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in training order, each as often as its source's target takes it."""
    return mixing.mix(docs)


def pack_windows(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces with the window and offset each lies at."""
    return packing.pack(docs)


STAGES = [("quality classifier", quality_filter), ("line dedup", line_dedup), ("n-gram Jaccard join", near_duplicates), ("mixing", mix_sources), ("packing", pack_windows)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = Kept(stage(spark, docs, sf_dir), name.replace(" ", "-")).df
    return docs
