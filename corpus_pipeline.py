"""A corpus pipeline of four stages: language, near duplicates, mixture, packing.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of
documents. ``run`` writes each stage's rows to the shared folder and reads them back for the next.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathq.llm.common import Workspace, prefilter
from pathq.llm.language import UNKNOWN, fit, identify
from pathq.llm.mixing import ADDED, mix
from pathq.llm.near_dedup import near_duplicates
from pathq.llm.packing import pack, word_length

#: Below this score nothing of a text resembles any language learned; prose in a learned language scores far above.
LEAST_SCORE = 0.05


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects documents without a letter, null and empty texts among them, or with n-grams that no profile has. Repeated
    rows fare alike; rows without an id or label are judged by their text; without any labelled row a letter is enough."""
    profiles = fit(docs.select("doc_id", "text", "lang"))
    if not profiles:
        return docs.filter(F.col("text").rlike(r"\p{L}"))
    said = identify(docs, profiles)
    return said.filter((F.col("lang_pred") != UNKNOWN) & (F.col("score") >= LEAST_SCORE)).select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group of near duplicates, the one with the smallest id; rows without an id stay."""
    work = Workspace(spark, "pipeline-dedup")
    verdict = near_duplicates(docs.select("doc_id", "text")).filter("doc_id is not null").groupBy("doc_id")
    verdict = work.table(verdict.agg(F.max("kept").alias("kept"), F.max("n_shingles").alias("n"), F.count(F.lit(1)).alias("rows")), "verdict")
    gone = verdict.filter("not kept and n > 0").select("doc_id")
    repeated = verdict.filter("rows > 1").select("doc_id")  # rows that repeat are copies too
    touched = gone.union(repeated)
    # texts of rows that are surely untouched are not shuffled
    left = prefilter(docs, touched, "doc_id").join(gone, "doc_id", "left_anti")
    if not repeated.isEmpty():
        once = left.join(repeated, "doc_id", "left_semi").dropDuplicates(["doc_id"])
        left = left.join(repeated, "doc_id", "left_anti").unionByName(once)
    return prefilter(docs, touched, "doc_id", out=True).unionByName(left.select(*docs.columns))


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Brings the sources nearer to equal shares within the same token budget; no source is repeated more than twice.

    A null source is a source of its own. Documents without words, null texts among them, are taken once. Repeated rows are
    rows of their own. An empty table stays empty.
    """
    return mix(docs, target_entropy=0.97, max_repeats=2.0).drop(*ADDED)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row with its bucket, batch and slot, without its text. Null and empty texts have length 0 and lie in the
    first bucket; repeated rows are rows of their own; an empty table stays empty; columns named like the added ones are replaced."""
    lengths = docs.select(*[c for c in docs.columns if c != "text"], word_length(F.col("text")).alias("__len"))
    work = Workspace(spark, "pipeline-packing")
    return work.finish(pack(work.table(lengths, "lengths"), length=F.col("__len")).drop("__len"))  # texts are read once


STAGES = [("language", language), ("near_dedup", near_dedup), ("mixture", mixture), ("packing", packing)]

#: The near-duplicate join and the dynamic program have no SQL form; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    work = Workspace(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = work.table(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
