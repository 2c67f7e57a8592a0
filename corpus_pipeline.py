"""Corpus pipeline: toxicity, near-duplicates, repeated passages, contamination, then packing.

Each stage takes (spark, docs, sf_dir), works on all rows that its predecessor kept and, but for the last, returns
the columns of ``documents``. ``run`` writes each stage's rows as Parquet into the shared folder and reads them again
as the next one's input.

Defined results of all stages: null and empty texts get the classifier's score of a text without words, resemble nothing, repeat
nothing, are not contaminated and pack as their end mark alone; texts are read whole, whatever their length; rows with a null doc_id stay, but for what a classifier rejects;
equal rows are treated alike, so a document that comes twice is kept or dropped with both of its rows; an empty table
gives an empty result; further columns than those of ``documents`` stay as they are until packing.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cellcount.llm import decontam, neardup, packing, substring, toxicity
from cellcount.llm.common import stage, table

#: Bands and rows for links at 0.80: a pair at the threshold meets in no band with probability (1 - 0.8^4)^24 = 3.2e-6.
NEAR_BANDS, NEAR_ROWS = 24, 4


def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity is under their language's threshold; the classifier learns from all labelled rows."""
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"), F.lit(True))
    return toxicity.keep_clean(docs, model)


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each group of near-duplicates (Jaccard 0.8 or more of five-word shingles)."""
    found = neardup.classes(docs.select(F.col("doc_id").alias("id"), "text"), 80, 100, bands=NEAR_BANDS, rows=NEAR_ROWS)
    kept = found.where("id = component or component is null").select(F.col("id").alias("_id"))
    return docs.join(kept, F.col("doc_id").eqNullSafe(F.col("_id")), "left_semi")


def substring_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without paragraphs and passages that an earlier document has, exactly or nearly; a document with nothing else goes."""
    return substring.remove(docs, substring.repeats(docs, near=True))


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the benchmark does not contaminate."""
    found = decontam.report(decontam.hits(docs, table(spark, sf_dir, "benchmark")))
    bad = found.where("contaminated").select(F.col("doc_id").alias("_id"))
    return docs.join(bad, F.col("doc_id") == F.col("_id"), "left_anti")


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents with their place in sequences of at most 2048 tokens."""
    return packing.pack(packing.pieces(docs))


STAGES = [
    ("toxicity", toxicity_stage),
    ("minhash_near_dedup", near_dedup_stage),
    ("substring_dedup", substring_stage),
    ("benchmark_decontamination", decontamination_stage),
    ("packing", packing_stage),
]

#: A trained classifier comes first, which SQL cannot express; tests/llm hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The packed pieces of ``documents`` after all stages."""
    docs = table(spark, sf_dir, "documents")
    for name, f in STAGES[:-1]:
        docs = stage(f(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
