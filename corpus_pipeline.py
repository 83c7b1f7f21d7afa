"""A corpus for training from raw documents: five stages, each over all that the one before kept.

Quality classifier, near-duplicate join, repeated passages, benchmark
decontamination, packing. ``STAGES`` lists them; every stage takes (spark, docs,
sf_dir) and returns documents with their columns, the last one the pieces of
packed sequences. ``run`` writes each stage's rows to the shared folder and reads
them again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from wdsum.llm import decontamination, jaccard, packing, quality, suffixes
from wdsum.llm.stored import discard, stored, written

#: repeated passages: this many bytes, about forty words, and the anchor's
PASSAGE_BYTES, ANCHOR_BYTES = 240, 80


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejected documents go; null and empty texts are scored by the labels' share, repeated rows alike; an empty table stays empty."""
    return quality.reject_bad(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def one_of_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class stays, that of least id; texts without words, null ones too, all stay; an empty table stays empty."""
    return jaccard.keep_one(docs)


def without_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages that occur elsewhere too are cut out of every text; all rows stay, null texts stay null; an empty table stays empty."""
    return suffixes.cut_repeats(docs, PASSAGE_BYTES, ANCHOR_BYTES)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a benchmark's passages go; texts without words stay, repeated rows alike; an empty table stays empty."""
    return decontamination.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences of at most 2048 tokens; null and empty texts are an end token, repeated rows are packed each; an empty table has no pieces."""
    return packing.pack_documents(docs)


STAGES = [
    ("quality classifier", good_quality),
    ("n-gram Jaccard join", one_of_near_duplicates),
    ("suffix-array dedup", without_repeats),
    ("benchmark decontamination", decontaminated),
    ("packing", packed),
]

#: SQL can't express the classifier or the tokenizer
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; a stage's intermediate tables go once its rows are written."""
    docs, mark = spark.read.parquet(f"{sf_dir}/documents.parquet"), written()
    for _, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir))
        discard(spark, mark, keep=1)
    return STAGES[-1][1](spark, docs, sf_dir)
