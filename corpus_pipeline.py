"""A corpus pipeline: quality, exact dedup, near-dedup, substring dedup, packing.

Each stage takes (spark, docs, sf_dir), works on all rows of docs and returns the columns of documents;
the last one returns the pieces of the packed sequences. run() writes each stage's rows to the shared
folder and reads them again, so a lost executor costs a stage at most.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgegraph.llm import exact, near_dedup, packing, quality, substring
from edgegraph.llm.links import store

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier predicts to be good; texts are not changed."""
    model = quality.fit_on(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality.quality_scores(docs, model, carry=COLUMNS[1:]).where("predicted = 1").select(*COLUMNS)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts (white space apart) the row of the smallest doc_id; of rows repeated whole, and of equal texts
    that all lack a doc_id, one."""
    kept = exact.exact_groups(docs, carry=COLUMNS[1:]).where("kept")
    return kept.dropDuplicates(["doc_id", "text_sha256"]).select(*COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each near-duplicate class the document of the smallest doc_id."""
    gone = near_dedup.near_duplicates(docs).where("not kept").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*COLUMNS)


def cut_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without passages of 50 words that a document of smaller id has; rows stay, emptied ones too."""
    cut = substring.repeated_passages(docs, carry=("lang", "source"))
    return cut.select("doc_id", F.col("kept_text").alias("text"), "lang", "source", F.length("kept_text").cast("long").alias("n_chars"))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences of 2048 tokens."""
    return packing.pack(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [("quality classifier", keep_quality), ("exact dedup", drop_copies), ("near-dedup", drop_near_copies), ("substring dedup", cut_passages), ("packing", pack_sequences)]

#: SQL can express neither the classifier nor the tokenizer; tests/llm/test_pipeline.py holds the stages against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = exact.shared_folder(spark, "pipeline")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs = store(docs, f"{folder}/{i}")
    return docs
