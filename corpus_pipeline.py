"""Corpus pipeline: quality, line dedup, near-dedup, decontamination, packing.

Each stage reads what its predecessor wrote and returns the columns of ``documents`` for the rows it keeps, the last
one packed pieces.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wsample.llm import decontaminate, lines, packing, quality, simhash
from wsample.llm.common import written

#: Jaccard similarity of their shingles at which documents are copies.
SIMILARITY = 0.8
#: Fingerprints that differ in so many bits name the pairs that are compared first; further ones are found by their shingles.
FIRST_BITS = 6


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier keeps; those labelled toxic teach it what is bad too."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return quality.classify(docs, labels, host="source", path="lang").where("keep").select(*docs.columns)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the lines that earlier ones have; one that had no other lines goes."""
    done = lines.dedup_lines(docs, keep_empty=False)
    changed = F.col("n_exact") + F.col("n_near") > 0
    return done.withColumn("n_chars", F.when(changed, F.char_length("text")).otherwise(F.col("n_chars"))).select(*docs.columns)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of the smallest id of each group of near copies (five-word shingles); equal rows once.

    Rows with a null id cannot be named and stay.
    """
    found = simhash.near_duplicates(docs, shingle=5, max_bits=None, min_similarity=SIMILARITY, first_bits=FIRST_BITS)
    keep = found.where("doc_id = component_id").select("doc_id").distinct()
    named = docs.where("doc_id is not null").join(keep, "doc_id", "left_semi").dropDuplicates(["doc_id", "text"])
    return named.select(*docs.columns).unionByName(docs.where("doc_id is null"))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a passage of the benchmark."""
    return decontaminate.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"), span=10)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces in sequences of 1024."""
    return packing.pack_documents(docs, public_tokenizers.path("byte_bpe_50k.json"), capacity=1024, end_id=2)


STAGES = [("quality", keep_good), ("line_dedup", drop_repeated_lines), ("near_dedup", drop_copies), ("decontamination", drop_contaminated), ("packing", pack)]

#: The quality classifier and the tokenizer have no SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
