"""One query for each operator, with production parameters, over whole tables."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wsample.llm import avi, decontaminate, langid, lines, packing, pii, quality, simhash, store, tokens
from wsample.llm.twins import SQL

__all__ = ["QUERIES", "SQL"]

QUERIES: dict = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


@query
def op1_line_dedup(spark, sf_dir):
    done = lines.dedup_lines(documents(spark, sf_dir))
    return done.select("doc_id", "n_lines", "n_exact", "n_near", F.md5(F.coalesce("text", F.lit("")).cast("binary")).alias("text_md5"))


@query
def op2_simhash_duplicates(spark, sf_dir):
    return simhash.near_duplicates(documents(spark, sf_dir), shingle=3, max_bits=2)


@query
def op3_language_id(spark, sf_dir):
    docs = documents(spark, sf_dir).withColumn("held_out", langid.held_out("doc_id"))
    profiles = langid.train(docs.where("not held_out"))
    told = langid.identify(docs, profiles)
    return told.select("doc_id", langid.held_out("doc_id").alias("held_out"), "lang_pred", "score")


@query
def op4_pack_sequences(spark, sf_dir):
    return packing.pack_documents(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"), capacity=1024, end_id=2)


@query
def op5_token_store(spark, sf_dir):
    return store.read_documents(store.write_store(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"), end_id=1))


@query
def op6_decontamination(spark, sf_dir):
    return decontaminate.contamination(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"), span=10)


@query
def op7_token_counts(spark, sf_dir):
    return tokens.token_counts(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"), limit=2048)


@query
def op8_quality(spark, sf_dir):
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    judged = quality.classify(documents(spark, sf_dir), labels, host="source", path="lang")
    return judged.select("doc_id", "p_doc", "host_rate", "path_rate", "p_good", "keep")


@query
def op9_motion_jpeg(spark, sf_dir):
    return avi.media_features(avi.to_media(documents(spark, sf_dir)))


@query
def op10_personal_data(spark, sf_dir):
    return pii.personal_data(documents(spark, sf_dir))
