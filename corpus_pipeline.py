"""Corpus preparation: each stage reads what the one before it wrote.

toxicity filter -> near-duplicate removal -> substring deduplication -> benchmark decontamination -> tokenisation."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skyweave.llm import byte_bpe, decontaminate, near_dup, substring_dedup, toxicity
from skyweave.llm import common as C

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _columns(docs: DataFrame) -> DataFrame:
    return docs.select(*COLUMNS)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the model, learnt from all labels of these documents, scores below the threshold. Null and empty texts score 0 and stay;
    without labels of both kinds all stay."""
    model = toxicity.train(docs, C.table(spark, sf_dir, "labels"))
    return toxicity.reject(_columns(docs), model, 0.3)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group at a similarity of 0.8 on five-word shingles: that with the smallest doc_id. Texts without a word stay; rows
    that share a doc_id, or have none, are told apart by their texts."""
    return near_dup.keep_one(_columns(docs), width=5, percent=80)


def remove_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the 20-word windows that occur earlier; texts that lose every word go, null texts and texts without a word stay as they are.
    n_chars is counted anew where words went."""
    out = substring_dedup.deduplicate(_columns(docs), 20).where("n_words = 0 or n_removed < n_words")
    return out.withColumn("n_chars", F.when(F.col("n_removed") > 0, F.char_length("text").cast("long")).otherwise(F.col("n_chars"))).select(*COLUMNS)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no item of the benchmark, nor one with other names, numbers or units; null and empty texts stay. An empty benchmark drops nothing."""
    return decontaminate.clean(_columns(docs), C.table(spark, sf_dir, "benchmark"))


def tokenise(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token count, and digests of the ids and of the text that they decode to, of every row; a null text is an empty one."""
    return byte_bpe.digests(docs)


STAGES = [("toxicity", drop_toxic), ("near_duplicates", drop_near_duplicates), ("substring_dedup", remove_repeats), ("decontamination", drop_contaminated), ("byte_bpe", tokenise)]

#: A trained model and byte-pair merges have no SQL; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = C.table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            path = C.scratch(spark, f"pipeline-{name}")
            docs.write.parquet(path)
            docs = spark.read.parquet(path)
    return docs
