"""A training corpus from raw documents in five stages: toxicity, near-duplicates, benchmark leaks, personal data, packing.

Each stage takes (spark, docs, sf_dir), where docs is what its predecessor kept, and all but the last return the columns
of documents, with all further columns that documents have, whatever their names. run() writes every stage's rows as Parquet in the shared scratch folder and reads them again for the next.
"""

from __future__ import annotations

from pairverify.llm import decontam, packing, pii, simhash, toxicity
from pairverify.llm._common import id_crc32, materialize, small_batches, without
from pairverify.llm.queries import pii_key
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity is below one half. The model learns from labelled documents of the stage's input.

    Null and empty texts score the labels' base rate. Rows of one id stay or go together, by their most toxic text; rows
    without an id stay. Without labels of both kinds every text scores the base rate. An empty table stays empty.
    """
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = toxicity.fit(docs, labels, id_crc32("doc_id") % 5 != 0)
    bad = toxicity.score(docs, model).where("score >= 0.5 and doc_id is not null").select("doc_id").distinct()
    with small_batches(spark):
        return without(docs, bad, "doc_id")


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates: sets of five-word shingles with a Jaccard similarity of 0.8 or more.

    The smallest id stays. Null and empty texts are alike. Rows of one id stay or go together; rows without an id stay.
    An empty table stays empty.
    """
    with small_batches(spark):
        return simhash.one_of_each(docs, k=3, shingle=5, similarity=(4, 5))


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a passage of the benchmark.

    Null and empty texts stay, as do rows without an id; rows of one id go together. With an empty benchmark all stay.
    """
    with small_batches(spark):
        return decontam.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def hide_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with surrogates for personal data; n_chars follows the new text, and is null for a null one.

    Every row stays, repeated ids, missing ids and empty texts included.
    """
    out = pii.replace_entities(docs, pii_key(spark), count_col="__entities").drop("__entities")
    return out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else out


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents in sequences of at most 1024 tokens.

    A null or empty text is the end id alone; rows that repeat an id, or have none, are packed one by one. An empty table
    gives no rows.
    """
    with small_batches(spark):
        return packing.pack(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash_near_dedup", drop_near_duplicates),
    ("benchmark_decontamination", drop_leaks),
    ("pii", hide_personal_data),
    ("packing", pack_sequences),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return docs
