"""What a question-answering system does with scores, and the extended dataset."""

from __future__ import annotations

from pairverify.constants import TAU
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def route(candidates: DataFrame, tau: float = TAU, tau_low: float = 0.25) -> DataFrame:
    """One row per request: request_id, action, chosen (rank of the candidate).

    accept: the first candidate is above tau. alternative: a later one is, and the first is at or below tau_low. refine:
    the best lies above tau_low. ask_user: none of these.
    """
    order = F.struct(-F.col("score"), F.col("rank"))
    g = candidates.groupBy("request_id").agg(F.min_by("score", "rank").alias("first"), F.min("rank").alias("first_rank"), F.max("score").alias("best"), F.min_by("rank", order).alias("best_rank"))
    action = F.when(F.col("first") > tau, "accept").when((F.col("best") > tau) & (F.col("first") <= tau_low), "alternative").when(F.col("best") > tau_low, "refine").otherwise("ask_user")
    chosen = F.when(action == "accept", F.col("first_rank")).when(action != "ask_user", F.col("best_rank"))
    return g.select("request_id", action.alias("action"), chosen.alias("chosen"))


def best_candidates(candidates: DataFrame, k: int = 1) -> DataFrame:
    w = Window.partitionBy("request_id").orderBy(F.col("score").desc(), "rank")
    return candidates.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)


def extended(queries: DataFrame, human: DataFrame, generated: DataFrame) -> DataFrame:
    """Nested record: query, relabelled query, descriptions, and both texts with their scores.

    queries: query_id, shape, split, sparql, q_text, described; human and generated: query_id, text, score.
    """
    side = lambda df, name: df.select("query_id", F.struct("text", "score").alias(name))
    return records(queries.join(side(human, "human"), "query_id", "left").join(side(generated, "generated"), "query_id", "left"))


def records(rows: DataFrame) -> DataFrame:
    """The nested records of queries that have both texts with their scores beside them, as structs human and generated."""
    return rows.select("query_id", F.struct("sparql", "shape").alias("original"), F.col("q_text").alias("relabelled"), F.col("described").alias("descriptions"), "human", "generated", "split", "shape")


def write_extended(rows: DataFrame, path: str, by: str = "split") -> None:
    """Parquet partitioned by split; writing a partition again takes the old one's place."""
    rows.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(by).parquet(path)


def mean_by_origin(rows: DataFrame) -> DataFrame:
    return rows.agg(F.avg("generated.score").alias("generated"), F.avg("human.score").alias("human")).select(F.explode(F.array(F.struct(F.lit("generated").alias("origin"), F.col("generated").alias("mean_score")), F.struct(F.lit("human").alias("origin"), F.col("human").alias("mean_score")))).alias("r")).select("r.*")
