"""Wrong partners for training: near-twins of a query, other queries' questions, and twins of what a verifier missed."""

from __future__ import annotations

import pandas as pd
from pairverify.operators.generators import TemplateGenerator, share
from pairverify.operators.translate import ship
from pairverify.plans.querytext import WRONG, parse, question, wrong_twin
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def perturbations(queries: DataFrame, kinds=tuple(WRONG), family: int | None = None, q_text: str = "q_text") -> DataFrame:
    """query_id, kind, text for every kind that changes a query's meaning; the terms stay the same but where the kind adds some."""
    ship()

    def run(frames):
        wording = TemplateGenerator(family)
        for frame in frames:
            rows = []
            for query_id, text in frame.itertuples(index=False):
                q = parse(text)
                for kind in kinds:
                    if twin := wrong_twin(q, kind):
                        rows.append((query_id, kind, question(twin, wording.wording(text))))
            yield pd.DataFrame(rows, columns=["query_id", "kind", "text"])

    kind = queries.schema["query_id"].dataType.simpleString()
    return queries.select("query_id", q_text).mapInPandas(run, f"query_id {kind}, kind string, text string")


def hard(queries: DataFrame, kinds=tuple(WRONG), seed: int = 0) -> DataFrame:
    """One near-twin for each query that has any, its kind chosen by hash."""
    all_ = perturbations(queries, kinds)
    best = F.md5(F.concat_ws("|", F.lit(str(seed)), "query_id", "kind"))
    return all_.groupBy("query_id").agg(F.min_by(F.struct("kind", "text"), best).alias("n")).select("query_id", "n.kind", "n.text")


def random_swap(pairs: DataFrame, text: str = "text", ring: int = 1000) -> DataFrame:
    """Every query with another one's text: rings of about `ring` pairs by md5, none with itself."""
    rings = max(1, pairs.count() // ring)
    pairs = pairs.withColumn("_order", F.md5(F.col("query_id").cast("string")))
    pairs = pairs.withColumn("_ring", F.conv(F.substring("_order", 1, 8), 16, 10).cast("bigint") % rings)
    # a ring of one joins ring 0, which takes all such; if that leaves one alone, it has no partner
    alone = pairs.groupBy("_ring").agg(F.count("*").alias("_n"))
    pairs = pairs.join(alone, "_ring").withColumn("_ring", F.when(F.col("_n") < 2, -1).otherwise(F.col("_ring")))
    w = Window.partitionBy("_ring").orderBy("_order", "query_id")
    whole = Window.partitionBy("_ring").orderBy("_order", "query_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    rows = pairs.withColumn("_other", F.coalesce(F.lead(F.struct("query_id", F.col(text))).over(w), F.first(F.struct("query_id", F.col(text))).over(whole)))
    return rows.where(F.col("_other.query_id") != F.col("query_id")).select("query_id", F.lit("random").alias("kind"), F.col(f"_other.{text}").alias("text"))


def targeted(queries: DataFrame, missed: DataFrame, copies: int = 2) -> DataFrame:
    """More twins of the kinds a verifier let through (missed: kind), `copies` for each query and kind."""
    all_ = perturbations(queries)
    wanted = missed.select("kind").distinct()
    return all_.join(F.broadcast(wanted), "kind").withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(copies)))).select("query_id", "kind", "text", "copy")


def training_pairs(positives: DataFrame, negatives: DataFrame) -> DataFrame:
    """query_id, q_text, text, kind, label from correct (query_id, q_text, question) and wrong (query_id, kind, text) ones."""
    yes = positives.select("query_id", "q_text", F.col("question").alias("text"), F.lit("correct").alias("kind"), F.lit(1).alias("label"))
    no = negatives.join(positives.select("query_id", "q_text"), "query_id").select("query_id", "q_text", "text", "kind", F.lit(0).alias("label"))
    return yes.unionByName(no)


__all__ = ["hard", "perturbations", "random_swap", "share", "targeted", "training_pairs"]
