"""Measures of verifiers, systems and metrics: confusion, histograms, filter effects, rank correlation, areas, intervals."""

from __future__ import annotations

from functools import reduce

from pairverify.constants import BINS, KEEP_TAU, TAU
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def _n(c: Column) -> Column:
    return F.sum(F.when(c, 1).otherwise(0)).cast("bigint")


def _part(a, b) -> Column:
    return F.col(a) / F.nullif(F.col(b), F.lit(0))


def confusion(scores: DataFrame, by: list[str], tau: float = TAU, truth: str = "correct", score: str = "score") -> DataFrame:
    """Counts and accuracy, precision, recall, specificity by group. Undefined shares are null."""
    yes, right = F.coalesce(F.col(score) > tau, F.lit(False)), F.col(truth).cast("boolean")
    c = scores.groupBy(*by).agg(_n(yes & right).alias("tp"), _n(yes & ~right).alias("fp"), _n(~yes & right).alias("fn"), _n(~yes & ~right).alias("tn"))
    c = c.withColumn("n", F.col("tp") + F.col("fp") + F.col("fn") + F.col("tn"))
    return c.withColumn("accuracy", (F.col("tp") + F.col("tn")) / F.nullif(F.col("n"), F.lit(0))).withColumn("precision", F.col("tp") / F.nullif(F.col("tp") + F.col("fp"), F.lit(0))).withColumn("recall", F.col("tp") / F.nullif(F.col("tp") + F.col("fn"), F.lit(0))).withColumn("specificity", F.col("tn") / F.nullif(F.col("tn") + F.col("fp"), F.lit(0)))


def macro(table: DataFrame, by: list[str], measures=("accuracy", "precision", "recall")) -> DataFrame:
    """Unweighted means over groups."""
    return table.groupBy(*by).agg(*[F.avg(m).alias(m) for m in measures])


def system_accuracy(pairs: DataFrame, z: float = 1.959964) -> DataFrame:
    """Share judged right by system with its Wilson interval."""
    t = pairs.groupBy("system").agg(F.count("*").alias("n"), F.avg(F.col("correct").cast("double")).alias("accuracy"))
    return wilson(t, z=z)


def wilson(t: DataFrame, p: str = "accuracy", n: str = "n", z: float = 1.959964) -> DataFrame:
    d = 1 + z * z / F.col(n)
    mid = (F.col(p) + z * z / (2 * F.col(n))) / d
    half = z * F.sqrt(F.col(p) * (1 - F.col(p)) / F.col(n) + z * z / (4 * F.col(n) * F.col(n))) / d
    return t.withColumn("low", mid - half).withColumn("high", mid + half)


def score_gap(scores: DataFrame, by: list[str], truth: str = "correct", score: str = "score") -> DataFrame:
    """Mean score, share judged right and the distance between both; rows without a score or a verdict count in neither."""
    t = scores.where(F.col(score).isNotNull() & F.col(truth).isNotNull()).groupBy(*by).agg(F.count("*").alias("n"), F.avg(score).alias("mean_score"), F.avg(F.col(truth).cast("double")).alias("accuracy"))
    return t.withColumn("gap", F.abs(F.col("mean_score") - F.col("accuracy")))


def histogram(scores: DataFrame, by: list[str], bins: int = BINS, score: str = "score") -> DataFrame:
    """Counts of all bins of [0, 1], empty ones included; the last bin is closed."""
    put = scores.where(F.col(score).isNotNull()).withColumn("bin", F.least(F.floor(F.col(score) * bins), F.lit(bins - 1)).cast("int"))
    counts = put.groupBy(*by, "bin").agg(F.count("*").alias("n"))
    grid = counts.select(*by).distinct().withColumn("bin", F.explode(F.sequence(F.lit(0), F.lit(bins - 1))))
    return grid.join(counts, [*by, "bin"], "left").withColumn("n", F.coalesce("n", F.lit(0)).cast("bigint"))


def filter_effect(scores: DataFrame, by: list[str], tau: float = KEEP_TAU, truth: str = "correct", score: str = "score") -> DataFrame:
    """before, after, retention from one pass."""
    right, kept = F.col(truth).cast("double"), F.col(score) >= tau
    return scores.groupBy(*by).agg(F.count("*").alias("n"), F.avg(right).alias("before"), F.avg(F.when(kept, right)).alias("after"), F.avg(F.coalesce(kept, F.lit(False)).cast("double")).alias("retention"))


def sweep(scores: DataFrame, by: list[str], steps: int = 100, truth: str = "correct", score: str = "score") -> DataFrame:
    """Accuracy, precision, recall and retention for thresholds k / steps, from counts by bin: no pass for each threshold.

    A score counts as accepted when it is at or above the threshold.
    """
    right = F.col(truth).cast("boolean")
    bins = scores.where(F.col(score).isNotNull()).groupBy(*by, F.least(F.floor(F.col(score) * steps + 1e-9), F.lit(steps)).cast("int").alias("bin")).agg(_n(right).alias("p"), _n(~right).alias("q"))
    grid = bins.select(*by).distinct().withColumn("bin", F.explode(F.sequence(F.lit(0), F.lit(steps))))
    up = Window.partitionBy(*by).orderBy(F.col("bin").desc())
    all_ = Window.partitionBy(*by)
    rows = grid.join(bins, [*by, "bin"], "left").fillna(0, ["p", "q"])
    rows = rows.withColumn("tp", F.sum("p").over(up)).withColumn("fp", F.sum("q").over(up)).withColumn("np", F.sum("p").over(all_)).withColumn("nq", F.sum("q").over(all_))
    rows = rows.withColumn("tau", F.col("bin") / steps).withColumn("kept", F.col("tp") + F.col("fp")).withColumn("n", F.col("np") + F.col("nq"))
    return rows.select(*by, "tau", ((F.col("tp") + F.col("nq") - F.col("fp")) / F.col("n")).alias("accuracy"), _part("tp", "kept").alias("precision"), _part("tp", "np").alias("recall"), _part("kept", "n").alias("retention"))


def pick_tau(swept: DataFrame, by: list[str], objective: str = "accuracy", least: float = 0.0) -> DataFrame:
    """Best threshold by group: highest accuracy, highest recall at a precision, or highest retention at a precision."""
    measure = {"accuracy": "accuracy", "recall_at_precision": "recall", "retention_at_precision": "retention"}[objective]
    rows = swept if objective == "accuracy" else swept.where(F.col("precision") >= least)
    return rows.groupBy(*by).agg(F.max_by("tau", F.struct(F.col(measure), -F.col("tau"))).alias("tau"), F.max(measure).alias(measure))


def auc(scores: DataFrame, by: list[str], truth: str = "correct", score: str = "score") -> DataFrame:
    """Area under the ROC curve from counts by distinct score; ties count half."""
    right = F.col(truth).cast("boolean")
    c = scores.where(F.col(score).isNotNull()).groupBy(*by, score).agg(_n(right).alias("p"), _n(~right).alias("q"))
    below = Window.partitionBy(*by).orderBy(score).rowsBetween(Window.unboundedPreceding, -1)
    c = c.withColumn("u", F.col("p") * (F.coalesce(F.sum("q").over(below), F.lit(0)) + F.col("q") / 2))
    return c.groupBy(*by).agg((F.sum("u") / F.nullif(F.sum("p") * F.sum("q"), F.lit(0))).alias("auc"))


def average_precision(scores: DataFrame, by: list[str], truth: str = "correct", score: str = "score") -> DataFrame:
    right = F.col(truth).cast("boolean")
    c = scores.where(F.col(score).isNotNull()).groupBy(*by, score).agg(_n(right).alias("p"), _n(~right).alias("q"))
    up = Window.partitionBy(*by).orderBy(F.col(score).desc())
    c = c.withColumn("gain", F.col("p") * F.sum("p").over(up) / F.sum(F.col("p") + F.col("q")).over(up))
    return c.groupBy(*by).agg((F.sum("gain") / F.nullif(F.sum("p"), F.lit(0))).alias("average_precision"))


def rank_correlation(table: DataFrame, truth: str, metrics: list[str]) -> DataFrame:
    """Spearman of each metric with truth over the table's few rows, with mean ranks for ties; rows without a value go, and a
    constant metric has none.

    Ranks are windows over one row for each system and metric, never over data. The table is read once for all metrics.
    """
    each = F.explode(F.array(*[F.struct(F.lit(m).alias("metric"), F.col(m).cast("double").alias("x")) for m in metrics])).alias("m")
    rows = table.select(F.col(truth).cast("double").alias("y"), each).select("m.metric", "m.x", "y").withColumn("ok", F.col("x").isNotNull() & F.col("y").isNotNull())
    for c in ("x", "y"):
        own = Window.partitionBy("metric", "ok")
        rows = rows.withColumn("_r", F.row_number().over(own.orderBy(c))).withColumn(f"r{c}", F.when(F.col("ok"), F.avg("_r").over(Window.partitionBy("metric", "ok", c)))).drop("_r")
    found = rows.groupBy("metric").agg(((F.avg(F.col("rx") * F.col("ry")) - F.avg("rx") * F.avg("ry")) / F.nullif(F.stddev_pop("rx") * F.stddev_pop("ry"), F.lit(0.0))).alias("rho"))
    names = table.sparkSession.createDataFrame([(m,) for m in metrics], "metric string")
    return names.join(found, "metric", "left").select("metric", "rho")


def mean_gap(table: DataFrame, truth: str, metrics: list[str]) -> DataFrame:
    return reduce(DataFrame.unionAll, [table.select("system", F.lit(m).alias("metric"), F.abs(F.col(m) - F.col(truth)).alias("gap")) for m in metrics])


def error_breakdown(scores: DataFrame, tau: float = TAU) -> DataFrame:
    return scores.groupBy("system", "kind").agg(F.count("*").alias("n"), _n(F.col("score") > tau).alias("accepted"))


def misclassified(scores: DataFrame, tau: float = TAU) -> DataFrame:
    return scores.where((F.col("score") > tau) != F.col("correct"))


def select_best(table: DataFrame, name: str, by: str) -> DataFrame:
    return table.agg(F.max_by(name, by).alias("best"), F.max(by).alias(by))


def export_sheet(pairs: DataFrame, path: str, n: int = 300) -> None:
    """A work sheet for people: n sampled pairs as one CSV file with empty `correct` and `reason`."""
    from pairverify.functions.text import sample_md5

    rows = sample_md5(pairs, "pair_id", n).select("pair_id", "q_text", F.array_join("described", "; ").alias("described"), "text", F.lit(None).cast("string").alias("correct"), F.lit(None).cast("string").alias("reason"))
    rows.coalesce(1).write.mode("overwrite").option("header", True).option("escape", '"').csv(path)


def import_sheet(spark, path: str) -> DataFrame:
    rows = spark.read.option("header", True).option("multiLine", True).option("escape", '"').schema("pair_id string, q_text string, described string, text string, correct string, reason string").csv(path)
    return rows.select("pair_id", F.lower("correct").isin("1", "true", "yes", "y").alias("correct"), "reason").where("correct is not null")
