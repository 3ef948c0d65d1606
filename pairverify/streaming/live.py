"""Live feedback over streams of requests: scoring, windows with watermarks, state for each user, idempotent sinks."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pairverify.operators.translate import ship
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def requests(spark: SparkSession, path: str, schema: str, time: str = "ts", **options) -> DataFrame:
    """A file stream whose time column is cast to a timestamp, which watermarks need."""
    return spark.readStream.schema(schema).options(**options).parquet(path).withColumn(time, F.col(time).cast("timestamp"))


def score_stream(stream: DataFrame, pairs: DataFrame, key: str = "pair_id") -> DataFrame:
    """Requests with the stored score of their pair: a stream-static join without state."""
    return stream.join(pairs.select(key, "score"), key, "left")


def verdict_windows(scored: DataFrame, tau: float = 0.5, size: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    rows = scored.withWatermark("ts", late) if scored.isStreaming else scored
    return rows.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.sum((F.col("score") > tau).cast("bigint")).alias("accepted")).select(F.col("w.start").alias("start"), "n", "accepted")


def sessions(scored: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    rows = scored.withWatermark("ts", late) if scored.isStreaming else scored
    return rows.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def distinct_requests(stream: DataFrame, key: str = "event_id", late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def with_verdicts(asked: DataFrame, verdicts: DataFrame, within: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Requests joined with verdicts on the same pair that come at most `within` after; both sides' state is bounded."""
    a = asked.withWatermark("ts", late)
    v = verdicts.select(F.col("pair_id").alias("v_pair"), F.col("ts").alias("v_ts"), "score").withWatermark("v_ts", late)
    return a.join(v, F.expr(f"pair_id = v_pair AND v_ts >= ts AND v_ts <= ts + interval {within}"))


def ask_after_failures(scored: DataFrame, tau: float = 0.5, failures: int = 3) -> DataFrame:
    """For each request: the user's accepted share so far, and whether to ask the user after so many failures in a row."""
    ship()

    def step(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, good, run = state.get if state.exists else (0, 0, 0)
        for f in frames:
            rows = []
            for r in f.sort_values(["ts", "event_id"]).itertuples(index=False):
                ok = bool(r.score is not None and r.score > tau)
                n, good, run = n + 1, good + ok, 0 if ok else run + 1
                rows.append((key[0], r.event_id, good / n, run >= failures))
                run = 0 if run >= failures else run
            yield pd.DataFrame(rows, columns=["user_id", "event_id", "share", "ask"])
        state.update((n, good, run))

    return scored.select("user_id", "event_id", "ts", "score").groupBy("user_id").applyInPandasWithState(step, "user_id long, event_id long, share double, ask boolean", "n long, good long, run long", "append", "NoTimeout")


def sink_once(path: str) -> Callable[[DataFrame, int], None]:
    """A foreachBatch sink: one folder for each batch id, so a batch that runs again replaces its own rows."""

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return write
