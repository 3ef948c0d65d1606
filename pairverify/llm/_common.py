"""Shared plumbing: scratch tables, shipping of code, column handling, connected components."""

from __future__ import annotations

import atexit
import contextlib
import shutil
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_BATCH = "spark.sql.execution.arrow.maxBytesPerBatch"


def ship() -> None:
    """Let workers get this package's functions with the task, so that they need no copy of the repository."""
    import pairverify
    from pyspark import cloudpickle

    cloudpickle.register_pickle_by_value(pairverify)


def scratch_base(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir. Where that is unset, a temporary folder in local mode, where all tasks share this machine, and an error on a cluster."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        if not _LOCAL:
            _LOCAL.append(tempfile.mkdtemp(prefix="pairverify-"))
            atexit.register(shutil.rmtree, _LOCAL[0], ignore_errors=True)
        base = f"file://{_LOCAL[0]}"
    return f"{base.rstrip('/')}/{spark.sparkContext.applicationId}"


def scratch_dir(spark: SparkSession) -> str:
    """A fresh folder in this application's part of the scratch folder."""
    return f"{scratch_base(spark)}/{uuid.uuid4().hex}"


_LOCAL: list[str] = []


def delete(spark: SparkSession, path: str) -> None:
    """Delete a path of any store that Spark can write."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(where, True)


def cleanup(spark: SparkSession) -> None:
    """Delete all scratch tables of this application, once its results have been written."""
    delete(spark, scratch_base(spark))


@contextlib.contextmanager
def freed_shuffles(spark: SparkSession):
    """Within, Spark deletes the shuffle files of each finished write, whose rows are in a table by then."""
    before = spark.conf.get(_CLEANUP, None)
    try:
        spark.conf.set(_CLEANUP, "true")
    except Exception:  # noqa: BLE001  a Spark without this setting keeps its files until they are collected
        before = False
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(_CLEANUP)
        elif before:
            spark.conf.set(_CLEANUP, before)


@contextlib.contextmanager
def small_batches(spark: SparkSession, size: int = 4 << 20):
    """Within, tables are written with Arrow batches of about `size` bytes, unless the session has a bound of its own.

    Spark's batches of 10,000 whole texts are held once in each task's Python worker and up to three times in the JVM.
    """
    if spark.conf.get(_BATCH, None) is not None:
        yield
        return
    spark.conf.set(_BATCH, str(size))
    try:
        yield
    finally:
        spark.conf.unset(_BATCH)


def materialize(df: DataFrame, name: str = "rows", codec: str | None = None) -> DataFrame:
    """Write df as Parquet in the shared scratch folder and read it again: lineage ends here, lost executors or not."""
    spark = df.sparkSession
    path = f"{scratch_dir(spark)}/{name}"
    with freed_shuffles(spark):
        (df.write.option("compression", codec) if codec else df.write).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def release(*tables: DataFrame) -> None:
    """Delete tables made by materialize() that nothing reads any more."""
    for df in tables:
        delete(df.sparkSession, df._scratch)


def join_counted(rows: DataFrame, keys: DataFrame, on: str, n: str, most: int = 10_000) -> DataFrame:
    """rows joined with keys, which has one row for each value of `on` and in column n how many rows have it (dropped here).

    Values that over a thousandth of all rows, and over `most`, have are fewer than a thousand: they are broadcast, so that
    their rows stay where they are. The others are shuffled. Both sides should be tables, as they may be read twice.
    """
    total, top = keys.agg(F.sum(n), F.max(n)).first()
    line = max(most, (total or 0) // 1000)
    if (top or 0) <= line:
        return rows.join(keys.drop(n), on)
    hot = keys.where(F.col(n) > line).drop(n)
    rest = rows.join(F.broadcast(hot.select(on)), on, "left_anti").join(keys.where(F.col(n) <= line).drop(n), on)
    return rows.join(F.broadcast(hot), on).unionByName(rest)


def without(rows: DataFrame, gone: DataFrame, on: str, most: int = 500_000) -> DataFrame:
    """The rows whose value of `on` is not among the distinct non-null values of the one column of gone.

    gone is written first. Up to `most` values are broadcast, so that the rows, whole texts among them, are not shuffled.
    """
    gone = materialize(gone.toDF("__gone"), "gone")
    few = gone.count() <= most
    return rows.join(F.broadcast(gone) if few else gone, rows[on] == gone["__gone"], "left_anti")


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def id_crc32(name: str = "doc_id") -> Column:
    """CRC-32 of an id written as decimal text."""
    return F.crc32(F.col(name).cast("string").cast("binary"))


def hashed_share(key: Column, share: float) -> Column:
    """A deterministic filter that keeps about `share` of all distinct keys."""
    return F.pmod(F.xxhash64(key, F.lit("share")), F.lit(1 << 30)) < int(share * (1 << 30))


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """Smallest node reachable from each node that has an edge.

    edges: two long columns, any direction, repeats and loops allowed. Returns (node, root). Alternates two star
    contractions until nothing changes, with a written table after every round. Minima are taken by a map-side combined
    aggregate, and the edges of a node with very many neighbours get its minimum by a broadcast, so that no
    neighbourhood is gathered in one task. Empty edges: no rows.
    """
    e = edges.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).where("a <> b")
    e = materialize(e.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    state = None
    for _ in range(max_rounds):
        both = e.unionAll(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = materialize(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"), F.count("*").alias("n")), "low")
        large = join_counted(both, low, "u", "n").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.unionAll(low.where("m < u").select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        large = materialize(large, "large")
        release(e, low)
        least = materialize(large.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")), "least")
        small = join_counted(large, least, "u", "n").where("v <> m").select(F.greatest("v", "m").alias("u"), F.least("v", "m").alias("v"))
        e = materialize(small.unionAll(least.select("u", F.col("m").alias("v"))).where("u <> v").distinct(), "edges")
        release(large, least)
        now = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == state:
            break
        state = now
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = e.select("v").distinct()
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionAll(roots.select(F.col("v").alias("node"), F.col("v").alias("root")))
