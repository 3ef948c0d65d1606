"""Readers and sinks: declared-schema tables, JSON lines, CSV, N-Triples text, links and titles of HTML pages."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")


def views(spark: SparkSession, sf_dir: str) -> None:
    """Register every table as a temporary view."""
    for name in SCHEMAS:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def json_lines(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).json(path)


def csv(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.schema(schema).option("header", True).option("multiLine", True).option("escape", '"').csv(path)


def ntriples(lines: DataFrame, column: str = "value") -> DataFrame:
    """head, relation, tail, tail_kind from lines of N-Triples text; comments and broken lines go."""
    form = r'^\s*(<[^>]*>|_:\w+)\s+<([^>]*)>\s+(<[^>]*>|_:\w+|"(?:[^"\\]|\\.)*"(?:@[\w-]+|\^\^<[^>]*>)?)\s*\.\s*$'
    c = F.col(column)
    part = lambda k: F.regexp_extract(c, form, k)
    bare = lambda x: F.regexp_replace(x, "^<|>$", "")
    tail = part(3)
    literal = tail.startswith('"')
    return lines.where(c.rlike(form)).select(
        bare(part(1)).alias("head"),
        part(2).alias("relation"),
        F.when(literal, F.regexp_extract(tail, r'^"((?:[^"\\]|\\.)*)"', 1)).otherwise(bare(tail)).alias("tail"),
        F.when(literal, "literal").otherwise("iri").alias("tail_kind"),
    )


class _Range(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class _TripleReader(DataSourceReader):
    def __init__(self, options):
        self.path, self.size = options["path"], int(options.get("rangeBytes", 32 << 20))

    def partitions(self):
        import os

        n = os.path.getsize(self.path)
        return [_Range(a, min(a + self.size, n)) for a in range(0, max(n, 1), self.size)]

    def read(self, partition):
        import re

        form = re.compile(r'\s*<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"((?:[^"\\]|\\.)*)"\S*)\s*\.')
        with open(self.path, "rb") as f:
            if partition.start:  # the line that holds the byte before belongs to the range before
                f.seek(partition.start - 1)
                f.readline()
            while f.tell() < partition.stop and (line := f.readline()):
                if m := form.match(line.decode("utf-8", "replace")):
                    yield m[1], m[2], m[3] if m[3] is not None else m[4], "iri" if m[3] is not None else "literal"


class TripleSource(DataSource):
    """spark.dataSource.register(TripleSource); spark.read.format("triples").option("path", local_or_mounted_file)."""

    @classmethod
    def name(cls):
        return "triples"

    def schema(self):
        return "head string, relation string, tail string, tail_kind string"

    def reader(self, schema):
        return _TripleReader(self.options)


def page_links(pages: DataFrame) -> DataFrame:
    links = F.regexp_extract_all("html", F.lit(r'<a href="([^"]*)"'), F.lit(1))
    return pages.select("page_id", F.posexplode(links).alias("pos", "target"))


def page_titles(pages: DataFrame) -> DataFrame:
    return pages.select("page_id", F.regexp_extract("html", r"<title>([^<]*)</title>", 1).alias("title"), F.regexp_extract("html", r'<html lang="([^"]*)"', 1).alias("lang"), F.regexp_extract("url", r"^https?://([^/]+)", 1).alias("host"))


def page_text(pages: DataFrame) -> DataFrame:
    """page_id and the article's text without markup, entities resolved."""
    import pandas as pd

    @F.pandas_udf("string")
    def plain(x: pd.Series) -> pd.Series:
        import html as h

        return x.map(h.unescape, na_action="ignore")

    body = F.regexp_extract("html", r"(?s)<article>(.*?)</article>", 1)
    return pages.select("page_id", plain(F.trim(F.regexp_replace(body, r"<[^>]+>", " "))).alias("text"))
