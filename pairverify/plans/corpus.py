"""The query workload: shapes bound to all entities of the star schema, and samples of it in md5 order."""

from __future__ import annotations

from functools import reduce

from pairverify.constants import DRAWN_PER_SHAPE, SHARES
from pairverify.functions.text import sample_md5
from pairverify.sources.tables import table
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: shape: base table, key that is drawn, and the query with {column} standing for a value
SHAPES = {
    "fact_out": ("customer", "c_custkey", "SELECT ?x WHERE { <ent:customer/{c_custkey}> <rel:located_in> ?x . }"),
    "fact_in": ("nation", "n_nationkey", "SELECT ?x WHERE { ?x <rel:located_in> <ent:nation/{n_nationkey}> . }"),
    "fact_typed": ("nation", "n_nationkey", "SELECT ?x WHERE { ?x <rel:instance_of> <cls:supplier> . ?x <rel:located_in> <ent:nation/{n_nationkey}> . }"),
    "path_2": ("orders", "o_orderkey", "SELECT ?x WHERE { <ent:order/{o_orderkey}> <rel:placed_by> ?c . ?c <rel:located_in> ?x . }"),
    "path_3": ("orders", "o_orderkey", "SELECT ?x WHERE { <ent:order/{o_orderkey}> <rel:placed_by> ?c . ?c <rel:located_in> ?n . ?n <rel:part_of_region> ?x . }"),
    "fork": ("part", "p_partkey", 'SELECT ?x WHERE { ?x <rel:brand> "{p_brand}" . ?x <rel:part_type> "{p_type}" . }'),
    "blank": ("orders", "o_orderkey", "SELECT DISTINCT ?x WHERE { <ent:order/{o_orderkey}> <rel:has_line> _:s . _:s <rel:line_supplier> ?x . }"),
    "statement": ("lineitem", "l_orderkey", "SELECT ?x WHERE { <ent:order/{l_orderkey}> <rel:has_line> _:s . _:s <rel:line_part> <ent:part/{l_partkey}> . _:s <rel:quantity> ?x . }"),
    "count": ("customer", "c_custkey", "SELECT (COUNT(?x) AS ?n) WHERE { ?x <rel:placed_by> <ent:customer/{c_custkey}> . }"),
    "filter_num": ("nation", "n_nationkey", "SELECT ?x WHERE { ?x <rel:located_in> <ent:nation/{n_nationkey}> . ?x <rel:account_balance> ?b . FILTER(?b > 5000) }"),
    "filter_str": ("customer", "c_custkey", 'SELECT ?x WHERE { ?x <rel:located_in> <ent:nation/{c_nationkey}> . ?x <rel:market_segment> ?m . FILTER(?m = "{c_mktsegment}") }'),
    "ask": ("supplier", "s_suppkey", "ASK WHERE { <ent:supplier/{s_suppkey}> <rel:located_in> <ent:nation/{s_nationkey}> . }"),
    "rank": ("part", "p_partkey", 'SELECT ?x WHERE { ?x <rel:brand> "{p_brand}" . ?x <rel:retail_price> ?p . } ORDER BY DESC(?p) LIMIT 1'),
    "two_answers": ("customer", "c_custkey", "SELECT ?x ?m WHERE { <ent:customer/{c_custkey}> <rel:located_in> ?x . <ent:customer/{c_custkey}> <rel:market_segment> ?m . }"),
}


def shape_queries(spark: SparkSession, sf_dir: str, shape: str, per_shape: int | None = None) -> DataFrame:
    """Queries of one shape for all rows of its table, or for per_shape of them."""
    import re

    name, key, text = SHAPES[shape]
    rows = table(spark, sf_dir, name) if name != "lineitem" else table(spark, sf_dir, name).groupBy("l_orderkey").agg(F.min("l_partkey").alias("l_partkey"))
    rows = sample_md5(rows, key, per_shape) if per_shape else rows
    parts = re.split(r"\{(\w+)\}", text)
    sparql = F.concat(*[F.lit(p) if k % 2 == 0 else F.col(p).cast("string") for k, p in enumerate(parts)])
    return rows.select(F.concat(F.lit(f"{shape}:"), F.col(key).cast("string")).alias("query_id"), F.lit(shape).alias("shape"), sparql.alias("sparql"))


def build(spark: SparkSession, sf_dir: str, per_shape: int | None = None, shapes=None) -> DataFrame:
    """query_id, shape, sparql: the whole workload, which grows with the tables, or per_shape queries of each shape."""
    return reduce(DataFrame.unionAll, [shape_queries(spark, sf_dir, s, per_shape) for s in shapes or SHAPES])


def names_of(shape: str) -> tuple[int, int]:
    """How many entities a query of a shape names, by its text, and how many relations and classes."""
    import re

    names = set(re.findall(r"<([^>]+)>", SHAPES[shape][2]))
    nodes = sum(x.startswith("ent:") for x in names)
    return nodes, len(names) - nodes


def forms(spark: SparkSession) -> DataFrame:
    """query_id, sparql: the text of each shape with its columns not yet bound."""
    return spark.createDataFrame([(shape, text) for shape, (_, _, text) in SHAPES.items()], "query_id string, sparql string")


def drawn(spark: SparkSession, sf_dir: str, per_shape: int = DRAWN_PER_SHAPE) -> DataFrame:
    """The sample that verifiers are trained, tuned and judged on: about 6,000 queries for training where the tables have them."""
    return build(spark, sf_dir, per_shape)


def split(df: DataFrame, key: str = "query_id") -> DataFrame:
    """Adds split (train, tune, eval) by a second md5 of the query's id, so no query is on two sides."""
    from pairverify.functions.text import md5_share

    share = md5_share(F.concat(F.lit("split|"), F.col(key).cast("string")))
    return df.withColumn("split", F.when(share < SHARES["train"], "train").when(share < SHARES["train"] + SHARES["tune"], "tune").otherwise("eval"))
