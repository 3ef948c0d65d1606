"""Triple graphs from ordinary tables: head, relation, tail, tail_kind, num_value, ts_value."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import page_links, page_titles, table

#: relation: label, label of the inverse, description
RELATIONS = {
    "part_of_region": ("region", "member nation", "world region that a nation belongs to"),
    "located_in": ("nation", "resident", "nation in which a company has its seat"),
    "placed_by": ("buyer", "order placed", "customer who placed an order"),
    "has_line": ("order line", "order of line", "statement of one article within an order"),
    "line_part": ("article", "line for article", "part that an order line is about"),
    "line_supplier": ("deliverer", "line delivered", "supplier who delivers an order line"),
    "quantity": ("quantity", "line with quantity", "number of pieces in an order line"),
    "ship_date": ("shipping date", "line shipped", "day on which an order line left"),
    "account_balance": ("account balance", "owner of balance", "money on a company's account"),
    "market_segment": ("market segment", "customer in segment", "branch that a customer works in"),
    "brand": ("brand", "article of brand", "maker's name of a part"),
    "part_type": ("material type", "article of type", "kind and finish of a part"),
    "size": ("size", "article of size", "size class of a part"),
    "retail_price": ("retail price", "article at price", "recommended price of a part"),
    "order_status": ("order status", "order in status", "state of an order"),
    "total_price": ("total price", "order at price", "sum of an order"),
    "order_date": ("order date", "order of day", "day on which an order was placed"),
    "priority": ("priority", "order of priority", "urgency of an order"),
    "instance_of": ("class", "member", "kind of thing that something is"),
}
CLASSES = {"customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "order": "o_orderkey", "nation": "n_nationkey", "region": "r_regionkey"}
EMPTY = {"num_value": "double", "ts_value": "timestamp_ntz"}


def iri(kind: str, key: Column | str) -> Column:
    return F.concat(F.lit(f"ent:{kind}/"), (F.col(key) if isinstance(key, str) else key).cast("string"))


def statement_id(*extra: Column) -> Column:
    """One id for each order line: md5 over all its columns, money and amounts as whole hundredths."""
    cents = lambda c: F.round(F.col(c) * 100).cast("bigint").cast("string")
    parts = [F.col(c).cast("string") for c in ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")] + [cents(c) for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax")]
    return F.concat(F.lit("stmt:"), F.md5(F.concat_ws("|", *parts, "l_returnflag", "l_linestatus", F.date_format("l_shipdate", "yyyy-MM-dd"))))


def _edge(df: DataFrame, head: Column, relation: str, tail: Column, kind: str = "iri", num: Column | None = None, ts: Column | None = None) -> DataFrame:
    return df.select(head.alias("head"), F.lit(relation).alias("relation"), tail.cast("string").alias("tail"), F.lit(kind).alias("tail_kind"), (num if num is not None else F.lit(None)).cast("double").alias("num_value"), (ts if ts is not None else F.lit(None)).cast("timestamp_ntz").alias("ts_value"))


def star_schema(spark: SparkSession, sf_dir: str, statements: bool = True) -> DataFrame:
    t = lambda n: table(spark, sf_dir, n)
    c, s, p, o, n, r = (t(x) for x in ("customer", "supplier", "part", "orders", "nation", "region"))
    number = lambda df, head, rel, col: _edge(df, head, rel, F.col(col).cast("string"), "literal", num=F.col(col))
    word = lambda df, head, rel, col: _edge(df, head, rel, F.col(col), "literal")
    C, S, P, O, N, R = (iri(k, v) for k, v in CLASSES.items())  # noqa: E741, N806
    edges = [
        _edge(n, N, "part_of_region", iri("region", "n_regionkey")),
        _edge(c, C, "located_in", iri("nation", "c_nationkey")),
        _edge(s, S, "located_in", iri("nation", "s_nationkey")),
        _edge(o, O, "placed_by", iri("customer", "o_custkey")),
        number(c, C, "account_balance", "c_acctbal"),
        number(s, S, "account_balance", "s_acctbal"),
        word(c, C, "market_segment", "c_mktsegment"),
        word(p, P, "brand", "p_brand"),
        word(p, P, "part_type", "p_type"),
        number(p, P, "size", "p_size"),
        number(p, P, "retail_price", "p_retailprice"),
        word(o, O, "order_status", "o_orderstatus"),
        number(o, O, "total_price", "o_totalprice"),
        _edge(o, O, "order_date", F.date_format("o_orderdate", "yyyy-MM-dd"), "literal", ts=F.col("o_orderdate")),
        word(o, O, "priority", "o_orderpriority"),
        *[_edge(df, head, "instance_of", F.lit(f"cls:{k}")) for k, df, head in (("customer", c, C), ("supplier", s, S), ("part", p, P), ("order", o, O), ("nation", n, N), ("region", r, R))],
    ]
    if statements:
        line, st = t("lineitem"), statement_id()
        edges += [
            _edge(line, iri("order", "l_orderkey"), "has_line", st),
            _edge(line, st, "line_part", iri("part", "l_partkey")),
            _edge(line, st, "line_supplier", iri("supplier", "l_suppkey")),
            _edge(line, st, "quantity", F.col("l_quantity").cast("string"), "literal", num=F.col("l_quantity")),
            _edge(line, st, "ship_date", F.date_format("l_shipdate", "yyyy-MM-dd"), "literal", ts=F.col("l_shipdate")),
        ]
    return reduce(DataFrame.unionAll, edges)


def from_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    head = F.concat(F.lit("page:"), F.col("page_id").cast("string"))
    titles = page_titles(pages)
    edges = [_edge(page_links(pages), head, "links_to", F.concat(F.lit("url:"), F.col("target")))]
    edges += [_edge(titles, head, rel, F.col(col), "literal") for rel, col in (("has_title", "title"), ("in_language", "lang"), ("hosted_by", "host"))]
    return reduce(DataFrame.unionAll, edges)


def labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """iri, label of entities, classes and relations."""
    return entity_labels(spark, sf_dir).unionAll(schema_labels(spark))


def schema_labels(spark: SparkSession) -> DataFrame:
    """iri, label of classes and relations, which no table has."""
    fixed = [(f"rel:{k}", v[0]) for k, v in RELATIONS.items()] + [(f"cls:{k}", k) for k in CLASSES]
    return spark.createDataFrame(fixed, "iri string, label string")


def entity_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = lambda n: table(spark, sf_dir, n)
    of = lambda n, kind, key, name: t(n).select(iri(kind, key).alias("iri"), F.col(name).alias("label"))
    rows = [of("region", "region", "r_regionkey", "r_name"), of("nation", "nation", "n_nationkey", "n_name"), of("customer", "customer", "c_custkey", "c_name"), of("supplier", "supplier", "s_suppkey", "s_name"), of("part", "part", "p_partkey", "p_name")]
    rows.append(t("orders").select(iri("order", "o_orderkey").alias("iri"), F.concat(F.lit("Order#"), F.col("o_orderkey").cast("string")).alias("label")))
    return reduce(DataFrame.unionAll, rows)


def descriptions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """iri, predicate (rdfs_comment or schema_description), description."""
    return entity_descriptions(spark, sf_dir).unionAll(schema_descriptions(spark))


def schema_descriptions(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(f"rel:{k}", "rdfs_comment", v[2]) for k, v in RELATIONS.items()], "iri string, predicate string, description string")


def entity_descriptions(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = lambda n: table(spark, sf_dir, n)
    of = lambda df, kind, key, predicate, text: df.select(iri(kind, key).alias("iri"), F.lit(predicate).alias("predicate"), text.alias("description"))
    customers = t("customer").join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 nations
    rows = [
        of(t("part"), "part", "p_partkey", "schema_description", F.concat_ws(" ", "p_brand", "p_type", F.lit("of size"), F.col("p_size").cast("string"))),
        of(customers, "customer", "c_custkey", "schema_description", F.concat_ws(" ", F.lit("customer of"), "n_name", F.lit("in"), F.lower("c_mktsegment"))),
        of(t("customer"), "customer", "c_custkey", "rdfs_comment", F.concat_ws(" ", F.lit("company with balance"), F.round(F.col("c_acctbal") * 100).cast("bigint").cast("string"))),
        of(t("nation"), "nation", "n_nationkey", "rdfs_comment", F.lit("sovereign state")),
        of(t("region"), "region", "r_regionkey", "rdfs_comment", F.lit("part of the world")),
    ]
    return reduce(DataFrame.unionAll, rows)
