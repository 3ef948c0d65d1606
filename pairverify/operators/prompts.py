"""Prompts: terms of a query, labels and descriptions from the graph, the relabelled query, and the four-part message."""

from __future__ import annotations

from functools import reduce

from pairverify.constants import SHOTS
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TASK_TEXT = "You are given a query over a graph, with names in square brackets. Write one English question that asks for exactly what the query asks for."
REFLECTION_TEXT = "Read your question again. If anything is missing, added or turned around, correct it. Answer with the final question alone."
EXAMPLES = [
    ("SELECT ?x WHERE { [River Thames] [mouth] ?x . }", "What is X such that X is the mouth of River Thames?"),
    ("SELECT (COUNT(?x) AS ?n) WHERE { ?x [author] [Jane Roe] . }", "How many X are there such that Jane Roe is the author of X?"),
    ("ASK WHERE { [Oslo] [capital of] [Norway] . }", "Is it true that Oslo has the capital of Norway?"),
    ("SELECT ?x WHERE { ?x [height] ?h . FILTER(?h > 100) } ORDER BY DESC(?h) LIMIT 1", "What is X such that H is the height of X and H is greater than 100, first by the highest H, only 1?"),
]
IRI = r"<([^>]+)>"
#: What an entity's IRI begins with; other IRIs are of relations and classes.
NODE = "ent:"
MESSAGES = "array<struct<turn:int,role:string,content:string>>"
PARTS = ("task", "examples", "descriptions", "query")


def query_terms(queries: DataFrame) -> DataFrame:
    """query_id, pos (in order of appearance), slot (relation or node), iri."""
    terms = F.regexp_extract_all("sparql", F.lit(IRI), F.lit(1))
    rows = queries.select("query_id", "sparql", F.posexplode(terms).alias("pos", "iri"))
    return rows.select("query_id", "pos", F.when(F.col("iri").startswith("rel:"), "relation").otherwise("node").alias("slot"), "iri")


def fetch(terms: DataFrame, labels: DataFrame, descriptions: DataFrame, priority=("rdfs_comment", "schema_description"), on_missing: str = "keep_iri") -> DataFrame:
    """terms with label, description and `missing`; the first predicate of `priority` that an entity has wins.

    A missing label keeps the local name of the IRI ("keep_iri") or stays null ("omit"). Distinct terms are looked up,
    so a name that every query uses travels once.
    """
    known = terms.select("iri").distinct()
    rank = F.array_position(F.array(*map(F.lit, priority)), F.col("predicate"))
    own = descriptions.where(F.col("predicate").isin(*priority)).groupBy("iri").agg(F.min_by("description", rank).alias("description"))
    known = known.join(labels, "iri", "left").join(own, "iri", "left")
    local = F.element_at(F.split("iri", "[:/]"), -1)
    label = F.coalesce("label", local) if on_missing == "keep_iri" else F.col("label")
    return terms.join(known.select("iri", label.alias("label"), "description", F.col("label").isNull().alias("missing")), "iri")


def relabel(queries: DataFrame, found: DataFrame) -> DataFrame:
    """queries with q_text, every IRI replaced by its [label], `used` (iri and label in order) and `described`.

    The text is taken apart at its IRIs and woven anew, so an IRI that begins another one is never touched.
    """
    item = F.struct("pos", "iri", "label", "description")
    rows = found.groupBy("query_id").agg(F.array_sort(F.collect_list(item)).alias("terms"))
    gaps = F.split("sparql", IRI, -1)
    named = F.transform("terms", lambda t: F.concat(F.lit("["), F.coalesce(t["label"], t["iri"]), F.lit("]")))
    woven = F.array_join(F.flatten(F.transform(F.arrays_zip(gaps.alias("g"), named.alias("n")), lambda z: F.array(z["g"], F.coalesce(z["n"], F.lit(""))))), "")
    out = queries.join(rows, "query_id", "left").withColumn("terms", F.coalesce("terms", F.array().cast("array<struct<pos:int,iri:string,label:string,description:string>>")))
    told = F.array_distinct(F.transform(F.filter("terms", lambda t: t["description"].isNotNull()), lambda t: F.concat(F.coalesce(t["label"], t["iri"]), F.lit(": "), t["description"])))
    return out.withColumn("q_text", F.when(F.size("terms") > 0, woven).otherwise(F.col("sparql"))).withColumn("used", F.transform("terms", lambda t: F.struct(t["iri"].alias("iri"), t["label"].alias("label")))).withColumn("described", told).drop("terms")


def known_names(labels: DataFrame, descriptions: DataFrame, priority=("rdfs_comment", "schema_description")) -> DataFrame:
    """iri, label, description: a row for each name; the first predicate of `priority` that an entity has wins."""
    rank = F.array_position(F.array(*map(F.lit, priority)), F.col("predicate"))
    none = lambda kind: F.lit(None).cast(kind)
    own = descriptions.where(F.col("predicate").isin(*priority)).select("iri", none("string").alias("label"), "description", rank.alias("_rank"))
    rows = labels.select("iri", "label", none("string").alias("description"), none("bigint").alias("_rank")).unionAll(own)
    return rows.groupBy("iri").agg(F.min("label").alias("label"), F.min_by("description", "_rank").alias("description"))


def form_terms(found: DataFrame) -> DataFrame:
    """What the queries of a form have in common, a row for each form, from the terms of the forms' own texts (fetch(), whose query_id is the form).

    names and labels: what stands for what in the text; told: the descriptions before, between and after the named nodes;
    used: the terms in order, with the place of a node among the nodes or null. A node is an entity's IRI, which differs
    from query to query; equal ones share a place.
    """
    rows = found.groupBy(F.col("query_id").alias("shape")).agg(F.array_sort(F.collect_list(F.struct("pos", "iri", "label", "description"))).alias("t"))
    node = lambda x: F.startswith(x["iri"], F.lit(NODE))
    rows = rows.withColumn("nodes", F.array_distinct(F.transform(F.filter("t", node), lambda x: x["iri"])))
    rows = rows.withColumn("fixed", F.filter("t", lambda x: ~node(x)))
    place = lambda x: F.nullif(F.array_position("nodes", x["iri"]), F.lit(0))
    first = lambda i: F.array_position(F.transform("t", lambda x: x["iri"]), F.get("nodes", i.cast("int")))
    upto = lambda i: F.when(i < F.size("nodes"), first(i)).otherwise(F.size("t") + 1)
    after = lambda i: F.when(i > 0, first(i - 1)).otherwise(0)
    told = lambda part: F.transform(F.filter(part, lambda x: ~node(x) & x["description"].isNotNull()), lambda x: F.concat(x["label"], F.lit(": "), x["description"]))
    return rows.select(
        "shape",
        F.transform("fixed", lambda x: F.concat(F.lit("<"), x["iri"], F.lit(">"))).alias("names"),
        F.transform("fixed", lambda x: F.concat(F.lit("["), x["label"], F.lit("]"))).alias("labels"),
        F.transform(F.sequence(F.lit(0), F.size("nodes")), lambda i: told(F.slice("t", after(i).cast("int") + 1, (upto(i) - after(i) - 1).cast("int")))).alias("told"),
        F.transform("t", lambda x: F.struct(x["iri"].alias("iri"), x["label"].alias("label"), place(x).cast("int").alias("place"))).alias("in_order"),
    )


def relabel_forms(parts: list[tuple[DataFrame, int]], forms: DataFrame, known: DataFrame, fixed: int) -> DataFrame:
    """relabel() of queries of forms (from form_terms, by their shape), in parts with the number of nodes that each names.

    No form has more than `fixed` other names. What a form has in common is looked up and put in order once, not for each
    query; a query is joined with `known` (from known_names) once for each node that it names, and stays in its row.
    """
    columns, nodes = parts[0][0].columns, max(n for _, n in parts)
    named = []
    for rows, n in parts:
        for k in range(nodes):
            if k >= n:
                rows = rows.withColumns({f"_{x}{k}": F.lit(None).cast("string") for x in ("iri", "label", "note")})
                continue
            # the first node from where the one before ends
            past = "1" if not k else f"locate(concat('<', _iri{k - 1}, '>'), sparql) + 1"
            rows = rows.withColumn("iri", F.expr(f"substring_index(substring(sparql, locate('<{NODE}', sparql, {past}) + 1), '>', 1)"))
            rows = rows.join(known, "iri", "left").withColumnsRenamed({"iri": f"_iri{k}", "label": f"_label{k}", "description": f"_note{k}"})
        named.append(rows.select(*columns, *[f"_{x}{k}" for k in range(nodes) for x in ("iri", "label", "note")]))
    rows = reduce(DataFrame.unionAll, named).join(F.broadcast(forms), "shape")
    for k in range(nodes):
        rows = rows.withColumn(f"_label{k}", F.coalesce(f"_label{k}", F.element_at(F.split(f"_iri{k}", "[:/]"), -1)))
    text, told, empty = F.col("sparql"), F.get("told", F.lit(0)), F.array().cast("array<string>")
    swap = lambda text, x, y: F.replace(text, F.coalesce(x, F.lit("")), F.coalesce(y, F.lit("")))
    for k in range(fixed):
        text = swap(text, F.get("names", F.lit(k)), F.get("labels", F.lit(k)))
    for k in range(nodes):  # marks first, so that no label is taken for a name
        text = swap(text, F.concat(F.lit("<"), F.col(f"_iri{k}"), F.lit(">")), F.lit(f"\x01{k}\x01"))
    for k in range(nodes):
        text = swap(text, F.lit(f"\x01{k}\x01"), F.concat(F.lit("["), F.col(f"_label{k}"), F.lit("]")))
        told = F.concat(told, F.array(F.concat(F.col(f"_label{k}"), F.lit(": "), F.col(f"_note{k}"))), F.coalesce(F.get("told", F.lit(k + 1)), empty))

    def used(x: Column) -> Column:
        own = F.struct(x["iri"].alias("iri"), x["label"].alias("label"))
        for k in range(nodes):
            own = F.when(x["place"] == k + 1, F.struct(F.col(f"_iri{k}").alias("iri"), F.col(f"_label{k}").alias("label"))).otherwise(own)
        return own

    none = F.array(F.lit(None).cast("string"))
    return rows.select(*columns, text.alias("q_text"), F.transform("in_order", used).alias("used"), F.array_except(told, none).alias("described"))


def few_shot_block(examples=EXAMPLES, k: int = SHOTS) -> str:
    return "\n\n".join(f"Query: {q}\nQuestion: {t}" for q, t in examples[:k])


def build_prompt(relabelled: DataFrame, parts=PARTS, k: int = SHOTS) -> DataFrame:
    """Adds prompt, messages and prompt_sha. Fixed parts come first, so that providers can keep them."""
    pieces = []
    if "task" in parts:
        pieces.append(F.lit(TASK_TEXT))
    if "examples" in parts and k:
        pieces.append(F.lit(few_shot_block(k=k)))
    if "descriptions" in parts:
        pieces.append(F.when(F.size("described") > 0, F.concat(F.lit("Notes:\n"), F.array_join("described", "\n"))))
    if "query" in parts:
        pieces.append(F.concat(F.lit("Query: "), F.col("q_text"), F.lit("\nQuestion:")))
    text = F.concat_ws("\n\n", *pieces)
    out = relabelled.withColumn("prompt", text)
    return out.withColumn("messages", F.array(F.struct(F.lit(1).alias("turn"), F.lit("user").alias("role"), F.col("prompt").alias("content")))).withColumn("prompt_sha", F.sha2("prompt", 256))
