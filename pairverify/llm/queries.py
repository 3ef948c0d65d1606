"""The ten corpus operators over their whole tables, with production parameters, and SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import covertree, decontam, langid, packing, pii, repeats, simhash, tokenfile, toxicity, warc
from ._common import id_crc32

LOWER_COS = 0.4


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def pii_key(spark: SparkSession) -> str:
    """The secret of surrogates: spark.pairverify.pii.key, which whoever publishes the results has to set to one of their own."""
    return spark.conf.get("spark.pairverify.pii.key", "key of the test tables")


def op1_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(_table(spark, sf_dir, "documents"), k=2, shingle=3)
    return found.select("doc_id", simhash.hex_fingerprint("fp").alias("fingerprint"), "component_id")


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = _table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels")
    model = toxicity.fit(docs, labels, id_crc32("doc_id") % 5 != 0)
    scored = toxicity.score(docs, model)
    return scored.select("doc_id", (id_crc32("doc_id") % 5 == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.remove_repeats(_table(spark, sf_dir, "documents"), window=13)


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.matches(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(_table(spark, sf_dir, "pages"), min_bytes=0).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_table(spark, sf_dir, "documents"))


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    model = langid.fit(docs, id_crc32("doc_id") % 3 != 1)
    found = langid.predict(docs, model)
    return found.select("doc_id", (id_crc32("doc_id") % 3 == 1).alias("held_out"), "lang_pred", "score")


def op8_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return covertree.near_vectors(_table(spark, sf_dir, "embeddings"), min_cos=0.95)


def vector_links_at_lower_cosine(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op8's search at a cosine that some of the given vectors reach, as none of the small tables has a pair at 0.95."""
    return covertree.near_vectors(_table(spark, sf_dir, "embeddings"), min_cos=LOWER_COS)


def op9_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.replace_entities(_table(spark, sf_dir, "documents"), pii_key(spark)).select("doc_id", "text", "n_entities")


def op10_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenfile.round_trip(_table(spark, sf_dir, "documents"))


def queries() -> dict:
    return {f.__name__: f for f in (op1_simhash, op2_toxicity, op3_substring_dedup, op4_decontamination, op5_warc, op6_packing, op7_language_id, op8_embedding_dedup, vector_links_at_lower_cosine, op9_pii, op10_token_files)}


_OP3 = r"""
WITH w AS (SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS words FROM documents),
s AS (SELECT doc_id, unnest(range(1, len(words) - 11)) AS i FROM w WHERE len(words) >= 13),
g AS (SELECT s.doc_id, s.i, md5(array_to_string(w.words[s.i:s.i + 12], chr(1))) AS h FROM s JOIN w USING (doc_id)),
m AS (SELECT h, min(doc_id) AS low FROM g GROUP BY h),
d AS (SELECT g.doc_id, g.i FROM g JOIN m USING (h) WHERE m.low < g.doc_id),
c AS (SELECT DISTINCT doc_id, unnest(range(i, i + 13)) AS p FROM d),
r AS (SELECT doc_id, list(p) AS gone FROM c GROUP BY doc_id),
k AS (SELECT w.doc_id, len(words) AS n, CASE WHEN gone IS NULL THEN words ELSE (SELECT list(words[p] ORDER BY p) FROM (SELECT unnest(range(1, len(words) + 1)) AS p) WHERE NOT list_contains(gone, p)) END AS kept
      FROM w LEFT JOIN r USING (doc_id))
SELECT doc_id, n::BIGINT AS n_words, (n - coalesce(len(kept), 0))::BIGINT AS n_removed, sha256(coalesce(array_to_string(kept, ' '), '')) AS kept_sha256 FROM k
"""

_OP5 = r"""
WITH p AS (SELECT page_id, strlen(coalesce(html, ''))::BIGINT AS n, sha1(coalesce(html, '')) AS hex FROM pages),
b AS (SELECT page_id, n, hex, array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + ((('0x' || substr(hex, 1 + 5 * (i // 4), 5))::BIGINT >> (15 - 5 * (i % 4))) & 31)::INT, 1)), '') AS digest FROM p),
m AS (SELECT *, max(page_id) OVER (PARTITION BY hex, n) AS first FROM b)
SELECT page_id, n AS payload_bytes, digest AS payload_digest, CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> first THEN first END AS refers_to FROM m
"""

_OP8 = r"""
WITH RECURSIVE v AS (SELECT vec_id, list_transform(embedding, lambda e: e::DOUBLE) AS x FROM embeddings),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id <> b.vec_id AND list_cosine_similarity(a.x, b.x) >= 0.95),
r AS (SELECT a AS node, b AS other FROM l UNION SELECT r.node, l.b FROM r JOIN l ON r.other = l.a),
c AS (SELECT node, least(node, min(other)) AS low FROM r GROUP BY node),
n AS (SELECT a AS vec_id, count(*) AS k FROM l GROUP BY a)
SELECT v.vec_id, coalesce(n.k, 0)::BIGINT AS n_links, coalesce(c.low, v.vec_id) AS component_id, coalesce(c.low, v.vec_id) = v.vec_id AS kept
FROM v LEFT JOIN n USING (vec_id) LEFT JOIN c ON c.node = v.vec_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op3_substring_dedup": _OP3, "op5_warc": _OP5, "op8_embedding_dedup": _OP8, "vector_links_at_lower_cosine": _OP8.replace("0.95", str(LOWER_COS))}
