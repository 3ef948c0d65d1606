"""All operators on null ids and texts, repeated rows, very long texts, clashing extra columns and empty tables."""

from collections import Counter

import pytest
from pairverify.llm import covertree, decontam, langid, packing, pii, repeats, simhash, tokenfile, toxicity, warc
from pyspark.sql import functions as F

SCHEMA = "doc_id long, text string, lang string, n_chars long, id long, value string, fp long, key string, part int, surrogate string, __x int"
LONG = " ".join(f"w{k % 977}x{k % 31}" for k in range(30_000))
TEXTS = [
    (None, "a lone text without any id, write to some.body@site.example.org about it soon please"),
    (None, "another one without id and nothing shared with any other text, from 10.20.30.40 it came"),
    (None, None),
    (1, None),
    (2, ""),
    (3, "   \t\n "),
    (4, "the same few words stand here twice over and over until thirteen words are reached at last"),
    (4, "the same few words stand here twice over and over until thirteen words are reached at last"),
    (5, "the same few words stand here twice over and over until thirteen words are reached at last"),
    (6, LONG),
    (7, "mail other.body@site.example.org"),
]


def rows(spark):
    return spark.createDataFrame([(k, t, None if k is None else "en" if k % 2 else "de", None, 7, "v", 1, "k", 2, "s", 3) for k, t in TEXTS], SCHEMA)


IDS = Counter(k for k, _ in TEXTS)


def ids(df):
    return Counter(r[0] for r in df.select("doc_id").collect())


def test_toxicity_rows(spark):
    docs = rows(spark)
    labels = spark.createDataFrame([(1, 1, 9), (2, 0, 9), (3, 1, 9), (None, 1, 9), (4, None, 9), (99, 0, 9)], "doc_id long, toxic int, id int")
    base = toxicity.fit(docs, labels, F.lit(True))  # the labelled documents have no word
    got = toxicity.score(docs, base)
    assert ids(got) == IDS and all(r["score"] == base.prior for r in got.where("doc_id in (1, 2, 3)").collect())
    empty = toxicity.fit(docs.limit(0), labels, F.lit(True))
    assert toxicity.score(docs.limit(0), empty).count() == 0 and ids(toxicity.score(docs, empty)) == IDS
    none = toxicity.fit(docs, labels.limit(0), F.lit(True))
    assert all(0 <= r["score"] <= 1 for r in toxicity.score(docs, none).collect())


def test_language_rows(spark):
    docs = rows(spark)
    for learn in (docs, docs.limit(0), docs.withColumn("lang", F.lit(None).cast("string"))):
        got = langid.predict(docs, langid.fit(learn, F.lit(True)))
        assert ids(got) == IDS
        assert all(r["lang_pred"] == "und" for r in got.collect() if r["doc_id"] in (1, 2, 3))


def test_one_of_each_keeps_rows_without_id(spark):
    docs = rows(spark)
    kept = simhash.one_of_each(docs, shingle=5)
    assert kept.columns == docs.columns
    # 5 goes for 4, whose rows stay together; 2 and 3 have no words either and go for 1; rows without id stay
    assert ids(kept) == Counter({None: 3, 1: 1, 4: 2, 6: 1, 7: 1})
    assert simhash.one_of_each(docs.limit(0)).count() == 0
    split = spark.createDataFrame([(1, "a b c d e f g h"), (2, "a b c d e f g h"), (2, "q r s t u v w x y z")], "doc_id long, text string")
    assert ids(simhash.one_of_each(split)) == Counter({1: 1, 2: 2})


def test_personal_data_rows(spark):
    docs = rows(spark)
    got = pii.replace_entities(docs, "k")
    clash = pii.replace_entities(docs.withColumn("n_entities", F.lit(-1)), "k")
    assert clash.columns == [*docs.columns, "n_entities", "n_entities_2"] and {r["n_entities"] for r in clash.collect()} == {-1}
    assert ids(got) == IDS and set(got.columns) == {*docs.columns, "n_entities"}
    texts = [r["text"] for r in got.where("doc_id is null").collect()]
    assert None in texts and not any("some.body" in (t or "") or "10.20.30.40" in (t or "") for t in texts)
    assert {r["value"] for r in got.collect()} == {"v"} and LONG in [r["text"] for r in got.collect()]


def test_leak_rows(spark):
    docs = rows(spark)
    tests = spark.createDataFrame([(1, TEXTS[6][1], 5), (None, LONG[:300], 5), (2, None, 5), (3, "", 5)], "item_id long, text string, id int")
    found = decontam.matches(docs, tests)
    assert {(r["doc_id"], r["item_id"]) for r in found.collect()} == {(4, 1), (5, 1), (6, None)}
    assert ids(decontam.clean(docs, tests)) == Counter({None: 3, 1: 1, 2: 1, 3: 1, 7: 1})
    assert ids(decontam.clean(docs, tests.limit(0))) == IDS and decontam.clean(docs.limit(0), tests).count() == 0


def test_repeat_rows(spark):
    got = repeats.remove_repeats(rows(spark))
    assert ids(got) == IDS
    gone = {r["doc_id"]: r["n_removed"] for r in got.where("doc_id is not null").collect()}
    assert gone[4] == 0 and gone[5] == len(TEXTS[8][1].split()) and gone[1] == gone[2] == gone[3] == 0
    assert repeats.remove_repeats(rows(spark).limit(0)).count() == 0


def test_packed_and_filed_rows(spark):
    docs = rows(spark)
    pieces = packing.pack(docs).collect()
    assert Counter(r["doc_id"] for r in pieces if r["start"] == 0) == IDS
    lengths = Counter()
    for r in pieces:
        lengths[r["sequence_id"]] += r["length"]
    assert sorted(lengths) == list(range(len(lengths))) and max(lengths.values()) <= 1024
    assert packing.pack(docs.limit(0)).count() == 0
    filed = tokenfile.round_trip(docs)
    assert ids(filed) == IDS and tokenfile.round_trip(docs.limit(0)).count() == 0


@pytest.mark.parametrize("n", [0, 5])
def test_vectors_and_pages_rows(spark, n):
    v = spark.createDataFrame([(1, [1.0, 0.0], 3), (1, [1.0, 0.0], 3), (None, None, 3), (2, [], 3), (3, [0.0, None], 3)][:n], "vec_id long, embedding array<float>, id int")
    got = covertree.near_vectors(v)
    assert Counter(r["vec_id"] for r in got.collect()) == Counter([1, 1, None, 2, 3][:n])
    p = spark.createDataFrame([(1, None, None, 2), (2, "u", "", 2), (None, "u", "<a>", 2), (3, "u", "WARC/1.0\r\n\r\n" * 50, 2), (4, None, "<a>", 2)][:n], "page_id long, url string, html string, size int")
    assert Counter(r["page_id"] for r in warc.round_trip(p).collect()) == Counter([1, 2, None, 3, 4][:n])
