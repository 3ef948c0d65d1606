"""What the pipeline's stages hold: Arrow batches bounded by bytes, and no shuffle of whole texts to leave some out."""

import corpus_pipeline
import pyarrow as pa
from pairverify.llm import _common, toxicity
from pyspark.sql import functions as F


def test_batches_are_bounded_within(spark):
    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([b.nbytes])], ["n", "size"])

    texts = spark.range(0, 6000, 1, 1).select("id", F.repeat(F.lit("x"), 3000).alias("text"))
    with _common.small_batches(spark, 1 << 20):
        got = _common.materialize(texts.mapInArrow(sizes, "n long, size long")).collect()
    assert sum(r["n"] for r in got) == 6000 and max(r["size"] for r in got) < 2 << 20
    assert spark.conf.get(_common._BATCH, None) is None
    spark.conf.set(_common._BATCH, "5000000")
    try:
        with _common.small_batches(spark):
            assert spark.conf.get(_common._BATCH) == "5000000"
        assert spark.conf.get(_common._BATCH) == "5000000"
    finally:
        spark.conf.unset(_common._BATCH)


def test_rows_left_out_by_broadcast_or_not(spark):
    rows = spark.createDataFrame([(None, "a"), (1, "b"), (1, "c"), (2, "d"), (3, None)], "doc_id long, text string")
    gone = spark.createDataFrame([(1,), (3,), (9,)], "doc_id long")
    want = [(None, "a"), (2, "d")]
    for most in (0, 3):
        assert sorted(map(tuple, _common.without(rows, gone, "doc_id", most).collect()), key=str) == sorted(want, key=str)
    assert _common.without(rows, gone.limit(0), "doc_id").count() == 5


def test_stages_do_not_shuffle_texts(spark, sf, monkeypatch):
    texts = ["w1 w2 w3 w4 w5 w6", "bad w2 w3 w4 w5 w6", "w1 w2 w3 w4 w5 w6", None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    seen = []

    def score(docs, model, id_col="doc_id", text_col="text"):
        return docs.select("doc_id", F.when(F.col("text").contains("bad"), 0.9).otherwise(0.1).alias("score"))

    monkeypatch.setattr(toxicity, "fit", lambda *a, **k: seen.append(1))
    monkeypatch.setattr(toxicity, "score", score)
    line = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        for stage, want in ((corpus_pipeline.drop_toxic, [0, 2, 3]), (corpus_pipeline.drop_near_duplicates, [0, 1, 3]), (corpus_pipeline.drop_leaks, [0, 1, 2, 3])):
            kept = stage(spark, docs, sf)
            plan = kept._jdf.queryExecution().executedPlan().toString()
            assert "SortMergeJoin" not in plan and "hashpartitioning" not in plan, stage.__name__
            assert sorted(r["doc_id"] for r in kept.collect()) == want
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", line)
    assert seen


def test_scores_do_not_depend_on_how_texts_are_cut():
    model = toxicity.ToxicityModel(toxicity.Network(2).p, 1.3, -0.2, 0.1)
    texts = pa.array([" ".join(f"w{(k * j) % 911}" for j in range(1, 40 + 300 * (k % 7))) for k in range(1, 400)] + [None, "", " "])
    whole, parts = model.scores(texts), [x for at in range(0, len(texts), 7) for x in model.scores(texts[at : at + 7], 16)]
    assert abs(whole - parts).max() < 1e-5
