"""From questions back to queries, in arms: untrained with exemplars, trained on raw pairs, trained on verified pairs.

A trained model is a classifier of a question's shape and, for each shape, what its pairs teach: the most frequent query
with a place for every name, and which of a question's mentions fills which place. Mentions are found and linked by a join
of a question's word runs with the graph's labels; of several entities with one name, the one whose description shares
most words with the question is taken, then the smallest IRI. The untrained arm only has the four exemplars of the
prompt: it takes the one whose wording is closest and puts the question's relation and names into its places.
"""

from __future__ import annotations

import copy
import re
from collections import Counter

import pandas as pd
from pairverify.constants import DRAW_TAU, N_DRAW
from pairverify.functions.text import sample_md5, tokens
from pairverify.operators.translate import ship
from pairverify.operators.prompts import EXAMPLES
from pairverify.plans.querytext import canonical, parse
from pairverify.sources.graph import CLASSES, RELATIONS
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def draw(pairs: DataFrame, n: int = N_DRAW, tau: float | None = None) -> DataFrame:
    """n pairs in md5 order, of all or of those with a score above tau."""
    return sample_md5(pairs if tau is None else pairs.where(F.col("score") > tau), "query_id", n)


def shape_words(column: str):
    """Words of a question that do not name things."""
    return F.filter(tokens(F.regexp_replace(column, r"\S*[#\d]\S*", " ")), lambda w: F.length(w) < 16)


class ShapeClassifier:
    @staticmethod
    def fit(pairs: DataFrame, weight: str | None = None) -> "ShapeClassifier":
        """From question and shape; weights of pairs may be their scores."""
        from pyspark.ml import Pipeline
        from pyspark.ml.classification import LogisticRegression
        from pyspark.ml.feature import HashingTF, IndexToString, StringIndexer

        rows = pairs.withColumn("_w", shape_words("question"))
        index = StringIndexer(inputCol="shape", outputCol="_y", stringOrderType="alphabetAsc").fit(rows)
        tf = HashingTF(numFeatures=2048, inputCol="_w", outputCol="_f")
        lr = LogisticRegression(featuresCol="_f", labelCol="_y", predictionCol="_p", probabilityCol="_pr", rawPredictionCol="_raw", regParam=1e-3, maxIter=40, **({"weightCol": weight} if weight else {}))
        model = Pipeline(stages=[tf, lr]).fit(index.transform(rows))
        out = ShapeClassifier()
        out.model, out.back = model, IndexToString(inputCol="_p", outputCol="shape_pred", labels=index.labels)
        return out

    def predict(self, questions: DataFrame) -> DataFrame:
        return self.back.transform(self.model.transform(questions.withColumn("_w", shape_words("question")))).drop("_w", "_f", "_p", "_pr", "_raw")


def link(terms: DataFrame, labels: DataFrame, descriptions: DataFrame) -> DataFrame:
    """terms (query_id, question, label) with iri."""
    known = descriptions.groupBy("iri").agg(F.min("description").alias("description"))
    cand = terms.join(labels, "label", "left").join(known, "iri", "left")
    shared = F.size(F.array_intersect(tokens(F.col("question")), tokens(F.col("description"))))
    return cand.groupBy("query_id", "label").agg(F.min_by("iri", F.struct(-shared, F.col("iri"))).alias("iri"))


#: Labels of relations and classes, which belong to a query's shape; every other label is a name.
VOCABULARY = {v[0] for v in RELATIONS.values()} | set(CLASSES)
PLACE = re.compile(r'\[([^\]]*)\]|"([^"]*)"')


def literals(pairs: DataFrame) -> DataFrame:
    """The quoted values of known queries, as labels without an entity."""
    values = F.regexp_extract_all("q_text", F.lit('"([^"]*)"'), F.lit(1))
    return pairs.select(F.explode(values).alias("label")).distinct()


def with_mentions(questions: DataFrame, labels: DataFrame, descriptions: DataFrame, values: DataFrame, longest: int = 5) -> DataFrame:
    """Adds mentions: place, words, text and IRI (null for a value) of every known label in the question, in order."""
    words = F.filter(F.split(F.regexp_replace("question", r"'s\b|[?,.](?=\s|$)", " "), r"\s+"), lambda w: w != "")
    spot = lambda w, n: F.transform(F.when(F.size(w) >= n, F.sequence(F.lit(1), F.size(w) - (n - 1))).otherwise(F.array().cast("array<int>")), lambda i: F.struct(i.alias("at"), F.lit(n).alias("n"), F.array_join(F.slice(w, i, n), " ").alias("label")))
    spots = questions.select("query_id", "question", words.alias("w")).select("query_id", "question", F.explode(F.flatten(F.array(*[spot(F.col("w"), n) for n in range(1, longest + 1)]))).alias("s")).select("query_id", "question", "s.*")
    linked = link(spots.select("query_id", "question", "label").distinct().join(labels.select("label").distinct(), "label", "left_semi"), labels, descriptions)
    known = spots.join(linked, ["query_id", "label"]).select("query_id", "at", "n", "label", "iri")
    quoted = spots.join(values, "label", "left_semi").select("query_id", "at", "n", "label", F.lit(None).cast("string").alias("iri"))
    each = known.unionAll(quoted).groupBy("query_id").agg(F.array_sort(F.collect_list(F.struct("at", "n", "label", "iri"))).alias("mentions"))
    return questions.join(each, "query_id", "left")


def _names(mentions) -> list[str]:
    """Mentions of names in order, the longest of those that overlap, relations and classes left out."""
    out, end = [], 0
    for m in sorted(mentions if mentions is not None else [], key=lambda m: (m["at"], -m["n"])):
        if m["at"] >= end and m["label"] not in VOCABULARY:
            out.append(m["label"])
            end = m["at"] + m["n"]
    return out


def _shape_of(query: str) -> tuple[str, list[str]]:
    """A query with places for its names, and the names."""
    names: list[str] = []

    def place(m):
        if m[1] is not None and m[1] in VOCABULARY:
            return m[0]
        names.append(m[1] if m[1] is not None else m[2])
        return f"[\x00{len(names) - 1}]" if m[1] is not None else f'"\x00{len(names) - 1}"'

    return PLACE.sub(place, query), names


def _filled(shape: str, names: list) -> str | None:
    for k, name in enumerate(names):
        if name is None:
            return None
        shape = shape.replace(f"\x00{k}", name)
    return None if "\x00" in shape else shape


def learned_shapes(pairs: DataFrame) -> dict[str, tuple[str, tuple]]:
    """By shape: its most frequent query with places, and the most frequent answer to which mention fills each place."""
    ship()

    def run(frames):
        for f in frames:
            seen: Counter = Counter()
            for shape, query, mentions in f[["shape", "q_text", "mentions"]].itertuples(index=False):
                form, names = _shape_of(query)
                have = _names(mentions)
                seen[shape, form, ",".join(str(have.index(n)) if n in have else "-" for n in names)] += 1
            yield pd.DataFrame([(*k, n) for k, n in seen.items()], columns=["shape", "form", "fill", "n"])

    rows = pairs.mapInPandas(run, "shape string, form string, fill string, n long").groupBy("shape", "form", "fill").agg(F.sum("n").alias("n"))
    best = rows.groupBy("shape").agg(F.max_by(F.struct("form", "fill"), F.struct("n", "form", "fill")).alias("best")).collect()  # one row for each shape
    return {r["shape"]: (r["best"]["form"], tuple(None if x == "-" else int(x) for x in r["best"]["fill"].split(",") if x)) for r in best}


class Reader:
    """Reads questions (with mentions) into queries: trained from pairs, or, made without pairs, from the prompt's exemplars."""

    def __init__(self, classifier: ShapeClassifier | None = None, shapes: dict | None = None):
        self.classifier, self.shapes = classifier, shapes

    @staticmethod
    def fit(pairs: DataFrame, weight: str | None = None) -> "Reader":
        return Reader(ShapeClassifier.fit(pairs, weight), learned_shapes(pairs))

    def read(self, questions: DataFrame) -> DataFrame:
        """Adds pred_text: the relabelled query that each question is taken for, null where a place stays open."""
        ship()
        rows = self.classifier.predict(questions) if self.classifier else questions.withColumn("shape_pred", F.lit(None).cast("string"))
        schema, shapes = copy.deepcopy(rows.schema).add("pred_text", "string"), self.shapes

        def trained(question, shape, mentions):
            form, fill = shapes[shape]
            have = _names(mentions)
            return _filled(form, [have[k] if k is not None and k < len(have) else None for k in fill])

        def closest(question, shape, mentions):
            plain = lambda t: set(re.findall(r"[a-z]+", t.lower()))
            query = max(EXAMPLES, key=lambda e: (len(plain(question) & plain(e[1])) / len(plain(question) | plain(e[1])), e))[0]
            relation = next((m["label"] for m in mentions if m["label"] in VOCABULARY), None) if mentions is not None else None
            q, have = parse(query), _names(mentions)
            known = [t for p in q["patterns"] for t in (p[0], p[2]) if t[:1] == "["]
            form = PLACE.sub(lambda m: f"[\x00{known.index(m[0]) + 1}]" if m[0] in known else "[\x000]", query)
            return _filled(form, [relation, *(have[k] if k < len(have) else None for k in range(len(known)))])

        def run(frames):
            one = trained if shapes else closest
            for f in frames:
                got = [one(r.question, r.shape_pred, r.mentions) for r in f.itertuples(index=False)]
                yield f.assign(pred_text=pd.Series(got, index=f.index, dtype=object))

        return rows.mapInPandas(run, schema)


def same_query(rows: DataFrame, a: str = "q_text", b: str = "pred_text") -> DataFrame:
    """Adds exact: both texts have one canonical form; false for a missing prediction."""
    ship()

    @F.pandas_udf("boolean")
    def same(x: pd.Series, y: pd.Series) -> pd.Series:
        def one(p, q):
            try:
                return bool(q) and canonical(parse(p)) == canonical(parse(q))
            except ValueError:
                return False

        return pd.Series([one(p, q) for p, q in zip(x, y, strict=True)])

    return rows.withColumn("exact", same(F.col(a), F.col(b)))


def arms(train: DataFrame, test: DataFrame, n: int = N_DRAW, tau: float = DRAW_TAU) -> DataFrame:
    """arm, trained_on, n, accuracy. train and test: query_id, shape, q_text, question, mentions, and score to train on."""
    out = None
    for arm in ("few_shot", "raw", "verified", "weighted"):
        own = None if arm == "few_shot" else draw(train, n, tau if arm == "verified" else None)
        reader = Reader() if own is None else Reader.fit(own, "score" if arm == "weighted" else None)
        row = same_query(reader.read(test)).agg(F.count("*").alias("n"), F.avg(F.col("exact").cast("double")).alias("accuracy"))
        row = row.select(F.lit(arm).alias("arm"), F.lit(0 if own is None else own.count()).alias("trained_on"), "n", "accuracy")
        out = row if out is None else out.unionAll(row)
    return out
