"""Language of whole texts: sparse multinomial logistic regression on TF-IDF of character n-grams.

Features are hashed n-grams of one to three lower-cased characters, with log-damped counts, inverse document frequencies
over all texts that may be learned from, and unit length. Weights come from follow-the-regularised-leader with an L1 and
an L2 penalty on a bounded, documented sample of labelled rows; a temperature fitted on a part of that sample kept out
of the fit turns margins into probabilities.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import ship, text_or_empty

BITS = 15
SALTS = (0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D)


def gram_counts(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Hashed n-grams of a text and how often each stands there."""
    c = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    one = c * np.uint32(SALTS[0])
    two = one[:-1] * np.uint32(31) + c[1:] * np.uint32(SALTS[1])
    three = two[:-1] * np.uint32(31) + c[2:] * np.uint32(SALTS[2])
    grams = np.concatenate([one ^ np.uint32(1), two, three])
    grams = (grams ^ (grams >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
    n = np.bincount((grams >> np.uint32(32 - BITS)).astype(np.int64), minlength=1 << BITS)
    at = np.flatnonzero(n)
    return at, n[at]


def has_letter(text: str) -> bool:
    return any(map(str.isalpha, text)) if len(text) < 64 else any(map(str.isalpha, text[:64])) or any(map(str.isalpha, text))


class FtrlSoftmax:
    """Multinomial logistic regression by follow-the-regularised-leader with an elastic net."""

    def __init__(self, classes: int, features: int, alpha: float = 0.3, beta: float = 1.0, l1: float = 0.02, l2: float = 0.02):
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z, self.n = np.zeros((features, classes)), np.zeros((features, classes))

    def weights(self, at=slice(None)) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        return np.where(np.abs(z) <= self.l1, 0.0, -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2))

    def learn(self, at: np.ndarray, x: np.ndarray, y: int) -> None:
        w = self.weights(at)
        p = softmax(x @ w)
        p[y] -= 1
        g = x[:, None] * p[None, :]
        n = self.n[at]
        self.z[at] += g - (np.sqrt(n + g * g) - np.sqrt(n)) / self.alpha * w
        self.n[at] = n + g * g


def softmax(m: np.ndarray) -> np.ndarray:
    e = np.exp(m - m.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def scaled(at: np.ndarray, n: np.ndarray, idf: np.ndarray) -> np.ndarray:
    x = (1 + np.log(n)) * idf[at]
    return x / max(np.sqrt((x * x).sum()), 1e-12)


class LanguageModel:
    def __init__(self, names: list[str], idf: np.ndarray, weights: np.ndarray, temperature: float):
        self.names, self.idf, self.weights, self.temperature = names, idf, weights, temperature

    def score(self, text: str) -> tuple[str, float]:
        if not self.names or not has_letter(text):
            return "und", 0.0
        at, n = gram_counts(text)
        p = softmax(scaled(at, n, self.idf) @ self.weights[at] / self.temperature)
        k = int(p.argmax())
        return self.names[k], float(p[k])


def document_frequencies(texts: DataFrame) -> tuple[np.ndarray, int]:
    """In how many of all texts each hashed n-gram stands, and the number of texts."""

    def count(batches):
        n = np.zeros((1 << BITS) + 1, np.int64)
        for b in batches:
            for text in b.column(0).to_pylist():
                n[gram_counts(text)[0]] += 1
                n[-1] += 1
        k = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(n[k])], ["k", "n"])

    out = np.zeros((1 << BITS) + 1, np.int64)
    for r in texts.mapInArrow(count, "k long, n long").groupBy("k").agg(F.sum("n").alias("n")).collect():
        out[r["k"]] = r["n"]
    return out[:-1], int(out[-1])


def fit(docs: DataFrame, learn: Column, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", sample: int = 4000, rounds: int = 3, seed: int = 11) -> LanguageModel:
    """A model from the rows of docs for which `learn` holds and the language is there.

    Document frequencies cover all those rows; weights are fitted on about `sample` of them in equal parts by language
    (all rows of a rare one), drawn by a hash of the id. Rows that repeat an id, or have none, count one by one; null texts
    are empty ones. An empty table gives a model that answers `und`. Other columns play no part, whatever their names.
    """
    ship()
    rows = docs.where(learn & F.col(lang_col).isNotNull()).select(F.col(id_col).cast("string").alias("id"), text_or_empty(text_col).alias("text"), F.col(lang_col).cast("string").alias("lang"))
    counts = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    names = sorted(counts)
    found, total = document_frequencies(rows.select("text"))
    idf = np.log((1 + total) / (1 + found)) + 1
    if len(names) < 2:
        return LanguageModel(names, idf, np.zeros((1 << BITS, max(1, len(names)))), 1.0)
    each = max(1, sample // len(names))
    drawn = None
    for name in names:
        share = min(1.0, 1.2 * each / counts[name])
        own = (F.col("lang") == name) & (F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1 << 20)) < int(share * (1 << 20)) + 1)
        drawn = own if drawn is None else drawn | own

    def sparse(batches):
        for b in batches:
            grams = [gram_counts(t) for t in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([g.astype("<u2").tobytes() for g, _ in grams]), pa.array([n.astype("<u4").tobytes() for _, n in grams]), b.column(1), b.column(2)], ["at", "n", "lang", "id"])

    got = rows.where(drawn).select("text", "lang", "id").mapInArrow(sparse, "at binary, n binary, lang string, id string").collect()
    got.sort(key=lambda r: (str(r["id"]), bytes(r["at"])))
    order = np.random.default_rng(seed).permutation(len(got))
    data = []
    for k in order.tolist():
        at = np.frombuffer(bytes(got[k]["at"]), "<u2").astype(np.int64)
        data.append((at, scaled(at, np.frombuffer(bytes(got[k]["n"]), "<u4"), idf), names.index(got[k]["lang"])))
    held = data[: len(data) // 5]
    model = FtrlSoftmax(len(names), 1 << BITS)
    for _ in range(rounds):
        for at, x, y in data[len(held) :]:
            if len(at):
                model.learn(at, x, y)
    weights = model.weights()
    margins = np.array([x @ weights[at] for at, x, _ in held if len(at)]).reshape(-1, len(names))
    truth = np.array([y for at, _, y in held if len(at)], np.int64)
    grid = np.exp(np.linspace(np.log(0.05), np.log(5), 60))
    loss = [-np.log(np.maximum(softmax(margins / t)[np.arange(len(truth)), truth], 1e-9)).sum() for t in grid] if len(truth) else [0.0]
    return LanguageModel(names, idf, weights, float(grid[int(np.argmin(loss))]) if len(truth) else 1.0)


def predict(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, lang_pred, score) for every row's whole text. Null texts and texts without a letter get `und` and score 0.

    Rows that repeat an id give rows of their own. An empty table gives no rows. Other columns play no part.
    """
    ship()
    kind = docs.schema[id_col].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast((model.names, model.idf, model.weights, model.temperature))

    def run(batches):
        own = LanguageModel(*shared.value)
        for b in batches:
            got = [own.score(t or "") for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x for x, _ in got], pa.string()), pa.array([x for _, x in got], pa.float64())], ["id", "lang_pred", "score"])

    return docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, f"id {kind}, lang_pred string, score double").withColumnRenamed("id", id_col)
