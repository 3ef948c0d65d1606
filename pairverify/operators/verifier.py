"""Verifiers of (query text, question) pairs: scores in [0, 1], thresholds, filters, sweeps.

Bi-encoder: both texts apart through one table of hashed n-gram embeddings, then cosine; trained by a contrastive loss.
Cross-encoder: features of both texts together and a one-layer logistic head, trained by cross-entropy.
"""

from __future__ import annotations

import copy
import math
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pairverify.constants import BI_BUCKETS, CROSS_BUCKETS, MARGIN, TAU, WIDTH
from pairverify.functions.text import cosine, tokens
from pairverify.operators.translate import ship
from pairverify.plans.querytext import bare_numbers
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# -- deciding ----------------------------------------------------------------------------------------------------


def decide(scores: DataFrame, tau: float = TAU, column: str = "score") -> DataFrame:
    """Adds predicted: the score is above tau, a tie counting as wrong; null without a score."""
    return scores.withColumn("predicted", F.col(column) > tau)


def keep(scores: DataFrame, tau: float, inclusive: bool = True, column: str = "score") -> DataFrame:
    """The rows that a filter leaves: those at tau or above, or strictly above."""
    return scores.where(F.col(column) >= tau if inclusive else F.col(column) > tau)


def always_one(pairs: DataFrame) -> DataFrame:
    return pairs.withColumn("score", F.lit(1.0))


def overlap_score(pairs: DataFrame, a: str = "q_text", b: str = "text") -> DataFrame:
    """Jaccard of tokens: what random negatives teach."""
    x, y = F.array_distinct(tokens(F.col(a))), F.array_distinct(tokens(F.col(b)))
    return pairs.withColumn("score", F.size(F.array_intersect(x, y)) / F.greatest(F.size(F.array_union(x, y)), F.lit(1)))


def query_text(rows: DataFrame, with_descriptions: bool = True) -> DataFrame:
    """q_text followed by the descriptions of its terms."""
    return rows.withColumn("q_text", F.concat_ws(" | ", "q_text", F.array_join("described", " | "))) if with_descriptions else rows


def explain(rows: DataFrame, q: str = "q_text", t: str = "text") -> DataFrame:
    """missing: labels of the query that the question lacks; extra: its numbers and capitalised words that the query lacks; operator_mismatch."""
    labels = F.regexp_extract_all(q, F.lit(r"\[([^\]]+)\]"), F.lit(1))
    missing = F.array_sort(F.array_distinct(F.filter(labels, lambda x: ~F.contains(F.lower(F.col(t)), F.lower(x)))))
    names = F.regexp_extract_all(t, F.lit(r"(?<=\s)[A-Z][\w#]{2,}|\d+(?:\.\d+)?"), F.lit(0))
    extra = F.array_sort(F.array_distinct(F.filter(names, lambda x: ~F.contains(F.col(q), x))))
    count = F.col(q).contains("COUNT(") != F.lower(F.col(t)).rlike("how many|number of|^count ")
    return rows.withColumn("missing", missing).withColumn("extra", extra).withColumn("operator_mismatch", count)


# -- cross-encoder -----------------------------------------------------------------------------------------------

TERM = r'(\[[^\]]*\]|\?\w+|_:\w+|"[^"]*"|-?\d+(?:\.\d+)?)'
PATTERN = re.compile(rf"{TERM} (\[[^\]]*\]) {TERM} \.")
OPERATOR = re.compile(r"\b(?:ASK|COUNT|SUM|AVG|MIN|MAX|DISTINCT|FILTER|ORDER|DESC|LIMIT|GROUP)\b|[<>!]?=|[<>](?=\s*-?\d)")
WORD = re.compile(r"'s\b|[\w#]+(?:[-.]\w+)*")


def _said(term: str) -> tuple[str, ...]:
    """The words that a term goes by: a label's or literal's, a variable's capital, a blank node's name."""
    if term[0] in '["':
        return tuple(WORD.findall(term[1:-1].lower()))
    return ("some", term[2:].lower()) if term[0] == "_" else (term[1:].upper(),) if term[0] == "?" else (term,)


def _spots(words: list[str], low: list[str], said: tuple[str, ...]) -> list[tuple[int, int]]:
    """Where a term stands; a variable is a word of capitals."""
    own = words if len(said) == 1 and said[0].isupper() else low
    n = len(said)
    return [(k, k + n) for k in range(len(own) - n + 1) if tuple(own[k : k + n]) == said] if n else []


def _shortest(heads, relations, tails):
    """Of the places of a pattern's three terms, those that stand closest together and don't overlap."""
    best = None
    for r in relations:
        h = min((x for x in heads if x[1] <= r[0] or x[0] >= r[1]), key=lambda x: abs(x[0] - r[0]), default=None)
        o = min((x for x in tails if x != h and (x[1] <= r[0] or x[0] >= r[1])), key=lambda x: abs(x[0] - r[0]), default=None)
        if h and o:
            size = max(h[1], r[1], o[1]) - min(h[0], r[0], o[0])
            if best is None or size < best[0]:
                best = (size, h, r, o)
    return best


def joint_features(q: str, t: str, context: str = "both") -> list[str]:
    """Features of a pair read together; what they mean is learned.

    Words and word pairs of the question; every operator of the query crossed with every word that names nothing; for each
    pattern of the query the shortest stretch of the question that holds its three terms, with H, R and O in their places,
    as runs of two and three and as a whole; and counts of terms that the other side lacks. context "left" keeps, of the
    stretches, only what a reader knows before the last of the three terms.
    """
    words = WORD.findall(t)
    low = [w.lower() for w in words]
    plain = [w for w in low if w.isalpha() or w == "'s"]
    out = [f"t:{w}" for w in plain] + [f"t:{a}_{b}" for a, b in zip(plain, plain[1:], strict=False)]
    out += [f"x:{op}:{w}" for op in {"SELECT", *OPERATOR.findall(q)} for w in set(plain)]
    patterns = PATTERN.findall(q)
    told: dict[tuple, int] = {}
    for h, r, o in patterns:
        places = [_spots(words, low, _said(x)) for x in (h, r, o)]
        told[_said(r)] = told.get(_said(r), 0) + 1
        out += [f"lost:{n}" for n, own in zip("hro", places, strict=True) if not own]
        best = _shortest(*places)
        if not best:
            continue
        size, *spots = best
        lo = min(x[0] for x in spots)
        held = {x[0]: n for x, n in zip(spots, "HRO", strict=True)}
        inside = {k for x in spots for k in range(x[0] + 1, x[1])}
        stretch = [held.get(k, low[k]) for k in range(lo, lo + min(size, 16)) if k not in inside]
        if context == "left":
            stretch = stretch[: max(k for k, w in enumerate(stretch) if w in "HRO")] if len(stretch) > 1 else stretch
        out += [f"s{n}:{'_'.join(stretch[k : k + n])}" for n in (2, 3) for k in range(len(stretch) - n + 1)]
        out.append("S:" + "_".join(stretch))
    for said, n in told.items():
        out.append(f"often:{max(-2, min(2, len(_spots(words, low, said)) - n))}")
    labels = {_said(x) for x in re.findall(r"\[[^\]]*\]", q)} | {_said(x) for x in re.findall(r'"[^"]*"', q)}
    named = {w for x in labels for w in x}
    out.append(f"gone:{min(3, sum(not _spots(words, low, x) for x in labels))}")
    out.append(f"extra:{min(3, sum(w[0].isupper() and len(w) > 2 and w.lower() not in named for w in words[1:]))}")
    numbers = set(re.findall(r"(?<=[<>=] )-?\d+(?:\.\d+)?|(?<=LIMIT )\d+", q))
    out.append(f"numbers:{min(3, len(numbers ^ {w for w in words if re.fullmatch(r'-?[0-9]+(?:[.][0-9]+)?', w)} - named))}")
    out.append(f"and:{max(-3, min(3, low.count('and') + 1 - len(patterns) - q.count('FILTER(')))}")
    return out


def murmur3(data: bytes, seed: int = 42) -> int:
    """The hash by which HashingTF finds a term's place: signed 32-bit MurmurHash3."""
    h, whole = seed, len(data) // 4 * 4
    for at in range(0, len(data), 4):
        k = int.from_bytes(data[at : at + 4], "little") * 0xCC9E2D51 & 0xFFFFFFFF
        h ^= ((k << 15 | k >> 17) & 0xFFFFFFFF) * 0x1B873593 & 0xFFFFFFFF
        if at < whole:
            h = ((h << 13 | h >> 19) & 0xFFFFFFFF) * 5 + 0xE6546B64 & 0xFFFFFFFF
    h ^= len(data)
    h = (h ^ h >> 16) * 0x85EBCA6B & 0xFFFFFFFF
    h = (h ^ h >> 13) * 0xC2B2AE35 & 0xFFFFFFFF
    h ^= h >> 16
    return h - (1 << 32) if h >> 31 else h


class LinearScorer:
    """Scores of pairs by a linear model's weights, in the worker.

    Features don't hold the numbers of names, unless such a name stands where it is not expected; so pairs that differ in
    numbers of names only, and have no feature with one, share a score that is worked out once.
    """

    def __init__(self, weights: np.ndarray, bias: float, context: str = "both", most: int = 1 << 18):
        self.weights, self.bias, self.context, self.most = weights, bias, context, most
        self.place: dict[str, float] = {}
        self.known: dict[tuple[str, str], float | None] = {}

    def _weigh(self, found: list[str]) -> float:
        total = self.bias
        for f in found:
            w = self.place.get(f)
            if w is None:
                if len(self.place) >= self.most:
                    self.place.clear()
                w = self.place[f] = float(self.weights[murmur3(f.encode()) % len(self.weights)])
            total += w
        return 1 / (1 + math.exp(-total)) if total > -700 else 0.0

    def shared(self, a: str, b: str) -> float | None:
        """The score of all pairs whose texts without the numbers of names are a and b; None where it depends on them."""
        if (a, b) not in self.known:
            if len(self.known) >= self.most:
                self.known.clear()
            found = joint_features(a, b, self.context)
            self.known[a, b] = None if any("#" in f for f in found) else self._weigh(found)
        return self.known[a, b]

    def score(self, q: str, t: str) -> float:
        seen: dict[str, str] = {}
        own = self.shared(bare_numbers(q, seen)[0], bare_numbers(t, seen)[0])
        return self._weigh(joint_features(q, t, self.context)) if own is None else own

    def scores(self, q: pa.Array, t: pa.Array, a: pa.Array, b: pa.Array) -> pa.Array:
        """score() of a batch of pairs (q, t) whose texts without numbers, a and b, are given or null; each distinct (a, b) is looked up once."""
        left, right = a.dictionary_encode(), b.dictionary_encode()
        i, j = (x.indices.fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64) for x in (left, right))
        pair, back = np.unique((i + 1) * (len(right.dictionary) + 1) + j + 1, return_inverse=True)
        known = [self.shared(left.dictionary[x - 1].as_py(), right.dictionary[y - 1].as_py()) if x and y else None for x, y in (divmod(int(p), len(right.dictionary) + 1) for p in pair)]
        out = np.array([np.nan if x is None else x for x in known])[back]
        for k in np.flatnonzero(np.array([x is None for x in known], bool)[back]).tolist():
            out[k] = self.score(q[k].as_py(), t[k].as_py()) if q[k].is_valid and t[k].is_valid else np.nan
        return pa.array(out, pa.float64(), mask=np.isnan(out))


def features(pairs: DataFrame, q: str = "q_text", t: str = "text", buckets: int = CROSS_BUCKETS, context: str = "both") -> DataFrame:
    from pyspark.ml.feature import HashingTF

    ship()

    @F.pandas_udf("array<string>")
    def joint(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([joint_features(x or "", y or "", context) for x, y in zip(a, b, strict=True)])

    return HashingTF(numFeatures=buckets, inputCol="_joint", outputCol="features").transform(pairs.withColumn("_joint", joint(F.col(q), F.col(t)))).drop("_joint")


class CrossEncoder:
    def __init__(self, model):
        self.model = model

    @staticmethod
    def fit(pairs: DataFrame, reg: float = 1e-4, rounds: int = 60, head: str = "linear", weight: str | None = None, **options) -> "CrossEncoder":
        """From q_text, text, label (and a weight). head "mlp" puts a hidden layer before the last one."""
        from pyspark.ml.classification import LogisticRegression, MultilayerPerceptronClassifier

        buckets = options.pop("buckets", 512 if head == "mlp" else CROSS_BUCKETS)
        rows = features(pairs, buckets=buckets, **options).withColumn("label", F.col("label").cast("double")).cache()
        if head == "mlp":
            made = MultilayerPerceptronClassifier(layers=[buckets, 8, 2], maxIter=rounds, seed=1).fit(rows)
        else:
            made = LogisticRegression(regParam=reg, maxIter=rounds, **({"weightCol": weight} if weight else {})).fit(rows)
        rows.unpersist()
        out = CrossEncoder(made)
        out.buckets, out.options = buckets, options
        out.losses = list(made.summary().objectiveHistory if head == "mlp" else made.summary.objectiveHistory)
        return out

    def score(self, pairs: DataFrame, out: str = "score") -> DataFrame:
        """Linear heads score in one pass over the texts; others through their features. q_bare and text_bare (last_answers()) spare them reading each text again."""
        from pyspark.ml.functions import vector_to_array

        if hasattr(self.model, "coefficients"):
            ship()
            shared, bias, context = pairs.sparkSession.sparkContext.broadcast(self.model.coefficients.toArray()), self.model.intercept, self.options.get("context", "both")

            if {"q_bare", "text_bare"} <= set(pairs.columns):

                @F.arrow_udf("double")
                def known(batches: Iterator[tuple[pa.Array, pa.Array, pa.Array, pa.Array]]) -> Iterator[pa.Array]:
                    scorer = LinearScorer(shared.value, bias, context)
                    for columns in batches:
                        yield scorer.scores(*columns)

                return pairs.withColumn(out, known("q_text", "text", "q_bare", "text_bare"))

            @F.pandas_udf("double")
            def run(frames: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
                scorer = LinearScorer(shared.value, bias, context)
                for a, b in frames:
                    yield pd.Series([None if x is None or y is None else scorer.score(x, y) for x, y in zip(a, b, strict=True)], dtype="float64")

            return pairs.withColumn(out, run("q_text", "text"))
        rows = self.model.transform(features(pairs, buckets=self.buckets, **self.options))
        s = F.when(F.col("q_text").isNotNull() & F.col("text").isNotNull(), vector_to_array("probability")[1])
        return rows.withColumn(out, s).drop("features", "rawPrediction", "probability", "prediction")


def bce(p: Column, y: Column) -> Column:
    """Binary cross-entropy with the probability kept off 0 and 1."""
    p = F.least(F.greatest(p, F.lit(1e-12)), F.lit(1 - 1e-12))
    return -(y * F.log(p) + (1 - y) * F.log(1 - p))


# -- bi-encoder --------------------------------------------------------------------------------------------------


def contrastive_loss(cos: Column, y: Column, margin: float = MARGIN) -> Column:
    """Half of squared distance for equal pairs, of squared shortfall of the margin for others; distance is 1 - cosine."""
    d = 1 - cos
    return (y * d * d + (1 - y) * F.pow(F.greatest(margin - d, F.lit(0.0)), 2)) / 2


def bare_words(text: str) -> list[str]:
    """A query's or question's words with names, literals and numbers as one word, so that their order can be learned for all of them."""
    text = re.sub(r'"[^"]*"', " NAME ", text)
    text = re.sub(r"\[([^\]]*)\]", lambda m: " NAME " if re.search(r"[A-Z#\d]", m[1]) else f" {m[1]} ", text)
    text = re.sub(r"\?(\w+)|_:(\w+)", lambda m: f" {(m[1] or 'some ' + m[2]).upper()} ", text)
    out: list[str] = []
    for k, w in enumerate(re.findall(r"'s\b|[\w#]+(?:[-.]\w+)*|[{}<>=]", text)):
        name = w != "NAME" and (re.search(r"[#\d]", w) or len(w) > 2 and w[0].isupper() and k > 0 and not w.isupper())
        w = "NAME" if name else w
        if not (w == "NAME" and out[-1:] == ["NAME"]):
            out.append(w)
    return out


def hashed_grams(text: str, buckets: int) -> np.ndarray:
    """Buckets of a text's words, and of runs of one to four of its words without their names."""
    import zlib

    words, bare = re.findall(r"[^\W_]+", text.lower()), bare_words(text)
    grams = words + [f"{n}:{' '.join(bare[k : k + n])}" for n in (1, 2, 3, 4) for k in range(len(bare) - n + 1)]
    return np.array([zlib.crc32(g.encode()) % buckets for g in grams] or [0], np.int64)


def start_table(buckets: int = BI_BUCKETS, width: int = WIDTH, seed: int = 1) -> np.ndarray:
    return (np.random.default_rng(seed).choice([-1.0, 1.0], (buckets, width)) / np.sqrt(width)).astype(np.float32)


class BiEncoder:
    """One table for both sides; an encoding is the mean of its n-grams' rows at unit length."""

    def __init__(self, table: np.ndarray, losses: list[float] | None = None):
        self.table, self.losses = table, losses or []

    def vector(self, text: str) -> np.ndarray:
        u = self.table[hashed_grams(text, len(self.table))].mean(0)
        return u / max(float(np.linalg.norm(u)), 1e-12)

    @staticmethod
    def gradient(table: np.ndarray, rows, margin: float = MARGIN) -> tuple[dict[int, np.ndarray], float]:
        """Sum of gradients by touched bucket and of losses over (q, t, y) rows, some hundred rows at a time."""
        out: dict[int, np.ndarray] = {}
        loss, rows = 0.0, list(rows)
        for lo in range(0, len(rows), 128):
            part = rows[lo : lo + 128]
            y = np.array([r[2] for r in part])
            sides = []
            for k in (0, 1):
                grams = [hashed_grams(r[k], len(table)) for r in part]
                size = np.array([len(g) for g in grams])
                flat = np.concatenate(grams)
                mean = np.add.reduceat(table[flat], np.cumsum(size) - size, axis=0) / size[:, None]
                norm = np.maximum(np.linalg.norm(mean, axis=1), 1e-12)[:, None]
                sides.append((flat, size, mean / norm, norm))
            (_, _, a, na), (_, _, b, nb) = sides
            c = np.einsum("ij,ij->i", a, b)
            d = 1 - c
            short = np.maximum(margin - d, 0.0)
            loss += float(((y * d * d + (1 - y) * short * short) / 2).sum())
            dc = np.where(y > 0, -d, short)[:, None]
            for (flat, size, _, _), side in zip(sides, (dc * (b - c[:, None] * a) / na, dc * (a - c[:, None] * b) / nb), strict=True):
                each = np.repeat(np.arange(len(size)), size)
                order = np.argsort(flat, kind="stable")
                first = np.flatnonzero(np.append(True, flat[order][1:] != flat[order][:-1]))
                sums = np.add.reduceat((side / size[:, None])[each[order]], first, axis=0)
                for k, g in zip(flat[order][first].tolist(), sums, strict=True):
                    out[k] = out[k] + g if k in out else g.astype(table.dtype)
        return out, loss

    @staticmethod
    def pass_over(table: np.ndarray, seen: np.ndarray, rows: list, margin: float, rate: float, batch: int) -> float:
        """One pass of Adagrad over rows in small batches; table and seen change in place. Returns the summed loss."""
        total = 0.0
        for lo in range(0, len(rows), batch):
            part = rows[lo : lo + batch]
            sums, loss = BiEncoder.gradient(table, part, margin)
            total += loss
            if sums:
                k = np.fromiter(sums, np.int64, len(sums))
                g = np.stack(list(sums.values())) / len(part)
                seen[k] += (g * g).sum(1, keepdims=True)
                table[k] -= rate * g / np.sqrt(seen[k])
        return total

    @staticmethod
    def fit(pairs: DataFrame, epochs: int = 6, rate: float = 0.4, margin: float = MARGIN, buckets: int = BI_BUCKETS, width: int = WIDTH, seed: int = 1, tasks: int = 8, batch: int = 64) -> "BiEncoder":
        """Adagrad in `tasks` parts whose tables are averaged after every pass, for the bounded sample that is trained on.

        What comes back of a pass is one table and its step sizes from each part, so the driver holds `tasks` of them.
        """
        ship()
        spark = pairs.sparkSession
        table, seen, losses = start_table(buckets, width, seed), np.full((buckets, 1), 1e-8, np.float32), []
        rows = pairs.select("q_text", "text", F.col("label").cast("int").alias("label"), F.xxhash64("q_text", "text", F.lit(seed)).alias("order"))
        rows = rows.repartition(tasks, "order").sortWithinPartitions("order").drop("order").cache()
        for _ in range(epochs):
            shared = spark.sparkContext.broadcast((table, seen))

            def part(frames, shared=shared):
                own, steps = (x.copy() for x in shared.value)
                rows = [r for f in frames for r in f.itertuples(index=False, name=None)]
                if rows:
                    loss = BiEncoder.pass_over(own, steps, rows, margin, rate, batch)
                    yield pd.DataFrame({"table": [own.astype("<f4").tobytes()], "seen": [steps.astype("<f4").tobytes()], "loss": [loss], "n": [len(rows)]})

            got = rows.mapInPandas(part, "table binary, seen binary, loss double, n long").collect()
            if got:
                weight = np.array([r["n"] for r in got], np.float32) / sum(r["n"] for r in got)
                table = sum(w * np.frombuffer(bytes(r["table"]), "<f4").reshape(table.shape) for w, r in zip(weight, got, strict=True))
                seen = sum(w * np.frombuffer(bytes(r["seen"]), "<f4").reshape(seen.shape) for w, r in zip(weight, got, strict=True))
                losses.append(sum(r["loss"] for r in got) / sum(r["n"] for r in got))
            shared.unpersist()
        rows.unpersist()
        return BiEncoder(table, losses)

    def encode(self, df: DataFrame, column: str, out: str) -> DataFrame:
        """Adds array<float> encodings; each distinct text should be encoded once by the caller."""
        ship()
        shared = df.sparkSession.sparkContext.broadcast(self.table)

        @F.pandas_udf("array<float>")
        def run(x: pd.Series) -> pd.Series:
            own = BiEncoder(shared.value)
            return x.map(own.vector, na_action="ignore")

        return df.withColumn(out, run(F.col(column)))

    def score(self, pairs: DataFrame, out: str = "score", affine: bool = False) -> DataFrame:
        """Distinct texts are encoded once and joined back; the cosine itself is native."""
        q = self.encode(pairs.select("q_text").where("q_text is not null").distinct(), "q_text", "_a")
        t = self.encode(pairs.select("text").where("text is not null").distinct(), "text", "_b")
        return pairs.join(q, "q_text", "left").join(t, "text", "left").withColumn(out, cosine(F.col("_a"), F.col("_b"), affine)).drop("_a", "_b")


class ExternalEncoder:
    """A plug for any encoder of text batches to vectors, made in the worker by `make` (for example a transformer)."""

    def __init__(self, make, batch: int = 64):
        self.make, self.batch = make, batch

    def encode(self, df: DataFrame, column: str, out: str) -> DataFrame:
        ship()
        make, size = self.make, self.batch
        schema = copy.deepcopy(df.schema).add(out, "array<float>")

        def run(frames):
            model = make()
            for f in frames:
                texts = f[column].fillna("").tolist()
                got = [v for k in range(0, len(texts), size) for v in model(texts[k : k + size])]
                yield f.assign(**{out: [list(map(float, v)) for v in got]})

        return df.mapInPandas(run, schema)
