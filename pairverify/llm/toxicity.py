"""Toxicity of whole texts: a bidirectional gated recurrent network with attention pooling, trained and run in numpy.

A text is read in overlapping windows of words. A word enters by two inputs: an embedding of its hash and the mean of
embeddings of its character trigrams. Both directions run over a window, attention weighs the states, and a linear head
gives a logit. A document's logit is that of its most toxic window, calibrated to a probability on documents kept out of
the fit. In training, a document's label is carried by the window with the highest logit so far and a random one.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._bytes import Hasher, lower_table, slices, space_table, spread, word_bounds
from ._common import ship, text_or_empty

WORD_BITS, CHAR_BITS = 14, 13
WORD_DIM, CHAR_DIM, HIDDEN, ATTEND = 12, 12, 8, 8
WINDOW, STRIDE = 64, 48


def trigrams(buf: np.ndarray, start: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashed trigrams centred at each byte of some words (a word's edges count as zero), and how many each word has."""
    size = stop - start
    at = spread(start, size)
    head, tail = np.repeat(start, size), np.repeat(stop, size) - 1
    b = buf.astype(np.uint32)
    before = np.where(at > head, b[np.maximum(at - 1, 0)], np.uint32(0))
    after = np.where(at < tail, b[np.minimum(at + 1, len(b) - 1)], np.uint32(0))
    h = (before * np.uint32(0x9E3779B1) ^ b[at] * np.uint32(0x85EBCA77)) * np.uint32(31) + after * np.uint32(0xC2B2AE3D)
    h = (h ^ (h >> np.uint32(13))) * np.uint32(0x2C1B3C6D)
    return (h >> np.uint32(32 - CHAR_BITS)).astype(np.int64), size


class Vocabulary:
    """Words by hash: their embedding row and their trigrams."""

    def __init__(self, hashes: np.ndarray, grams: np.ndarray, size: np.ndarray):
        self.row = (hashes >> np.uint64(64 - WORD_BITS)).astype(np.int64)
        self.grams, self.size = grams, size
        self.first = np.cumsum(size) - size


def starts_of_windows(n: int) -> list[int]:
    """Starts of the windows that cover n words; the last one ends with the text."""
    return [0] if n <= WINDOW else [*range(0, n - WINDOW, STRIDE), n - WINDOW]


def _sigmoid(x):
    return 0.5 * (1 + np.tanh(0.5 * x))


class Network:
    def __init__(self, seed: int = 3):
        g = np.random.default_rng(seed)
        d = WORD_DIM + CHAR_DIM
        r = lambda *s, k=0.1: (g.normal(size=s) * k).astype(np.float32)
        self.p = {
            "word": r(1 << WORD_BITS, WORD_DIM), "char": r(1 << CHAR_BITS, CHAR_DIM, k=0.3), "in": r(2, d, 3 * HIDDEN, k=d**-0.5), "bias": np.zeros((2, 1, 3 * HIDDEN), np.float32),
            "back": r(2, HIDDEN, 3 * HIDDEN, k=HIDDEN**-0.5), "key": r(2 * HIDDEN, ATTEND, k=0.3), "key0": np.zeros(ATTEND, np.float32), "query": r(ATTEND, k=0.3), "out": r(2 * HIDDEN, k=0.3), "out0": np.zeros(1, np.float32),
        }

    def features(self, v: Vocabulary, which: np.ndarray) -> np.ndarray:
        size = v.size[which]
        rows = self.p["char"][v.grams[spread(v.first[which], size)]]
        mean = np.add.reduceat(rows, np.cumsum(size) - size, axis=0) / size[:, None].astype(np.float32) if len(which) else rows[:0]
        return np.concatenate([self.p["word"][v.row[which]], mean], axis=1)

    def gates(self, x: np.ndarray) -> np.ndarray:
        """Input part of all gates for each word, by direction, and a last word of zeros for padding."""
        g = np.matmul(x[None], self.p["in"]) + self.p["bias"]
        return np.concatenate([g, np.zeros((2, 1, g.shape[2]), np.float32)], axis=1)

    def forward(self, gates: np.ndarray, index: np.ndarray, keep: bool = False):
        """Logits of windows of words (index into gates, the last entry for padding)."""
        n, t = index.shape
        pad = index == gates.shape[1] - 1
        any_pad = bool(pad.any())
        h = np.zeros((2, n, HIDDEN), np.float32)
        states = np.empty((t, 2, n, HIDDEN), np.float32)
        tape = []
        k = HIDDEN
        for s in range(t):
            cols = (index[:, s], index[:, t - 1 - s])
            x = np.stack([gates[0][cols[0]], gates[1][cols[1]]])
            u = np.matmul(h, self.p["back"])
            zr = _sigmoid(x[..., : 2 * k] + u[..., : 2 * k])
            z, r = zr[..., :k], zr[..., k:]
            c = np.tanh(x[..., 2 * k :] + r * u[..., 2 * k :])
            new = c + z * (h - c)
            if any_pad:
                off = np.stack([pad[:, s], pad[:, t - 1 - s]])[..., None]
                new = np.where(off, h, new)
            if keep:
                tape.append((h, z, r, c, u[..., 2 * k :]))
            h = new
            states[s, 0] = h[0]
            states[t - 1 - s, 1] = h[1]
        both = np.concatenate([states[:, 0], states[:, 1]], axis=2)
        key = np.tanh(both @ self.p["key"] + self.p["key0"])
        a = key @ self.p["query"]
        if any_pad:
            a = np.where(pad.T, np.float32(-30), a)
        a = np.exp(a - a.max(0))
        a /= a.sum(0)
        pooled = (a[..., None] * both).sum(0)
        logit = pooled @ self.p["out"] + self.p["out0"][0]
        return (logit, (both, key, a, pooled, tape, pad)) if keep else logit

    def gradients(self, v: Vocabulary, index: np.ndarray, truth: np.ndarray, weight: np.ndarray, dropped=None):
        """Gradients of the weighted logistic loss. index: windows of vocabulary entries, -1 for padding.

        dropped: a generator and a share of words that enter by their characters alone this time.
        """
        used, flat = np.unique(index, return_inverse=True)
        flat = flat.reshape(index.shape)
        if used[0] < 0:
            used, flat = used[1:], np.where(flat == 0, len(used) - 1, flat - 1)
        x = self.features(v, used)
        there = np.ones((len(used), 1), np.float32)
        if dropped:
            there[dropped[0].random(len(used)) < dropped[1]] = 0
            x[:, :WORD_DIM] *= there
        gates = self.gates(x)
        logit, (both, key, a, pooled, tape, pad) = self.forward(gates, flat, True)
        n, t = index.shape
        p, k, g = self.p, HIDDEN, {}
        d = ((_sigmoid(logit) - truth) * weight / n).astype(np.float32)
        g["out"], g["out0"] = pooled.T @ d, d.sum(keepdims=True)
        dpool = d[:, None] * p["out"]
        dboth = a[..., None] * dpool[None]
        da = (both * dpool[None]).sum(2)
        da = a * (da - (a * da).sum(0))
        g["query"] = (key * da[..., None]).sum((0, 1))
        dkey = da[..., None] * p["query"] * (1 - key * key)
        g["key0"] = dkey.sum((0, 1))
        g["key"] = both.reshape(-1, 2 * k).T @ dkey.reshape(-1, ATTEND)
        dboth += dkey @ p["key"].T
        dgates = np.zeros_like(gates)
        g["back"] = np.zeros_like(p["back"])
        dh = np.zeros((2, n, k), np.float32)
        for s in range(t - 1, -1, -1):
            dh[0] += dboth[s, :, :k]
            dh[1] += dboth[t - 1 - s, :, k:]
            h, z, r, c, u = tape[s]
            off = np.stack([pad[:, s], pad[:, t - 1 - s]])[..., None]
            live = np.where(off, np.float32(0), dh)
            dz = live * (h - c) * z * (1 - z)
            dc = live * (1 - z) * (1 - c * c)
            dr = dc * u * r * (1 - r)
            du = np.concatenate([dz, dr, dc * r], axis=2)
            dx = np.concatenate([dz, dr, dc], axis=2)
            g["back"] += np.matmul(h.transpose(0, 2, 1), du)
            dh = np.where(off, dh, live * z + np.matmul(du, p["back"].transpose(0, 2, 1)))
            np.add.at(dgates[0], flat[:, s], dx[0])
            np.add.at(dgates[1], flat[:, t - 1 - s], dx[1])
        dgates = dgates[:, :-1]
        g["bias"] = dgates.sum(1, keepdims=True)
        g["in"] = np.matmul(x.T[None], dgates)
        dx = np.matmul(dgates, p["in"].transpose(0, 2, 1)).sum(0)
        g["word"] = np.zeros_like(p["word"])
        np.add.at(g["word"], v.row[used], dx[:, :WORD_DIM] * there)
        size = v.size[used]
        g["char"] = np.zeros_like(p["char"])
        np.add.at(g["char"], v.grams[spread(v.first[used], size)], np.repeat(dx[:, WORD_DIM:] / size[:, None], size, axis=0))
        loss = float((weight * np.logaddexp(0, np.where(truth > 0, -logit, logit))).mean())
        return g, loss


class Adam:
    def __init__(self, p: dict, rate: float = 0.01):
        self.p, self.rate, self.t = p, rate, 0
        self.m, self.v = ({k: np.zeros_like(x) for k, x in p.items()} for _ in range(2))

    def step(self, g: dict) -> None:
        self.t += 1
        for k, x in self.p.items():
            self.m[k] += 0.1 * (g[k] - self.m[k])
            self.v[k] += 0.01 * (g[k] ** 2 - self.v[k])
            x -= self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.99**self.t)) + 1e-8)


class ToxicityModel:
    def __init__(self, parameters: dict, slope: float, shift: float, prior: float):
        self.network = Network()
        self.network.p = parameters
        self.slope, self.shift, self.prior = slope, shift, prior

    def scores(self, column, most: int = 1024) -> np.ndarray:
        """Probability for each text of an Arrow column, from all its windows; texts without words get the base rate."""
        out = np.full(len(column), -np.inf, np.float64)
        hasher, lower, space = Hasher(), lower_table(), space_table()
        for i, j, buf, off in slices(column, 1 << 19):
            buf = lower[buf]
            start, stop, before = word_bounds(buf, off, space)
            if not len(start):
                continue
            keys, first, back = np.unique(hasher.word(buf, start, stop), return_index=True, return_inverse=True)
            vocabulary = Vocabulary(keys, *trigrams(buf, start[first], stop[first]))
            gates = self.network.gates(self.network.features(vocabulary, np.arange(len(keys))))
            at, owner, end = all_windows(before)
            for lo in range(0, len(at), most):
                grid = at[lo : lo + most, None] + np.arange(WINDOW)[None, :]
                inside = grid < end[lo : lo + most, None]
                index = np.where(inside, back[np.minimum(grid, len(back) - 1)], len(keys))
                np.maximum.at(out, i + owner[lo : lo + most], self.network.forward(gates, index))
        none = np.isinf(out)
        return np.where(none, self.prior, _sigmoid(self.slope * np.where(none, 0, out) + self.shift))


def all_windows(before: np.ndarray):
    """First word, text, and word after the text's last, of every window of every text that has words."""
    n = np.diff(before)
    more = np.maximum(n - WINDOW, 0)
    count = np.where(n > 0, 1 + -(-more // STRIDE), 0)
    owner = np.repeat(np.arange(len(n)), count)
    step = spread(np.zeros(len(n), np.int64), count)
    return before[:-1][owner] + np.minimum(step * STRIDE, more[owner]), owner, before[1:][owner]


def fit(docs: DataFrame, labels: DataFrame, learn: Column, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", sample: int = 3000, epochs: int = 14, rate: float = 0.03, steps: int = 32, most_batch: int = 96, drop: float = 0.4, decay: float = 0.002, seed: int = 5) -> ToxicityModel:
    """A model from labelled documents for whose id `learn` holds (an expression over `id_col`).

    At most about `sample` documents, in equal parts by label and drawn by a hash of their id, are learned from, each with
    all its windows. Labels of rows without an id, and other values than 0 and 1, count for nothing; of several labels of
    one id the largest holds; every row of a drawn id is learned from. A label table without both labels, or labelled
    documents without any word, give a model without weights, which scores every text by the labels' base rate; so does an
    empty table. Other columns of either table play no part, whatever their names.
    """
    ship()
    rows = labels.where(learn & F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull()).select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("y"))
    counts = {r["y"]: r["n"] for r in rows.groupBy("y").agg(F.count("*").alias("n")).collect()}
    prior = counts.get(1, 0) / max(1, sum(counts.values()))
    untrained = ToxicityModel(Network(seed).p, 0.0, float(np.log((prior + 1e-3) / (1 - prior + 1e-3))), prior)
    if len(counts) < 2:
        return untrained
    share = {y: min(1.0, sample / 2 / n) for y, n in counts.items()}
    low = lambda y: F.pmod(F.xxhash64(F.col("id"), F.lit(seed)), F.lit(1 << 20)) < int(share[y] * (1 << 20)) + 1
    drawn = rows.where(((F.col("y") == 0) & low(0)) | ((F.col("y") == 1) & low(1))).groupBy("id").agg(F.max("y").alias("y"))
    texts = docs.select(F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).join(F.broadcast(drawn), "id").select("id", "text", "y")  # about `sample` rows

    def read(batches):
        """Of each text the hashes of its words, and its distinct words with their trigrams."""
        hasher, space, lower = Hasher(), space_table(), lower_table()
        for b in batches:
            ids = b.column(0).to_pylist()
            for i, _, buf, off in slices(b.column(1)):
                buf = lower[buf]
                start, stop, before = word_bounds(buf, off, space)
                h = hasher.word(buf, start, stop)
                rows = []
                for r in range(len(off) - 1):
                    own = slice(int(before[r]), int(before[r + 1]))
                    if own.stop > own.start:
                        _, first = np.unique(h[own], return_index=True)
                        g, size = trigrams(buf, start[own][first], stop[own][first])
                        rows.append((str(ids[i + r]), b.column(2)[i + r].as_py(), h[own].tobytes(), g.astype("<u2").tobytes(), size.astype("<u4").tobytes()))
                if rows:
                    cols = [pa.array(c) for c in zip(*rows, strict=True)]
                    yield pa.RecordBatch.from_arrays([cols[0], cols[1].cast(pa.int32()), *cols[2:]], ["id", "y", "words", "grams", "size"])

    got = texts.mapInArrow(read, "id string, y int, words binary, grams binary, size binary").toArrow()
    if not got.num_rows:
        return untrained
    got = got.take(pa.array(sorted(range(got.num_rows), key=lambda k: (got["id"][k].as_py(), got["words"][k].as_py()))))
    part = lambda name, kind: [np.frombuffer(x.as_buffer(), kind) for x in got[name]]
    texts_ = part("words", "<u8")
    own = [np.unique(x) for x in texts_]
    keys, first = np.unique(np.concatenate(own), return_index=True)
    size = np.concatenate(part("size", "<u4")).astype(np.int64)
    at = (np.cumsum(size) - size)[first]
    v = Vocabulary(keys, np.concatenate(part("grams", "<u2"))[spread(at, size[first])].astype(np.int64), size[first])
    begins = [np.array(starts_of_windows(len(x))) for x in texts_]
    count = np.array([len(x) for x in texts_])
    base = np.cumsum(count) - count
    back = np.searchsorted(keys, np.concatenate(texts_)).astype(np.int32)
    begin, n = np.concatenate([x + b for x, b in zip(begins, base, strict=True)]), np.array([len(x) for x in begins])
    end = np.repeat(base + count, n)
    grid = begin[:, None] + np.arange(WINDOW)[None, :]
    index = np.where(grid < end[:, None], back[np.minimum(grid, len(back) - 1)], -1)
    doc = np.repeat(np.arange(len(texts_)), n)
    truth = np.array(got["y"].to_pylist(), np.float32)
    del grid, texts_, own, got
    rng = np.random.default_rng(seed)
    held = rng.random(len(truth)) < 0.2
    network = Network(seed)
    adam = Adam(network.p)

    def logits(windows: np.ndarray) -> np.ndarray:
        gates = network.gates(network.features(v, np.arange(len(keys))))
        return np.concatenate([network.forward(gates, np.where(index[windows[k : k + 4096]] < 0, len(keys), index[windows[k : k + 4096]])) for k in range(0, len(windows), 4096)])

    def best_of(windows: np.ndarray, value: np.ndarray) -> np.ndarray:
        order = np.lexsort((value, doc[windows]))
        last = np.append(doc[windows][order][1:] != doc[windows][order][:-1], True)
        return windows[order][last]

    fit_windows = np.flatnonzero(~held[doc])
    balance = np.where(truth > 0, len(truth) / max(1.0, 2 * truth.sum()), len(truth) / max(1.0, 2 * (1 - truth).sum())).astype(np.float32)
    for epoch in range(epochs):
        top = best_of(fit_windows, logits(fit_windows) if epoch else rng.random(len(fit_windows)))
        any_ = best_of(fit_windows, rng.random(len(fit_windows)))
        chosen = np.unique(np.concatenate([top, any_[truth[doc[any_]] == 0]]))
        chosen = rng.permutation(chosen)
        adam.rate = rate if epoch < epochs * 2 // 3 else rate * 0.3
        batch = min(most_batch, max(16, len(chosen) // steps))
        for k in range(0, len(chosen), batch):
            part = chosen[k : k + batch]
            g, _ = network.gradients(v, index[part], truth[doc[part]], balance[doc[part]], (rng, drop))
            for name in ("word", "char"):
                network.p[name] *= 1 - decay
            adam.step(g)
    # a document's best logit, calibrated by logistic regression on documents kept out, at the labels' own base rate
    check = np.flatnonzero(held[doc]) if held.any() and len(np.unique(truth[held])) == 2 else np.arange(len(doc))
    value = logits(check)
    best = best_of(check, value)
    x = dict(zip(check.tolist(), value.tolist(), strict=True))
    x = np.array([x[k] for k in best.tolist()])
    y = truth[doc[best]]
    mean, spread_ = x.mean(), x.std() + 1e-6
    u = (x - mean) / spread_
    weight = np.where(y > 0, prior / max(y.mean(), 1e-6), (1 - prior) / max(1 - y.mean(), 1e-6))
    a, b = 1.0, 0.0
    for _ in range(500):
        p = _sigmoid(a * u + b)
        e = weight * (p - y)
        a, b = a - 0.3 * ((e * u).mean() + 0.002 * a), b - 0.3 * e.mean()
    return ToxicityModel(network.p, float(a / spread_), float(b - a * mean / spread_), prior)


def score(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, score) for every row's whole text, rows that repeat an id included; null and empty texts get the base rate of the labels.

    An empty table gives no rows. Other columns play no part.
    """
    ship()
    kind = docs.schema[id_col].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast((model.network.p, model.slope, model.shift, model.prior))

    def run(batches):
        own = ToxicityModel(*shared.value)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(own.scores(b.column(1)))], ["id", "score"])

    return docs.select(F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"id {kind}, score double").withColumnRenamed("id", id_col)
