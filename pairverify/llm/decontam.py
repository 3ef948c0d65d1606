"""Benchmark leaks in training texts: rare n-gram seeds, then local alignment of words.

Words are runs of letters and digits, A-Z lower-cased. Every n-gram of a test item is looked up in all documents and its
document frequency counted over all of them; an item's seeds are its n-grams that are rare beside its own median, so an
item that a third of all documents copy keeps its seeds too. Around each seed found, the item is aligned with the
document's words (Smith-Waterman: match 2, mismatch -1, gap -1). The best score, as a share of a whole match, tells
exact, edited and paraphrased copies from chance.

Test items are read in blocks of a bounded number of bytes; a block's n-grams go to every task.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._bytes import Hasher, lower_table, mix, slices, spread, word_bounds
from ._common import ship, text_or_empty, without

MATCH, MISS, GAP = 2, -1, -1


def gap_table() -> np.ndarray:
    """Bytes that are not part of a word: ASCII other than letters and digits."""
    t = np.ones(256, bool)
    t[128:] = False
    for a, b in ((48, 58), (65, 91), (97, 123)):
        t[a:b] = False
    return t


def align(item: np.ndarray, windows: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Best local score of item against each row of windows (padded, with its size), and the position after its end."""
    n, width = windows.shape
    ramp = np.arange(width + 1, dtype=np.int32) * -GAP
    pad = np.arange(width)[None, :] >= sizes[:, None]
    h = np.zeros((n, width + 1), np.int32)
    best, end = np.zeros(n, np.int32), np.zeros(n, np.int64)
    for w in item:
        s = np.where(windows == w, np.int32(MATCH), np.int32(MISS))
        s[pad] = -(1 << 20)
        new = np.maximum(h + GAP, 0)
        np.maximum(new[:, 1:], h[:, :-1] + s, out=new[:, 1:])
        h = np.maximum.accumulate(new + ramp, axis=1) - ramp
        h[:, 1:][pad] = 0
        top = h.argmax(1)
        score = h[np.arange(n), top]
        more = score > best
        best[more], end[more] = score[more], top[more]
    return best, end


class Items:
    """A block of test items: their word hashes and their n-grams by hash."""

    def __init__(self, keys: list, texts: list[str], n: int):
        hasher, lower, gaps = Hasher(), lower_table(), gap_table()
        self.keys, self.words, self.n = keys, [], n
        grams, item, place, size = [], [], [], []
        for k, text in enumerate(texts):
            buf = lower[np.frombuffer((text or "").encode(), np.uint8)]
            start, stop, _ = word_bounds(buf, np.array([0, len(buf)]), gaps)
            w = hasher.word(buf, start, stop)
            self.words.append(w)
            if len(w):
                m = min(n, len(w))
                g = mix(hasher.grams(w, m) ^ np.uint64(m))
                grams.append(g)
                item += [k] * len(g)
                place += range(len(g))
                size += [m] * len(g)
        grams = np.concatenate(grams) if grams else np.zeros(0, np.uint64)
        order = np.argsort(grams, kind="stable")
        self.item, self.place, self.size = (np.array(x, np.int64)[order] for x in (item, place, size))
        self.grams, self.first = np.unique(grams[order], return_index=True)
        self.first = np.append(self.first, len(order))
        self.sizes = np.unique(self.size).tolist()

    def keep_rare(self, found: np.ndarray, factor: float) -> None:
        """Drop n-grams of an item that are in more than factor x (median + 1) documents; found: documents by n-gram."""
        which = np.repeat(np.arange(len(self.grams)), np.diff(self.first))
        keep = np.zeros(len(which), bool)
        for k in range(len(self.keys)):
            own = np.flatnonzero(self.item == k) if len(self.keys) < 64 else self._of(k)
            if len(own):
                n = found[which[own]]
                keep[own] = n <= factor * (np.median(n) + 1)
        self.item, self.place, self.size, which = (x[keep] for x in (self.item, self.place, self.size, which))
        used, self.first = np.unique(which, return_index=True)
        self.grams, self.first = self.grams[used], np.append(self.first, len(which))

    def _of(self, k: int) -> np.ndarray:
        if not hasattr(self, "_order") or len(self._order) != len(self.item):
            self._order = np.argsort(self.item, kind="stable")
            self._edge = np.searchsorted(self.item[self._order], np.arange(len(self.keys) + 1))
        return self._order[self._edge[k] : self._edge[k + 1]]

    def look_up(self, hasher: Hasher, words: np.ndarray, before: np.ndarray):
        """Positions of words at which an n-gram of the block starts, and which it is."""
        at, which = [], []
        if not hasattr(self, "_maybe") or self._made_of is not self.grams:
            self._maybe, self._made_of = np.zeros(1 << 20, bool), self.grams
            self._maybe[(self.grams >> np.uint64(44)).astype(np.int64)] = True
        for m in self.sizes:
            g = hasher.grams(words, m)
            if not len(g) or not len(self.grams):
                continue
            g = mix(g ^ np.uint64(m))
            k = np.flatnonzero(self._maybe[(g >> np.uint64(44)).astype(np.int64)])
            spot = np.searchsorted(self.grams, g[k])
            spot[spot == len(self.grams)] = 0
            same = self.grams[spot] == g[k]
            k, spot = k[same], spot[same]
            inside = np.searchsorted(before, k, "right") == np.searchsorted(before, k + m - 1, "right")  # not across two texts
            at.append(k[inside])
            which.append(spot[inside])
        return (np.concatenate(at), np.concatenate(which)) if at else (np.zeros(0, np.int64), np.zeros(0, np.int64))


def _windows(items: Items, words: np.ndarray, before: np.ndarray, at: np.ndarray, which: np.ndarray):
    """Stretches of words to align: text, item, first word, word after the last; each hit is well inside one of them."""
    count = items.first[which + 1] - items.first[which]
    hit = spread(items.first[which], count)
    at = np.repeat(at, count)
    item = items.item[hit]
    text = np.searchsorted(before, at, "right") - 1
    size = np.array([len(w) for w in items.words])[item]
    first = at - items.place[hit]
    order = np.lexsort((first, item, text))
    text, item, first, size = text[order], item[order], first[order], size[order]
    cell = first // (2 * size)  # hits on near diagonals share a stretch of two and a half items' length at each side
    new = np.append(True, (text[1:] != text[:-1]) | (item[1:] != item[:-1]) | (cell[1:] != cell[:-1])) if len(text) else np.zeros(0, bool)
    text, item, cell, size = text[new], item[new], cell[new], size[new]
    lo = np.maximum(cell * 2 * size - size, before[text])
    hi = np.minimum(cell * 2 * size + 4 * size, before[text + 1])
    return text, item, lo, hi


def matches(docs: DataFrame, benchmark: DataFrame, n: int = 3, min_share: float = 0.6, rare: float = 4.0, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", block_bytes: int = 16 << 20) -> DataFrame:
    """(id, item_id, score, first_word, stop_word) of each document and item whose alignment reaches min_share.

    score: 1 for a whole exact copy. Several places of one document count by the best one. Null and empty texts match
    nothing; rows that repeat an id give rows of their own, items that repeat an id too; an item of fewer than n words is
    looked up whole. Empty tables on either side give no rows. Other columns play no part, whatever their names.

    Items are broadcast in blocks of at most about `block_bytes` of text, by a hash of their texts; documents are read
    twice for each block.
    """
    ship()
    spark = docs.sparkSession
    kind, item_kind = docs.schema[id_col].dataType.simpleString(), benchmark.schema[item_col].dataType.simpleString()
    tests = benchmark.select(F.col(item_col).alias("key"), text_or_empty(item_text).alias("text"))
    total = tests.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(1, -(-total // block_bytes))
    texts = docs.select(F.col(id_col).alias("id"), text_or_empty(text_col).alias("text"))
    out = None
    for block in range(blocks):
        rows = tests.where(F.pmod(F.xxhash64("text"), F.lit(blocks)) == block).collect()
        items = Items([r["key"] for r in rows], [r["text"] for r in rows], n)
        items.keep_rare(_frequencies(texts, items), rare)
        own = _aligned(texts, spark.sparkContext.broadcast(items), min_share, kind, item_kind)
        out = own if out is None else out.unionAll(own)
    return out.withColumnsRenamed({"id": id_col, "item": item_col})


def _frequencies(texts: DataFrame, items: Items) -> np.ndarray:
    """In how many texts each n-gram of the block stands, over all texts."""

    shared = texts.sparkSession.sparkContext.broadcast(items)

    def count(batches):
        items = shared.value
        hasher, lower, gaps, n = Hasher(), lower_table(), gap_table(), np.zeros(len(items.grams), np.int64)
        for b in batches:
            for _, _, buf, off in slices(b.column(0)):
                buf = lower[buf]
                start, stop, before = word_bounds(buf, off, gaps)
                at, which = items.look_up(hasher, hasher.word(buf, start, stop), before)
                text = np.searchsorted(before, at, "right") - 1
                n += np.bincount(np.unique(text * len(n) + which) % max(1, len(n)), minlength=len(n))
        k = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(n[k])], ["k", "n"])

    out = np.zeros(len(items.grams), np.int64)
    for r in texts.select("text").mapInArrow(count, "k long, n long").groupBy("k").agg(F.sum("n").alias("n")).collect():
        out[r["k"]] = r["n"]
    return out


def _aligned(texts: DataFrame, shared, min_share: float, kind: str, item_kind: str) -> DataFrame:
    def run(batches):
        items, hasher, lower, gaps = shared.value, Hasher(), lower_table(), gap_table()
        for b in batches:
            item_type = pa.int64() if item_kind in ("bigint", "int", "smallint", "tinyint") else pa.string()
            for i, _, buf, off in slices(b.column(1)):
                buf = lower[buf]
                start, stop, before = word_bounds(buf, off, gaps)
                words = hasher.word(buf, start, stop)
                text, item, lo, hi = _windows(items, words, before, *items.look_up(hasher, words, before))
                score, end = np.zeros(len(text)), np.zeros(len(text), np.int64)
                for k in np.unique(item).tolist():
                    own = np.flatnonzero(item == k)
                    w = items.words[k]
                    for at in range(0, len(own), max(1, 2_000_000 // (5 * len(w)))):
                        part = own[at : at + max(1, 2_000_000 // (5 * len(w)))]
                        width = int((hi - lo)[part].max())
                        grid = np.minimum(lo[part][:, None] + np.arange(width)[None, :], len(words) - 1)
                        got, stop_at = align(w, words[grid], (hi - lo)[part])
                        score[part], end[part] = got / (MATCH * len(w)), lo[part] + stop_at
                good = np.flatnonzero(score >= min_share)
                order = good[np.lexsort((-score[good], item[good], text[good]))]
                if not len(order):
                    continue
                new = np.append(True, (text[order][1:] != text[order][:-1]) | (item[order][1:] != item[order][:-1]))
                best = order[new]
                last = end[best] - before[text[best]]
                size = np.array([len(items.words[k]) for k in item[best]])
                cols = [b.column(0).take(pa.array(i + text[best])), pa.array([items.keys[k] for k in item[best]], item_type), pa.array(score[best]), pa.array(np.maximum(last - size, 0)), pa.array(last)]
                yield pa.RecordBatch.from_arrays(cols, ["id", "item", "score", "first_word", "stop_word"])

    return texts.mapInArrow(run, f"id {kind}, item {'long' if item_kind in ('bigint', 'int', 'smallint', 'tinyint') else 'string'}, score double, first_word long, stop_word long")


def clean(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """The documents that match no item, with all their columns. A document without an id stays."""
    found = matches(docs, benchmark, id_col=id_col, **options).select(id_col).where(F.col(id_col).isNotNull()).distinct()
    return without(docs, found, id_col)
