"""SimHash near-duplicates through a hierarchical index in Gray order.

Fingerprints are 64-bit majority votes over the XXH64 values of word shingles. Two of them that differ in at most k bits
agree wholly on one of k + 1 blocks of bits, so a shuffle on (block, its bits) brings every linked pair together. In
each task the distinct fingerprints of one block value are sorted by Gray rank; runs of neighbours are factored into
nodes that hold the bits all members share (mask and pattern), upwards until few are left. A search walks down from the
top for all fingerprints at once, adds the differences that each node's own bits bring, and leaves a whole node as soon
as the sum passes k.

Exact copies share a fingerprint and so one entry; tasks emit one link for each fingerprint that is not the smallest of
its local component, never the pairs of a group. Block values with more than `hot_group` fingerprints are divided by
the same argument over the bits outside the block, again and again, so no task holds an unbounded group; a task searches
the groups that it gets one run of groups after the other.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._bytes import lower_table, slices, space_table, spread, word_bounds, xxh64
from ._common import connected_components, join_counted, materialize, ship, text_or_empty, without

FAN = 16


def text_fingerprints(column, shingle: int = 3, seed: int = 42) -> np.ndarray:
    """Fingerprint of every text of an Arrow string column; a text without words has zero."""
    out = np.zeros(len(column), np.uint64)
    space, lower = space_table(), lower_table()
    for i, j, buf, off in slices(column, 2 << 20):
        buf = lower[buf]
        start, stop, words = word_bounds(buf, off, space)
        if not len(start):
            continue
        size = stop - start
        at = np.cumsum(size + 1) - size - 1
        flat = np.full(int(at[-1] + size[-1]) + 1, 0x20, np.uint8)
        letters = np.ones(len(flat), bool)
        letters[at + size] = False
        flat[letters] = buf[~space[buf]]
        count = np.diff(words)
        grams = np.where(count >= shingle, count - shingle + 1, np.minimum(count, 1))
        first = spread(words[:-1], grams)
        last = np.minimum(first + shingle - 1, np.repeat(words[1:] - 1, grams))
        h = xxh64(flat, at[first], at[last] + size[last] - at[first], seed)
        bits = np.unpackbits(h.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        have = np.flatnonzero(grams)
        votes = np.add.reduceat(bits, (np.cumsum(grams) - grams)[have], axis=0, dtype=np.uint32)
        out[i + have] = np.packbits(2 * votes > grams[have][:, None], axis=1, bitorder="little").view("<u8").ravel()
    return out


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, seed: int = 42) -> DataFrame:
    """(id, fp long): the signed 64-bit fingerprint of each row's whole text."""
    ship()

    def votes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(text_fingerprints(b.column(1), shingle, seed).view(np.int64))], ["id", "fp"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(votes, f"id {kind}, fp long")


def gray_rank(x: np.ndarray) -> np.ndarray:
    """Position of x in the reflected binary order."""
    for s in (1, 2, 4, 8, 16, 32):
        x = x ^ (x >> np.uint64(s))
    return x


class GrayIndex:
    """Levels of nodes above fingerprints that are sorted by group and Gray rank; level 0 holds the fingerprints."""

    def __init__(self, fps: np.ndarray, group: np.ndarray):
        full = ~np.uint64(0)
        self.pattern, self.mask = [fps], [np.full(len(fps), full)]
        self.first, self.root = [np.arange(len(fps) + 1)], None
        owner = group
        while True:
            n = len(owner)
            new = np.ones(n, bool)
            new[1:] = owner[1:] != owner[:-1]
            base = np.maximum.accumulate(np.where(new, np.arange(n), 0))
            cut = np.flatnonzero((np.arange(n) - base) % FAN == 0)
            p, m = self.pattern[-1], self.mask[-1]
            pattern = p[cut]
            parent = np.repeat(np.arange(len(cut)), np.diff(np.append(cut, n)))
            agreed = np.bitwise_and.reduceat(m & ~(p ^ pattern[parent]), cut)
            self.mask[-1] = m & ~agreed[parent]  # only the bits that a node adds to those above it
            self.first.append(np.append(cut, n))
            self.pattern.append(pattern)
            self.mask.append(agreed)
            owner = owner[cut]
            if len(np.unique(owner)) == len(owner):
                break
        self.owner = owner

    def pairs(self, fps: np.ndarray, group: np.ndarray, k: int, chunk: int = 1 << 15):
        """Yields index arrays (i, j), i < j, of fingerprints of one group at most k bits apart."""
        top = len(self.pattern) - 1
        where = np.searchsorted(self.owner, group)
        for lo in range(0, len(fps), chunk):
            q = np.arange(lo, min(lo + chunk, len(fps)))
            node = where[q]
            sum_ = np.bitwise_count((fps[q] ^ self.pattern[top][node]) & self.mask[top][node]).astype(np.int64)
            for level in range(top - 1, -1, -1):
                keep = sum_ <= k
                q, node, sum_ = q[keep], node[keep], sum_[keep]
                first = self.first[level + 1]
                count = first[node + 1] - first[node]
                child = spread(first[node], count)
                q, sum_ = np.repeat(q, count), np.repeat(sum_, count)
                sum_ = sum_ + np.bitwise_count((fps[q] ^ self.pattern[level][child]) & self.mask[level][child])
                node = child
            keep = (sum_ <= k) & (node > q)
            yield q[keep], node[keep]


def settle(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Labels after joining a with b: each entry points at the smallest index known to be reachable."""
    while len(a):
        x, y = label[a], label[b]
        open_ = x != y
        if not open_.any():
            break
        a, b, x, y = a[open_], b[open_], x[open_], y[open_]
        low = np.minimum(x, y)
        np.minimum.at(label, x, low)
        np.minimum.at(label, y, low)
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
    return label


def local_links(table: np.ndarray, key: np.ndarray, fps: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Links within each (table, key) group: for each fingerprint that has a smaller one in its component, that one."""
    if len(fps) < 2:
        return fps[:0], fps[:0]
    order = np.lexsort((gray_rank(fps), key, table))
    table, key, fps = table[order], key[order], fps[order]
    new = np.ones(len(fps), bool)
    new[1:] = (table[1:] != table[:-1]) | (key[1:] != key[:-1])
    group = np.cumsum(new) - 1
    many = np.bincount(group)[group] > 1
    fps, group = fps[many], np.unique(group[many], return_inverse=True)[1]
    if not len(fps):
        return fps, fps
    label = np.arange(len(fps))
    for a, b in GrayIndex(fps, group).pairs(fps, group, k):
        label = settle(label, a, b)
    has = np.flatnonzero(label != np.arange(len(fps)))
    return fps[has], fps[label[has]]


def blocks(k: int, bits: list[int]) -> list[int]:
    """Masks of k + 1 near-equal blocks of the given bit positions."""
    return [sum(1 << b for b in part.tolist()) for part in np.array_split(np.array(bits), k + 1)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def links(fps: DataFrame, k: int = 2, hot_group: int = 1 << 18) -> DataFrame:
    """Links (a, b) between distinct fingerprints of column fp, enough to connect every pair at most k bits apart."""
    ship()
    masks = dict(enumerate(blocks(k, list(range(64)))))
    entry = lambda t: F.struct(F.lit(t).alias("t"), F.col("fp").bitwiseAND(F.lit(_signed(masks[t]))).alias("key"))
    rows, done = fps.select("fp", F.explode(F.array(*map(entry, masks))).alias("e")).select("fp", "e.t", "e.key"), None
    while True:
        hot = materialize(rows.groupBy("t", "key").count().where(F.col("count") > hot_group).select("t", "key"), "hot")
        over = sorted(r["t"] for r in hot.select("t").distinct().collect())  # one for each mask at most
        if not over:
            break
        finer = None
        for t in over:
            own = {len(masks) + s: masks[t] | p for s, p in enumerate(blocks(k, [b for b in range(64) if not masks[t] >> b & 1]))}
            masks |= own
            e = F.array(*map(entry, own))
            finer = F.when(F.col("t") == t, e) if finer is None else finer.when(F.col("t") == t, e)
        hot = F.broadcast(hot)  # at most one row for every hot_group rows
        cool = rows.join(hot, ["t", "key"], "left_anti").select("fp", "t", "key")
        done = cool if done is None else done.unionAll(cool)
        rows = rows.join(hot, ["t", "key"], "left_semi").select("fp", F.explode(finer).alias("e")).select("fp", "e.t", "e.key")
    done = rows if done is None else done.unionAll(rows)

    def search(batches):
        held, size = [], 0

        def found(t, key, fp):
            a, b = local_links(t, key, fp.view(np.uint64), k)
            return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["a", "b"])

        for b in batches:
            held.append([b.column(c).to_numpy(zero_copy_only=False) for c in range(3)])
            size += b.num_rows
            if size >= 2 * hot_group:
                t, key, fp = (np.concatenate(x) for x in zip(*held, strict=True))
                last = int(np.argmax((t == t[-1]) & (key == key[-1])))  # the last group may go on
                if last:
                    yield found(t[:last], key[:last], fp[:last])
                held, size = [[t[last:], key[last:], fp[last:]]], len(t) - last
        if size:
            yield found(*(np.concatenate(x) for x in zip(*held, strict=True)))

    return done.select("t", "key", "fp").repartition("t", "key").sortWithinPartitions("t", "key").mapInArrow(search, "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 2, shingle: int = 3, seed: int = 42, hot_group: int = 1 << 18, similarity: tuple[int, int] | None = None) -> DataFrame:
    """One row per document: id, fp (signed 64-bit) and component_id, the smallest id reachable over links.

    similarity: then documents are linked by the Jaccard similarity of their shingle sets instead, exactly: the index's
    links are checked, and completed by what its bits can't reach (see shingles); the rows have no fp.

    Null and empty texts have no words and so fingerprint zero, linked like any other. Rows that repeat an id stay, one
    row each; a null id counts for no minimum. Other columns of docs play no part. An empty table gives no rows.
    """
    if similarity:
        from .shingles import near_duplicates as by_similarity

        return by_similarity(docs, id_col, text_col, shingle, similarity, seed, k)
    marked = materialize(fingerprints(docs, id_col, text_col, shingle, seed), "fingerprints")
    groups = materialize(marked.groupBy("fp").agg(F.min("id").alias("least"), F.count("*").alias("n")), "groups")
    return components_of(marked, groups, links(groups.select("fp"), k, hot_group), "fp").withColumnRenamed("id", id_col)


def components_of(marked: DataFrame, groups: DataFrame, linked: DataFrame, key: str) -> DataFrame:
    """Each row of marked (id, key) with component_id, the smallest id reachable over links between keys.

    groups: key, least id, and n, how many rows have the key. Frequent keys and large components are joined by broadcast.
    """
    roots = materialize(connected_components(linked).withColumnRenamed("node", key), "roots")
    low = materialize(groups.join(roots, key).groupBy("root").agg(F.min("least").alias("low"), F.count("*").alias("members")), "low")
    named = join_counted(roots, low, "root", "members").select(key, "low")
    final = materialize(groups.join(named, key, "left").select(key, F.coalesce("low", "least").alias("component_id"), "n"), "components")
    return join_counted(marked, final, key, "n").select("id", key, "component_id")


def hex_fingerprint(col="fp"):
    return F.lower(F.lpad(F.hex(col), 16, "0"))


def one_of_each(docs: DataFrame, id_col: str = "doc_id", found: DataFrame | None = None, **options) -> DataFrame:
    """The documents that are the smallest id of their component, with all their columns. Components may be given as `found`.

    Rows of one id stay together: they go only if none of them has the smallest id of its component. Rows without an id
    stay, as nothing names the document that would stand for them.
    """
    found = near_duplicates(docs, id_col, **options) if found is None else found
    stands = found.where(F.col(id_col).isNotNull()).groupBy(id_col).agg(F.max(F.col(id_col) == F.col("component_id")).alias("stands"))
    return without(docs, stands.where(~F.col("stands")).select(id_col), id_col)
