"""Repeated passages across documents, by suffix trees that are divided along prefixes of variable length.

Every word position starts a suffix. A first pass counts suffixes by hashed prefixes of one to four words; a prefix class
with more than `group` suffixes is told apart by one more word, and one that stays too large by its whole window. Classes
are put together into groups of at most about `group` suffixes, so each group's subtree fits one task's memory.

A leaf that hangs less than `window` words deep can't be part of a repeat, so such leaves are pruned before words are
shipped: suffixes go to their groups as the 64-bit labels of their paths of `window` words, and a label that no second
document has is a leaf to prune. What is left travels with its words. In each group the words are numbered exactly, the
suffixes are sorted into a suffix array with the lengths of common prefixes between neighbours, and a run of common
prefixes of `window` words is an internal node that deep: a repeat. Its smallest document keeps the passage. Neighbouring
windows grow together into maximal repeats. Labels only propose; a proposal that no node of real words confirms is
returned as an exception, so labels that collide cost time and change nothing.

What a task has seen twice itself is settled there, after a comparison of the words, so a passage that a third of all
documents share comes to its group once for each map batch only.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._bytes import Hasher, mix, slices, space_table, spread, word_bounds
from ._common import materialize, release, ship, text_or_empty

LEVELS = 4


class Suffixes:
    """Of each text of a slice: word bounds, and for each start of a window its label and its prefix hashes."""

    def __init__(self, window: int, label_bits: int = 64):
        self.window, self.hasher, self.space = window, Hasher(), space_table()
        self.mask = np.uint64((1 << label_bits) - 1)

    def read(self, buf: np.ndarray, off: np.ndarray, levels: int = 0):
        start, stop, before = word_bounds(buf, off, self.space)
        count = np.maximum(np.diff(before) - self.window + 1, 0)
        first = spread(before[:-1], count)
        words = self.hasher.word(buf, start, stop)
        sums = self.sums = self.hasher.words.sums(words)
        label = self.hasher.words.runs(sums, first, first + self.window) & self.mask if len(first) else np.zeros(0, np.uint64)
        prefix = [mix(self.hasher.words.runs(sums, first, first + min(n, self.window)) ^ np.uint64(n)) for n in range(1, levels + 1)] if len(first) else [label] * levels
        return start, stop, before, count, first, label, prefix

    def prefixes(self, at: np.ndarray) -> list[np.ndarray]:
        """Prefix hashes of the suffixes at these words of the texts last read; each has as many words as a prefix takes."""
        return [mix(self.hasher.words.runs(self.sums, at, at + min(n, self.window)) ^ np.uint64(n)) for n in range(1, LEVELS + 1)]

    def values(self, before: np.ndarray) -> np.ndarray:
        """For each word of the texts last read the hash of its longest prefix; the last words of a text have none."""
        n = min(LEVELS, self.window)
        at = spread(before[:-1], np.maximum(np.diff(before) - n + 1, 0))
        out = np.full(int(before[-1]), ~np.uint64(0))
        out[at] = self.hasher.words.runs(self.sums, at, at + n)
        return out


class Router:
    """Group of each suffix from the prefix classes' counts."""

    def __init__(self, counts: np.ndarray, group: int):
        self.levels, slots = counts.shape
        self.bits = int(slots).bit_length() - 1
        self.heavy = counts > group
        used, self.group = 0, np.zeros(counts.shape, np.int64)
        for n in range(self.levels):
            light = np.flatnonzero(~self.heavy[n])
            totals = np.cumsum(counts[n][light])
            self.group[n][light] = used + totals // max(group, 1)
            used += int(totals[-1] // max(group, 1)) + 1 if len(light) else 0
        self.whole = used
        self.n_whole = max(1, int(counts[-1][self.heavy[-1]].sum() // max(group, 1)) + 1)

    def route(self, prefix: list[np.ndarray], label: np.ndarray) -> np.ndarray:
        out = (self.whole + (mix(label) % np.uint64(self.n_whole)).astype(np.int64)).astype(np.int64)
        for n in range(self.levels - 1, -1, -1):
            slot = (prefix[n] >> np.uint64(64 - self.bits)).astype(np.int64)
            light = ~self.heavy[n][slot]
            out[light] = self.group[n][slot[light]]
        return out


def prefix_counts(docs: DataFrame, window: int, slot_bits: int) -> np.ndarray:
    """Suffixes by prefix length and hashed prefix, over all texts; the table's size is fixed."""
    slots = 1 << slot_bits

    def count(batches):
        suffixes, n = Suffixes(window), np.zeros((LEVELS, slots), np.int64)
        for b in batches:
            for _, _, buf, off in slices(b.column(0)):
                for k, p in enumerate(suffixes.read(buf, off, LEVELS)[-1]):
                    n[k] += np.bincount((p >> np.uint64(64 - slot_bits)).astype(np.int64), minlength=slots)
        k, s = np.nonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(k * slots + s), pa.array(n[k, s])], ["at", "n"])

    out = np.zeros(LEVELS * slots, np.int64)
    for r in docs.select(text_or_empty("text").alias("text")).mapInArrow(count, "at long, n long").groupBy("at").agg(F.sum("n").alias("n")).collect():
        out[r["at"]] = r["n"]
    return out.reshape(LEVELS, slots)


def slot_bits_for(texts: DataFrame, group: int) -> int:
    """Bits of the prefix table: some eight classes for each group that the texts can fill, between 2^12 and 2^22."""
    size = texts.agg(F.sum(F.octet_length("text").cast("long"))).first()[0] or 0
    return min(22, max(12, (8 * size // (6 * max(group, 1))).bit_length()))


def _pack(ids: np.ndarray, labels: np.ndarray) -> bytes:
    """Labels with their documents' ids in one value, ordered by id."""
    order = np.argsort(ids, kind="stable")
    own, runs = np.unique(ids, return_counts=True)
    return np.array([len(own)], "<i8").tobytes() + np.diff(own, prepend=0).astype("<i8").tobytes() + runs.astype("<u4").tobytes() + labels[order].astype("<u8").tobytes()


def _unpack(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    n = int(np.frombuffer(raw, "<i8", 1)[0])
    own = np.cumsum(np.frombuffer(raw, "<i8", n, 8))
    return np.repeat(own, np.frombuffer(raw, "<u4", n, 8 + 8 * n)), np.frombuffer(raw, "<u8", -1, 8 + 12 * n)


MORE, LEAST = 0, 1


def repeated_labels(docs: DataFrame, window: int = 13, group: int = 1 << 20, slot_bits: int | None = None, batch: int = 1_500_000, label_bits: int = 64) -> tuple[DataFrame, Router, DataFrame]:
    """(id, more, least) for each document with any, how suffixes are routed, and the scratch table that the rows come from.

    more: labels of the document's windows that a document with a smaller id has too; least: those that only larger ids
    have too. Both are proposals by labels. Subtrees' findings travel in one value for each task and bucket of documents,
    whatever number of groups a document's suffixes went to; a bucket holds the windows of about `group` suffixes, and
    gives one row for each of its documents.

    docs: columns id (long) and text. Rows without an id take no part.
    """
    ship()
    docs = docs.where("id is not null").select("id", text_or_empty("text").alias("text"))
    bits = slot_bits or slot_bits_for(docs, group)
    counts = prefix_counts(docs, window, bits)
    router, buckets = Router(counts, group), int(counts[0].sum()) // max(group, 1) + 1
    names = ["group", "at", "kind", "blob"]

    def row(group, at, kind, blob):
        return pa.RecordBatch.from_arrays([pa.array([group], pa.int64()), pa.array([at], pa.int64()), pa.array([kind], pa.int32()), pa.array([blob], pa.binary())], names)

    def suffixes(batches):
        reader = Suffixes(window, label_bits)
        held, size = [], 0

        def settle():
            ids, label, where = (np.concatenate(x) for x in zip(*held, strict=True))
            held.clear()
            order = np.lexsort((ids, label))
            ids, label, where = ids[order], label[order], where[order]
            new = np.append(True, label[1:] != label[:-1])
            head = np.maximum.accumulate(np.where(new, np.arange(len(ids)), 0))
            more = ids > ids[head]
            if more.any():  # the batch has both sides of these
                first = np.unique(head[more])
                yield row(-1, int(ids[-1]), MORE, _pack(ids[more], label[more]))
                yield row(-1, int(ids[-1]), LEAST, _pack(ids[first], label[first]))
            order = np.lexsort((ids[new], where[new]))
            ids, label, where = ids[new][order], label[new][order], where[new][order]
            groups, cut = np.unique(where, return_index=True)
            ends = np.append(cut[1:], len(where))
            rows = [_pack(ids[a:b], label[a:b]) for a, b in zip(cut.tolist(), ends.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(groups), pa.array(groups), pa.array(np.zeros(len(groups), np.int32)), pa.array(rows, pa.binary())], names)

        for b in batches:
            keys = b.column(0).to_numpy(zero_copy_only=False)
            for i, j, buf, off in slices(b.column(1)):
                *_, count, _, label, prefix = reader.read(buf, off, LEVELS)
                if len(label):
                    held.append((np.repeat(keys[i:j], count), label, router.route(prefix, label)))
                    size += len(label)
                if size >= batch:
                    yield from settle()
                    size = 0
        if held:
            yield from settle()

    def shared(blobs: list[bytes]):
        """Ids and labels of the paths that more than one document of a group has: of all but the smallest, and of the smallest."""
        ids, labels = (np.concatenate(x) for x in zip(*map(_unpack, blobs), strict=True))
        order = np.argsort(labels)
        labels, ids = labels[order], ids[order]
        twin = np.zeros(len(labels), bool)
        twin[1:] = labels[1:] == labels[:-1]
        twin[:-1] |= twin[1:]
        labels, ids = labels[twin], ids[twin]
        if not len(labels):
            return (ids, labels), (ids, labels)
        new = np.append(True, labels[1:] != labels[:-1])
        start, of = np.flatnonzero(new), np.cumsum(new) - 1
        low, high = np.minimum.reduceat(ids, start)[of], np.maximum.reduceat(ids, start)[of]
        more, least = ids > low, (ids == low) & (high > low)
        return (ids[more], labels[more]), (ids[least], labels[least])

    def prune(batches):
        held, now, out, size = [], None, ([], []), 0

        def flush():
            for kind, own in enumerate(out):
                if own:
                    ids, labels = (np.concatenate(x) for x in zip(*own, strict=True))
                    own.clear()
                    bucket = (mix(ids.astype(np.uint64)) % np.uint64(buckets)).astype(np.int64)
                    order = np.argsort(bucket, kind="stable")
                    own_buckets, cut = np.unique(bucket[order], return_index=True)
                    parts = np.split(order, cut[1:]) if len(order) else []
                    yield pa.RecordBatch.from_arrays([pa.array(own_buckets), pa.array(np.full(len(parts), kind, np.int32)), pa.array([_pack(ids[p], labels[p]) for p in parts], pa.binary())], ["bucket", "kind", "blob"])

        def take(found) -> int:
            for own, got in zip(out, found, strict=True):
                own.append(got)
            return sum(len(x[0]) for x in found)

        for b in batches:
            for g, kind, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), strict=True):
                if g < 0:
                    out[kind].append(_unpack(blob.as_py()))
                    size += len(out[kind][-1][0])
                    continue
                if g != now and held:
                    size += take(shared(held))
                    held = []
                now = g
                held.append(blob.as_py())
                if size >= batch:
                    yield from flush()
                    size = 0
        if held:
            take(shared(held))
        yield from flush()

    def documents(batches):
        held, now = ([], []), None
        for b in batches:
            for g, kind, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), strict=True):
                if g != now and now is not None:
                    yield from rows(held)
                    held = ([], [])
                now = g
                held[kind].append(blob.as_py())
        if now is not None:
            yield from rows(held)

    def rows(held):
        """One row for each document of a bucket, its labels cut out of the bucket's labels in order of ids."""
        sides = []
        for blobs in held:
            ids, labels = (np.concatenate(x) for x in zip(*map(_unpack, blobs), strict=True)) if blobs else (np.zeros(0, np.int64), np.zeros(0, np.uint64))
            order = np.argsort(ids, kind="stable")
            sides.append((ids[order], np.ascontiguousarray(labels[order])))
        keys = np.unique(np.concatenate([ids for ids, _ in sides]))
        cols = []
        for ids, labels in sides:
            raw, lo, hi = labels.tobytes(), np.searchsorted(ids, keys) * 8, np.searchsorted(ids, keys, "right") * 8
            cols.append([raw[x:y] for x, y in zip(lo.tolist(), hi.tolist(), strict=True)])
        for k in range(0, len(keys), 5000):
            yield pa.RecordBatch.from_arrays([pa.array(keys[k : k + 5000], pa.int64()), *(pa.array(c[k : k + 5000], pa.binary()) for c in cols)], ["id", "more", "least"])

    sent = docs.mapInArrow(suffixes, "group long, at long, kind int, blob binary")
    found = sent.repartition("group", "at").sortWithinPartitions("group").select("group", "kind", "blob").mapInArrow(prune, "bucket long, kind int, blob binary")
    found = materialize(found, "found")
    marks = found.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(documents, "id long, more binary, least binary")
    return marks, router, found


def word_array(letters: np.ndarray, size: np.ndarray) -> pa.Array:
    """Words of given sizes that stand one after the other, as an Arrow array."""
    off = np.concatenate([[0], np.cumsum(size)]).astype(np.int64)
    return pa.Array.from_buffers(pa.large_binary(), len(size), [None, pa.py_buffer(off), pa.py_buffer(np.ascontiguousarray(letters))])


def twins(label: np.ndarray, ids: np.ndarray, first: np.ndarray, number: np.ndarray, window: int) -> np.ndarray:
    """Of each window, the window of the smallest id that has its label and its words; itself where there is none.

    first: each window's first word, ascending; number: of all words, one for each distinct word. A window that follows
    its neighbour, as its twin does, only compares its last word.
    """
    order = np.lexsort((ids, label))
    new = np.append(True, label[order][1:] != label[order][:-1])
    twin = np.empty(len(label), np.int64)
    twin[order] = order[np.maximum.accumulate(np.where(new, np.arange(len(order)), 0))]
    f, t, step = first, first[twin], np.arange(window)
    follows = np.zeros(len(label), bool)
    follows[1:] = (f[1:] == f[:-1] + 1) & (t[1:] == t[:-1] + 1)
    same = number[f + window - 1] == number[t + window - 1]
    whole = lambda k: (number[f[k][:, None] + step] == number[t[k][:, None] + step]).all(1)
    k = np.flatnonzero(~follows & same)
    same[k] = whole(k)
    # a window behind one that failed in its run has more than its last word to compare
    failed = np.cumsum(~same)
    head = np.maximum.accumulate(np.where(~follows, np.arange(len(label)), 0))
    k = np.flatnonzero(follows & same & (failed - failed[head] + ~same[head] > 0))
    same[k] = whole(k)
    return np.where(same, twin, np.arange(len(label)))


def suffix_array(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of the rows of numbered words, and how many words each row in that order shares with the row before it."""
    wide = np.zeros((len(words), words.shape[1] + words.shape[1] % 2), np.uint32)
    wide[:, : words.shape[1]] = words
    order = np.lexsort((wide[:, ::2].astype(np.uint64) << np.uint64(32) | wide[:, 1::2]).T[::-1])
    sorted_ = words[order]
    common = np.zeros(len(words), np.int64)
    if len(words) > 1:
        common[1:] = np.logical_and.accumulate(sorted_[1:] == sorted_[:-1], axis=1).sum(1)
    return order, common


def anchors(value: np.ndarray, first: np.ndarray, window: int) -> np.ndarray:
    """Of each window, the place of its inner suffix with the least value, the leftmost of several; value: of all words."""
    best, at = value[first], first.copy()
    for step in range(1, max(window - LEVELS, 0) + 1):
        v = value[first + step]
        less = v < best
        best[less], at[less] = v[less], first[less] + step
    return at


def pack_stretches(rid: np.ndarray, ids: np.ndarray, at: np.ndarray, more: np.ndarray, first: np.ndarray, window: int, letters: np.ndarray, word_at: np.ndarray, sizes: np.ndarray) -> bytes:
    """Windows, ordered by row and place, as stretches: neighbours share the words that they have in common."""
    new = np.append(True, (rid[1:] != rid[:-1]) | (at[1:] != at[:-1] + 1))
    head = np.flatnonzero(new)
    runs = np.diff(np.append(head, len(rid)))
    words = spread(first[head], runs + window - 1)
    lo = word_at[first[head]]
    last = first[head] + runs + window - 2
    text = letters[spread(lo, word_at[last] + sizes[last] - lo)]
    size = sizes[words]
    wide = size.max(initial=0) > 255
    parts = [np.array([len(rid), len(head), len(words), wide], "<i8"), rid[head].astype("<i8"), ids[head].astype("<i8"), at[head].astype("<i4"), runs.astype("<i4"), more.astype(np.uint8), size.astype("<u4" if wide else "<u1"), text]
    return b"".join(x.tobytes() for x in parts)


def unpack_stretches(raw: bytes, window: int):
    """Row, id, place and proposal of each window, its first word, and the sizes and letters of all words."""
    n, m, w, wide = np.frombuffer(raw, "<i8", 4).tolist()
    at, out = 32, []
    for kind, size in (("<i8", m), ("<i8", m), ("<i4", m), ("<i4", m), (np.uint8, n), ("<u4" if wide else "<u1", w)):
        out.append(np.frombuffer(raw, kind, size, at))
        at += out[-1].nbytes
    rid, ids, place, runs, more, size = out
    runs = runs.astype(np.int64)
    words = runs + window - 1
    return np.repeat(rid, runs), np.repeat(ids, runs), spread(place.astype(np.int64), runs), more, spread(np.cumsum(words) - words, runs), size.astype(np.int64), np.frombuffer(raw, np.uint8, -1, at)


def exceptions(marked: DataFrame, router: Router, window: int, label_bits: int, batch: int = 400_000) -> DataFrame:
    """(rid, at): windows proposed for removal whose words start in no document with a smaller id.

    A window goes to the group of the least of its inner suffixes by prefix hash. Equal windows choose alike, and so do
    most neighbours, whose words then travel once.

    marked: rid, id, text, more, least, the last two as packed bits of the text's windows.
    """

    def words(batches):
        reader = Suffixes(window, label_bits)
        held, size = [], 0

        def settle():
            letters, sizes = (np.concatenate([x[k] for x in held]) for k in (0, 1))
            count = np.cumsum([0] + [len(x[1]) for x in held])
            first = np.concatenate([x[2] + c for x, c in zip(held, count, strict=False)])
            label, ids, rid, at, more, where = (np.concatenate([x[k] for x in held]) for k in range(3, 9))
            held.clear()
            number = word_array(letters, sizes).dictionary_encode().indices.to_numpy()
            word_at = np.cumsum(sizes) - sizes
            twin = twins(label, ids, first, number, window)
            goes = np.flatnonzero((twin == np.arange(len(twin))) | ((ids == ids[twin]) & more))
            goes = goes[np.lexsort((at[goes], rid[goes], where[goes]))]
            groups, cut = np.unique(where[goes], return_index=True)
            rows = [pack_stretches(rid[k], ids[k], at[k], more[k], first[k], window, letters, word_at, sizes) for k in np.split(goes, cut[1:])]
            yield pa.RecordBatch.from_arrays([pa.array(groups), pa.array(rows, pa.binary())], ["group", "blob"])

        for b in batches:
            rids, keys = (b.column(k).to_numpy(zero_copy_only=False) for k in (0, 1))
            for i, j, buf, off in slices(b.column(2)):
                start, stop, before, count, first, label, _ = reader.read(buf, off)
                more, least = (np.concatenate([bits_of(b.column(c)[r], n) for r, n in zip(range(i, j), count.tolist(), strict=True)]) for c in (3, 4))
                k = np.flatnonzero(more | least)
                if len(k):
                    row = np.repeat(np.arange(i, j), count)[k]
                    at = anchors(reader.values(before), first[k], window)
                    held.append((buf[~reader.space[buf]], stop - start, first[k], label[k], keys[row], rids[row], first[k] - before[row - i], more[k], router.route(reader.prefixes(at), label[k])))
                    size += len(k)
                if size >= batch:
                    yield from settle()
                    size = 0
        if held:
            yield from settle()

    def subtree(blobs: list[bytes]):
        """The group's suffix array over real words; of each node `window` words deep, what was proposed of its smallest document."""
        parts = [unpack_stretches(raw, window) for raw in blobs]
        rid, ids, at, more = (np.concatenate([p[k] for p in parts]) for k in range(4))
        number = word_array(*(np.concatenate([p[k] for p in parts]) for k in (6, 5))).dictionary_encode().indices.to_numpy()
        base = np.cumsum([0] + [len(p[5]) for p in parts])
        first = np.concatenate([p[4] + c for p, c in zip(parts, base, strict=False)])
        order, common = suffix_array(number[first[:, None] + np.arange(window)])
        node = np.cumsum(common < window) - 1
        low = np.minimum.reduceat(ids[order], np.flatnonzero(common < window))[node]
        wrong = order[(more[order] > 0) & (ids[order] == low)]
        return pa.RecordBatch.from_arrays([pa.array(rid[wrong], pa.int64()), pa.array(at[wrong].astype(np.int32))], ["rid", "at"])

    def trees(batches):
        held, now = [], None
        for b in batches:
            for g, blob in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                if g != now and held:
                    yield subtree(held)
                    held = []
                now = g
                held.append(blob.as_py())
        if held:
            yield subtree(held)

    sent = marked.select("rid", "id", "text", "more", "least").mapInArrow(words, "group long, blob binary")
    return sent.repartition("group").sortWithinPartitions("group").mapInArrow(trees, "rid long, at int")


def bits_of(value, n: int) -> np.ndarray:
    """The first n of packed bits; a null stands for none set."""
    if not value.is_valid or not n:
        return np.zeros(n, bool)
    return np.unpackbits(np.frombuffer(value.as_buffer(), np.uint8), count=n).astype(bool)


def marked_windows(base: DataFrame, marks: DataFrame, window: int, label_bits: int) -> DataFrame:
    """base (id, own_id, text) with rid, which numbers the rows, and its windows' proposals as packed bits in more and least."""
    kind = base.schema["own_id"].dataType.simpleString()

    def mark(batches):
        reader = Suffixes(window, label_bits)
        for b in batches:
            sides = (b.column(3), b.column(4))
            for i, j, buf, off in slices(b.column(2)):
                bits = [[None] * (j - i), [None] * (j - i)]
                if any(s[r].is_valid for s in sides for r in range(i, j)):
                    _, _, _, count, _, label, _ = reader.read(buf, off)
                    row = np.repeat(np.arange(j - i), count)
                    salt = mix(np.arange(1, j - i + 1, dtype=np.uint64))
                    for s, out in zip(sides, bits, strict=True):
                        own = [mix(np.frombuffer(s[i + r].as_buffer(), "<u8") ^ salt[r]) for r in range(j - i) if s[i + r].is_valid]
                        hit = np.isin(mix(label ^ salt[row]), np.concatenate(own)) if own else np.zeros(len(label), bool)
                        ends = np.cumsum(count)
                        for r in np.unique(row[hit]).tolist():
                            out[r] = np.packbits(hit[ends[r] - count[r] : ends[r]]).tobytes()
                cols = [b.column(k).slice(i, j - i) for k in range(3)]
                yield pa.RecordBatch.from_arrays([*cols, pa.array(bits[MORE], pa.binary()), pa.array(bits[LEAST], pa.binary())], ["id", "own_id", "text", "more", "least"])

    joined = base.join(marks.hint("shuffle_hash"), "id", "left").select("id", "own_id", "text", "more", "least")
    rows = joined.mapInArrow(mark, f"id long, own_id {kind}, text string, more binary, least binary")
    return materialize(rows.withColumn("rid", F.monotonically_increasing_id()), "marked", "zstd")


def remove_repeats(docs: DataFrame, window: int = 13, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False, with_spans: bool = False, label_bits: int = 64, **options) -> DataFrame:
    """One row per document: id, n_words, n_removed, kept_sha256, and on request the kept words and the removed spans.

    A word goes if a window of `window` words that covers it also starts in a document with a smaller id. spans: array of
    (first word, word after the last) of each maximal removed stretch. Null and empty texts have no words. Rows that
    repeat an id do not count against each other; rows without an id keep all their words. Empty tables give no rows.
    Other columns of docs play no part, whatever their names. Ids have to be whole numbers. label_bits: fewer bits let
    labels collide, which changes no result.
    """
    ship()
    kind = docs.schema[id_col].dataType.simpleString()
    base = docs.select(F.col(id_col).cast("long").alias("id"), F.col(id_col).alias("own_id"), text_or_empty(text_col).alias("text"))
    marks, router, found = repeated_labels(base.select("id", "text"), window, label_bits=label_bits, **options)
    marked = marked_windows(base, marks, window, label_bits)
    release(found)
    odd = materialize(exceptions(marked.where("more is not null or least is not null"), router, window, label_bits), "exceptions")
    if odd.limit(1).count():
        rows = marked.join(odd.groupBy("rid").agg(F.collect_list("at").alias("odd")), "rid", "left")
    else:
        rows = marked.withColumn("odd", F.lit(None).cast("array<int>"))
    schema = f"id {kind}, n_words long, n_removed long, kept_sha256 string" + ", kept string" * with_text + ", spans array<struct<first:long,stop:long>>" * with_spans

    def cut(batches):
        space = space_table()
        for b in batches:
            for i, j, buf, off in slices(b.column(1)):
                start, stop, before = word_bounds(buf, off, space)
                n = j - i
                keep = np.ones(len(start), bool)
                edge = np.zeros(len(start) + 1, np.int64)
                for r in range(n):
                    if b.column(2)[i + r].is_valid:
                        hit = bits_of(b.column(2)[i + r], int(before[r + 1] - before[r]) - window + 1)
                        if b.column(3)[i + r].is_valid:
                            hit[b.column(3)[i + r].as_py()] = False
                        at = before[r] + np.flatnonzero(hit)
                        edge[at] += 1
                        edge[at + window] -= 1
                keep = np.cumsum(edge[:-1]) == 0
                words = np.diff(before)
                kept = np.add.reduceat(np.append(keep, False).astype(np.int64), before[:-1]) * (words > 0)
                size = (stop - start)[keep]
                room = size + 1
                flat = np.full(int(room.sum()) + 1, 0x20, np.uint8)
                at = np.cumsum(room) - room
                letters = np.ones(len(flat), bool)
                letters[at + size] = False
                letters[-1] = False
                flat[letters] = buf[~space[buf]][np.repeat(keep, stop - start)]
                ends = np.cumsum(kept)
                edges = np.append(at, len(flat) - 1)
                lo, hi = edges[ends - kept], np.where(kept > 0, edges[ends] - 1, edges[ends])
                raw = memoryview(flat)
                pieces = [raw[x : max(x, y)] for x, y in zip(lo.tolist(), hi.tolist(), strict=True)]
                cols = [b.column(0).slice(i, n), pa.array(words), pa.array(words - kept), pa.array([hashlib.sha256(x).hexdigest() for x in pieces])]
                if with_text:
                    cols.append(pa.array([bytes(x).decode() for x in pieces]))
                if with_spans:
                    gone = np.flatnonzero(~keep)
                    owner = np.searchsorted(before, gone, "right") - 1
                    new = np.append(True, (np.diff(gone) > 1) | (np.diff(owner) > 0)) if len(gone) else np.zeros(0, bool)
                    head = np.flatnonzero(new)
                    tail = np.append(head[1:], len(gone)) - 1 if len(head) else head
                    spans: list[list[dict]] = [[] for _ in range(n)]
                    for h, t in zip(head.tolist(), tail.tolist(), strict=True):
                        r = owner[h]
                        spans[r].append({"first": int(gone[h] - before[r]), "stop": int(gone[t] - before[r] + 1)})
                    cols.append(pa.array(spans, pa.list_(pa.struct([("first", pa.int64()), ("stop", pa.int64())]))))
                yield pa.RecordBatch.from_arrays(cols, ["id", "n_words", "n_removed", "kept_sha256"] + ["kept"] * with_text + ["spans"] * with_spans)

    return rows.select("own_id", "text", "more", "odd").mapInArrow(cut, schema).withColumnRenamed("id", id_col)
