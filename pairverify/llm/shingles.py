"""Near-duplicates by exact Jaccard similarity of word shingles, with SimHash links first.

Shingles are XXH64 values of runs of words, taken as in simhash. Texts with one set of shingles share a key and so one
entry, whose fingerprint is the SimHash of the set. The Gray-order index links fingerprints within k bits. Sets at a
similarity of 4/5 may differ in more bits than any such index can search, so the rest is found by the sets themselves:
shingles are put in one order for all texts, rare ones first by counts in hashed slots, and two sets that are alike enough
must share one of their first members, at 4/5 one of the first fifth of each. A parity sketch of each set, about a bit
for each member, bounds how far two sets differ from below and drops most candidates that aren't alike before any set is
read. Whole sets decide on all others, those of the index too; equality of shingles and of keys rests on 64 bits.

Only components are wanted, so a group of many near-copies isn't compared pair by pair: each set first meets one other
set for each of its first members, and the index's links; after the components of what is alike among these, sets are
compared across components only. Every component is complete, whatever the counts and the index say. Work still grows
with the square of the number of sets that share a rare member without being alike, and one task takes one member.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._bytes import lower_table, mix, slices, space_table, spread, word_bounds, xxh64
from ._common import connected_components, join_counted, materialize, release, ship, text_or_empty
from .simhash import components_of
from .simhash import links as close_prints

SLOTS, PART, WIDEST = 1 << 20, 1 << 14, 1 << 15
#: 64-bit words of the least sketch, to which all others fold.
BRIEF = 4


def shingle_sets(column, shingle: int = 5, seed: int = 42):
    """Yields (first row, cuts, hashes): hashes[cuts[r]:cuts[r + 1]] is the sorted set of row first + r of an Arrow string column."""
    space, lower = space_table(), lower_table()
    for i, j, buf, off in slices(column, 1 << 19):
        buf = lower[buf]
        start, stop, words = word_bounds(buf, off, space)
        if not len(start):
            yield i, np.zeros(j - i + 1, np.int64), np.zeros(0, np.uint64)
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
        row = np.repeat(np.arange(len(grams)), grams)
        order = np.lexsort((h, row))
        h, row = h[order], row[order]
        new = np.append(True, (h[1:] != h[:-1]) | (row[1:] != row[:-1]))
        h, row = h[new], row[new]
        yield i, np.searchsorted(row, np.arange(len(grams) + 1)), h


def set_keys(cuts: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    """One 64-bit key for each set, from the sum of its members' mixed values; the empty set has one as well."""
    sums = np.append(np.uint64(0), np.cumsum(mix(hashes), dtype=np.uint64))
    return mix(sums[cuts[1:]] - sums[cuts[:-1]])


def set_prints(cuts: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    """The SimHash of each set; zero for an empty one."""
    out, size = np.zeros(len(cuts) - 1, np.uint64), np.diff(cuts)
    have = np.flatnonzero(size)
    if len(have):
        bits = np.unpackbits(hashes.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        votes = np.add.reduceat(bits, cuts[:-1][have], axis=0, dtype=np.uint32)
        out[have] = np.packbits(2 * votes > size[have][:, None], axis=1, bitorder="little").view("<u8").ravel()
    return out


def set_sketches(cuts: np.ndarray, hashes: np.ndarray) -> list[bytes]:
    """For each set the parity of its members in each of a power of two of hashed places: a place for each member, 256 at least and WIDEST at most.

    Sketches fold: the halves of a wider one, joined by exclusive or, are the sketch at half the width. Two sets differ in
    at least as many members as their sketches at one width differ in places.
    """
    size = np.diff(cuts)
    width = np.int64(1) << np.ceil(np.log2(np.clip(size, 64 * BRIEF, WIDEST))).astype(np.int64)
    base = np.cumsum(width) - width
    place = ((hashes >> np.uint64(24)) & np.repeat(width - 1, size).astype(np.uint64)).astype(np.int64) + np.repeat(base, size)
    flat = np.packbits(np.bincount(place, minlength=int(width.sum())).astype(np.uint8) & 1, bitorder="little").tobytes()
    return [flat[i:j] for i, j in zip((base // 8).tolist(), ((base + width) // 8).tolist(), strict=True)]


def least_difference(x, y, chunk: int = 1 << 19) -> np.ndarray:
    """For each row of two binary Arrow columns of sketches, the places in which they differ at the smaller one's width."""

    def parts(column):
        at = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
        return np.frombuffer(column.buffers()[2] or b"", np.uint64, count=int(at[-1]) // 8), at[:-1] // 8, np.diff(at) // 8

    sides, out = [parts(c) for c in (x, y)], np.zeros(len(x), np.int64)
    widths = np.stack([sides[0][2], sides[1][2]], axis=1)
    for pair in np.unique(widths, axis=0).tolist():
        rows = np.flatnonzero((widths == pair).all(axis=1))
        for lo in range(0, len(rows), step := max(1, chunk // max(pair))):
            some, folded = rows[lo : lo + step], []
            for (data, first, _), width in zip(sides, pair, strict=True):
                bits = data[first[some][:, None] + np.arange(width)]
                while bits.shape[1] > min(pair):
                    half = bits.shape[1] // 2
                    bits = bits[:, :half] ^ bits[:, half:]
                folded.append(bits)
            out[some] = np.bitwise_count(folded[0] ^ folded[1]).sum(axis=1, dtype=np.int64)
    return out


def brief_words(column) -> np.ndarray:
    """Sketches of a binary Arrow column folded to BRIEF words each."""
    at = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data, first, width = np.frombuffer(column.buffers()[2] or b"", np.uint64, count=int(at[-1]) // 8), at[:-1] // 8, np.diff(at) // 8
    out = np.zeros((len(column), BRIEF), np.uint64)
    for w in np.unique(width).tolist():
        rows = np.flatnonzero(width == w)
        for lo in range(0, len(rows), step := max(1, (1 << 19) // w)):
            bits = data[first[rows[lo : lo + step]][:, None] + np.arange(w)]
            out[rows[lo : lo + step]] = np.bitwise_xor.reduce(bits.reshape(len(bits), -1, BRIEF), axis=1)
    return out


def _near(brief: np.ndarray | None, size: np.ndarray, a: np.ndarray, b: np.ndarray, bound: tuple[int, int]) -> np.ndarray:
    """Whether the folded sketches of rows a and b leave room for the bound; it never leaves out a pair that reaches it."""
    if brief is None:
        return np.ones(len(a), bool)
    apart = np.bitwise_count(brief[a] ^ brief[b]).sum(axis=1, dtype=np.int64)
    return (bound[0] + bound[1]) * apart <= (bound[1] - bound[0]) * (size[a].astype(np.int64) + size[b])


def _keyed(docs: DataFrame, id_col: str, text_col: str, shingle: int, seed: int) -> DataFrame:
    """(id, key, fp, size, sketch) for each row; the sketch is null where the task has given one for that key before."""

    def keys(batches):
        seen = set()
        for b in batches:
            cols = [[np.zeros(0, np.int64)] for _ in range(3)]
            sketches = []
            for _, cuts, h in shingle_sets(b.column(1), shingle, seed):
                key = set_keys(cuts, h).view(np.int64)
                for col, part in zip(cols, (key, set_prints(cuts, h).view(np.int64), np.diff(cuts)), strict=True):
                    col.append(part)
                for k, sketch in zip(key.tolist(), set_sketches(cuts, h), strict=True):
                    sketches.append(None if k in seen else sketch)
                    seen.add(k)
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(np.concatenate(c)) for c in cols), pa.array(sketches, pa.binary())], ["id", "key", "fp", "size", "sketch"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(keys, f"id {kind}, key long, fp long, size long, sketch binary")


def slot_counts(texts: DataFrame, shingle: int, seed: int) -> np.ndarray:
    """How many texts have a shingle in each slot, one count for each shingle."""

    def count(batches):
        total = np.zeros(SLOTS, np.int64)
        for b in batches:
            for _, _, h in shingle_sets(b.column(0), shingle, seed):
                total += np.bincount((h & np.uint64(SLOTS - 1)).astype(np.int64), minlength=SLOTS)
        parts = total.reshape(-1, PART)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(parts))), pa.array([p.tobytes() for p in parts], pa.binary())], ["part", "blob"])

    def add(batches):
        held = {}
        for b in batches:
            for part, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                held[part] = held.get(part, 0) + np.frombuffer(blob, np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int64()), pa.array([v.tobytes() for v in held.values()], pa.binary())], ["part", "blob"])

    out = np.zeros((SLOTS // PART, PART), np.int64)
    for part, blob in texts.mapInArrow(count, "part long, blob binary").repartition("part").mapInArrow(add, "part long, blob binary").collect():
        out[part] = np.frombuffer(blob, np.int64)
    return out.ravel()


def prefixes(cuts: np.ndarray, hashes: np.ndarray, level: np.ndarray, bound: tuple[int, int]) -> tuple[np.ndarray, ...]:
    """(row, place, hash) of the members of each set of which a set alike enough must share one, rare ones first."""
    size = np.diff(cuts)
    row = np.repeat(np.arange(len(size)), size)
    order = np.lexsort((hashes, level[(hashes & np.uint64(len(level) - 1)).astype(np.int64)], row))
    place = np.arange(len(row)) - cuts[row]
    need = -(-bound[0] * size // bound[1])
    keep = place <= (size - need)[row]
    return row[keep], place[keep], hashes[order][keep]


def _met(token, key, size, place, *more):
    """The rows ordered by token, size and key, each key once for a token, and their token's number."""
    order = np.lexsort((key, size, token))
    new = np.append(True, (token[order][1:] != token[order][:-1]) | (key[order][1:] != key[order][:-1]))[: len(token)]
    order = order[new]
    token, key, size, place, *more = (x[order] for x in (token, key, size.astype(np.int64), place.astype(np.int64), *more))
    return np.cumsum(np.append(True, token[1:] != token[:-1])[: len(token)]) - 1, token, key, size, place, *more


def _fits(size: np.ndarray, place: np.ndarray, a: np.ndarray, b: np.ndarray, bound: tuple[int, int]) -> np.ndarray:
    """Whether rows a and b can be alike if this is their first common member: what is left of the shorter has to be enough."""
    room = np.minimum(size[a] - place[a], size[b] - place[b])
    return (bound[0] + bound[1]) * room >= bound[0] * (size[a] + size[b])


def _distinct(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.lexsort((y, x))
    x, y = x[order], y[order]
    new = np.append(True, (x[1:] != x[:-1]) | (y[1:] != y[:-1]))[: len(x)]
    return x[new], y[new]


def stars(token: np.ndarray, key: np.ndarray, size: np.ndarray, place: np.ndarray, bound: tuple[int, int]):
    """Pairs of each key with the smallest set that shares its token and may be alike, and which rows have more partners."""
    group, _, key, size, place = met = _met(token, key, size, place)
    step = int(size.max(initial=0)) + 1
    first = np.searchsorted(group * step + size, group * step + -(-bound[0] * size // bound[1]), "left")
    b = np.flatnonzero(first < np.arange(len(key)))
    b = b[_fits(size, place, first[b], b, bound)]
    return _distinct(key[first[b]], key[b]), np.bincount(group, minlength=1)[group] > 2 if len(group) else np.zeros(0, bool), met


def chains(token: np.ndarray, key: np.ndarray, size: np.ndarray, place: np.ndarray, own: np.ndarray, bound: tuple[int, int], salt: int, brief: np.ndarray | None = None):
    """Pairs of neighbours of different components in an order of each token's keys that differs from token to token."""
    mixed = mix(key.view(np.uint64) ^ mix(token.view(np.uint64) + np.uint64(salt)))
    order = np.lexsort((mixed, token))
    a, b = order[:-1], order[1:]
    good = (token[a] == token[b]) & (own[a] != own[b])
    a, b = a[good], b[good]
    good = _fits(size.astype(np.int64), place.astype(np.int64), a, b, bound) & _near(brief, size, a, b, bound)
    x, y = key[a[good]], key[b[good]]
    return _distinct(np.minimum(x, y), np.maximum(x, y))


def candidates(token: np.ndarray, key: np.ndarray, size: np.ndarray, place: np.ndarray, bound: tuple[int, int], chunk: int = 1 << 21, own: np.ndarray | None = None, brief: np.ndarray | None = None):
    """Yields arrays (a, b), a < b, of keys that share a token and whose sizes and places leave room for the bound.

    own: a component for each row; then only keys of different components are paired, and a token's rows of one component
    are not met with each other if that is less work than to take all partners by size. brief: the folded sketch of each
    row's set; pairs that it shows to be too different are left out here, before they become rows of a join.
    """
    group, _, key, size, place, *own = _met(token, key, size, place, *([] if own is None else [own]), *([] if brief is None else [brief]))
    brief = own.pop() if brief is not None else None
    at, n = np.arange(len(key)), len(key)
    step = int(size.max(initial=0)) * bound[1] + 1
    # sizes rise within a token, so partners of a row are the run behind it up to the largest size the bound allows
    end = np.searchsorted(group * step + size, group * step + np.minimum(size * bound[1] // bound[0], step - 1), "right")
    ways = [(at, at + 1, end)]
    if own and n:
        order = np.lexsort((own[0], group))
        run = np.cumsum(np.append(True, (group[order][1:] != group[order][:-1]) | (own[0][order][1:] != own[0][order][:-1])))
        behind, last = np.searchsorted(run, run, "right"), np.searchsorted(group, group, "right")  # both orders keep tokens together
        across, by_size = (np.bincount(group, x) for x in (last - behind, end - at - 1))
        use = (across < by_size)[group]
        ways = [(at, at + 1, np.where(use, at + 1, end)), (order, behind, np.where(use, last, behind))]
    for order, lo_, hi_ in ways:
        count = hi_ - lo_
        sums, lo = np.cumsum(count), 0
        while lo < n:
            hi = max(int(np.searchsorted(sums, (sums[lo - 1] if lo else 0) + chunk, "right")), lo + 1)
            a = order[np.repeat(np.arange(lo, hi), count[lo:hi])]
            b = order[spread(lo_[lo:hi], count[lo:hi])]
            good = _fits(size, place, a, b, bound)
            if own:
                good &= own[0][a] != own[0][b]
            if brief is not None:
                a, b = a[good], b[good]
                good = _near(brief, size, a, b, bound)
            x, y = key[a[good]], key[b[good]]
            yield _distinct(np.minimum(x, y), np.maximum(x, y))
            lo = hi


def by_token(batches, rows: int = 1 << 21):
    """Columns of batches that are sorted by their first column, in runs of about so many rows that end with a value of it."""
    held, size = [], 0
    for b in batches:
        if b.num_rows:
            held.append([b.column(k).to_numpy(zero_copy_only=False) for k in range(b.num_columns)])
            size += b.num_rows
        if size >= rows:
            cols = [np.concatenate(x) for x in zip(*held, strict=True)]
            last = int(np.argmax(cols[0] == cols[0][-1]))
            if last:
                yield [c[:last] for c in cols]
            held, size = [[c[last:] for c in cols]], size - last
    if size:
        yield [np.concatenate(x) for x in zip(*held, strict=True)]


def key_bits(keys: DataFrame) -> tuple[np.ndarray, int]:
    """A packed bit for each hashed slot that a key falls in, and the mask that gives the slot: 2^27 bits at most."""
    n = keys.count()
    mask = (1 << min(27, max(14, (8 * n).bit_length()))) - 1

    def slots(batches):
        held: dict[int, np.ndarray] = {}
        for b in batches:
            at = b.column(0).to_numpy(zero_copy_only=False) & mask
            for part in np.unique(at // PART).tolist():
                held.setdefault(part, np.zeros(PART, bool))[at[at // PART == part] % PART] = True
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int64()), pa.array([np.packbits(v).tobytes() for v in held.values()], pa.binary())], ["part", "blob"])

    def either(batches):
        held: dict[int, np.ndarray] = {}
        for b in batches:
            for part, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                held[part] = held.get(part, 0) | np.frombuffer(blob, np.uint8)
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int64()), pa.array([v.tobytes() for v in held.values()], pa.binary())], ["part", "blob"])

    out = np.zeros(((mask + 1) // PART, PART // 8), np.uint8)
    for part, blob in keys.mapInArrow(slots, "part long, blob binary").repartition("part").mapInArrow(either, "part long, blob binary").collect():
        out[part] = np.frombuffer(blob, np.uint8)
    return out.ravel(), mask


def sets_of(texts: DataFrame, wanted: DataFrame, shingle: int, seed: int) -> DataFrame:
    """(key, members) of the distinct keys in wanted, whose sets are taken from the texts again."""
    wanted = materialize(wanted.distinct(), "wanted")
    bits, mask = key_bits(wanted)
    shared = texts.sparkSession.sparkContext.broadcast(bits)

    def whole_sets(batches):
        marks, seen = shared.value, set()
        for b in batches:
            keys, sets = [], []
            for _, cuts, h in shingle_sets(b.column(0), shingle, seed):
                own = set_keys(cuts, h).view(np.int64)
                slot = own & mask
                for r in np.flatnonzero(marks[slot >> 3] >> (7 - (slot & 7)) & 1).tolist():
                    if (k := int(own[r])) not in seen:
                        seen.add(k)
                        keys.append(k)
                        sets.append(h[cuts[r] : cuts[r + 1]].view(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(sets, pa.list_(pa.int64()))], ["key", "members"])

    return texts.mapInArrow(whole_sets, "key long, members array<long>").join(wanted, "key", "left_semi").dropDuplicates(["key"])


def may_be_alike(pairs: DataFrame, sketches: DataFrame, bound: tuple[int, int]) -> DataFrame:
    """The rows of pairs (a, b) but those whose sketches show that their sets are less alike than the bound."""

    def near(batches):
        for b in batches:
            total = b.column(2).to_numpy(zero_copy_only=False)
            good = (bound[0] + bound[1]) * least_difference(b.column(3), b.column(4)) <= (bound[1] - bound[0]) * total
            yield pa.RecordBatch.from_arrays([c.filter(pa.array(good)) for c in b.columns[:2]], ["a", "b"])

    side = lambda key, n, bits: sketches.select(F.col("key").alias(key), F.col("size").alias(n), F.col("sketch").alias(bits))
    both = pairs.join(side("b", "m", "y"), "b").join(side("a", "n", "x"), "a")
    return both.select("a", "b", (F.col("n") + F.col("m")).alias("total"), "x", "y").mapInArrow(near, "a long, b long")


def alike(texts: DataFrame, pairs: DataFrame, sketches: DataFrame, shingle: int, bound: tuple[int, int], seed: int) -> DataFrame:
    """The rows of pairs (a, b) whose sets have at least the similarity; sets that the sketches leave are read from the texts once."""
    near = materialize(may_be_alike(pairs, sketches, bound), "near")
    if not near.limit(1).count():
        return near
    sets = materialize(sets_of(texts, near.select(F.col("a").alias("key")).unionAll(near.select(F.col("b").alias("key"))), shingle, seed), "sets")
    side = lambda key, members: sets.select(F.col("key").alias(key), F.col("members").alias(members))
    both = near.join(side("b", "y"), "b").join(side("a", "x"), "a").select("a", "b", (F.size("x") + F.size("y")).alias("total"), F.size(F.array_intersect("x", "y")).alias("shared"))
    out = materialize(both.where((bound[0] + bound[1]) * F.col("shared") >= bound[0] * F.col("total")).select("a", "b"), "alike")
    release(near, sets)
    return out


def links(docs: DataFrame, sketches: DataFrame, text_col: str = "text", shingle: int = 5, bound: tuple[int, int] = (4, 5), seed: int = 42, rows: int = 1_000_000, first: DataFrame | None = None, rounds: int = 2) -> DataFrame:
    """Edges (a, b) between keys of sets that connect exactly those which chains of sets with at least the similarity connect.

    sketches: key, size and sketch of each set, see set_sketches. first: pairs of keys to compare before all others, from another index. rounds: how often at most neighbours in a mixed
    order are compared before all pairs that are still in different components.
    """
    ship()
    texts = docs.select(text_or_empty(text_col).alias("text"))
    counts = slot_counts(texts, shingle, seed)
    level = np.ceil(np.log2(counts + 1.0)).astype(np.uint8)
    tasks = max(int(counts.sum()) * (bound[1] - bound[0]) // bound[1] // rows + 1, docs.sparkSession.sparkContext.defaultParallelism)

    def first_members(batches):
        seen = set()
        for b in batches:
            for _, cuts, h in shingle_sets(b.column(0), shingle, seed):
                keys = set_keys(cuts, h).view(np.int64)
                fresh = np.zeros(len(keys), bool)
                for r, k in enumerate(keys.tolist()):
                    if k not in seen:
                        seen.add(k)
                        fresh[r] = True
                row, place, token = prefixes(cuts, h, level, bound)
                use = fresh[row]
                row, place, token = row[use], place[use], token[use]
                size = np.diff(cuts)[row]
                yield pa.RecordBatch.from_arrays([pa.array(token.view(np.int64)), pa.array(keys[row]), pa.array(size.astype(np.int32)), pa.array(place.astype(np.int32))], ["token", "key", "size", "place"])

    def meet(batches):
        """Pairs as rows without a size, and rows that may have further partners."""
        for token, key, size, place in by_token(batches):
            (a, b), more, (_, token, key, size, place) = stars(token, key, size, place, bound)
            none = pa.nulls(len(a), pa.int32())
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), none, none], names)
            yield pa.RecordBatch.from_arrays([pa.array(token[more]), pa.array(key[more]), pa.array(size[more].astype(np.int32)), pa.array(place[more].astype(np.int32))], names)

    def across(batches):
        for token, key, size, place, own, *words in by_token(batches):
            for a, b in candidates(token, key, size, place, bound, own=own, brief=np.stack(words, axis=1).view(np.uint64)):
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])

    def neighbours(salt):
        def run(batches):
            for token, key, size, place, own, *words in by_token(batches):
                a, b = chains(token, key, size, place, own, bound, salt, np.stack(words, axis=1).view(np.uint64))
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])

        return run

    def work(batches):
        """Rows, and pairs at most that are left to compare."""
        rows = pairs = 0
        square = lambda first: int((np.diff(np.append(np.flatnonzero(first), len(first))) ** 2).sum())
        for token, _, _, _, own, *_ in by_token(batches):
            order = np.lexsort((own, token))
            token, own = token[order], own[order]
            new = np.append(True, token[1:] != token[:-1])
            run = new | np.append(True, own[1:] != own[:-1])
            rows, pairs = rows + len(token), pairs + (square(new) - square(run)) // 2
        yield pa.RecordBatch.from_arrays([pa.array([rows]), pa.array([pairs])], ["n", "pairs"])

    def apart(edges):
        """What may have further partners, with its component by the edges, and the edges as one link to each component's root."""
        roots = materialize(connected_components(edges), "roots")
        rest = met.where("size is not null").join(roots.withColumnRenamed("node", "key"), "key", "left").join(briefs, "key").select("token", "key", "size", "place", F.coalesce("root", "key").alias("own"), *words)
        return rest.repartition(tasks, "token").sortWithinPartitions("token"), roots.select(F.col("node").alias("a"), F.col("root").alias("b"))

    def folded(batches):
        for b in batches:
            own = brief_words(b.column(1)).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(own[:, k].copy()) for k in range(BRIEF))], ["key", *words])

    words = [f"w{k}" for k in range(BRIEF)]
    briefs = materialize(sketches.select("key", "sketch").mapInArrow(folded, "key long, " + ", ".join(f"{w} long" for w in words)), "briefs")
    names = ["token", "key", "size", "place"]
    members = texts.mapInArrow(first_members, "token long, key long, size int, place int")
    met = materialize(members.repartition(tasks, "token").sortWithinPartitions("token").mapInArrow(meet, "token long, key long, size int, place int"), "met")
    pairs = met.where("size is null").select(F.col("token").alias("a"), F.col("key").alias("b"))
    pairs = materialize((pairs if first is None else pairs.unionAll(first.select("a", "b"))).where("a <> b").distinct(), "pairs")
    rest, edges = apart(alike(texts, pairs, sketches, shingle, bound, seed))
    release(pairs)
    for salt in range(1, rounds + 1):
        n, left = rest.mapInArrow(work, "n long, pairs long").agg(F.sum("n"), F.sum("pairs")).first()
        if (left or 0) <= 4 * (n or 0):
            break
        # too many pairs to compare all: first at most as many as there are rows, which join what is alike in large groups
        pairs = materialize(rest.mapInArrow(neighbours(salt), "a long, b long").distinct(), "neighbours")
        close = alike(texts, pairs, sketches, shingle, bound, seed)
        release(pairs)
        if not close.limit(1).count():
            break
        rest, edges = apart(edges.unionAll(close))
    more = materialize(rest.mapInArrow(across, "a long, b long").distinct(), "candidates")
    release(met)
    return edges.unionAll(alike(texts, more, sketches, shingle, bound, seed)) if more.limit(1).count() else edges


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, bound: tuple[int, int] = (4, 5), seed: int = 42, k: int = 3) -> DataFrame:
    """One row per document: id and component_id, the smallest id reachable over pairs at or above the bound.

    Texts without words have the empty set and are alike. Ids are treated as in simhash.near_duplicates.
    """
    ship()
    marked = materialize(_keyed(docs, id_col, text_col, shingle, seed), "keys")
    sketches = materialize(marked.where("sketch is not null").select("key", "size", "sketch").dropDuplicates(["key"]), "sketches")
    groups = materialize(marked.groupBy("key").agg(F.min("id").alias("least"), F.count("*").alias("n"), F.first("fp").alias("fp")), "groups")
    heads = materialize(groups.groupBy("fp").agg(F.min("key").alias("head"), F.count("*").alias("n")), "heads")
    same = join_counted(groups.select("key", "fp"), heads, "fp", "n").select(F.col("head").alias("a"), F.col("key").alias("b"))
    head = lambda fp, name: heads.select(F.col("fp").alias(fp), F.col("head").alias(name))
    close = close_prints(heads.select("fp"), k).join(head("a", "x"), "a").join(head("b", "y"), "b").select(F.col("y").alias("a"), F.col("x").alias("b"))
    edges = links(docs, sketches, text_col, shingle, bound, seed, first=same.unionAll(close))
    return components_of(marked.select("id", "key"), groups.drop("fp"), edges, "key").withColumnRenamed("id", id_col).select(id_col, "component_id")
