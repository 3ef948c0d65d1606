"""Sum-of-squares online packing of tokenised documents into fixed windows.

Each task packs its own documents as they come. A document's ids (its end id included) are cut into full windows and one
rest; the rest goes whole to the fill level for which the sum of squared counts of open windows at each level becomes
least, as kept in one array of counts by level. At the task's end, and where more than `max_open` windows are open, the
least filled windows are dissolved and their pieces placed again by the same rule; only a piece that fits nowhere whole is
cut, to close the window with the most room. What is left of the last window fills windows whose length is a power of
two, so that nothing is padded. Nothing is dropped, and what a task holds is bounded by `max_open` windows.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ._common import materialize, ship, text_or_empty
from .tokenizing import STYLES, encoder, tokenizer_file


class SquaresPacker:
    """put() pieces of less than a window; closed windows, lists of (piece, offset, size, placed by the rule), come from put() and close().

    A piece is (document, start, length). moved: tokens of dissolved windows; cut: tokens cut off to close windows.
    """

    def __init__(self, window: int = 1024, max_open: int = 4096):
        self.window, self.max_open = window, max_open
        self.count = np.zeros(window + 1, np.int64)
        self.open: list[list[list]] = [[] for _ in range(window)]
        self.n_open = self.moved = self.cut = 0

    def level(self, size: int, may_open: bool = True) -> int:
        """The fill level that a piece goes to; 0 opens a window, or stands for nowhere. Equal costs go to the fullest level."""
        c, w = self.count, self.window
        here = c[1 : w - size + 1]
        there = c[1 + size : w + 1]
        change = 2 * (there - here) + 2
        change[-1:] -= 1  # a full window is no longer counted
        change[here == 0] = np.iinfo(np.int64).max
        if len(change):
            best = len(change) - 1 - int(np.argmin(change[::-1]))
            if change[best] <= (2 * c[size] + 1 if may_open else np.iinfo(np.int64).max - 1):
                return best + 1
        return 0

    def _take(self, level: int) -> list:
        self.count[level] -= 1
        self.n_open -= 1
        return self.open[level].pop()

    def _add(self, at: int, piece: tuple, ruled: bool) -> list[list[tuple]]:
        """Put a piece into a window of level `at` (0: a new one)."""
        pieces, size = self._take(at) if at else [], piece[2]
        pieces.append((piece, at, size, ruled))
        if at + size == self.window:
            return [pieces]
        self.open[at + size].append(pieces)
        self.count[at + size] += 1
        self.n_open += 1
        return []

    def put(self, piece: tuple, size: int) -> list[list[tuple]]:
        out = self._add(self.level(size), piece, True)
        return out + self.close(self.max_open // 2) if self.n_open > self.max_open else out

    def close(self, leave: int = 0) -> list[list[tuple]]:
        """Dissolve windows, the least filled first, until `leave` are open; with 0, the last one goes into powers of two."""
        out: list[list[tuple]] = []
        while self.n_open > max(leave, 1):
            pieces = self._take(int(np.argmax(self.count > 0)))
            for (doc, start, n), _, _, _ in sorted(pieces, key=lambda p: -p[2]):
                self.moved += n
                while n:
                    at = self.level(n, may_open=False)
                    if at or not self.n_open:
                        out += self._add(at, (doc, start, n), True)
                        break
                    at = int(np.argmax(self.count > 0))  # the most room
                    take = self.window - at
                    self.cut += take
                    out += self._add(at, (doc, start, take), False)
                    start, n = start + take, n - take
        if leave == 0 and self.n_open:
            pieces = self._take(int(np.argmax(self.count > 0)))
            total, k, used = sum(p[2] for p in pieces), 0, 0
            for length in [1 << b for b in range(self.window.bit_length(), -1, -1) if total >> b & 1]:
                have, own = 0, []
                while have < length:
                    (doc, start, n), _, size, ruled = pieces[k]
                    take = min(size - used, length - have)
                    own.append(((doc, start + used, take), have, take, ruled and take == size))
                    have, used = have + take, used + take
                    if used == size:
                        k, used = k + 1, 0
                out.append(own)
        return out


def pack(docs: DataFrame, tokenizer: str | None = None, style: str = "lone_space", end_id: int = 0, window: int = 1024, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False, max_open: int = 4096) -> DataFrame:
    """One row per piece: id, start, length, ids_crc32, doc_tokens, sequence_id, offset, by_rule (and the ids, if asked).

    A null or empty text is the end id alone. Rows that repeat an id are packed one by one. Sequence ids count without
    gaps over all tasks, by prefix sums of the tasks' counts. by_rule: the piece is a full window of its own, or a
    rest, or what a cut left of one, that lies where the least sum of squares put it. An empty table gives no rows. Other columns of docs play no part.
    """
    ship()
    path = tokenizer or tokenizer_file("byte_bpe_50k.json")
    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"id {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence long, offset long, by_rule boolean, part int" + ", ids array<int>" * with_ids

    def run(batches):
        from pyspark import TaskContext

        part, coder, packer = TaskContext.get().partitionId(), encoder(path, style), SquaresPacker(window, max_open)
        kept: dict[int, tuple] = {}
        rows, done, number = [], 0, 0

        def shut(windows):
            nonlocal done
            for pieces in windows:
                for (doc, start, n), at, _, ruled in pieces:
                    ids, first, key, size, left = kept[doc]
                    cut = ids[start - first : start - first + n]
                    rows.append((key, start, n, zlib.crc32(cut.astype("<u4").tobytes()), size, done, at, ruled, cut))
                    if left == n:
                        del kept[doc]
                    else:
                        kept[doc] = (ids, first, key, size, left - n)
                done += 1

        def flush():
            cols = list(zip(*rows, strict=True))
            arrays = [pa.array(cols[0], type=id_type)] + [pa.array(np.array(c, np.int64)) for c in cols[1:7]] + [pa.array(cols[7]), pa.array(np.full(len(rows), part, np.int32))]
            if with_ids:
                arrays.append(pa.array([c.astype(np.int32) for c in cols[8]], type=pa.list_(pa.int32())))
            rows.clear()
            return pa.RecordBatch.from_arrays(arrays, names)

        names = ["id", "start", "length", "ids_crc32", "doc_tokens", "sequence", "offset", "by_rule", "part"] + ["ids"] * with_ids
        id_type = None
        for b in batches:
            id_type = b.schema.field(0).type
            keys = b.column(0).to_pylist()
            for i, j, ids, off in coder.encode(b.column(1)):
                for r in range(i, j):
                    own = np.append(ids[off[r - i] : off[r - i + 1]], np.uint32(end_id)).astype(np.uint32)
                    size, doc = len(own), number
                    number += 1
                    whole = size // window * window
                    kept[doc] = (own, 0, keys[r], size, size)
                    shut([[((doc, s, window), 0, window, True)] for s in range(0, whole, window)])
                    if size > whole:
                        kept[doc] = (own[whole:].copy(), whole, keys[r], size, size - whole)
                        shut(packer.put((doc, whole, size - whole), size - whole))
                    if len(rows) >= 20_000:
                        yield flush()
        shut(packer.close())
        if rows:
            yield flush()

    packed = materialize(docs.select(F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(run, schema), "packed")
    counts = packed.groupBy("part").agg((F.max("sequence") + 1).alias("n"))
    bases = counts.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("base"))  # one row per task
    out = packed.join(F.broadcast(bases), "part").withColumn("sequence_id", F.col("base") + F.col("sequence"))
    return out.select(F.col("id").alias(id_col), "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "by_rule", *["ids"] * with_ids)


__all__ = ["STYLES", "SquaresPacker", "pack"]
