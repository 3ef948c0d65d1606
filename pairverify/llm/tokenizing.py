"""Token ids of whole texts, equal to one call of the tokenizer on each text, but with each distinct chunk encoded once.

A chunk is a stretch that the tokenizer treats by itself whatever stands beside it. "lone_space" (byte-level BPE with its
usual splitting pattern): a text may be cut before any space that a visible character follows. "words" (white space
dropped before splitting): the stretches between ASCII white space. In both, a cut also stands between an ASCII letter
and ASCII punctuation, except the bar, which is part of special tokens. Ids of chunks are kept for all tasks of a worker, found
by a hash of the chunk's bytes; the bytes are kept too and compared on every hit, so hashes that collide change no id.
"""

from __future__ import annotations

import os
import sys
import types

import numpy as np

from ._bytes import HashIndex, Hasher, mix, slices, space_table, spread, word_bounds

STYLES = {"byte_bpe_50k.json": "lone_space", "word_bpe_49k.json": "words"}
#: Lead bytes of characters among which are kinds of white space; no cut stands before them.
LEADS = (0xC2, 0xE1, 0xE2, 0xE3)


def tokenizer_file(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def encoder(path: str, style: str, most_kept: int = 2_000_000) -> "ChunkEncoder":
    """This process's encoder for a tokenizer; it outlives the task, so later tasks find the chunks it knows.

    most_kept bounds what it keeps: about 70 bytes for a chunk, of which most stand in one text only.
    """
    # functions are shipped by value, so what a worker keeps between tasks has to live in a module of its own
    held = sys.modules.setdefault("pairverify_worker_state", types.ModuleType("pairverify_worker_state")).__dict__.setdefault("encoders", {})
    if (path, style, most_kept) not in held:
        held.clear()
        held[path, style, most_kept] = ChunkEncoder(path, style, most_kept)
    return held[path, style, most_kept]


class ChunkEncoder:
    def __init__(self, path: str, style: str, most_kept: int = 2_000_000, hash_bits: int = 64):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer, self.style, self.most_kept = Tokenizer.from_file(path), style, most_kept
        self.mask = np.uint64(((1 << hash_bits) - 1) << (64 - hash_bits))
        self.hasher, self.space = Hasher(), space_table()
        self.mark = "<|endoftext|>"
        self.mark_id = self.tokenizer.token_to_id(self.mark)
        if self.mark_id is None:
            raise ValueError(f"the tokenizer has no token {self.mark}")
        self.stops = np.zeros(256, bool)
        self.stops[:0x21] = True
        self.stops[list(LEADS)] = True
        self.letter, self.point = np.zeros(256, bool), np.zeros(256, bool)
        self.letter[65:91] = self.letter[97:123] = True
        for a, b in ((33, 48), (58, 65), (91, 97), (123, 127)):
            self.point[a:b] = True
        self.point[ord("|")] = False
        self._forget()

    def _forget(self) -> None:
        self.index = HashIndex(self.most_kept)
        self.first, self.size, self.pool, self.used = np.zeros(1 << 14, np.int32), np.zeros(1 << 14, np.int32), np.zeros(1 << 16, np.uint32), 0
        self.begin, self.length, self.text, self.filled = np.zeros(1 << 14, np.int64), np.zeros(1 << 14, np.int32), np.zeros(1 << 18, np.uint8), 0

    @property
    def vocabulary(self) -> int:
        return self.tokenizer.get_vocab_size(with_added_tokens=True)

    def _chunks(self, buf: np.ndarray, off: np.ndarray):
        cut = np.zeros(len(buf) + 1, bool)
        points = np.flatnonzero(self.point[buf[1:]] & self.letter[buf[:-1]]) + 1
        if self.style == "words":
            start, stop, _ = word_bounds(buf, off, self.space)
            points = points[~np.isin(points, off)] if len(points) else points
            cut[start] = True
            cut[points] = True
            start = np.flatnonzero(cut[:-1])
            cut[:] = False
            cut[stop] = True
            cut[points] = True
            return start, np.flatnonzero(cut), np.searchsorted(start, off)
        cut[:-2] = (buf[:-1] == 0x20) & ~self.stops[buf[1:]]
        if len(off) > 1:  # a space that ends one text is not before the next text's first letter
            last = off[1:][off[1:] > off[:-1]] - 1
            cut[last] = False
        cut[points] = True
        cut[off[off < len(buf)]] = True
        start = np.flatnonzero(cut[:-1])
        stop = np.append(start[1:], len(buf)) if len(start) else start
        return start, stop, np.searchsorted(start, off)

    def _keep(self, buf: np.ndarray, start: np.ndarray, stop: np.ndarray) -> None:
        """Keep the bytes of chunks that are about to be numbered."""
        held, more, size = self.index.used, self.index.used + len(start), stop - start
        total = int(size.sum())
        if self.filled + total > len(self.text):
            self.text = np.concatenate([self.text[: self.filled], np.zeros(total + self.filled // 2 + 1, np.uint8)])
        if more > len(self.begin):
            self.begin, self.length = (np.concatenate([x[:held], np.zeros(more + more // 2 - held, x.dtype)]) for x in (self.begin, self.length))
        self.text[self.filled : self.filled + total] = buf[spread(start, size)]
        self.begin[held:more], self.length[held:more] = self.filled + np.cumsum(size) - size, size
        self.filled += total

    def _other(self, buf: np.ndarray, start: np.ndarray, stop: np.ndarray, place: np.ndarray) -> np.ndarray:
        """Chunks whose bytes are not those kept under their number."""
        size = stop - start
        alike = self.length[place] == size
        k = np.flatnonzero(alike)
        if len(k):
            n = size[k]
            equal = buf[spread(start[k], n)] == self.text[spread(self.begin[place[k]], n)]
            alike[k] = np.logical_and.reduceat(equal, np.cumsum(n) - n)
        return np.flatnonzero(~alike)

    def _learn(self, buf: np.ndarray, start: np.ndarray, stop: np.ndarray, keys: np.ndarray) -> None:
        raw = buf.tobytes()
        texts = [raw[a:b].decode("utf-8", "replace") for a, b in zip(start.tolist(), stop.tolist(), strict=True)]
        own = {k: self.tokenizer.encode(x, add_special_tokens=False).ids for k, x in enumerate(texts) if self.mark in x}
        for k in own:
            texts[k] = ""
        # one call for many chunks, with a special token between them, which takes no part in splitting
        runs = [self.mark.join(texts[k : k + 500]) for k in range(0, len(texts), 500)]
        ids = [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(runs, add_special_tokens=False)]
        ids = np.concatenate([np.append(x, np.uint32(self.mark_id)) for x in ids])
        at = np.flatnonzero(ids == self.mark_id)
        size = np.diff(at, prepend=-1) - 1
        ids = np.delete(ids, at)
        if own:
            ends = np.cumsum(size)
            ids = np.insert(ids, np.repeat(ends[list(own)], [len(x) for x in own.values()]), [y for x in own.values() for y in x])
            size[list(own)] = [len(x) for x in own.values()]
        total, held, more = len(ids), self.index.used, self.index.used + len(keys)
        if self.used + total > len(self.pool):
            self.pool = np.concatenate([self.pool[: self.used], np.zeros(total + self.used // 2 + 1, np.uint32)])
        if more > len(self.first):
            room = np.zeros(more + more // 2, np.int32)
            self.first, self.size = (np.concatenate([x[:held], room[held:]]) for x in (self.first, self.size))
        self.pool[self.used : self.used + total] = ids
        self.first[held:more], self.size[held:more] = self.used + np.cumsum(size) - size, size
        self.used += total
        self._keep(buf, start, stop)
        self.index.add(keys)

    def encode(self, column):
        """Yields first row, row after the last, their ids one after the other, and each row's offset in them."""
        for i, j, buf, off in slices(column):
            start, stop, before = self._chunks(buf, off)
            if not len(start):
                yield i, j, np.zeros(0, np.uint32), np.zeros(j - i + 1, np.int64)
                continue
            h = mix(self.hasher.word(buf, start, stop) ^ (stop - start).astype(np.uint64)) & self.mask
            place = self.index.find(h)
            new = np.flatnonzero(place < 0)
            if len(new):
                keys, at = np.unique(h[new], return_index=True)
                if self.index.used + len(keys) > self.most_kept:
                    self._forget()
                    new = np.arange(len(h))
                    keys, at = np.unique(h, return_index=True)
                    if len(keys) > self.most_kept:
                        self.index = HashIndex(len(keys))
                self._learn(buf, start[new[at]], stop[new[at]], keys)
                place = self.index.find(h)
            size = self.size[place].astype(np.int64)
            other = self._other(buf, start, stop, place)
            if len(other):  # hashes that collide: such a chunk is encoded anew each time
                own = [self.tokenizer.encode(buf[start[k] : stop[k]].tobytes().decode("utf-8", "replace"), add_special_tokens=False).ids for k in other.tolist()]
                size[other] = 0
                ids = self.pool[spread(self.first[place].astype(np.int64), size)]
                at = np.cumsum(size)[other]
                size[other] = [len(x) for x in own]
                ids = np.insert(ids, np.repeat(at, size[other]), np.array([y for x in own for y in x], np.uint32))
            else:
                ids = self.pool[spread(self.first[place].astype(np.int64), size)]
            ends = np.concatenate([[0], np.cumsum(size)])
            yield i, j, ids, ends[before]
