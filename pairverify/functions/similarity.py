"""Similarity of a candidate to a reference text: BLEU, ROUGE-L, edit distance, greedy embedding matching.

BLEU, edit distance and the short form of ROUGE-L are native; the longest common subsequence of long texts and matching
of token vectors run on Arrow batches. A null on either side gives null.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .text import bind, ngrams


def _overlap(a: Column, b: Column) -> Column:
    """Matches of a's entries in b, each entry of b used once; a may be much longer than b."""
    count = lambda xs, g: F.size(F.filter(xs, lambda x: x == g))
    known = lambda s: F.struct(F.filter(s["a"], lambda x: F.array_contains(s["b"], x)).alias("a"), s["b"].alias("b"))
    matched = lambda s: F.aggregate(F.array_distinct(s["b"]), F.lit(0), lambda n, g: n + F.least(count(s["a"], g), count(s["b"], g)))
    return bind(bind(F.struct(a.alias("a"), b.alias("b")), known), matched)


def bleu_counts(candidate: Column, reference: Column, most: int = 4) -> list[tuple[Column, Column]]:
    return [(_overlap(ngrams(candidate, n), ngrams(reference, n)), F.greatest(F.size(candidate) - (n - 1), F.lit(0))) for n in range(1, most + 1)]


def _bleu(counts, c, r, smooth: str) -> Column:
    logs = F.lit(0.0)
    for n, (m, total) in enumerate(counts, 1):
        if smooth == "add_one" and n > 1:
            p = (m + 1) / (total + 1)
        elif smooth == "floor":
            p = F.greatest(m.cast("double"), F.lit(0.1)) / F.greatest(total, F.lit(1))
        else:
            p = m / F.nullif(total, F.lit(0))
        logs = logs + F.log(F.nullif(p.cast("double"), F.lit(0.0))) / len(counts)
    brevity = F.when(c >= r, F.lit(1.0)).otherwise(F.exp(1 - r / F.nullif(c, F.lit(0))))
    return F.coalesce(brevity * F.exp(logs), F.lit(0.0))


def bleu(candidate: Column, reference: Column, smooth: str = "add_one", most: int = 4) -> Column:
    """Sentence BLEU of token arrays. smooth: none, add_one (n > 1), floor (0.1 for no match)."""
    return _bleu(bleu_counts(candidate, reference, most), F.size(candidate), F.size(reference), smooth)


def corpus_bleu(pairs: DataFrame, candidate: str, reference: str, by: list[str], smooth: str = "none", most: int = 4) -> DataFrame:
    """BLEU from summed counts of all pairs of a group."""
    counts = bleu_counts(F.col(candidate), F.col(reference), most)
    rows = pairs.select(*by, F.size(candidate).alias("_c"), F.size(reference).alias("_r"), *[x.alias(f"{k}{n}") for n, own in enumerate(counts) for k, x in zip("mt", own, strict=True)])
    sums = rows.groupBy(*by).agg(*[F.sum(x).alias(x) for x in rows.columns if x not in by])
    return sums.select(*by, _bleu([(F.col(f"m{n}"), F.col(f"t{n}")) for n in range(most)], F.col("_c"), F.col("_r"), smooth).alias("bleu"))


LIMB = 62


def lcs_native(a: Column, b: Column) -> Column:
    """Longest common subsequence of two token arrays, native: lcs_length with b's bits in numbers of 62 bits each.

    A carry goes from one number to the next, so b may have any length; each word of a costs one step for each number.
    """
    one = F.lit(1).cast("bigint")
    limbs = lambda s: F.sequence(F.lit(0), F.floor((F.size(s["b"]) - 1) / LIMB).cast("int"))
    places = lambda s, k: F.sequence(F.lit(0), F.least(F.lit(LIMB), F.size(s["b"]) - k * LIMB) - 1)
    shifted = lambda i: F.call_function("shiftleft", one, i)
    held = lambda s, k, keep: F.aggregate(places(s, k), F.lit(0).cast("bigint"), lambda n, i: n.bitwiseOR(F.when(keep(k * LIMB + i + 1), shifted(i)).otherwise(F.lit(0).cast("bigint"))))
    rows = lambda s, keep: F.transform(limbs(s), lambda k: held(s, k, keep))

    def placed(s: Column) -> Column:
        kinds = F.array_distinct(s["b"])
        masks = F.transform(kinds, lambda w: rows(s, lambda j: F.element_at(s["b"], j) == w))
        at = F.filter(F.transform(s["a"], lambda w: F.array_position(kinds, w).cast("int")), lambda p: p > 0)
        return F.struct(at.alias("at"), masks.alias("masks"), rows(s, lambda _: F.lit(True)).alias("full"), F.size(s["b"]).alias("n"))

    def step(s: Column, row: Column, p: Column) -> Column:
        start = F.struct(F.lit(0).cast("bigint").alias("carry"), F.array().cast("array<bigint>").alias("row"))

        def one_limb(acc: Column, k: Column) -> Column:
            x, full = F.element_at(row, k), F.element_at(s["full"], k)
            hit = x.bitwiseAND(F.element_at(F.element_at(s["masks"], p), k))
            total = x + hit + acc["carry"]
            return F.struct(F.shiftright(total, LIMB).alias("carry"), F.concat(acc["row"], F.array(total.bitwiseOR(x - hit).bitwiseAND(full))).alias("row"))

        return F.aggregate(F.sequence(F.lit(1), F.size(row)), start, one_limb, lambda acc: acc["row"])

    def length(s: Column) -> Column:
        left = F.aggregate(s["at"], s["full"], lambda row, p: step(s, row, p))
        return F.aggregate(left, s["n"], lambda n, x: n - F.bit_count(x))

    n = bind(F.struct(a.alias("a"), b.alias("b")), lambda s: F.when((F.size(s["a"]) > 0) & (F.size(s["b"]) > 0), bind(placed(s), length)).otherwise(F.lit(0)))
    return F.when(a.isNotNull() & b.isNotNull(), n)


def lcs_length(a: list, b: list) -> int:
    """The same by bit-parallel rows: one pass over a with b held in the bits of one number."""
    where: dict = {}
    for j, w in enumerate(b):
        where[w] = where.get(w, 0) | 1 << j
    full = (1 << len(b)) - 1
    row = full
    for w in a:
        hit = row & where.get(w, 0)
        row = ((row + hit) | (row - hit)) & full
    return len(b) - row.bit_count()


def lcs(a: Column, b: Column) -> Column:
    """Longest common subsequence for texts of any length, on Arrow batches."""

    @F.pandas_udf("int")
    def run(x: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series([None if p is None or q is None else lcs_length(list(p), list(q)) for p, q in zip(x, y, strict=True)], dtype="Int32")

    return run(a, b)


def gram_matches(a: list, b: list, most: int = 4) -> list[int]:
    """For runs of 1 to `most` words, how many of a's are in b, each of b's used once."""
    number: dict = {}
    for w in b:
        number.setdefault(w, len(number))
    x, y = (np.fromiter((number.get(w, -1) for w in ws), np.int64, len(ws)) for ws in (a, b))
    out, u, v = [], x, y
    for n in range(1, most + 1):
        if n > 1:  # runs are numbered anew by those of b, so that numbers stay small
            u, v = (np.where((g[:-1] >= 0) & (z[n - 1 :] >= 0), g[:-1] * len(number) + z[n - 1 :], -1) if len(z) >= n else np.zeros(0, np.int64) for g, z in ((u, x), (v, y)))
            kinds = np.unique(v)
            at = np.minimum(np.searchsorted(kinds, u), max(len(kinds) - 1, 0))
            u = np.where(kinds[at] == u, at, -1) if len(kinds) else np.full(len(u), -1)
            v = np.searchsorted(kinds, v)
        have, want = np.bincount(u[u >= 0], minlength=len(v) + 1), np.bincount(v, minlength=len(v) + 1)
        out.append(int(np.minimum(have[: len(want)], want[: len(have)]).sum()))
    return out


def edits(a: bytes, b: bytes) -> int:
    """Edits of single bytes. Of a text that holds the other's bytes in their order only the rest has to go; otherwise bit-parallel rows."""
    long, short = (a, b) if len(a) >= len(b) else (b, a)
    at = 0
    for k in range(len(short)):
        at = long.find(short[k : k + 1], at) + 1
        if not at:
            break
    else:
        return len(long) - len(short)
    where = [0] * 256
    for k, x in enumerate(short):
        where[x] |= 1 << k
    full, top = (1 << len(short)) - 1, 1 << len(short) - 1
    up, down, score = full, 0, len(short)
    for x in long:
        eq = where[x]
        xv, xh = eq | down, (((eq & up) + up) ^ up) | eq
        more, less = down | ~(xh | up) & full, up & xh
        score += 1 if more & top else -1 if less & top else 0
        more, less = (more << 1 | 1) & full, less << 1 & full
        up, down = less | ~(xv | more) & full, more & xv
    return score


def pair_counts(a: Column, b: Column) -> Column:
    """What the measures of two token arrays need, in one pass over whole texts: matches m1 to m4 of runs of words, lcs, and edits of the bytes of the joined words."""

    @F.pandas_udf("m1 int, m2 int, m3 int, m4 int, lcs int, lev int")
    def run(x: pd.Series, y: pd.Series) -> pd.DataFrame:
        out = []
        for p, q in zip(x, y, strict=True):
            if p is None or q is None:
                out.append((None,) * 6)
                continue
            u, v = p.split(), q.split()
            own = set(v)
            out.append((*gram_matches(u, v), lcs_length([w for w in u if w in own], v), edits(p.encode(), q.encode())))
        return pd.DataFrame(out, columns=["m1", "m2", "m3", "m4", "lcs", "lev"], dtype="Int32")

    joined = lambda c: F.when(c.isNotNull(), F.array_join(c, " "))
    return run(joined(a), joined(b))


def measures(a: Column, b: Column, counts: Column) -> dict[str, Column]:
    """BLEU (add_one), F1 of ROUGE-L and byte edits from pair_counts of the same arrays."""
    runs = [(counts[f"m{n}"], F.greatest(F.size(a) - (n - 1), F.lit(0))) for n in range(1, 5)]
    p, r = (counts["lcs"] / F.nullif(F.size(x), F.lit(0)) for x in (a, b))
    return {"bleu": _bleu(runs, F.size(a), F.size(b), "add_one"), "rouge": F.coalesce(2 * p * r / F.nullif(p + r, F.lit(0.0)), F.lit(0.0)), "lev": counts["lev"]}


def rouge_l(candidate: Column, reference: Column, native: bool = False) -> dict[str, Column]:
    """Precision, recall and F1 of the longest common subsequence of token arrays."""
    if native:  # words that only one side has can't be common
        own = lambda s: F.struct(F.filter(s["a"], lambda x: F.array_contains(s["b"], x)).alias("a"), s["b"].alias("b"))
        n = bind(bind(F.struct(candidate.alias("a"), reference.alias("b")), own), lambda s: lcs_native(s["a"], s["b"]))
    else:
        n = lcs(candidate, reference)

    def measured(s: Column) -> Column:
        p, r = s["n"] / F.nullif(s["a"], F.lit(0)), s["n"] / F.nullif(s["b"], F.lit(0))
        f = F.coalesce(2 * p * r / F.nullif(p + r, F.lit(0.0)), F.lit(0.0))
        return F.struct(F.coalesce(p, F.lit(0.0)).alias("p"), F.coalesce(r, F.lit(0.0)).alias("r"), f.alias("f"))

    sizes = F.struct(n.alias("n"), F.size(candidate).alias("a"), F.size(reference).alias("b"))
    if native:  # counted once, whatever is taken of it
        m = bind(sizes, measured)
        return {k: m[k] for k in "prf"}
    p, r = n / F.nullif(F.size(candidate), F.lit(0)), n / F.nullif(F.size(reference), F.lit(0))
    f = F.coalesce(2 * p * r / F.nullif(p + r, F.lit(0.0)), F.lit(0.0))
    return {"p": F.coalesce(p, F.lit(0.0)), "r": F.coalesce(r, F.lit(0.0)), "f": f}


def edit_distance(a: Column, b: Column, normal: bool = False, unit: str = "character") -> Column:
    """Single-character edits, or edits of UTF-8 bytes; normal: 1 for equal texts down to 0."""
    if unit == "byte":  # one character for each byte
        a, b = (F.decode(F.encode(x, "UTF-8"), "ISO-8859-1") for x in (a, b))
    d = F.levenshtein(a, b)
    return 1 - d / F.greatest(F.length(a), F.length(b), F.lit(1)) if normal else d


def embedscore(a: Column, b: Column, pooling: str = "greedy") -> Column:
    """Struct p, r, f of matching each token vector of one text with the nearest of the other (arrays of vectors).

    pooling "mean" compares the mean vectors instead. Empty sides give zeros.
    """

    @F.pandas_udf("p double, r double, f double")
    def run(x: pd.Series, y: pd.Series) -> pd.DataFrame:
        import numpy as np

        out = []
        for p, q in zip(x, y, strict=True):
            if p is None or q is None:
                out.append((None, None, None))
            elif len(p) == 0 or len(q) == 0:
                out.append((0.0, 0.0, 0.0))
            else:
                u, v = (np.array([list(w) for w in s], float) for s in (p, q))
                if pooling == "mean":
                    u, v = u.mean(0, keepdims=True), v.mean(0, keepdims=True)
                u, v = (w / np.maximum(np.linalg.norm(w, axis=1, keepdims=True), 1e-12) for w in (u, v))
                m = u @ v.T
                pr, re = float(m.max(1).mean()), float(m.max(0).mean())
                out.append((pr, re, 2 * pr * re / (pr + re) if pr + re else 0.0))
        return pd.DataFrame(out, columns=["p", "r", "f"])

    return run(a, b)


def text_vectors(words: Column, size: int = 64) -> Column:
    """Static stand-in token vectors: signed hashes of a word's character trigrams."""

    @F.pandas_udf("array<array<double>>")
    def run(x: pd.Series) -> pd.Series:
        import zlib

        import numpy as np

        def vector(w: str):
            v = np.zeros(size)
            for k in range(len(w) + 1):
                h = zlib.crc32(f"^{w}$"[k : k + 3].encode())
                v[h % size] += 1 if h >> 16 & 1 else -1
            return v.tolist()

        return x.map(lambda ws: None if ws is None else [vector(w) for w in ws])

    return run(words)
