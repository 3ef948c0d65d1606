"""Near-duplicates by Jaccard similarity against brute force, and the pipeline's stage on edited copies."""

import itertools
import random

import corpus_pipeline
import numpy as np
import pyarrow as pa
from pairverify.llm import shingles


def jaccard_parts(a: str, b: str) -> tuple[int, int]:
    def grams(text):
        w = text.split()
        return {tuple(w[i : i + 5]) for i in range(max(len(w) - 4, min(len(w), 1)))}

    x, y = grams(a), grams(b)
    return len(x & y), len(x | y)


def edited(seed: int = 3) -> list[str]:
    """Texts over few words, copies with 0 to 3 words changed, and texts that share a long common ending."""
    rng = random.Random(seed)
    words = [f"w{k}" for k in range(300)]
    notice, out = rng.choices(words, k=40), ["", "  ", "one two", "one two", "a b c d e"]
    for _ in range(40):
        base = rng.choices(words, k=rng.randint(6, 160)) + (notice if rng.random() < 0.4 else [])
        out.append(" ".join(base))
        for _ in range(rng.randint(0, 3)):
            copy = list(base)
            for _ in range(rng.randint(0, 3)):
                copy[rng.randrange(len(copy))] = rng.choice(words)
            out.append(" ".join(copy[: len(copy) - rng.randint(0, 3)]))
    rng.shuffle(out)
    return out


def smallest(texts: list[str]) -> dict[int, int]:
    root = list(range(len(texts)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, j in itertools.combinations(range(len(texts)), 2):
        shared, either = jaccard_parts(texts[i], texts[j])
        if 5 * shared >= 4 * either:
            a, b = find(i), find(j)
            root[max(a, b)] = min(a, b)
    return {i: find(i) for i in range(len(texts))}


def test_stage_drops_edited_copies(spark, sf):
    texts = edited()
    want = smallest(texts)
    exact = {i: texts.index(t) for i, t in enumerate(texts)}
    assert sum(want[i] != i for i in want) > sum(exact[i] != i for i in exact) + 10
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(5)
    got = {r.doc_id: r.component_id for r in shingles.near_duplicates(docs).collect()}
    assert got == want
    kept = corpus_pipeline.drop_near_duplicates(spark, docs, sf)
    assert sorted(r.doc_id for r in kept.collect()) == [i for i in want if want[i] == i]


def test_stage_on_rows_without_words_or_id(spark, sf):
    ten = "a b c d e f g h i j k l m n o p q r s t"
    docs = spark.createDataFrame([(1, None), (2, ""), (3, ten), (None, ten), (4, ten + " u"), (5, "x y")], "doc_id long, text string")
    assert sorted((r.doc_id or 0) for r in corpus_pipeline.drop_near_duplicates(spark, docs, sf).collect()) == [0, 1, 3, 5]
    assert corpus_pipeline.drop_near_duplicates(spark, docs.limit(0), sf).count() == 0


def test_candidates_do_not_depend_on_counts():
    rng = np.random.default_rng(0)
    sets = [np.unique(rng.integers(0, 60, rng.integers(1, 40)).astype(np.uint64)) for _ in range(150)]
    sets += [np.delete(s, rng.integers(0, len(s))) for s in sets if len(s) > 5]
    cuts, h = np.append(0, np.cumsum([len(s) for s in sets])), np.concatenate(sets)
    alike = {(i, j) for i, j in itertools.combinations(range(len(sets)), 2) if 5 * len(np.intersect1d(sets[i], sets[j])) >= 4 * len(np.union1d(sets[i], sets[j]))}
    for level in (np.zeros(64, np.uint8), rng.integers(0, 9, 64).astype(np.uint8)):
        row, place, token = shingles.prefixes(cuts, h, level, (4, 5))
        found = set()
        for a, b in shingles.candidates(token, row, np.diff(cuts)[row], place, (4, 5), chunk=50):
            found |= set(zip(a.tolist(), b.tolist(), strict=True))
        assert len(alike) > 50 and alike <= found


def test_sketches_never_exceed_the_difference_of_sets():
    rng = np.random.default_rng(1)
    sets = [np.unique(rng.integers(0, 1 << 63, n).astype(np.uint64)) for n in (0, 1, 5, 63, 64, 65, 300, 1000, 5000, 50_000)]
    sets += [np.append(s[rng.random(len(s)) < share], np.arange(k, dtype=np.uint64) << np.uint64(30)) for s in sets for share, k in ((1.0, 0), (0.97, 3), (0.5, 40), (0.0, 0))]
    cuts = np.append(0, np.cumsum([len(s) for s in sets]))
    bits = shingles.set_sketches(cuts, np.concatenate(sets))
    assert {len(b) for b in bits} <= {8 << k for k in range(10)}
    pairs = list(itertools.product(range(len(sets)), repeat=2))
    x, y = (pa.array([bits[p[side]] for p in pairs], pa.binary()) for side in (0, 1))
    least = shingles.least_difference(x, y, chunk=100)
    apart = np.array([len(np.setxor1d(sets[i], sets[j])) for i, j in pairs])
    assert (least <= apart).all() and (least[apart == 0] == 0).all()
    small = apart <= 2
    assert (least[~small] > 0).mean() > 0.95
    assert (shingles.least_difference(x.slice(7, 50), y.slice(7, 50)) == least[7:57]).all()


def test_folded_sketches_leave_out_near_copies_that_are_not_alike():
    """Copies of one text with two words changed share rare members by pairs; few of those pairs become rows, and none alike is lost."""
    rng = random.Random(8)
    base, texts = [f"b{k}" for k in range(60)], []
    for k in range(400):
        own = list(base)
        for at in rng.sample(range(60), 1 + k % 2):
            own[at] = f"x{rng.randrange(3)}"
        texts.append(" ".join(own))
    texts = sorted(set(texts))
    ((_, cuts, h),) = shingles.shingle_sets(pa.array(texts), 5)
    size, key = np.diff(cuts), np.arange(len(texts))
    brief = shingles.brief_words(pa.array(shingles.set_sketches(cuts, h), pa.binary()))
    row = np.repeat(key, size)
    token, place = h.view(np.int64), np.zeros(len(row), np.int64)  # every shingle, as though all were among the first
    pairs = lambda brief: {p for a, b in shingles.candidates(token, row, size[row], place, (4, 5), own=row, brief=brief) for p in zip(a.tolist(), b.tolist(), strict=True)}
    plain, left = pairs(None), pairs(brief[row])
    parts = {p: jaccard_parts(texts[p[0]], texts[p[1]]) for p in plain}
    alike = {p for p, (n, m) in parts.items() if 5 * n >= 4 * m}
    assert alike <= left < plain and len(alike) > 100 and len(left) - len(alike) < (len(plain) - len(alike)) // 20
    a, b = np.arange(len(texts) - 1), np.arange(1, len(texts))
    difference = np.array([len(set(h[cuts[x] : cuts[x + 1]].tolist()) ^ set(h[cuts[y] : cuts[y + 1]].tolist())) for x, y in zip(a, b, strict=True)])
    assert (np.bitwise_count(brief[a] ^ brief[b]).sum(axis=1) <= difference).all()
    wide = shingles.set_sketches(np.array([0, 5000]), np.sort(np.random.default_rng(1).integers(0, 1 << 63, 5000).astype(np.uint64)))
    assert shingles.brief_words(pa.array(wide, pa.binary())).shape == (1, shingles.BRIEF)
