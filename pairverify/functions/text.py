"""Native text columns: tokens, n-grams, portable hash buckets and md5-ordered samples."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def tokens(text: Column) -> Column:
    """Lower-case runs of letters and digits; null gives no tokens."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(r"[\p{L}\p{N}]+"), F.lit(0))


def bind(value: Column, then) -> Column:
    """then(value) with value computed once, where then uses it within functions over array elements."""
    return F.element_at(F.transform(F.array(value), then), 1)


def ngrams(words: Column, n: int) -> Column:
    """Runs of n words joined by a space; none if there are fewer words."""
    grams = lambda w: F.transform(F.sequence(F.lit(1), F.size(w) - (n - 1)), lambda i: F.array_join(F.slice(w, i, n), " "))
    return F.when(F.size(words) >= n, bind(words, grams)).otherwise(F.array().cast("array<string>"))


def bucket(text: Column, size: int) -> Column:
    """A number below size from the first eight hexadecimal digits of the md5; the same in other engines."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("bigint") % size


def md5_share(key: Column) -> Column:
    """A number in [0, 1) from a key, in whose order samples are drawn."""
    return F.conv(F.substring(F.md5(key.cast("string")), 1, 8), 16, 10).cast("double") / float(1 << 32)


def sample_md5(df: DataFrame, key: str, n: int, total: int | None = None) -> DataFrame:
    """The n rows whose keys come first in md5 order. With a known total, most rows go before the ordered limit."""
    digest = F.md5(F.col(key).cast("string"))
    if total and total > 4 * n:
        df = df.where(md5_share(F.col(key)) < min(1.0, 4.0 * n / total + 1e-3))
    return df.orderBy(digest, key).limit(n)


def sigmoid(x: Column) -> Column:
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-x))


def cosine(a: Column, b: Column, affine: bool = False) -> Column:
    """Cosine of two arrays brought into [0, 1]: negative ones count as 0, or (1 + cosine) / 2. Zero vectors score 0."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    c = dot(a, b) / F.nullif(F.sqrt(dot(a, a) * dot(b, b)), F.lit(0.0))
    c = F.when(F.size(a) != F.size(b), F.raise_error(F.lit("vectors of different lengths"))).otherwise(c)
    c = (c + 1) / 2 if affine else F.greatest(c, F.lit(0.0))
    return F.when(a.isNotNull() & b.isNotNull(), F.coalesce(c, F.lit(0.0)))
