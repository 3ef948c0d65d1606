"""The package's functions for SQL users."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def register(spark: SparkSession) -> None:
    """SQL functions lcs_length(a, b), canonical_sha(query), ask(query) and the table functions ngrams and perturbations."""
    from pairverify.functions.similarity import lcs_length
    from pairverify.operators.translate import ship
    from pairverify.plans import querytext

    ship()
    @F.pandas_udf("int")
    def lcs(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([lcs_length(list(x), list(y)) for x, y in zip(a, b, strict=True)])

    @F.pandas_udf("string")
    def sha(a: pd.Series) -> pd.Series:
        return a.map(querytext.canonical_sha, na_action="ignore")

    @F.pandas_udf("string")
    def ask(a: pd.Series) -> pd.Series:
        return a.map(lambda x: querytext.question(querytext.parse(x)), na_action="ignore")

    @F.udtf(returnType="pos int, gram string")
    class Grams:
        def eval(self, text: str, n: int):
            words = re.findall(r"[^ \t\n\x0b\f\r]+", text or "")
            for k in range(len(words) - n + 1):
                yield k, " ".join(words[k : k + n])

    @F.udtf(returnType="kind string, text string")
    class Twins:
        def eval(self, query: str):
            q = querytext.parse(query)
            for kind in querytext.WRONG:
                if twin := querytext.wrong_twin(q, kind):
                    yield kind, querytext.question(twin)

    spark.udf.register("lcs_length", lcs)
    spark.udf.register("canonical_sha", sha)
    spark.udf.register("ask", ask)
    spark.udtf.register("ngrams", Grams)
    spark.udtf.register("perturbations", Twins)
