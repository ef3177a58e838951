"""SQL functions: expression functions, an Arrow scalar function, table functions, and the estimate as an aggregate."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from headcount.sources.shipping import ship

from .hashing import coefficients, signature
from .shingles import PRIME


class _Grams:
    """Character grams of a text, one row each."""

    def eval(self, text: str, k: int) -> Iterator[tuple[str]]:
        if not text:
            return
        seen = dict.fromkeys(text[i : i + k] for i in range(max(1, len(text) - k + 1)))
        for g in seen:
            yield (g,)


class _DecodePair:
    """The pair (i, j) of a rank in the space of all pairs."""

    def eval(self, rank: int) -> Iterator[tuple[int, int]]:
        from math import isqrt

        j = (1 + isqrt(1 + 8 * rank)) // 2
        yield rank - j * (j - 1) // 2, j


class _BucketRows:
    """The L bucket keys of a token set in the portable form, one row per table; none for an empty set."""

    def __init__(self):
        self.known = {}

    def eval(self, rec_id: int, tokens: list[int], k: int, l: int, seed: int) -> Iterator[tuple[int, int, int]]:  # noqa: E741
        if not tokens:
            return
        if (k, l, seed) not in self.known:
            self.known[k, l, seed] = np.array(coefficients(seed, k * l), np.int64)
        c = self.known[k, l, seed]
        t = np.asarray(tokens, np.int64)
        least = [int(((a * t + b) % PRIME).min()) for a, b in c]
        for tbl in range(l):
            key = tbl + 1
            for m in least[tbl * k : (tbl + 1) * k]:
                key = (key * 1_000_003 + m) % PRIME
            yield rec_id, tbl, key


_SQL = (
    "CREATE OR REPLACE TEMPORARY FUNCTION retrieval_probability(j DOUBLE, k INT, l INT) RETURNS DOUBLE RETURN 1 - power(1 - power(j, k), l)",
    "CREATE OR REPLACE TEMPORARY FUNCTION set_jaccard(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS DOUBLE RETURN CASE WHEN size(a) + size(b) = 0 THEN 1.0D ELSE size(array_intersect(a, b)) / size(array_union(a, b)) END",
    "CREATE OR REPLACE TEMPORARY FUNCTION component_weight(s BIGINT, p DOUBLE) RETURNS DOUBLE RETURN CASE WHEN s = 2 THEN (2 * p - 1) / p WHEN s = 3 THEN (1 - 6 * p * (1 - p) * (1 - p)) / (p * p * (3 - 2 * p)) ELSE 1.0D END",
)


def entity_estimate_udaf():
    """The estimate as a grouped aggregate for any exact size; plain ``sum(n * component_weight(size, p))`` for the published
    one needs no Python."""
    @pandas_udf("double")
    def entity_estimate(size: pd.Series, n: pd.Series, p: pd.Series) -> float:
        from headcount.functions.estimators import estimate

        hist = n.groupby(size).sum()
        return float(estimate({int(k): float(v) for k, v in hist.items()}, float(p.iloc[0]))) if len(size) else None

    return entity_estimate


def register(spark: SparkSession) -> None:
    ship(spark)
    for s in _SQL:
        spark.sql(s)
    spark.udtf.register("grams", udtf(_Grams, returnType="gram string"))
    spark.udtf.register("bucket_rows", udtf(_BucketRows, returnType="id long, tbl int, key long"))
    spark.udtf.register("decode_pair", udtf(_DecodePair, returnType="i long, j long"))
    spark.udf.register("minhash_signature", signature(16))
    spark.udf.register("entity_estimate", entity_estimate_udaf())
