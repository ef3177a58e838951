"""Competing estimates of the number of entities under the same budget of pair queries.

The published formulas of two of them are not at hand; what stands here are reconstructions, variants side by side.
"""

from __future__ import annotations

from math import isqrt

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from headcount.functions.estimators import random_recall
from headcount.sources.pairsource import shuffled_ranks
from headcount.sources.shipping import ship
from headcount.sources.storage import stored

from .components import components_auto
from .labelling import label_by_truth
from .observed import histogram_row, size_histogram
from .sampling import dense_index


def seeded(id_col: str, seed: int) -> Column:
    """Portable order of records: 32 bits of the MD5 of id and seed."""
    s = F.concat_ws(",", F.col(id_col).cast("string"), F.lit(str(seed)))
    return F.conv(F.substring(F.md5(s.cast("binary")), 1, 8), 16, 10).cast("long")


def drawn_matches(df: DataFrame, id_col: str, entity: str, m: int, seed: int = 42) -> DataFrame:
    """(id_a, id_b): the true pairs among m distinct pairs drawn uniformly, by the place of each in a keyed order of all pairs."""
    ship(df.sparkSession)
    n = df.count()
    total = n * (n - 1) // 2

    @F.pandas_udf("boolean")
    def drawn(i: pd.Series, j: pd.Series) -> pd.Series:
        x, y = np.minimum(i.to_numpy(), j.to_numpy()), np.maximum(i.to_numpy(), j.to_numpy())
        return pd.Series(shuffled_ranks(y * (y - 1) // 2 + x, total, seed) < m)

    places = dense_index(df, id_col)
    t = df.select(F.col(id_col).alias("r"), F.col(entity).alias("e"))
    several = t.join(t.groupBy("e").agg(F.count("*").alias("_n")).where("_n > 1").select("e"), "e", "left_semi")
    t = stored(several.join(places.select("idx", F.col(id_col).alias("r")), "r"), "places")
    x, y = t.alias("x"), t.alias("y")
    pairs = x.join(y, (F.col("x.e") == F.col("y.e")) & (F.col("x.r") < F.col("y.r")))
    return pairs.where(drawn("x.idx", "y.idx")).select(F.col("x.r").alias("id_a"), F.col("y.r").alias("id_b"))


def uniform_pair_estimate(df: DataFrame, id_col: str, entity: str, m: int, seed: int = 42) -> DataFrame:
    """The non-adaptive twin: m uniform pairs, then the same estimator with p = 2 m / (M (M - 1)). Without a sampled match
    the formula gives M (``no_match``): measured on labelled pairs, p would be undefined.

    The sample is never listed: it holds the m pairs that come first in a keyed order of all pairs, and true pairs are asked for theirs."""
    from headcount.functions.estimators import with_errors

    n = df.count()
    matched = stored(drawn_matches(df, id_col, entity, m, seed), "drawn")
    h = size_histogram(components_auto(matched), n)
    row = with_errors(histogram_row(h).withColumn("p", F.lit(random_recall(m, n))))
    return row.withColumn("status", F.when(F.col("s1") == F.col("m_records"), "no_match").otherwise(F.col("status")))


def subgraph_size(m: int) -> int:
    """Most vertices whose pairs fit a budget of m queries."""
    return (1 + isqrt(1 + 8 * m)) // 2


def subgraph_estimate(df: DataFrame, id_col: str, entity: str, m: int, seed: int = 42, variant: str = "transitive") -> DataFrame:
    """v records by least seeded hash (a top-k), all their pairs queried; classes of k of them extrapolated:

    ``transitive`` 1 - (-1)^k prod_{i<k} (M - v + i) / (v - i), unbiased for disjoint cliques, of explosive variance;
    ``forest`` M - matches * M (M - 1) / (v (v - 1)), low once cliques exceed two;
    ``scale`` classes * M / v.
    """
    n = df.count()
    v = min(subgraph_size(m), n)
    chosen = df.select(id_col, entity).orderBy(seeded(id_col, seed), id_col).limit(v)
    k = chosen.groupBy(entity).agg(F.count("*").alias("k"))
    if variant == "transitive":
        prod = F.aggregate(F.sequence(F.lit(0), F.col("k").cast("int") - 1), F.lit(1.0), lambda a, i: a * (F.lit(float(n - v)) + i) / (F.lit(float(v)) - i))
        return k.agg(F.sum(1 - F.when(F.col("k") % 2 == 0, 1.0).otherwise(-1.0) * prod).alias("estimate"))
    if variant == "forest":
        return k.agg((F.lit(float(n)) - F.sum(F.col("k") * (F.col("k") - 1) / 2) * (float(n) * (n - 1) / (float(v) * (v - 1)))).alias("estimate"))
    return k.agg((F.count("*") * float(n) / v).alias("estimate"))


def expansions(n: int, m: int) -> tuple[int, int]:
    """How many records of n can be compared with all others for m distinct queries, and what is left of the budget."""
    r, left = 0, m
    while r < n and left >= n - 1 - r:
        left -= n - 1 - r
        r += 1
    return r, left


def vertex_bfs_estimate(df: DataFrame, id_col: str, entity: str, m: int, seed: int = 42, partial: str = "use", max_component: int | None = None) -> DataFrame:
    """Mean of 1 / (size of the component) over random starts, times M. Expanding a record asks for all others; with cliques
    the component of a start is known after one expansion. Starts follow the seeded order until the budget is spent; the
    interrupted start sees the first records of that order only, and is used (``use``), used beside finished starts only
    (``beside``) or dropped (``drop``).

    All starts expand in one aggregation: the frontier is bounded by the budget (a few records for budgets below M)."""
    n = df.count()
    r, left = expansions(n, m)
    order = F.row_number().over(Window.orderBy(seeded(id_col, seed), id_col))  # over the top few only
    starts = df.select(id_col, entity).orderBy(seeded(id_col, seed), id_col).limit(r + 1).withColumn("o", order)
    seen_cut = df.select(F.col(id_col).alias("_i"), F.col(entity).alias("_e"))
    full = starts.where(F.col("o") <= r).join(seen_cut, F.col(entity) == F.col("_e")).groupBy(id_col).agg((1.0 / F.count("*")).alias("x"))
    parts = full.select("x")
    if (partial == "use" or partial == "beside" and r > 0) and left > 0 and r < n:
        seen = df.select(F.col(id_col).alias("_i"), F.col(entity).alias("_e")).orderBy(seeded(id_col, seed), id_col).limit(left + 1 + r)
        cut = starts.where(F.col("o") == r + 1).join(seen, F.col(entity) == F.col("_e")).groupBy(id_col).agg((1.0 / F.count("*")).alias("x"))
        parts = parts.union(cut.select("x"))
    if max_component:  # components above that size count 0
        parts = parts.select(F.when(F.col("x") >= 1.0 / max_component, F.col("x")).otherwise(0.0).alias("x"))
    row = parts.agg((F.avg("x") * n).alias("estimate"), F.count("*").alias("starts"))
    return row.withColumn("status", F.when(F.col("starts") == 0, "undefined").otherwise("ok"))


def observed_count(pairs: DataFrame, truth: DataFrame, id_col: str, entity: str) -> DataFrame:
    """No correction: components of the sampled graph (blocking with any sampler, then resolving)."""
    matched = label_by_truth(pairs, truth, id_col, entity).where("is_match").select("id_a", "id_b")
    return size_histogram(components_auto(matched), truth.count()).agg(F.sum("n").alias("estimate"))


def exact_entity_count(df: DataFrame, entity: str) -> DataFrame:
    return df.agg(F.countDistinct(entity).alias("estimate"))


def distinct_text_count(df: DataFrame, text: Column | str, approximate: bool = False, rsd: float = 0.02) -> DataFrame:
    """What a naive user would do."""
    return df.agg((F.approx_count_distinct(text, rsd) if approximate else F.countDistinct(text)).alias("estimate"))


def threshold_count(similarities: DataFrame, n_records: int, theta: float) -> DataFrame:
    """Entities if every pair of at least this similarity is taken for a match."""
    edges = similarities.where(F.col("similarity") >= theta).select("id_a", "id_b")
    return size_histogram(components_auto(edges), n_records).agg(F.sum("n").alias("estimate")).withColumn("theta", F.lit(theta))
