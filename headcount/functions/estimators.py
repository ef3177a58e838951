"""The estimator of the number of entities: weights of observed components, recovered counts, variance, and their properties.

An entity with i records is a clique; the sample keeps each of its edges with probability p. With q = 1 - p, a pair stays whole
with p; a triple stays whole with p^2 (3 - 2p), loses one record with 3 p q^2 and falls apart with q^3. Inverting these counts
gives the estimate as a weighted sum over the sizes of observed components. Sizes beyond the exact ones count once each.
"""

from __future__ import annotations

from collections.abc import Mapping
from fractions import Fraction
from math import comb

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Number = float | Fraction


# --- scalars (floats or exact fractions) -----------------------------------------------------------------------------


def connected_probability(n: int, p: Number) -> Number:
    """That a random graph of n vertices, each edge there with probability p, is connected."""
    q, c = 1 - p, [0 * p, 1 + 0 * p]
    for m in range(2, n + 1):
        c.append(1 - sum(comb(m - 1, j - 1) * c[j] * q ** (j * (m - j)) for j in range(1, m)))
    return c[n]


def breakage(k: int, p: Number) -> list[Number]:
    """Expected number of components of size 1..k that a clique of k leaves."""
    q = 1 - p
    return [comb(k, j) * connected_probability(j, p) * q ** (j * (k - j)) for j in range(1, k + 1)]


def component_weights(p: Number, max_exact: int = 3) -> list[Number]:
    """Weights of observed components of size 1..max_exact: a triangular solve that makes every clique up to that size count
    one on average. At 3 this is the published estimator. Unstable for small p."""
    w: list[Number] = []
    for k in range(1, max_exact + 1):
        e = breakage(k, p)
        w.append((1 - sum(x * y for x, y in zip(e, w, strict=False))) / e[-1])
    return w


def expected_histogram(true: Mapping[int, Number], p: Number) -> dict[int, Number]:
    """Expected observed counts by size. Sizes of 4 and more are taken to survive."""
    t = {k: true.get(k, 0) for k in {1, 2, 3, *true}}
    one, two, three = breakage(1, p), breakage(2, p), breakage(3, p)
    out = dict(t)
    out[1] = t[1] * one[0] + t[2] * two[0] + t[3] * three[0]
    out[2] = t[2] * two[1] + t[3] * three[1]
    out[3] = t[3] * three[2]
    return out


def recover_counts(seen: Mapping[int, Number], p: Number) -> dict[int, Number]:
    """Back-substitution from observed to true counts; negative values are kept."""
    two, three = breakage(2, p), breakage(3, p)
    n3 = seen.get(3, 0) / three[2]
    n2 = (seen.get(2, 0) - three[1] * n3) / two[1]
    n1 = seen.get(1, 0) - two[0] * n2 - three[0] * n3
    return {1: n1, 2: n2, 3: n3}


def estimate(seen: Mapping[int, Number], p: Number, max_exact: int = 3) -> Number:
    w = component_weights(p, max_exact)
    return sum(n * (w[k - 1] if k <= max_exact else 1) for k, n in seen.items())


def variance(n2: Number, n3: Number, p: Number) -> Number:
    """Closed form for true counts of pairs and triples."""
    q = 1 - p
    return n3 * q**2 * (3 * p**2 - p + 1) / (p**2 * (3 - 2 * p)) + n2 * q / p


def variance_slope(n2: float, n3: float, p: float, step: float = 1e-6) -> float:
    return (variance(n2, n3, p + step) - variance(n2, n3, p - step)) / (2 * step)


def variance_gain(p_adaptive: float, p_random: float, n2: float, n3: float) -> float:
    """How many times smaller the variance is at the recall of adaptive sampling."""
    return variance(n2, n3, p_random) / variance(n2, n3, p_adaptive)


def retrieval_probability(j: Number, k: int, tables: int) -> Number:
    return 1 - (1 - j**k) ** tables


def similarity_at(probability: float, k: int, tables: int) -> float:
    return (1 - (1 - probability) ** (1 / tables)) ** (1 / k)


def random_recall(m: int, n_records: int) -> float:
    """Share of all pairs in a uniform sample of m pairs."""
    return 2 * m / (n_records * (n_records - 1))


# --- Columns ---------------------------------------------------------------------------------------------------------


def weight(size: Column, p: Column) -> Column:
    """Published weights as an expression: 1, (2p - 1) / p, (1 - 6 p q^2) / (p^2 (3 - 2p)), then 1."""
    q = 1 - p
    return F.when(size == 2, (2 * p - 1) / p).when(size == 3, (1 - 6 * p * q * q) / (p * p * (3 - 2 * p))).otherwise(F.lit(1.0))


def weight_upto(size: Column, p: float, max_exact: int) -> Column:
    w = component_weights(p, max_exact)
    out = F.when(F.lit(False), F.lit(0.0))
    for k, x in enumerate(w, 1):
        out = out.when(size == k, F.lit(float(x)))
    return out.otherwise(F.lit(1.0))


def with_errors(row: DataFrame) -> DataFrame:
    """Adds estimate, variance, sd, bounds and status to rows of (p, s1, s2, s3, s_rest): observed components by size.

    p null: no estimate, ``undefined``. p below one half: ``low_p`` (pairs get a negative weight). Recovered counts below 0 stay in
    the estimate and are 0 in the variance."""
    p = F.when(F.col("p") > 0, F.col("p"))
    q = 1 - p
    n3 = F.col("s3") / (p * p * (3 - 2 * p))
    n2 = (F.col("s2") - 3 * p * q * q * n3) / p
    row = row.withColumn("n3", n3).withColumn("n2", n2)
    est = F.col("s1") + F.col("s2") * weight(F.lit(2), p) + F.col("s3") * weight(F.lit(3), p) + F.col("s_rest")
    var = F.greatest("n3", F.lit(0.0)) * q * q * (3 * p * p - p + 1) / (p * p * (3 - 2 * p)) + F.greatest("n2", F.lit(0.0)) * q / p
    row = row.withColumn("estimate", est).withColumn("variance", var).withColumn("sd", F.sqrt(var))
    row = row.withColumn("lo", F.col("estimate") - 1.96 * F.col("sd")).withColumn("hi", F.col("estimate") + 1.96 * F.col("sd"))
    status = F.when(p.isNull(), "undefined").when(p < 0.5, "low_p").when((F.col("n2") < 0) | (F.col("n3") < 0), "negative_counts").otherwise("ok")
    return row.withColumn("status", status)


def with_total_error(row: DataFrame, step: float = 1e-5) -> DataFrame:
    """Adds sd_p, the part of the error that comes from measuring p on ``n_labelled`` matches with ``hits`` in the sample, and
    sd_total with the closed form, which the bounds then follow. The share is shrunk by half a match, so that a p of 1 on few matches is not taken for
    certain; its error goes through the slope of the estimate in p."""
    shrunk = (F.col("hits") + 0.5) / (F.col("n_labelled") + 1)
    se = F.sqrt(shrunk * (1 - shrunk) / F.col("n_labelled"))
    at = lambda p: F.col("s2") * weight(F.lit(2), p) + F.col("s3") * weight(F.lit(3), p)
    slope = (at(F.col("p") + step) - at(F.col("p") - step)) / (2 * step)
    row = row.withColumn("sd_p", F.abs(slope) * se)
    row = row.withColumn("sd_total", F.sqrt(F.col("variance") + F.col("sd_p") * F.col("sd_p")))
    return row.withColumn("lo", F.col("estimate") - 1.96 * F.col("sd_total")).withColumn("hi", F.col("estimate") + 1.96 * F.col("sd_total"))
