"""Families of locality-sensitive hashes: min-wise, one-permutation with densification, sign projections.

``portable`` forms are built-in functions with residues modulo a prime, and have SQL twins; ``native`` forms are numpy
kernels over Arrow batches: one pass per record, n + B steps for one permutation instead of n * B.
"""

from __future__ import annotations

import random

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .shingles import PRIME, Texts, col, let


def coefficients(seed: int, n: int) -> list[tuple[int, int]]:
    """n pairs (a, b) with 0 < a < prime and 0 <= b < prime; longer lists begin with the shorter ones."""
    rng = random.Random(seed)
    return [(rng.randrange(1, PRIME), rng.randrange(PRIME)) for _ in range(n)]


def affine(x: Column, a: int, b: int) -> Column:
    return (F.lit(a).cast("long") * x + F.lit(b).cast("long")) % PRIME


def minhash(tokens: Texts, b: int, seed: int = 42) -> Column:
    """b independent minima of a set of portable numbers (null for an empty set)."""
    t = col(tokens)

    def least(a: int, c: int) -> Column:
        return F.array_min(F.transform(t, lambda x: affine(x, a, c)))

    return F.when(F.size(t) > 0, F.array(*(least(*c) for c in coefficients(seed, b))))


def one_permutation(tokens: Texts, b: int, seed: int = 42) -> Column:
    """b bins of one permutation; a bin holds the least value in it, empty bins are null."""
    (a, c), *_ = coefficients(seed, 1)
    h = F.transform(col(tokens), lambda x: affine(x, a, c))
    bins = lambda v: F.transform(F.sequence(F.lit(0), F.lit(b - 1)), lambda j: F.array_min(F.transform(F.filter(v, lambda x: x % b == j), lambda x: F.floor(x / b))))
    return let(h, bins)


def rotated(bins: Texts, b: int) -> Column:
    """Densification by rotation: an empty bin borrows from the next filled one, plus its distance times the range."""
    s = col(bins)
    step = PRIME // b + 1

    def borrow(x):
        far = F.transform(F.sequence(F.lit(0), F.lit(b - 1)), lambda d: F.struct(d.alias("d"), d.alias("i")))
        own = lambda j: F.filter(F.transform(far, lambda d: F.struct(d["d"].alias("d"), F.get(x, (j + d["d"]) % b).alias("v"))), lambda d: d["v"].isNotNull())
        return F.transform(F.sequence(F.lit(0), F.lit(b - 1)), lambda j: let(F.get(own(j), F.lit(0)), lambda d: d["v"] + d["d"] * step))

    return F.when(F.exists(s, lambda v: v.isNotNull()), let(s, borrow))


def equal_share(a: Texts, b: Texts) -> Column:
    """Share of equal positions of two signatures: estimates the Jaccard similarity, with error sqrt(J (1 - J) / B)."""
    same = F.zip_with(col(a), col(b), lambda x, y: (x == y).cast("int"))
    return F.aggregate(same, F.lit(0), lambda s, x: s + F.coalesce(x, F.lit(0))) / F.size(col(a))


# --- numpy kernels --------------------------------------------------------------------------------------------------

_M = (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB)  # multipliers of a public 64-bit mixer


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    z = x.astype(np.uint64) + np.uint64((salt * _M[0] + _M[0]) % 2**64)
    z = (z ^ (z >> np.uint64(30))) * np.uint64(_M[1])
    z = (z ^ (z >> np.uint64(27))) * np.uint64(_M[2])
    return z ^ (z >> np.uint64(31))


EMPTY = np.uint64(2**64 - 1)


def bins_of(tokens: np.ndarray, b: int, seed: int) -> np.ndarray:
    """One permutation: least hash in each of b bins."""
    out = np.full(b, EMPTY, np.uint64)
    if len(tokens):
        h = mix(tokens.view(np.uint64) if tokens.dtype == np.int64 else tokens, seed)
        np.minimum.at(out, (h >> np.uint64(32)) % np.uint64(b), h)
    return out


def densified(bins: np.ndarray, how: str, seed: int = 42) -> np.ndarray:
    """Fills empty bins. ``rotation``: next filled bin to the right plus an offset by distance; ``two_way``: left or right by a
    bit of the bin; ``probe``: bins tried in an order of their own by a universal hash until one is filled; ``none``."""
    empty = np.flatnonzero(bins == EMPTY)
    b = len(bins)
    if how == "none" or not len(empty) or len(empty) == b:
        return bins
    out = bins.copy()
    if how == "probe":
        at, todo, attempt = np.zeros(b, np.int64), empty, 0
        while len(todo):
            attempt += 1
            at[todo] = (mix(todo.astype(np.uint64) * np.uint64(1_000_003) + np.uint64(attempt), seed + 1) % np.uint64(b)).astype(np.int64)
            todo = todo[bins[at[todo]] == EMPTY]
        out[empty] = bins[at[empty]]
        return out
    filled = np.flatnonzero(bins != EMPTY)
    right = filled[np.searchsorted(filled, empty) % len(filled)]
    source, far = right, (right - empty) % b
    if how == "two_way":
        left = filled[np.searchsorted(filled, empty) - 1]
        go_left = (mix(empty.astype(np.uint64), seed + 2) & np.uint64(1)).astype(bool)
        source = np.where(go_left, left, right)
        far = np.where(go_left, (empty - left) % b + b, far)
    out[empty] = mix(bins[source] + far.astype(np.uint64), seed + 3)
    return out


def probed_rows(tokens: np.ndarray, lengths: np.ndarray, b: int, seed: int) -> np.ndarray:
    """Signatures of many sets at once (a row each), densified by probing: what :func:`bins_of` and :func:`densified` give set by
    set, with one pass over all tokens and one step per attempt for all empty bins."""
    n = len(lengths)
    h = mix(tokens.view(np.uint64), seed)
    out = np.full(n * b, EMPTY, np.uint64)
    row = np.repeat(np.arange(n, dtype=np.int64), lengths)
    np.minimum.at(out, row * b + ((h >> np.uint64(32)) % np.uint64(b)).astype(np.int64), h)
    todo = np.flatnonzero((out == EMPTY) & np.repeat(lengths > 0, b))
    filled, attempt = out.copy(), 0
    while len(todo):
        attempt += 1
        place = mix(np.arange(b, dtype=np.uint64) * np.uint64(1_000_003) + np.uint64(attempt), seed + 1) % np.uint64(b)
        found = out[todo - todo % b + place[todo % b].astype(np.int64)]
        filled[todo] = found
        todo = todo[found == EMPTY]
    return filled.reshape(n, b)


def minima_of(tokens: np.ndarray, b: int, seed: int) -> np.ndarray:
    """b independent minima."""
    if not len(tokens):
        return np.full(b, EMPTY, np.uint64)
    x = tokens.view(np.uint64)
    return np.array([mix(x, seed * 1_000 + s).min() for s in range(b)], np.uint64)


def minima_of_sets(tokens: np.ndarray, lengths: np.ndarray, b: int, seed: int) -> np.ndarray:
    """The same for many sets at once, a row each: a pass over all tokens per minimum instead of a call per set and minimum."""
    out = np.full((len(lengths), b), EMPTY, np.uint64)
    full = lengths > 0
    start = (np.cumsum(lengths) - lengths)[full]
    x = tokens.view(np.uint64)
    for s in range(b if len(start) else 0):
        out[full, s] = np.minimum.reduceat(mix(x, seed * 1_000 + s), start)
    return out


def distinct(a: np.ndarray) -> np.ndarray:
    """Sorted values without repeats, by sorting: ``np.unique`` of numpy 2.3 puts whole numbers through a hash table first, at 20 times the cost."""
    a = np.sort(a)
    return a[np.flatnonzero(np.concatenate([[True], a[1:] != a[:-1]]))] if len(a) else a


def grams_of(text: str, k: int) -> np.ndarray:
    """Sorted distinct 64-bit numbers of the k-grams of a text (of the text itself, if shorter): a polynomial over code points,
    mixed; one step a character and gram place."""
    c = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    n = len(c) - k + 1
    width = k if n > 0 else len(c)
    h = c[: max(n, min(1, len(c)))].copy()
    for i in range(1, width):
        h = h * np.uint64(_M[0]) + c[i : i + len(h)]
    return distinct(mix(h, width))


def gram_numbers(k: int):
    """An Arrow UDF from normalised texts to sets of gram numbers: the native counterpart of grams, distinct and hash, which as
    higher-order functions are interpreted per gram."""

    @F.pandas_udf(T.ArrayType(T.LongType()))
    def run(text: pd.Series) -> pd.Series:
        return text.map(lambda t: grams_of(t or "", k).view(np.int64))

    return run


def signature(b: int, seed: int = 42, how: str = "probe"):
    """An Arrow UDF from arrays of 64-bit token numbers to signatures; ``how`` is a densification or ``classic``. Empty sets
    give null."""

    @F.pandas_udf(T.ArrayType(T.LongType()))
    def run(tokens: pd.Series) -> pd.Series:
        if how in ("probe", "classic") and len(tokens):
            sets = [np.empty(0, np.int64) if t is None else np.asarray(t, np.int64) for t in tokens]
            lengths = np.fromiter(map(len, sets), np.int64, len(sets))
            rows = (probed_rows if how == "probe" else minima_of_sets)(np.concatenate(sets), lengths, b, seed).view(np.int64)
            return pd.Series([row if n else None for row, n in zip(rows, lengths.tolist(), strict=True)])

        def one(t):
            if t is None or len(t) == 0:
                return None
            return densified(bins_of(np.asarray(t, np.int64), b, seed), how, seed).view(np.int64)

        return tokens.map(one)

    return run


def sign_projection(b: int, seed: int = 42):
    """Signs of b random projections of a dense vector (the cosine family), as 0 / 1."""

    @F.pandas_udf(T.ArrayType(T.LongType()))
    def run(vec: pd.Series) -> pd.Series:
        if not len(vec):
            return vec
        x = np.stack(vec.to_numpy()).astype(np.float64)
        plane = np.random.default_rng(seed).normal(size=(x.shape[1], b))
        return pd.Series(list((x @ plane > 0).astype(np.int64)))

    return run


def sign_keys(texts, k: int, bits: int, tables: int, width: int = 128, seed: int = 42):
    """(rec_id, grp, keys) of (rec_id, grp, s): tables of ``bits`` signs each, of the projections of :func:`sign_projection`; a text is the
    vector of how many of its k-grams fall on each of ``width`` residues. Neither sets nor vectors leave the worker."""

    def run(batches):
        plane = np.random.default_rng(seed).normal(size=(width, bits * tables))
        place = 1 << np.arange(bits, dtype=np.int64)
        for batch in batches:
            sets = [grams_of(t or "", k).view(np.int64) for t in batch["s"].to_pylist()]
            row = np.repeat(np.arange(len(sets)), list(map(len, sets)))
            flat = np.concatenate([np.empty(0, np.int64), *sets])
            dense = np.bincount(row * width + flat % width, minlength=len(sets) * width).reshape(len(sets), width)
            signs = (dense.astype(np.float64) @ plane > 0).reshape(len(sets), tables, bits)
            keys = (signs * place).sum(axis=2)
            keys = pa.ListArray.from_arrays(pa.array(np.arange(len(sets) + 1, dtype=np.int32) * tables), pa.array(keys.ravel(), pa.int64()))
            yield pa.RecordBatch.from_arrays([batch["rec_id"], batch["grp"], keys], ["rec_id", "grp", "keys"])

    return texts.mapInArrow(run, "rec_id long, grp long, keys array<long>")


def stock_minhash_join(df: DataFrame, tokens: str, id_col: str, tables: int, least: float, width: int = 1 << 18) -> DataFrame:
    """Spark's own min-hash join (one minimum per table), as a cross-check: pairs with a Jaccard similarity of ``least``."""
    from pyspark.ml.feature import HashingTF, MinHashLSH

    v = HashingTF(inputCol=tokens, outputCol="_v", numFeatures=width, binary=True).transform(df.where(F.size(tokens) > 0)).select(id_col, "_v")
    model = MinHashLSH(inputCol="_v", outputCol="_h", numHashTables=tables, seed=42).fit(v)
    j = model.approxSimilarityJoin(v, v, 1 - least, "distance").where(F.col(f"datasetA.{id_col}") < F.col(f"datasetB.{id_col}"))
    return j.select(F.col(f"datasetA.{id_col}").alias("id_a"), F.col(f"datasetB.{id_col}").alias("id_b"), (1 - F.col("distance")).alias("similarity"))


def stock_projection_join(df: DataFrame, vec: str, id_col: str, tables: int, bucket: float, most: float) -> DataFrame:
    """Spark's own Euclidean family, as a cross-check: pairs at a distance of ``most``."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    v = df.select(id_col, array_to_vector(F.col(vec).cast("array<double>")).alias("_v"))
    model = BucketedRandomProjectionLSH(inputCol="_v", outputCol="_h", bucketLength=bucket, numHashTables=tables, seed=42).fit(v)
    j = model.approxSimilarityJoin(v, v, most, "distance").where(F.col(f"datasetA.{id_col}") < F.col(f"datasetB.{id_col}"))
    return j.select(F.col(f"datasetA.{id_col}").alias("id_a"), F.col(f"datasetB.{id_col}").alias("id_b"), "distance")


def monotone_check(pairs: DataFrame, similarity: str, collided: str, bins: int = 5) -> DataFrame:
    """Collision rate per band of similarity: it must not fall as the similarity grows."""
    band = F.least(F.floor(F.col(similarity) * bins), F.lit(bins - 1)).cast("int")
    return pairs.groupBy(band.alias("band")).agg(F.count("*").alias("n"), F.avg(F.col(collided).cast("double")).alias("rate"))
