"""The (K, L) sampler and its competitors: bucket tables, pairs, budgets, uniform pairs, blocking."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from headcount.functions.shingles import PRIME, col, jaccard, let
from headcount.sources.shipping import ship
from headcount.sources.storage import stored

# --- bucket tables ---------------------------------------------------------------------------------------------------


def fold(minima: list[Column], table: int, mode: str = "native") -> Column:
    """One key of K minima; ``portable`` is a polynomial modulo the prime."""
    if mode == "native":
        return F.xxhash64(F.lit(table), *minima)
    key = F.lit(table + 1).cast("long")
    for m in minima:
        key = (key * 1_000_003 + m) % PRIME
    return key


def meta_keys(sig: Column | str, k: int, tables: int, address_range: int | None = None, mode: str = "native") -> Column:
    """L keys of K minima each; a range folds them further, which can only add pairs."""
    def keys(s: Column) -> Column:
        out = [fold([F.get(s, t * k + i) for i in range(k)], t, mode) for t in range(tables)]
        if address_range:
            out = [F.pmod(x, F.lit(address_range).cast("long")) for x in out]
        return F.when(s.isNotNull(), F.array(*out))

    return let(col(sig), keys)  # evaluated once, not once per minimum


def bucket_table(df: DataFrame, id_col: str, keys: str = "keys", narrow: bool = False) -> DataFrame:
    """(tbl, key, rec_id, keys): a row per record and table; records without keys are in no bucket. Narrow rows leave the L keys
    of the record out, so a record costs L small rows in a shuffle and not L * L keys."""
    return df.select(F.posexplode(keys).alias("tbl", "key"), F.col(id_col).alias("rec_id"), *([] if narrow else [F.col(keys).alias("keys")]))


def bucket_stats(buckets: DataFrame) -> DataFrame:
    """Buckets, the largest, and the raw pairs that a join would make: known before the join, from one aggregation."""
    sizes = buckets.groupBy("tbl", "key").agg(F.count("*").alias("s"))
    return sizes.groupBy("tbl").agg(F.count("*").alias("n_buckets"), F.max("s").alias("max_size"), F.sum(F.expr("s * (s - 1) div 2")).alias("raw_pairs"))


def shared_buckets(buckets: DataFrame) -> DataFrame:
    """Rows of buckets with two records or more; most keys are alone at K > 1. The counts aggregate before they are shuffled, so a
    hot bucket is a row per task, and the join back is one that AQE may split."""
    shared = buckets.groupBy("tbl", "key").agg(F.count("*").alias("_n")).where("_n > 1").drop("_n")
    return buckets.join(shared, ["tbl", "key"], "left_semi")


def sample_pairs(buckets: DataFrame, dedupe: str | None = None, max_bucket: int | None = None, policy: str = "keep") -> DataFrame:
    """Distinct unordered pairs that share a bucket of any table.

    ``distinct`` (of narrow buckets) shuffles small bucket rows and then the pairs, combined before they are sent; ``first_table``
    (of buckets that carry their records' keys) keeps a pair in the first table in which its keys agree, so it shuffles no pairs, but
    L keys with every bucket row: for settings that make far more pairs than bucket rows. Buckets above ``max_bucket`` are kept,
    ``split`` by a further hash, or ``subsample``d to about that many records by hash; the recall p is measured on the pairs after
    that, so the estimate stays corrected.
    """
    dedupe = dedupe or ("first_table" if "keys" in buckets.columns else "distinct")
    b = buckets
    if max_bucket and policy != "keep":
        hot = b.groupBy("tbl", "key").agg(F.count("*").alias("_n")).where(F.col("_n") > max_bucket)
        b = b.select("tbl", "key", "rec_id").join(hot, ["tbl", "key"], "left")
        if policy == "split":
            part = F.when(F.col("_n").isNotNull(), hash32("rec_id", "tbl") % F.ceil(F.col("_n") / max_bucket)).otherwise(-1)
            b = b.select("tbl", F.struct("key", part.alias("part")).alias("key"), "rec_id")
        else:
            u = hash32("rec_id", F.lit("subsample")) / float(2**32)
            b = b.where(F.col("_n").isNull() | (u * F.col("_n") < max_bucket)).drop("_n")
        dedupe = "distinct"  # keys no longer tell the first table
    x, y = b.alias("x"), b.alias("y")
    same = (F.col("x.tbl") == F.col("y.tbl")) & (F.col("x.key") == F.col("y.key")) & (F.col("x.rec_id") < F.col("y.rec_id"))
    j = x.join(y, same)
    if dedupe == "first_table":
        agree = F.zip_with(F.col("x.keys"), F.col("y.keys"), lambda p, q: p == q)
        return j.where(F.array_position(agree, True) == F.col("x.tbl") + 1).select(F.col("x.rec_id").alias("id_a"), F.col("y.rec_id").alias("id_b"))
    return j.select(F.col("x.rec_id").alias("id_a"), F.col("y.rec_id").alias("id_b")).distinct()


def sample_pairs_listed(buckets: DataFrame) -> DataFrame:
    """The bucket-as-a-list form: members collected per bucket and paired inside. For small buckets: a list is held in memory."""
    lists = buckets.groupBy("tbl", "key").agg(F.sort_array(F.collect_list("rec_id")).alias("m")).where(F.size("m") > 1)
    first = lists.select(F.posexplode("m").alias("i", "id_a"), "m")
    return first.select("id_a", F.explode(F.slice("m", F.col("i") + 2, F.size("m"))).alias("id_b")).distinct()


def _cell_pairs(cell: pa.Table) -> pa.Table:
    """Pairs of the two blocks that meet in a cell, or of one block with itself."""
    i, j = cell["i"][0].as_py(), cell["j"][0].as_py()
    own, ids = cell["own"].to_numpy(), cell["rec_id"].to_numpy()
    x, y = ids[own == i], ids[own == j]
    if i == j:
        a, b = np.triu_indices(len(x), 1)
        a, b = x[a], x[b]
    else:
        a, b = np.repeat(x, len(y)), np.tile(y, len(x))
    a, b = a[a != b], b[a != b]
    return pa.table({"id_a": pa.array(np.minimum(a, b), pa.int64()), "id_b": pa.array(np.maximum(a, b), pa.int64())})


def sample_pairs_grouped(buckets: DataFrame, most: int = 500) -> DataFrame:
    """The pairs of :func:`sample_pairs` as a grouped map over Arrow tables, for policies that need a bucket's members at once.

    No group is a whole bucket: its members are dealt into blocks of about ``most``, and every two blocks meet in a cell of their
    own. A task holds two blocks whatever the bucket's size, and no pair is lost."""
    ship(buckets.sparkSession)
    sizes = buckets.groupBy("tbl", "key").agg(F.count("*").alias("_n")).where("_n > 1")
    parts = F.ceil(F.col("_n") / most).cast("int")
    b = buckets.join(sizes, ["tbl", "key"]).select("tbl", "key", "rec_id", parts.alias("parts"), F.pmod(F.xxhash64("rec_id"), parts).cast("int").alias("own"))
    cells = b.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    cells = cells.select("tbl", "key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "rec_id")
    return cells.groupBy("tbl", "key", "i", "j").applyInArrow(_cell_pairs, "id_a long, id_b long").distinct()


def query_buckets(queries: DataFrame, buckets: DataFrame) -> DataFrame:
    """(query_id, rec_id): neighbours of query records, given as rows (query_id, tbl, key)."""
    return queries.join(buckets.select("tbl", "key", "rec_id"), ["tbl", "key"]).where("query_id <> rec_id").select("query_id", "rec_id").distinct()


def candidates_per_record(pairs: DataFrame) -> DataFrame:
    both = pairs.select("id_a", "id_b").union(pairs.select(F.col("id_b"), F.col("id_a")))
    return both.groupBy(F.col("id_a").alias("rec_id")).agg(F.sort_array(F.collect_set("id_b")).alias("candidates"))


def hash32(*parts: Column | str) -> Column:
    """32 bits of the MD5 of the parts, comma-joined: the same in any engine."""
    s = F.concat_ws(",", *((F.col(p) if isinstance(p, str) else p).cast("string") for p in parts))
    return F.conv(F.substring(F.md5(s.cast("binary")), 1, 8), 16, 10).cast("long")


def pair_hash(a: str = "id_a", b: str = "id_b", seed: int = 0) -> Column:
    """32 bits of the MD5 of a pair and a seed."""
    return hash32(a, b, F.lit(str(seed)))


def cap_pairs(pairs: DataFrame, m: int, seed: int = 0) -> DataFrame:
    """At most m pairs: the m least by hash. p has to be measured after it.

    A threshold a little below the m-th hash takes nearly all of them where they are; only the rest, some multiples of sqrt(m),
    goes through one task as a top-k."""
    p = stored(pairs.select("id_a", "id_b", pair_hash(seed=seed).alias("_h")), "hashed")
    n = p.count()
    if n <= m:
        return p.drop("_h")
    below = p.where(F.col("_h") < int(2**32 * max(0.0, m - 5 * m**0.5) / n))
    left = m - below.count()
    if left < 0:  # hashes far from even
        return p.orderBy("_h", "id_a", "id_b").limit(m).drop("_h")
    rest = p.where(F.col("_h") >= int(2**32 * max(0.0, m - 5 * m**0.5) / n)).orderBy("_h", "id_a", "id_b").limit(left)
    return below.union(rest).drop("_h")


def thin_pairs(pairs: DataFrame, p: float, seed: int = 0) -> DataFrame:
    """Each pair kept with probability p, by its hash."""
    return pairs.where(pair_hash(seed=seed) < int(p * 2**32))


# --- samplers that are not LSH ---------------------------------------------------------------------------------------


def all_pairs(df: DataFrame, id_col: str, most: int = 20_000) -> DataFrame:
    """Brute force, refused for more than ``most`` records."""
    n = df.count()
    if n > most:
        raise ValueError(f"{n} records have too many pairs for brute force")
    x, y = df.select(F.col(id_col).alias("id_a")), df.select(F.col(id_col).alias("id_b"))
    return x.join(y, F.col("id_a") < F.col("id_b"))


def all_pair_similarity(sets: DataFrame, id_col: str, tokens: str, least: float = 0.0) -> DataFrame:
    """Exact similarities above ``least`` (and 0) of all pairs, by an inverted index: pairs that share no token never meet."""
    t = sets.select(F.col(id_col).alias("rec_id"), F.size(tokens).alias("n"), F.explode(tokens).alias("t"))
    x, y = t.alias("x"), t.alias("y")
    j = x.join(y, (F.col("x.t") == F.col("y.t")) & (F.col("x.rec_id") < F.col("y.rec_id")))
    g = j.groupBy(F.col("x.rec_id").alias("id_a"), F.col("y.rec_id").alias("id_b")).agg(F.count("*").alias("c"), F.first("x.n").alias("na"), F.first("y.n").alias("nb"))
    return g.select("id_a", "id_b", (F.col("c") / (F.col("na") + F.col("nb") - F.col("c"))).alias("similarity")).where(F.col("similarity") >= least)


def dense_index(df: DataFrame, id_col: str) -> DataFrame:
    """(idx 0..M-1, id) without one global window: counts per partition give offsets. Deterministic: ranged by id first."""
    spark = df.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranged = df.select(id_col).repartitionByRange(parts, id_col).sortWithinPartitions(id_col).withColumn("_p", F.spark_partition_id())
    local = ranged.withColumn("_r", F.row_number().over(Window.partitionBy("_p").orderBy(id_col)) - 1)
    counts = ranged.groupBy("_p").agg(F.count("*").alias("c"))
    offset = counts.select("_p", (F.sum("c").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, 0)) - F.col("c")).alias("_o"))  # one row per partition
    return local.join(F.broadcast(offset), "_p").select((F.col("_r") + F.col("_o")).cast("long").alias("idx"), id_col)


def decode_rank(rank: Column) -> tuple[Column, Column]:
    """The (i, j), i < j, of a number below M (M - 1) / 2: triangular root with an exact correction."""
    j = F.floor((1 + F.sqrt(1 + 8 * rank.cast("double"))) / 2).cast("long")
    j = F.when(j * (j - 1) / 2 > rank, j - 1).otherwise(j)
    tri = F.floor(j * (j - 1) / 2).cast("long")
    j = F.when(rank - tri >= j, j + 1).otherwise(j)
    return (rank - F.floor(j * (j - 1) / 2)).cast("long"), j


def uniform_pairs(df: DataFrame, id_col: str, m: int, seed: int = 42) -> DataFrame:
    """m distinct pairs drawn uniformly: random ranks of the pair space, decoded; the space itself is never built."""
    n = df.count()
    total = n * (n - 1) // 2
    m = min(m, total)
    spark = df.sparkSession
    draws = int(1.02 * m + m * m / max(1, total) + 50)  # a few more than m, for those drawn twice
    dense = draws * 2 > total  # then the whole rank space is shuffled instead
    ranks = spark.range(total if dense else draws)
    if not dense:
        u = F.conv(F.substring(F.md5(F.concat_ws(",", "id", F.lit(str(seed))).cast("binary")), 1, 15), 16, 10).cast("decimal(20,0)")
        ranks = ranks.select(F.pmod(u, F.lit(total).cast("decimal(20,0)")).cast("long").alias("id")).distinct()
    ranks = ranks.orderBy(F.xxhash64("id", F.lit(seed)), "id").limit(m)
    i, j = decode_rank(F.col("id"))
    index = dense_index(df, id_col)
    at = ranks.select(i.alias("i"), j.alias("j"))
    a = at.join(index.select(F.col("idx").alias("i"), F.col(id_col).alias("x")), "i")
    b = a.join(index.select(F.col("idx").alias("j"), F.col(id_col).alias("y")), "j")
    return b.select(F.least("x", "y").alias("id_a"), F.greatest("x", "y").alias("id_b"))


def similarity_proportional_pairs(similarities: DataFrame, m: int, seed: int = 0) -> DataFrame:
    """Pairs kept with a chance in proportion to their similarity, m on average: the ideal that the LSH sample stands in for."""
    total = similarities.agg(F.sum("similarity")).first()[0] or 1.0
    u = pair_hash(seed=seed) / float(2**32)
    return similarities.where(u < F.least(F.lit(1.0), F.lit(m / total) * F.col("similarity"))).select("id_a", "id_b")


def block_pairs(df: DataFrame, id_col: str, keys: list[Column | str]) -> DataFrame:
    """All pairs that agree on a deterministic key. Missing keys match nothing. Its recall cannot be corrected for."""
    b = df.select(F.col(id_col).alias("rec_id"), *(col(k).alias(f"k{i}") for i, k in enumerate(keys))).dropna()
    x, y = b.alias("x"), b.alias("y")
    on = F.col("x.rec_id") < F.col("y.rec_id")
    for i in range(len(keys)):
        on = (F.col(f"x.k{i}") == F.col(f"y.k{i}")) & on
    return x.join(y, on).select(F.col("x.rec_id").alias("id_a"), F.col("y.rec_id").alias("id_b"))


def block_pairs_any(df: DataFrame, id_col: str, rules: list[list[Column | str]]) -> DataFrame:
    """Pairs that agree on any of several keys."""
    parts = [block_pairs(df, id_col, r) for r in rules]
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out.distinct()


def pair_similarity(pairs: DataFrame, sets: DataFrame, id_col: str, tokens: str) -> DataFrame:
    """(id_a, id_b, similarity) of given pairs: two joins that bring the sets."""
    a = sets.select(F.col(id_col).alias("id_a"), F.col(tokens).alias("_x"))
    b = sets.select(F.col(id_col).alias("id_b"), F.col(tokens).alias("_y"))
    return pairs.select("id_a", "id_b").join(a, "id_a").join(b, "id_b").select("id_a", "id_b", jaccard("_x", "_y").alias("similarity"))


def empty_pairs(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], T.StructType([T.StructField("id_a", T.LongType()), T.StructField("id_b", T.LongType())]))
