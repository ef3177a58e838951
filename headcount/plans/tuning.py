"""Choosing K and L under a limit on the sample, by cross-validation over labelled matches."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from headcount.functions.hashing import signature
from headcount.operators.sampling import meta_keys, pair_hash
from headcount.sources.shipping import ship
from headcount.sources.storage import stored


def predicted_sizes(sets: DataFrame, grid, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """(cfg, raw_pairs, max_bucket) before any join, and the keys they come from: signatures are made once, at the largest K L."""
    ship(sets.sparkSession)
    sig = signature(max(k * t for k, t in grid), seed, "classic")("tokens")
    s = stored(sets.select("rec_id", sig.alias("sig")), "sigs")
    keys = s.select("rec_id", *(meta_keys("sig", k, t).alias(f"keys{c}") for c, (k, t) in enumerate(grid)))
    rows = None
    for c in range(len(grid)):
        part = keys.select(F.lit(c).alias("cfg"), F.posexplode(f"keys{c}").alias("tbl", "key"))
        rows = part if rows is None else rows.union(part)
    sizes = rows.groupBy("cfg", "tbl", "key").agg(F.count("*").alias("s"))
    return sizes.groupBy("cfg").agg(F.sum(F.expr("s * (s - 1) div 2")).alias("raw_pairs"), F.max("s").alias("max_bucket")), keys


def tune_kl(sets: DataFrame, grid, matched: DataFrame, max_pairs: int, folds: int = 5, seed: int = 42) -> DataFrame:
    """Per setting: predicted raw pairs, whether the limit allows it, mean recall over folds and its spread; ``chosen`` marks the
    allowed one with the highest mean recall. Recall needs no sample: the keys of labelled records are compared."""
    sizes, keys = predicted_sizes(sets, grid, seed)
    fold = (pair_hash(seed=seed) % folds).alias("fold")
    names = [f"keys{c}" for c in range(len(grid))]
    a = keys.select(F.col("rec_id").alias("id_a"), *(F.col(n).alias(f"a_{n}") for n in names))
    b = keys.select(F.col("rec_id").alias("id_b"), *(F.col(n).alias(f"b_{n}") for n in names))
    j = matched.select("id_a", "id_b", fold).join(a, "id_a").join(b, "id_b")
    rows = None
    for c, n in enumerate(names):
        same = F.exists(F.zip_with(f"a_{n}", f"b_{n}", lambda x, y: x == y), lambda x: x)
        part = j.select(F.lit(c).alias("cfg"), "fold", same.cast("double").alias("hit"))
        rows = part if rows is None else rows.union(part)
    per = rows.groupBy("cfg", "fold").agg(F.avg("hit").alias("r")).groupBy("cfg").agg(F.avg("r").alias("recall"), F.stddev_samp("r").alias("recall_sd"))
    settings = sets.sparkSession.createDataFrame([(c, k, t) for c, (k, t) in enumerate(grid)], "cfg int, k int, l int")
    out = settings.join(sizes, "cfg", "left").join(per, "cfg", "left").withColumn("allowed", F.coalesce(F.col("raw_pairs"), F.lit(0)) <= max_pairs)
    best = F.row_number().over(Window.orderBy(F.desc("allowed"), F.desc("recall"), "raw_pairs", "cfg"))  # a row per setting
    return out.withColumn("chosen", (best == 1) & F.col("allowed"))
