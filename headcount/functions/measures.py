"""Cost and accuracy measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from headcount.functions.shingles import Texts, col


def relative_error(estimate: Texts, n: Texts) -> Column:
    return F.abs(col(estimate) - col(n)) / col(n)


def reduction_ratio(m: Texts, records: Texts) -> Column:
    """1 - m / all pairs."""
    r = col(records).cast("double")
    return 1 - col(m) / (r * (r - 1) / 2)


def sample_share(m: Texts, records: Texts) -> Column:
    r = col(records).cast("double")
    return 100 * col(m) / (r * (r - 1) / 2)


def hash_cost(records: int, k: int, tables: int) -> dict[str, int]:
    """Hash evaluations of plain min-hash and of one permutation, and table look-ups."""
    return {"plain": records * k * tables, "one_pass": records * tables + k * tables, "lookups": records * tables}


def spread(runs: DataFrame, by: list[str], estimate: str = "estimate", truth: str = "n") -> DataFrame:
    """Over repeats: mean and spread of the estimate and of the relative error, bias, mean squared error, coverage."""
    re = relative_error(estimate, truth)
    cols = [F.count("*").alias("runs"), F.avg(estimate).alias("mean_estimate"), F.stddev_samp(estimate).alias("sd_estimate"), F.avg(re).alias("mean_re"), F.stddev_samp(re).alias("sd_re"), F.avg(F.col(estimate) - F.col(truth)).alias("bias"), F.avg(F.pow(F.col(estimate) - F.col(truth), 2)).alias("mse")]
    if {"lo", "hi"} <= set(runs.columns):
        cols.append(F.avg(((F.col("lo") <= F.col(truth)) & (F.col(truth) <= F.col("hi"))).cast("double")).alias("coverage"))
    return runs.groupBy(*by).agg(*cols)


def pair_measures(sample: DataFrame, truth_pairs: DataFrame, n_records: int) -> DataFrame:
    """One row: size of the sample, recall, precision, reduction ratio, share of all pairs."""
    s = sample.select("id_a", "id_b").withColumn("_s", F.lit(1))
    t = truth_pairs.select("id_a", "id_b").withColumn("_t", F.lit(1))
    j = s.join(t, ["id_a", "id_b"], "full")
    row = j.agg(F.count("_s").alias("m"), F.count("_t").alias("n_true"), F.count_if(F.col("_s").isNotNull() & F.col("_t").isNotNull()).alias("tp"))
    return with_measures(row, n_records)


def with_measures(row: DataFrame, n_records: int) -> DataFrame:
    """The measures of (m, n_true, tp)."""
    row = row.withColumn("recall", F.col("tp") / F.nullif("n_true", F.lit(0))).withColumn("precision", F.col("tp") / F.nullif("m", F.lit(0)))
    return row.withColumn("reduction", reduction_ratio("m", F.lit(n_records))).withColumn("share_percent", sample_share("m", F.lit(n_records)))


def dataset_summary(df: DataFrame, entity: list[str], n_fields: int) -> DataFrame:
    """Records, fields, entities, matching pairs, duplicate records."""
    s = df.groupBy(*entity).agg(F.count("*").alias("s"))
    return s.agg(F.sum("s").alias("n_records"), F.lit(n_fields).cast("long").alias("n_fields"), F.count("*").alias("n_entities"), F.sum(F.expr("s * (s - 1) div 2")).alias("matching_pairs"), F.sum(F.col("s") - 1).alias("surplus_records"))


def reviewer_agreement(labels: DataFrame) -> DataFrame:
    """Share of equal decisions of two reviewers, over the pairs both have seen: rows (reviewer, id_a, id_b, is_match)."""
    x, y = labels.alias("x"), labels.alias("y")
    j = x.join(y, (F.col("x.id_a") == F.col("y.id_a")) & (F.col("x.id_b") == F.col("y.id_b")) & (F.col("x.reviewer") < F.col("y.reviewer")))
    return j.groupBy(F.col("x.reviewer").alias("first"), F.col("y.reviewer").alias("second")).agg(F.count("*").alias("n"), F.avg((F.col("x.is_match") == F.col("y.is_match")).cast("double")).alias("agreement"))
