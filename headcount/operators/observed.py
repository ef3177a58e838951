"""The observed graph: sizes of components, histograms, clique checks, and the estimate from a histogram."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from headcount.functions import estimators as E


def truth_histogram(truth: DataFrame, entity: str | list[str]) -> DataFrame:
    """(size, n): entities by number of records."""
    keys = [entity] if isinstance(entity, str) else entity
    return truth.groupBy(*keys).agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("n"))


def size_histogram(comps: DataFrame, n_records: int) -> DataFrame:
    """(size, n) of the observed graph. Records in no matched pair are singletons, by subtraction: they are never listed."""
    sizes = comps.groupBy("component").agg(F.count("*").alias("size"))
    h = sizes.groupBy("size").agg(F.count("*").alias("n"))
    alone = comps.agg((F.lit(n_records) - F.count("*")).alias("n")).select(F.lit(1).cast("long").alias("size"), "n")
    return h.union(alone).groupBy("size").agg(F.sum("n").alias("n")).where("n > 0")


def histogram_row(h: DataFrame) -> DataFrame:
    """One row (s1, s2, s3, s_rest, observed, m_records) of a histogram."""
    s = lambda c: F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0)).cast("long")
    return h.agg(s(F.col("size") == 1).alias("s1"), s(F.col("size") == 2).alias("s2"), s(F.col("size") == 3).alias("s3"), s(F.col("size") > 3).alias("s_rest"), F.sum("n").alias("observed"), F.sum(F.col("n") * F.col("size")).alias("m_records"))


def estimate_row(h: DataFrame, p: float | None) -> DataFrame:
    """The estimate with its errors, from a histogram and the recall."""
    return E.with_errors(histogram_row(h).withColumn("p", F.lit(p).cast("double")))


def estimate_rows(h: DataFrame, group: list[str], recall: DataFrame) -> DataFrame:
    """Estimates of many groups (or seeds, or settings) at once: (group.., size, n) and (group.., p)."""
    s = lambda c: F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0)).cast("long")
    rows = h.groupBy(*group).agg(s(F.col("size") == 1).alias("s1"), s(F.col("size") == 2).alias("s2"), s(F.col("size") == 3).alias("s3"), s(F.col("size") > 3).alias("s_rest"), F.sum("n").alias("observed"))
    return E.with_errors(rows.join(recall, group))


def clique_check(edges: DataFrame, comps: DataFrame) -> DataFrame:
    """(component, size, n_edges, is_clique)."""
    e = edges.join(comps.select(F.col("rec_id").alias("id_a"), "component"), "id_a").groupBy("component").agg(F.count("*").alias("n_edges"))
    s = comps.groupBy("component").agg(F.count("*").alias("size"))
    return s.join(e, "component").withColumn("is_clique", F.col("n_edges") * 2 == F.col("size") * (F.col("size") - 1))


def toy_graph(spark) -> DataFrame:
    """Six records: a triple, a pair and a singleton (record 6, in no edge)."""
    return spark.createDataFrame([(1, 2), (1, 3), (2, 3), (4, 5)], "id_a long, id_b long")
