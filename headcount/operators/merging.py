"""Emulated hand matching: block, label by rule, merge every match group into one record, and go over the result again."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from headcount.functions.shingles import char_grams, jaccard, normalise
from headcount.sources.storage import stored

from .components import components_auto


def rule_label(pairs: DataFrame, records: DataFrame, id_col: str, name: str, strict: float = 0.6) -> DataFrame:
    """A reviewer's rule: names alike enough, by their grams."""
    g = records.select(F.col(id_col).alias("_id"), char_grams(normalise(name), 2).alias("_g"))
    j = pairs.join(g.select(F.col("_id").alias("id_a"), F.col("_g").alias("_x")), "id_a").join(g.select(F.col("_id").alias("id_b"), F.col("_g").alias("_y")), "id_b")
    return j.select("id_a", "id_b", (jaccard("_x", "_y") >= strict).alias("is_match"))


def majority(df: DataFrame, group: str, field: str, order: str, seed: int = 0) -> DataFrame:
    """(group, field): the longest value that is there (the most precise), then the most frequent, ties by seeded hash."""
    n = df.where(F.col(field).isNotNull()).groupBy(group, field).agg(F.count("*").alias("_n"))
    w = Window.partitionBy(group).orderBy(F.desc(F.length(F.col(field).cast("string")) if order == "longest" else F.lit(0)), F.desc("_n"), F.xxhash64(F.col(field), F.lit(seed)), F.col(field))
    return n.withColumn("_r", F.row_number().over(w)).where("_r = 1").select(group, field)


def merge_records(records: DataFrame, comps: DataFrame, id_col: str, fields: dict[str, str], seed: int = 0) -> DataFrame:
    """One record per match group; ``fields`` says per field whether the ``longest`` or the most ``frequent`` value wins.

    Fields become rows (group, field, value), counted with a map-side combine; the winner of a group and field is the least
    (-precision, -count, hash, value) in one more aggregation, and a last one turns the winners back into columns. Three
    shuffles, however many fields there are.
    """
    c = records.join(comps.select(F.col("rec_id").alias(id_col), "component"), id_col, "left").withColumn("_g", F.coalesce("component", F.col(id_col)))
    cells = F.array(*(F.struct(F.lit(f).alias("f"), F.col(f).cast("string").alias("v")) for f in fields))
    long = [f for f, how in fields.items() if how == "longest"]
    n = c.select("_g", F.explode(cells).alias("x")).select("_g", "x.f", "x.v").groupBy("_g", "f", "v").agg(F.count("*").alias("n"))
    precise = F.when(F.col("f").isin(long), -F.length("v")).otherwise(0)
    order = F.struct(F.col("v").isNull().alias("none"), precise.alias("a"), (-F.col("n")).alias("b"), F.xxhash64("v", F.lit(seed)).alias("h"), F.col("v").alias("v"))
    first = next(iter(fields))
    won = n.groupBy("_g", "f").agg(F.min(order).alias("o"), F.sum("n").alias("n"))
    wide = won.groupBy("_g").agg(F.map_from_entries(F.collect_list(F.struct("f", "o.v"))).alias("m"), F.max(F.when(F.col("f") == first, F.col("n"))).alias("n_merged"))
    types = dict(records.dtypes)
    return wide.select(F.col("_g").alias(id_col), "n_merged", *(F.element_at("m", f).cast(types[f]).alias(f) for f in fields))


def near_days(df: DataFrame, id_col: str, keys: list[str], day: str, within: int = 1, ring: int | None = None) -> DataFrame:
    """Pairs that agree on the keys and lie at most ``within`` days apart, across any border: a day bin and its next, then the
    exact difference. With ``ring`` the first key is a region of so many around a ring, and the two have to be neighbours."""
    width = max(1, within)
    x = df.select(F.col(id_col).alias("id_a"), *(F.col(k).alias(f"x_{k}") for k in keys), F.col(day).alias("_dx"), F.floor(F.col(day) / width).alias("_bx"))
    y = df.select(F.col(id_col).alias("id_b"), *(F.col(k).alias(f"y_{k}") for k in keys), F.col(day).alias("_dy"), F.explode(F.array(*(F.floor(F.col(day) / width) + i for i in (-1, 0, 1)))).alias("_by"))
    if ring:
        at = F.col(f"y_{keys[0]}")
        y = y.withColumn(f"y_{keys[0]}", F.explode(F.array_distinct(F.array(F.pmod(at + 1, F.lit(ring)), F.pmod(at - 1, F.lit(ring))))))
    on: Column = F.col("_bx") == F.col("_by")
    for k in keys:
        on = on & (F.col(f"x_{k}") == F.col(f"y_{k}"))
    return x.join(y, on & (F.col("id_a") < F.col("id_b")) & (F.abs(F.col("_dx") - F.col("_dy")) <= within)).select("id_a", "id_b")


def iterative_match_merge(records: DataFrame, id_col: str, block: list[str], day: str, name: str, fields: dict[str, str], strict: float = 0.6, rounds: int = 2, ring: int | None = None) -> DataFrame:
    """The reference answer: blocks by region and period, labels by rule, merges; then again over the merged records and across
    the borders of periods and, with ``ring``, of neighbouring regions. Returns the merged records with how many records each
    stands for."""
    from .sampling import block_pairs

    current = records.withColumn("n_merged", F.lit(1).cast("long"))
    for i in range(rounds):
        pairs = block_pairs(current, id_col, [*block[:-1], F.floor(F.col(day) / 365)]) if i == 0 else near_days(current, id_col, block[:-1], day, 1)
        if i and ring:
            pairs = pairs.union(near_days(current, id_col, block[:-1], day, 1, ring))
        labels = rule_label(pairs, current, id_col, name, strict)
        comps = stored(components_auto(stored(labels.where("is_match").select("id_a", "id_b"), "matched")), "groups")
        c = current.select(id_col, F.col("n_merged").alias("_m")).join(comps.select(F.col("rec_id").alias(id_col), "component"), id_col, "left")
        weights = c.groupBy(F.coalesce("component", F.col(id_col)).alias(id_col)).agg(F.sum("_m").alias("n_merged"))
        current = stored(merge_records(current.drop("n_merged"), comps, id_col, fields).drop("n_merged").join(weights, id_col), "merged")
    return current
