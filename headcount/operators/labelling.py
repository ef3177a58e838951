"""Labels of sampled pairs (truth, table, threshold, trained classifiers) and the recall p of a sample."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .sampling import hash32, pair_hash, pair_similarity


def label_by_truth(pairs: DataFrame, truth: DataFrame, id_col: str, entity: str) -> DataFrame:
    """(id_a, id_b, is_match): two joins that bring the entities."""
    a = truth.select(F.col(id_col).alias("id_a"), F.col(entity).alias("_ea"))
    b = truth.select(F.col(id_col).alias("id_b"), F.col(entity).alias("_eb"))
    return pairs.select("id_a", "id_b").join(a, "id_a").join(b, "id_b").select("id_a", "id_b", (F.col("_ea") == F.col("_eb")).alias("is_match"))


def label_by_table(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """Labels from a table of labelled pairs; pairs without one get null."""
    return pairs.select("id_a", "id_b").join(labels.select("id_a", "id_b", "is_match"), ["id_a", "id_b"], "left")


def label_by_threshold(pairs: DataFrame, sets: DataFrame, id_col: str, tokens: str, theta: float) -> DataFrame:
    return pair_similarity(pairs, sets, id_col, tokens).select("id_a", "id_b", (F.col("similarity") >= theta).alias("is_match"))


def truth_pairs(truth: DataFrame, id_col: str, entity: str) -> DataFrame:
    """All matching pairs."""
    t = truth.select(F.col(id_col).alias("r"), F.col(entity).alias("e"))
    x, y = t.alias("x"), t.alias("y")
    return x.join(y, (F.col("x.e") == F.col("y.e")) & (F.col("x.r") < F.col("y.r"))).select(F.col("x.r").alias("id_a"), F.col("y.r").alias("id_b"))


def recall_row(pairs: DataFrame, matched: DataFrame) -> DataFrame:
    """One row: n_labelled matches, hits in the sample, p (null if there are none), its binomial error."""
    hit = pairs.select("id_a", "id_b").withColumn("_hit", F.lit(1))
    j = matched.select("id_a", "id_b").join(hit, ["id_a", "id_b"], "left")
    row = j.agg(F.count("*").alias("n_labelled"), F.count("_hit").alias("hits"))
    p = F.when(F.col("n_labelled") > 0, F.col("hits") / F.col("n_labelled"))
    return row.withColumn("p", p).withColumn("p_se", F.sqrt(p * (1 - p) / F.col("n_labelled")))


def edge_recall(pairs: DataFrame, matched: DataFrame) -> float | None:
    """The scalar p, undefined (None) without labelled matches."""
    return recall_row(pairs, matched).first()["p"]


def edge_recall_by_keys(keys: DataFrame, matched: DataFrame, id_col: str = "rec_id") -> DataFrame:
    """p without any sample: labelled matches whose keys agree in some table. The labelled pairs are small, the keys are joined
    by record."""
    a = keys.select(F.col(id_col).alias("id_a"), F.col("keys").alias("_ka"))
    b = keys.select(F.col(id_col).alias("id_b"), F.col("keys").alias("_kb"))
    j = matched.select("id_a", "id_b").join(a, "id_a", "left").join(b, "id_b", "left")
    hit = F.coalesce(F.exists(F.zip_with("_ka", "_kb", lambda x, y: x == y), lambda x: x), F.lit(False))
    row = j.agg(F.count("*").alias("n_labelled"), F.coalesce(F.sum(hit.cast("int")), F.lit(0)).cast("long").alias("hits"))
    return row.withColumn("p", F.when(F.col("n_labelled") > 0, F.col("hits") / F.col("n_labelled")))


def modelled_recall(similarities: DataFrame, k: int, tables: int, weight: str | None = None) -> DataFrame:
    """p as the retrieval formula implies it for labelled matches: a diagnostic. A row counts ``weight`` times, or once."""
    w = F.col(weight) if weight else F.lit(1)
    p = 1 - F.pow(1 - F.pow("similarity", F.lit(k)), F.lit(tables))
    return similarities.agg((F.sum(p * w) / F.sum(w)).alias("p_model"))


def bootstrap_recall(pairs: DataFrame, matched: DataFrame, rounds: int = 200, seed: int = 0) -> DataFrame:
    """Spread of p under resampling of the labelled matches: Poisson(1) weights by hash, all rounds in one aggregation."""
    hit = pairs.select("id_a", "id_b").withColumn("_hit", F.lit(1))
    j = matched.select("id_a", "id_b").join(hit, ["id_a", "id_b"], "left")
    r = j.select("*", F.explode(F.sequence(F.lit(1), F.lit(rounds))).alias("round"))
    u = hash32("id_a", "id_b", "round", F.lit(seed)) / float(2**32)
    w = F.when(u < 0.36788, 0).when(u < 0.73576, 1).when(u < 0.91970, 2).when(u < 0.98101, 3).otherwise(4)
    per = r.groupBy("round").agg((F.sum(w * F.coalesce("_hit", F.lit(0))) / F.nullif(F.sum(w), F.lit(0))).alias("p"))
    return per.agg(F.avg("p").alias("p_mean"), F.stddev_samp("p").alias("p_sd"))


def close_labels(matched: DataFrame) -> DataFrame:
    """The transitive closure of matched pairs: all pairs within their components."""
    from .components import components_auto

    c = components_auto(matched.select("id_a", "id_b"))
    x, y = c.alias("x"), c.alias("y")
    return x.join(y, (F.col("x.component") == F.col("y.component")) & (F.col("x.rec_id") < F.col("y.rec_id"))).select(F.col("x.rec_id").alias("id_a"), F.col("y.rec_id").alias("id_b"))


# --- trained labels --------------------------------------------------------------------------------------------------


def pair_features(pairs: DataFrame, records: DataFrame, id_col: str, fields: list[str], k: int = 2) -> tuple[DataFrame, list[str]]:
    """Features of record pairs: gram similarity, edit ratio, equality and missing flags of every field."""
    from headcount.functions.shingles import char_grams, jaccard, normalise

    prepared = records.select(F.col(id_col).alias("_id"), *(F.coalesce(F.col(f).cast("string"), F.lit("")).alias(f) for f in fields), *(char_grams(normalise(F.col(f).cast("string")), k).alias(f"{f}_g") for f in fields))
    a = prepared.select(F.col("_id").alias("id_a"), *(F.col(c).alias(f"a_{c}") for c in prepared.columns[1:]))
    b = prepared.select(F.col("_id").alias("id_b"), *(F.col(c).alias(f"b_{c}") for c in prepared.columns[1:]))
    j = pairs.join(a, "id_a").join(b, "id_b")
    cols, names = [], []

    def add(name: str, c: Column) -> None:
        cols.append(c.cast("double").alias(name))
        names.append(name)

    for f in fields:
        x, y = F.col(f"a_{f}"), F.col(f"b_{f}")
        add(f"{f}_grams", jaccard(f"a_{f}_g", f"b_{f}_g"))
        add(f"{f}_edits", 1 - F.levenshtein(x, y) / F.greatest(F.length(x), F.length(y), F.lit(1)))
        add(f"{f}_same", (x == y) & (x != ""))
        add(f"{f}_missing", (x == "") | (y == ""))
    return j.select(*pairs.columns, *cols), names


def training_pairs(matched: DataFrame, candidates: DataFrame, share_of: int, share: float = 1e-4, seed: int = 0) -> DataFrame:
    """(id_a, id_b, is_match): matches and equally many hard non-matches, at most ``share`` of ``share_of`` pairs in all."""
    half = max(1, int(share * share_of / 2))
    yes = matched.select("id_a", "id_b").orderBy(pair_hash(seed=seed), "id_a", "id_b").limit(half)
    no = candidates.select("id_a", "id_b").join(matched.select("id_a", "id_b"), ["id_a", "id_b"], "left_anti").orderBy(pair_hash(seed=seed + 1), "id_a", "id_b").limit(half)
    return yes.withColumn("is_match", F.lit(True)).union(no.withColumn("is_match", F.lit(False)))


def train_labeller(features: DataFrame, names: list[str], kind: str = "svm", seed: int = 42):
    """A fitted pipeline on ``is_match``: linear support vectors or a random forest."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LinearSVC, RandomForestClassifier
    from pyspark.ml.feature import VectorAssembler

    data = features.withColumn("label", F.col("is_match").cast("double"))
    model = LinearSVC(maxIter=50, regParam=0.001) if kind == "svm" else RandomForestClassifier(numTrees=40, maxDepth=6, seed=seed)
    return Pipeline(stages=[VectorAssembler(inputCols=names, outputCol="features"), model]).fit(data)


def label_by_model(features: DataFrame, model) -> DataFrame:
    return model.transform(features).select("id_a", "id_b", (F.col("prediction") == 1.0).alias("is_match"))


def confusion(labels: DataFrame, truth: DataFrame) -> DataFrame:
    """Counts of (tp, fp, fn, tn) of labelled pairs against true labels, with precision and recall of the labeller."""
    j = labels.select("id_a", "id_b", F.col("is_match").alias("x")).join(truth.select("id_a", "id_b", F.col("is_match").alias("y")), ["id_a", "id_b"])
    n = lambda c: F.count_if(c)
    row = j.agg(n(F.col("x") & F.col("y")).alias("tp"), n(F.col("x") & ~F.col("y")).alias("fp"), n(~F.col("x") & F.col("y")).alias("fn"), n(~F.col("x") & ~F.col("y")).alias("tn"))
    return row.withColumn("precision", F.col("tp") / F.nullif(F.col("tp") + F.col("fp"), F.lit(0))).withColumn("recall", F.col("tp") / F.nullif(F.col("tp") + F.col("fn"), F.lit(0)))
