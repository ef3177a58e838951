"""The public procedure: records -> sets -> signatures -> buckets -> pairs -> labels -> components -> estimate with error."""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from headcount.functions.estimators import random_recall, weight_upto, with_total_error
from headcount.functions.hashing import minhash, signature
from headcount.operators import labelling, observed, sampling
from headcount.operators.components import components_auto
from headcount.operators.textsets import TextSets
from headcount.sources.shipping import ship
from headcount.sources.storage import stored
from headcount.sources.tables import RecordSpec


@dataclass(frozen=True)
class Sampler:
    """K minima per key, L tables. ``portable`` has SQL twins; ``native`` is one Arrow pass (one permutation, densified)."""

    k: int = 4
    tables: int = 4
    seed: int = 42
    mode: str = "native"
    densify: str = "probe"
    address_range: int | None = None
    max_bucket: int | None = None
    policy: str = "keep"

    def keys(self, sets: DataFrame) -> DataFrame:
        """(rec_id, keys): narrow, no shuffle."""
        b = self.k * self.tables
        if self.mode == "portable":
            sig = minhash("tokens", b, self.seed)
        else:
            ship(sets.sparkSession)
            sig = signature(b, self.seed, self.densify)("tokens")
        s = sets.select("rec_id", sig.alias("sig"))
        return s.select("rec_id", sampling.meta_keys("sig", self.k, self.tables, self.address_range, self.mode).alias("keys"))

    def pairs(self, sets: DataFrame, shared_only: bool = False) -> DataFrame:
        b = sampling.bucket_table(self.keys(sets), "rec_id", narrow=True)
        if shared_only:
            b = sampling.shared_buckets(b)
        return sampling.sample_pairs(b, max_bucket=self.max_bucket, policy=self.policy)


def observed_pass(judged: DataFrame, known: DataFrame) -> tuple[DataFrame, int, int]:
    """The matched pairs, the size of the sample and the number of known matches in it: sampling, labelling and p share the one
    pass that writes the judged pairs, and one conditional aggregate over what it wrote. (An ``Observation`` would spare that
    read, but puts a manager into the session that models of Spark ML cannot serialise.)"""
    flagged = judged.join(known.select("id_a", "id_b").withColumn("_known", F.lit(1)), ["id_a", "id_b"], "left")
    flagged = stored(flagged.select("id_a", "id_b", "is_match", "_known"), "judged")
    m, hits = flagged.agg(F.count("*"), F.count("_known")).first()
    return flagged.where("is_match").select("id_a", "id_b"), m, hits


def trained_labels(pairs: DataFrame, df: DataFrame, spec: RecordSpec, training: DataFrame, kind: str) -> DataFrame:
    """Labels of the pairs by a classifier (``svm`` or ``forest``) trained on (id_a, id_b, is_match)."""
    fields = list(spec.fields)
    f, names = labelling.pair_features(training, df, spec.id_col, fields)
    model = labelling.train_labeller(stored(f, "train"), names, kind)
    return labelling.label_by_model(labelling.pair_features(pairs, df, spec.id_col, fields)[0], model)


def estimate_unique_entities(
    df: DataFrame,
    spec: RecordSpec,
    sampler: Sampler = Sampler(),
    labels: DataFrame | None = None,
    theta: float | None = None,
    labelled: DataFrame | None = None,
    budget: int | None = None,
    n_records: int | None = None,
    sets: DataFrame | None = None,
    labeller: str | None = None,
    training: DataFrame | None = None,
    p_from: str | float = "labelled",
    max_exact: int = 3,
) -> DataFrame:
    """One row: method, m, p, observed counts by size, estimate, errors, bounds, status.

    Sampled pairs are labelled by ``theta`` (exact similarity of their sets), by a table ``labels`` (unlabelled pairs count as
    no match), by a ``labeller`` (``svm`` or ``forest``) trained on ``training`` (id_a, id_b, is_match), or by the truth of the
    spec. p comes from ``labelled`` matches (id_a, id_b), by default all true pairs, counted in the pass that labels the sample;
    ``p_from`` may also be ``model`` (the retrieval formula over the similarities of those matches), ``uniform`` (the share of
    all pairs, for a uniform sample) or a number. ``sd`` is the closed form; ``sd_total`` and the bounds add the error of a
    measured p. Entities of more than ``max_exact`` records are taken to survive; above 3, ``estimate_upto`` holds the estimate
    with exact weights to that size. ``sets`` are (rec_id, tokens), if they are there already.
    """
    if not (isinstance(p_from, float) or p_from in ("labelled", "model", "uniform")):
        raise ValueError(f"p_from: {p_from}")
    if sampler.k < 1 or sampler.tables < 1 or (budget is not None and budget < 1) or max_exact < 3:
        raise ValueError("K, L and the budget are 1 or more, max_exact 3 or more")
    if labeller and training is None:
        raise ValueError("a labeller needs training pairs")
    sets = sets if sets is not None else stored(spec.sets(df, sampler.mode), "sets")
    n = n_records if n_records is not None else sets.count()  # of written Parquet: a footer count
    pairs = sampler.pairs(sets)
    if budget:
        pairs = sampling.cap_pairs(pairs, budget)
    if theta is not None:
        judged = labelling.label_by_threshold(pairs, sets, "rec_id", "tokens", theta)
    elif labels is not None:
        judged = labelling.label_by_table(pairs, labels)
    elif labeller:
        judged = trained_labels(pairs, df, spec, training, labeller)
    else:
        judged = labelling.label_by_truth(pairs, sets, "rec_id", "entity")
    known = labelled if labelled is not None else stored(labelling.truth_pairs(sets, "rec_id", "entity"), "known")
    matched, m, hits = observed_pass(judged, known)
    n_labelled = known.count()
    if isinstance(p_from, float):
        p = p_from
    elif p_from == "uniform":
        p = random_recall(m, n)
    elif p_from == "model":
        p = labelling.modelled_recall(sampling.pair_similarity(known, sets, "rec_id", "tokens"), sampler.k, sampler.tables).first()[0]
    else:
        p = hits / n_labelled if n_labelled else None
    h = observed.size_histogram(components_auto(matched), n)
    row = observed.estimate_row(h, p)
    if p_from == "labelled":
        row = with_total_error(row.withColumn("n_labelled", F.lit(n_labelled).cast("long")).withColumn("hits", F.lit(hits).cast("long")))
    if max_exact > 3 and p:
        upto = h.agg(F.sum(F.col("n") * weight_upto(F.col("size"), p, max_exact)).alias("estimate_upto"))
        row = row.crossJoin(upto)  # one row each
    first = {"method": F.lit("lsh"), "k": F.lit(sampler.k), "l": F.lit(sampler.tables), "m_pairs": F.lit(m).cast("long")}
    return row.select(*(v.alias(c) for c, v in first.items()), "*")


def estimate_texts(df: DataFrame, spec: RecordSpec, sampler: Sampler, theta: float, among: DataFrame | None = None) -> DataFrame:
    """The row of :func:`estimate_unique_entities` for texts whose sets are too large to be written: labels by exact similarity
    ``theta``, p from all pairs of that similarity among the records ``among`` (rec_id)."""
    t = TextSets(df, spec, sampler.k, sampler.tables, sampler.seed, sampler.mode, sampler.densify)
    r = t.recall(t.known(theta, among)).first()
    m = t.n_pairs(theta)  # first: the whole sample is written once
    row = observed.estimate_row(t.histogram(t.matched(theta)), r["p"])
    row = with_total_error(row.withColumn("n_labelled", F.lit(r["n_labelled"]).cast("long")).withColumn("hits", F.lit(r["hits"]).cast("long")))
    first = {"method": F.lit("lsh"), "k": F.lit(sampler.k), "l": F.lit(sampler.tables), "m_pairs": F.lit(m).cast("long")}
    return row.select(*(v.alias(c) for c, v in first.items()), "*")


def repeated_estimate(df: DataFrame, spec: RecordSpec, sampler: Sampler, repeats: int, **options) -> DataFrame:
    """Mean and spread over hash seeds beside the mean closed-form error, over one set of grams."""
    sets = stored(spec.sets(df, sampler.mode), "sets")
    rows = [estimate_unique_entities(df, spec, replace(sampler, seed=sampler.seed + i), sets=sets, **options) for i in range(repeats)]
    runs = reduce(DataFrame.unionByName, rows)
    return runs.agg(F.count("*").alias("repeats"), F.avg("m_pairs").alias("m_pairs"), F.avg("p").alias("p"), F.avg("estimate").alias("estimate"), F.stddev_samp("estimate").alias("sd_seeds"), F.avg("sd").alias("sd"))


def rounded(df: DataFrame, digits: int = 6) -> DataFrame:
    """Doubles rounded, for comparison with other engines."""
    return df.select(*(F.round(c, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes))
