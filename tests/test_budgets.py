"""Estimators at equal budgets: samples counted without a list give what listed ones give."""

import pytest
from pyspark.sql import functions as F

from headcount.operators import baselines as B
from headcount.operators import labelling as L
from headcount.operators import observed as O
from headcount.operators import sampling as P
from headcount.operators.components import components_auto
from headcount.plans import workloads as W
from headcount.plans.estimate import Sampler
from headcount.sources import tables as R
from headcount.sources.storage import stored

DOCS = R.RecordSpec("rec_id", ("text",), 5, truth="entity")


@pytest.mark.parametrize("name", ["registry", "documents"])
def test_counted_runs_equal_listed_ones(spark, tiny, monkeypatch, name):
    df, spec, grid = (R.registry(spark, tiny), R.REGISTRY, ((4, 1), (4, 3))) if name == "registry" else (R.documents(spark, tiny), DOCS, ((8, 1), (4, 4)))
    if name == "documents":  # texts without a gram, alike and not
        df = df.select("rec_id", "text", "entity").union(spark.createDataFrame([(10**9, "", 10**9), (10**9 + 1, "", 10**9), (10**9 + 2, None, 10**9 + 2)], "rec_id long, text string, entity long"))
    df = stored(df, "records")
    s = stored(spec.sets(df), "sets")
    true, n, want = stored(L.truth_pairs(s, "rec_id", "entity"), "true"), s.count(), {}
    for c, (k, t) in enumerate(grid):
        for seed in (1, 2):
            pairs = stored(Sampler(k, t, seed).pairs(s), "pairs")
            row = O.estimate_row(O.size_histogram(components_auto(pairs.join(true, ["id_a", "id_b"])), n), L.edge_recall(pairs, true)).first()
            want[c, seed] = (pairs.count(), *(row[x] for x in ("p", "s1", "s2", "s3", "s_rest", "observed", "estimate")))
    monkeypatch.setattr(R.RecordSpec, "sets", lambda *a, **b: pytest.fail("gram sets are written"))
    monkeypatch.setattr(Sampler, "keys", lambda *a, **b: pytest.fail("a pass over the sets for every run"))
    got = W._runs(df, spec, grid, (1, 2)).collect()
    assert {(r["cfg"], r["seed"]): tuple(r[x] for x in ("m", "p", "s1", "s2", "s3", "s_rest", "observed", "estimate")) for r in got} == want


def test_drawn_matches_are_a_uniform_sample(spark, monkeypatch):
    monkeypatch.setattr(P, "uniform_pairs", lambda *a: pytest.fail("lists the sample"))
    df = stored(spark.range(300).select("id", F.floor(F.col("id") / 3).alias("e")), "r")
    share = [B.drawn_matches(df, "id", "e", 300 * 299 // 4, seed).count() / 300 for seed in (1, 2, 3)]
    assert len(set(share)) > 1 and all(0.4 < x < 0.6 for x in share)
    every = B.drawn_matches(df, "id", "e", 10**6).collect()
    assert {tuple(r) for r in every} == {(a, b) for a in range(300) for b in range(a + 1, 300) if a // 3 == b // 3} and len(every) == 300
    assert B.drawn_matches(df, "id", "e", 0).count() == 0
    assert B.uniform_pair_estimate(df, "id", "e", 300 * 299 // 2).first()["estimate"] == 100
