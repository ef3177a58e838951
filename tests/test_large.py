"""What only shows on tables larger than the smallest: budgets below the table, counts without listed pairs, work dealt over tasks."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from headcount.functions import measures as M
from headcount.functions.hashing import sign_projection
from headcount.operators import baselines as B
from headcount.operators import labelling as L
from headcount.operators import paircounts as C
from headcount.operators import sampling as P
from headcount.plans import workloads as W
from headcount.plans.estimate import Sampler
from headcount.sources import tables as R
from headcount.sources.storage import stored

DATA = "/root/testdata"


def test_vertex_search_without_a_finished_start(spark):
    d = f"{DATA}/sf0.1"
    con = duckdb.connect()
    for t in ("customer", "nation"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet'")
    want = con.execute(entry.oracle_sql()["vertex_bfs_estimate"]).fetchall()
    assert [tuple(r) for r in entry.queries()["vertex_bfs_estimate"](spark, d).collect()] == want
    used = B.vertex_bfs_estimate(R.registry(spark, d), "rec_id", "entity_id", 20_000).first()
    assert used["starts"] == 1 and used["estimate"] is not None  # the operator itself keeps the interrupted start


def test_registry_is_dealt_over_the_cores(spark):
    parts = R.registry(spark, f"{DATA}/sf0.1").rdd.getNumPartitions()
    assert parts == spark.sparkContext.defaultParallelism > 1


def test_pairs_are_counted_as_they_would_be_listed(spark, monkeypatch):
    rng = np.random.default_rng(4)
    keys = np.concatenate([rng.integers(0, 6, (60, 7)), np.repeat(rng.integers(0, 2, (30, 7)), 3, axis=0), np.repeat(rng.integers(0, 9, (1, 7)), 20, axis=0), rng.integers(10, 500, (40, 7))])
    df = spark.createDataFrame([(k.tolist(),) for k in keys] + [(None,)], "keys array<long>")
    want = sum((keys[i] == keys[j]).any() for j in range(len(keys)) for i in range(j))
    assert C.count_pairs(C.classes_of_keys(df), 7) == want
    monkeypatch.setattr(C, "SMALL", 1)  # by splitting
    monkeypatch.setattr(C, "BLOCK", 3)
    rows, w = np.unique(keys, axis=0, return_counts=True)
    assert sum(C.first_pairs(rows[:, t], rows[:, :t], w) for t in range(7)) + int((w * (w - 1) // 2).sum()) == want
    wide, w = np.concatenate([rng.integers(0, 40, (1500, 4)), rng.integers(0, 3, (500, 4))]), rng.integers(1, 4, 2000)
    want = sum(int((w[i] * w[i + 1 :])[~(wide[i + 1 :] == wide[i]).any(axis=1)].sum()) for i in range(2000))
    rows, at = np.unique(wide, axis=0, return_inverse=True)
    assert C._compared(rows, np.bincount(at, w).astype(np.int64)) == want
    assert C.apart(rows, np.bincount(at, w).astype(np.int64)) == want


def test_projection_lists_no_sample(spark, tiny, monkeypatch):
    r, spec = R.registry(spark, tiny), R.REGISTRY
    s = spec.sets(r).persist()
    dense = F.transform(F.sequence(F.lit(0), F.lit(127)), lambda j: F.size(F.filter("tokens", lambda x: F.pmod(x, F.lit(128)) == j)).cast("double"))
    sig = stored(stored(s.select("rec_id", dense.alias("v"))).select("rec_id", sign_projection(160)("v").alias("sig")))
    listed = {"signs": P.sample_pairs(P.bucket_table(sig.select("rec_id", P.meta_keys("sig", 20, 8).alias("keys")), "rec_id")), "minima": Sampler(3, 8).pairs(s)}
    true = L.truth_pairs(s, "rec_id", "entity")
    want = {name: M.pair_measures(p, true, s.count()).first() for name, p in listed.items()}
    monkeypatch.setattr(P, "sample_pairs", lambda *a, **b: pytest.fail("lists the sample"))
    got = {x["family"]: x[1:] for x in entry.queries()["projection_against_minhash"](spark, tiny).collect()}
    assert got == {name: tuple(x) for name, x in want.items()}


def test_lines_are_counted_by_text(spark, tiny, monkeypatch):
    s = stored(W.LONG_LINES.sets(R.lines(spark, tiny)))
    want = (s.count(), Sampler(4, 25).pairs(s).count())
    monkeypatch.setattr(R.RecordSpec, "sets", lambda *a, **b: pytest.fail("writes the sets of all lines"))
    assert entry.queries()["lines_k4_450k"](spark, tiny).first()[:2] == want
