"""Pair source, grouped pairs, neighbouring regions and text of pages against brute force."""

from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from headcount.operators import merging
from headcount.operators import sampling as P
from headcount.plans import domains
from headcount.sources import pairsource
from headcount.sources.tables import html_text, similar_pairs


@pytest.mark.parametrize("total", [1, 2, 3, 10, 300, 4096, 5050])
def test_shuffled_ranks_are_a_permutation(total):
    out = pairsource.shuffled_ranks(np.arange(total), total, 7)
    assert sorted(out.tolist()) == list(range(total))


def test_decoded_pairs():
    i, j = pairsource.decoded(np.arange(45))
    assert sorted(zip(i.tolist(), j.tolist(), strict=True)) == list(combinations(range(10), 2))
    big = np.array([2**59, 2**59 + 1, (2**29) * (2**29 - 1) // 2 - 1])
    i, j = pairsource.decoded(big)
    assert all(0 <= a < b and b * (b - 1) // 2 + a == r for a, b, r in zip(i.tolist(), j.tolist(), big.tolist(), strict=True))


def test_draws_are_near_uniform():
    hits = np.zeros(45)
    for seed in range(400):
        hits[pairsource.shuffled_ranks(np.arange(9), 45, seed)] += 1
    assert ((hits - 80) ** 2 / 80).sum() < 90  # 44 degrees of freedom


def test_source_of_few_places(spark):
    for n in (0, 1, 2):
        assert pairsource.read_pairs(spark, n, 10).count() == n * (n - 1) // 2


def test_grouped_pairs_of_a_hot_bucket(spark):
    rows = [(0, 5, i) for i in range(60)] + [(1, 5, i) for i in range(3)] + [(0, 6, 99), (0, 7, 1), (0, 7, 1)]
    b = spark.createDataFrame(rows, "tbl int, key long, rec_id long")
    got = sorted(map(tuple, P.sample_pairs_grouped(b, 7).collect()))
    assert got == list(combinations(range(60), 2))


def test_neighbours_around_the_ring(spark):
    rows = [(i, i % 5, "s", i % 3) for i in range(20)] + [(30, None, "s", 1), (31, 2, None, 1)]
    df = spark.createDataFrame(rows, "rec_id long, region int, segment string, day int")
    got = sorted(map(tuple, merging.near_days(df, "rec_id", ["region", "segment"], "day", 1, ring=5).collect()))
    want = [(x[0], y[0]) for x, y in combinations(rows[:20], 2) if (x[1] - y[1]) % 5 in (1, 4) and abs(x[3] - y[3]) <= 1]
    assert got == want


def test_html_text(spark):
    page = "<html><script>var t='</p>';</script><style>p{}</style><!-- a\n<b> --><p class='x'>one</p>\n<p>two</p>"
    got = spark.createDataFrame([(page,), (None,), ("",)], "html string").select(html_text("html").alias("t")).collect()
    assert got[0].t.split() == ["one", "two"] and got[1].t is None and got[2].t == ""


def test_similar_pairs(spark):
    sets = {1: [1, 2, 3, 4], 2: [2, 3, 4, 1], 3: [1, 2, 3], 4: [9], 5: [], 6: []}
    df = spark.createDataFrame(list(sets.items()), "rec_id long, tokens array<long>")
    got = {(r.id_a, r.id_b) for r in similar_pairs(df, 0.7).where("is_match").collect()}
    assert got == {(1, 2), (1, 3), (2, 3), (5, 6)}


def test_vectors_without_copies(spark, tiny):
    r = domains.QUERIES["sign_projection_control"](spark, tiny).first()
    assert abs(r.estimate - r.m_records) <= 0.01 * r.m_records
    assert r.p > 0.9
    assert spark.read.parquet(f"{tiny}/embeddings.parquet").agg(F.count("*")).first()[0] == r.m_records
