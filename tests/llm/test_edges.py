"""Null ids, repeated rows and empty tables through every operator: one result row per row, no crash."""

import pytest

from headcount.llm import decontamination, jaccard_join, language_id, packing, quality_classifier, quality_rules, secrets, sharding, substring_dedup, token_counts

LONG = " ".join(f"word{i}" for i in range(80))
PROSE = " ".join(f"the word{i} of" for i in range(40))
ROWS = [(None, LONG, "en", 1), (None, None, None, None), (5, LONG, None, None), (5, LONG, None, None), (7, LONG + " tail", "en", 3), (9, "", "de", 0), (9, "", "de", 0), (11, None, "fr", None), (2, "x" * 30_000, "en", 30_000)]


@pytest.fixture(scope="module")
def rows(spark):
    return spark.createDataFrame(ROWS, "doc_id long, text string, lang string, n_chars long")


@pytest.fixture(scope="module")
def bench(spark):
    return spark.createDataFrame([(None, LONG), (1, None), (2, " ".join(LONG.split()[:12]))], "item_id long, text string")


@pytest.mark.parametrize("empty", [False, True])
def test_every_operator(spark, rows, bench, empty):
    df = rows.where("false") if empty else rows
    n = 0 if empty else len(ROWS)
    labels = spark.createDataFrame([(5, 1), (9, 0), (None, 1), (7, None)], "doc_id long, quality int")
    assert quality_rules.judge(df).count() == n
    assert packing.pack_documents(df).where("piece = 0").count() == n
    model = quality_classifier.train(df, labels, ("n_chars",))
    assert quality_classifier.score(df, model, ("n_chars",)).where("score between 0 and 1").count() == n
    assert decontamination.hits(df, bench).count() == n
    assert secrets.scan(df).count() == n
    got = jaccard_join.jaccard_classes(df)
    assert got.count() == n
    assert {r["component_id"] for r in got.where("doc_id in (5, 7)").collect()} == (set() if empty else {5})
    out = substring_dedup.remove_repeats(df)
    assert out.count() == n
    assert {(r["doc_id"], r["n_removed"]) for r in out.where("n_removed > 0").collect()} == (set() if empty else {(7, 80)})
    assert sharding.shard(df).count() == n
    assert (token_counts.length_histogram(df).groupBy().sum("n_docs").first()[0] or 0) == n
    assert language_id.identify(df, language_id.train(df)).count() == n
    for f in (quality_rules.filter_quality, jaccard_join.drop_near_duplicates, secrets.redact_secrets, lambda d: decontamination.decontaminate(d, bench)):
        left = f(df)
        assert left.columns == df.columns and left.count() <= n


def test_columns_with_odd_names(spark, bench):
    df = spark.createDataFrame([(1, PROSE, "a", 2, 3), (2, PROSE, "b", 4, 5)], "doc_id long, text string, `_gone` string, `a.b` int, `_new` int")
    for f in (quality_rules.filter_quality, jaccard_join.drop_near_duplicates, secrets.redact_secrets, lambda d: decontamination.decontaminate(d, bench, max_coverage=1.0)):
        left = f(df)
        assert left.columns == df.columns and left.count() >= 1
