"""Settings measured without listing pairs; candidates counted without lists."""

import pytest

import __spark_entry__ as entry
from headcount.operators import labelling as L
from headcount.operators import sampling as P
from headcount.plans import catalogue as C
from headcount.sources import tables as R
from headcount.sources.storage import stored


def test_counted_settings_equal_listed_ones(spark, tiny, monkeypatch):
    docs = R.documents(spark, tiny)
    s = stored(R.RecordSpec("rec_id", ("text",), 5, truth="entity").sets(docs), "sets")
    want = C.sweep_kl(s, ((1, 4), (2, 4), (4, 4), (8, 2), (16, 2)), "native", s.count(), L.truth_pairs(s, "rec_id", "entity")).collect()
    monkeypatch.setattr(C, "sweep_kl", lambda *a: pytest.fail("lists all pairs"))
    got = entry.queries()["sweep_kl_documents"](spark, tiny).collect()
    key = lambda rows: sorted((r["cfg"], r["m"], round(r["recall"], 9), round(r["precision"], 9), round(r["reduction"], 9)) for r in rows)
    assert key(got) == key(want) and len(got) == 5


@pytest.mark.parametrize("name", ["bucket_stats", "bucket_table", "candidates_per_record"])
def test_registry_buckets_come_from_texts(spark, tiny, monkeypatch, name):
    monkeypatch.setattr(R.RecordSpec, "sets", lambda *a, **b: pytest.fail("sets by interpreted functions"))
    monkeypatch.setattr(P, "candidates_per_record", lambda *a: pytest.fail("holds lists"))
    assert entry.queries()[name](spark, tiny).count()
