"""All pairs that share tokens, met block by block: brute force, and no token or pair in a shuffle."""

import numpy as np
import pytest

import __spark_entry__ as entry
from headcount.functions import gramsets as G
from headcount.operators import sampling as P
from headcount.operators import setblocks as X
from headcount.plans.estimate import Sampler
from headcount.sources import tables as R
from headcount.sources.tables import RecordSpec


def test_bit_sums():
    rng = np.random.default_rng(3)
    for n in (1, 2, 3, 64, 301):
        rows = rng.integers(0, 1 << 62, (n, 3)).astype(np.uint64)
        bits = np.unpackbits(rows.view(np.uint8), axis=1, bitorder="little")
        got = sum(np.unpackbits(p.view(np.uint8), bitorder="little").astype(int) << d for d, p in enumerate(X.bit_sums(rows)))
        assert got.tolist() == bits.sum(axis=0).tolist()


@pytest.mark.parametrize(("rows", "frequent"), [(7, 64), (50, 3), (8192, 64)])
def test_blocks_against_brute_force(spark, monkeypatch, rows, frequent):
    monkeypatch.setattr(X, "ROWS", rows)
    monkeypatch.setattr(X, "FREQUENT", frequent)
    rng = np.random.default_rng(4)
    texts = ["".join(rng.choice(list("abc" if i % 3 else "xyz"), n)) for i, n in enumerate(rng.integers(1, 60, 90))]
    texts += [texts[5], texts[5][:-9], texts[8] + texts[9], "", None, "ab", "?"]
    df = spark.createDataFrame([(i, t, i % 3) for i, t in enumerate(texts)], "rec_id long, text string, lang int")
    sets = [set(s.tolist()) for _, k, n in G.sets_of([(t or "").strip("?") for t in texts], 5) for s in np.split(k, np.cumsum(n)[:-1])]
    want = {(i, j): len(a & b) / len(a | b) for j, b in enumerate(sets) for i, a in enumerate(sets[:j]) if a & b}
    b = X.SetBlocks(df, RecordSpec("rec_id", ("text",), 5), "portable", df["lang"])
    assert b.linked() == len(want) > 300
    got = b.similar(0.2).collect()
    assert {(r["id_a"], r["id_b"]): r["similarity"] for r in got} == {p: s for p, s in want.items() if s >= 0.2}
    assert len(got) == len({r[:2] for r in got}) > 5


def test_sampling_cost_counts(spark, tiny, monkeypatch):
    docs = R.table(spark, tiny, "documents").withColumnRenamed("doc_id", "rec_id")
    s = R.DOCUMENTS.sets(docs)
    want = {"sampling": Sampler(4, 8).pairs(s).count(), "all_pairs": P.all_pair_similarity(s, "rec_id", "tokens").count()}
    monkeypatch.setattr(P, "all_pair_similarity", lambda *a: pytest.fail("a row per pair and shared gram"))
    monkeypatch.setattr(Sampler, "pairs", lambda *a: pytest.fail("lists the sample"))
    assert {r["form"]: r["pairs"] for r in entry.queries()["sampling_cost"](spark, tiny).collect()} == want


def test_all_similarities_without_rows_per_gram(spark, tiny, monkeypatch):
    docs = R.table(spark, tiny, "documents").withColumnRenamed("doc_id", "rec_id")
    want = P.all_pair_similarity(R.DOCUMENTS.sets(docs, "portable"), "rec_id", "tokens", 0.2).collect()
    monkeypatch.setattr(P, "all_pair_similarity", lambda *a: pytest.fail("a row per pair and shared gram"))
    got = entry.queries()["all_pairs_similarity"](spark, tiny).collect()
    assert sorted(map(tuple, got)) == sorted((r[0], r[1], round(r[2], 6)) for r in want) and len(got) > 0
