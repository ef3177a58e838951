"""Sets that are never written: the numpy rows against the built-in functions, pairs against brute force."""

import numpy as np
import pytest

import __spark_entry__ as entry
from headcount.functions import gramsets as G
from headcount.functions import hashing as H
from headcount.functions import shingles as S
from headcount.operators import textsets as X
from headcount.sources.tables import RecordSpec

TEXTS = ["", None, "a", "abcd", "abcde", "ünïcödéß", "smile\U0001f600twice\U0001f600smile", "ab" * 3000, "ottermay" * 3, "".join(chr(0x4E00 + i) for i in range(5000))]


def test_sets_are_those_of_the_columns(spark, monkeypatch):
    monkeypatch.setattr(G, "PIECE", 50)
    df = spark.createDataFrame(list(enumerate(TEXTS)), "i int, s string")
    want = {r["i"]: r for r in df.select("i", S.token_ids(S.char_grams("s", 5), "portable").alias("t")).select("i", "t", H.minhash("t", 8).alias("m")).collect()}
    for start, tokens, lengths in G.sets_of(TEXTS, 5):
        sig = G.signatures(tokens, lengths, 8, 42, "portable")
        for j, part in enumerate(np.split(tokens, np.cumsum(lengths)[:-1])):
            r = want[start + j]
            assert part.tolist() == sorted(r["t"])
            assert r["m"] is None if not len(part) else sig[j].tolist() == r["m"]


def test_parities_never_exceed_the_difference():
    rng = np.random.default_rng(1)
    a = np.unique(rng.integers(0, 1 << 31, 900))
    b = np.unique(np.concatenate([a[:500], rng.integers(0, 1 << 31, 100)]))
    x, y = G.parities(np.concatenate([a, b]), np.array([len(a), len(b)]))
    w = min(len(x), len(y))
    apart = np.bitwise_count((G.folded(x[None], w) ^ G.folded(y[None], w)).view(np.uint64)).sum()
    assert 0 < apart <= len(np.setxor1d(a, b))


def test_known_and_sampled_pairs(spark, monkeypatch):
    monkeypatch.setattr(X, "BLOCK", 7)
    rng = np.random.default_rng(2)
    base = ["".join(rng.choice(list("abcdefgh"), n)) for n in rng.integers(20, 300, 25)]
    texts = [t[: int(len(t) * f)] for t in base for f in (1.0, 1.0, 0.9, 0.75, 0.5)] + ["", "", None]
    df = spark.createDataFrame(list(enumerate(texts)), "rec_id long, text string")
    t = X.TextSets(df, RecordSpec("rec_id", ("text",), 5))
    sets = [set(s.tolist()) for s in (p for _, k, n in G.sets_of(texts, 5) for p in np.split(k, np.cumsum(n)[:-1]))]
    true = {(i, j): 1.0 if not sets[i] | sets[j] else len(sets[i] & sets[j]) / len(sets[i] | sets[j]) for j in range(len(sets)) for i in range(j)}
    want = {p for p, s in true.items() if s >= 0.7}
    known = t.known(0.7)
    assert sum(r["w"] for r in known.collect()) == len(want)
    keys = {r["rec_id"]: r["keys"] for r in t.rows.collect()}
    sampled = {p for p in true if keys[p[0]] and keys[p[1]] and any(x == y for x, y in zip(keys[p[0]], keys[p[1]], strict=True))}
    assert t.n_pairs(0.7) == len(sampled)
    r = t.recall(known).first()
    assert (r["n_labelled"], r["hits"]) == (len(want), len(want & sampled))
    edges = t.record_pairs(t.matched(0.7)).union(t.copies()).collect()
    assert {tuple(e) for e in edges} == want & sampled and len(edges) == len(want & sampled)


WRITES_NO_SETS = [
    "estimate_by_lang",
    "estimate_by_list",
    "estimate_documents",
    "estimate_documents_native",
    "estimate_pages",
    "labelled_recall",
    "labelled_recall_by_keys",
    "model_implied_recall",
    "partial_label_documents",
    "clique_check",
    "estimate_turns",
    "observed_histogram",
    "threshold_labels",
    "components_lsh",
]


@pytest.mark.parametrize("name", WRITES_NO_SETS)
def test_no_set_is_written(spark, tiny, monkeypatch, name):
    monkeypatch.setattr(RecordSpec, "sets", lambda *a, **b: pytest.fail("gram sets take several times the room of the texts"))
    assert entry.queries()[name](spark, tiny).count()


@pytest.mark.parametrize(("rows", "theta"), [(7, 0.7), (7, 0.4), (1000, 0.7)])
def test_near_pairs_are_all_pairs(spark, monkeypatch, rows, theta):
    from pyspark.sql.group import GroupedData

    monkeypatch.setattr(X, "BLOCK", rows)
    monkeypatch.setattr(X, "BYTES", 1)
    monkeypatch.setattr(GroupedData, "applyInArrow", lambda *a: pytest.fail("a block is shuffled to every cell it meets"))
    rng = np.random.default_rng(6)
    sets = [np.unique(rng.integers(0, 1 << 31, n)) for n in (3, 40, 44, 90, 200, 1500, 1600, 90_000)]
    sets += [np.unique(np.concatenate([s[: int(len(s) * f)], rng.integers(0, 1 << 31, len(s) // 20)])) for s in sets for f in (1.0, 0.9, 0.75, 0.5)]
    n = np.array(list(map(len, sets)))
    bits = G.parities(np.concatenate(sets), n)
    df = spark.createDataFrame([(i, i % 2, int(n[i]), bits[i].tolist()) for i in range(len(sets))], "rec_id long, grp long, n int, bits array<long>")

    def near(i, j):
        w, most = min(len(bits[i]), len(bits[j])), (n[i] + n[j]) * (1 - theta) / (1 + theta) + 1e-6
        apart = np.bitwise_count((G.folded(bits[i][None], w) ^ G.folded(bits[j][None], w)).view(np.uint64)).sum()
        return (i - j) % 2 == 0 and apart <= most

    got = [tuple(r) for r in X.near_pairs(df, theta).collect()]
    want = {(i, j) for j in range(len(sets)) for i in range(j) if near(i, j) and min(n[i], n[j]) >= theta * max(n[i], n[j])}
    assert want <= set(got) and len(got) == len(set(got)) and len(want) > 10
    assert all(near(*p) for p in got)  # sizes may be let through, never held back
