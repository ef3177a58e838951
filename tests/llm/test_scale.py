"""What small tables do not show: large benchmarks, hot keys, many lengths, long texts, thousands of matches."""

import math
import random
import re
import string
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from headcount.llm import decontamination, language_id, quality_classifier, quality_rules, secrets, sharding, shared, token_counts


def test_a_hot_group_leaves_no_shard_empty(spark):
    rng = random.Random(6)
    for share in (0.05, 0.1, 1 / 3):
        sizes = [rng.randrange(50, 150) for _ in range(4000)]
        rest = sum(sizes)
        sizes[1700] = hot = int(rest * share / (1 - share))
        cuts = [0, *sharding.minimax_cuts(sizes, 40), len(sizes)]
        parts = sorted(sum(sizes[a:b]) for a, b in zip(cuts, cuts[1:], strict=False))
        assert len(parts) == 40 and parts[-1] == hot
        assert parts[0] > 0.8 * rest / 39 and parts[-2] < 1.1 * rest / 39
    docs = spark.range(3000).selectExpr("id AS doc_id", "CASE WHEN id % 3 = 0 THEN repeat('same ', 8) ELSE concat('text of its own, number ', id) END AS text")
    got = sorted(r[1] for r in sharding.shard(docs, n_shards=10).groupBy("shard").sum("size").collect())
    assert len(got) == 10 and got[-2] < 1.1 * 2000 * 44 / 8  # the stretches before and after the group are no whole shards


def test_decontamination_of_a_benchmark_beyond_one_broadcast(spark):
    words = [f"w{i}" for i in range(600)]
    items = spark.createDataFrame([(i, " ".join(words[20 * i : 20 * i + 20])) for i in range(30)], "item_id long, text string")
    texts = [" ".join(["own"] * 40 + words[20 * i + 5 : 20 * i + 33] + ["end"] * 5) for i in range(0, 29, 4)] + ["nothing here", "", None]
    rows = [(None if i % 3 == 0 else i % 4, t) for i, t in enumerate(texts * 2)]  # null and repeated ids
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    key = lambda df: sorted(map(repr, df.collect()))
    for f in (decontamination.hits, decontamination.decontaminate):
        many, one = f(docs, items, shard_words=20, max_shards=2), f(docs, items)
        assert many.columns == one.columns and key(many) == key(one)
    assert len(key(many)) == len(rows)


def test_decontamination_of_three_megabytes_of_items(spark):
    rng = random.Random(11)
    word = lambda: "".join(rng.choice(string.ascii_lowercase) for _ in range(6))
    items = [(i, " ".join(word() for _ in range(150))) for i in range(2800)] + [(9000, " ".join(word() for _ in range(30_000)))]
    assert sum(len(t) for _, t in items) > 3_000_000
    pieces, texts = [items[i][1].split() for i in (0, 700, 1400, 2799)], {}
    for k in range(40):
        own = [word() for _ in range(60)]
        if k % 2:
            w = pieces[k % 4]
            at = rng.randrange(100)
            own[30:30] = w[at : at + 8 + k % 5]
        if k % 5 == 0:
            at = rng.randrange(29_000)
            own[10:10] = items[-1][1].split()[at : at + 25]
        texts[k] = " ".join(own)
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    bench = spark.createDataFrame(items, "item_id long, text string").repartition(4)
    windows = {}
    for i, t in items:
        w = t.split()
        for k in range(len(w) - 9):
            windows.setdefault(tuple(w[k : k + 10]), set()).add(str(i))
    held = []
    for shards, _ in decontamination._shard_passes(bench, 10, 100_000, 2):
        held.append([sum(len(t.split()) for _, t in s) for s in shards])
    assert len(held) > 2 and all(len(h) <= 2 and max(h) <= 100_000 for h in held)  # one pass, each shard within its bound
    got = {r["doc_id"]: r for r in decontamination.hits(docs, bench, max_shards=2).collect()}
    clean = {r["doc_id"]: r["text"] for r in decontamination.decontaminate(docs, bench, max_shards=2).collect()}
    for k, t in texts.items():
        w, hit, found = t.split(), set(), set()
        for j in range(len(w) - 9):
            if own := windows.get(tuple(w[j : j + 10])):
                hit |= set(range(j, j + 10))
                found |= own
        assert sum(s["b"] - s["a"] for s in got[k]["spans"]) == len(hit) and list(got[k]["items"]) == sorted(found)
        assert clean[k].split() == [x for j, x in enumerate(w) if j not in hit]


def test_the_verdict_measures_a_text_once(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    for df in (quality_rules.filter_quality(docs), quality_rules.judge(docs)):
        plan = df._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("xxhash64") == 1, plan
    kept = {r["doc_id"] for r in quality_rules.judge(docs).where("kept").collect()}
    assert {r["doc_id"] for r in quality_rules.filter_quality(docs).collect()} == kept


def test_a_hundred_thousand_lengths(spark):
    n = 100_000
    h = spark.range(n).selectExpr("id * 3 AS length", "id % 7 + 1 AS n_docs")
    got = token_counts.suffix_sums(h).orderBy("length").toPandas()
    length = np.arange(n) * 3
    docs = np.arange(n) % 7 + 1
    docs_from = docs[::-1].cumsum()[::-1]
    tokens_from = (docs * length)[::-1].cumsum()[::-1]
    assert (got.docs_from == docs_from).all() and (got.tokens_from == tokens_from).all()
    assert (got.tokens_within == (docs * length).sum() - tokens_from + docs_from * length).all()
    a = token_counts.answers(token_counts.suffix_sums(h), (1000,), (0.5, 0.99)).first()
    every = np.repeat(length, docs)
    assert a["tokens_at_1000"] == np.minimum(every, 1000).sum() and a["q500"] == every[math.ceil(0.5 * len(every)) - 1] and a["q990"] == every[math.ceil(0.99 * len(every)) - 1]


@pytest.mark.parametrize("how", ["inner", "left"])
def test_hot_keys_are_dealt_to_many_parts(spark, monkeypatch, how):
    monkeypatch.setattr(shared, "LEAST_HOT", 50)
    rows = spark.range(3000).selectExpr("CASE WHEN id % 3 = 0 THEN -1 ELSE id % 700 END AS k", "id AS v")
    few = spark.range(-1, 500).selectExpr("id AS k", "id * 2 AS w")
    counts = rows.groupBy("k").agg(F.count("*").alias("n"))
    got = shared.salted_join(rows, few, "k", counts, 3000, how)
    assert sorted(map(tuple, got.select("k", "v", "w").collect()), key=str) == sorted(map(tuple, rows.join(few, "k", how).select("k", "v", "w").collect()), key=str)
    parts = shared.salted_join(rows, few, "k", counts, 3000, how)._jdf.queryExecution().optimizedPlan().toString()
    assert "pmod" in parts.lower()


# --- secrets --------------------------------------------------------------------------------------------------------------------


def battery(run):
    """The tests of one run in plain Python."""
    core = re.sub("[^A-Za-z0-9]", "", run)
    if re.search("[+/]", run):
        k, t = 64, run.rstrip("=").replace("-", "+").replace("_", "/")
    elif re.fullmatch("[0-9a-f]+|[0-9A-F]+", core):
        k, t = 16, core.lower()
    elif re.fullmatch("[A-Z2-7]+", core):
        k, t = 32, core
    elif re.fullmatch("[0-9a-z]+|[0-9A-Z]+", core):
        k, t = 36, core.lower()
    else:
        k, t = 62, core
    x = [secrets.ALPHABETS[k].index(c) for c in t]
    n, mean, counts = len(x), sum(x) / len(x), Counter(x)
    chi = sum((counts[j] - n / k) ** 2 / (n / k) for j in range(k))
    flips = sum((a < k / 2) != (b < k / 2) for a, b in zip(x, x[1:], strict=False))
    spread = sum((c - mean) ** 2 for c in x)
    serial = sum((a - mean) * (b - mean) for a, b in zip(x, x[1:], strict=False)) / spread * math.sqrt(n) if spread else math.sqrt(n)
    pairs, even = sum(c * (c - 1) for c in counts.values()), n * (n - 1) / k
    return n, k, chi, (flips - (n - 1) / 2) / math.sqrt((n - 1) / 4), serial, (pairs - even) / math.sqrt(2 * even * (1 - 1 / k))


def runs_of(rng, kind, n):
    return "".join(rng.choice(secrets.ALPHABETS[kind]) for _ in range(n))


def test_battery_against_plain_statistics(spark):
    rng = random.Random(3)
    runs = [runs_of(rng, k, rng.randrange(20, 90)) for k in (16, 32, 36, 62, 64) for _ in range(8)]
    runs += ["aaaaaaaaaaaaaaaaaaaaaaaa1", "abcdefghijklmnopqrstuvwxyz0123456789", "internationalisation_of_words_v2", "a1------------------------", "0123456789abcdef" * 3]
    df = spark.createDataFrame([(i, r) for i, r in enumerate(runs)], "i long, r string")
    got = {x["i"]: x["s"] for x in df.select("i", secrets.randomness(F.col("r")).alias("s")).collect()}
    for i, r in enumerate(runs):
        assert [got[i][c] for c in ("n", "k", "chi", "runs", "serial", "uneven")] == pytest.approx(list(battery(r)), abs=1e-9), r
    assert [got[len(runs) - j]["p"] for j in (1, 4, 5)] == [1.0, 1.0, 1.0]


def test_battery_finds_planted_secrets_and_leaves_names_alone(spark):
    rng = random.Random(17)
    rows, n = [], 400
    for i in range(n):
        kind = (36, 62, 64)[i % 3]
        secret = runs_of(rng, kind, rng.randrange(32, 65))
        rows.append((i, f"the value in use here is {secret} and it must not be told"))
    names = ["get_user_account_settings_by_identifier_v2", "https-www-example-org-articles-2024-05-17-a-title", "LongCamelCaseIdentifierNamesAreNotSecrets1", "1234-5678-9012-3456-7890-abc", "chapter_01_section_02_paragraph_03_line_04"]
    rows += [(n + i, f"see {x} for more") for i, x in enumerate(names * 20)]
    got = {r["doc_id"]: [s["found"] for s in r["spans"] if s["kind"] == 3] for r in secrets.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    found = sum(bool(got[i]) for i in range(n)) / n
    wrong = sum(bool(got[i]) for i in range(n, len(rows)))
    print(f"recall on planted runs {found:.3f}, names taken for secrets {wrong} of {len(rows) - n}")
    assert found > 0.6 and wrong == 0


def test_thousands_of_matches_and_very_long_texts(spark):
    rng = random.Random(23)
    many = " ".join(f"{runs_of(rng, 16, 24)} w{i} " for i in range(4000))
    long = "plain words of a text, " * 60_000 + "token=abcdef123 end"
    df = spark.createDataFrame([(1, many), (2, long)], "doc_id long, text string")
    got = {r["doc_id"]: r for r in secrets.scan(df).collect()}
    want = [(m.start(), m.end()) for m in re.finditer("[0-9a-f]{24,}", many)]
    assert [(s["start"], s["end"]) for s in got[1]["base"]] == want and len(want) == 4000
    at = long.index("token=")
    assert [(s["kind"], s["start"], s["end"]) for s in got[2]["spans"]] == [(0, at, at + 15)]
    clean = {r["doc_id"]: r["text"] for r in secrets.redact_secrets(df).collect()}
    assert clean[1] == re.sub("[0-9a-f]{24,}", secrets.MASK, many) and clean[2] == long[:at] + secrets.MASK + " end"


def test_masks_of_spans_that_overlap(spark):
    spans = [(0, 0, 4), (1, 2, 6), (2, 6, 8), (0, 10, 11), (1, 10, 14)]
    df = spark.createDataFrame([("0123456789abcdef", [(k, a, b, "") for k, a, b in spans])], "t string, s array<struct<kind:int,start:int,end:int,found:string>>")
    assert df.select(secrets.redacted(F.col("t"), F.col("s"))).first()[0] == f"{secrets.MASK}{secrets.MASK}89{secrets.MASK}ef"


# --- shards ---------------------------------------------------------------------------------------------------------------------


def test_shards_are_near_equal_and_minimax(spark):
    rng = random.Random(8)
    for _ in range(20):
        sizes = [rng.randrange(16, 3000) for _ in range(1000)]
        cap = sharding.smallest_capacity(sizes, 40)
        cuts = [0, *sharding.minimax_cuts(sizes, 40), len(sizes)]
        parts = [sum(sizes[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)]
        assert len(parts) == 40 and max(parts) <= cap and min(parts) > 0.75 * sum(sizes) / 40
    texts = [f"{i} " + "x" * rng.randrange(500) for i in range(900)]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    got = sharding.shard(docs, n_shards=12)
    by = [r[1] for r in got.groupBy("shard").sum("size").collect()]
    # the optimum over the groups themselves, in the order of their hashes
    order = [r["n"] for r in docs.select((F.octet_length("text") + 16).alias("n"), F.shiftrightunsigned(F.xxhash64("text"), 1).alias("h"), F.xxhash64("text").alias("x")).orderBy(F.expr("x < 0"), "x").collect()]
    best = sharding.smallest_capacity([int(x) for x in order], 12)
    assert len(by) == 12 and best <= max(by) <= 1.02 * best and min(by) > 0.9 * sum(by) / 12


# --- models against plain forms ---------------------------------------------------------------------------------------------------


def test_scores_are_those_of_the_plain_sum_over_pairs(spark):
    rng = np.random.default_rng(4)
    m = quality_classifier.FactorizationMachine(quality_classifier.BUCKETS + quality_classifier.N_STRUCTURE * quality_classifier.BINS, 4)
    m.w0, m.w, m.v = 0.3, rng.normal(0, 0.2, m.w.shape), rng.normal(0, 0.2, m.v.shape)
    texts = {1: "a b a c", 2: "", 3: None, 4: "Some longer text!! with 12 numbers\nand lines\nand lines"}
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r["doc_id"]: r["score"] for r in quality_classifier.score(df, m).collect()}
    for i, t in texts.items():
        at, x = quality_classifier.features((t or "").encode())
        z = m.w0 + sum(m.w[a] * v for a, v in zip(at, x, strict=True))
        z += sum(float(m.v[at[a]] @ m.v[at[b]]) * x[a] * x[b] for a in range(len(at)) for b in range(a + 1, len(at)))
        assert got[i] == pytest.approx(1 / (1 + math.exp(-z)), abs=1e-5)


def test_predictions_are_those_of_a_plain_convolution(spark):
    net = language_id.ByteNetwork(["aa", "bb", "cc"], filters=3, seed=5)
    texts = {1: "Été naïve \u0430\u0431\u0432 \u03b1\u03b2\u03b3 " * 9, 2: "plain words only", 3: "\u4e2d\u6587" * 70}
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in language_id.identify(df, net).collect()}
    for i, t in texts.items():
        raw = t.encode()
        raw += b" " * (-len(raw) % language_id.WINDOW)
        total = np.zeros(3)
        for s in range(0, len(raw), language_id.WINDOW):
            x = raw[s : s + language_id.WINDOW]
            pooled = [max(sum(net.conv[w][o, x[p + o], f] for o in range(w)) for p in range(len(x) - w + 1)) for w in language_id.WIDTHS for f in range(3)]
            z = np.maximum(np.array(pooled) + net.bias, 0) @ net.out + net.shift
            total += z - np.log(np.exp(z).sum())
        p = np.exp(total / (len(raw) // language_id.WINDOW))
        assert got[i][0] == net.classes[int(p.argmax())] and got[i][1] == pytest.approx(p.max() / p.sum(), abs=1e-4)


def test_scripts_are_told_apart(spark):
    rng = random.Random(9)
    letters = {"el": "\u03b1\u03b2\u03b3\u03b4\u03b5\u03b6", "ru": "\u0430\u0431\u0432\u0433\u0434\u0435", "ar": "\u0627\u0628\u062a\u062b\u062c\u062d", "zh": "\u4e2d\u6587\u5b57\u7684\u4e00\u662f", "en": "abcdef", "EN": "ABCDEF"}
    rows = [(k * 10 + j, la, " ".join("".join(rng.choice(a) for _ in range(5)) for _ in range(30))) for k in range(60) for j, (la, a) in enumerate(letters.items())]
    df = spark.createDataFrame(rows, "doc_id long, lang string, text string")
    pred = language_id.identify(df, language_id.train(df)).join(df, "doc_id").where(quality_classifier.held_out())
    assert pred.where("lang_pred <> lang").count() == 0


# --- the pipeline on awkward tables -------------------------------------------------------------------------------------------------


def test_pipeline_of_awkward_tables(spark, tiny, tmp_path):
    pipeline = pytest.importorskip("corpus_pipeline")
    prose = " ".join(f"the word{i} of" for i in range(40))
    rows = [(None, prose, "x", 1), (1, prose, "y", 2), (1, prose, "y", 2), (2, None, None, None), (3, "", "z", 0), (4, prose + " password: abcdefgh1", "w", 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, `_row` string, slot int")
    bench = spark.createDataFrame([(1, "never to be seen in any of the texts of this table at all"), (None, prose)], "item_id long, text string")
    for case, (d, b) in enumerate(((docs, bench), (docs, bench.where("false")), (docs.where("false"), bench))):
        base = f"{tmp_path}/{case}"
        d.write.parquet(f"{base}/documents.parquet")
        b.write.parquet(f"{base}/benchmark.parquet")
        got = pipeline.run(spark, base).toPandas()
        if case == 2:
            assert got.empty and list(got.columns) == ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
        else:  # rows without an id are no copies of others; repeated rows of the least id stay together; of near copies the least stays
            assert sorted(-1 if math.isnan(x) else int(x) for x in got.doc_id) == [-1, 1, 1]
