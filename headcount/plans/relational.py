"""The relational surface that the methods rest on: one query per operator, with its SQL twin."""

from __future__ import annotations


from pyspark.sql import Window
from pyspark.sql import functions as F

from headcount.functions import shingles as S
from headcount.operators import merging, sampling
from headcount.sources import tables as R
from headcount.sources.storage import shared_dir

from . import twins as W

QUERIES: dict = {}
TWINS: dict[str, str] = {}


def rel(sql: str | None = None):
    def add(f):
        QUERIES[f"rel_{f.__name__}"] = f
        if sql:
            TWINS[f"rel_{f.__name__}"] = sql
        return f

    return add


_t = R.table
_REG = f"WITH {W.REGISTRY}"

# --- sources and sinks ------------------------------------------------------------------------------------------------


@rel("SELECT doc_id, n_chars, lang FROM documents")
def scan_prune(spark, d):
    return _t(spark, d, "documents").select("doc_id", "n_chars", "lang")


@rel("SELECT doc_id, source, (substr(source, 4)::INT % 4)::INT AS list_id FROM documents")
def scan_union_lists(spark, d):
    docs = _t(spark, d, "documents").select("doc_id", "source")
    n = F.substring("source", 4, 9).cast("int") % 4
    return R.union_lists([docs.where(n == i) for i in range(4)])


@rel("SELECT p_partkey, p_name, p_brand, p_type, p_size, round(p_retailprice, 4) AS p_retailprice FROM part")
def csv_json_roundtrip(spark, d):
    base, p = shared_dir(spark), _t(spark, d, "part")
    p.write.option("header", True).csv(f"{base}/csv")
    p.write.json(f"{base}/json")
    c, j = R.read_list(spark, f"{base}/csv", "csv", R.SCHEMAS["part"]), R.read_list(spark, f"{base}/json", "json", R.SCHEMAS["part"])
    out = c.where("p_partkey % 2 = 0").unionByName(j.where("p_partkey % 2 = 1").select(*c.columns))
    return out.withColumn("p_retailprice", F.round("p_retailprice", 4))


@rel("SELECT o_orderkey, o_custkey FROM orders WHERE year(o_orderdate) = 1995")
def partitioned_sink(spark, d):
    base = shared_dir(spark)
    o = _t(spark, d, "orders").select("o_orderkey", "o_custkey", F.year("o_orderdate").alias("y"))
    o.repartition("y").write.partitionBy("y").parquet(f"{base}/orders")
    return spark.read.parquet(f"{base}/orders").where("y = 1995").select("o_orderkey", "o_custkey")


@rel(f"WITH RECURSIVE {W.REGISTRY}, {W.sets('registry', 'rec_id', W.REGISTRY_TEXT, 2)}, {W.sampled(2, 8)} SELECT id_a, id_b FROM pairs")
def bucketed_join(spark, d):
    """Bucket rows stored in buckets of their keys: the self-join needs no exchange."""
    from .estimate import Sampler

    b = sampling.bucket_table(Sampler(2, 8, mode="portable").keys(R.REGISTRY.sets(R.registry(spark, d), "portable")), "rec_id")
    name = f"hc_buckets_{abs(hash(d)) % 10**6}"
    path = f"{shared_dir(spark)}/buckets"
    spark.sql(f"DROP TABLE IF EXISTS {name}")
    b.write.bucketBy(16, "tbl", "key").sortBy("tbl", "key").option("path", path).mode("overwrite").saveAsTable(name)
    return sampling.sample_pairs(spark.table(name))


# --- filters ----------------------------------------------------------------------------------------------------------


@rel(f"{_REG} SELECT count(*) FILTER (street IS NULL)::BIGINT AS no_street, count(*) FILTER (street IS NULL OR balance IS NULL)::BIGINT AS any_missing, count(*) FILTER (coalesce(balance, '') = '')::BIGINT AS no_balance, count(*) FILTER (NOT (street = city))::BIGINT AS differ, count(*) FILTER (street IS NOT DISTINCT FROM balance)::BIGINT AS same_or_both_missing FROM registry")
def filter_nulls(spark, d):
    r, c = R.registry(spark, d), F.col
    return r.agg(F.count_if(c("street").isNull()).alias("no_street"), F.count_if(c("street").isNull() | c("balance").isNull()).alias("any_missing"), F.count_if(F.coalesce("balance", F.lit("")) == "").alias("no_balance"), F.count_if(~(c("street") == c("city"))).alias("differ"), F.count_if(c("street").eqNullSafe(c("balance"))).alias("same_or_both_missing"))


@rel("SELECT x.s_suppkey AS id_a, y.s_suppkey AS id_b FROM supplier x JOIN supplier y ON x.s_nationkey = y.s_nationkey AND x.s_suppkey < y.s_suppkey WHERE least(abs(x.s_acctbal), abs(y.s_acctbal)) >= 0.7 * greatest(abs(x.s_acctbal), abs(y.s_acctbal))")
def filter_length_ratio(spark, d):
    s = _t(spark, d, "supplier")
    p = sampling.block_pairs(s, "s_suppkey", ["s_nationkey"])
    b = s.select("s_suppkey", F.abs("s_acctbal").alias("b"))
    j = p.join(b.toDF("id_a", "ba"), "id_a").join(b.toDF("id_b", "bb"), "id_b")
    return j.where("least(ba, bb) >= 0.7 * greatest(ba, bb)").select("id_a", "id_b")


@rel("SELECT c_custkey FROM customer WHERE c_mktsegment IN ('BUILDING', 'MACHINERY') AND c_name LIKE '%1%' AND c_acctbal BETWEEN 0 AND 5000 AND regexp_matches(c_name, '[0-9]+[02468]$')")
def filter_like_in_between(spark, d):
    c = _t(spark, d, "customer")
    return c.where(F.col("c_mktsegment").isin("BUILDING", "MACHINERY") & F.col("c_name").like("%1%") & F.col("c_acctbal").between(0, 5000) & F.col("c_name").rlike("[0-9]+[02468]$")).select("c_custkey")


# --- joins ------------------------------------------------------------------------------------------------------------

_JOIN = "SELECT p_brand, count(*)::BIGINT AS n, round(sum(l_quantity), 2) AS qty FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand"


def _hinted(spark, d, hint):
    p = _t(spark, d, "part").select("p_partkey", "p_brand").hint(hint)
    j = _t(spark, d, "lineitem").select("l_partkey", "l_quantity").join(p, F.col("l_partkey") == F.col("p_partkey"))
    return j.groupBy("p_brand").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))


@rel(_JOIN)
def join_hash(spark, d):
    return _hinted(spark, d, "shuffle_hash")


@rel(_JOIN)
def join_merge(spark, d):
    return _hinted(spark, d, "merge")


@rel(_JOIN)
def join_broadcast(spark, d):
    return _hinted(spark, d, "broadcast")


@rel("SELECT r_name, count(*)::BIGINT AS n, count(DISTINCT p_brand)::BIGINT AS brands FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def join_star(spark, d):
    li = _t(spark, d, "lineitem").select("l_partkey", "l_suppkey")
    j = li.join(_t(spark, d, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")).join(_t(spark, d, "supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    j = j.join(F.broadcast(_t(spark, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(_t(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy("r_name").agg(F.count("*").alias("n"), F.countDistinct("p_brand").alias("brands"))


@rel("SELECT x.p_partkey AS id_a, y.p_partkey AS id_b FROM part x JOIN part y ON x.p_name = y.p_name AND x.p_brand = y.p_brand AND x.p_partkey < y.p_partkey")
def join_self_bucket(spark, d):
    return sampling.block_pairs(_t(spark, d, "part"), "p_partkey", ["p_name", "p_brand"])


@rel("SELECT x.s_suppkey AS id_a, y.s_suppkey AS id_b FROM supplier x JOIN supplier y ON x.s_suppkey < y.s_suppkey AND abs(x.s_acctbal - y.s_acctbal) < 10")
def join_theta(spark, d):
    """As a band join: bins of the width, neighbours, exact difference; no nested loop."""
    s = _t(spark, d, "supplier").select("s_suppkey", "s_acctbal")
    x = s.select(F.col("s_suppkey").alias("id_a"), F.col("s_acctbal").alias("ba"), F.floor(F.col("s_acctbal") / 10).alias("bin"))
    y = s.select(F.col("s_suppkey").alias("id_b"), F.col("s_acctbal").alias("bb"), F.explode(F.array(*(F.floor(F.col("s_acctbal") / 10) + i for i in (-1, 0, 1)))).alias("bin"))
    return x.join(y, "bin").where("id_a < id_b and abs(ba - bb) < 10").select("id_a", "id_b")


@rel("SELECT count(*)::BIGINT AS n FROM nation, region")
def join_cross(spark, d):
    return _t(spark, d, "nation").crossJoin(F.broadcast(_t(spark, d, "region"))).agg(F.count("*").alias("n"))


@rel("SELECT x.o_orderkey AS id_a, y.o_orderkey AS id_b FROM orders x JOIN orders y ON x.o_custkey = y.o_custkey AND x.o_orderkey < y.o_orderkey AND abs(date_diff('day', x.o_orderdate::DATE, y.o_orderdate::DATE)) <= 7")
def join_range_days(spark, d):
    o = _t(spark, d, "orders").select("o_orderkey", "o_custkey", F.unix_date(F.to_date("o_orderdate")).alias("day"))
    return merging.near_days(o, "o_orderkey", ["o_custkey"], "day", 7)


@rel("SELECT x.o_orderkey AS id_a, y.o_orderkey AS id_b FROM orders x JOIN orders y ON x.o_custkey = y.o_custkey AND x.o_orderkey < y.o_orderkey AND abs(date_diff('day', x.o_orderdate::DATE, y.o_orderdate::DATE)) <= 30 AND year(x.o_orderdate) <> year(y.o_orderdate)")
def join_year_border(spark, d):
    o = _t(spark, d, "orders").select("o_orderkey", "o_custkey", F.unix_date(F.to_date("o_orderdate")).alias("day"))
    p = merging.near_days(o, "o_orderkey", ["o_custkey"], "day", 30)
    y = o.select("o_orderkey", F.year(F.date_from_unix_date(F.col("day"))).alias("y"))
    return p.join(y.toDF("id_a", "ya"), "id_a").join(y.toDF("id_b", "yb"), "id_b").where("ya <> yb").select("id_a", "id_b")


@rel("WITH p AS (SELECT * FROM events WHERE event_type = 'purchase'), o AS (SELECT user_id, ts, event_id FROM events WHERE event_type <> 'purchase'), j AS (SELECT p.event_id, max((o.ts, o.event_id)) AS m FROM p LEFT JOIN o ON p.user_id = o.user_id AND o.ts < p.ts GROUP BY p.event_id) SELECT event_id, m[2] AS before FROM j".replace("m[2]", "struct_extract_at(m, 2)"))
def join_asof(spark, d):
    """Last other event of the user before each purchase: one window over the union, no range join."""
    e = _t(spark, d, "events").select("event_id", "user_id", "ts", (F.col("event_type") == "purchase").alias("buy"))
    timed = e.withColumn("u", F.unix_micros(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("u").rangeBetween(Window.unboundedPreceding, -1)
    last = F.max(F.when(~F.col("buy"), F.struct("u", "event_id"))).over(w)
    return timed.withColumn("before", last["event_id"]).where("buy").select("event_id", "before")


@rel("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def join_semi(spark, d):
    return _t(spark, d, "documents").select("doc_id").join(_t(spark, d, "labels"), "doc_id", "left_semi")


@rel("SELECT doc_id FROM documents x WHERE NOT EXISTS (SELECT 1 FROM documents y WHERE y.text = x.text AND y.doc_id <> x.doc_id)")
def join_anti(spark, d):
    docs = R.documents(spark, d)
    edges = R.clique_edges(docs, "rec_id", ["entity"])
    touched = edges.select(F.explode(F.array("id_a", "id_b")).alias("rec_id")).distinct()
    return docs.select("rec_id").join(touched, "rec_id", "left_anti").select(F.col("rec_id").alias("doc_id"))


@rel(f"{_REG}, s AS (SELECT x.rec_id AS a, y.rec_id AS b FROM registry x JOIN registry y ON x.city = y.city AND x.rec_id < y.rec_id), t AS (SELECT x.rec_id AS a, y.rec_id AS b FROM registry x JOIN registry y ON x.entity_id = y.entity_id AND x.rec_id < y.rec_id) SELECT count(*) FILTER (s.a IS NOT NULL AND t.a IS NOT NULL)::BIGINT AS tp, count(*) FILTER (t.a IS NULL)::BIGINT AS fp, count(*) FILTER (s.a IS NULL)::BIGINT AS fn FROM s FULL JOIN t ON s.a = t.a AND s.b = t.b")
def join_full_confusion(spark, d):
    r = R.registry(spark, d)
    s = sampling.block_pairs(r, "rec_id", ["city"]).withColumn("s", F.lit(1))
    t = sampling.block_pairs(r, "rec_id", ["entity_id"]).withColumn("t", F.lit(1))
    j = s.join(t, ["id_a", "id_b"], "full")
    return j.agg(F.count_if(F.col("s").isNotNull() & F.col("t").isNotNull()).alias("tp"), F.count_if(F.col("t").isNull()).alias("fp"), F.count_if(F.col("s").isNull()).alias("fn"))


@rel("SELECT e.event_type, count(*)::BIGINT AS n, round(sum(value - a), 2) AS spread FROM events e JOIN (SELECT event_type, avg(value) AS a FROM events GROUP BY event_type) x ON e.event_type = x.event_type GROUP BY e.event_type".replace("round(sum(value - a), 2) AS spread", "count(DISTINCT user_id)::BIGINT AS users"))
def join_skew(spark, d):
    """A few hot keys: the large side is salted, the small side repeated once per salt."""
    salts = 8
    e = _t(spark, d, "events").select("event_type", "user_id", F.pmod(F.xxhash64("event_id"), F.lit(salts)).alias("salt"))
    a = _t(spark, d, "events").groupBy("event_type").agg(F.avg("value").alias("a"))
    a = a.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))).alias("salt"))
    return e.join(a, ["event_type", "salt"]).groupBy("event_type").agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("users"))



# --- aggregation ------------------------------------------------------------------------------------------------------


@rel("SELECT l_partkey, l_suppkey, count(*)::BIGINT AS n, min(l_quantity) AS lo, max(l_quantity) AS hi, round(avg(l_quantity), 4) AS mean FROM lineitem GROUP BY l_partkey, l_suppkey")
def agg_basic(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_partkey", "l_suppkey").agg(F.count("*").alias("n"), F.min("l_quantity").alias("lo"), F.max("l_quantity").alias("hi"), F.round(F.avg("l_quantity"), 4).alias("mean"))


@rel("SELECT size::BIGINT AS size, count(*)::BIGINT AS n FROM (SELECT count(*) AS size FROM events GROUP BY user_id) GROUP BY size")
def agg_two_level_histogram(spark, d):
    return _t(spark, d, "events").groupBy("user_id").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("n"))


@rel("SELECT count(DISTINCT text)::BIGINT AS texts, count(DISTINCT lang)::BIGINT AS langs FROM documents")
def agg_distinct(spark, d):
    return _t(spark, d, "documents").agg(F.countDistinct(F.md5(F.col("text").cast("binary"))).alias("texts"), F.countDistinct("lang").alias("langs"))


@rel()
def agg_distinct_approx(spark, d):
    docs = _t(spark, d, "documents")
    return docs.agg(F.approx_count_distinct("text", 0.02).alias("hll"), F.hll_sketch_estimate(F.hll_sketch_agg(F.xxhash64("text"))).alias("sketch"))


@rel("SELECT count(*)::BIGINT AS n, count(*) FILTER (quality = 1)::BIGINT AS good, sum(CASE WHEN toxic = 1 THEN 1 ELSE 0 END)::BIGINT AS toxic FROM labels")
def agg_filter(spark, d):
    return _t(spark, d, "labels").agg(F.count("*").alias("n"), F.count_if(F.col("quality") == 1).alias("good"), F.sum(F.when(F.col("toxic") == 1, 1).otherwise(0)).alias("toxic"))


_G = "SELECT lang, source, grouping(lang)::INT AS gl, grouping(source)::INT AS gs, count(*)::BIGINT AS n, count(DISTINCT md5(text))::BIGINT AS texts FROM documents GROUP BY {}"


def _grouped(g):
    return g.agg(F.grouping("lang").cast("int").alias("gl"), F.grouping("source").cast("int").alias("gs"), F.count("*").alias("n"), F.countDistinct("h").alias("texts"))


def _docs_hashed(spark, d):
    return _t(spark, d, "documents").select("lang", "source", F.md5(F.col("text").cast("binary")).alias("h"))


@rel(_G.format("ROLLUP (lang, source)"))
def agg_rollup(spark, d):
    return _grouped(_docs_hashed(spark, d).rollup("lang", "source"))


@rel(_G.format("CUBE (lang, source)"))
def agg_cube(spark, d):
    return _grouped(_docs_hashed(spark, d).cube("lang", "source"))


@rel(_G.format("GROUPING SETS ((lang), (source), ())"))
def agg_sets(spark, d):
    return _grouped(_docs_hashed(spark, d).groupingSets([["lang"], ["source"], []], "lang", "source"))


@rel("SELECT source, count(*) FILTER (lang = 'en')::BIGINT AS en, count(*) FILTER (lang = 'de')::BIGINT AS de, count(*) FILTER (lang = 'fr')::BIGINT AS fr, count(*) FILTER (lang = 'es')::BIGINT AS es FROM documents GROUP BY source")
def agg_pivot(spark, d):
    return _t(spark, d, "documents").groupBy("source").pivot("lang", ["en", "de", "fr", "es"]).agg(F.count(F.lit(1))).fillna(0)


@rel("SELECT round(stddev_samp(s), 6) AS sd, quantile_cont(s, 0.9)::DOUBLE AS q90, max(s)::BIGINT AS top FROM (SELECT count(*) AS s FROM orders GROUP BY o_custkey)")
def agg_stats(spark, d):
    s = _t(spark, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("s"))
    return s.agg(F.round(F.stddev_samp("s"), 6).alias("sd"), F.percentile("s", 0.9).alias("q90"), F.max("s").alias("top"))


@rel("SELECT p_name, p_brand, array_to_string(list_sort(list(p_partkey)), ',') AS members FROM part GROUP BY p_name, p_brand HAVING count(*) > 1")
def agg_collect(spark, d):
    g = _t(spark, d, "part").groupBy("p_name", "p_brand").agg(F.sort_array(F.collect_list("p_partkey")).alias("m")).where(F.size("m") > 1)
    return g.select("p_name", "p_brand", F.array_join(F.col("m").cast("array<string>"), ",").alias("members"))


# --- windows and top k ------------------------------------------------------------------------------------------------


@rel("SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)".replace("rank() OVER w", "rank() OVER w").replace(" AS rn", "::INT AS rn").replace(" AS rk", "::INT AS rk").replace(" AS dr", "::INT AS dr").replace(" AS nt", "::INT AS nt"))
def win_rank(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return _t(spark, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("nt"))


@rel("SELECT event_id, epoch_us(ts) - lag(epoch_us(ts)) OVER w AS gap, lead(event_id) OVER w AS next FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_leadlag(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    u = F.unix_micros(F.col("ts").cast("timestamp"))
    return _t(spark, d, "events").select("event_id", (u - F.lag(u).over(w)).alias("gap"), F.lead("event_id").over(w).alias("next"))


@rel("SELECT l_orderkey, l_linenumber, l_partkey, sum(l_quantity) OVER (PARTITION BY l_suppkey ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey, l_quantity ROWS UNBOUNDED PRECEDING) AS running FROM lineitem")
def win_rows_frame(spark, d):
    w = Window.partitionBy("l_suppkey").orderBy("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity").rowsBetween(Window.unboundedPreceding, 0)
    return _t(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.sum("l_quantity").over(w).alias("running"))



@rel("WITH o AS (SELECT o_orderkey, o_custkey, date_diff('day', DATE '1970-01-01', o_orderdate::DATE) AS day FROM orders) SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY day RANGE BETWEEN 7 PRECEDING AND CURRENT ROW)::BIGINT AS n FROM o")
def win_range_frame(spark, d):
    o = _t(spark, d, "orders").select("o_orderkey", "o_custkey", F.unix_date(F.to_date("o_orderdate")).alias("day"))
    return o.select("o_orderkey", F.count("*").over(Window.partitionBy("o_custkey").orderBy("day").rangeBetween(-7, 0)).alias("n"))


@rel("WITH e AS (SELECT user_id, event_id, CASE WHEN event_type = 'purchase' THEN value END AS v FROM events) SELECT event_id, first_value(v IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS filled FROM e")
def win_fill(spark, d):
    e = _t(spark, d, "events").select("user_id", "event_id", F.when(F.col("event_type") == "purchase", F.col("value")).alias("v"))
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(0, Window.unboundedFollowing)
    return e.select("event_id", F.first("v", ignorenulls=True).over(w).alias("filled"))


@rel("WITH c AS (SELECT o_custkey, o_orderpriority AS v, count(*) AS n FROM orders GROUP BY ALL) SELECT o_custkey, v AS priority FROM c QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY n DESC, v) = 1")
def win_majority(spark, d):
    c = _t(spark, d, "orders").groupBy("o_custkey", F.col("o_orderpriority").alias("priority")).agg(F.count("*").alias("n"))
    w = Window.partitionBy("o_custkey").orderBy(F.desc("n"), "priority")
    return c.withColumn("r", F.row_number().over(w)).where("r = 1").select("o_custkey", "priority")


@rel("SELECT l_orderkey, count(*)::BIGINT AS size FROM lineitem GROUP BY l_orderkey ORDER BY size DESC, l_orderkey LIMIT 20")
def topk_global(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("size")).orderBy(F.desc("size"), "l_orderkey").limit(20)


@rel("SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def topk_per_group(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return _t(spark, d, "orders").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey")


# --- set operations ---------------------------------------------------------------------------------------------------

_S1, _S2 = "SELECT l_partkey AS k FROM lineitem WHERE l_quantity < 10", "SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 45"


def _two(spark, d):
    li = _t(spark, d, "lineitem")
    return li.where("l_quantity < 10").select(F.col("l_partkey").alias("k")), li.where("l_quantity > 45").select(F.col("l_partkey").alias("k"))


for _op, _sqlop, _f in (
    ("union", "UNION", lambda a, b: a.union(b).distinct()),
    ("union_all", "UNION ALL", lambda a, b: a.union(b)),
    ("intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("except", "EXCEPT", lambda a, b: a.subtract(b)),
    ("except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    QUERIES[f"rel_set_{_op}"] = lambda spark, d, f=_f: f(*_two(spark, d))
    TWINS[f"rel_set_{_op}"] = f"{_S1} {_sqlop} {_S2}"


@rel(f"({_S1} EXCEPT {_S2}) UNION ALL ({_S2} EXCEPT {_S1})")
def set_symdiff(spark, d):
    a, b = _two(spark, d)
    return a.subtract(b).union(b.subtract(a))


# --- strings, dates, numbers ------------------------------------------------------------------------------------------


@rel(f"SELECT doc_id, md5({W.norm('text')}) AS digest FROM documents")
def str_normalise(spark, d):
    return _t(spark, d, "documents").select("doc_id", F.md5(S.normalise("text").cast("binary")).alias("digest"))


@rel(f"{_REG} SELECT x.rec_id AS id_a, y.rec_id AS id_b, levenshtein(x.full_name, y.full_name)::INT AS edits FROM registry x JOIN registry y ON x.entity_id = y.entity_id AND x.rec_id < y.rec_id")
def str_distance(spark, d):
    r = R.registry(spark, d)
    p = sampling.block_pairs(r, "rec_id", ["entity_id"])
    n = r.select("rec_id", "full_name")
    return p.join(n.toDF("id_a", "x"), "id_a").join(n.toDF("id_b", "y"), "id_b").select("id_a", "id_b", F.levenshtein("x", "y").alias("edits"))


@rel("SELECT w, count(*)::BIGINT AS n FROM (SELECT unnest(string_split(text, ' ')) AS w FROM benchmark) WHERE w <> '' GROUP BY w")
def str_split_explode(spark, d):
    return _t(spark, d, "benchmark").select(F.explode(F.split("text", " ")).alias("w")).where("w <> ''").groupBy("w").agg(F.count("*").alias("n"))


@rel("SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:]+)', 1) AS host, length(regexp_replace(html, '<[^>]*>', '', 'g'))::INT AS text_length FROM pages")
def str_url_html(spark, d):
    return _t(spark, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/:]+)", 1).alias("host"), F.length(F.regexp_replace("html", "<[^>]*>", "")).alias("text_length"))


@rel(f"SELECT p_partkey, {W.token('p_name')} AS token FROM part")
def str_md5_hash(spark, d):
    return _t(spark, d, "part").select("p_partkey", S.token_number(F.col("p_name")).alias("token"))


@rel("SELECT o_orderkey, year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, day(o_orderdate)::INT AS dd, quarter(o_orderdate)::INT AS q FROM orders")
def date_parts(spark, d):
    o = F.col("o_orderdate")
    return _t(spark, d, "orders").select("o_orderkey", F.year(o).alias("y"), F.month(o).alias("m"), F.dayofmonth(o).alias("dd"), F.quarter(o).alias("q"))


@rel("SELECT l_orderkey, l_linenumber, l_partkey, date_diff('day', o_orderdate::DATE, l_shipdate::DATE)::INT AS days FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def date_diff(spark, d):
    li = _t(spark, d, "lineitem")
    j = li.join(_t(spark, d, "orders").select("o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.select("l_orderkey", "l_linenumber", "l_partkey", F.datediff(F.to_date("l_shipdate"), F.to_date("o_orderdate")).alias("days"))



@rel("SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*)::BIGINT AS n FROM orders GROUP BY 1")
def date_trunc(spark, d):
    return _t(spark, d, "orders").groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month")).agg(F.count("*").alias("n"))


@rel("SELECT s_suppkey, round(sqrt(abs(s_acctbal)), 6) AS root, round(ln(1 + abs(s_acctbal)), 6) AS log, round(pow(abs(s_acctbal) / 20000, 0.5), 6) AS p, (s_suppkey & 7)::BIGINT AS low, CASE WHEN s_nationkey = 0 THEN NULL ELSE round(s_acctbal / s_nationkey, 9) END AS safe FROM supplier")
def math(spark, d):
    b = F.abs("s_acctbal")
    return _t(spark, d, "supplier").select("s_suppkey", F.round(F.sqrt(b), 6).alias("root"), F.round(F.log1p(b), 6).alias("log"), F.round(F.pow(b / 20000, F.lit(0.5)), 6).alias("p"), F.col("s_suppkey").bitwiseAND(7).alias("low"), F.round(F.try_divide("s_acctbal", "s_nationkey"), 9).alias("safe"))


# --- arrays, maps, JSON -----------------------------------------------------------------------------------------------

_W2 = "WITH w AS (SELECT item_id, string_split(text, ' ') AS a, list_transform(string_split(text, ' '), lambda x: lower(x)) AS b FROM benchmark) "


@rel(_W2 + "SELECT item_id, len(list_intersect(a, b))::INT AS both, len(list_distinct(list_concat(a, b)))::INT AS either, len(list_distinct(list_filter(a, lambda x: NOT list_contains(b, x))))::INT AS only_a, len(list_distinct(a))::INT AS distinct_a, array_to_string(a[1:3], ' ') AS head FROM w")
def array_ops(spark, d):
    w = _t(spark, d, "benchmark").select("item_id", F.split("text", " ").alias("a"), F.split(F.lower("text"), " ").alias("b"))
    return w.select("item_id", F.size(F.array_intersect("a", "b")).alias("both"), F.size(F.array_union("a", "b")).alias("either"), F.size(F.array_except("a", "b")).alias("only_a"), F.size(F.array_distinct("a")).alias("distinct_a"), F.array_join(F.slice("a", 1, 3), " ").alias("head"))


@rel(_W2 + "SELECT item_id, list_sum(list_transform(a, lambda x: length(x)))::BIGINT AS chars, len(list_filter(a, lambda x: length(x) > 5))::INT AS long_words, len(list_filter(a, lambda x: x = 'the')) > 0 AS has_the, len(list_filter(range(1, len(a) + 1), lambda i: a[i] = b[i]))::INT AS lower_already FROM w")
def array_hof(spark, d):
    w = _t(spark, d, "benchmark").select("item_id", F.split("text", " ").alias("a"), F.split(F.lower("text"), " ").alias("b"))
    same = F.filter(F.zip_with("a", "b", lambda x, y: x == y), lambda x: x)
    return w.select("item_id", F.aggregate("a", F.lit(0).cast("long"), lambda s, x: s + F.length(x)).alias("chars"), F.size(F.filter("a", lambda x: F.length(x) > 5)).alias("long_words"), F.exists("a", lambda x: x == "the").alias("has_the"), F.size(same).alias("lower_already"))


@rel("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm2, round(list_sum(list_transform(range(1, 64), lambda i: embedding[i]::DOUBLE * embedding[i + 1]::DOUBLE)), 4) AS lag1 FROM embeddings")
def array_vector(spark, d):
    e = _t(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + F.coalesce(x, F.lit(0.0)))
    return e.select("vec_id", F.round(dot("v", "v"), 4).alias("norm2"), F.round(dot(F.slice("v", 1, 63), F.slice("v", 2, 63)), 4).alias("lag1"))


@rel("SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")
def json_props(spark, d):
    return _t(spark, d, "events").select("event_id", F.from_json("props", "map<string,string>")["k"].alias("k"))


@rel("SELECT user_id, event_type, count(*)::BIGINT AS n FROM events GROUP BY user_id, event_type")
def map_ops(spark, d):
    g = _t(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return g.select("user_id", F.explode("m").alias("event_type", "n"))


# --- subqueries, recursion, functions ---------------------------------------------------------------------------------


def _views(spark, d, *names):
    for n in names:
        _t(spark, d, n).createOrReplaceTempView(n)
    return spark


_SCALAR = "SELECT size, n, round(n * CASE WHEN size = 2 THEN (2 * p - 1) / p ELSE 1 END, 6) AS weighted FROM (SELECT size, count(*) AS n, (SELECT count(*) * 1.0e0 / (SELECT count(*) FROM documents) FROM labels) AS p FROM (SELECT count(*) AS size FROM lineitem GROUP BY l_partkey, l_suppkey) z GROUP BY size) y"


@rel(_SCALAR)
def subquery_scalar(spark, d):
    return _views(spark, d, "documents", "labels", "lineitem").sql(_SCALAR)


_EXISTS = "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 200000)"


@rel(_EXISTS)
def subquery_exists(spark, d):
    return _views(spark, d, "customer", "orders").sql(_EXISTS)


@rel("SELECT p_partkey, g FROM part, LATERAL (SELECT DISTINCT substring(p_brand, i, 2) AS g FROM (SELECT unnest(range(1, length(p_brand))) AS i))")
def subquery_lateral(spark, d):
    return _views(spark, d, "part").sql("SELECT p_partkey, g FROM part, LATERAL (SELECT explode(array_distinct(transform(sequence(1, length(p_brand) - 1), i -> substring(p_brand, i, 2)))) AS g)")


_RECURSE = "WITH RECURSIVE e(a, b) AS (SELECT * FROM (SELECT o_orderkey AS a, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS b FROM orders) t WHERE b IS NOT NULL), r(x, y, depth) AS (SELECT a, b, 1 FROM e UNION ALL SELECT r.x, e.b, r.depth + 1 FROM r JOIN e ON r.y = e.a WHERE r.depth < 3) SELECT x AS rec_id, least(x, min(y)) AS component FROM r GROUP BY x"


@rel(_RECURSE)
def cte_recursive(spark, d):
    """Orders of a customer, each linked with the one before: the least within three links. The limit of rows is lifted: three per
    order are made."""
    spark.conf.set("spark.sql.cteRecursionRowLimit", "-1")
    return _views(spark, d, "orders").sql(_RECURSE)


@rel(f"SELECT o_orderkey FROM orders WHERE {W.hash32('o_orderkey')} < 429496729")
def sample_hash(spark, d):
    return _t(spark, d, "orders").where(R.portable_hash("o_orderkey") < 429_496_729).select("o_orderkey")


@rel("SELECT c_custkey, concat_ws('|', c_custkey::VARCHAR, c_nationkey::VARCHAR, c_acctbal::BIGINT::VARCHAR, CASE WHEN c_acctbal < 0 THEN 'debt' ELSE 'ok' END) AS t FROM customer".replace("c_acctbal::BIGINT", "trunc(c_acctbal)::BIGINT"))
def case_cast(spark, d):
    return _t(spark, d, "customer").select("c_custkey", S.record_text([F.col("c_custkey"), F.col("c_nationkey"), F.col("c_acctbal").cast("long"), F.when(F.col("c_acctbal") < 0, "debt").otherwise("ok")], "|").alias("t"))


@rel("SELECT k, l, round(1 - pow(1 - pow(0.7, k), l), 6) AS p FROM (SELECT unnest([1, 4, 8])::INT AS k, unnest([8, 25, 25])::INT AS l)")
def udf_sqlfn(spark, d):
    from headcount.functions.sqlfuncs import register

    register(spark)
    return spark.sql("SELECT k, l, round(retrieval_probability(0.7D, k, l), 6) AS p FROM VALUES (1, 8), (4, 25), (8, 25) AS t(k, l)")


@rel(f"SELECT p_partkey, unnest({W.grams('p_brand', 2)}) AS gram FROM part")
def udf_udtf(spark, d):
    from headcount.functions.sqlfuncs import register

    register(spark)
    return _views(spark, d, "part").sql("SELECT p_partkey, g.gram FROM part, LATERAL grams(p_brand, 2) g")


@rel(f"WITH {W.REGISTRY}, {W.sets('registry', 'rec_id', W.REGISTRY_TEXT, 2)}, {W.sampled(2, 8)} SELECT rec_id, tbl::INT AS tbl, key::BIGINT AS key FROM buckets")
def udf_bucket_rows(spark, d):
    from headcount.functions.sqlfuncs import register

    register(spark)
    R.REGISTRY.sets(R.registry(spark, d), "portable").createOrReplaceTempView("registry_sets")
    return spark.sql("SELECT rec_id, b.tbl, b.key FROM registry_sets, LATERAL bucket_rows(rec_id, tokens, 2, 8, 42) b")


@rel("SELECT round(sum(n * CASE WHEN size = 2 THEN (2 * 0.83 - 1) / 0.83 WHEN size = 3 THEN (1 - 6 * 0.83 * 0.0289) / (0.6889 * (3 - 1.66)) ELSE 1 END), 4) AS estimate FROM (SELECT count(*) AS size FROM part GROUP BY p_name, p_brand) z, LATERAL (SELECT 1 AS n)")
def udf_udaf(spark, d):
    from headcount.functions.sqlfuncs import register

    register(spark)
    return _views(spark, d, "part").sql("SELECT round(entity_estimate(size, 1L, 0.83D), 4) AS estimate FROM (SELECT count(*) AS size FROM part GROUP BY p_name, p_brand) z")


@rel()
def udf_scalar(spark, d):
    from headcount.functions.sqlfuncs import register

    register(spark)
    return _views(spark, d, "part").sql("SELECT p_partkey, size(minhash_signature(token_ids)) AS b FROM (SELECT p_partkey, array(xxhash64(p_name), xxhash64(p_brand)) AS token_ids FROM part) z")
