"""The method on other kinds of records: pages, turns of conversations, vectors without copies, and uniform pairs from a source."""

from __future__ import annotations

from pyspark.sql import functions as F

from headcount.functions import hashing as H
from headcount.functions import shingles as S
from headcount.operators import labelling as L
from headcount.operators import observed as O
from headcount.operators import sampling as P
from headcount.operators.components import components_auto
from headcount.operators.textsets import TextSets
from headcount.sources import pairsource
from headcount.sources import tables as R
from headcount.sources.shipping import ship
from headcount.sources.storage import stored

from . import twins as W
from .catalogue import _EST_COLS, _MATCHED, _ROWS, _contained
from .estimate import rounded

QUERIES: dict = {}
TWINS: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            TWINS[f.__name__] = sql
        return f

    return add


# --- near copies on pages and turns ---------------------------------------------------------------------------------------

_TEXT = "regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '<script[^>]*>[\\s\\S]*?</script>', ' ', 'g'), '<style[^>]*>[\\s\\S]*?</style>', ' ', 'g'), '<!--[\\s\\S]*?-->', ' ', 'g'), '<[^>]*>', ' ', 'g')"
_PAGES = f"(SELECT page_id AS rec_id, {_TEXT} AS text FROM pages)"
_TURNS = "(SELECT conv_id * 1000000 + turn AS rec_id, text FROM conversations)"
_KNOWN = f"known AS MATERIALIZED (SELECT x.rec_id AS id_a, y.rec_id AS id_b FROM sets x JOIN sets y ON x.rec_id < y.rec_id AND len(x.tokens) >= 0.69 * len(y.tokens) AND len(y.tokens) >= 0.69 * len(x.tokens) WHERE {W.jaccard('x.tokens', 'y.tokens')} >= 0.7)"


def _twin(source: str) -> str:
    return f"WITH RECURSIVE {W.sets(source, 'rec_id', 'text', 5)}, {W.sampled(4, 4)}, {_KNOWN}, {_MATCHED}, {W.components('matched')}, {W.histogram('(SELECT count(*) FROM sets)')} " + W.estimates(f"({_ROWS})", "")


def _estimate(records):
    """The estimate of a table of texts; p is measured on all pairs of similarity .7, found by an exact join."""
    t = TextSets(records, R.DOCUMENTS)
    p = t.recall(t.known(0.7)).first()["p"]
    return rounded(O.estimate_row(t.histogram(t.matched(0.7)), p).select(*_EST_COLS))


@query(_twin(_PAGES))
def estimate_pages(spark, d):
    """Distinct pages by their text."""
    return _estimate(R.page_texts(spark, d))


@query(_twin(_TURNS))
def estimate_turns(spark, d):
    """Distinct turns of conversations."""
    return _estimate(R.turn_texts(spark, d))


def _contained_sql(source: str) -> str:
    words = "list_distinct(list_filter(string_split(text, ' '), lambda x: x <> ''))"
    return f"WITH c AS (SELECT rec_id, {words} AS w FROM {source}), b AS (SELECT item_id, {words} AS w FROM benchmark) SELECT item_id, rec_id, round(len(list_intersect(b.w, c.w))::DOUBLE / len(b.w), 6) AS containment FROM b, c WHERE len(list_intersect(b.w, c.w)) >= 0.8 * len(b.w) AND len(b.w) > 0"


def _items(spark, d):
    return R.table(spark, d, "benchmark").select("item_id", S.word_set("text").alias("w"))


@query(_contained_sql(_PAGES))
def containment_benchmark_in_pages(spark, d):
    """Items contained in the text of pages."""
    return _contained(_items(spark, d), R.page_texts(spark, d), "rec_id")


@query(_contained_sql(_TURNS))
def containment_benchmark_in_turns(spark, d):
    """Items contained in turns of conversations."""
    return _contained(_items(spark, d), R.turn_texts(spark, d), "rec_id")


# --- vectors ----------------------------------------------------------------------------------------------------------------


@query()
def sign_projection_control(spark, d):
    """W16, control: the vectors as they are, without planted copies. Labels by cosine .98 find next to nothing, so the estimate is
    about the number of vectors; p comes from the table with copies under the same signatures."""
    ship(spark)
    v = stored(R.vectors(spark, d).withColumnRenamed("vec_id", "rec_id"), "vectors")
    s = stored(v.select("rec_id", "entity", H.sign_projection(64)("vec").alias("sig")).select("rec_id", "entity", P.meta_keys("sig", 8, 8).alias("keys")), "keys")
    pairs = stored(P.sample_pairs(P.bucket_table(s, "rec_id")), "pairs")
    p = L.edge_recall(pairs, L.truth_pairs(s, "rec_id", "entity"))
    own = v.where("rec_id = entity").select("rec_id", "vec")
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b)
    j = pairs.join(own.toDF("id_a", "x"), "id_a").join(own.toDF("id_b", "y"), "id_b")
    near = stored(j.where(dot("x", "y") >= 0.98 * F.sqrt(dot("x", "x") * dot("y", "y"))).select("id_a", "id_b"), "near")
    return O.estimate_row(O.size_histogram(components_auto(near), own.count()), p)


# --- uniform pairs from a data source ---------------------------------------------------------------------------------------


@query("SELECT x.n_nationkey AS id_a, y.n_nationkey AS id_b FROM nation x JOIN nation y ON x.n_nationkey < y.n_nationkey")
def pair_source_whole(spark, d):
    """The source asked for more pairs than there are gives every pair once."""
    return pairsource.pairs_of(R.table(spark, d, "nation"), "n_nationkey", 1_000).select(F.col("id_a").cast("int"), F.col("id_b").cast("int"))


@query("SELECT count(*) * 2 AS m, count(*) * 2 AS distinct_pairs, true AS ordered FROM customer")
def pair_source_sample(spark, d):
    """Twice as many pairs as customers, none drawn twice."""
    c = R.table(spark, d, "customer")
    p = pairsource.pairs_of(c, "c_custkey", 2 * c.count(), 7)
    return p.agg(F.count("*").alias("m"), F.count_distinct("id_a", "id_b").alias("distinct_pairs"), F.min(F.col("id_a") < F.col("id_b")).alias("ordered"))
