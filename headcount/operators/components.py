"""Connected components of an edge table: distributed contraction, label propagation, and a bounded local form."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from headcount.sources.storage import dropped, stored


def _both(edges: DataFrame) -> DataFrame:
    return edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))


def _least(sym: DataFrame) -> DataFrame:
    return sym.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))


def _large_star(edges: DataFrame) -> DataFrame:
    """Link every larger neighbour to the least vertex around: a vertex of high degree costs one aggregated row, and the
    join back is a plain sort-merge join that AQE may split."""
    sym = _both(edges)
    return sym.join(_least(sym), "u").where("v > u and v > m").select(F.col("m").alias("u"), "v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Edges are (smaller u, larger v): every vertex hangs its smaller neighbours and itself on the least of them."""
    down = edges.select(F.col("v").alias("u"), F.col("u").alias("v"))  # u > v
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    hung = down.join(least, "u").where("v > m").select(F.col("m").alias("u"), "v")
    return hung.union(least.select(F.col("m").alias("u"), F.col("u").alias("v"))).distinct()


def components(edges: DataFrame, a: str = "id_a", b: str = "id_b", max_rounds: int = 60) -> DataFrame:
    """(rec_id, component): the least id reachable, for all vertices that have an edge.

    Alternating star contraction: O(log^2) rounds, two shuffles of the edges each; every round is a written table, so no
    lineage grows and a lost executor costs one round at most. Loops and repeated edges are harmless.
    """
    now = edges.select(F.least(a, b).alias("u"), F.greatest(a, b).alias("v")).where("u < v").distinct()
    seen = None
    for _ in range(max_rounds):
        before, now = now, stored(_small_star(_large_star(now)), "star")
        dropped(before)
        state = tuple(now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first())
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError("components did not settle")
    roots = now.select(F.col("u").alias("rec_id")).distinct()
    return now.select(F.col("v").alias("rec_id"), F.col("u").alias("component")).union(roots.select("rec_id", F.col("rec_id").alias("component")))


def components_propagated(edges: DataFrame, a: str = "id_a", b: str = "id_b", max_rounds: int = 1000) -> DataFrame:
    """The breadth-first form: the least label moves one edge a round. Simple, and slow on long chains."""
    sym = stored(_both(edges.select(F.col(a).alias("u"), F.col(b).alias("v")).where("u <> v")).distinct(), "edges")
    label = sym.select("u").distinct().select(F.col("u").alias("rec_id"), F.col("u").alias("component"))
    for _ in range(max_rounds):
        heard = sym.join(label, sym.v == label.rec_id).groupBy("u").agg(F.min("component").alias("heard"))
        after = label.join(heard, label.rec_id == heard.u, "left").select("rec_id", F.least("component", "heard").alias("component"), (F.col("heard") < F.col("component")).alias("moved"))
        after = stored(after, "labels")
        label = after.select("rec_id", "component")
        if after.where("moved").isEmpty():
            return label
    raise RuntimeError("labels did not settle")


def components_local(edges: DataFrame, a: str = "id_a", b: str = "id_b", limit: int = 2_000_000) -> DataFrame:
    """Union-find on the driver, refused beyond ``limit`` edges."""
    pairs = edges.select(a, b).limit(limit + 1).collect()
    if len(pairs) > limit:
        raise ValueError(f"more than {limit} edges: use components()")
    parent: dict = {}

    def root(x):
        while parent.setdefault(x, x) != x:
            parent[x] = x = parent[parent[x]]
        return x

    for x, y in pairs:
        if x != y and (p := root(x)) != (q := root(y)):
            parent[max(p, q)] = min(p, q)
    kind = edges.schema[a].dataType.simpleString()
    return edges.sparkSession.createDataFrame([(x, root(x)) for x in sorted(parent)], f"rec_id {kind}, component {kind}")


def components_auto(edges: DataFrame, a: str = "id_a", b: str = "id_b", limit: int = 200_000) -> DataFrame:
    """Local below ``limit`` edges, distributed beyond."""
    return components_local(edges, a, b, limit) if edges.limit(limit + 1).count() <= limit else components(edges, a, b)
