"""Sharding by a minimax contiguous partition of atomic groups, with DataFrame functions only.

Groups (equal texts) stand in the order of a hash of their text. Neighbouring groups form ``2**bin_bits`` atomic blocks, a
fixed number whatever the size of the data, so one aggregation gives an ordered list of block sizes that is small enough for
the driver; while there are far fewer groups than blocks, nearly every block is one group. A binary search finds the smallest
capacity for which a greedy pass needs no more than ``n_shards`` shards. Any cuts that keep this capacity are minimax cuts; of
those, the ones taken leave every shard as near as may be to an equal share of what is left, so that the slack does not
gather in the last one. Blocks larger than an equal share become shards of their own, and the search is repeated on the
stretches between them with the other shards. Slots within a shard come from block counts (prefix sums) and a rank within the
block; a block with far more rows than the mean is ranked in parts by a hash of the row, as many as it takes, so that a text
with a third of all rows is not ranked in one task.

Defined cases: a null text has 16 bytes and is a group of its own; texts of any length count with all their bytes; null and
repeated ids are rows like others; repeated rows get slots of their own (equal rows are ranked in one part); ties are ordered
by id and text; extra columns are ignored; with fewer blocks than shards the last shards stay empty; an empty table gives an
empty result.
"""

from __future__ import annotations

import heapq
from bisect import bisect_left, bisect_right
from itertools import accumulate

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

N_SHARDS, OVERHEAD, BIN_BITS = 40, 16, 16


def greedy_cuts(sizes: list[int], capacity: int) -> list[int]:
    """Places where a new shard starts when each takes as many blocks as fit; a block over the capacity stands alone."""
    cuts, fill = [], 0
    for i, n in enumerate(sizes):
        if fill and fill + n > capacity:
            cuts.append(i)
            fill = 0
        fill += n
    return cuts


def smallest_capacity(sizes: list[int], n_shards: int) -> int:
    low, high = max([*sizes, -(-sum(sizes) // n_shards)], default=0), sum(sizes)
    while low < high:
        mid = (low + high) // 2
        if len(greedy_cuts(sizes, mid)) < n_shards:
            high = mid
        else:
            low = mid + 1
    return low


def _stretches(sizes: list[int], alone: list[int]) -> list[tuple[int, int]]:
    """What lies between the blocks that stand alone, without empty stretches."""
    ends = [-1, *sorted(alone), len(sizes)]
    return [(a + 1, b) for a, b in zip(ends, ends[1:], strict=False) if b > a + 1]


def _oversized(sizes: list[int], n_shards: int, capacity: int) -> list[int]:
    """Blocks larger than an equal share of what is left without them, largest first: as many as can stand alone while the
    rest still fits the other shards under ``capacity``."""
    order, rest, out = sorted(range(len(sizes)), key=lambda i: -sizes[i])[:n_shards], sum(sizes), []
    for i in order:
        left = n_shards - len(out)
        if sizes[i] * left <= rest:
            break
        out.append(i)
        rest -= sizes[i]
    while out:
        parts = [greedy_cuts(sizes[a:b], capacity) for a, b in _stretches(sizes, out)]
        if sum(len(p) + 1 for p in parts) <= n_shards - len(out):
            break
        out.pop()
    return out


def minimax_cuts(sizes: list[int], n_shards: int) -> list[int]:
    """Cuts with the least maximum. Oversized blocks stand alone, so that they do not set the capacity of the others, which are
    divided by a search of their own; shards left over after that halve the largest of the others."""
    capacity = smallest_capacity(sizes, n_shards)
    alone = _oversized(sizes, n_shards, capacity)
    stretches, shards = _stretches(sizes, alone), n_shards - len(alone)
    need = lambda c: [len(greedy_cuts(sizes[a:b], c)) + 1 for a, b in stretches]
    low, high = max((max(sizes[a:b]) for a, b in stretches), default=0), capacity
    while low < high:
        mid = (low + high) // 2
        if sum(need(mid)) <= shards:
            high = mid
        else:
            low = mid + 1
    starts = set(alone) | {i + 1 for i in alone}
    for (a, b), n in zip(stretches, need(low), strict=True):
        starts |= {a, *(a + c for c in minimax_of(sizes[a:b], n))}
    cuts = sorted(starts - {0, len(sizes)})
    ends = [0, *cuts, len(sizes)]
    heap = [(-sum(sizes[a:b]), a, b) for a, b in zip(ends, ends[1:], strict=False) if b > a + 1]
    heapq.heapify(heap)
    while heap and len(cuts) + 1 < n_shards:
        _, a, b = heapq.heappop(heap)
        c = a + (minimax_of(sizes[a:b], 2) or [1])[0]  # blocks of no size have no cut
        cuts.append(c)
        for x, y in ((a, c), (c, b)):
            if y > x + 1:
                heapq.heappush(heap, (-sum(sizes[x:y]), x, y))
    return sorted(cuts)


def minimax_of(sizes: list[int], n_shards: int) -> list[int]:
    return level_cuts(sizes, n_shards, smallest_capacity(sizes, n_shards))


def level_cuts(sizes: list[int], n_shards: int, capacity: int) -> list[int]:
    """Cuts that keep the capacity with every shard as near as may be to an equal share of what is left: a shard ends where it
    is nearest to that, but not before the rest fits the other shards and not beyond the capacity."""
    n, upto = len(sizes), [0, *accumulate(sizes)]
    need = [0] * (n + 1)  # shards that the blocks from here on take at least
    for i in range(n - 1, -1, -1):
        need[i] = 1 + need[max(i + 1, bisect_right(upto, upto[i] + capacity) - 1)]
    fewer = [-x for x in need]  # ascending
    cuts, at = [], 0
    for left in range(min(n_shards, n), 1, -1):
        share = upto[at] + (upto[n] - upto[at]) / left
        to = bisect_left(upto, share)
        if to > at + 1 and share - upto[to - 1] < upto[to] - share:
            to -= 1
        first = max(at + 1, bisect_left(fewer, 1 - left))
        last = max(at + 1, bisect_right(upto, upto[at] + capacity) - 1)
        at = min(max(to, first), last)
        if at >= n:
            break
        cuts.append(at)
    return cuts


def _block(bits: int) -> Column:
    key = F.when(F.col("text").isNull(), F.xxhash64("doc_id", F.lit("null text"))).otherwise(F.xxhash64("text"))
    return F.shiftrightunsigned(key, 64 - bits).cast("int")


def shard(docs: DataFrame, n_shards: int = N_SHARDS, overhead: int = OVERHEAD, bin_bits: int = BIN_BITS) -> DataFrame:
    """doc_id, size, text_crc32, block, shard, slot of every row."""
    rows = docs.select(
        "doc_id",
        (F.coalesce(F.octet_length("text"), F.lit(0)) + overhead).cast("long").alias("size"),
        F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32"),
        _block(bin_bits).alias("block"),
    )
    blocks = rows.groupBy("block").agg(F.sum("size").alias("size"), F.count("*").alias("n")).orderBy("block").collect()  # 2**bin_bits rows at most
    cuts = [blocks[i]["block"] for i in minimax_cuts([b["size"] for b in blocks], n_shards)]
    limit = max(64, 8 * sum(b["n"] for b in blocks) // 2**bin_bits)
    hot = [(b["block"], -(-b["n"] // limit)) for b in blocks if b["n"] > limit]  # their parts are fewer than 2**bin_bits / 4
    hot = F.broadcast(docs.sparkSession.createDataFrame(hot, "block int, parts int"))
    salt = F.pmod(F.xxhash64("doc_id", "text_crc32", "size"), F.coalesce("parts", F.lit(1))).cast("int")
    rows = rows.join(hot, "block", "left").withColumn("salt", salt).drop("parts")
    of = F.lit(0)
    for c in cuts:
        of = of + (F.col("block") >= c).cast("int")
    # starts of sub-blocks within their shard: a table of at most 1.25 * 2**bin_bits rows, ranked in one small window
    counts = rows.groupBy("block", "salt").agg(F.count("*").alias("n")).withColumn("shard", of)
    before = Window.partitionBy("shard").orderBy("block", "salt").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select("block", "salt", "shard", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("start"))
    place = F.row_number().over(Window.partitionBy("block", "salt").orderBy("doc_id", "text_crc32")) - 1
    ranked = rows.withColumn("place", place)
    return ranked.join(F.broadcast(starts), ["block", "salt"]).select("doc_id", "size", "text_crc32", "block", "shard", (F.col("start") + F.col("place")).alias("slot"))
