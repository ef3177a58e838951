"""Token counts: an exact histogram of encoded lengths whose suffix sums answer totals, quantiles and truncated totals.

Documents are encoded once and aggregated by length before anything is shuffled. The histogram has one row per distinct
length, so its windows run over lengths and not over documents.

Defined cases: null and empty texts have length 0; texts of any length are encoded whole; ids are not read, so null and
repeated ones count like others, and repeated rows count as often as they occur; equal lengths share a row; extra columns are
ignored; an empty table gives no rows and :func:`answers` gives zeros and nulls.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import batches, ship, stored
from .tokens import encoder, vocabulary_path

BLOCK_BITS = 10


def encoded_lengths(docs: DataFrame, tokenizer: str | None = None) -> DataFrame:
    """(length, n_docs) as counted within each batch."""
    from collections import Counter

    ship(docs.sparkSession)
    path = tokenizer or vocabulary_path()

    def count(it):
        encode = encoder(path).encode
        for b in it:
            c = Counter(len(encode(t.decode("utf-8", "replace"))) // 4 for (t,) in batches([b], ("text",)))
            yield pa.RecordBatch.from_arrays([pa.array(list(c), pa.int64()), pa.array(list(c.values()), pa.int64())], ["length", "n_docs"])

    return docs.select(F.coalesce(F.col("text").cast("binary"), F.lit(b"")).alias("text")).mapInArrow(count, "length long, n_docs long")


def suffix_sums(histogram: DataFrame, block_bits: int = BLOCK_BITS) -> DataFrame:
    """(length, n_docs) with docs_from, tokens_from, tokens_within and share_below.

    Sums run in two levels, downwards: over blocks of ``2**block_bits`` neighbouring lengths, which is the only window that one
    task sees whole, and over the lengths of each block. Each row is added once, so the cost is linear in the number of lengths."""
    h = histogram.select("length", "n_docs", (F.col("n_docs") * F.col("length")).alias("_t"), F.shiftright("length", block_bits).alias("_b"))
    blocks = h.groupBy("_b").agg(F.sum("n_docs").alias("n"), F.sum("_t").alias("t"))
    after = Window.orderBy(F.desc("_b")).rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.orderBy(F.desc("_b")).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    blocks = blocks.select("_b", F.coalesce(F.sum("n").over(after), F.lit(0)).alias("_n1"), F.coalesce(F.sum("t").over(after), F.lit(0)).alias("_t1"), F.sum("n").over(everything).alias("_docs"), F.sum("t").over(everything).alias("_tokens"))
    from_here = Window.partitionBy("_b").orderBy(F.desc("length")).rowsBetween(Window.unboundedPreceding, 0)
    h = h.withColumn("_n0", F.sum("n_docs").over(from_here)).withColumn("_t0", F.sum("_t").over(from_here)).join(blocks, "_b")
    docs_from, tokens_from = F.col("_n0") + F.col("_n1"), F.col("_t0") + F.col("_t1")
    within = F.col("_tokens") - tokens_from + docs_from * F.col("length")
    return h.select("length", "n_docs", docs_from.alias("docs_from"), tokens_from.alias("tokens_from"), within.alias("tokens_within"), F.round(1 - docs_from / F.col("_docs"), 9).alias("share_below"))


def length_histogram(docs: DataFrame, tokenizer: str | None = None) -> DataFrame:
    """Per distinct length: n_docs; docs_from and tokens_from (suffix sums); tokens_within, the total if every document
    were cut at this length; share_below, the share of documents that are shorter."""
    counted = encoded_lengths(docs, tokenizer).groupBy("length").agg(F.sum("n_docs").alias("n_docs"))
    return suffix_sums(stored(counted, "lengths"))  # written once: the sums read it twice, and encoding is what costs


def truncated_total(limit: int) -> Column:
    """Tokens that remain if every document is cut at ``limit``; aggregate it over a histogram."""
    return F.coalesce(F.sum(F.least(F.col("length"), F.lit(limit)) * F.col("n_docs")), F.lit(0))


def answers(histogram: DataFrame, limits: tuple[int, ...] = (512, 1024, 2048, 4096), quantiles: tuple[float, ...] = (0.5, 0.9, 0.99)) -> DataFrame:
    """One row: totals, the smallest length that at least a share q of the documents do not exceed, truncated totals."""
    docs = F.coalesce(F.sum("n_docs"), F.lit(0)).alias("n_docs")
    tokens = F.coalesce(F.sum(F.col("length") * F.col("n_docs")), F.lit(0)).alias("n_tokens")
    total = histogram.agg(F.sum("n_docs").alias("total"))
    up_to = F.col("total") - F.col("docs_from") + F.col("n_docs")
    h = histogram.crossJoin(F.broadcast(total))  # one row
    q = [F.min(F.when(up_to >= F.ceil(F.lit(x) * F.col("total")), F.col("length"))).alias(f"q{round(1000 * x)}") for x in quantiles]
    return h.agg(docs, tokens, *q, *(truncated_total(x).alias(f"tokens_at_{x}") for x in limits))
