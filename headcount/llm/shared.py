"""What the text operators share: word splitting, hashing, bounded bit filters.

Conventions that hold for all operators of this subpackage:

* a null text counts as a text without words unless the operator says otherwise; an empty table gives an empty result
  with the same columns;
* extra columns are ignored by the operators that return digests and kept by those that return documents;
* repeated rows give repeated result rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from headcount.sources.shipping import ship  # noqa: F401
from headcount.sources.storage import dropped, release, shared_dir, stored  # noqa: F401

#: The characters between words, fixed by the contract of the operators: space, tab, line feed, vertical tab, form feed,
#: carriage return. ``bytes.split()`` splits at exactly these.
BLANKS = r"[\x20\x09-\x0D]"
NOT_BLANK = r"[^\x20\x09-\x0D]"

def let(value: Column, body) -> Column:
    """Evaluate ``value`` once per row and use it many times in ``body`` (Catalyst would inline and repeat it)."""
    return F.transform(F.array(value), body)[0]


def text_bytes(df: DataFrame, *cols: str, text: str = "text") -> DataFrame:
    """The named columns and the text as UTF-8 bytes (null: empty)."""
    return df.select(*cols, F.coalesce(F.col(text).cast("binary"), F.lit(b"")).alias("text"))


class WordHash(dict):
    """Word -> 63-bit hash, remembered for as many words as ``limit``."""

    def __init__(self, limit: int = 150_000):
        import xxhash

        super().__init__()
        self._digest, self._limit = xxhash.xxh64_intdigest, limit

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self._limit:
            self.clear()
        v = self[word] = self._digest(word) >> 1
        return v


_WORDS: WordHash | None = None


def word_hashes(words: list[bytes]) -> np.ndarray:
    global _WORDS
    if _WORDS is None:
        _WORDS = WordHash()
    return np.fromiter(map(_WORDS.__getitem__, words), np.int64, len(words)).view(np.uint64)


_STEP = np.uint64(0x9E3779B97F4A7C15)  # odd multipliers of public 64-bit mixers
_MIX = np.uint64(0xBF58476D1CE4E5B9)


def mixed(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(30))
    h *= _MIX
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def gram_hashes(a: np.ndarray, k: int) -> np.ndarray:
    """64-bit hashes of all runs of ``k`` consecutive entries; empty if there are fewer."""
    n = len(a) - k + 1
    if n <= 0:
        return a[:0]
    if k <= 8:
        h = a[:n].copy()
        for i in range(1, k):
            h *= _STEP
            h += a[i : i + n]
        return mixed(h)
    # long runs: doubling, the same polynomial
    h, width, done = a, 1, None
    at = 0
    bits = k
    while bits:
        if bits & 1:
            part = h[at : at + n] if done is None else h[at : at + n]
            done = part.copy() if done is None else done * np.uint64(pow(int(_STEP), width, 2**64)) + part
            at += width
        bits >>= 1
        if bits:
            h = h[:-width] * np.uint64(pow(int(_STEP), width, 2**64)) + h[width:]
            width *= 2
    return mixed(done)


def batches(it, columns: tuple[str, ...], at_once: int = 256) -> Iterator[tuple]:
    """Rows of Arrow batches as tuples of Python values, a few at a time, so that texts are not held twice."""
    for b in it:
        cols = [b.column(c) for c in columns]
        for start in range(0, b.num_rows, at_once):
            yield from zip(*(c.slice(start, at_once).to_pylist() for c in cols), strict=True)


# --- joins on keys of which some have very many rows ------------------------------------------------------------------------------

LEAST_HOT, MOST_HOT = 1_000, 20_000


def salted_join(many: DataFrame, few: DataFrame, key: str, counts: DataFrame, total: int, how: str = "inner") -> DataFrame:
    """``many`` joined with the few rows per key of ``few``; no task gets all rows of a key that has very many.

    ``counts`` (key, n) holds the rows per key of ``many``, ``total`` in all. Keys with more than ``total / MOST_HOT`` rows, of
    which there can be no more than ``MOST_HOT``, are broadcast with their counts; their rows are dealt to as many parts as it
    takes, and each part gets a copy of the rows of ``few``. Whatever AQE would do, this needs no threshold in bytes. Without
    such keys it is a plain join."""
    limit = max(LEAST_HOT, total // MOST_HOT)
    hot = counts.where(F.col("n") > limit).select(F.col(key).alias("_k"), F.ceil(F.col("n") / limit).cast("int").alias("_parts"))
    if hot.isEmpty():
        return many.join(few, key, how)
    hot = F.broadcast(hot)
    parts = F.coalesce("_parts", F.lit(1))
    own = F.when(F.col("_parts").isNotNull(), F.pmod(F.xxhash64(*(F.col(f"`{c}`") for c in many.columns if c != key)), parts).cast("int")).otherwise(0)
    left = many.join(hot, many[key] == F.col("_k"), "left").withColumn("_part", own).drop("_k", "_parts")
    right = few.join(hot, few[key] == F.col("_k"), "left").withColumn("_part", F.explode(F.sequence(F.lit(0), parts - 1))).drop("_k", "_parts")
    return left.join(right, [key, "_part"], how).drop("_part")


# --- a bit filter of fixed size: says "surely not" or "perhaps"; it only saves work, results never depend on it --------------------


def bit_filter(df: DataFrame, col: str, bits: int = 26) -> np.ndarray:
    """Bits set at the hash of each value. 2^bits bits whatever the data's size; a full filter lets everything pass."""
    return slot_filter(df, F.shiftrightunsigned(F.xxhash64(F.col(col)), 64 - bits), bits)


def slot_filter(df: DataFrame, slot: Column, bits: int) -> np.ndarray:
    """The same from slots, numbers below 2^bits."""
    words = (
        df.select(F.shiftright(slot, 6).alias("w"), F.call_function("shiftleft", F.lit(1).cast("long"), (slot % 64).cast("int")).alias("b"))
        .groupBy("w")
        .agg(F.bit_or("b").alias("b"))
    )
    out = np.zeros(2 ** (bits - 6), np.int64)
    got = words.toArrow()
    out[got["w"].to_numpy()] = got["b"].to_numpy()
    return out


def passes(filter_words, slots: np.ndarray) -> np.ndarray:
    """Which of the slots (see :func:`filter_slot`) have their bit set."""
    return (filter_words[slots >> 6] >> (slots & 63)) & 1 == 1


def filter_slot(col: str, bits: int = 26) -> Column:
    return F.shiftrightunsigned(F.xxhash64(F.col(col)), 64 - bits)
