"""Records as sets: text of a record, normalising, grams of characters and words, token numbers, set similarities.

Everything here builds Columns of built-in functions; sets are arrays without repeats.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable

from pyspark.sql import Column
from pyspark.sql import functions as F

#: A prime just below 2^31: products of two residues stay below 2^62, so any engine computes them exactly in 64 bits.
PRIME = 2_147_483_647

Texts = Column | str


def col(c: Texts) -> Column:
    return F.col(c) if isinstance(c, str) else c


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Evaluate ``value`` once per row, however often ``body`` names it inside lambdas."""
    return F.transform(F.array(value), body)[0]


def record_text(fields: Iterable[Texts], sep: str = " ") -> Column:
    """All fields of a record as one string; missing fields are skipped."""
    return F.concat_ws(sep, *(col(f).cast("string") for f in fields))


def normalise(text: Texts, keep_space: bool = False) -> Column:
    """Lower case, letters and digits only (and single spaces, if kept)."""
    t = F.lower(F.coalesce(col(text), F.lit("")))
    if keep_space:
        return F.trim(F.regexp_replace(F.regexp_replace(t, r"[^\p{L}\p{N}\s]", ""), r"\s+", " "))
    return F.regexp_replace(t, r"[^\p{L}\p{N}]", "")


def _runs(units: Column, k: int, sep: str = "") -> Column:
    """All runs of k neighbouring units, joined; units shorter than k give one run, none give no run. One pass: no substring
    calls, whose cost grows with their place in a UTF-8 string."""
    at = F.sequence(F.lit(1), F.size(units) - (k - 1))
    run = lambda i: F.concat_ws(sep, *(F.get(units, i - 1 + j) for j in range(k)))
    return F.when(F.size(units) == 0, F.array().cast("array<string>")).when(F.size(units) < k, F.array(F.array_join(units, sep))).otherwise(F.transform(at, run))


def _units(text: Column) -> Column:
    return F.when(F.length(text) > 0, F.split(text, "")).otherwise(F.array().cast("array<string>"))


def char_grams(text: Texts, k: int = 2, multiset: bool = False) -> Column:
    """Character k-grams; as a bag, a repeated gram carries the number of its occurrence (for short records)."""
    grams = let(_units(F.coalesce(col(text), F.lit(""))), lambda u: _runs(u, k))
    if not multiset:
        return F.array_distinct(grams)
    return let(grams, lambda g: F.transform(g, lambda x, i: F.concat(x, F.lit("#"), F.size(F.filter(F.slice(g, F.lit(1), i + 1), lambda y: y == x)).cast("string"))))


def _words(text: Texts) -> Column:
    return F.filter(F.split(F.coalesce(col(text), F.lit("")), " "), lambda w: w != "")


def word_set(text: Texts) -> Column:
    return F.array_distinct(_words(text))


def word_grams(text: Texts, n: int = 3) -> Column:
    return F.array_distinct(let(_words(text), lambda w: _runs(w, n, " ")))


def combined_set(text: Texts, k: int = 2) -> Column:
    """Grams and words side by side, kept apart by a mark."""
    mark = lambda m, a: F.transform(a, lambda x: F.concat(F.lit(m), x))
    return F.array_union(mark("c:", char_grams(F.regexp_replace(col(text), " ", ""), k)), mark("w:", word_set(text)))


def field_grams(fields: dict[str, Texts], k: int = 2) -> Column:
    """Grams of each field under the field's name, so that equal strings in different fields differ."""

    def tagged(name: str, c: Texts) -> Column:
        return F.transform(char_grams(normalise(c), k), lambda x: F.concat(F.lit(f"{name}:"), x))

    return F.flatten(F.array(*(tagged(*f) for f in fields.items())))


def token_number(token: Column) -> Column:
    """The portable number of a token: 32 bits of its MD5, modulo the prime. Any SQL engine computes the same."""
    return F.conv(F.substring(F.md5(token.cast("binary")), 1, 8), 16, 10).cast("long") % PRIME


def token_ids(tokens: Texts, mode: str = "native") -> Column:
    """Token numbers: ``native`` 64-bit hashes for work at scale, ``portable`` ones for tests against other engines."""
    one = {"native": F.xxhash64, "portable": token_number}[mode]
    return F.array_distinct(F.transform(col(tokens), lambda t: one(t)))


def jaccard(a: Texts, b: Texts) -> Column:
    """|A n B| / |A u B| of arrays without repeats; two empty sets are equal. One intersection, no union."""
    a, b = col(a), col(b)
    both = F.size(F.array_intersect(a, b))
    return let(both, lambda n: F.when(F.size(a) + F.size(b) == 0, 1.0).otherwise(n / (F.size(a) + F.size(b) - n)))


def set_similarity(a: Texts, b: Texts, kind: str = "jaccard") -> Column:
    a, b = col(a), col(b)
    n = F.size(F.array_intersect(a, b)).cast("double")
    if kind == "jaccard":
        return jaccard(a, b)
    whole = {"containment": F.size(a).cast("double"), "overlap": F.least(F.size(a), F.size(b)).cast("double"), "cosine": F.sqrt(F.size(a).cast("double") * F.size(b))}[kind]
    return F.when(whole > 0, n / whole).otherwise(F.when(F.size(a) == F.size(b), 1.0).otherwise(0.0))
