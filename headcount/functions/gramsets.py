"""Gram sets as numpy rows, ``portable`` (what :func:`shingles.token_ids` of :func:`shingles.char_grams` gives, without a string per
gram) or ``native`` (:func:`hashing.grams_of`). Batches of texts are worked through in pieces that stay in a core's cache; nothing of
the size of the sets leaves the worker."""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import md5

import numpy as np

from .hashing import bins_of, coefficients, densified, distinct, grams_of, minima_of_sets, mix, probed_rows
from .shingles import PRIME

_P = np.uint64(PRIME)
#: Characters of texts that are numbered at once; a longer text is a piece of its own.
PIECE = 1 << 16


def number_of(gram: str) -> int:
    """The portable number of one gram."""
    return int.from_bytes(md5(gram.encode("utf-8", "surrogatepass")).digest()[:4], "big") % PRIME


class Numbers:
    """Numbers of k-grams, remembered per worker in a table of fixed size: a place holds the gram that was last there."""

    def __init__(self, k: int, bits: int = 21):
        self.k, self.width, self.bits = k, 64 // k, bits
        self.place = np.zeros(0x110000, np.uint32)  # of a code point in the alphabet seen so far
        self.letters = 0
        self.code = np.zeros(1 << bits, np.uint64)
        self.number = np.zeros(1 << bits, np.uint32)

    def _places(self, points: np.ndarray) -> np.ndarray | None:
        """Places of code points, from 1; None where the alphabet outgrows the bits that a place has."""
        at = self.place[points]
        if not at.all():
            fresh = np.unique(points[at == 0])
            if self.letters + len(fresh) >= 1 << min(self.width, 31):
                return None
            self.place[fresh] = np.arange(self.letters + 1, self.letters + 1 + len(fresh), dtype=np.uint32)
            self.letters += len(fresh)
            at = self.place[points]
        return at.astype(np.uint64)

    def __call__(self, points: np.ndarray) -> np.ndarray:
        """The number of the gram that starts at each place but the last k - 1."""
        n, k = len(points) - self.k + 1, self.k
        at = self._places(points)
        if at is None:  # more letters than fit: gram by gram
            text = points.tobytes().decode("utf-32-le", "surrogatepass")
            seen: dict[str, int] = {}
            return np.fromiter((seen[g] if (g := text[i : i + k]) in seen else seen.setdefault(g, number_of(g)) for i in range(n)), np.int64, n)
        code = at[:n].copy()
        for i in range(1, k):
            code = (code << np.uint64(self.width)) | at[i : i + n]
        slot = (code * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)
        out = self.number[slot].astype(np.int64)
        miss = np.flatnonzero(self.code[slot] != code)
        if len(miss):
            fresh, first, back = np.unique(code[miss], return_index=True, return_inverse=True)
            grams = points[miss[first][:, None] + np.arange(k)].tobytes().decode("utf-32-le", "surrogatepass")
            found = np.fromiter((number_of(grams[i : i + k]) for i in range(0, len(grams), k)), np.int64, len(fresh))
            out[miss] = found[back]
            where = slot[miss[first]]
            self.number[where] = found
            self.code[where] = 0
            self.code[where] = fresh  # of several grams at a place the last stays in both tables
            self.number[where] = found
        return out


_KNOWN: dict[int, Numbers] = {}


def sets_of(texts: list[str | None], k: int, mode: str = "portable") -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(start, tokens, lengths) of stretches of normalised texts from number ``start`` on: their sets one after the other, each
    sorted, and how large they are."""
    if k not in _KNOWN:
        _KNOWN[k] = Numbers(k)
    numbers = _KNOWN[k]
    start = 0
    while start < len(texts):
        stop, size = start, 0
        while stop < len(texts) and (stop == start or size + len(texts[stop] or "") <= PIECE):
            size += len(texts[stop] or "")
            stop += 1
        part = [t or "" for t in texts[start:stop]]
        if mode == "native":
            sets = [grams_of(t, k) for t in part]
            yield start, np.concatenate(sets).view(np.int64), np.fromiter(map(len, sets), np.int64, len(sets))
            start = stop
            continue
        chars = np.fromiter(map(len, part), np.int64, len(part))
        points = np.frombuffer("".join(part).encode("utf-32-le", "surrogatepass"), np.uint32)
        end = np.cumsum(chars)
        row = np.repeat(np.arange(len(part)), chars)
        if len(points) >= k:
            n = len(points) - k + 1
            whole = np.arange(n) + k <= end[row[:n]]
            both = (row[:n][whole].astype(np.int64) << 31) | numbers(points)[whole]
        else:
            both = np.empty(0, np.int64)
        short = [(i << 31) | number_of(part[i]) for i in np.flatnonzero((chars > 0) & (chars < k)).tolist()]
        both = distinct(np.concatenate([both, np.array(short, np.int64)]))
        yield start, both & ((1 << 31) - 1), np.bincount(both >> 31, minlength=len(part))
        start = stop


def residues(tokens: np.ndarray, a: int, c: int) -> np.ndarray:
    """(a x + c) modulo the prime 2^31 - 1, by folding."""
    v = tokens.astype(np.uint64) * np.uint64(a) + np.uint64(c)
    v = (v & _P) + (v >> np.uint64(31))
    v = (v & _P) + (v >> np.uint64(31))
    return np.where(v >= _P, v - _P, v)


def per_set(ufunc, values: np.ndarray, lengths: np.ndarray, none: int = 0) -> np.ndarray:
    """``ufunc`` reduced over each set; ``none`` for the empty ones."""
    out = np.full(len(lengths), none, values.dtype)
    full = lengths > 0
    if full.any():
        out[full] = ufunc.reduceat(values, (np.cumsum(lengths) - lengths)[full])
    return out


def minima(tokens: np.ndarray, lengths: np.ndarray, coefficients) -> np.ndarray:
    """A row of minima per set: :func:`hashing.minhash` of every set (an empty one has zeros)."""
    return np.stack([per_set(np.minimum, residues(tokens, a, c), lengths) for a, c in coefficients], axis=1).astype(np.int64)


def digests(tokens: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit sums of mixed tokens per set: sets with equal sums are taken for equal."""
    return tuple(per_set(np.add, mix(tokens, salt), lengths).view(np.int64) for salt in (11, 12))


def signatures(tokens: np.ndarray, lengths: np.ndarray, b: int, seed: int, mode: str, how: str = "probe") -> np.ndarray:
    """A row of b minima per set, as :func:`hashing.minhash` (``portable``) or :func:`hashing.signature` makes them."""
    if mode == "portable":
        return minima(tokens, lengths, coefficients(seed, b))
    if how == "probe":
        return probed_rows(tokens, lengths, b, seed).view(np.int64)
    if how == "classic":
        return minima_of_sets(tokens, lengths, b, seed).view(np.int64)
    ends = np.cumsum(lengths)
    rows = [densified(bins_of(tokens[e - n : e], b, seed), how, seed) for e, n in zip(ends, lengths, strict=True)]
    return np.stack(rows).view(np.int64)


#: Words of 64 bits that a parity row has at most.
MOST_WORDS = 1 << 10


def parities(tokens: np.ndarray, lengths: np.ndarray) -> list[np.ndarray]:
    """Per set the parity of the number of tokens in each of B bins, B the power of two from 1.5 tokens a bin on. Rows of two sets
    differ in no more bits than the sets differ in tokens, and folding a row in two keeps that."""
    words = np.ones(len(lengths), np.int64)
    while (small := (words * 64 < 1.5 * lengths) & (words < MOST_WORDS)).any():
        words[small] *= 2
    first = np.cumsum(words) - words
    bins = (mix(tokens, 13) & np.repeat((words * 64 - 1).astype(np.uint64), lengths)).astype(np.int64) + np.repeat(first * 64, lengths)
    odd = np.bincount(bins, minlength=int(words.sum()) * 64).astype(np.uint8) & 1
    packed = np.packbits(odd, bitorder="little").view(np.int64)
    return np.split(packed, first[1:])


def folded(rows: np.ndarray, words: int) -> np.ndarray:
    """Parity rows with half the bins, as often as it takes: bins are residues, so halves are added without a carry."""
    while rows.shape[1] > words:
        half = rows.shape[1] // 2
        rows = rows[:, :half] ^ rows[:, half:]
    return rows


def jaccards(a: list[str | None], b: list[str | None], k: int, mode: str) -> np.ndarray:
    """Exact similarities of the sets of texts a[i] and b[i]; texts that come again are worked through once."""
    at: dict[str, int] = {}
    for t in (*a, *b):
        at.setdefault(t or "", len(at))
    sets: list[np.ndarray] = []
    for _, tokens, lengths in sets_of(list(at), k, mode):
        sets += np.split(tokens, np.cumsum(lengths)[:-1])
    out = np.empty(len(a))
    for i, (s, t) in enumerate(zip(a, b, strict=True)):
        x, y = sets[at[s or ""]], sets[at[t or ""]]
        both = np.concatenate([x, y])
        both.sort(kind="stable")
        n = int(np.count_nonzero(both[1:] == both[:-1]))
        out[i] = n / (len(both) - n) if len(both) else 1.0
    return out
