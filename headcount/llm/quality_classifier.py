"""Quality classifier: a factorisation machine over hashed words, structure statistics and metadata.

score = sigmoid(w0 + sum w_i x_i + 1/2 sum_f [(sum v_if x_i)^2 - sum v_if^2 x_i^2]): all pairs of features interact through
``RANK`` factors at a cost linear in the features of a text.

Trained in numpy (AdaGrad) on a bounded sample of labelled documents: at most ``max_rows``, those with the least hash of their
id; scoring covers every whole text. Words are split at ASCII blanks and hashed to ``BUCKETS`` numbers.

Defined cases: null and empty texts are scored by their (empty) structure; texts of any length are read whole; without labels
every score is near 0.5; null labels and null ids are not learned from, and of repeated ids the least label and the least row are; a
null metadata value is a feature of its own; rows with null or repeated ids are scored like others; a score of exactly 0.5
counts as label 1; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import batches, ship, word_hashes

BUCKETS, RANK, MAX_ROWS, BINS = 1 << 16, 8, 6_000, 12


def held_out(doc_id: str = "doc_id") -> Column:
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 3 == 1, F.lit(False))


def structure(text: bytes, words: list[bytes]) -> list[float]:
    """Ratios between 0 and 1 that tell prose from junk, and the length on a logarithmic scale."""
    c = np.bincount(np.frombuffer(text, np.uint8), minlength=256)
    n, w = max(1, len(text)), max(1, len(words))
    small, large, digits = int(c[97:123].sum()), int(c[65:91].sum()), int(c[48:58].sum())
    beyond, blank = int(c[128:].sum()), int(c[9:14].sum() + c[32])
    lines = text.split(b"\n")
    marks = n - small - large - digits - beyond - blank
    return [
        min(1.0, np.log1p(w) / 12),
        min(1.0, marks / w / 3),
        large / max(1, small + large),
        digits / n,
        beyond / n,
        1 - len(set(lines)) / len(lines),
        1 - len(set(words)) / w,
        min(1.0, (n - blank) / w / 16),
        min(1.0, w / len(lines) / 200),
        min(1.0, text.count(b"!!") / w),
    ]


N_STRUCTURE = 10


def features(text: bytes, metadata: tuple = ()) -> tuple[np.ndarray, np.ndarray]:
    """Numbers and values of a text's features."""
    words = text.split()
    ids, counts = np.unique(word_hashes(words) % np.uint64(BUCKETS), return_counts=True)
    values = np.log1p(counts)
    values = values / max(1e-9, np.sqrt((values**2).sum()))
    s = structure(text, words)
    binned = [BUCKETS + i * BINS + min(BINS - 1, int(x * BINS)) for i, x in enumerate(s)]
    for i, x in enumerate(metadata, N_STRUCTURE):
        place = 0 if x is None else 1 + (min(BINS - 2, int(np.log1p(abs(x)))) if isinstance(x, (int, float)) else zlib.crc32(str(x).encode()) % (BINS - 1))
        binned.append(BUCKETS + i * BINS + place)
    return np.concatenate([ids.astype(np.int64), np.array(binned)]), np.concatenate([values, np.full(len(binned), 0.5)])


class FactorizationMachine:
    def __init__(self, n: int, rank: int = RANK, seed: int = 7):
        self.w0 = 0.0
        self.w = np.zeros(n)
        self.v = np.random.default_rng(seed).normal(0, 0.05, (n, rank))

    def raw(self, at: np.ndarray, x: np.ndarray) -> float:
        v = self.v[at]
        s = x @ v
        return float(self.w0 + self.w[at] @ x + 0.5 * (s @ s - ((v * x[:, None]) ** 2).sum()))

    def score(self, at: np.ndarray, x: np.ndarray) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.raw(at, x), -30, 30))))

    def fit(self, rows: list[tuple[np.ndarray, np.ndarray, int]], epochs: int = 5, rate: float = 0.08, decay: float = 1e-4, seed: int = 7) -> FactorizationMachine:
        if not rows:
            return self
        ones = sum(y for _, _, y in rows)
        weight = {1: len(rows) / 2 / max(1, ones), 0: len(rows) / 2 / max(1, len(rows) - ones)}
        g0, gw, gv = 1.0, np.ones_like(self.w), np.ones_like(self.v)
        rng = np.random.default_rng(seed)
        for _ in range(epochs):
            for i in rng.permutation(len(rows)):
                at, x, y = rows[i]
                v = self.v[at]
                s = x @ v
                z = self.w0 + self.w[at] @ x + 0.5 * (s @ s - ((v * x[:, None]) ** 2).sum())
                d = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y) * weight[y]
                g0 += d * d
                self.w0 -= rate * d / np.sqrt(g0)
                step = d * x + decay * self.w[at]
                gw[at] += step * step
                self.w[at] -= rate * step / np.sqrt(gw[at])
                step = d * (x[:, None] * s - v * (x * x)[:, None]) + decay * v
                gv[at] += step * step
                self.v[at] -= rate * step / np.sqrt(gv[at])
        return self


def _texts(df: DataFrame, *cols: str) -> DataFrame:
    return df.select(*cols, F.coalesce(F.col("text").cast("binary"), F.lit(b"")).alias("text"))


def train(docs: DataFrame, labels: DataFrame, metadata: tuple[str, ...] = (), max_rows: int = MAX_ROWS, label: str = "quality") -> FactorizationMachine:
    """Learns from labelled rows that are not held out; texts become features before they reach the driver."""
    ship(docs.sparkSession)
    sample = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out()).select("doc_id", F.col(label).cast("int").alias("y"))
    sample = sample.groupBy("doc_id").agg(F.min("y").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)
    one = docs.select("doc_id", F.struct("text", *metadata).alias("r")).join(F.broadcast(sample), "doc_id")  # at most max_rows rows are broadcast
    one = one.groupBy("doc_id").agg(F.min("y").alias("y"), F.min("r").alias("r"))
    rows = _texts(one.select("doc_id", "y", "r.*"), "doc_id", "y", *metadata)

    def build(it):
        for b in it:
            out = [[], [], [], []]
            for doc, y, text, *m in batches([b], ("doc_id", "y", "text", *metadata)):
                at, x = features(text, tuple(m))
                for o, v in zip(out, (doc, y, at.astype(np.int32), x.astype(np.float32)), strict=True):
                    o.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], b.schema.field("doc_id").type), pa.array(out[1], pa.int32()), pa.array(out[2], pa.list_(pa.int32())), pa.array(out[3], pa.list_(pa.float32()))], ["doc_id", "y", "at", "x"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    got = rows.mapInArrow(build, f"doc_id {kind}, y int, at array<int>, x array<float>").toArrow().sort_by([("doc_id", "ascending"), ("y", "ascending")])
    data = [(a.values.to_numpy().astype(np.int64), x.values.to_numpy().astype(float), y) for a, x, y in zip(got["at"], got["x"], got["y"].to_pylist(), strict=True)]
    return FactorizationMachine(BUCKETS + (N_STRUCTURE + len(metadata)) * BINS).fit(data)


def score(docs: DataFrame, model: FactorizationMachine, metadata: tuple[str, ...] = ()) -> DataFrame:
    """doc_id and score of every document."""
    spark = docs.sparkSession
    ship(spark)
    small = FactorizationMachine(1)
    small.w0, small.w, small.v = model.w0, model.w.astype(np.float32), model.v.astype(np.float32)
    sent = spark.sparkContext.broadcast(small)
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(it):
        m = sent.value
        for b in it:
            out = [m.score(*features(text, tuple(meta))) for text, *meta in batches([b], ("text", *metadata))]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(out, pa.float64())], ["doc_id", "score"])

    return _texts(docs, "doc_id", *metadata).mapInArrow(run, f"doc_id {kind}, score double")
