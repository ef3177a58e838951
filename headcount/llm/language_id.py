"""Language identification by a byte convolutional network, trained and applied in numpy.

Filters of widths 2, 3 and 4 run over windows of ``WINDOW`` bytes, all 256 of which are symbols of their own; each filter keeps
its largest value (max pooling), a rectifier and a softmax layer follow. A filter's value is a sum of table rows, one for
each byte under it: convolution is looking up and adding. A document's prediction is the mean of the log-probabilities of all
its windows.

Trained on a bounded sample of labelled documents (the ``max_rows`` with the least hash of their id, ``per_doc`` windows each);
applied to every window of every text.

Defined cases: null texts and texts without a letter are ``und`` with score 0; without labelled rows all are; texts of any
length are read whole, some windows at a time; rows with null lang or null id are not learned from, and of repeated ids the
least (lang, text) is; rows with null or repeated ids are predicted like others; of equally likely languages the first by name
is taken; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .quality_classifier import held_out
from .shared import batches, ship

WINDOW, FILTERS, WIDTHS, SYMBOLS, MAX_ROWS, PER_DOC, BLANK = 128, 16, (2, 3, 4), 256, 3_000, 4, 32


def windows(text: bytes, length: int = WINDOW) -> np.ndarray:
    """All windows of a text as rows of bytes; the last is filled up with blanks."""
    n = max(1, -(-len(text) // length))
    out = np.full(n * length, BLANK, np.uint8)
    out[: len(text)] = np.frombuffer(text, np.uint8)
    return out.reshape(n, length)


class ByteNetwork:
    def __init__(self, classes: list[str], filters: int = FILTERS, seed: int = 11):
        rng = np.random.default_rng(seed)
        self.classes, self.filters = classes, filters
        self.conv = {w: rng.normal(0, 0.25, (w, SYMBOLS, filters)).astype(np.float32) for w in WIDTHS}
        self.bias = np.zeros(filters * len(WIDTHS), np.float32)
        self.out = rng.normal(0, 0.1, (filters * len(WIDTHS), len(classes))).astype(np.float32)
        self.shift = np.zeros(len(classes), np.float32)

    def pooled(self, x: np.ndarray, where: bool = False):
        """Largest filter values of each window, and their places if asked for."""
        vals, places = [], []
        for w, table in self.conv.items():
            n = x.shape[1] - w + 1
            z = table[0][x[:, :n]]
            for o in range(1, w):
                z = z + table[o][x[:, o : o + n]]
            if where:
                places.append(z.argmax(1))
            vals.append(z.max(1))
        return np.concatenate(vals, 1) + self.bias, places

    def probabilities(self, pooled: np.ndarray) -> np.ndarray:
        z = np.maximum(pooled, 0) @ self.out + self.shift
        z -= z.max(1, keepdims=True)
        e = np.exp(z)
        return e / e.sum(1, keepdims=True)

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int = 4, batch: int = 96, rate: float = 0.01, seed: int = 11, least_steps: int = 300) -> ByteNetwork:
        """Adam on the cross entropy; the gradient of a maximum goes to its place. Small samples get more epochs."""
        epochs = max(epochs, -(-least_steps * batch // max(1, len(x))))
        rng = np.random.default_rng(seed)
        params = [*self.conv.values(), self.bias, self.out, self.shift]
        m, v = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
        t, f = 0, self.filters
        for _ in range(epochs):
            order = rng.permutation(len(x))
            for i in range(0, len(x), batch):
                at = order[i : i + batch]
                xb, yb = x[at], y[at]
                pooled, places = self.pooled(xb, True)
                act = np.maximum(pooled, 0)
                d = self.probabilities(pooled)
                d[np.arange(len(at)), yb] -= 1
                d /= len(at)
                da = (d @ self.out.T) * (pooled > 0)
                grads = []
                rows = np.arange(len(at))[:, None]
                for k, w in enumerate(WIDTHS):
                    g = np.zeros_like(self.conv[w])
                    part = da[:, k * f : (k + 1) * f]
                    for o in range(w):
                        np.add.at(g[o], (xb[rows, places[k] + o], np.arange(f)[None, :]), part)
                    grads.append(g)
                grads += [da.sum(0), act.T @ d, d.sum(0)]
                t += 1
                for p, g, a, b in zip(params, grads, m, v, strict=True):
                    a += 0.1 * (g - a)
                    b += 0.001 * (g * g - b)
                    p -= rate * (a / (1 - 0.9**t)) / (np.sqrt(b / (1 - 0.999**t)) + 1e-8)
        return self

    def compiled(self) -> Compiled:
        return Compiled(self)


class Compiled:
    """One table over pairs of bytes, with the columns of all filters, and one over the last byte of the filters of width 3: two
    look-ups a byte."""

    def __init__(self, net: ByteNetwork):
        self.net = net
        c2, c3, c4 = (net.conv[w] for w in WIDTHS)
        first = np.concatenate([c2[0], c3[0], c4[0], c4[2]], 1)
        second = np.concatenate([c2[1], c3[1], c4[1], c4[3]], 1)
        self.pair = (first[:, None, :] + second[None, :, :]).reshape(SYMBOLS**2, -1)
        self.last = np.ascontiguousarray(c3[2])

    def log_probabilities(self, x: np.ndarray) -> np.ndarray:
        f = self.net.filters
        x = x.astype(np.intp)
        g = np.take(self.pair, x[:, :-1] * SYMBOLS + x[:, 1:], 0)
        two = g[:, :, :f].max(1)
        three = (g[:, :-1, f : 2 * f] + np.take(self.last, x[:, 2:], 0)).max(1)
        four = (g[:, :-2, 2 * f : 3 * f] + g[:, 2:, 3 * f :]).max(1)
        return np.log(self.net.probabilities(np.concatenate([two, three, four], 1) + self.net.bias) + 1e-12)


def train(docs: DataFrame, max_rows: int = MAX_ROWS, per_doc: int = PER_DOC) -> ByteNetwork | None:
    """Learns from documents that are not held out and have a lang; their windows reach the driver (2 MB at most)."""
    ship(docs.sparkSession)
    known = docs.where(F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & F.col("text").rlike(r"\p{L}") & ~held_out())
    ids = known.select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)
    one = known.join(F.broadcast(ids), "doc_id", "left_semi").groupBy("doc_id").agg(F.min(F.struct("lang", "text")).alias("r"))
    rows = one.select("doc_id", F.col("r.lang").alias("lang"), F.col("r.text").cast("binary").alias("text"))

    def cut(it):
        for b in it:
            doc, lang, out = [], [], []
            for i, la, text in batches([b], ("doc_id", "lang", "text")):
                w = windows(text)
                for k in np.unique(np.linspace(0, len(w) - 1, per_doc).astype(int)):
                    doc.append(i)
                    lang.append(la)
                    out.append(w[k].tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(doc, b.schema.field("doc_id").type), pa.array(lang, pa.string()), pa.array(out, pa.binary())], ["doc_id", "lang", "x"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    got = rows.mapInArrow(cut, f"doc_id {kind}, lang string, x binary").toArrow().sort_by([("doc_id", "ascending"), ("x", "ascending")])
    if got.num_rows == 0:
        return None
    langs = got["lang"].to_pylist()
    classes = sorted(set(langs))
    x = np.frombuffer(b"".join(got["x"].to_pylist()), np.uint8).reshape(-1, WINDOW)
    return ByteNetwork(classes).fit(x, np.array([classes.index(c) for c in langs]))


def identify(docs: DataFrame, model: ByteNetwork | None, chunk: int = 128) -> DataFrame:
    """doc_id, lang_pred, score of every document."""
    spark = docs.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast(model)
    kind = docs.schema["doc_id"].dataType.simpleString()
    letters = F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False))

    def run(it):
        net = sent.value and sent.value.compiled()
        for b in it:
            langs, scores = [], []
            for text, has in batches([b], ("text", "letters")):
                if not has or net is None:
                    langs.append("und")
                    scores.append(0.0)
                    continue
                w = windows(text)
                total = sum(net.log_probabilities(w[i : i + chunk]).sum(0, dtype=float) for i in range(0, len(w), chunk)) / len(w)
                p = np.exp(total - total.max())
                k = int(p.argmax())
                langs.append(net.net.classes[k])
                scores.append(float(p[k] / p.sum()))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], ["doc_id", "lang_pred", "score"])

    base = docs.select("doc_id", letters.alias("letters"), F.coalesce(F.col("text").cast("binary"), F.lit(b"")).alias("text"))
    return base.mapInArrow(run, f"doc_id {kind}, lang_pred string, score double")
