"""Substring dedup: word spans that occur in an earlier document, or in a reference, are removed.

Two forms:

* :func:`remove_reference_spans` broadcasts suffix automata of the shards of a reference of checked size and streams the
  documents for matching statistics; every maximal span of at least ``window`` words that matches goes.
* :func:`remove_repeats` takes the corpus itself as the reference. Automata of all documents cannot be broadcast, and streaming
  every document past every shard costs shards x documents, the square of the corpus. So windows are matched by their
  hashes instead, and only where that can succeed:

  1. Copies (equal texts) collapse to their least document; all windows of the others occur in it.
  2. Every window of ``window`` words selects its least 10-gram hash as anchor, so equal windows select equal anchors. About one
     10-gram in twenty is an anchor of anything. Anchors that occur in one text only are dropped, and with them most windows.
  3. The remaining windows are hashed (64 bits); the least document of each hash is aggregated before the shuffle, so that a
     passage in a third of all documents costs a row per task. Windows of later documents are hits; the join that tells them
     deals the rows of hot hashes, and those of hot texts, to many tasks.
  4. Documents without hits, which a bit filter of fixed size tells, never leave their scan task.

Windows are judged on the input. Words are split at ASCII blanks and kept unchanged; what is left is joined by one space.

Defined cases: null texts have no words; texts shorter than a window lose nothing; repeated rows of one id are one document
and get equal result rows; rows without an id neither lose words nor serve as sources; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .automaton import SuffixAutomaton
from .shared import batches, bit_filter, dropped, filter_slot, gram_hashes, passes, release, salted_join, ship, stored, text_bytes, word_hashes

WINDOW, ANCHOR, SHARD_WORDS, MAX_SHARDS = 50, 10, 100_000, 4


def window_anchors(a: np.ndarray, window: int, anchor: int) -> np.ndarray:
    """For each window of word hashes, the hash of its anchor."""
    h = gram_hashes(a, anchor)
    if len(a) < window:
        return h[:0]
    if window <= anchor:
        return h
    reach = np.lib.stride_tricks.sliding_window_view(h, window - anchor + 1)
    return h[reach.argmin(1) + np.arange(len(reach))]


def _copies(docs: DataFrame) -> DataFrame:
    """doc_id, s1, s2 (of the text) of all documents with an id and a text."""
    return docs.where("doc_id is not null and text is not null").select("doc_id", F.xxhash64("text").alias("s1"), (F.hash("text").cast("long") * 2**31 + F.octet_length("text")).alias("s2"))


def hit_windows(docs: DataFrame, window: int = WINDOW, anchor: int = ANCHOR) -> tuple[DataFrame, DataFrame, list[DataFrame]]:
    """(doc_id, starts): the first words of hit windows of least copies; (doc_id): the other copies; and the written tables that
    both read."""
    spark = docs.sparkSession
    ship(spark)
    kind = docs.schema["doc_id"].dataType.simpleString()
    docs = docs.select("doc_id", "text")
    anchor = min(anchor, window)

    def pick(it):
        for b in it:
            keys, out = [], []
            for s1, text in batches([b], ("s1", "text")):
                words = text.split()
                if len(words) >= window:
                    own = np.unique(window_anchors(word_hashes(words), window, anchor)).view(np.int64)
                    out.append(own)
                    keys.append(np.full(len(own), s1, np.int64))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(out)), pa.array(np.concatenate(keys))], ["anchor", "s1"])

    source = docs.where("doc_id is not null").select(F.xxhash64("text").alias("s1"), F.coalesce(F.col("text").cast("binary"), F.lit(b"")).alias("text"))
    anchors = stored(source.mapInArrow(pick, "anchor long, s1 long"), "anchors")
    repeated = anchors.groupBy("anchor").agg(F.min("s1").alias("x"), F.max("s1").alias("y")).where("x <> y").select("anchor")
    per_text = anchors.join(repeated, "anchor", "left_semi").groupBy("s1").agg(F.collect_set("anchor").alias("anchors"))

    texts = stored(_copies(docs), "texts")
    least = texts.groupBy("s1", "s2").agg(F.min("doc_id").alias("rep"))
    wanted = stored(least.join(per_text, "s1").select(F.col("rep").alias("doc_id"), "anchors"), "wanted")
    near = spark.sparkContext.broadcast(bit_filter(wanted, "doc_id"))

    def only_near(it):
        for b in it:
            yield b.filter(pa.array(passes(near.value, b.column("slot").to_numpy()))).select(["doc_id", "text"])

    def hash_windows(it):
        for b in it:
            ids, starts, hashes = [], [], []
            for doc, text, own in batches([b], ("doc_id", "text", "anchors")):
                a = word_hashes(text.split())
                at = np.flatnonzero(np.isin(window_anchors(a, window, anchor).view(np.int64), np.array(own, np.int64)))
                starts.append(at.astype(np.int32))
                hashes.append(gram_hashes(a, window).view(np.int64)[at])
                ids += [doc] * len(at)
            if ids:
                yield pa.RecordBatch.from_arrays([pa.array(ids, b.schema.field("doc_id").type), pa.array(np.concatenate(starts)), pa.array(np.concatenate(hashes))], ["doc_id", "start", "h"])

    some = text_bytes(docs, "doc_id").where("doc_id is not null").withColumn("slot", filter_slot("doc_id")).mapInArrow(only_near, f"doc_id {kind}, text binary")
    windows = stored(some.join(wanted, "doc_id").mapInArrow(hash_windows, f"doc_id {kind}, start int, h long"), "windows")
    release(spark)
    dropped(anchors)
    first = windows.groupBy("h").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last"), F.count("*").alias("n")).where("first < last")
    first = stored(first.select("h", "first", "n"), "first")
    dropped(wanted)
    hits = salted_join(windows, first.select("h", "first"), "h", first, windows.count()).where("doc_id > first").groupBy("doc_id").agg(F.collect_set("start").alias("starts"))
    same = texts.groupBy("s1", "s2").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n")).where("n > 1").withColumn("s", F.struct("s1", "s2"))
    copies = texts.select(F.struct("s1", "s2").alias("s"), "doc_id")
    others = salted_join(copies, same.select("s", "rep"), "s", same.select("s", "n"), texts.count()).where("doc_id <> rep").select("doc_id").distinct()
    return hits, others, [windows, first, texts]


def _judge(text: bytes, starts, window: int, whole: bool) -> tuple[list[bytes], np.ndarray]:
    """Words and which of them go."""
    words = text.split()
    n = len(words)
    if whole:
        return words, np.full(n, n >= window)
    gone = np.zeros(n + 1, np.int64)
    if starts is not None and len(starts):
        at = np.asarray(starts)
        np.add.at(gone, at, 1)
        np.add.at(gone, np.minimum(at + window, n), -1)
    return words, np.cumsum(gone[:n]) > 0


def remove_repeats(docs: DataFrame, window: int = WINDOW, anchor: int = ANCHOR) -> DataFrame:
    """doc_id, n_words, n_removed, kept (the words left, joined by a space), removed (spans of words) of all documents."""
    spark = docs.sparkSession
    kind = docs.schema["doc_id"].dataType.simpleString()
    hits, others, read = hit_windows(docs, window, anchor)
    touched = stored(hits.withColumn("whole", F.lit(False)).unionByName(others.select("doc_id", F.array().cast("array<int>").alias("starts"), F.lit(True).alias("whole"))).groupBy("doc_id").agg(F.flatten(F.collect_list("starts")).alias("starts"), F.max("whole").alias("whole")), "touched")
    release(spark)
    dropped(*read)
    near = spark.sparkContext.broadcast(bit_filter(touched, "doc_id"))
    schema = f"doc_id {kind}, n_words long, n_removed long, kept binary, removed array<struct<a:int,b:int>>"
    span = pa.list_(pa.struct([("a", pa.int32()), ("b", pa.int32())]))

    def result(b, rows):
        n, gone, kept, spans = [], [], [], []
        for text, starts, whole in rows:
            words, out = _judge(text, starts, window, whole)
            n.append(len(words))
            gone.append(int(out.sum()))
            kept.append(b" ".join(w for w, x in zip(words, out.tolist(), strict=True) if not x) if gone[-1] else b" ".join(words))
            edges = np.flatnonzero(np.diff(np.concatenate([[0], out.astype(np.int8), [0]])))
            spans.append([{"a": x, "b": y} for x, y in edges.reshape(-1, 2).tolist()])
        return pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(kept, pa.binary()), pa.array(spans, span)], ["doc_id", "n_words", "n_removed", "kept", "removed"])

    def untouched(it):
        for b in it:
            b = b.filter(pa.array(~(passes(near.value, b.column("slot").to_numpy()) & np.asarray(b.column("known")))))
            yield result(b, ((t, None, False) for (t,) in batches([b], ("text",))))

    def perhaps(it):
        for b in it:
            yield b.filter(pa.array(passes(near.value, b.column("slot").to_numpy()))).select(["doc_id", "text"])

    def judged(it):
        for b in it:
            yield result(b, ((t, s, bool(w)) for t, s, w in batches([b], ("text", "starts", "whole"))))

    base = text_bytes(docs, "doc_id").withColumn("slot", filter_slot("doc_id")).withColumn("known", F.col("doc_id").isNotNull())
    plain = base.mapInArrow(untouched, schema)
    other = base.where("known").mapInArrow(perhaps, f"doc_id {kind}, text binary").join(touched, "doc_id", "left").mapInArrow(judged, schema)
    return plain.union(other)


def digest(kept: bytes) -> str:
    return hashlib.sha256(kept).hexdigest()


def remove_reference_spans(docs: DataFrame, reference: DataFrame, window: int = WINDOW, shard_words: int = SHARD_WORDS, max_shards: int = MAX_SHARDS) -> DataFrame:
    """The same columns, with a reference table (``text``) of at most ``shard_words * max_shards`` words, which is checked."""
    spark = docs.sparkSession
    ship(spark)
    shards: list[list[bytes]] = [[]]
    size = 0
    for (text,) in reference.select(F.col("text").cast("binary")).where("text is not null").toLocalIterator():
        n = len(bytes(text).split())
        if size + n > shard_words and shards[-1]:
            shards.append([])
            size = 0
        if len(shards) > max_shards:
            raise ValueError("the reference is larger than a broadcast may be: use remove_repeats on the union of both")
        shards[-1].append(bytes(text))
        size += n
    sent = spark.sparkContext.broadcast(shards)
    kind = docs.schema["doc_id"].dataType.simpleString()
    span = pa.list_(pa.struct([("a", pa.int32()), ("b", pa.int32())]))

    def stream(it):
        built = []
        for texts in sent.value:
            number: dict[bytes, int] = {}
            auto = SuffixAutomaton()
            for t in texts:
                auto.add([number.setdefault(w, len(number)) for w in t.split()])
            built.append((number, auto))
        for b in it:
            n, gone, kept, spans = [], [], [], []
            for (text,) in batches([b], ("text",)):
                words = text.split()
                out = np.zeros(len(words) + 1, np.int64)
                for number, auto in built:
                    for end, length in enumerate(auto.statistics([number.get(w, -1) for w in words]), 1):
                        if length >= window:
                            out[end - length] += 1
                            out[end] -= 1
                hit = np.cumsum(out[:-1]) > 0
                n.append(len(words))
                gone.append(int(hit.sum()))
                kept.append(b" ".join(w for w, x in zip(words, hit.tolist(), strict=True) if not x))
                edges = np.flatnonzero(np.diff(np.concatenate([[0], hit.astype(np.int8), [0]])))
                spans.append([{"a": x, "b": y} for x, y in edges.reshape(-1, 2).tolist()])
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(kept, pa.binary()), pa.array(spans, span)], ["doc_id", "n_words", "n_removed", "kept", "removed"])

    return text_bytes(docs, "doc_id").mapInArrow(stream, f"doc_id {kind}, n_words long, n_removed long, kept binary, removed array<struct<a:int,b:int>>")
