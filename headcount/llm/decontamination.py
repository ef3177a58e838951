"""Benchmark decontamination: documents stream through a generalised suffix automaton of the normalised test items.

Normalising lower-cases A-Z and keeps runs of ASCII letters, digits and all characters beyond ASCII. A document word is hit
if it lies inside an occurrence of a window: ``window`` consecutive words of an item, or a whole shorter item. The cleaning
form removes hit spans, and the document itself if more than ``max_coverage`` of its words are hit.

The items go to the workers as automata of at most ``shard_words`` words each. Spark normalises the items, counts their words
and cuts longer ones into parts that overlap by a window less one word, so that every window is whole in some part. The driver
streams the parts and holds the shards of one pass at most: ``max_shards`` automata, which is what one broadcast carries. A
larger benchmark takes further passes by itself, over rows that are written once with a number; hits are united by row.

Defined cases: null texts and texts without words have no hits; texts of any length stream whole; null and empty items, and
items without an id, have no windows; repeated items count by item_id; an empty benchmark hits nothing; null and repeated
document ids are rows like others, and repeated documents give repeated rows; extra columns are kept by :func:`decontaminate`
and ignored by :func:`hits`; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import string
from collections.abc import Iterator
from itertools import chain

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .automaton import SuffixAutomaton
from .shared import batches, bit_filter, filter_slot, passes, ship, stored, text_bytes

WINDOW, SHARD_WORDS, MAX_SHARDS = 10, 100_000, 4
SPAN = pa.struct([("a", pa.int32()), ("b", pa.int32())])
#: Byte table: A-Z to a-z, word bytes to themselves, all others to a space.
FOLD = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


class Detector:
    """Automata of items with the numbering of their words."""

    def __init__(self, items: list[tuple[str, bytes]], window: int = WINDOW):
        self.window, self.number, self.ids = window, {}, [i for i, _ in items]
        seqs = [[self.number.setdefault(w, len(self.number)) for w in t.translate(FOLD).split()] for _, t in items]
        self.automaton = SuffixAutomaton()
        for s in seqs:
            self.automaton.add(s)
        self.automaton.settle(seqs, window)
        self.least = min((min(len(s), window) for s in seqs if s), default=0)

    def spans(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set[str]]:
        """Maximal hit spans (first word, end) and the items that have occurring windows."""
        out: list[tuple[int, int]] = []
        found: set[int] = set()
        if not self.least:
            return out, set()
        numbers = list(map(self.number.get, words))
        numbers.append(None)
        start, n = 0, len(numbers)
        while start < n:
            try:  # stretches without words of any item cannot be hit
                stop = numbers.index(None, start)
            except ValueError:
                stop = n
            if stop - start >= self.least:
                for end, length, items in self.automaton.matches(numbers[start:stop], self.window):
                    a, b = start + end - length, start + end
                    while out and out[-1][1] >= a:
                        a = min(a, out.pop()[0])
                    out.append((a, b))
                    found |= set(items)
            start = stop + 1
        return out, {self.ids[i] for i in found}


def item_parts(benchmark: DataFrame, window: int = WINDOW, shard_words: int = SHARD_WORDS) -> DataFrame:
    """(item, text, n): the items as folded words joined by spaces, in overlapping parts of at most ``shard_words`` words."""
    size = max(shard_words, 2 * window)
    step = size - (window - 1)
    folded = F.translate(F.col("text"), string.ascii_uppercase, string.ascii_lowercase)
    words = F.regexp_extract_all(folded, F.lit(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"), F.lit(0))
    items = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("string").alias("item"), words.alias("w")).where(F.size("w") > 0)
    parts = F.when(F.size("w") <= size, F.lit(1)).otherwise(F.ceil((F.size("w") - (window - 1)) / step)).cast("int")
    items = items.select("item", "w", F.explode(F.sequence(F.lit(0), parts - 1)).alias("i"))
    own = F.slice("w", F.col("i") * step + 1, F.lit(size))
    return items.select("item", F.array_join(own, " ").cast("binary").alias("text"), F.size(own).cast("long").alias("n"))


def _shard_passes(benchmark: DataFrame, window: int, shard_words: int, max_shards: int) -> Iterator[tuple[list[list[tuple[str, bytes]]], bool]]:
    """The shards of one pass after the other, and whether more follow. The driver holds one pass and one partition of parts,
    which are made about as large as a shard."""
    parts = item_parts(benchmark, window, shard_words)
    words = parts.agg(F.sum("n")).first()[0] or 0
    if words > shard_words * max_shards:
        parts = stored(parts, "items").repartition(-(-words // shard_words))
    shards: list[list[tuple[str, bytes]]] = [[]]
    size = 0
    for item, text, n in parts.toLocalIterator():
        if shards[-1] and size + n > shard_words:
            if len(shards) == max_shards:
                yield shards, True
                shards = []
            shards.append([])
            size = 0
        shards[-1].append((item, bytes(text)))
        size += n
    yield shards, False


def hits(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, shard_words: int = SHARD_WORDS, max_shards: int = MAX_SHARDS) -> DataFrame:
    """doc_id, n_words, spans (array of first word and end), items (sorted ids as strings) for every document."""
    passes_ = _shard_passes(benchmark, window, shard_words, max_shards)
    shards, more = next(passes_)
    if not more:
        return _one_pass(docs, shards, window)
    rows = stored(docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", "text"), "rows")
    found = _found(rows, chain([(shards, more)], passes_), window)
    counted = _one_pass(rows.select(F.col("row").alias("doc_id"), "text"), [[]], window).select(F.col("doc_id").alias("row"), "n_words")
    out = rows.select("row", "doc_id").join(counted, "row").join(found, "row", "left")
    none = F.array().cast
    return out.select("doc_id", "n_words", F.coalesce("spans", none("array<struct<a:int,b:int>>")).alias("spans"), F.coalesce("items", none("array<string>")).alias("items"))


def _found(rows: DataFrame, passes_, window: int) -> DataFrame:
    """(row, spans, items) of the rows that are hit in any pass. Every pass is run and written before the next one is read."""
    out = None
    for shards, _ in passes_:
        one = _one_pass(rows.select(F.col("row").alias("doc_id"), "text"), shards, window).where(F.size("spans") > 0)
        one = stored(one.select(F.col("doc_id").alias("row"), "spans", "items"), "pass")
        out = one if out is None else out.union(one)
    g = out.groupBy("row").agg(F.flatten(F.collect_list("spans")).alias("s"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))

    def united(b):
        for x in b:
            spans = [_united([(s["a"], s["b"]) for s in row]) for row in x.column("s").to_pylist()]
            yield pa.RecordBatch.from_arrays([x.column("row"), pa.array([[{"a": i, "b": j} for i, j in s] for s in spans], pa.list_(SPAN)), x.column("items")], ["row", "spans", "items"])

    return g.mapInArrow(united, "row long, spans array<struct<a:int,b:int>>, items array<string>")


def _united(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Maximal spans of a union: those that touch become one."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and out[-1][1] >= a:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def _detectors(shards, window, cache={}):  # noqa: B006  one per worker
    key = id(shards)
    if key not in cache:
        cache.clear()
        cache[key] = shards, [Detector(s, window) for s in shards]  # holding the shards keeps their id taken
    return cache[key][1]


def _find(detectors: list[Detector], words: list[bytes]) -> tuple[list[tuple[int, int]], set[str]]:
    out, found = [], set()
    for d in detectors:
        spans, items = d.spans(words)
        out += spans
        found |= items
    return _united(out) if len(detectors) > 1 else out, found


def _one_pass(docs: DataFrame, shards, window: int) -> DataFrame:
    ship(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(shards)
    kind = docs.schema["doc_id"].dataType.simpleString()

    def look(it):
        detectors = _detectors(sent.value, window)
        for b in it:
            n, spans, items = [], [], []
            for (text,) in batches([b], ("text",)):
                words = text.translate(FOLD).split()
                s, i = _find(detectors, words)
                n.append(len(words))
                spans.append([{"a": x, "b": y} for x, y in s])
                items.append(sorted(i))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(n, pa.int64()), pa.array(spans, pa.list_(SPAN)), pa.array(items, pa.list_(pa.string()))], ["doc_id", "n_words", "spans", "items"])

    return text_bytes(docs, "doc_id").mapInArrow(look, f"doc_id {kind}, n_words long, spans array<struct<a:int,b:int>>, items array<string>")


def digest(items: list[str]) -> str:
    return hashlib.sha256(",".join(items).encode()).hexdigest()


def cut(text: bytes, spans: list[tuple[int, int]]) -> bytes:
    """The text without the words of the spans and what stands between them."""
    import re

    at = [m.span() for m in re.finditer(rb"[^ ]+", text.translate(FOLD))]
    out, done = [], 0
    for a, b in spans:
        out.append(text[done : at[a][0]])
        done = at[b - 1][1]
    out.append(text[done:])
    return b"".join(out)


def decontaminate(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, max_coverage: float = 0.5, shard_words: int = SHARD_WORDS, max_shards: int = MAX_SHARDS) -> DataFrame:
    """The documents without hit spans and without those covered beyond ``max_coverage``; untouched documents keep every
    byte, and n_chars, where there is one, follows the text."""
    passes_ = _shard_passes(benchmark, window, shard_words, max_shards)
    shards, more = next(passes_)
    names = [f"c{i}" for i in range(len(docs.columns))]  # clashing names of extra columns don't matter
    text = names[docs.columns.index("text")]
    packed = docs.toDF(*names).withColumn("_text", F.coalesce(F.col(text).cast("binary"), F.lit(b"")))
    schema = ", ".join(f"{n} {f.dataType.simpleString()}" for n, f in zip(names, docs.schema.fields, strict=True)) + ", _new binary"
    ship(docs.sparkSession)

    def cleaned(b, found):
        """The rows of a batch that stay, with their new texts (null: unchanged)."""
        keep, new = [], []
        for (raw,), spans in zip(batches([b], ("_text",)), found, strict=False):
            words = raw.translate(FOLD).split() if spans else ()
            keep.append(sum(y - x for x, y in spans) <= max_coverage * len(words))
            new.append(cut(raw, spans) if spans and keep[-1] else None)
        return pa.RecordBatch.from_arrays([*map(b.column, names), pa.array(new, pa.binary())], [*names, "_new"]).filter(pa.array(keep, pa.bool_()))

    if not more:
        sent = docs.sparkSession.sparkContext.broadcast(shards)

        def clean(it):
            detectors = _detectors(sent.value, window)
            for b in it:
                yield cleaned(b, (_find(detectors, raw.translate(FOLD).split())[0] for (raw,) in batches([b], ("_text",))))

        out = packed.mapInArrow(clean, schema)
    else:
        rows = stored(packed.withColumn("_row", F.monotonically_increasing_id()), "packed")
        found = stored(_found(rows.select(F.col("_row").alias("row"), F.col("_text").alias("text")), chain([(shards, more)], passes_), window).select(F.col("row").alias("_row"), "spans"), "found")
        near = docs.sparkSession.sparkContext.broadcast(bit_filter(found, "_row"))

        def untouched(it):
            for b in it:
                far = b.filter(pa.array(~passes(near.value, b.column("_slot").to_numpy())))
                yield cleaned(far, ((),) * far.num_rows)

        def perhaps(it):
            for b in it:
                yield b.filter(pa.array(passes(near.value, b.column("_slot").to_numpy()))).select([*names, "_text", "_row"])

        def joined(it):
            for b in it:
                yield cleaned(b, ([(s["a"], s["b"]) for s in x or ()] for (x,) in batches([b], ("spans",))))

        slotted = rows.withColumn("_slot", filter_slot("_row"))
        some = slotted.mapInArrow(perhaps, schema.replace(", _new binary", ", _text binary, _row long")).join(found, "_row", "left")
        out = slotted.mapInArrow(untouched, schema).union(some.mapInArrow(joined, schema))
    changed = F.col("_new").cast("string")
    cols = []
    for n, f in zip(names, docs.schema.fields, strict=True):
        new = {"text": changed, "n_chars": F.length(changed).cast(f.dataType)}.get(f.name)
        cols.append((F.col(n) if new is None else F.when(F.col("_new").isNotNull(), new).otherwise(F.col(n))).alias(f.name))
    return out.select(*cols)
