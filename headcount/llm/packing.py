"""Best-fit packing: bounded-space online best fit over sequences of fixed capacity.

Documents are encoded, ended by a separator id, and cut only if longer than a sequence; then the first piece is the short
one. Full pieces take a sequence each. The others are dealt by a hash of their id and each task packs its share online:
batch by batch, the longest first:
open sequences are kept by free space, a bitset (one integer) finds the tightest that fits, and when more than ``open_bins``
are open the fullest closes. What a task leaves unfilled goes, as one item per sequence, to a second round of fewer tasks,
so that the number of half-filled sequences does not grow with the number of tasks.

Defined cases: a null or empty text is the separator alone; repeated rows are packed as often as they occur; an empty table
gives no pieces.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from .shared import batches, ship, stored, text_bytes
from .tokens import encoder, vocabulary_path

CAPACITY, SEPARATOR, OPEN_BINS = 1024, 2, 4096


class OpenBins:
    """Open sequences by free space. ``put`` returns (bin, offset) and, in ``closed``, what had to close."""

    def __init__(self, capacity: int = CAPACITY, limit: int = OPEN_BINS):
        self.capacity, self.limit = capacity, limit
        self.bits, self.count, self.made = 0, 0, 0
        self.by_free: list[list[int]] = [[] for _ in range(capacity + 1)]
        self.closed: list[tuple[int, int]] = []  # (bin, fill)

    def put(self, size: int) -> tuple[int, int]:
        fits = self.bits >> size
        if fits:
            free = size + (fits & -fits).bit_length() - 1
            own = self.by_free[free]
            b = own.pop()
            self.count -= 1
            if not own:
                self.bits ^= 1 << free
        else:
            b, free = self.made, self.capacity
            self.made += 1
        left = free - size
        if left == 0:
            self.closed.append((b, self.capacity))
        else:
            self._open(b, left)
            if self.count > self.limit:
                least = (self.bits & -self.bits).bit_length() - 1
                self.closed.append((self._take(least), self.capacity - least))
        return b, self.capacity - free

    def _open(self, b: int, free: int) -> None:
        self.by_free[free].append(b)
        self.bits |= 1 << free
        self.count += 1

    def _take(self, free: int) -> int:
        b = self.by_free[free].pop()
        self.count -= 1
        if not self.by_free[free]:
            self.bits ^= 1 << free
        return b

    def rest(self) -> list[tuple[int, int]]:
        """Closes what is still open: (bin, fill)."""
        return [(b, self.capacity - f) for f, own in enumerate(self.by_free) for b in own]


def pieces(docs: DataFrame, tokenizer: str | None = None, capacity: int = CAPACITY, separator: int = SEPARATOR, with_ids: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 (and the ids as little-endian bytes if asked for) of all documents."""
    ship(docs.sparkSession)
    path, end, key = tokenizer or vocabulary_path(), np.array([separator], "<u4").tobytes(), docs.schema["doc_id"].dataType
    names = ["doc_id", "piece", "start", "length", "ids_crc32"] + ["ids"] * with_ids

    def cut(it) -> Iterator[pa.RecordBatch]:
        encode = encoder(path).encode
        for b in it:
            rows: list[list] = [[] for _ in names]
            for doc, text in batches([b], ("doc_id", "text")):
                ids = encode(text.decode("utf-8", "replace")) + end
                n = len(ids) // 4
                first = n % capacity or capacity
                at = 0
                for k in range(-(-n // capacity)):
                    to = first + k * capacity
                    part = ids[4 * at : 4 * to]
                    for out, v in zip(rows, (doc, k, at, to - at, zlib.crc32(part), part), strict=False):
                        out.append(v)
                    at = to
            kinds = [b.schema.field("doc_id").type, pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array(r, k) for r, k in zip(rows, kinds, strict=False)], names)

    schema = f"doc_id {key.simpleString()}, piece int, start long, length long, ids_crc32 long" + ", ids binary" * with_ids
    return text_bytes(docs, "doc_id").mapInArrow(cut, schema)


def _placed(bins: OpenBins, sizes: pa.Array) -> list[tuple[int, int]]:
    """Puts the items of one batch, the longest first."""
    n = sizes.to_numpy(zero_copy_only=False)
    at: list = [None] * len(n)
    for i in np.argsort(-n, kind="stable").tolist():
        at[i] = bins.put(int(n[i]))
    return at


def pack(items: DataFrame, capacity: int = CAPACITY, open_bins: int = OPEN_BINS) -> DataFrame:
    """``items`` (any columns, among them ``length`` <= capacity) with sequence_id and offset.

    Round 1 packs within tasks. Sequences that it leaves less than full by more than 1/32 are the items of round 2; a task
    hands on ``open_bins`` of them at most, so round 2 gets one task for each 1,000 shuffle partitions.
    """
    from pyspark.taskcontext import TaskContext

    names = [*items.columns, "sequence_id", "offset"]
    schema = StructType([*items.schema.fields, StructField("sequence_id", LongType()), StructField("offset", LongType()), StructField("_fill", IntegerType())])
    slack = capacity - capacity // 32

    def first(it):
        base, bins = TaskContext.get().partitionId() << 32, OpenBins(capacity, open_bins)
        for b in it:
            at = _placed(bins, b.column("length"))
            cols = [*b.columns, pa.array([base + x for x, _ in at], pa.int64()), pa.array([y for _, y in at], pa.int64()), pa.nulls(len(at), pa.int32())]
            yield pa.RecordBatch.from_arrays(cols, [*b.schema.names, "sequence_id", "offset", "_fill"])
        # rows without an item: what stays open, with its fill
        left = [(base + x, fill) for x, fill in bins.rest() if fill < slack]
        if left:
            empty = [pa.nulls(len(left), f.type) for f in b.schema]
            cols = [*empty, pa.array([x for x, _ in left], pa.int64()), pa.nulls(len(left), pa.int64()), pa.array([y for _, y in left], pa.int32())]
            yield pa.RecordBatch.from_arrays(cols, [*b.schema.names, "sequence_id", "offset", "_fill"])

    def again(it):
        base, bins = (1 << 62) + (TaskContext.get().partitionId() << 32), OpenBins(capacity, 4 * open_bins)
        for b in it:
            at = _placed(bins, b.column("_fill"))
            yield pa.RecordBatch.from_arrays([b.column("sequence_id"), pa.array([base + x for x, _ in at], pa.int64()), pa.array([y for _, y in at], pa.int64())], ["sequence_id", "_into", "_shift"])

    ship(items.sparkSession)
    merge_tasks = int(items.sparkSession.conf.get("spark.sql.shuffle.partitions")) // 1000 + 1
    one = stored(items.mapInArrow(first, schema), "packed")
    moved = one.where("_fill is not null").select("sequence_id", "_fill").repartition(merge_tasks).sortWithinPartitions(F.desc("_fill"), "sequence_id")
    moved = moved.mapInArrow(again, "sequence_id long, _into long, _shift long")
    out = one.where("_fill is null").drop("_fill").join(moved, "sequence_id", "left")
    return out.withColumn("sequence_id", F.coalesce("_into", "sequence_id")).withColumn("offset", F.col("offset") + F.coalesce("_shift", F.lit(0))).select(*names)


def pack_documents(docs: DataFrame, tokenizer: str | None = None, capacity: int = CAPACITY, separator: int = SEPARATOR, open_bins: int = OPEN_BINS, with_ids: bool = False) -> DataFrame:
    """Encode, cut and pack all documents."""
    items = pieces(docs, tokenizer, capacity, separator, with_ids)
    dealt = items.repartition("doc_id", "piece")  # AQE joins small shares, so a task packs many pieces
    return pack(dealt.sortWithinPartitions("doc_id", "piece"), capacity, open_bins)


def sequences(packed: DataFrame) -> DataFrame:
    """The sequences themselves, from a result of ``pack_documents(..., with_ids=True)``: id and token ids as bytes."""
    parts = F.sort_array(F.collect_list(F.struct("offset", "ids")))
    return packed.groupBy("sequence_id").agg(F.aggregate(parts, F.lit(b""), lambda a, x: F.concat(a, x["ids"])).alias("ids"))
