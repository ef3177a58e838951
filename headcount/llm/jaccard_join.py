"""N-gram Jaccard join: an exact grouped prefix join over sets of word shingles, and the classes of linked documents.

Two sets with a similarity of t or more share one of their first n - ceil(t n) + 1 elements under any order of elements that
all sets agree on. The order here is: elements of at most ``frequent`` sets first, the frequent ones last, by hash within
each. Frequent shingles (passages and lines that many documents share) so leave the prefixes of all documents that have
enough other text.

1. Counts. Every task sends its shingle hashes, sorted, deduplicated and cut to 32 bits within buckets, as byte blocks; each
   bucket is counted apart, and there are as many buckets as the bytes of the texts ask for. All shingles above ``frequent`` set
   a bit of a filter of fixed size (16 MB), which is broadcast. A rare shingle that meets a set bit is taken for frequent
   wherever it occurs, so the order is the same for all sets; it only steers the work, and results do not depend on it.
2. Sets. Documents with equal sets collapse into one representative, representatives with equal prefix and size into one
   group, whose least member is its key. Both steps aggregate before they shuffle.
3. Candidates. Groups that share prefix elements of at most ``frequent`` sets are paired if their sizes allow a link and
   they share as many as a link needs (few pairs by construction). The frequent elements of a prefix are too common for that: all documents of such a block, and all
   members of a group, are compared with the least one of the block, the hub.
4. Verification reads the shingles of candidate documents only (a bit filter of fixed size picks them) and counts exactly.
5. Components of the links so far. What a block could still link are members of different components. Two members that link
   must have a number of differences to their hub in common, for which :func:`differences` gives lower bounds, so a prefix
   join over the differences finds these pairs; they are verified too. No link between different texts is lost, and a block of
   m near copies costs far fewer than m * m pairs.

Similarity is compared in integers: 100 * intersection >= percent * union. Hashes have 64 bits.

Rows of hot keys (a hub with a family of a third of all documents, an element of very many prefixes, a text with very many
copies) are dealt to many tasks by :func:`~headcount.llm.shared.salted_join`; a hub's set is sent once to each of them.

Defined cases: null and blank texts have an empty set and are linked with nothing; texts of fewer words than a shingle have
one element, all their words; texts of any length are taken whole; a similarity equal to the bound links; rows without an id
are linked with nothing; repeated rows get equal result rows; extra columns are ignored by :func:`jaccard_classes` and kept by
:func:`drop_near_duplicates`; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from headcount.operators.components import components

from .shared import batches, bit_filter, dropped, filter_slot, gram_hashes, mixed, passes, release, salted_join, ship, slot_filter, stored, text_bytes, word_hashes

WORDS, PERCENT, FREQUENT, FILTER_BITS, BUCKET_BYTES = 5, 80, 8, 27, 32 << 20
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def shingles(text: bytes, k: int = WORDS) -> np.ndarray:
    """Sorted distinct 64-bit shingle hashes of one text."""
    words = text.translate(_FOLD).split()
    a = word_hashes(words)
    if not words:
        return a
    if len(words) < k:
        h = len(words)
        for x in a.tolist():
            h = (h * 0x9E3779B97F4A7C15 + x) % 2**64
        return mixed(np.array([h], np.uint64))
    return np.unique(gram_hashes(a, k))


def prefix_length(n: int, percent: int = PERCENT) -> int:
    return n - -(-percent * n // 100) + 1


def bucket_bits(docs: DataFrame) -> int:
    """Buckets of :func:`frequent_shingles`, as a power of two: a few for each reducer, and as many as it takes for a bucket to
    hold about ``BUCKET_BYTES``, if a word has six bytes and a shingle is sent with four."""
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    by_tasks = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")).bit_length() + 2
    return min(20, max(by_tasks, int(total * 4 / 6 / BUCKET_BYTES).bit_length()))


def frequent_shingles(docs: DataFrame, k: int = WORDS, above: int = FREQUENT) -> DataFrame:
    """(element, n): the leading 32 + ``bits`` bits of shingle hashes that occur in more than ``above`` documents, with their
    counts; and ``bits``."""
    bits = bucket_bits(docs)
    flush = max(1_500_000, min(6_000_000, 24 << bits))  # some shingles for each bucket, in 50 MB at most

    def send(it):
        held, size = [], 0

        def blocks():
            v, n = np.unique(np.concatenate(held) >> np.uint64(32 - bits), return_counts=True)
            ends = np.searchsorted(v, np.arange(1, 2**bits + 1, dtype=np.uint64) << np.uint64(32))
            low = v.astype("<u4")
            out, start = ([], [], [], []), 0
            for bucket, end in enumerate(ends.tolist()):
                if end > start:
                    many = np.flatnonzero(n[start:end] > 1)
                    part = low[start:end]
                    for o, x in zip(out, (bucket, part.tobytes(), part[many].tobytes(), n[start:end][many].astype("<u4").tobytes()), strict=True):
                        o.append(x)
                start = end
            return pa.RecordBatch.from_arrays([pa.array(out[0], pa.int32()), *(pa.array(o, pa.binary()) for o in out[1:])], ["bucket", "once", "again", "times"])

        for (text,) in batches(it, ("text",)):
            s = shingles(text, k)
            held.append(s)
            size += len(s)
            if size >= flush:
                yield blocks()
                held, size = [], 0
        if size:
            yield blocks()

    def count(key, batch_iter):
        parts, again, times = [], [], []
        for b in batch_iter:
            parts += [np.frombuffer(x, "<u4") for x in b.column("once").to_pylist()]
            again += [np.frombuffer(x, "<u4") for x in b.column("again").to_pylist()]
            times += [np.frombuffer(x, "<u4") for x in b.column("times").to_pylist()]
        v, n = np.unique(np.concatenate(parts), return_counts=True)
        a, t = np.concatenate(again), np.concatenate(times)
        np.add.at(n, np.searchsorted(v, a), t.astype(np.int64) - 1)
        top = np.flatnonzero(n > above)
        element = v[top].astype(np.int64) | (key[0].as_py() << 32)
        yield pa.RecordBatch.from_arrays([pa.array(element, pa.int64()), pa.array(n[top], pa.int64())], ["element", "n"])

    def counted(key, table):
        return pa.Table.from_batches(list(count(key, table.to_batches())))

    sent = text_bytes(docs).mapInArrow(send, "bucket int, once binary, again binary, times binary")
    return sent.groupBy("bucket").applyInArrow(counted, "element long, n long"), bits


def _prefixes(docs: DataFrame, k: int, percent: int, frequent: np.ndarray) -> DataFrame:
    """doc_id, n, sig (of the set), pre (of the prefix), rare and common (the prefix by frequency)."""
    sent = docs.sparkSession.sparkContext.broadcast(frequent)
    kind = docs.schema["doc_id"].dataType.simpleString()
    factors = mixed(np.arange(1, 3, dtype=np.uint64))

    def digest(s: np.ndarray, salt: int) -> int:
        return int(mixed(np.array([(mixed(s ^ factors[salt])).sum(dtype=np.uint64) + np.uint64(len(s))], np.uint64)).view(np.int64)[0])

    def build(it):
        common = sent.value
        for b in it:
            cols: list[list] = [[] for _ in range(6)]
            for (text,) in batches([b], ("text",)):
                s = shingles(text, k)
                n = len(s)
                if n == 0:
                    row = (0, 0, 0, 0, None, None)
                else:
                    is_common = passes(common, (s >> np.uint64(64 - FILTER_BITS)).view(np.int64))
                    p = prefix_length(n, percent)
                    rare = s[~is_common][:p]
                    more = s[is_common][: p - len(rare)]
                    pre = np.concatenate([rare, more])
                    row = (n, digest(s, 0), digest(s, 1), digest(pre, 0), rare.view(np.int64), more.view(np.int64))
                for c, v in zip(cols, row, strict=True):
                    c.append(v)
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64())]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(c, t) for c, t in zip(cols, kinds, strict=True))], ["doc_id", "n", "sig", "sig2", "pre", "rare", "common"])

    return text_bytes(docs, "doc_id").mapInArrow(build, f"doc_id {kind}, n long, sig long, sig2 long, pre long, rare array<long>, common array<long>")


def _verified(docs: DataFrame, pairs: DataFrame, k: int, percent: int) -> DataFrame:
    """pairs (a, b, hub) with ``same``; where a is the hub of b, with the prefixes of their differences.

    A pair takes the set of b along, and b is in few pairs; the set of a hub meets its many pairs in the last join, once a part."""
    spark = docs.sparkSession
    ids = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct()
    words = spark.sparkContext.broadcast(bit_filter(ids, "id"))

    def sets(it):
        for b in it:
            slots = b.column("slot").to_numpy()
            near = pa.array(passes(words.value, slots))
            b = b.filter(near)
            out = [shingles(t, k).tobytes() for (t,) in batches([b], ("text",))]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(out, pa.binary())], ["id", "set"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    own = text_bytes(docs, "doc_id").where("doc_id is not null").withColumn("slot", filter_slot("doc_id")).mapInArrow(sets, f"id {kind}, set binary")
    own = own.join(ids, "id", "left_semi")
    with_b = pairs.join(own.select(F.col("id").alias("b"), F.col("set").alias("set_b")), "b")
    both = salted_join(with_b, own.select(F.col("id").alias("a"), F.col("set").alias("set_a")), "a", pairs.groupBy("a").agg(F.count("*").alias("n")), pairs.count())

    def compare(it):
        for b in it:
            cols: list[list] = [[] for _ in range(4)]
            for x, y, hub in batches([b], ("set_a", "set_b", "hub")):
                x, y = np.frombuffer(x, "<u8"), np.frombuffer(y, "<u8")
                inter = len(np.intersect1d(x, y, assume_unique=True))
                same = 100 * inter >= percent * (len(x) + len(y) - inter)
                for c, v in zip(cols, (same, *(differences(x, y, same, percent) if hub else (None, None, None))), strict=True):
                    c.append(v)
            lists = pa.list_(pa.int64())
            yield pa.RecordBatch.from_arrays([b.column("a"), b.column("b"), b.column("hub"), pa.array(cols[0], pa.bool_()), *(pa.array(c, lists) for c in cols[1:])], ["a", "b", "hub", "same", "near", "far", "sizes"])

    return both.select("a", "b", "hub", "set_a", "set_b").mapInArrow(compare, f"a {kind}, b {kind}, hub boolean, same boolean, near array<long>, far array<long>, sizes array<long>")


def differences(hub: np.ndarray, x: np.ndarray, same: bool, percent: int) -> tuple[np.ndarray, np.ndarray | None, list[int]]:
    """Prefixes of the symmetric difference of a set and its hub, see point 5 above, and [|hub|, |A|, |R|, need, weak].

    With A = x - hub and R = hub - x, |x n y| = |hub| - |R_x| - |R_y| + o, where o counts differences that x and y have in
    common. A link of x and y, of which y is not linked to the hub, needs o > a |A_x| + (1 - a) |R_x| with a = t / (1 + t); one of a
    linked y and an x that is not linked needs (1 - 2 a) |hub| less, but 1 at least. Both are bounds for prefix filters over
    the differences: added elements first, as few documents share them."""
    gone, new = np.setdiff1d(hub, x, assume_unique=True), np.setdiff1d(x, hub, assume_unique=True)
    delta = np.concatenate([new, gone]).view(np.int64)
    base = percent * len(new) + 100 * len(gone)
    need = base // (100 + percent) + 1
    weak = max(1, -(-(base - (100 - percent) * len(hub)) // (100 + percent)))
    return delta[: len(delta) - need + 1], None if same else delta[: len(delta) - weak + 1], [len(hub), len(new), len(gone), need, weak]


def jaccard_classes(docs: DataFrame, k: int = WORDS, percent: int = PERCENT, frequent: int = FREQUENT) -> DataFrame:
    """doc_id, n_shingles, representative, component_id for every row; see also :func:`jaccard_links`."""
    return _join(docs, k, percent, frequent)[0]


def jaccard_links(docs: DataFrame, k: int = WORDS, percent: int = PERCENT, frequent: int = FREQUENT) -> DataFrame:
    """Verified links (a, b) between representatives, enough of them to connect every class."""
    return _join(docs, k, percent, frequent)[1]


def _join(docs: DataFrame, k: int, percent: int, frequent: int) -> tuple[DataFrame, DataFrame]:
    spark = docs.sparkSession
    ship(spark)
    docs = docs.select("doc_id", "text")
    often, bits = frequent_shingles(docs, k, frequent)
    common = slot_filter(often, F.shiftright("element", 32 + bits - FILTER_BITS), FILTER_BITS)
    release(spark)
    rows = stored(_prefixes(docs, k, percent, common), "prefixes")

    # equal sets -> representative; equal prefix and size -> group
    full = rows.where("n > 0 and doc_id is not null")
    reps = stored(full.groupBy("n", "pre", "sig", "sig2").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n_docs")), "sets")
    alike = F.struct("n", "pre").alias("s")
    groups = reps.groupBy(alike).agg(F.min("rep").alias("g"), F.count("*").alias("n"))
    member = salted_join(reps.select(alike, "n", "sig", "sig2", "rep", "n_docs"), groups.select("s", "g"), "s", groups.select("s", "n"), reps.count())
    member = stored(member.select("n", "sig", "sig2", "rep", "n_docs", "g"), "members")
    dropped(reps)
    keys = full.join(member.select(F.col("g").alias("doc_id")).distinct(), "doc_id", "left_semi").dropDuplicates(["doc_id"])
    # n and the number of frequent elements of the prefix share a long: it is sent once per element
    keys = keys.select(F.col("doc_id").alias("g"), (F.col("n") * 2**31 + F.size("common")).alias("nh"), "rare", "common")

    # rare elements: all pairs of groups that share enough of them
    el = keys.select(F.explode("rare").alias("e"), "g", "nh")
    x, y = el.alias("x"), el.alias("y")
    n = lambda c: F.shiftright(c, 31)
    fits = (F.least(n("x.nh"), n("y.nh")) * 100 >= F.greatest(n("x.nh"), n("y.nh")) * percent) & (F.col("x.g") < F.col("y.g"))
    shared = x.join(y, (F.col("x.e") == F.col("y.e")) & fits)
    shared = shared.groupBy(F.col("x.g").alias("ga"), F.col("y.g").alias("gb")).agg(F.count("*").alias("c"), F.first("x.nh").alias("na"), F.first("y.nh").alias("nb"))
    # With o common elements at least, the k-th of them has a rank of k + n - o at most in either set, so the prefixes share at
    # least o - max(ceil(t n)) + 1 elements; the frequent ones among them are not counted here and are given away.
    least = F.ceil((n("na") + n("nb")) * percent / (100 + percent) - 1e-9) - F.greatest(*(F.ceil(n(c) * percent / 100 - 1e-9) for c in ("na", "nb"))) + 1
    given = F.least(F.col("na").bitwiseAND(2**31 - 1), F.col("nb").bitwiseAND(2**31 - 1))
    shared = shared.where(F.col("c") >= least - given).select("ga", "gb")
    # members of groups that are not alone; most groups are
    size = member.groupBy("g").agg(F.count("*").alias("n")).where("n > 1")
    many = stored(salted_join(member.select("g", "rep"), size.select("g"), "g", size, member.count()), "many")
    expanded = shared.join(many.select(F.col("g").alias("ga"), F.col("rep").alias("ra")), "ga", "left").join(many.select(F.col("g").alias("gb"), F.col("rep").alias("rb")), "gb", "left")
    near = expanded.select(F.coalesce("ra", "ga").alias("p"), F.coalesce("rb", "gb").alias("q"))

    # frequent elements and groups with members: blocks with a hub
    elements = keys.select(F.explode("common").alias("e"), "g")
    of_many = salted_join(many, elements.join(size.select("g"), "g", "left_semi"), "g", size, many.count()).select("e", "rep")
    blocks = elements.join(size.select("g"), "g", "left_anti").select("e", F.col("g").alias("rep")).union(of_many)
    blocks = stored(blocks.union(many.select(F.xxhash64("g", F.lit("group")).alias("e"), "rep")), "blocks")
    hubs = stored(blocks.groupBy("e").agg(F.min("rep").alias("hub"), F.count("*").alias("n")).where("n > 1"), "hubs")
    to_hub = salted_join(blocks, hubs.select("e", "hub"), "e", hubs, blocks.count())
    to_hub = to_hub.where("hub <> rep").select(F.col("hub").alias("a"), F.col("rep").alias("b"), F.lit(True).alias("hub"))
    pairs = near.where("p <> q").select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"), F.lit(False).alias("hub"))
    pairs = pairs.union(to_hub).groupBy("a", "b").agg(F.max("hub").alias("hub"))
    pairs = stored(pairs, "pairs")
    dropped(many, blocks, hubs)
    release(spark)
    first = stored(_verified(docs, pairs, k, percent), "verified")
    dropped(pairs)
    release(spark)

    # what blocks could still link: members of different components that share a difference to their hub
    links = first.where("same").select("a", "b")
    so_far = stored(components(links, "a", "b"), "components")
    of = so_far.select(F.col("rec_id").alias("b"), F.col("component"))
    at = first.where("hub").join(of, "b", "left").select(F.col("a").alias("h"), F.col("b").alias("rep"), "same", "near", "far", "sizes", F.coalesce("component", "b").alias("c"))
    open_hubs = at.groupBy("h").agg(F.min("c").alias("c0"), F.max("c").alias("c1")).where("c0 <> c1").select("h")
    at = stored(at.join(open_hubs, "h", "left_semi"), "open")

    def row(which, prefix: str, place: int, name: str) -> DataFrame:
        size = lambda i: F.get("sizes", F.lit(i))
        return at.where(which).select("h", F.explode(prefix).alias("e"), "rep", "c", F.struct(size(0).alias("hub"), size(1).alias("new"), size(2).alias("gone"), size(place).alias("need")).alias("v")).alias(name)

    def sharing(x: DataFrame, y: DataFrame, more) -> DataFrame:
        """Pairs that share as many differences in their prefixes as their link needs: by the ranks of common elements, the
        number needed by the pair, less the larger of the numbers that the prefixes are made for, plus 1."""
        on = (F.col("x.h") == F.col("y.h")) & (F.col("x.e") == F.col("y.e")) & (F.col("x.c") != F.col("y.c")) & more
        g = x.join(y, on).groupBy("x.h", F.col("x.rep").alias("p"), F.col("y.rep").alias("q")).agg(F.count("*").alias("n"), F.first("x.v").alias("v"), F.first("y.v").alias("w"))
        both = 2 * F.col("v.hub") - F.col("v.gone") - F.col("w.gone") + F.col("v.new") + F.col("w.new")
        needed = F.ceil(both * percent / (100 + percent) - 1e-9) - F.col("v.hub") + F.col("v.gone") + F.col("w.gone")
        return g.where(F.col("n") >= needed - F.greatest("v.need", "w.need") + 1).select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"))

    apart = sharing(row(~F.col("same"), "near", 3, "x"), row(~F.col("same"), "near", 3, "y"), F.col("x.rep") < F.col("y.rep"))
    across = sharing(row(F.col("same"), "near", 3, "x"), row(~F.col("same"), "far", 4, "y"), F.lit(True))
    rest = apart.union(across).distinct()
    rest = stored(rest.join(first.select("a", "b"), ["a", "b"], "left_anti").withColumn("hub", F.lit(False)), "rest")
    dropped(at)
    if not rest.isEmpty():
        more = stored(_verified(docs, rest, k, percent), "verified2").where("same").select("a", "b")
        links = links.union(more)
        release(spark)
        so_far = stored(components(links, "a", "b"), "components2")
    same_set = F.struct("sig", "sig2", "n").alias("s")
    of_rep = stored(member.join(so_far, member.rep == so_far.rec_id, "left").select(same_set, "rep", F.coalesce("component", "rep").alias("component"), "n_docs"), "classes")
    dropped(member)
    # a representative's row goes to all documents with its set
    out = salted_join(rows.select("doc_id", "n", same_set), of_rep.select("s", "rep", "component"), "s", of_rep.select("s", F.col("n_docs").alias("n")), rows.count(), "left")
    own = F.col("n") == 0
    classes = out.select("doc_id", F.col("n").alias("n_shingles"), F.when(own | F.col("doc_id").isNull(), F.col("doc_id")).otherwise(F.col("rep")).alias("representative"), F.when(own | F.col("doc_id").isNull(), F.col("doc_id")).otherwise(F.col("component")).alias("component_id"))
    return classes, links


def drop_near_duplicates(docs: DataFrame, k: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """One document of each class stays, the one with the least id; documents without words or id stay."""
    gone = jaccard_classes(docs, k, percent).where("component_id <> doc_id").select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, docs["doc_id"] == gone["_gone"], "left_anti")
