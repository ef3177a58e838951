"""Streaming forms: keys at read time, incremental pairs against stored buckets, running estimates, windowed estimates,
duplicate dropping under a watermark, interval joins, and buckets kept as state."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from headcount.functions.hashing import minhash
from headcount.operators import observed, sampling
from headcount.operators.components import components_auto
from headcount.sources.storage import dropped, shared_dir, stored
from headcount.sources.tables import RecordSpec


def keyed(stream: DataFrame, spec: RecordSpec, k: int, tables: int, seed: int = 42, *keep: str) -> DataFrame:
    """(rec_id, keys[, kept]) of a stream or a table: stateless, at read time."""
    from headcount.functions.shingles import char_grams, normalise, record_text, token_ids

    grams = token_ids(char_grams(normalise(record_text(spec.fields), spec.keep_space), spec.k), "portable")
    s = stream.select(F.col(spec.id_col).alias("rec_id"), minhash(grams, k * tables, seed).alias("sig"), *keep)
    return s.select("rec_id", sampling.meta_keys("sig", k, tables, mode="portable").alias("keys"), *keep)


class PairIndex:
    """A bucket table in storage that grows by micro-batches. Each batch is joined with itself and with what is stored;
    what a batch makes is written under its number, so a repeated batch replaces its own output.

    With ``truth`` (rec_id, entity) and ``known`` (id_a, id_b) the estimate is kept up too: a batch labels its own pairs only, its
    matches join components of the batch before it, and its hits add to the tally that p is read from."""

    def __init__(self, spark: SparkSession, truth: DataFrame | None = None, known: DataFrame | None = None):
        self.spark, self.truth, self.known = spark, truth, known
        self.base = shared_dir(spark)

    def _write(self, df: DataFrame, table: str, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{self.base}/{table}/batch={batch}")

    def _read(self, table: str, before: int | None = None) -> DataFrame | None:
        from pyspark.errors import AnalysisException

        try:
            df = self.spark.read.parquet(f"{self.base}/{table}")
        except AnalysisException:
            return None
        return df.where(F.col("batch") < before) if before is not None else df

    def add(self, keys: DataFrame, batch: int) -> None:
        """``foreachBatch`` target for rows (rec_id, keys)."""
        new = sampling.bucket_table(keys, "rec_id")
        self._write(new, "buckets", batch)
        now = self.spark.read.parquet(f"{self.base}/buckets/batch={batch}")
        pairs = sampling.sample_pairs(now)
        old = self._read("buckets", batch)
        if old is not None:
            x, y = now.alias("x"), old.alias("y")
            j = x.join(y, (F.col("x.tbl") == F.col("y.tbl")) & (F.col("x.key") == F.col("y.key")) & (F.col("x.rec_id") != F.col("y.rec_id")))
            agree = F.zip_with(F.col("x.keys"), F.col("y.keys"), lambda p, q: p == q)
            j = j.where(F.array_position(agree, True) == F.col("x.tbl") + 1)
            pairs = pairs.union(j.select(F.least("x.rec_id", "y.rec_id").alias("id_a"), F.greatest("x.rec_id", "y.rec_id").alias("id_b")))
        self._write(pairs.distinct(), "pairs", batch)
        if self.truth is not None:
            self._grow(self.spark.read.parquet(f"{self.base}/pairs/batch={batch}"), now, batch)

    def _grow(self, fresh: DataFrame, now: DataFrame, batch: int) -> None:
        """Components and tallies after a batch from those before it and the batch's own pairs."""
        from headcount.operators.labelling import label_by_truth

        matched = stored(label_by_truth(fresh, self.truth, "rec_id", "entity").where("is_match").select("id_a", "id_b"), "fresh")
        before = self._read("components", batch)
        empty = self.spark.createDataFrame([], "rec_id long, component long")
        # every batch writes all components, so the batch before holds the last state
        before = before.where(F.col("batch") == batch - 1).select("rec_id", "component") if before is not None else empty
        ends = matched.select(F.posexplode(F.array("id_a", "id_b")).alias("side", "rec_id"), F.struct("id_a", "id_b").alias("edge"))
        ends = ends.join(before, "rec_id", "left").select("side", "rec_id", "edge", F.coalesce("component", "rec_id").alias("at"))
        contracted = ends.groupBy("edge").agg(F.min("at").alias("id_a"), F.max("at").alias("id_b")).where("id_a <> id_b").select("id_a", "id_b").distinct()
        joined = stored(components_auto(stored(contracted, "contracted")).select(F.col("rec_id").alias("at"), F.col("component").alias("to")), "joined")
        vertices = before.union(ends.where(F.col("at") == F.col("rec_id")).select("rec_id", "at")).distinct()
        after = vertices.select("rec_id", F.col("component").alias("at")).join(joined, "at", "left").select("rec_id", F.coalesce("to", "at").alias("component"))
        self._write(after, "components", batch)
        hits = fresh.join(self.known, ["id_a", "id_b"], "left_semi").agg(F.count("*").alias("hits"))
        n = now.agg(F.count_distinct("rec_id").alias("n_records"))
        self._write(n.crossJoin(hits), "tally", batch)  # one row each
        dropped(matched, joined)

    def running_estimate(self) -> DataFrame:
        """The estimate as of the last batch, from what its increments left: no pair is labelled and no component found anew."""
        comps = self.spark.read.parquet(f"{self.base}/components")
        last = comps.agg(F.max("batch")).first()[0]
        t = self.spark.read.parquet(f"{self.base}/tally").agg(F.sum("n_records").alias("n"), F.sum("hits").alias("hits")).first()
        seen = self.spark.read.parquet(f"{self.base}/buckets").select("rec_id").distinct()
        arrived = self.known.join(seen.toDF("id_a"), "id_a", "left_semi").join(seen.toDF("id_b"), "id_b", "left_semi").count()
        comps = comps.where(F.col("batch") == (-1 if last is None else last))
        return observed.estimate_row(observed.size_histogram(comps, t["n"]), t["hits"] / arrived if arrived else None)

    def pairs(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.base}/pairs").select("id_a", "id_b").distinct()

    def estimate(self, truth: DataFrame, id_col: str, entity: str, known: DataFrame) -> DataFrame:
        """The estimate as of now; p from labelled matches whose records have both arrived."""
        from headcount.operators.labelling import edge_recall, label_by_truth

        seen = self.spark.read.parquet(f"{self.base}/buckets").select("rec_id").distinct()
        arrived = known.join(seen.toDF("id_a"), "id_a", "left_semi").join(seen.toDF("id_b"), "id_b", "left_semi")
        pairs = self.pairs()
        matched = label_by_truth(pairs, truth, id_col, entity).where("is_match")
        return observed.estimate_row(observed.size_histogram(components_auto(matched), seen.count()), edge_recall(pairs, arrived))


def drop_repeats(events: DataFrame, key: list[str], ts: str, late: str = "10 minutes") -> DataFrame:
    """Exact repeats of a key within the watermark are dropped; later rows than that are lost to the state, and counted by
    the query's progress."""
    return events.withWatermark(ts, late).dropDuplicatesWithinWatermark(key)


def windowed_histogram(events: DataFrame, ts: str, entity: list[str], width: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Records per window and entity; the sizes that a windowed estimate needs. Tumbling or sliding."""
    w = F.window(ts, width, slide) if slide else F.window(ts, width)
    return events.withWatermark(ts, late).groupBy(w.alias("w"), *entity).agg(F.count("*").alias("size"))


def session_histogram(events: DataFrame, ts: str, user: str, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return events.withWatermark(ts, late).groupBy(F.session_window(ts, gap).alias("w"), user).agg(F.count("*").alias("size"))


def interval_pairs(left: DataFrame, right: DataFrame, user: str, ts: str, id_col: str, minutes: int = 10) -> DataFrame:
    """Pairs of events of one user at most so many minutes apart, as a stream-stream join under two watermarks."""
    x = left.select(F.col(id_col).alias("id_a"), F.col(user).alias("ua"), F.col(ts).alias("ta")).withWatermark("ta", "1 hour")
    y = right.select(F.col(id_col).alias("id_b"), F.col(user).alias("ub"), F.col(ts).alias("tb")).withWatermark("tb", "1 hour")
    near = F.expr(f"ua = ub AND tb >= ta - INTERVAL {minutes} MINUTES AND tb <= ta + INTERVAL {minutes} MINUTES AND id_a < id_b")
    return x.join(y, near)


def _bucket_members(key, frames: Iterator[pd.DataFrame], state, limit: int = 0) -> Iterator[pd.DataFrame]:
    """T5: members of one bucket as state: every arrival is paired with those before it."""
    held = list(state.get[0]) if state.exists else []
    out = []
    for f in frames:
        for r in f["rec_id"].tolist():
            out += [(min(r, h), max(r, h)) for h in held if h != r]
            if r not in held:
                held.append(r)
    state.update((held[-limit:] if limit else held,))
    yield pd.DataFrame(out, columns=["id_a", "id_b"])


def stateful_pairs(buckets: DataFrame, keep_last: int = 0) -> DataFrame:
    """T5: pairs from a stream of (tbl, key, rec_id). State is a list per bucket, complete by default; ``keep_last`` bounds it to the
    latest members where hot buckets would outgrow memory (p is measured on what is left)."""

    def members(key, frames, state):
        return _bucket_members(key, frames, state, keep_last)

    return buckets.groupBy("tbl", "key").applyInPandasWithState(members, "id_a long, id_b long", "members array<long>", "append", "NoTimeout")


def _members_in_time(key, frames: Iterator[pd.DataFrame], state, span: int) -> Iterator[pd.DataFrame]:
    """Pairs of a bucket's members at most ``span`` milliseconds apart; older members and idle buckets leave the state."""
    if state.hasTimedOut:
        state.remove()
        return
    held = list(zip(*state.get, strict=True)) if state.exists else []
    out = []
    for f in frames:
        for r, at in zip(f["rec_id"].tolist(), f["at_ms"].tolist(), strict=True):
            out += [(min(r, h), max(r, h)) for h, then in held if h != r and abs(at - then) <= span]
            held.append((r, at))
    now = state.getCurrentWatermarkMs()
    held = [(h, then) for h, then in held if then >= now - span]
    if held:
        state.update(tuple(list(c) for c in zip(*held, strict=True)))
        state.setTimeoutTimestamp(max(now, max(then for _, then in held)) + span + 1)
    elif state.exists:
        state.remove()
    yield pd.DataFrame(out, columns=["id_a", "id_b"])


def expiring_pairs(buckets: DataFrame, ts: str, seconds: int, late: str = "1 hour") -> DataFrame:
    """T5 with a time limit: pairs of a stream of (tbl, key, rec_id, ts) that share a bucket at most so many seconds apart. A member
    is held until the watermark has passed it by that much, so the state follows the arrival rate and not the length of the
    stream; rows later than the watermark are lost to it."""

    def members(key, frames, state):
        return _members_in_time(key, frames, state, seconds * 1000)

    b = buckets.select("tbl", "key", "rec_id", F.unix_millis(ts).alias("at_ms"), F.col(ts).alias("_ts")).withWatermark("_ts", late)
    return b.groupBy("tbl", "key").applyInPandasWithState(members, "id_a long, id_b long", "members array<long>, at array<long>", "append", "EventTimeTimeout")


def run_to_end(df: DataFrame) -> DataFrame:
    """Run a finite stream to its end into a Parquet sink in shared storage, exactly once per batch, and read it back."""
    base = shared_dir(df.sparkSession)
    q = df.writeStream.outputMode("append").format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/stream").trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.read.schema(df.schema).parquet(f"{base}/out")
