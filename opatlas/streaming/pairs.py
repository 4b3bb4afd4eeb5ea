"""Pair statistics and support on streams: each function takes and gives a streaming DataFrame.

Streams have columns ts, event_id, user_id, event_type. Batch twins are in ``queries``.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.itemsets import enumerate_all, least_count
from ..session import shared_dir


def tumble(events: DataFrame, *, watermark: str = "1 hour", window: str = "1 day") -> DataFrame:
    """Events per type and window; late rows beyond the watermark are dropped."""
    late = events.withWatermark("ts", watermark) if events.isStreaming else events
    return late.groupBy(F.window("ts", window).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def slide(events: DataFrame, *, watermark: str = "1 hour", window: str = "1 day", slide: str = "6 hours") -> DataFrame:
    late = events.withWatermark("ts", watermark) if events.isStreaming else events
    return late.groupBy(F.window("ts", window, slide).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def session(events: DataFrame, *, watermark: str = "1 hour", gap: str = "12 hours") -> DataFrame:
    """Sessions of a user by a gap: user_id, start, n."""
    late = events.withWatermark("ts", watermark) if events.isStreaming else events
    return late.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def dedup(events: DataFrame, *, watermark: str = "1 day") -> DataFrame:
    """Each event once, however often it is delivered within the watermark."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def with_catalogue(events: DataFrame, operators: DataFrame) -> DataFrame:
    """Stream-static join: known operators only."""
    return events.join(F.broadcast(operators), "event_type")


def interval_join(events: DataFrame, *, watermark: str = "1 hour", before: str = "10 minutes") -> DataFrame:
    """Views of a user up to ``before`` before a purchase, stream with stream: view_id, purchase_id."""
    views = events.where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("event_id").alias("view_id"), F.col("ts").alias("view_ts")).withWatermark("view_ts", watermark)
    buys = events.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("purchase_ts")).withWatermark("purchase_ts", watermark)
    near = F.expr(f"u = user_id AND view_ts >= purchase_ts - INTERVAL {before} AND view_ts <= purchase_ts")
    return views.join(buys, near).select("view_id", "purchase_id")


def neighbour_pairs(events: DataFrame) -> DataFrame:
    """Pairs of a user's consecutive events across micro-batches: the state is the last operator and its place.

    Rows of a micro-batch are put in order; rows older than the state's place are late and
    counted as such, not paired.
    """

    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        last = state.get if state.exists else (None, None, None)
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        out = []
        for r in rows.itertuples():
            at = (r.ts.value, int(r.event_id))
            if last[0] is not None and at <= (last[1], last[2]):
                out.append((int(key[0]), None, r.event_type, True))
                continue
            if last[0] is not None:
                out.append((int(key[0]), last[0], r.event_type, False))
            last = (r.event_type, *at)
        if last[0] is not None:
            state.update(last)
        yield pd.DataFrame(out, columns=["user_id", "caller", "callee", "late"])

    return events.select("user_id", "ts", "event_id", "event_type").groupBy("user_id").applyInPandasWithState(
        step, "user_id long, caller string, callee string, late boolean", "op string, at long, id long", "append", "NoTimeout"
    )


class IncrementalSupport:
    """Counts of all sets up to ``k`` items, kept up over micro-batches by ``foreachBatch``.

    Records must arrive whole. Counts are a table in ``path`` (else in the shared folder), in one
    version for each batch: those of the version before and the batch's own, added by set; the
    empty set counts the records. A version stands once it is written whole, so a batch that
    failed is done anew and one that is delivered again changes nothing, after a restart on the
    same ``path`` too. Batch ids must rise, as those of a stream do. Only frequent sets come to
    the driver. ``border`` says which sets crossed the threshold by the last batch, the only ones
    to mine anew above ``k``.
    """

    def __init__(self, spark: SparkSession, min_support: str = "0.05", k: int = 2, path: str | None = None) -> None:
        self.spark, self.min_support, self.k = spark, min_support, k
        self.path = path or f"{shared_dir(spark).rstrip('/')}/support-{uuid.uuid4().hex}"

    def _folder(self, name: str):
        """A path below the table's and its file system, whichever that is."""
        found = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
        return found, found.getFileSystem(self.spark._jsparkSession.sessionState().newHadoopConf())

    def versions(self) -> list[int]:
        """The batches whose counts are written whole; older ones than the last two are removed."""
        marks, files = self._folder("*/_SUCCESS")
        return sorted(int(x.getPath().getParent().getName()) for x in files.globStatus(marks) or ())

    def _frequent(self, version: int) -> dict[tuple[str, ...], int]:
        counts = self.spark.read.parquet(f"{self.path}/{version}")
        n = counts.where(F.size("items") == 0).first().freq
        least = least_count(self.min_support, n) if n else 1
        return {tuple(r["items"]): r.freq for r in counts.where((F.size("items") > 0) & (F.col("freq") >= least)).collect()}

    def frequent(self) -> dict[tuple[str, ...], int]:
        done = self.versions()
        return self._frequent(done[-1]) if done else {}

    @property
    def border(self) -> set[tuple[str, ...]]:
        done = self.versions()
        before = set(self._frequent(done[-2])) if len(done) > 1 else set()
        return before ^ set(self.frequent())

    def add(self, batch: DataFrame, batch_id: int) -> None:
        """One micro-batch of records (items); a batch that is delivered again is not counted again."""
        done = self.versions()
        if done and batch_id <= done[-1]:
            return
        rows = batch.select("items")
        own = enumerate_all(rows, self.k).select("items", "freq")
        both = own.unionByName(rows.agg(F.array().cast("array<string>").alias("items"), F.count("*").alias("freq")))
        if done:
            both = both.unionByName(batch.sparkSession.read.parquet(f"{self.path}/{done[-1]}"))
        both.groupBy("items").agg(F.sum("freq").alias("freq")).write.mode("overwrite").parquet(f"{self.path}/{batch_id}")
        for old in done[:-1]:
            folder, files = self._folder(str(old))
            files.delete(folder, True)
