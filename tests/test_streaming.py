"""Streams give what their batch twins give, with rows out of order, doubled and late."""

import shutil

import pytest
from pyspark.sql import functions as F

from opatlas.operators import itemsets, pairs, records
from opatlas.sources import corpus, io
from opatlas.streaming import pairs as streams

SF = "/root/testdata/sf0.001"
SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def events(spark):
    return io.read(spark, SF, "events").withColumn("ts", F.col("ts").cast("timestamp"))


@pytest.fixture()
def source(spark, tmp_path):
    """Events in four files by time, the second with rows doubled."""
    e = events(spark).repartitionByRange(1, "ts").sortWithinPartitions("ts", "event_id")
    cuts = e.selectExpr("percentile_approx(ts, array(0.25, 0.5, 0.75))").first()[0]
    bounds = [None, *cuts, None]
    for i in range(4):
        part = e.where((F.lit(True) if bounds[i] is None else F.col("ts") >= bounds[i]) & (F.lit(True) if bounds[i + 1] is None else F.col("ts") < bounds[i + 1]))
        part = part.unionByName(part.limit(20)) if i == 1 else part
        part.orderBy(F.xxhash64("event_id")).coalesce(1).write.parquet(str(tmp_path / f"p{i}"))
        for f in (tmp_path / f"p{i}").glob("*.parquet"):
            (tmp_path / "in").mkdir(exist_ok=True)
            shutil.move(f, tmp_path / "in" / f"{i}.parquet")
    return str(tmp_path / "in")


def drain(stream, name, mode="append"):
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return stream.sparkSession.table(name)


def read(spark, source):
    return io.read_stream(spark, source, SCHEMA, maxFilesPerTrigger="1")


def test_dedup_then_windows(spark, source):
    once = streams.dedup(read(spark, source), watermark="60 days")
    got = drain(once, "once")
    assert got.count() == events(spark).count() == got.select("event_id").distinct().count()


def test_complete_windows_equal_batch(spark, source):
    stream = read(spark, source).dropDuplicates(["event_id"])
    counts = stream.groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")
    got = {tuple(r) for r in drain(counts, "windows", "complete").collect()}
    assert got == {tuple(r) for r in streams.tumble(events(spark)).collect()}


def test_late_rows_are_dropped(spark, tmp_path):
    # a batch filters late rows by the watermark that stood before the batch ahead of it
    rows = [(1, "2024-01-01 00:00:00"), (2, "2024-01-10 00:00:00"), (5, "2024-01-11 00:00:00"), (3, "2024-01-01 01:00:00"), (4, "2024-01-20 00:00:00")]
    for i, (n, ts) in enumerate(rows):
        df = spark.createDataFrame([(n, ts)], "event_id long, ts string").selectExpr("event_id", "CAST(ts AS TIMESTAMP) AS ts", "1L AS user_id", "'click' AS event_type", "0D AS value", "'' AS props")
        df.coalesce(1).write.parquet(str(tmp_path / f"q{i}"))
        (tmp_path / "late").mkdir(exist_ok=True)
        for f in (tmp_path / f"q{i}").glob("*.parquet"):
            shutil.move(f, tmp_path / "late" / f"{i}.parquet")
    got = drain(streams.tumble(read(spark, str(tmp_path / "late"))), "late")
    assert {(str(r.start)[:10], r.n) for r in got.collect()} == {("2024-01-01", 1), ("2024-01-10", 1), ("2024-01-11", 1)}


def test_stateful_pairs_equal_batch(spark, source):
    stream = read(spark, source).dropDuplicates(["event_id"])
    got = drain(streams.neighbour_pairs(stream), "pairs")
    assert got.where("late").count() == 0
    batch = pairs.neighbour(events(spark), ("ts", "event_id"), rec="user_id", op="event_type")
    count = lambda df: {(r.caller, r.callee): r["count"] for r in df.groupBy("caller", "callee").count().collect()}
    assert count(got) == count(batch)


def test_interval_join_and_catalogue(spark, source):
    stream = read(spark, source).dropDuplicates(["event_id"])
    got = drain(streams.interval_join(stream, watermark="60 days", before="10 hours"), "near")
    from opatlas.queries.relational import g_interval

    want = {tuple(r) for r in g_interval(spark, SF).select("view_id", "purchase_id").collect()}
    assert {tuple(r) for r in got.collect()} == want
    known = spark.createDataFrame([("click",)], "event_type string")
    assert drain(streams.with_catalogue(read(spark, source), known), "known").where("event_type <> 'click'").count() == 0


def test_incremental_support_equals_batch(spark):
    rec = records.make(corpus.event_items(spark, SF)).withColumn("p", F.pmod(F.xxhash64("rec_id"), F.lit(3)))
    kept = streams.IncrementalSupport(spark, "0.05", 2)
    for i in range(3):
        kept.add(rec.where(F.col("p") == i), i)
    kept.add(rec.where("p = 0"), 0)  # delivered twice
    want = {tuple(r["items"]): r.freq for r in itemsets.apriori(rec, "0.05", max_k=2).combos.collect()}
    assert kept.frequent() == want
    assert kept.border <= set(want) | set(kept._frequent(1))
    # another driver on the same table goes on from there
    again = streams.IncrementalSupport(spark, "0.05", 2, kept.path)
    again.add(rec.where("p = 1"), 1)
    assert again.frequent() == want and again.versions() == [1, 2]


def test_incremental_support_of_nothing_and_of_a_failed_batch(spark):
    kept = streams.IncrementalSupport(spark, "0.5", 2)
    assert kept.frequent() == {} and kept.border == set()
    none = spark.createDataFrame([], "rec_id long, items array<string>")
    kept.add(none, 0)
    assert kept.frequent() == {} and kept.versions() == [0]
    # what a failed batch left without its mark is written anew
    spark.createDataFrame([(["z"], 9)], "items array<string>, freq long").write.option("mapreduce.fileoutputcommitter.marksuccessfuljobs", "false").parquet(f"{kept.path}/1")
    assert kept.versions() == [0]
    kept.add(spark.createDataFrame([(1, ["a", "b"]), (2, ["a"])], "rec_id long, items array<string>"), 1)
    assert kept.frequent() == {("a",): 2, ("b",): 1, ("a", "b"): 1}
    assert kept.border == set(kept.frequent())
