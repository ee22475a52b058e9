"""Streams that really run, against the same operators on tables."""

import hashlib

import pytest
from pyspark.sql import functions as F

from pairsample.operators.baskets import support_counts
from pairsample.operators.sampling import sample_pairs
from pairsample.sources import tables
from pairsample.streaming import streams


@pytest.fixture(scope="module")
def events(spark, tmp_path_factory):
    """Events of three users over two days in three files, by time; one event is sent twice, the last lies days later and closes all windows."""
    path = str(tmp_path_factory.mktemp("events") / "in")
    rows = [(k, k % 3, f"2024-01-0{1 + k // 30} {(k % 30) * 40 // 60:02d}:{(k % 30) * 40 % 60:02d}:00", "view" if k % 2 else "buy", f'{{"k": {(k * 7) % 50}}}') for k in range(60)]
    rows += [rows[5]] + [(100, 9, "2024-02-01 00:00:00", "view", '{"k": 1}')]
    df = spark.createDataFrame(rows, "event_id long, user_id long, ts string, event_type string, props string").withColumn("ts", F.to_timestamp("ts"))
    df.orderBy("ts").coalesce(1).write.option("maxRecordsPerFile", 25).parquet(path)
    return path


def run(stream, tmp_path, name, mode="append"):
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
    query.awaitTermination(180)
    return stream.sparkSession.table(name)


def rows_of(df, *columns):
    return sorted(map(tuple, df.select(*columns).collect()))


def source(spark, events):
    schema = spark.read.parquet(events).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(events)


@pytest.mark.parametrize("kind", [{"length": "1 day"}, {"length": "1 day", "slide": "12 hours"}, {"length": "1 day", "session_gap": "2 hours"}])
def test_closed_windows_equal_the_batch(spark, events, tmp_path, kind):
    streamed = run(streams.window_baskets(source(spark, events), watermark="1 hour", **kind), tmp_path, f"w{len(kind)}{'g' if 'session_gap' in kind else ''}")
    batch = streams.window_baskets(spark.read.parquet(events), **kind).where("user_id <> 9")
    assert rows_of(streamed.where("user_id <> 9"), "user_id", "start", "items", "n") == rows_of(batch, "user_id", "start", "items", "n")


def test_repeats_are_dropped(spark, events, tmp_path):
    got = run(streams.without_repeats(source(spark, events), "40 days"), tmp_path, "once")
    assert got.count() == got.select("event_id").distinct().count() == 61


def test_running_supports_come_to_those_of_the_batch(spark, events, tmp_path):
    got = run(streams.running_supports(source(spark, events)), tmp_path, "supports", "complete")
    assert rows_of(got, "i", "c") == rows_of(streams.running_supports(spark.read.parquet(events), exact=True), "i", "c")


def test_stream_meets_a_static_table(spark, events, tmp_path):
    table = spark.createDataFrame([("view:0", 7)], "i string, price int")
    got = run(streams.with_items(source(spark, events), table), tmp_path, "static")
    assert rows_of(got, "event_id", "price") == rows_of(streams.with_items(spark.read.parquet(events), table), "event_id", "price")
    assert got.where("price = 7").count() > 0 and got.where("price IS NULL").count() > 0


def test_pairs_come_once_each(spark, events, tmp_path):
    got = run(streams.pairs_as_they_come(source(spark, events)), tmp_path, "pairs")
    baskets = spark.read.parquet(events).select(F.concat_ws("@", F.col("user_id"), F.date_format("ts", "yyyy-MM-dd")).alias("t"), streams.item().alias("i")).distinct()
    wanted = baskets.alias("x").join(baskets.select("t", F.col("i").alias("j")), "t").where("i < j").select("t", "i", "j")
    assert rows_of(got, "t", "i", "j") == rows_of(wanted, "t", "i", "j")
    for row in got.limit(5).collect():
        assert row.r == int(hashlib.md5(f"42:{row.t}".encode()).hexdigest()[:8], 16) / 2**32


def test_candidates_of_unknown_items_are_kept(spark):
    baskets = spark.createDataFrame([(t, i) for t in range(3) for i in (1, 2)], "t long, i long")
    early = spark.createDataFrame([(1, 1)], "i long, c long")
    got = streams.thin(streams.admit(baskets, early, "cosine", 15.0, 0.5), support_counts(baskets), "cosine", 15.0, 0.5)
    assert rows_of(got, "i", "j", "k", "ci", "cj") == rows_of(sample_pairs(baskets, "cosine", 15.0, 0.5), "i", "j", "k", "ci", "cj") == [(1, 2, 3, 3, 3)]


def test_stream_source_reads_its_schema(spark, events):
    assert tables.stream_events(spark, events).isStreaming
