import pytest
from helpers import TINY
from pyspark.sql import functions as F

from hypertriad.model import canonicalize, incidence
from hypertriad.plans.planner import triads
from hypertriad.sources.files import from_lists
from hypertriad.streaming.triads import TriadStore, event_stream, merge_samples, session_edges, windowed_edges


def some(df):
    return {r["pattern"]: r["cnt"] for r in df.collect() if r["cnt"]}


def test_store_equals_batch(spark, tmp_path):
    lists = [[1, 2, 3], [2, 3], [3, 4, 5], [1, 5], [2, 5, 6], [1, 2, 3, 4], [3, 2], [7]]
    rows = [(k, m) for k, m in enumerate(lists, 1)]
    store = TriadStore(spark, str(tmp_path / "store"))
    for batch, part in enumerate((rows[:3], rows[3:6], rows[6:])):
        store.add(spark.createDataFrame(part, "e long, members array<long>"), batch)
    want = some(triads(canonicalize(from_lists(spark, lists)), mode="count"))
    assert some(store.counts()) == want
    store.add(spark.createDataFrame(rows[6:], "e long, members array<long>"), 2)  # the same batch again
    assert some(store.counts()) == want
    assert store.edges().count() == 7
    whole = store.sample(4)
    assert whole.count() == 4
    halves = [store.links().where(F.col("i") % 2 == k).select("i", "j") for k in (0, 1)]
    assert sorted(merge_samples(*halves, 4).collect()) == sorted(whole.select("i", "j").collect())


@pytest.fixture(scope="module")
def events_in_files(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("events"))
    ev = spark.read.parquet(f"{TINY}/events.parquet").orderBy("ts").coalesce(1).withColumn("ts", F.col("ts").cast("timestamp"))
    for k in range(3):
        ev.where(F.dayofmonth("ts").between(1 + 11 * k, 11 + 11 * k)).coalesce(1).write.mode("append").parquet(folder)
    return folder


def test_stream_of_windows_equals_batch(spark, tmp_path, events_in_files):
    schema = spark.read.parquet(events_in_files).schema
    edges = windowed_edges(event_stream(spark, events_in_files, schema, 10), "10 minutes")
    store = TriadStore(spark, str(tmp_path / "store"))
    store.start(edges, str(tmp_path / "ck")).awaitTermination()
    stored = store.edges()
    last = stored.agg(F.max("e")).first()[0]
    raw = spark.read.parquet(events_in_files)
    inc = incidence(raw, F.floor(F.unix_seconds("ts") / 600) * 600, "user_id").where(F.col("e") <= last)
    want = canonicalize(inc)
    assert sorted(r["members"] for r in stored.collect()) == sorted(r["members"] for r in want.edges.collect())
    assert some(store.counts()) == some(triads(want, mode="count"))


def test_sessions_and_sliding_windows(spark, tmp_path, events_in_files):
    schema = spark.read.parquet(events_in_files).schema
    for k, df in enumerate((session_edges(event_stream(spark, events_in_files, schema, 10)), windowed_edges(event_stream(spark, events_in_files, schema, 10), "1 hour", "30 minutes"))):
        q = df.writeStream.format("memory").queryName(f"sealed{k}").outputMode("append").option("checkpointLocation", str(tmp_path / f"c{k}")).trigger(availableNow=True).start()
        q.awaitTermination()
        assert spark.table(f"sealed{k}").count() > 0
