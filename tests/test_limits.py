"""Queries that took too long, too much disk or no table."""

from helpers import TINY
from pyspark.sql import functions as F
from test_whole import brute

from hypertriad.operators import baseline
from hypertriad.plans.registry import QUERIES, graph
from hypertriad.sources import builders
from hypertriad.sources.builders import BUILDERS


def test_table_function_reads_events(spark, tmp_path):
    rows = [(k, "purchase", u, f"2024-01-0{day} {h:02}:10:00") for k, (day, h, u) in enumerate([(1, 1, 1), (1, 1, 2), (1, 5, 2), (1, 5, 3), (1, 9, 1), (1, 9, 3), (2, 1, 1), (2, 2, 1), (2, 2, 2), (2, 3, 2), (2, 3, 3)])]
    df = spark.createDataFrame(rows, "event_id long, event_type string, user_id long, ts string").withColumn("ts", F.col("ts").cast("timestamp"))
    df.write.parquet(f"{tmp_path}/events.parquet")
    assert [r.asDict() for r in QUERIES["table_function_triads"](spark, str(tmp_path)).collect()] == [{"day": "2024-01-01", "i": 1, "j": 5, "k": 9, "pattern": 17}]


def test_baseline_compares_sets_once_a_pair(spark):
    df = baseline.baseline_triads(graph(spark, TINY, "order_suppliers"))
    text = df._jdf.queryExecution().optimizedPlan().toString()
    assert text.count("array_intersect") == 1  # of the overlaps of two pairs; members were compared when the lists were made
    found, _ = brute(BUILDERS["order_suppliers"](spark, TINY).collect())
    assert sorted(tuple(r) for r in df.select("pattern", "i", "j", "k").collect()) == sorted((p, *t) for p, x in found.items() for t in x)


def test_interval_edges_stage_no_memberships(spark, tmp_path, monkeypatch):
    rows = [(1, "view", 5, "10:00:00"), (2, "purchase", 6, "10:20:00"), (3, "purchase", None, "10:25:00"), (4, "purchase", 7, "10:30:00"), (5, "purchase", 7, "10:30:01"), (6, "view", 8, None), (7, "purchase", None, "12:00:00")]
    make = lambda rows, at: spark.createDataFrame([(k, kind, u, t and f"2024-01-01 {t}") for k, kind, u, t in rows], "event_id long, event_type string, user_id long, ts string").withColumn("ts", F.col("ts").cast("timestamp")).write.parquet(f"{at}/events.parquet")
    make(rows, tmp_path / "a")
    got = lambda at: sorted(tuple(r) for r in builders.interval_edges(spark, str(at)).collect())
    staged = []
    monkeypatch.setattr(builders, "stage", lambda df: staged.append(df.columns) or df)
    assert got(tmp_path / "a") == [(2, 2, [5, 6]), (4, 3, [5, 6, 7]), (5, 2, [6, 7])] and staged == [["e"]]
    make([*rows, (2, "purchase", 9, "13:00:00")], tmp_path / "b")  # one id of two purchases: one edge
    assert got(tmp_path / "b") == [(2, 3, [5, 6, 9]), (3, 2, [5, 6]), (4, 3, [5, 6, 7]), (5, 2, [6, 7])]
