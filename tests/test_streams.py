"""Appended rows of a stream are files that executors write, not a table of the driver."""

import pytest

from doccurate.plans import catalogue
from doccurate.streaming import ingest

EVENTS = [
    (1, "2024-01-01 00:00:00", 7, "view"), (2, "2024-01-01 00:29:59", 7, "view"), (3, "2024-01-01 00:59:59", 7, "view"),  # a gap of 30 minutes parts sessions
    (4, "2024-01-01 00:10:00", 8, "view"), (5, "2024-01-01 00:10:00", 8, "view"), (6, "2024-01-31 23:59:00", 9, "signup"), (7, "2024-01-31 23:59:30", 9, "signup"),
    (8, "2024-01-31 23:59:59", None, "view"), (9, "2024-01-01 00:00:01", 70, "view"),
]


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    out = str(tmp_path_factory.mktemp("events"))
    rows = spark.createDataFrame(EVENTS, "event_id long, ts string, user_id long, event_type string")
    rows.selectExpr("event_id", "cast(ts as timestamp_ntz) as ts", "user_id", "event_type", "1.0D as value", "'' as props").repartition(3).write.parquet(f"{out}/events.parquet/")
    spark.createDataFrame([(7, 1), (8, 2), (9, 3)], "c_custkey long, c_nationkey int").write.parquet(f"{out}/customer.parquet")
    return out


def found(spark, folder, name):
    before = {t.name for t in spark.catalog.listTables()}
    rows = catalogue.QUERIES[name](spark, f"{folder}")
    assert {t.name for t in spark.catalog.listTables()} == before  # no memory table
    return sorted(map(tuple, rows.collect()), key=repr)


def test_dedup(spark, folder):
    hour = 1704067200
    assert found(spark, folder, "op_stream_dedup") == sorted([(7, "view", hour), (8, "view", hour), (9, "signup", hour + 743 * 3600), (None, "view", hour + 743 * 3600), (70, "view", hour)], key=repr)


def test_join_static(spark, folder):
    assert found(spark, folder, "op_stream_join_static") == [(1, 1), (2, 1), (3, 1), (4, 2), (5, 2), (6, 3), (7, 3)]


def test_join_static_broadcasts_no_table(spark, folder, monkeypatch):
    """Users are dealt out however small Spark takes them to be."""
    plans, drained = [], ingest.drained
    monkeypatch.setattr(ingest, "drained", lambda spark, stream: plans.append(stream._jdf.queryExecution().analyzed().toString()) or drained(spark, stream))
    assert len(found(spark, folder, "op_stream_join_static")) == 7
    assert "strategy=merge" in plans[0]


def test_session(spark, folder):
    hour = 1704067200
    assert found(spark, folder, "op_stream_session") == sorted([(hour, 7, 2), (hour + 3599, 7, 1), (hour + 600, 8, 2), (hour + 743 * 3600 + 3540, 9, 2), (hour + 743 * 3600 + 3599, None, 1), (hour + 1, 70, 1)], key=repr)
