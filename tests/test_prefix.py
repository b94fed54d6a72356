"""Prefixes in time order without one task for all documents."""

from pyspark.sql import functions as F

from nestdep.sources.collections import prefix_by_time, prefixes_by_time


def test_prefixes_equal_sorted_ones_and_limit_nothing(spark):
    df = spark.range(100).selectExpr("id", "nullif(id * 37 % 10, 3) as at")
    for n in (1, 25, 50, 99, 100):
        got = prefix_by_time(df, "at", n, "id")
        assert {r["id"] for r in got.collect()} == {r["id"] for r in df.orderBy("at", "id").limit(n).collect()}
        # Documents are filtered; a limit stands over the times of one range at most.
        plan = got._jdf.queryExecution().optimizedPlan().toString()
        assert "LeftSemi" in plan if n < 100 else "Limit" not in plan
        assert got.agg(F.count(F.lit(1))).first()[0] == n


def test_prefixes_of_all_sizes_come_from_one_set_of_ranges(spark, monkeypatch):
    from nestdep.sources import collections

    made, real = [], collections.written
    monkeypatch.setattr(collections, "written", lambda df, what: made.append(what) or real(df, what))
    df = spark.range(60).selectExpr("id", "timestamp_seconds(id * 37 % 11) as at")
    want = [r["id"] for r in sorted(df.collect(), key=lambda r: (r["at"], r["id"]))]
    sizes = [1, 17, 59, 60]
    for n, got in zip(sizes, prefixes_by_time(df, "at", sizes, "id")):
        assert sorted(r["id"] for r in got.collect()) == sorted(want[:n])
    assert made == ["times"]
