import os

import pytest
from pyspark.sql import functions as F

from nestdep.operators import results
from nestdep.plans import cells as plans
from nestdep.sources import tables
from nestdep.sources.collections import COLLECTIONS, build_collection, inject, synthesize
from nestdep.streaming import stream


def test_all_collections(spark, sf_dir):
    for name, (_, key) in COLLECTIONS.items():
        df = build_collection(name, spark, sf_dir)
        assert key in df.columns and df.count() == df.select(key).distinct().count() > 0


def test_json_documents(spark, tmp_path):
    (tmp_path / "d.json").write_text('{"id": 1, "a": [1, 2]}\n{"id": 2, "a": "x"}\nnot json\n')
    from pyspark.sql.types import StructType

    schema = StructType.fromDDL("id long, a array<int>")
    rows = tables.read_documents(spark, str(tmp_path / "d.json"), schema).collect()
    assert len(rows) == 3 and [r["id"] for r in rows if r["_corrupt"] is None] == [1]
    parsed = tables.parse_documents(spark.createDataFrame([(1, '{"k": 3}'), (2, '{"j": "x"}')], "id long, doc string"), "doc")
    assert parsed.select("doc.k").collect()[0][0] == 3


def test_variants_walk_any_shape(spark):
    df = spark.createDataFrame([(1, '{"a": [1, {"b": "x"}], "c": true}'), (2, "broken {")], "doc_id long, j string")
    rows = {(r[1], r[2]) for r in plans.unroll_variant(df, "j").collect()}
    assert rows == {("$.a[*]", "n1"), ("$.a[*].b", "sx"), ("$.c", "btrue")}


def test_cell_store_and_dependency_sink(spark, sf_dir, tmp_path):
    df = build_collection("conversation_docs", spark, sf_dir)
    cells = plans.unroll_dynamic(df, "conv_id")
    tables.write_cells(cells, str(tmp_path / "cells"))
    back = tables.read_cells(spark, str(tmp_path / "cells"))
    assert back.count() == cells.count()


def test_dirt(spark):
    df = spark.range(1000).withColumn("s", F.lit("x"))
    assert inject(df, "id", "s", "null", 50).where("s is null").count() == 50
    assert inject(df, "id", "s", "foreign", 10).where("s <> 'x'").count() == 10


def test_synthetic_expansion_grows(spark):
    one, two = (plans.expansion_factor(synthesize(spark, 10, k, 3).drop("doc_id")).first()["expansion"] for k in (1, 2))
    assert (one, two) == (3.0, 9.0)


def test_windows_of_a_stream(spark, sf_dir, tmp_path):
    path = f"{sf_dir}/events.parquet"
    source = stream.stream_documents(spark, path, spark.read.parquet(path).schema)
    out = stream.profile_stream(source.withColumn("ts", F.col("ts").cast("timestamp")), "ts", "event_type", "7 days")
    query = out.writeStream.outputMode("complete").format("memory").queryName("profile").start()
    query.processAllAvailable()
    query.stop()
    assert spark.sql("select sum(n) from profile").first()[0] == spark.read.parquet(path).count()


def test_state_is_idempotent(spark):
    state = stream.MetadataState(spark, ["$.a", "$.b"])
    batch = spark.createDataFrame([(0, "n1"), (1, "n1"), (1, "n2")], "path_id int, value string")
    state.merge(batch, 0)
    state.merge(batch, 0)
    assert {(r["lhs"], r["valid"]) for r in state.dependencies().collect()} == {("$.a", True), ("$.b", False)}
    state.merge(spark.createDataFrame([(0, "n3")], "path_id int, value string"), 1)
    assert not any(r["valid"] for r in state.dependencies().collect())


def test_profile_and_timing(spark, sf_dir):
    df = build_collection("conversation_docs", spark, sf_dir)
    row = results.collection_profile(df, "c").first()
    assert row["documents"] == df.count() and row["max_nesting"] >= 3 and row["mean_bytes"] > 0
    assert results.time_run(lambda: df, 1)["status"] == "ok"
    assert results.time_run(lambda: df.select(F.raise_error(F.lit("x"))), 1)["seconds"] is None


def test_state_outlives_the_application(spark, tmp_path):
    """A second state on the same folder goes on; compaction changes nothing; any number of paths."""
    names = [f"$.p{i}" for i in range(130)]
    root = f"file://{tmp_path}/state"
    batches = [spark.createDataFrame([(p, f"n{(v * 7 + b) % 50}") for v in range(20) for p in ((v + b) % 130, 65 + b % 60, 129)], "path_id int, value string") for b in range(9)]
    first = stream.MetadataState(spark, names, root, compact_every=4)
    for i in range(5):
        first.merge(batches[i], i)
    second = stream.MetadataState(spark, names, root, compact_every=4)
    for i in range(3, 9):  # batches 3 and 4 come again
        second.merge(batches[i], i)
    assert len(second.parts()) <= 4
    from functools import reduce

    from nestdep.operators import inclusion

    cells = reduce(lambda a, b: a.unionAll(b), batches)
    want = inclusion.value_masks(cells, len(names))
    key = lambda df: sorted(map(tuple, df.select("value", "m0", "m1", "m2").collect()))
    assert key(second.masks()) == key(want)
    assert second.dependencies().where("valid and lhs = '$.p70' and rhs = '$.p129'").count() == 1


def test_uncommitted_batch_is_not_read(spark, tmp_path):
    state = stream.MetadataState(spark, ["$.a"], f"file://{tmp_path}/state")
    assert state.masks().count() == 0
    state.merge(spark.createDataFrame([(0, "n1")], "path_id int, value string"), 0)
    (tmp_path / "state" / "masks-000000001-000000001").mkdir()
    assert [p[0] for p in state.parts()] == [0] and state.masks().count() == 1


def test_stream_goes_on_after_a_restart(spark, tmp_path):
    source, root, checkpoint = tmp_path / "in", f"file://{tmp_path}/state", f"file://{tmp_path}/checkpoint"
    rows = lambda lo, hi: spark.range(lo, hi).selectExpr("id", "id % 5 as a", "id % 7 as b")
    rows(0, 10).coalesce(1).write.parquet(f"file://{source}")
    to_cells = lambda df: plans.unroll_dynamic(df, "id", ["$.a", "$.b"])
    schema = rows(0, 1).schema
    run = lambda: stream.mine_stream(spark, str(source), schema, to_cells, ["$.a", "$.b"], root=root, checkpoint=checkpoint)
    assert run().masks().count() == 7
    rows(100, 101).selectExpr("id", "cast(99 as bigint) as a", "b").coalesce(1).write.mode("append").parquet(f"file://{source}")
    again = run()
    assert again.masks().count() == 8 and len(again.parts()) == 2


def test_late_rows_are_counted(spark, tmp_path):
    source = tmp_path / "in"
    source.mkdir()
    for k, day in enumerate(("2024-01-01", "2024-03-01", "2024-03-02", "2024-01-02")):  # a batch drops by the watermark of the one before
        part = spark.sql(f"select timestamp'{day} 00:00:00' ts, 'k' key, {k} value")
        (source / f"{k}.json").write_text(f'{{"ts": "{day} 00:00:00", "key": "k", "value": {k}}}\n')
        os.utime(source / f"{k}.json", (1_700_000_000 + 60 * k,) * 2)  # files are read in the order of their times
    out = stream.profile_stream(stream.stream_documents(spark, str(source), part.schema, "json"), "ts", "key")
    query = out.writeStream.outputMode("append").format("memory").queryName("late").start()
    query.processAllAvailable()
    dropped = stream.late_rows(query)
    query.stop()
    assert dropped == 1


def test_timed_runs_end_at_their_limit(spark):
    slow = lambda: spark.range(0, 4, 1, 2).select(F.expr("reflect('java.lang.Thread', 'sleep', cast(60000 as bigint))"))
    import time

    began = time.time()
    got = results.time_run(slow, 1, limit_s=1.0)
    assert got == {"status": "time-out", "seconds": None} and time.time() - began < 30

    def refused():
        raise plans.TooLarge("x")

    assert results.time_run(refused, 1) == {"status": "refused", "seconds": None}
    import pytest

    with pytest.raises(Exception):
        results.settled(results.time_run(lambda: spark.range(1).select(F.raise_error(F.lit("x"))), 1))
    assert results.settled(results.time_run(lambda: spark.range(1), 1, 60.0))["status"] == "ok"


def test_capped_products_are_cut_from_the_stored_whole_ones(spark, sf_dir, monkeypatch):
    from nestdep.sources import collections

    whole = collections.stored_collection("product_docs", spark, sf_dir)
    want = collections.build_collection("product_docs", spark, sf_dir, cap=2)
    rows = lambda df: sorted(map(str, df.drop("size_rank").collect()))
    monkeypatch.setattr(collections, "build_collection", lambda *a: pytest.fail("the joins run again"))
    got = collections.stored_collection("product_docs", spark, sf_dir, cap=2)
    assert rows(got) == rows(want) != rows(whole)
    assert all(set(r["related"]["returned_with"]) <= set(r["related"]["ordered_with"]) for r in got.collect())
