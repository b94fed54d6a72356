"""Experiment workloads: run time, scale and complexity.

Collections are stored before anything is timed, so that seconds are those of
the miners.  What does not depend on the machine (documents, cells, flat rows,
dependencies found) comes from queries of its own, which SQL can repeat.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import functional, inclusion, overlap, results
from .plans.cells import expansion, expansion_factor, unroll_dynamic, unroll_static
from .sources.collections import prefixes_by_time, shaped, stored_collection
from .sources.tables import load

_PATHS = {
    "order_docs": (["$.orderkey", "$.custkey", "$.status", "$.items[*].partkey", "$.items[*].suppkey", "$.items[*].returnflag"], "orderkey"),
    "customer_docs": (["$.custkey", "$.segment", "$.nation.name", "$.orders[*].orderkey", "$.orders[*].custkey", "$.orders[*].items[*].partkey", "$.orders[*].items[*].suppkey"], "custkey"),
    "product_docs": (["$.partkey", "$.brand", "$.related.ordered_with[*]", "$.related.returned_with[*]", "$.suppliers[*]"], "partkey"),
}
#: Orders with independent arrays, whose flat rows are some twenty times the documents.
SCALE_PATHS = ["$.orderkey", "$.custkey", "$.status", "$.items[*].partkey", "$.items[*].suppkey", "$.items[*].returnflag", "$.flags[*]", "$.flag_or_status[*]"]
DAY_PATHS = ["$.user_id", "$.day", "$.events[*].event_type", "$.events[*].k", "$.events[*].value"]
SHARES = (0.1, 0.25, 0.5, 1.0)
SIZES = (25, 50, 100, 200, 500, 2000, 10**9)
#: Arrays of a document, their width and their depth.
GRID = ((1, 4, 1), (2, 4, 1), (3, 4, 1), (4, 4, 1), (2, 2, 1), (2, 8, 1), (2, 16, 1), (2, 4, 2), (2, 4, 3))
STATIC_ROWS = 2e6
SCALE_ROWS = 2e7
LIMIT_S = 300.0
_UNROLLINGS = ("dynamic", "static")


def _tops(paths: list[str]) -> list[str]:
    return list(dict.fromkeys(p.split(".")[1].split("[")[0] for p in paths))


def inclusion_runtime(spark: SparkSession, sf_dir: str, theta: float = 0.99, repeat: int = 3, cap: int = 10) -> DataFrame:
    """Three whole collections by two miners by two unrollings, and product documents with arrays of at most cap as a row of its own."""
    rows = []
    runs = [(name, name, None) for name in _PATHS] + [(f"product_docs cap {cap}", "product_docs", cap)]
    for label, name, most in runs:
        paths, key = _PATHS[name]
        docs = stored_collection(name, spark, sf_dir, cap=most).select(*_tops(paths))
        n, factor = docs.count(), expansion_factor(docs).first()["expansion"]
        for method in ("sorted", "inverted"):
            if not rows:  # one untimed run, so that the first measured one does not pay for compilation
                results.time_run(lambda m=method: inclusion.mine_inclusion(docs, key, m, theta, "dynamic", paths), 1)
            seconds = {}
            for unrolling in _UNROLLINGS:
                run = lambda m=method, u=unrolling: inclusion.mine_inclusion(docs, key, m, theta, u, paths, row_limit=STATIC_ROWS)
                got = results.settled(results.time_run(run, repeat, LIMIT_S))
                seconds[unrolling] = got["seconds"]
                rows.append((label, n, float(factor), method, unrolling, got["status"], got["seconds"], results.improvement(seconds)))
    return spark.createDataFrame(rows, "collection string, documents long, expansion double, method string, unrolling string, status string, seconds double, improvement double")


def inclusion_volumes(spark: SparkSession, sf_dir: str, theta: float = 0.99) -> DataFrame:
    """Of the whole collections of the run-time experiment: documents, cells, flat rows, valid dependencies."""
    out = None
    for name, (paths, key) in _PATHS.items():
        docs = stored_collection(name, spark, sf_dir).select(*_tops(paths))
        size = expansion_factor(docs).select(F.lit(name).alias("collection"), "documents", "unrolled_rows")
        cells = unroll_dynamic(docs, key, paths).agg(F.count(F.lit(1)).alias("cells"))
        found = inclusion.mine_inclusion(docs, key, theta=theta, paths=paths).agg(F.count_if("valid").alias("dependencies"))
        row = size.join(cells).join(found)
        out = row if out is None else out.unionByName(row)
    return out


def _prefixes(docs: DataFrame, column: str, key: str, sizes: list[int]) -> list[tuple[int, DataFrame]]:
    total = docs.count()
    chosen = sorted({min(s, total) for s in sizes})
    return list(zip(chosen, prefixes_by_time(docs, column, chosen, key)))


def inclusion_scale(spark: SparkSession, sf_dir: str, shares: tuple[float, ...] = SHARES, repeat: int = 3) -> DataFrame:
    """Growing prefixes of the orders in time order, up to all of them: both miners over both unrollings."""
    docs = stored_collection("order_docs", spark, sf_dir)
    total, rows = docs.count(), []
    for n, part in _prefixes(docs, "orderdate", "orderkey", [max(1, round(total * s)) for s in shares]):
        part = part.select(*_tops(SCALE_PATHS)).cache()
        factor = expansion_factor(part).first()["expansion"]
        for method in ("sorted", "inverted"):
            seconds = {}
            for unrolling in _UNROLLINGS:
                run = lambda m=method, u=unrolling, p=part: inclusion.mine_inclusion(p, "orderkey", m, 0.99, u, SCALE_PATHS, row_limit=SCALE_ROWS)
                if not rows:
                    results.time_run(run, 1)
                got = results.settled(results.time_run(run, repeat, LIMIT_S))
                seconds[unrolling] = got["seconds"]
                rows.append((n, float(factor), method, unrolling, got["status"], got["seconds"], results.improvement(seconds)))
        part.unpersist()
    return spark.createDataFrame(rows, "documents long, expansion double, method string, unrolling string, status string, seconds double, improvement double")


def inclusion_scale_volumes(spark: SparkSession, sf_dir: str, shares: tuple[float, ...] = SHARES) -> DataFrame:
    """Of each prefix: documents, flat rows, cells, valid dependencies at 0.99."""
    docs = stored_collection("order_docs", spark, sf_dir)
    total, out = docs.count(), None
    for n, part in _prefixes(docs, "orderdate", "orderkey", [max(1, round(total * s)) for s in shares]):
        part = part.select(*_tops(SCALE_PATHS))
        size = part.agg(F.sum(expansion(part)).cast("long").alias("unrolled_rows"))
        cells = unroll_dynamic(part, "orderkey", SCALE_PATHS).agg(F.count(F.lit(1)).alias("cells"))
        found = inclusion.mine_inclusion(part, "orderkey", theta=0.99, paths=SCALE_PATHS).agg(F.count_if("valid").alias("dependencies"))
        row = size.join(cells).join(found).select(F.lit(n).cast("long").alias("documents"), "unrolled_rows", "cells", "dependencies")
        out = row if out is None else out.unionByName(row)
    return out


def functional_scale(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = SIZES, repeat: int = 3) -> DataFrame:
    """Growing prefixes of users' days: both miners over both unrollings, and the linear validator, up to all of them."""
    docs, rows = stored_collection("user_day_docs", spark, sf_dir), []
    for n, part in _prefixes(docs, "day", "doc_key", list(sizes)):
        part = part.cache()
        flat = part.select("user_id", "day", "events")
        tests = {f"{m}, {u}": (m, u) for m in ("levelwise", "negative_cover") for u in _UNROLLINGS}
        for name, (method, unrolling) in tests.items():
            if unrolling == "dynamic":
                run = lambda m=method, p=part: functional.mine_functional(p, "doc_key", m, paths=DAY_PATHS)
            else:
                run = lambda m=method, p=flat: functional.mine_functional(p, "doc_key", m, unrolling="static", row_limit=STATIC_ROWS)
            got = results.settled(results.time_run(run, repeat, LIMIT_S))
            rows.append((n, name, got["status"], got["seconds"]))
        got = results.settled(results.time_run(lambda p=part: functional.validate_nfd(p, "doc_key", ["$.events[*].k"], "$.user_id"), repeat, LIMIT_S))
        rows.append((n, "linear validation", got["status"], got["seconds"]))
        part.unpersist()
    return spark.createDataFrame(rows, "documents long, method string, status string, seconds double")


def functional_volumes(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = SIZES[:5]) -> DataFrame:
    """Of each prefix of users' days: documents and pairs by overlap mask."""
    docs, out = stored_collection("user_day_docs", spark, sf_dir), None
    for n, part in _prefixes(docs, "day", "doc_key", list(sizes)):
        masks = overlap.overlap_masks(unroll_dynamic(part, "doc_key", DAY_PATHS)).groupBy("mask").agg(F.count(F.lit(1)).alias("pairs"))
        row = masks.select(F.lit(n).cast("long").alias("documents"), "mask", "pairs")
        out = row if out is None else out.unionByName(row)
    return out


def _ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers give the documents of all shapes their ids, from which the values follow."""
    return load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("doc_id"))


def complexity_sweep(spark: SparkSession, sf_dir: str, repeat: int = 3) -> DataFrame:
    """More arrays, wider arrays, deeper arrays: rows of both unrollings and seconds."""
    rows = []
    for arrays, width, depth in GRID:
        docs = shaped(_ids(spark, sf_dir), arrays, width, depth)
        factor = expansion_factor(docs.drop("doc_id")).first()["expansion"]
        seconds = {}
        for unrolling in _UNROLLINGS:
            run = lambda u=unrolling, d=docs: inclusion.mine_inclusion(d, "doc_id", theta=0.99, unrolling=u, row_limit=STATIC_ROWS)
            seconds[unrolling] = results.settled(results.time_run(run, repeat, LIMIT_S))["seconds"]
        rows.append((arrays, width, depth, float(factor), seconds["dynamic"], seconds["static"], results.improvement(seconds)))
    return spark.createDataFrame(rows, "arrays int, width int, depth int, expansion double, dynamic_s double, static_s double, improvement double")


def complexity_volumes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of each shape: rows of static unrolling and cells of dynamic unrolling, both counted."""
    out = None
    for arrays, width, depth in GRID:
        docs = shaped(_ids(spark, sf_dir), arrays, width, depth)
        rows = unroll_static(docs).agg(F.count(F.lit(1)).alias("unrolled_rows"))
        cells = unroll_dynamic(docs, "doc_id").agg(F.count(F.lit(1)).alias("cells"))
        row = rows.join(cells).select(F.lit(arrays).alias("arrays"), F.lit(width).alias("width"), F.lit(depth).alias("depth"), "unrolled_rows", "cells")
        out = row if out is None else out.unionByName(row)
    return out
