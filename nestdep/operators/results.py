"""Result frames: ranking, top lists, comparison of miners, profiles and measures."""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Callable
from functools import reduce

from pyspark import SparkContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.paths import leaf_paths, nesting_level, path_values
from ..plans.cells import TooLarge, expansion
from ..sources.tables import drain


def rank_dependencies(deps: DataFrame) -> DataFrame:
    """Strongest first; ties by name. Results of a miner are small, so one window orders them."""
    return deps.withColumn("rank", F.dense_rank().over(Window.partitionBy("kind").orderBy(F.desc("strength"))))


def top_dependencies(deps: DataFrame, k: int) -> DataFrame:
    return deps.orderBy(F.desc("strength"), F.desc("support") if "support" in deps.columns else F.lit(0), "lhs", "rhs").limit(k)


def compare_results(one: DataFrame, two: DataFrame, on: tuple[str, ...] = ("lhs", "rhs")) -> DataFrame:
    """(only_one, only_two, both): do two miners agree?"""
    a, b = one.select(*on).distinct(), two.select(*on).distinct()
    left = a.exceptAll(b).agg(F.count(F.lit(1)).alias("only_one"))
    right = b.exceptAll(a).agg(F.count(F.lit(1)).alias("only_two"))
    return left.join(right).join(a.intersect(b).agg(F.count(F.lit(1)).alias("both")))


def top_values_per_path(cells: DataFrame, k: int) -> DataFrame:
    counts = cells.groupBy("path_id", "value").agg(F.count(F.lit(1)).alias("n"))
    rank = F.row_number().over(Window.partitionBy("path_id").orderBy(F.desc("n"), "value"))
    return counts.withColumn("rank", rank).where(F.col("rank") <= k)


def values_per_document(df: DataFrame) -> Column:
    """Number of atomic values of a document, without exploding it."""
    return reduce(lambda a, b: a + b, [F.size(path_values(df, p)) for p in leaf_paths(df.schema)])


def max_nesting(df: DataFrame) -> int:
    return max(map(nesting_level, leaf_paths(df.schema)))


def collection_profile(df: DataFrame, name: str) -> DataFrame:
    """One row of the collection table: documents, mean JSON bytes, nesting, values, expansion."""
    rows = df.select(F.octet_length(F.to_json(F.struct("*"))).alias("bytes"), values_per_document(df).alias("values"), expansion(df).alias("rows"))
    out = rows.agg(F.count(F.lit(1)).alias("documents"), F.avg("bytes").alias("b"), F.avg("values").alias("v"), F.sum("rows").alias("r"))
    return out.select(
        F.lit(name).alias("collection"), "documents", F.round("b", 1).alias("mean_bytes"), F.lit(max_nesting(df)).alias("max_nesting"),
        F.lit(len(leaf_paths(df.schema))).alias("leaf_paths"), F.round("v", 6).alias("mean_values"), F.round(F.col("r") / F.col("documents"), 6).alias("expansion"),
    )


def blowup(df: DataFrame) -> DataFrame:
    """(nested_bytes, unrolled_bytes, factor): size of static rows from closed forms and the mean bytes of leaves."""
    size = F.octet_length(F.to_json(F.struct("*")))
    rows = df.select(size.alias("bytes"), expansion(df).alias("rows"), values_per_document(df).alias("values"))
    width = len(leaf_paths(df.schema))
    out = rows.agg(F.sum("bytes").alias("nested_bytes"), F.sum(F.col("rows") * F.col("bytes") / F.greatest(F.col("values"), F.lit(1)) * width).alias("u"))
    return out.select("nested_bytes", F.round("u", 0).cast("long").alias("unrolled_bytes"), F.round(F.col("u") / F.col("nested_bytes"), 3).alias("factor"))


def strength_distribution(deps: DataFrame) -> DataFrame:
    """Where each dependency stands among all: quarter, percent rank, cumulative share."""
    order = Window.partitionBy("kind").orderBy("strength")
    return deps.withColumns({"quarter": F.ntile(4).over(Window.partitionBy("kind").orderBy("strength", "lhs", "rhs")), "percent_rank": F.round(F.percent_rank().over(order), 6), "cume_dist": F.round(F.cume_dist().over(order), 6)})


def plan_volume(df: DataFrame) -> dict[str, int]:
    """Run a plan and add up what its operators counted: exchanges, rows and bytes shuffled, rows generated and joined."""
    execution = df._jdf.queryExecution()
    execution.toRdd().count()
    total = {"exchanges": 0, "first_exchange_rows": 0, "shuffle_rows": 0, "shuffle_bytes": 0, "generated_rows": 0, "joined_rows": 0}

    def value(node, name: str) -> int:
        metrics = node.metrics()
        return int(metrics.apply(name).value()) if metrics.contains(name) else 0

    def walk(node) -> None:
        kind = node.nodeName()
        if kind == "AdaptiveSparkPlan":
            return walk(node.executedPlan())
        if kind.endswith("QueryStage"):
            return walk(node.plan())
        below = node.children()
        for i in range(below.size()):
            walk(below.apply(i))
        if kind == "Exchange":
            rows = value(node, "shuffleRecordsWritten")
            total["exchanges"] += 1
            total["first_exchange_rows"] = total["first_exchange_rows"] or rows
            total["shuffle_rows"] += rows
            total["shuffle_bytes"] += value(node, "shuffleBytesWritten")
        elif kind == "Generate":
            total["generated_rows"] += value(node, "numOutputRows")
        elif "Join" in kind:
            total["joined_rows"] += value(node, "numOutputRows")

    walk(execution.executedPlan())
    return total


def time_run(make: Callable[[], DataFrame], repeat: int = 3, limit_s: float | None = None) -> dict:
    """Mean seconds of runs into a null sink, and a status: ok, refused (TooLarge) or time-out.

    A run that passes the limit is ended: its jobs are cancelled by their tag.
    Any other failure is no result of an experiment: its status tells the error,
    and `settled`, which all workloads ask, raises it.
    """
    context = SparkContext.getOrCreate()
    took = []
    for _ in range(repeat):
        tag, late = f"timed-{uuid.uuid4().hex}", threading.Event()

        def stop(tag: str = tag, late: threading.Event = late) -> None:
            late.set()
            while not done.wait(0.2):  # a miner may start its next job after one was cancelled
                context.cancelJobsWithTag(tag)

        done = threading.Event()
        clock = threading.Timer(limit_s, stop) if limit_s is not None else None
        context.addJobTag(tag)
        began = time.time()
        try:
            if clock:
                clock.start()
            drain(make())
        except TooLarge:
            return {"status": "refused", "seconds": None}
        except Exception as e:
            if not late.is_set():
                return {"status": f"error: {type(e).__name__}", "seconds": None, "error": e}
        finally:
            done.set()
            if clock:
                clock.cancel()
            context.removeJobTag(tag)
        if late.is_set():
            return {"status": "time-out", "seconds": None}
        took.append(time.time() - began)
    return {"status": "ok", "seconds": sum(took) / len(took)}


def settled(run: dict) -> dict:
    """The run, unless a miner failed."""
    if run.get("error") is not None:
        raise run["error"]
    return run


def improvement(seconds: dict[str, float | None]) -> float | None:
    """Static over dynamic seconds."""
    static, dynamic = seconds.get("static"), seconds.get("dynamic")
    return static / dynamic if static and dynamic else None
