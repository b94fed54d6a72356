"""Oracles straight from the definitions; they compare everything with everything and are guarded."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.cells import TooLarge, resolve, unroll_dynamic
from ..sources.tables import written
from . import lattice
from .functional import _frame
from .inclusion import dependency
from .overlap_counts import shared_profiles

ROW_LIMIT = 5_000


def bruteforce_ninds(df: DataFrame, doc_id: str, theta: float = 1.0, paths: list[str] | None = None, limit: int | None = None) -> DataFrame:
    """Each ordered pair of paths, each value of the left one looked up at the right one: values times paths, so refused only on demand."""
    names = [str(p) for p in resolve(df, doc_id, paths)]
    values = unroll_dynamic(df, doc_id, names).select("path_id", "value").distinct()
    if limit is not None and (n := values.count()) > limit:
        raise TooLarge(f"{n} values; the limit is {limit}")
    there = values.select(F.col("path_id").alias("r"), "value", F.lit(1).alias("hit"))
    right = values.select(F.col("path_id").alias("r")).distinct()
    pairs = values.select(F.col("path_id").alias("l"), "value").crossJoin(F.broadcast(right)).where("l <> r")
    counts = pairs.join(there, ["r", "value"], "left").groupBy("l", "r").agg(F.count(F.lit(1)).alias("support"), F.count("hit").alias("included"))
    name = F.array(*map(F.lit, names))
    return dependency(counts.withColumns({"lhs": F.get(name, F.col("l")), "rhs": F.get(name, F.col("r"))}), "nind", "lhs", "rhs", theta)


def bruteforce_nfds(df: DataFrame, doc_id: str, paths: list[str] | None = None, max_lhs: int = 3, limit: int = ROW_LIMIT) -> DataFrame:
    """All pairs of documents, all left sides.

    Values of one document overlap with nothing; documents with the same values otherwise are compared once.
    """
    names = [str(p) for p in resolve(df, doc_id, paths)]
    rows = written(shared_profiles(unroll_dynamic(df, doc_id, names), len(names)).withColumn("id", F.monotonically_increasing_id()), "profiles")
    if (n := rows.count()) > limit:
        raise TooLarge(f"{n} different documents to compare pairwise; the limit is {limit}")
    one, two = rows.alias("a"), rows.alias("b")
    bits = [F.when(F.arrays_overlap(f"a.p{i}", f"b.p{i}"), F.lit(1 << i)).otherwise(F.lit(0)).cast("long") for i in range(len(names))]
    met = F.when(F.col("a.id") < F.col("b.id"), F.col("a.w") * F.col("b.w")).otherwise(F.expr("a.w * (a.w - 1) div 2"))
    pairs = one.crossJoin(two).where("a.id <= b.id").select(reduce(lambda x, y: x.bitwiseOR(y), bits).alias("mask"), met.alias("n")).where("n > 0")
    hist = {r["mask"]: r["n"] for r in pairs.where("mask <> 0").groupBy("mask").agg(F.sum("n").alias("n")).toLocalIterator()}
    docs = df.count()
    if none := docs * (docs - 1) // 2 - sum(hist.values()):
        hist[0] = none
    return _frame(df, [(x, a, 1.0, True) for x, a in lattice.brute_force(hist, len(names), max_lhs)], names)
