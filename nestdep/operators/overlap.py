"""Which paths two documents overlap on.

Two documents overlap on a path if they share a value there.  overlap_masks
gives every pair of documents that share any value a bit mask of paths; the
histogram of masks is all that exact mining of functional dependencies needs.
Pairs can be quadratic, so their number is computed from value frequencies
before any pair is made, and refused beyond a limit; overlap_histogram then
counts them without making any.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.cells import TooLarge, register_metadata
from ..sources.tables import written
from .overlap_counts import COUNTED_PATHS, mask_counts, pairs_on

PAIR_LIMIT = 50_000_000
HOT, SALTS = 1_000, 16
MAX_PATHS = 62


def _frequencies(cells: DataFrame) -> DataFrame:
    return cells.groupBy("path_id", "value").agg(F.count(F.lit(1)).alias("f"))


def _made(frequencies: DataFrame) -> int:
    return int(frequencies.agg(F.coalesce(F.sum(F.expr("f * (f - 1) div 2")), F.lit(0))).first()[0])


def pair_estimate(cells: DataFrame) -> int:
    """Joined rows that overlap_masks would make: the sum over values of f * (f - 1) / 2."""
    return _made(_frequencies(cells.select("doc_id", "path_id", "value").distinct()))


def _met(cells: DataFrame, limit: int) -> DataFrame:
    """(path_id, d1, d2), d1 < d2: documents that share a value, once for each value.

    The distinct cells are written once.  Where the pairs are within the limit,
    fewer than 2 * limit / HOT ** 2 values stand in more than HOT documents; that
    list is broadcast, and the documents of such a value are spread over SALTS
    tasks on one side and copied to all of them on the other.
    """
    one = written(cells.select("doc_id", "path_id", "value").distinct(), "distinct-cells")
    frequencies = _frequencies(one)
    if (made := _made(frequencies)) > limit:
        raise TooLarge(f"{made} pairs of documents share a value; the limit is {limit}: sample, choose paths, or validate linearly")
    hot = F.broadcast(frequencies.where(F.col("f") > HOT).select("path_id", "value", F.lit(True).alias("hot")))
    one = one.join(hot, ["path_id", "value"], "left") if limit <= 10 * PAIR_LIMIT else one.withColumn("hot", F.lit(None).cast("boolean"))
    salt = F.when(F.col("hot"), F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)).cast("int")).otherwise(0)
    left = one.select(F.col("doc_id").alias("d1"), "path_id", "value", salt.alias("salt"))
    copies = F.when(F.col("hot"), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))
    right = one.select(F.col("doc_id").alias("d2"), "path_id", "value", F.explode(copies).alias("salt"))
    return left.join(right, ["path_id", "value", "salt"]).where("d1 < d2").select("path_id", "d1", "d2")


@register_metadata("overlaps")
def _overlap_metadata(cells: DataFrame, n_paths: int) -> DataFrame:
    return overlap_masks(cells)


def overlap_masks(cells: DataFrame, limit: int = PAIR_LIMIT) -> DataFrame:
    """(d1, d2, mask), d1 < d2, of all pairs that share a value somewhere."""
    return _met(cells, limit).groupBy("d1", "d2").agg(F.bit_or(F.expr("shiftleft(1L, path_id)")).alias("mask"))


def presence_masks(cells: DataFrame) -> DataFrame:
    """(doc_id, mask) of the paths where a document has values: it overlaps itself there."""
    return cells.groupBy("doc_id").agg(F.bit_or(F.expr("shiftleft(1L, path_id)")).alias("mask"))


def histogram(masks: DataFrame, n_docs: int) -> dict[int, int]:
    """mask -> number of pairs; pairs that share nothing follow by subtraction."""
    return _with_none({r["mask"]: r["n"] for r in masks.groupBy("mask").agg(F.count(F.lit(1)).alias("n")).toLocalIterator()}, n_docs)


def _with_none(found: dict[int, int], n_docs: int) -> dict[int, int]:
    none = n_docs * (n_docs - 1) // 2 - sum(found.values())
    return found | ({0: none} if none else {})


def overlap_histogram(cells: DataFrame, n_paths: int, n_docs: int, limit: int | None = None) -> dict[int, int]:
    """The histogram of overlap_masks; without a limit of the caller's, pairs beyond PAIR_LIMIT are counted and not made."""
    try:
        return histogram(overlap_masks(cells, PAIR_LIMIT if limit is None else limit), n_docs)
    except TooLarge:
        if limit is not None or n_paths > COUNTED_PATHS:
            raise
    return _with_none(mask_counts(cells, n_paths), n_docs)


def mask_has(mask: Column, paths: list[int]) -> Column:
    wanted = sum(1 << p for p in paths)
    return mask.bitwiseAND(F.lit(wanted)) == F.lit(wanted)


@register_metadata("bitmaps")
def _bitmap_metadata(cells: DataFrame, n_paths: int) -> DataFrame:
    return adjacency_bitmaps(cells)


def adjacency_bitmaps(cells: DataFrame, limit: int = PAIR_LIMIT) -> DataFrame:
    """(path_id, d1, bucket, bitmap): for each document the compressed set of documents that overlap it on a path."""
    half = _met(cells.withColumn("doc_id", F.col("doc_id").cast("long")), limit).distinct()
    both = half.unionAll(half.select("path_id", F.col("d2").alias("d1"), F.col("d1").alias("d2")))
    bucket = F.bitmap_bucket_number("d2").alias("bucket")
    return both.groupBy("path_id", "d1", bucket).agg(F.bitmap_construct_agg(F.bitmap_bit_position("d2")).alias("bitmap"))


def overlap_holds(cells: DataFrame, lhs: list[int], rhs: int) -> DataFrame:
    """The row of bitmap_holds: by bitmaps where the pairs are within PAIR_LIMIT, else by their counted number."""
    try:
        return bitmap_holds(adjacency_bitmaps(cells, PAIR_LIMIT), lhs, rhs)
    except TooLarge:
        x, both = (sum(1 << p for p in set(paths)) for paths in (lhs, [*lhs, rhs]))
    found = pairs_on(cells, max(*lhs, rhs) + 1, [x, both])
    row = (2 * found[x], 2 * found[both], found[x] == found[both])
    return cells.sparkSession.createDataFrame([row], "lhs_pairs long, both_pairs long, holds boolean")


def bitmap_holds(bitmaps: DataFrame, lhs: list[int], rhs: int) -> DataFrame:
    """One row: do all pairs that overlap on lhs overlap on rhs?  (pairs on lhs, pairs on lhs and rhs)

    Ordered pairs are counted; a path without a bitmap for (d1, bucket) is an empty set there.
    """

    def common(paths: list[int]) -> DataFrame:
        part = bitmaps.where(F.col("path_id").isin(paths)).groupBy("d1", "bucket")
        both = part.agg(F.bitmap_and_agg("bitmap").alias("b"), F.count(F.lit(1)).alias("n")).where(F.col("n") == len(set(paths)))
        return both.agg(F.coalesce(F.sum(F.bitmap_count("b")), F.lit(0)).alias("pairs"))

    out = common(lhs).withColumnRenamed("pairs", "lhs_pairs").join(common([*lhs, rhs]).withColumnRenamed("pairs", "both_pairs"))
    return out.withColumn("holds", F.col("lhs_pairs") == F.col("both_pairs"))
