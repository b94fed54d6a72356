"""Greedy covers of more violating pairs than can be made, in the affine order.

Pairs are made in slices of the order.  What a slice takes is gone before the
next one is made, and as the order deals pairs evenly, a slice of many pairs
leaves few documents that still violate with each other.  Documents are joined by
the sets on the left side that meet, and within a slice by the remainder that the
order asks of the second document, so that no other pairs are looked at.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import forget_frame, written
from . import lattice
from .cover import AFFINE, greedy_matching
from .overlap_counts import combinations_of

SALTS, NARROW = 16, 64
#: Pairs of a slice: what is left after it shrinks with its square, while each round of the greedy cover exchanges what it has.
SLICE = 2_000_000


def _members(docs: DataFrame, n_paths: int, candidates: list[tuple[int, int]]) -> tuple[DataFrame, DataFrame]:
    """(cand, c, doc_id, y): documents by candidate, with the class of their left sets and their right set; (c, c2): the classes that meet."""
    q = [f"q{i}" for i in range(n_paths)]
    lhs = F.explode(F.array(*[F.lit(x).cast("long") for x in sorted({x for x, _ in candidates})]))
    rows = docs.withColumn("x", lhs)
    for i, name in enumerate(q):
        rows = rows.withColumn(name, F.when(F.col("x").bitwiseAND(F.lit(1 << i)) != 0, F.col(f"p{i}")).otherwise(F.array(F.lit(-1).cast("long"))))
    rows = rows.where(reduce(lambda a, b: a & b, [F.size(n) > 0 for n in q]))
    classes = written(rows.select("x", *q).distinct().withColumn("c", F.monotonically_increasing_id()), "classes")
    atoms = combinations_of(classes, q).select("x", *[f"v{i}" for i in range(n_paths)], "c")
    meets = written(atoms.join(atoms.withColumnRenamed("c", "c2"), ["x", *[f"v{i}" for i in range(n_paths)]]).select("c", "c2").distinct(), "meets")
    rights = F.array(*[F.struct(F.lit(i).alias("cand"), F.lit(x).cast("long").alias("of"), F.col(f"p{a}").alias("y")) for i, (x, a) in enumerate(candidates)])
    each = rows.withColumn("r", F.explode(rights)).where("r.of = x")
    return written(each.join(classes, ["x", *q]).select("r.cand", "c", "doc_id", "r.y"), "members"), meets


def _slice(live: DataFrame, meets: DataFrame, lo: int, hi: int) -> DataFrame:
    """(cand, d1, d2) of the violating pairs whose place in the order lies in [lo, hi)."""
    by_one, by_two, seed, size = AFFINE
    one = live.join(meets, "c").select("cand", F.col("c2").alias("c"), F.col("doc_id").alias("d1"), F.col("y").alias("y1"))
    two = live.select("cand", "c", F.col("doc_id").alias("d2"), F.col("y").alias("y2"))
    part, place = F.pmod(F.col("d1") * by_one + seed, F.lit(size)), F.pmod(F.col("d2") * by_two, F.lit(size))
    if hi - lo <= NARROW:
        one = one.withColumn("h", F.explode(F.sequence(F.lit(lo), F.lit(hi - 1)))).withColumn("k", F.pmod(F.col("h") - part, F.lit(size)).cast("long"))
        two = two.withColumn("k", place.cast("long"))
    else:
        one = one.withColumn("k", F.pmod(F.xxhash64("d1"), F.lit(SALTS)))
        two = two.withColumn("k", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    both = one.join(two, ["cand", "c", "k"]).where("d1 < d2 and not arrays_overlap(y1, y2)")
    return both.where(F.pmod(part + place, F.lit(size)).between(lo, hi - 1)).select("cand", "d1", "d2").distinct()


def dense_matchings(docs: DataFrame, n_paths: int, candidates: list[tuple[int, int]], limit: int, bad: int) -> dict[tuple[int, int], int]:
    """Edges that the greedy scan takes of the violating pairs of each candidate; docs as of document_sets, with integer ids.

    A slice is chosen to have some `limit` pairs at most; `bad` is their whole number.
    """
    live, meets = _members(docs, n_paths, candidates)
    size, lo, out = AFFINE[-1], 0, dict.fromkeys(candidates, 0)
    while lo < size:
        held = live.groupBy("cand", "c").agg(F.count(F.lit(1)).alias("n"))
        left = held.join(meets, "c").join(held.select("cand", F.col("c").alias("c2"), F.col("n").alias("n2")), ["cand", "c2"])
        pairs = int(left.agg(F.coalesce(F.sum(F.when(F.col("c") == F.col("c2"), F.expr("n * (n - 1)")).otherwise(F.expr("n * n2"))), F.lit(0))).first()[0]) // 2
        if not pairs:
            break
        most = max(1, min(bad * (size - lo) // size, pairs))
        hi = min(size, lo + max(1, (size - lo) * limit // most))
        taken = written(greedy_matching(_slice(live, meets, lo, hi), "affine", by=("cand",)), "taken")
        for r in taken.groupBy("cand").agg(F.count(F.lit(1)).alias("n")).collect():
            out[candidates[r["cand"]]] += r["n"]
        last, lo = live, hi
        live = written(live.join(taken.select("cand", F.explode(F.array("d1", "d2")).alias("doc_id")), ["cand", "doc_id"], "left_anti").select(*live.columns), "members")
        forget_frame(last)
    return out
