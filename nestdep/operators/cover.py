"""Document covers of violating pairs: how many documents must go to repair a dependency.

The greedy cover takes both ends of an edge unless one is taken already.  In a
fixed order of edges that is the same as rounds in which every edge that is
least at both of its ends is taken; rounds are joins, so they scale.  A hashed
order needs few rounds; the lexicographic one ("lex") needs half as many as a
clique has documents, and "affine", an arithmetic order of integer ids that SQL
can repeat, stands between.  The matching found bounds the optimum: matching <= optimum <= 2 * matching.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.tables import forget_frame, written


#: Factors of both ids, the seed that `greedy_matching` has by default, and the number of places.
AFFINE = 7919, 104729, 7, 1009


def _order(order: str, seed: int) -> Column:
    if order == "lex":
        return F.struct(F.lit(0).cast("long").alias("h"), "d1", "d2")
    if order == "affine":
        return F.struct(F.pmod(F.col("d1") * 7919 + F.col("d2") * 104729 + seed, F.lit(1009)).alias("h"), "d1", "d2")
    return F.struct(F.xxhash64(F.lit(seed), "d1", "d2").alias("h"), "d1", "d2")


def greedy_matching(edges: DataFrame, order: str = "lex", by: tuple[str, ...] = (), seed: int = 7) -> DataFrame:
    """Edges (by..., d1, d2) taken by the greedy scan in the given order, for each group of `by`."""
    keys = list(by)
    now = written(edges.select(*keys, F.least("d1", "d2").alias("d1"), F.greatest("d1", "d2").alias("d2")).where("d1 <> d2").distinct(), "edges")
    taken = None
    while now.take(1):
        ranked = now.withColumn("o", _order(order, seed))
        ends = ranked.select(*keys, F.explode(F.array("d1", "d2")).alias("d"), "o").groupBy(*keys, "d").agg(F.min("o").alias("m"))
        one = ends.select(*keys, F.col("d").alias("d1"), F.col("m").alias("m1"))
        two = ends.select(*keys, F.col("d").alias("d2"), F.col("m").alias("m2"))
        best = ranked.join(one, [*keys, "d1"]).join(two, [*keys, "d2"]).where("o = m1 and o = m2").select(*keys, "d1", "d2")
        best = written(best, "matched")
        gone = best.select(*keys, F.explode(F.array("d1", "d2")).alias("d"))
        last = now
        for end in ("d1", "d2"):
            now = now.join(gone.withColumnRenamed("d", end), [*keys, end], "left_anti")
        now = written(now.select(*keys, "d1", "d2"), "edges")
        forget_frame(last)
        taken = best if taken is None else taken.unionAll(best)
    return taken if taken is not None else now


def greedy_cover(edges: DataFrame, order: str = "lex", by: tuple[str, ...] = (), seed: int = 7) -> DataFrame:
    """Documents (by..., doc_id) of the greedy cover."""
    return greedy_matching(edges, order, by, seed).select(*by, F.explode(F.array("d1", "d2")).alias("doc_id"))


def cover_strength(edges: DataFrame, n_docs: int, order: str = "hashed", theta: float = 1.0) -> DataFrame:
    """One row: matching, cover, strength 1 - cover / n with its bounds, and validity."""
    return strength_row(greedy_matching(edges, order).agg(F.count(F.lit(1)).alias("matching")), n_docs, theta)


def strength_row(matching: DataFrame, n_docs: int, theta: float) -> DataFrame:
    return matching.select(
        "matching",
        (2 * F.col("matching")).alias("cover"),
        F.round(1 - 2 * F.col("matching") / F.lit(n_docs), 6).alias("strength"),
        F.round(1 - 2 * F.col("matching") / F.lit(n_docs), 6).alias("strength_lo"),
        F.round(1 - F.col("matching") / F.lit(n_docs), 6).alias("strength_hi"),
        (F.lit(n_docs) - 2 * F.col("matching") >= F.lit(theta * n_docs)).alias("valid"),
    )


def sequential_cover(edges: Iterable[tuple]) -> list:
    """The scan itself, for small inputs and tests."""
    out: list = []
    for a, b in edges:
        if a not in out and b not in out:
            out += [a, b]
    return out


def exact_cover(edges: Iterable[tuple], limit: int = 20) -> set:
    """A smallest cover by branching on a vertex of greatest degree; refuses over `limit` vertices."""
    edges = {tuple(sorted(e)) for e in edges if e[0] != e[1]}
    if len({v for e in edges for v in e}) > limit:
        raise ValueError(f"exact cover is for at most {limit} documents")

    def best(rest: set, room: int) -> set | None:
        if not rest:
            return set()
        if room <= 0:
            return None
        degree: dict = {}
        for a, b in rest:
            degree[a] = degree.get(a, 0) + 1
            degree[b] = degree.get(b, 0) + 1
        v = max(degree, key=lambda x: (degree[x], str(x)))
        with_v = best({e for e in rest if v not in e}, room - 1)
        near = {b if a == v else a for a, b in rest if v in (a, b)}
        without = best({e for e in rest if not near & set(e)}, min(room, len(with_v) if with_v is not None else room) - len(near))
        options = [s for s in ((with_v | {v}) if with_v is not None else None, (without | near) if without is not None else None) if s is not None]
        return min(options, key=len) if options else None

    return best(edges, limit) or set()
