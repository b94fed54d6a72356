"""Functional dependencies between sets of paths: checks, miners, measures.

X -> Y holds if any two documents whose value sets overlap on every path of X
overlap on every path of Y.  Pairs range over distinct documents unless
self_pairs; a missing right side is a violation unless missing_rhs="ignores"
(only in checks: that reading is not transitive, so miners refuse it).
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.paths import as_path, named, path_type, path_values
from ..functions.values import keys_of
from ..plans.cells import TooLarge, resolve, unroll_dynamic, unroll_static
from ..sources.tables import written
from . import lattice
from .cover import cover_strength, greedy_matching, strength_row
from .dense_cover import SLICE, dense_matchings
from .overlap import MAX_PATHS, PAIR_LIMIT, histogram, overlap_histogram, overlap_masks, presence_masks
from .overlap_counts import COUNTED_PATHS, document_sets, largest_meeting, pairs_meeting, pairs_on

DEPS = "kind string, lhs string, rhs string, strength double, valid boolean"


def _sets(df: DataFrame, doc_id: str, paths: dict[str, str]) -> DataFrame:
    """doc_id and the set of value keys at each named path."""
    return df.select(
        named(doc_id).alias("doc_id"), *[F.array_distinct(keys_of(path_values(df, p), path_type(df.schema, p))).alias(n) for n, p in paths.items()]
    )


def _tuple_rows(df: DataFrame, doc_id: str, lhs: list[str], rhs: list[str]) -> tuple[DataFrame, list[str], list[str]]:
    """One row per document and tuple of left values; each left path is exploded on its own."""
    left = {f"x{i}": p for i, p in enumerate(lhs)}
    right = {f"y{i}": p for i, p in enumerate(rhs)}
    rows = _sets(df, doc_id, left | right)
    for name in left:
        rows = rows.withColumn(name, F.explode(name))
    return rows, list(left), list(right)


def nfd_violations(df: DataFrame, doc_id: str, lhs: list[str], rhs: list[str], self_pairs: bool = False, missing_rhs: str = "violates", limit: int = PAIR_LIMIT) -> DataFrame:
    """Distinct violating pairs (d1, d2), d1 < d2 (d1 = d2 too with self_pairs)."""
    rows, xs, ys = _tuple_rows(df, doc_id, lhs, rhs)
    made = rows.groupBy(*xs).agg(F.count(F.lit(1)).alias("f")).agg(F.sum(F.expr("f * (f - 1) div 2"))).first()[0] or 0
    if made > limit:
        raise TooLarge(f"{made} pairs share a left side; the limit is {limit}: use validate_nfd")
    one = rows.select(*xs, F.col("doc_id").alias("d1"), *[F.col(y).alias(f"{y}_1") for y in ys])
    two = rows.select(*xs, F.col("doc_id").alias("d2"), *[F.col(y).alias(f"{y}_2") for y in ys])
    apart: list[Column] = []
    for y in ys:
        bad = ~F.arrays_overlap(f"{y}_1", f"{y}_2")
        if missing_rhs == "ignores":
            bad = bad & (F.size(f"{y}_1") > 0) & (F.size(f"{y}_2") > 0)
        apart.append(bad)
    order = F.col("d1") <= F.col("d2") if self_pairs else F.col("d1") < F.col("d2")
    if xs:
        both = one.join(two, xs).where(order)
    else:  # an empty left side compares all documents
        both = one.crossJoin(two).where(order)
    return both.where(reduce(lambda a, b: a | b, apart)).select("d1", "d2").distinct()


def count_violations(df: DataFrame, doc_id: str, lhs: list[str], rhs: list[str], limit: int = PAIR_LIMIT) -> DataFrame:
    """One row: the number of pairs that nfd_violations gives; beyond the limit they are counted and not made."""
    try:
        return nfd_violations(df, doc_id, lhs, rhs, limit=limit).agg(F.count(F.lit(1)).alias("pairs"))
    except TooLarge:
        names = list(dict.fromkeys([*lhs, *rhs]))
    x, both = (sum(1 << names.index(p) for p in set(side)) for side in (lhs, names))
    found = pairs_on(unroll_dynamic(df, doc_id, names), len(names), [x, both])
    return df.sparkSession.createDataFrame([(found[x] - found[both],)], "pairs long")


def validate_nfd(df: DataFrame, doc_id: str, lhs: list[str], rhs: str, self_pairs: bool = False, limit: int = PAIR_LIMIT) -> DataFrame:
    """One row (groups, failing_groups, holds) without pairs of documents wherever semantics allow.

    Documents overlap on all of X iff they share a tuple of values, so each group
    of a tuple is tested: it passes if some right value is held by all of its
    documents; if none is, it fails if a document has no value or one only.  What
    is left compares distinct right sets, one of which lacks the group's most
    frequent value in any disjoint pair; these pairs are counted first.
    """
    rows, xs, _ = _tuple_rows(df, doc_id, lhs, [rhs])
    group = F.struct(*xs) if xs else F.lit(0)
    rows = rows.select(group.alias("g"), "doc_id", F.array_sort("y0").alias("y")).distinct()
    size = rows.groupBy("g").agg(F.count(F.lit(1)).alias("docs"), F.min("y").alias("lo"), F.max("y").alias("hi"), F.min(F.size("y")).alias("least"))
    open_groups = size.where((F.col("docs") > 1) | F.lit(self_pairs))
    if not as_path(rhs).repeated:
        bad = open_groups.where((F.col("lo") != F.col("hi")) | (F.col("least") == 0)).select("g")
    else:
        rows = written(rows, "groups")
        held = rows.select("g", F.explode("y").alias("v")).groupBy("g", "v").agg(F.count(F.lit(1)).alias("n")).groupBy("g").agg(F.max(F.struct("n", "v")).alias("most"))
        unsure = written(open_groups.join(held, "g", "left").where(F.coalesce("most.n", F.lit(0)) < F.col("docs")).select("g", "least", "most.v"), "unsure")
        bad = unsure.where("least <= 1").select("g")
        sets = rows.join(unsure.where("least > 1").select("g", "v"), "g").groupBy("g", "y").agg(F.any_value("v").alias("v"))
        sets = written(sets.select("g", "y", (~F.array_contains("y", F.col("v"))).alias("lacks")), "sets")
        made = sets.groupBy("g").agg(F.count(F.lit(1)).alias("n"), F.count_if("lacks").alias("m")).agg(F.coalesce(F.sum(F.col("n") * F.col("m")), F.lit(0))).first()[0]
        if made > limit:
            raise TooLarge(f"{made} pairs of right sides to compare; the limit is {limit}: choose another left side")
        clash = sets.where("lacks").alias("a").join(sets.alias("b"), "g").where("not arrays_overlap(a.y, b.y)").select("g").distinct()
        bad = bad.unionAll(clash)
    return size.agg(F.count(F.lit(1)).alias("groups")).join(bad.agg(F.count(F.lit(1)).alias("failing_groups"))).withColumn("holds", F.col("failing_groups") == 0)


def _name(mask: int, names: list[str]) -> str:
    return ",".join(names[i] for i in lattice.bits(mask))


def _frame(df: DataFrame, found: list[tuple], names: list[str], kind: str = "nfd") -> DataFrame:
    rows = [(kind, _name(lhs, names), names[rhs], strength, valid) for lhs, rhs, strength, valid in found]
    return df.sparkSession.createDataFrame(sorted(rows), DEPS)


def mask_histogram(df: DataFrame, doc_id: str, paths: list[str] | None = None, self_pairs: bool = False, limit: int | None = None) -> tuple[dict[int, int], list[str]]:
    names = [str(p) for p in resolve(df, doc_id, paths)]
    if len(names) > MAX_PATHS:
        raise TooLarge(f"{len(names)} paths: choose at most {MAX_PATHS}")
    cells = unroll_dynamic(df, doc_id, names)
    hist = overlap_histogram(cells, len(names), df.count(), limit)
    if self_pairs:
        own = {r["mask"]: r["n"] for r in presence_masks(cells).groupBy("mask").agg(F.count(F.lit(1)).alias("n")).toLocalIterator()}
        bare = df.count() - sum(own.values())
        for m, n in (own | ({0: bare + own.get(0, 0)} if bare else {})).items():
            hist[m] = hist.get(m, 0) + n
    return hist, names


def mine_functional(
    df: DataFrame,
    doc_id: str,
    method: str = "levelwise",
    theta: float = 1.0,
    max_lhs: int = 3,
    paths: list[str] | None = None,
    unrolling: str = "dynamic",
    self_pairs: bool = False,
    missing_rhs: str = "violates",
    pooling: str = "pooled",
    order: str = "hashed",
    limit: int | None = None,
    row_limit: float = 1e6,
) -> DataFrame:
    """Minimal dependencies with one path on the right and at most max_lhs on the left.

    With a limit, more pairs of documents are refused; without, pairs are counted where they are too many to make. At theta below 1 only
    those are made then that violate a dependency which counts and degrees leave open, and these are limited.
    """
    if missing_rhs != "violates":
        raise ValueError("missing_rhs='ignores' is not transitive; miners need 'violates'")
    if unrolling == "static":
        return mine_static(df, method, max_lhs, paths, row_limit)
    if theta < 1.0:
        return _mine_approximate(df, doc_id, method, theta, max_lhs, paths, pooling, order, limit)
    hist, names = mask_histogram(df, doc_id, paths, self_pairs, limit)
    found = search(hist, len(names), method, max_lhs)
    return _frame(df, [(x, a, 1.0, True) for x, a in found], names)


def search(hist: dict[int, int], n_paths: int, method: str, max_lhs: int) -> set[tuple[int, int]]:
    if method == "levelwise":
        return lattice.levelwise(hist, n_paths, max_lhs)
    if method == "negative_cover":
        return lattice.invert(lattice.negative_cover(hist, n_paths), n_paths, max_lhs)
    if method == "bruteforce":
        return lattice.brute_force(hist, n_paths, max_lhs)
    raise ValueError(f"unknown method {method!r}")


def _undecided(candidates: list[tuple[int, int]], n_docs: int, hist: dict[int, int], theta: float) -> tuple[dict[tuple[int, int], float], dict[tuple[int, int], list[int]]]:
    """Strengths of the candidates that the histogram decides, and the violating masks of the others."""
    out: dict[tuple[int, int], float] = {}
    tests: dict[tuple[int, int], list[int]] = {}
    for x, a in candidates:
        broken = [m for m in hist if m and m & x == x and not m >> a & 1]
        bad = sum(hist[m] for m in broken)
        most = 1 - bad / max(1, n_docs - 1) / n_docs
        if not bad or most < theta:
            out[x, a] = most
        else:
            tests[x, a] = broken
    return out, tests


def candidate_strengths(masks: DataFrame, candidates: list[tuple[int, int]], n_docs: int, order: str = "hashed", hist: dict[int, int] | None = None, theta: float = 0.0) -> dict[tuple[int, int], float]:
    """Strength 1 - cover / n of each (lhs mask, rhs), all candidates in one set of rounds.

    The histogram decides some at once: no violating pair means 1, and as a
    document is in n - 1 pairs at most, too many of them mean less than theta;
    for those an upper bound is returned.  Edges are made for the others only.
    """
    if hist is None:
        hist = {r["mask"]: r["n"] for r in masks.groupBy("mask").agg(F.count(F.lit(1)).alias("n")).toLocalIterator()}
    out, tests = _undecided(candidates, n_docs, hist, theta)
    return out | _cover_strengths(masks, tests, n_docs, order)


def _cover_strengths(masks: DataFrame, tests: dict[tuple[int, int], list[int]], n_docs: int, order: str) -> dict[tuple[int, int], float]:
    """Strengths by covers of the pairs of each candidate's violating masks."""
    if not tests:
        return {}
    wanted: dict[int, list[int]] = {}
    for i, broken in enumerate(tests.values()):
        for m in broken:
            wanted.setdefault(m, []).append(i)
    table = masks.sparkSession.createDataFrame(sorted(wanted.items()), "mask long, cands array<int>")
    edges = masks.join(F.broadcast(table), "mask").select("d1", "d2", F.explode("cands").alias("cand"))
    taken = greedy_matching(edges, order, by=("cand",)).groupBy("cand").agg(F.count(F.lit(1)).alias("m"))
    size = {r["cand"]: 2 * r["m"] for r in taken.toLocalIterator()}
    return {c: 1 - size.get(i, 0) / n_docs for i, c in enumerate(tests)}


class _MadePairs:
    """Strengths and heavy masks from the masks of all pairs."""

    def __init__(self, masks: DataFrame, n_docs: int, order: str):
        self.masks, self.n_docs, self.order = masks, n_docs, order
        self.hist = histogram(masks, n_docs)

    def strengths(self, candidates: list[tuple[int, int]], hist: dict[int, int], theta: float = 0.0) -> dict[tuple[int, int], float]:
        return candidate_strengths(self.masks, candidates, self.n_docs, self.order, hist, theta)

    def heavy(self, theta: float) -> set[int]:
        return _heavy_masks(self.masks, [m for m in self.hist if m], self.n_docs, theta, self.order)

    def overlapping(self, path: int | None) -> DataFrame:
        return self.masks if path is None else self.masks.where(F.col("mask").bitwiseAND(F.lit(1 << path)) != 0)


class _CountedPairs:
    """The same where all pairs are too many to make.

    Of e edges of which no document is in more than d, every cover has e / d
    documents at least.  With the number of pairs by mask and d from the values'
    frequencies, that settles what is far from theta; the edges of the rest are made
    by joins on the left side.
    """

    def __init__(self, cells: DataFrame, n_paths: int, n_docs: int, order: str, limit: int):
        self.n_paths, self.n_docs, self.order, self.limit = n_paths, n_docs, order, limit
        self.hist = overlap_histogram(cells, n_paths, n_docs)
        self.docs = written(document_sets(cells, n_paths), "sets")
        self._degree: dict[int, int] = {}

    def _least(self, pairs: int, x: int) -> float:
        """The least size of a cover of so many pairs that overlap on x."""
        if x not in self._degree:
            self._degree[x] = min(self.n_docs - 1, largest_meeting(self.docs, list(lattice.bits(x))))
        return pairs / max(1, self._degree[x])

    def strengths(self, candidates: list[tuple[int, int]], hist: dict[int, int], theta: float = 0.0) -> dict[tuple[int, int], float]:
        out, tests = _undecided(candidates, self.n_docs, hist, theta)
        for (x, a), broken in list(tests.items()):
            if theta and (most := 1 - self._least(sum(hist[m] for m in broken), x) / self.n_docs) < theta:
                out[x, a] = most
                del tests[x, a]
        for x in sorted({x for x, _ in tests}):
            made = pairs_meeting(self.docs, self.n_paths, list(lattice.bits(x)), self.limit)
            out |= _cover_strengths(made, {c: broken for c, broken in tests.items() if c[0] == x}, self.n_docs, self.order)
        return out

    def heavy(self, theta: float) -> set[int]:
        kept, most = set(), (1 - theta) * self.n_docs
        for m, pairs in self.hist.items():
            if not m or 2 * pairs <= most:  # a matching has no more edges than there are
                continue
            if self._least(pairs, m) > most:
                kept.add(m)
                continue
            made = pairs_meeting(self.docs, self.n_paths, list(lattice.bits(m)), self.limit).where(F.col("mask") == m)
            kept |= _heavy_masks(made, [m], self.n_docs, theta, self.order)
        return kept

    def overlapping(self, path: int | None) -> DataFrame:
        raise TooLarge(f"{sum(n for m, n in self.hist.items() if m)} pairs of documents share a value; the limit is {self.limit}: choose paths")


def strengths(cells: DataFrame, n_paths: int, candidates: list[tuple[int, int]], n_docs: int, limit: int | None = None) -> dict[tuple[int, int], float]:
    """candidate_strengths in the affine order; without a limit of the caller's, more pairs than PAIR_LIMIT are made in slices of the order."""
    most = PAIR_LIMIT if limit is None else limit
    try:
        return candidate_strengths(overlap_masks(cells, most), candidates, n_docs, "affine")
    except TooLarge:
        if limit is not None or n_paths > COUNTED_PATHS:
            raise
    hist = overlap_histogram(cells, n_paths, n_docs)
    out, tests = _undecided(candidates, n_docs, hist, 0.0)
    docs = written(document_sets(cells, n_paths), "sets")
    bad = {c: sum(hist[m] for m in broken) for c, broken in tests.items()}
    few, many, total = [], [], 0
    for c in sorted(bad, key=bad.get):
        total += bad[c]
        (few if total <= min(most, SLICE) else many).append(c)
    for part in (few, many):
        if part:
            taken = dense_matchings(docs, n_paths, part, min(most, SLICE), sum(bad[c] for c in part))
            out |= {c: 1 - 2 * m / n_docs for c, m in taken.items()}
    return out


def _mine_approximate(df: DataFrame, doc_id: str, method: str, theta: float, max_lhs: int, paths: list[str] | None, pooling: str, order: str, limit: int | None) -> DataFrame:
    """Pooled strengths are searched level by level whatever the method: negative_cover has its own search per mask only."""
    names = [str(p) for p in resolve(df, doc_id, paths)]
    n_docs, n = df.count(), len(names)
    cells = unroll_dynamic(df, doc_id, names)
    most = PAIR_LIMIT if limit is None else limit
    try:
        pairs = _MadePairs(written(overlap_masks(cells, most), "masks"), n_docs, order)
    except TooLarge:
        if limit is not None or n > COUNTED_PATHS:
            raise
        pairs = _CountedPairs(cells, n, n_docs, order, most)
    hist = pairs.hist
    ids = df.select(named(doc_id).alias("doc_id"))
    empty, alone = _empty_strengths(ids, cells, pairs, n_docs, n, theta, order, most)
    if method == "negative_cover" and pooling == "per_mask":
        # Each negative dependency counts alone: it stays only if its own pairs need too many documents.
        kept = pairs.heavy(theta)
        full, hist = hist, {m: c for m, c in hist.items() if m in kept or not m and alone < theta}
        found = lattice.invert(lattice.negative_cover(hist, n), n, max_lhs)
        strength = pairs.strengths(sorted(c for c in found if c[0]), full)
        return _frame(df, [(x, a, round(strength[x, a] if x else empty[a], 6), True) for x, a in found], names)
    found: dict[tuple[int, int], float] = {(0, a): s for a, s in empty.items() if s >= theta}
    for size in range(1, max_lhs + 1):
        level = []
        for x in _subsets(n, size):
            for a in range(n):
                if not x >> a & 1 and not any(f & x == f and r == a for f, r in found):
                    level.append((x, a))
        strengths = pairs.strengths(level, hist, theta)
        found |= {c: s for c, s in strengths.items() if s >= theta}
    return _frame(df, [(x, a, round(s, 6), True) for (x, a), s in found.items()], names)


def _empty_strengths(ids: DataFrame, cells: DataFrame, made: _MadePairs | _CountedPairs, n_docs: int, n_paths: int, theta: float, order: str, limit: int) -> tuple[dict[int, float], float]:
    """Strength of {} -> A for each path A, and that of the pairs that share nothing anywhere.

    The pairs that violate {} -> A are those that do not overlap on A.  Without
    the documents that lack A's most frequent value none is left, and no cover is
    smaller where documents have one value at most.  Elsewhere pairs are made
    only if neither this cover nor their number decides, and are counted first.
    """
    one = cells.select("doc_id", "path_id", "value").distinct()
    most = {r["path_id"]: r["f"] for r in one.groupBy("path_id", "value").agg(F.count(F.lit(1)).alias("f")).groupBy("path_id").agg(F.max("f").alias("f")).toLocalIterator()}
    width = {r["path_id"]: r["w"] for r in one.groupBy("doc_id", "path_id").agg(F.count(F.lit(1)).alias("w")).groupBy("path_id").agg(F.max("w").alias("w")).toLocalIterator()}

    def strength(bad: int, shared: int, atomic: bool, path: int | None) -> float:
        if not bad:
            return 1.0
        simple = 1 - (n_docs - max(1, shared)) / n_docs
        if atomic or simple >= theta or 1 - bad / (n_docs - 1) / n_docs < theta:  # a document is in n - 1 pairs at most
            return simple
        if bad > limit:
            raise TooLarge(f"{bad} pairs of documents do not overlap; the limit is {limit}: choose paths")
        pairs = ids.select(F.col("doc_id").alias("d1")).join(ids.select(F.col("doc_id").alias("d2"))).where("d1 < d2")
        m = greedy_matching(pairs.join(made.overlapping(path).select("d1", "d2"), ["d1", "d2"], "left_anti"), order).count()
        return max(simple, 1 - 2 * m / n_docs)

    total = n_docs * (n_docs - 1) // 2
    empty = {}
    for a in range(n_paths):
        bad = total - sum(c for m, c in made.hist.items() if m >> a & 1)
        empty[a] = strength(bad, most.get(a, 0), width.get(a, 0) <= 1, a)
    return empty, strength(made.hist.get(0, 0), max(most.values(), default=0), False, None)


def _subsets(n: int, size: int) -> list[int]:
    return [sum(1 << p for p in c) for c in combinations(range(n), size)]


def _heavy_masks(masks: DataFrame, values: list[int], n_docs: int, theta: float, order: str) -> set[int]:
    taken = greedy_matching(masks.select(F.col("mask").alias("cand"), "d1", "d2"), order, by=("cand",)).groupBy("cand").agg(F.count(F.lit(1)).alias("m"))
    return {r["cand"] for r in taken.toLocalIterator() if 2 * r["m"] > (1 - theta) * n_docs} & set(values)


def _single_groups(df: DataFrame, doc_id: str, lhs: list[str], rhs: list[str]) -> DataFrame:
    """(g, y, n, size): documents by left and right values where all paths are single-valued; a missing right value is in no y but its own."""
    rows, xs, ys = _tuple_rows(df, doc_id, lhs, rhs)
    given = reduce(lambda a, b: a & b, [F.size(y) > 0 for y in ys])
    alone = F.when(~given, F.col("doc_id"))
    kinds = rows.groupBy(*xs, *ys, alone.alias("alone")).agg(F.count(F.lit(1)).alias("n"))
    return kinds.withColumn("size", F.sum("n").over(Window.partitionBy(*xs) if xs else Window.partitionBy(F.lit(0))))


def nfd_strength(df: DataFrame, doc_id: str, lhs: list[str], rhs: list[str], order: str = "hashed", theta: float = 1.0, limit: int = PAIR_LIMIT) -> DataFrame:
    """By the greedy cover of the violating pairs.

    Where these are too many to make and paths are single-valued, two documents of a
    group violate unless their right values are equal: of n documents, m with the most
    frequent value, min(n div 2, n - m) disjoint pairs are taken, in an order that has them first.
    """
    try:
        return cover_strength(nfd_violations(df, doc_id, lhs, rhs, limit=limit), df.count(), order, theta)
    except TooLarge:
        if order != "hashed" or any(as_path(p).repeated for p in [*lhs, *rhs]):
            raise
    groups = _single_groups(df, doc_id, lhs, rhs).groupBy(*[f"x{i}" for i in range(len(lhs))]).agg(F.sum("n").alias("n"), F.max("n").alias("m"))
    return strength_row(groups.agg(F.sum(F.least(F.expr("n div 2"), F.col("n") - F.col("m"))).alias("matching")), df.count(), theta)


# -- static baselines and classical measures -----------------------------------


def agree_masks(flat: DataFrame, names: list[str], row_limit: float = 3000) -> dict[int, int]:
    """Histogram of columns on which two rows agree (null agrees with null)."""
    rows = flat.select(*[named(n) for n in names]).distinct()
    if (n := rows.count()) > row_limit:
        raise TooLarge(f"{n} rows to compare pairwise; the limit is {row_limit:.0f}")
    keyed = rows.select(F.xxhash64(*[named(n) for n in names], *[named(n).isNull() for n in names]).alias("row"), *[named(c).alias(f"c{i}") for i, c in enumerate(names)])
    one, two = keyed.alias("a"), keyed.alias("b")
    mask = reduce(lambda m, i: m.bitwiseOR(F.when(F.col(f"a.c{i}").eqNullSafe(F.col(f"b.c{i}")), F.lit(1 << i)).otherwise(F.lit(0)).cast("long")), range(len(names)), F.lit(0).cast("long"))
    pairs = one.join(F.broadcast(two), F.col("a.row") < F.col("b.row")).select(mask.alias("mask"))
    return {r["mask"]: r["n"] for r in pairs.groupBy("mask").agg(F.count(F.lit(1)).alias("n")).toLocalIterator()}


def mine_static(df: DataFrame, method: str, max_lhs: int, paths: list[str] | None = None, row_limit: float = 1e6) -> DataFrame:
    """Classical dependencies of the statically unrolled rows (other semantics than the dynamic miners)."""
    flat = unroll_static(df, row_limit=row_limit)
    names = [str(as_path(p)) for p in paths] if paths is not None else flat.columns
    if method == "negative_cover":
        found = lattice.invert(lattice.negative_cover(agree_masks(flat, names, min(row_limit, 5000)), len(names)), len(names), max_lhs)
        return _frame(df, [(x, a, 1.0, True) for x, a in found], names, "fd")
    rows = flat.select(*[named(c).alias(f"c{i}") for i, c in enumerate(names)]).cache()
    distinct: dict[int, int] = {0: 1}
    found: set[tuple[int, int]] = set()
    for size in range(max_lhs + 1):
        level = [x for x in _subsets(len(names), size) if len(names) > size]
        tests = [(x, a) for x in level for a in range(len(names)) if not x >> a & 1 and not any(f & x == f and r == a for f, r in found)]
        need = sorted({m for x, a in tests for m in (x, x | 1 << a)} - set(distinct))
        for lo in range(0, len(need), 24):  # partitions of many column sets in one job
            part = need[lo : lo + 24]
            sets = [F.count_distinct(F.struct(*[f"c{i}" for i in lattice.bits(m)])).alias(f"n{k}") for k, m in enumerate(part)]
            row = rows.agg(*sets).first()
            distinct |= {m: row[k] for k, m in enumerate(part)}
        found |= {(x, a) for x, a in tests if distinct[x] == distinct[x | 1 << a]}
    rows.unpersist()
    return _frame(df, [(x, a, 1.0, True) for x, a in found], names, "fd")


def fd_holds(df: DataFrame, lhs: list[str], rhs: str) -> DataFrame:
    """One row: a classical dependency between columns."""
    groups = df.groupBy(*lhs).agg(F.min(rhs).alias("lo"), F.max(rhs).alias("hi"), F.count(F.lit(1)).alias("n"), F.count(rhs).alias("given"))
    bad = (F.col("lo") != F.col("hi")) | ((F.col("given") > 0) & (F.col("given") < F.col("n")))
    return groups.agg(F.count(F.lit(1)).alias("groups"), F.count_if(bad).alias("failing_groups")).withColumn("holds", F.col("failing_groups") == 0)


def fd_error(df: DataFrame, lhs: list[str], rhs: str, measure: str = "g3") -> DataFrame:
    """One row (measure, part, total, error): g1 violating ordered pairs, g2 involved rows, g3 rows to remove."""
    cells = df.groupBy(*lhs, rhs).agg(F.count(F.lit(1)).alias("n"))
    groups = cells.groupBy(*lhs).agg(F.sum("n").alias("size"), F.max("n").alias("most"), F.sum(F.col("n") * F.col("n")).alias("same"), F.count(F.lit(1)).alias("kinds"))
    parts = {"g1": F.col("size") * F.col("size") - F.col("same"), "g2": F.when(F.col("kinds") > 1, F.col("size")).otherwise(0), "g3": F.col("size") - F.col("most")}
    total = F.sum("size") * F.sum("size") if measure == "g1" else F.sum("size")
    out = groups.agg(F.sum(parts[measure]).alias("part"), total.alias("total"))
    return out.select(F.lit(measure).alias("measure"), "part", "total", F.round(F.col("part") / F.col("total"), 6).alias("error"))


def nfd_error(df: DataFrame, doc_id: str, lhs: list[str], rhs: list[str], limit: int = PAIR_LIMIT) -> DataFrame:
    """Violating pairs and documents involved in them, with their shares; of single-valued paths beyond the limit by group sizes."""
    n = df.count()
    try:
        pairs = nfd_violations(df, doc_id, lhs, rhs, limit=limit)
        docs = pairs.select(F.explode(F.array("d1", "d2")).alias("d")).distinct().agg(F.count(F.lit(1)).alias("documents"))
        out = pairs.agg(F.count(F.lit(1)).alias("pairs")).join(docs)
    except TooLarge:
        if any(as_path(p).repeated for p in [*lhs, *rhs]):
            raise
        apart = F.col("n") * (F.col("size") - F.col("n"))
        kinds = _single_groups(df, doc_id, lhs, rhs)
        out = kinds.agg(F.sum(apart).alias("pairs"), F.sum(F.when(apart > 0, F.col("n")).otherwise(0)).alias("documents")).withColumn("pairs", F.expr("pairs div 2"))
    return out.select("pairs", "documents", F.round(F.col("pairs") / max(1, n * (n - 1) // 2), 6).alias("g1"), F.round(F.col("documents") / max(1, n), 6).alias("g2"))


def candidate_keys(df: DataFrame, doc_id: str, max_size: int = 3, paths: list[str] | None = None) -> DataFrame:
    """Minimal sets of paths on all of which no two documents overlap."""
    hist, names = mask_histogram(df, doc_id, paths)
    keys = lattice.minimal_keys(hist, len(names), max_size)
    return df.sparkSession.createDataFrame(sorted((_name(k, names), k.bit_count()) for k in keys), "paths string, size int")


def repair_hints(df: DataFrame, doc_id: str, lhs: str, rhs: str) -> DataFrame:
    """Minority documents of an almost valid dependency, and the value of their group's majority."""
    rows, _, _ = _tuple_rows(df, doc_id, [lhs], [rhs])
    one = rows.select(F.col("x0").alias("group"), "doc_id", F.explode("y0").alias("value")).distinct()
    counts = one.groupBy("group", "value").agg(F.count(F.lit(1)).alias("n"))
    best = counts.withColumn("r", F.row_number().over(Window.partitionBy("group").orderBy(F.desc("n"), "value"))).where("r = 1")
    return one.join(best.select("group", F.col("value").alias("majority"), F.col("n").alias("votes")), "group").where("value <> majority").select("doc_id", "group", "value", "majority", "votes")


def hash_sample(doc_id: str, seed: int = 11) -> Callable[[int, float], Column]:
    """Chooses about a fraction of the documents for sample k by a hash of their id."""
    return lambda k, fraction: F.pmod(F.xxhash64(F.lit(seed + k), named(doc_id)), F.lit(1_000_000)) < int(fraction * 1_000_000)


def mine_functional_sampled(
    df: DataFrame, doc_id: str, samples: int = 3, fraction: float = 0.2, max_lhs: int = 3, paths: list[str] | None = None, limit: int | None = None, choose: Callable[[int, float], Column] | None = None
) -> DataFrame:
    """Mine the union of the masks of several samples once: what all samples support."""
    names = [str(p) for p in resolve(df, doc_id, paths)]
    choose = choose or hash_sample(doc_id)
    hist: dict[int, int] = {}
    for k in range(samples):
        chosen = df.where(choose(k, fraction))
        for m, n in overlap_histogram(unroll_dynamic(chosen, doc_id, names), len(names), chosen.count(), limit).items():
            hist[m] = hist.get(m, 0) + n
    return _frame(df, [(x, a, 1.0, True) for x, a in lattice.levelwise(hist, len(names), max_lhs)], names)


def mine_validated(df: DataFrame, doc_id: str, paths: list[str], max_lhs: int = 2, sample: float = 0.1, seed: int = 11, limit: int | None = None) -> tuple[DataFrame, int]:
    """Exact dependencies of all documents from sampled masks and linear validation, and the rounds it took.

    Candidates of the masks known so far are validated on all documents; each
    one that fails adds the masks of counterexample pairs, until none fails.
    Where that would compare too many right sides or pairs, the masks of all
    documents are counted instead, unless the caller gives a limit.
    """
    names = [str(as_path(p)) for p in paths]
    n = len(names)
    chosen = df.where(hash_sample(doc_id, seed)(0, sample))
    hist = dict.fromkeys(overlap_histogram(unroll_dynamic(chosen, doc_id, names), n, chosen.count(), limit), 1)
    good: set[tuple[int, int]] = set()
    rounds = 0
    while True:
        rounds += 1
        failed = 0
        for x, a in sorted(lattice.levelwise(hist, n, max_lhs) - good):
            lhs = [names[i] for i in lattice.bits(x)]
            try:
                if validate_nfd(df, doc_id, lhs, names[a]).first()["holds"]:
                    good.add((x, a))
                    continue
                hist |= dict.fromkeys(_counterexamples(df, doc_id, names, x, a), 1)
            except TooLarge:
                if limit is not None:
                    raise
                hist, failed = mask_histogram(df, doc_id, names)[0], 0  # of all documents, so that nothing is left to validate
                break
            failed += 1
        if not failed:
            return _frame(df, [(x, a, 1.0, True) for x, a in lattice.levelwise(hist, n, max_lhs)], names), rounds


def _counterexamples(df: DataFrame, doc_id: str, names: list[str], lhs: int, rhs: int, groups: int = 5) -> set[int]:
    """Masks of some violating pairs: documents of a few failing groups compared with their group's extremes."""
    rows, xs, _ = _tuple_rows(df, doc_id, [names[i] for i in lattice.bits(lhs)], [names[rhs]])
    key = F.struct(*xs) if xs else F.lit(0)
    sets = rows.select(key.alias("g"), "doc_id", F.array_sort("y0").alias("y"))
    kinds = sets.groupBy("g").agg(F.count_distinct("y").alias("k"), F.min(F.struct("y", "doc_id")).alias("lo"), F.count_distinct("doc_id").alias("n"), F.min(F.size("y")).alias("s"))
    some = kinds.where("n > 1 and (k > 1 or s = 0)").orderBy("g").limit(50 * groups).select("g")
    # A group's documents meet those of its least and its largest right set only, so a hot group gives few rows.
    ends = sets.join(F.broadcast(some), "g").groupBy("g").agg(F.min(F.struct("y", "doc_id")).alias("lo"), F.max(F.struct("y", "doc_id")).alias("hi"))
    met = sets.join(F.broadcast(ends), "g").select("doc_id", "y", F.explode(F.array("lo", "hi")).alias("e")).where("doc_id <> e.doc_id and not arrays_overlap(y, e.y)")
    found = met.select(F.least("doc_id", "e.doc_id").alias("d1"), F.greatest("doc_id", "e.doc_id").alias("d2")).limit(groups).collect()
    if not found:  # a rare failing group: ask for pairs themselves
        found = nfd_violations(df, doc_id, [names[i] for i in lattice.bits(lhs)], [names[rhs]]).limit(groups).collect()
    ids = sorted({i for r in found for i in r})
    part = overlap_masks(unroll_dynamic(df.where(F.col(doc_id).isin(ids)), doc_id, names))
    wanted = {tuple(r) for r in found}
    masks = {(r["d1"], r["d2"]): r["mask"] for r in part.collect()}
    return {masks.get(w, 0) for w in wanted}
