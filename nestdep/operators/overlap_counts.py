"""Number of pairs of documents by overlap mask, without the pairs of documents.

Values of one document overlap with nothing and go; others are numbered.
Documents with the same value sets on a set S of paths are one class with a
weight.  Classes keep only values that stand in a combination (one value a path)
of two classes at least.  Two classes overlap on a path iff the sum over the
non-empty sets T of values they share there of (-1) ** (|T| + 1) is 1, so that
the pairs that overlap on all of S follow from one aggregation by (T for each
path), linear in the classes.  Classes with many subsets have few others that
share a combination, or else are few themselves: for each S the number of subsets
from which on classes are compared with those they meet is the one with the least
subsets and comparisons, both counted before.  The masks follow from the numbers
of all S by subtraction.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.cells import TooLarge
from ..sources.tables import forget_frame, written
from .lattice import bits

#: Classes of at most so many subsets are taken by these, the others by comparison.
SMALL = tuple(float(1 << k) for k in (0, 2, 4, 6, 8, 10, 12, 14, 17, 20, 24))
#: Comparisons that one subset takes the time of.
SUBSET_COST = 4.0
#: A combination with more comparisons is dealt over SALTS tasks.
HOT, SALTS = 1_000_000, 16
COUNTED_PATHS = 12


def shared_cells(cells: DataFrame) -> DataFrame:
    """Distinct cells (doc_id, path_id, value) whose value stands in another document, too; values are numbers."""
    one = written(cells.select("doc_id", "path_id", "value").distinct(), "distinct-cells")
    shared = one.groupBy("path_id", "value").agg(F.count(F.lit(1)).alias("f")).where("f > 1").select("path_id", "value")
    numbers = written(shared.withColumn("number", F.monotonically_increasing_id()), "numbers")
    return one.join(numbers, ["path_id", "value"]).select("doc_id", "path_id", F.col("number").alias("value"))


def document_sets(cells: DataFrame, n_paths: int) -> DataFrame:
    """(doc_id, p0, p1, ...): the sets of shared values of each document that has any."""
    sets = [F.array_sort(F.collect_list(F.when(F.col("path_id") == i, F.col("value")))).alias(f"p{i}") for i in range(n_paths)]
    return shared_cells(cells).groupBy("doc_id").agg(*sets)


def shared_profiles(cells: DataFrame, n_paths: int) -> DataFrame:
    """(p0, p1, ..., w): the distinct combinations of sets of shared values, and how many documents have each."""
    return document_sets(cells, n_paths).groupBy(*[f"p{i}" for i in range(n_paths)]).agg(F.count(F.lit(1)).alias("w"))


def largest_meeting(docs: DataFrame, paths: list[int]) -> int:
    """At least as many documents as one of `docs` (see document_sets) overlaps with on all paths."""
    values = [f"v{i}" for i in range(len(paths))]
    atoms = combinations_of(docs.select("doc_id", *[f"p{i}" for i in paths]), [f"p{i}" for i in paths]).select("doc_id", *values)
    met = atoms.groupBy(*values).agg((F.count(F.lit(1)) - 1).alias("f")).where("f > 0")
    return atoms.join(met, values).groupBy("doc_id").agg(F.sum("f").alias("f")).agg(F.coalesce(F.max("f"), F.lit(0))).first()[0]


def pairs_meeting(docs: DataFrame, n_paths: int, paths: list[int], limit: int) -> DataFrame:
    """(d1, d2, mask), d1 < d2, of the pairs that overlap on all of some paths; bits of all n_paths paths."""
    values, names = [f"v{i}" for i in range(len(paths))], [f"p{i}" for i in range(n_paths)]
    atoms = combinations_of(docs.select("doc_id", *[F.col(p).alias(f"c{p}") for p in names], *[f"p{i}" for i in paths]), [f"p{i}" for i in paths])
    made = atoms.groupBy(*values).agg(F.count(F.lit(1)).alias("f")).agg(F.coalesce(F.sum(F.expr("f * (f - 1) div 2")), F.lit(0))).first()[0]
    if made > limit:
        raise TooLarge(f"{made} pairs of documents overlap on {len(paths)} of the paths; the limit is {limit}: sample, choose paths, or validate linearly")
    one = atoms.select(*values, F.col("doc_id").alias("d1"), *[f"c{p}" for p in names])
    two = atoms.select(*values, F.col("doc_id").alias("d2"), *[F.col(f"c{p}").alias(f"c{p}_2") for p in names])
    both = one.join(two, values).where("d1 < d2")
    for i, v in zip(paths, values):  # each pair at the least combination that both have
        both = both.where(f"array_min(array_intersect(cp{i}, cp{i}_2)) = {v}")
    bits_ = [F.lit(1 << i).cast("long") if i in paths else F.when(F.arrays_overlap(f"cp{i}", f"cp{i}_2"), F.lit(1 << i)).otherwise(F.lit(0)).cast("long") for i in range(n_paths)]
    return both.select("d1", "d2", reduce(lambda x, y: x.bitwiseOR(y), bits_).alias("mask"))


def mask_counts(cells: DataFrame, n_paths: int, small: tuple[float, ...] = SMALL) -> dict[int, int]:
    """mask -> number of pairs, of all pairs that share a value somewhere."""
    if n_paths > COUNTED_PATHS:
        raise ValueError(f"{n_paths} paths have too many sets to count pairs for: at most {COUNTED_PATHS}")
    profiles = written(shared_profiles(cells, n_paths), "profiles")
    on: dict[int, int] = {}
    level = [1 << i for i in range(n_paths)]
    while level:
        found = _pairs_on(profiles, n_paths, level, small)
        on |= {s: n for s, n in found.items() if n}
        grown = {s | 1 << i for s in found for i in range(n_paths) if not s >> i & 1}
        level = sorted(s for s in grown if all(on.get(s & ~(1 << i)) for i in bits(s)))
    forget_frame(profiles)
    out = {}
    for s in sorted(on, key=int.bit_count, reverse=True):  # pairs on s less those on more than s
        out[s] = on[s] - sum(n for t, n in out.items() if t != s and t & s == s)
    return {s: n for s, n in out.items() if n}


def pairs_on(cells: DataFrame, n_paths: int, masks: list[int], small: tuple[float, ...] = SMALL) -> dict[int, int]:
    """Number of pairs that overlap on all paths of each mask."""
    profiles = written(shared_profiles(cells, n_paths), "profiles")
    found = _pairs_on(profiles, n_paths, masks, small)
    forget_frame(profiles)
    return {m: found.get(m, 0) for m in masks}


def _pairs_on(profiles: DataFrame, n_paths: int, level: list[int], small: tuple[float, ...]) -> dict[int, int]:
    names = [f"p{i}" for i in range(n_paths)]
    # Paths out of the mask hold one value that all documents share.
    sets = [F.when(F.col("s").bitwiseAND(F.lit(1 << i)) != 0, F.col(p)).otherwise(F.array(F.lit(-1).cast("long"))).alias(p) for i, p in enumerate(names)]
    rows = profiles.withColumn("s", F.explode(F.array(*[F.lit(s).cast("long") for s in level]))).select("s", *sets, "w").where(reduce(lambda a, b: a & b, [F.size(p) > 0 for p in names]))
    classes = written(rows.groupBy("s", *names).agg(F.sum("w").alias("w")).withColumn("id", F.monotonically_increasing_id()), "classes")
    out = {s: 0 for s in level}
    for r in classes.groupBy("s").agg(F.sum(F.expr("w * (w - 1) div 2")).alias("n")).collect():
        out[r["s"]] += int(r["n"])
    reduced = written(_met_somewhere(classes, names).withColumn("id", F.monotonically_increasing_id()), "reduced")
    for s, n in _across(reduced, names, small).items():
        out[s] += n
    forget_frame(classes)
    forget_frame(reduced)
    return out


def combinations_of(classes: DataFrame, names: list[str]) -> DataFrame:
    """Each class once for each combination of one value a path (v0, v1, ...)."""
    for i, p in enumerate(names):
        classes = classes.withColumn(f"v{i}", F.explode(p))
    return classes


def _met_somewhere(classes: DataFrame, names: list[str]) -> DataFrame:
    """(s, sets, w, q): classes with the values that another class may share with them; q sums the squared weights."""
    values = [f"v{i}" for i in range(len(names))]
    atoms = combinations_of(classes, names).select("s", "id", "w", *values)
    met = atoms.groupBy("s", *values).agg(F.count(F.lit(1)).alias("c")).where("c > 1").drop("c")
    kept = atoms.join(met, ["s", *values], "left_semi").groupBy("s", "id").agg(F.first("w").alias("w"), *[F.array_sort(F.collect_set(v)).alias(p) for p, v in zip(names, values)])
    return kept.groupBy("s", *names).agg(F.sum("w").alias("w"), F.sum(F.col("w") * F.col("w")).alias("q"))


def _across(reduced: DataFrame, names: list[str], small: tuple[float, ...]) -> dict[int, int]:
    """Pairs of documents of different classes that overlap on every path of s."""
    rows = reduced.withColumn("t", reduce(lambda a, b: a * b, [F.pow(F.lit(2.0), F.size(p)) - 1 for p in names]))
    most, compared = _cuts(rows, names, small)
    if not most:
        return {}
    cut = F.element_at(F.create_map(*[F.lit(x) for s, c in most.items() for x in (s, c)]), F.col("s").cast("int"))
    rows = rows.withColumn("large", F.col("t") > cut)
    out = _by_subsets(rows.where("not large"), names)
    if compared:
        for s, n in _by_comparison(rows, names, compared).items():
            out[s] = out.get(s, 0) + n
    return out


def _cuts(rows: DataFrame, names: list[str], small: tuple[float, ...]) -> tuple[dict[int, float], int]:
    """For each s the number of subsets up to which classes are taken by these, and how many comparisons the others need."""
    terms = [F.sum(F.when(F.col("t") <= c, F.col("t")).otherwise(0.0)).alias(f"t{j}") for j, c in enumerate(small)]
    sizes = {r["s"]: r for r in rows.groupBy("s").agg(*terms, F.max("t").alias("t")).collect()}
    if all(r["t"] <= small[0] for r in sizes.values()):
        return {s: small[0] for s in sizes}, 0
    atoms = combinations_of(rows, names).groupBy("s", *[f"v{i}" for i in range(len(names))])
    met = atoms.agg(F.count(F.lit(1)).cast("double").alias("n"), *[F.count_if(F.col("t") > c).cast("double").alias(f"l{j}") for j, c in enumerate(small)])
    pairs = met.groupBy("s").agg(*[F.sum(F.expr(f"l{j} * (l{j} - 1) / 2 + l{j} * (n - l{j})")).alias(f"c{j}") for j in range(len(small))]).collect()
    most, compared = {}, 0.0
    for r in pairs:
        best = min(range(len(small)), key=lambda j: SUBSET_COST * sizes[r["s"]][f"t{j}"] + r[f"c{j}"])
        most[r["s"]] = small[best]
        compared += r[f"c{best}"]
    return most, int(compared)


def _by_subsets(rows: DataFrame, names: list[str]) -> dict[int, int]:
    """Pairs among classes, each by all combinations of a non-empty subset a path."""
    own = {r["s"]: r["q"] for r in rows.groupBy("s").agg(F.sum("q").alias("q")).collect()}
    subsets = rows.select("s", "w", F.lit(1).alias("sign"), *names)
    for i, p in enumerate(names):
        keys = F.aggregate(p, F.array(F.lit("")), lambda a, v: F.concat(a, F.transform(a, lambda x: F.concat(x, v.cast("string"), F.lit(",")))))
        # The place of a subset in the list, in bits, tells its members.
        subsets = subsets.select("*", F.posexplode(keys).alias("at", f"k{i}")).where("at > 0")
        subsets = subsets.withColumn("sign", F.when(F.bit_count("at") % 2 == 1, F.col("sign")).otherwise(-F.col("sign"))).drop("at", p)
    sums = subsets.groupBy("s", "sign", *[f"k{i}" for i in range(len(names))]).agg(F.sum("w").alias("w"))
    total = sums.groupBy("s").agg(F.sum(F.col("sign") * F.col("w").cast("decimal(19,0)") * F.col("w")).alias("n"))
    return {r["s"]: (int(r["n"]) - own[r["s"]]) // 2 for r in total.collect()}


def _by_comparison(rows: DataFrame, names: list[str], compared: int) -> dict[int, int]:
    """Pairs with large classes, each looked at once for every combination that both have and counted at the least one."""
    values = [f"v{i}" for i in range(len(names))]
    atoms = combinations_of(rows.withColumns({f"c{p}": F.col(p) for p in names}).drop("t", "q"), names).drop(*names)
    salt, copies = F.lit(0), F.array(F.lit(0))
    if compared > HOT:
        met = atoms.groupBy("s", *values).agg(F.count(F.lit(1)).alias("n"), F.count_if("large").alias("l"))
        hot = met.where(F.col("n") * F.col("l") > HOT).select("s", *values, F.lit(True).alias("hot"))
        atoms = atoms.join(F.broadcast(hot), ["s", *values], "left")
        salt = F.when(F.col("hot"), F.pmod(F.xxhash64("id"), F.lit(SALTS)).cast("int")).otherwise(0)
        copies = F.when(F.col("hot"), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))
    one = atoms.where("large").select("s", *values, "id", "w", *[f"c{p}" for p in names], salt.alias("salt"))
    two = atoms.select("s", *values, *[F.col(c).alias(f"{c}_2") for c in ("id", "w", "large", *[f"c{p}" for p in names])], F.explode(copies).alias("salt"))
    both = one.join(two, ["s", *values, "salt"]).where("not large_2 or id < id_2")
    for p, v in zip(names, values):
        both = both.where(f"size(c{p}) = 1 or size(c{p}_2) = 1 or array_min(array_intersect(c{p}, c{p}_2)) = {v}")
    out = {r["s"]: int(r["n"]) for r in both.groupBy("s").agg(F.sum(F.col("w").cast("decimal(19,0)") * F.col("w_2")).alias("n")).collect()}
    for r in rows.where("large").groupBy("s").agg(F.sum(F.expr("(w * w - q) div 2")).alias("n")).collect():
        out[r["s"]] = out.get(r["s"], 0) + int(r["n"])
    return out
