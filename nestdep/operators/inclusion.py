"""Inclusion dependencies between paths of nested documents.

P1 is included in P2 if every value found at P1 anywhere in the collection is
found at P2.  Everything reduces to the mask of paths that hold each value:

* the inverted miner groups values once and sums over distinct masks;
* the sorted miner sorts values and merges runs of equal ones in one pass over
  each partition, in rounds of hash slices, and drops candidates as soon as
  their missing values pass the budget.

Masks are 62-bit words, as many as the paths need.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from itertools import combinations, permutations
from math import comb, perm

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..deploy import ship
from ..functions.paths import EACH, Mark, PathExpr, as_path, named, path_type, path_values
from ..functions.values import keys_of, value_key
from ..plans.cells import TooLarge, cells_of_flat, register_metadata, resolve, unroll_dynamic, unroll_static
from ..sources.tables import forget, scratch, written

_BITS = 62
#: Shares of the values that the sorted miner reads round by round.
ROUNDS = (2, 18, 80)
DEPS = "kind string, lhs string, rhs string, support long, included long, strength double, valid boolean"


def mask_words(n_paths: int) -> int:
    return max(1, -(-n_paths // _BITS))


def mask_columns(n_paths: int) -> list[Column]:
    """bit_or aggregates: one word of the path mask each."""
    return [
        F.bit_or(F.when(F.floor(F.col("path_id") / _BITS) == w, F.expr(f"shiftleft(1L, cast(path_id % {_BITS} as int))")).otherwise(F.lit(0).cast("long"))).alias(f"m{w}")
        for w in range(mask_words(n_paths))
    ]


@register_metadata("values")
def value_masks(cells: DataFrame, n_paths: int) -> DataFrame:
    """value and the mask of paths that hold it; repeats are combined before the shuffle."""
    return cells.groupBy("value").agg(*mask_columns(n_paths))


def signatures(masks: DataFrame, n_paths: int) -> DataFrame:
    """Distinct masks with the number of values that have them."""
    return masks.groupBy(*[f"m{w}" for w in range(mask_words(n_paths))]).agg(F.count(F.lit(1)).alias("n_values"))


def _paths_of(n_paths: int) -> Column:
    """Path ids of the mask in m0, m1, ..."""
    ids = [F.when(F.col(f"m{i // _BITS}").bitwiseAND(F.lit(1 << (i % _BITS))) != 0, F.lit(i)) for i in range(n_paths)]
    return F.filter(F.array(*ids), lambda i: i.isNotNull())


def pair_counts(sigs: DataFrame, n_paths: int) -> DataFrame:
    """(lhs, rhs, included) for all pairs of paths that share a value, lhs = rhs giving the support."""
    listed = sigs.select(_paths_of(n_paths).alias("ids"), "n_values")
    left = listed.select(F.explode("ids").alias("lhs"), "ids", "n_values")
    return left.select("lhs", F.explode("ids").alias("rhs"), "n_values").groupBy("lhs", "rhs").agg(F.sum("n_values").alias("included"))


def name_dependencies(pairs: DataFrame, names: list[str], theta: float, kind: str = "nind") -> DataFrame:
    """Pairs with counts -> dependencies, all ordered pairs of paths that have values.

    The counts are read once: they join the grid of all pairs of paths, and a
    path's support is handed along its row and its column of the grid.  All this
    is one partition, as it has one row a pair of paths whatever the data.
    """
    spark, n = pairs.sparkSession, len(names)
    pairs = pairs.coalesce(1)
    catalog = spark.createDataFrame(list(enumerate(names)), "id int, name string")
    grid = spark.range(0, n * n, 1, 1).select(F.expr(f"cast(id div {n} as int) as lhs"), F.expr(f"cast(id % {n} as int) as rhs"))
    every = grid.join(pairs, ["lhs", "rhs"], "left")
    own = F.max(F.when(F.col("lhs") == F.col("rhs"), F.col("included")))
    every = every.withColumn("support", own.over(Window.partitionBy("lhs"))).withColumn("there", own.over(Window.partitionBy("rhs")))
    every = every.where("lhs <> rhs and support is not null and there is not null").withColumn("included", F.coalesce("included", F.lit(0)))
    out = every.join(F.broadcast(catalog.select(F.col("id").alias("lhs"), F.col("name").alias("lhs_name"))), "lhs")
    out = out.join(F.broadcast(catalog.select(F.col("id").alias("rhs"), F.col("name").alias("rhs_name"))), "rhs")
    return dependency(out, kind, "lhs_name", "rhs_name", theta)


def dependency(rows: DataFrame, kind: str, lhs: str, rhs: str, theta: float) -> DataFrame:
    ratio = F.col("included") / F.col("support")
    # The exact decision is on integers: included >= theta * support.
    valid = F.col("included") >= F.lit(theta) * F.col("support")
    return rows.select(F.lit(kind).alias("kind"), F.col(lhs).alias("lhs"), F.col(rhs).alias("rhs"), "support", "included", F.round(ratio, 6).alias("strength"), valid.alias("valid"))


def _cells(df: DataFrame, doc_id: str, paths: list[str] | None, unrolling: str, array_mode: str, row_limit: float | None) -> tuple[DataFrame, list[str]]:
    if unrolling == "dynamic":
        names = (paths or df.columns) if array_mode == "opaque" else [str(p) for p in resolve(df, doc_id, paths)]
        return unroll_dynamic(df, doc_id, paths, array_mode), list(names)
    flat = unroll_static(df, row_limit=row_limit)
    names = [str(as_path(p)) for p in paths] if paths is not None else flat.columns
    return cells_of_flat(flat.select(*map(named, names)), names), names


def mine_inclusion(
    df: DataFrame,
    doc_id: str,
    method: str = "inverted",
    theta: float = 1.0,
    unrolling: str = "dynamic",
    paths: list[str] | None = None,
    array_mode: str = "elements",
    weight: str = "distinct",
    row_limit: float | None = None,
    rounds: tuple[int, ...] = ROUNDS,
) -> DataFrame:
    """All unary inclusion dependencies with support, included, strength and validity.

    The sorted method reports only candidates it did not refute (their strengths are exact).
    """
    cells, names = _cells(df, doc_id, paths, unrolling, array_mode, row_limit)
    if method == "inverted":
        if weight == "occurrence":
            return name_dependencies(_occurrence_pairs(cells), names, theta)
        if weight == "document":
            return _document_weighted(cells, names, theta)
        return name_dependencies(pair_counts(signatures(value_masks(cells, len(names)), len(names)), len(names)), names, theta)
    if method != "sorted":
        raise ValueError(f"unknown method {method!r}")
    return sorted_rounds(cells, names, theta, rounds)[0]


def _occurrence_pairs(cells: DataFrame) -> DataFrame:
    """(lhs, rhs, included) counting occurrences at lhs of values that rhs holds."""
    held = cells.groupBy("value", "path_id").agg(F.count(F.lit(1)).alias("n"))
    listed = held.groupBy("value").agg(F.collect_list(F.struct("path_id", "n")).alias("at"))
    left = listed.select(F.explode("at").alias("l"), "at").select(F.col("l.path_id").alias("lhs"), F.col("l.n").alias("n"), F.explode("at").alias("r"))
    return left.groupBy("lhs", F.col("r.path_id").alias("rhs")).agg(F.sum("n").alias("included"))


def _document_weighted(cells: DataFrame, names: list[str], theta: float) -> DataFrame:
    """Share of documents with values at lhs all of whose values rhs holds."""
    n = len(names)
    masks = value_masks(cells, n)
    common = [F.bit_and(f"m{w}").alias(f"m{w}") for w in range(mask_words(n))]
    per_doc = cells.select("doc_id", F.col("path_id").alias("lhs"), "value").join(masks, "value").groupBy("doc_id", "lhs").agg(*common)
    pairs = per_doc.select("lhs", F.explode(_paths_of(n)).alias("rhs")).groupBy("lhs", "rhs").agg(F.count(F.lit(1)).alias("included"))
    return name_dependencies(pairs, names, theta)


def _merge(n_words: int):
    """Merge the runs of a sorted partition: path masks of its values, counted as they end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[tuple[int, ...], int] = {}
        last, mask = None, np.zeros(n_words, np.int64)

        def close(masks: np.ndarray) -> None:
            for words, k in zip(*np.unique(masks, axis=0, return_counts=True)):
                key = tuple(words.tolist())
                counts[key] = counts.get(key, 0) + int(k)

        for batch in batches:
            if not batch.num_rows:
                continue
            value, path = batch.column("value"), batch.column("path_id").to_numpy()
            other = pc.not_equal(value.slice(1), value.slice(0, len(value) - 1)).to_numpy(zero_copy_only=False)
            begin = np.concatenate([[0], np.flatnonzero(other) + 1])
            bit = np.left_shift(np.int64(1), path.astype(np.int64) % _BITS)
            words = np.stack([np.bitwise_or.reduceat(np.where(path // _BITS == w, bit, 0), begin) for w in range(n_words)], axis=1)
            if value[0].as_py() == last:
                words[0] |= mask
            elif last is not None:
                close(mask[None])
            close(words[:-1])
            last, mask = value[-1].as_py(), words[-1].copy()
        if last is not None:
            close(mask[None])
        if counts:
            found = np.array(list(counts), dtype=np.int64).reshape(len(counts), n_words)
            columns = [pa.array(found[:, w]) for w in range(n_words)]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(list(counts.values()), pa.int64())], names=[*(f"m{w}" for w in range(n_words)), "n_values"])

    return run


def merged_signatures(cells: DataFrame, n_paths: int) -> DataFrame:
    """Signatures by sort and merge: one exchange by value, one sort, one pass over the runs."""
    words = mask_words(n_paths)
    runs = cells.select("value", "path_id").repartition("value").sortWithinPartitions("value")
    schema = ", ".join([*(f"m{w} long" for w in range(words)), "n_values long"])
    return runs.mapInArrow(_merge(words), schema).groupBy(*[f"m{w}" for w in range(words)]).agg(F.sum("n_values").alias("n_values"))


def sorted_rounds(cells: DataFrame, names: list[str], theta: float, rounds: tuple[int, ...] = ROUNDS) -> tuple[DataFrame, list[dict]]:
    """The sorted miner and what each round saw (candidates alive, cells left, signatures).

    The distinct values of each path are written once, in a folder for each
    round's slice of the values; equal cells of a task are combined in compiled
    code before they are exchanged.  A round exchanges and merges only its slice
    of the paths that some candidate still needs.  A path's distinct values are
    those known and those left; a candidate goes when it misses more of them than
    the threshold forgives.
    """
    spark, n = cells.sparkSession, len(names)
    ship(spark)  # merging runs in Python workers
    ends = [sum(rounds[: k + 1]) for k in range(len(rounds))]
    place = F.pmod(F.xxhash64("value"), F.lit(ends[-1]))
    turn = F.when(F.lit(False), 0)
    for k, end in enumerate(ends):
        turn = turn.when(place < end, k)
    path = scratch(spark, "cells")
    cells.select("path_id", "value").distinct().withColumn("turn", turn).write.partitionBy("turn").parquet(path)
    stored = spark.read.schema("path_id int, value string, turn int").parquet(path)
    left = {(r["turn"], r["path_id"]): r["n"] for r in stored.groupBy("turn", "path_id").agg(F.count(F.lit(1)).alias("n")).toLocalIterator()}
    known = sorted({p for _, p in left})
    alive = set(permutations(known, 2))
    missing = dict.fromkeys(alive, 0)
    support = dict.fromkeys(known, 0)
    seen = []
    for k, share in enumerate(rounds):
        used = sorted({p for pair in alive for p in pair})
        if not used:
            break
        part = stored.where((F.col("turn") == k) & F.col("path_id").isin(used))
        found = [(r[:-1], r[-1]) for r in merged_signatures(part, n).toLocalIterator()]
        for words, count in found:
            mask = sum(w << (_BITS * i) for i, w in enumerate(words))
            holders = {p for p in used if mask >> p & 1}
            for p in holders:
                support[p] += count
            for a, b in alive:
                if a in holders and b not in holders:
                    missing[a, b] += count
        seen.append({"share": share, "candidates": len(alive), "cells": sum(left.get((k, p), 0) for p in used), "signatures": len(found)})
        bound = {p: support[p] + sum(left.get((later, p), 0) for later in range(k + 1, len(rounds))) for p in used}
        # In integers, as the decision below: what is included at most against the least support.
        alive = {(a, b) for a, b in alive if bound[a] - missing[a, b] >= theta * bound[a]}
    forget(spark, path)
    rows = []
    for a, b in sorted(alive):
        if support[a] and support[b]:
            held = support[a] - missing[a, b]
            if held >= theta * support[a]:
                rows.append(("nind", names[a], names[b], support[a], held, round(held / support[a], 6), True))
    return spark.createDataFrame(rows, DEPS), seen


def holds_nind(df: DataFrame, lhs: str, rhs: str, other: DataFrame | None = None, theta: float = 1.0) -> DataFrame:
    """One row: the dependency lhs in rhs (of `other` if given) by definition."""
    other = df if other is None else other
    left = df.select(F.explode(keys_of(path_values(df, lhs), path_type(df.schema, lhs))).alias("value")).distinct()
    right = other.select(F.explode(keys_of(path_values(other, rhs), path_type(other.schema, rhs))).alias("value")).distinct()
    lost = left.join(right, "value", "left_anti").agg(F.count(F.lit(1)).alias("missing"))
    both = left.agg(F.count(F.lit(1)).alias("support")).join(lost).withColumn("included", F.col("support") - F.col("missing"))
    return dependency(both.withColumns({"l": F.lit(lhs), "r": F.lit(rhs)}), "nind", "l", "r", theta)


def nind_verdicts(df: DataFrame, doc_id: str, lhs: str, rhs: str) -> DataFrame:
    """For each document with values at lhs: does rhs, anywhere, hold them all?"""
    left = df.select(named(doc_id).alias("doc_id"), F.explode(keys_of(path_values(df, lhs), path_type(df.schema, lhs))).alias("value"))
    right = df.select(F.explode(keys_of(path_values(df, rhs), path_type(df.schema, rhs))).alias("value"), F.lit(1).alias("there")).distinct()
    return left.join(right, "value", "left").groupBy("doc_id").agg((F.count(F.lit(1)) == F.count("there")).alias("holds"))


def holds_within_document(df: DataFrame, lhs: str, rhs: str) -> DataFrame:
    """Documents whose own values at lhs all stand at rhs of the same document."""
    rest = F.array_except(keys_of(path_values(df, lhs), path_type(df.schema, lhs)), keys_of(path_values(df, rhs), path_type(df.schema, rhs)))
    some = F.size(path_values(df, lhs)) > 0
    rows = df.where(some).agg(F.count(F.lit(1)).alias("support"), F.count_if(F.size(rest) == 0).alias("included"))
    return dependency(rows.withColumns({"l": F.lit(lhs), "r": F.lit(rhs)}), "within", "l", "r", 1.0)


def mine_inclusion_across(collections: dict[str, tuple[DataFrame, str]], theta: float = 1.0, paths: dict[str, list[str]] | None = None) -> DataFrame:
    """Dependencies within and between collections; paths are named collection:path."""
    cells, names = None, []
    for name, (df, doc_id) in collections.items():
        chosen = resolve(df, doc_id, (paths or {}).get(name))
        part = unroll_dynamic(df, doc_id, [str(p) for p in chosen]).select((F.col("path_id") + len(names)).alias("path_id"), "value")
        names += [f"{name}:{p}" for p in chosen]
        cells = part if cells is None else cells.unionAll(part)
    n = len(names)
    return name_dependencies(pair_counts(signatures(value_masks(cells, n), n), n), names, theta)


def _tuple_rows(df: DataFrame, paths: list[str], alignment: str) -> DataFrame:
    """Columns c0, c1, ... : keys of one element's fields ("element") or arrays of a document's keys ("product")."""
    if alignment == "product":
        return df.select(*[F.array_distinct(keys_of(path_values(df, p), path_type(df.schema, p))).alias(f"c{i}") for i, p in enumerate(paths)])
    if alignment != "element":
        raise ValueError(f"unknown alignment {alignment!r}")
    # Paths below one array are paired by the element they come from.
    steps = [as_path(p).steps for p in paths]
    cut = max(i + 1 for i, s in enumerate(steps[0]) if isinstance(s, Mark) and s == EACH)
    if any(s[:cut] != steps[0][:cut] or len(s) != cut + 1 for s in steps):
        raise ValueError("element alignment needs fields of the same array")
    array = PathExpr(steps[0][:cut])
    kind = path_type(df.schema, array)
    rows = df.select(F.explode(path_values(df, array)).alias("e"))
    return rows.select(*[value_key(F.col("e").getField(s[cut]), kind[s[cut]].dataType).alias(f"c{i}") for i, s in enumerate(steps)])


def _sequence_cells(rows: DataFrame, sequences: list[tuple[int, ...]], alignment: str) -> DataFrame:
    """(path_id, value): number of a sequence of paths, and a tuple of keys that stands there."""
    if alignment == "element":
        each = [F.when(_all_given(x), F.struct(F.lit(i).alias("path_id"), F.array(*[F.col(f"c{p}") for p in x]).alias("value"))) for i, x in enumerate(sequences)]
        return rows.select(F.explode(F.filter(F.array(*each), lambda c: c.isNotNull())).alias("cell")).select("cell.path_id", "cell.value")
    out = None
    for chosen in sorted({tuple(sorted(x)) for x in sequences}):
        part = rows.select(*[f"c{p}" for p in chosen])
        for p in chosen:
            part = part.withColumn(f"c{p}", F.explode(f"c{p}"))
        each = [F.struct(F.lit(i).alias("path_id"), F.array(*[F.col(f"c{p}") for p in x]).alias("value")) for i, x in enumerate(sequences) if tuple(sorted(x)) == chosen]
        part = part.select(F.explode(F.array(*each)).alias("cell")).select("cell.path_id", "cell.value")
        out = part if out is None else out.unionAll(part)
    return out


def _all_given(sequence: tuple[int, ...]) -> Column:
    out = F.lit(True)
    for p in sequence:
        out = out & F.col(f"c{p}").isNotNull()
    return out


def mine_inclusion_nary(df: DataFrame, doc_id: str, max_arity: int = 2, theta: float = 1.0, paths: list[str] | None = None, alignment: str = "product", limit: int = 20_000) -> DataFrame:
    """Dependencies between sequences of distinct paths of 2 to max_arity, left ones in path order.

    A tuple stands at a sequence if one element ("element") or one document
    ("product") has a value at each of its paths.  All pairs of sequences are
    tested, one job an arity, except where a projection proves a pair wrong: at
    theta 1, and only if no value is missing anywhere, a valid pair stays valid
    when a position is left out, a sequence being included in itself.  At lower
    thresholds, or with missing values, a part of a valid pair may well be weak.
    """
    spark = df.sparkSession
    names = [str(p) for p in resolve(df, doc_id, paths)]
    every = range(len(names))
    base = written(_tuple_rows(df, names, alignment), "tuples")
    absent = (lambda c: F.size(c) == 0) if alignment == "product" else (lambda c: F.col(c).isNull())
    gap = F.lit(False)
    for i in every:
        gap = gap | absent(f"c{i}")
    prune = theta == 1.0 and not base.where(gap).take(1)
    last: set[tuple[tuple[int, ...], tuple[int, ...]]] = set()
    single, rows = {(p, p) for p in every}, []
    for arity in range(1 if prune else 2, max_arity + 1):
        if prune and arity > 1:
            whole = {(x, x) for x in combinations(every, arity - 1)} | last
            grown = {((*x, a), (*y, b)) for x, y in whole for a, b in single if a > x[-1] and b not in y}
            without = lambda x, i: x[:i] + x[i + 1 :]
            pairs = [(x, y) for x, y in sorted(grown) if x != y and all((without(x, i), without(y, i)) in whole for i in range(arity))]
        else:
            pairs = [(x, y) for x in combinations(every, arity) for y in permutations(every, arity) if x != y] if comb(len(names), arity) * perm(len(names), arity) <= 50 * limit else None
        if pairs is None or len(pairs) > limit:
            raise TooLarge(f"too many pairs of {arity} paths; the limit is {limit}: choose fewer paths")
        if not pairs:
            last = set()
            continue
        sequences = sorted({s for pair in pairs for s in pair})
        n, number = len(sequences), {s: i for i, s in enumerate(sequences)}
        masks, last = value_masks(_sequence_cells(base, sequences, alignment), n), set()
        counts = {(r["lhs"], r["rhs"]): r["included"] for r in pair_counts(signatures(masks, n), n).toLocalIterator()}
        for x, y in pairs:
            support, held = counts.get((number[x], number[x]), 0), counts.get((number[x], number[y]), 0)
            good = support > 0 and held >= theta * support
            if arity > 1 and support:
                rows.append(("nary", ",".join(names[i] for i in x), ",".join(names[i] for i in y), support, held, round(held / support, 6), good))
            if good:
                last.add((x, y))
        if arity == 1:
            single |= {(x[0], y[0]) for x, y in last}
    return spark.createDataFrame(rows, DEPS)


def prune_candidates(df: DataFrame, doc_id: str, theta: float = 1.0, paths: list[str] | None = None) -> DataFrame:
    """Pairs that value domains do not rule out: type, and at theta 1 also the range of keys."""
    cells, names = _cells(df, doc_id, paths, "dynamic", "elements", None)
    tag = F.substring("value", 1, 1)
    stats = cells.groupBy("path_id").agg(F.collect_set(tag).alias("tags"), F.min("value").alias("lo"), F.max("value").alias("hi"), F.approx_count_distinct("value").alias("about"))
    left = stats.select(*[F.col(c).alias(f"l_{c}") for c in stats.columns])
    right = stats.select(*[F.col(c).alias(f"r_{c}") for c in stats.columns])
    both = left.join(F.broadcast(right), F.col("l_path_id") != F.col("r_path_id"))
    keep = F.arrays_overlap("l_tags", "r_tags")
    if theta == 1.0:
        keep = keep & (F.size(F.array_except("l_tags", "r_tags")) == 0) & (F.col("l_lo") >= F.col("r_lo")) & (F.col("l_hi") <= F.col("r_hi"))
    catalog = F.array(*[F.lit(n) for n in names])
    return both.where(keep).select(F.get(catalog, F.col("l_path_id")).alias("lhs"), F.get(catalog, F.col("r_path_id")).alias("rhs"))


def key_paths(df: DataFrame, doc_id: str, paths: list[str] | None = None) -> DataFrame:
    """Paths with one value per document that no other document has."""
    cells, names = _cells(df, doc_id, paths, "dynamic", "elements", None)
    docs = cells.groupBy("path_id", "value").agg(F.count(F.lit(1)).alias("n"))
    stats = docs.groupBy("path_id").agg(F.max("n").alias("most"), F.count(F.lit(1)).alias("values"))
    total = df.agg(F.count(F.lit(1)).alias("documents"))
    catalog = F.array(*[F.lit(n) for n in names])
    single = [i for i, n in enumerate(names) if not as_path(n).repeated]
    good = stats.join(F.broadcast(total)).where((F.col("most") == 1) & (F.col("values") == F.col("documents")) & F.col("path_id").isin(single or [-1]))
    return good.select(F.get(catalog, F.col("path_id")).alias("path"))


def suggest_references(deps: DataFrame, keys: DataFrame) -> DataFrame:
    """Valid dependencies into a key path, ranked: candidates for references."""
    good = deps.where("valid").join(F.broadcast(keys.select(F.col("path").alias("rhs"))), "rhs")
    return good.select("lhs", "rhs", "support", "strength").orderBy(F.desc("strength"), F.desc("support"), "lhs", "rhs")


def follow_reference(df: DataFrame, lhs: str, other: DataFrame, rhs: str, how: str = "inner") -> DataFrame:
    """Join documents to the documents that their values at lhs refer to; columns r_* are the target's."""
    left = df.withColumn("_ref", F.explode_outer(F.array_distinct(keys_of(path_values(df, lhs), path_type(df.schema, lhs)))))
    right = other.select(F.explode(F.array_distinct(keys_of(path_values(other, rhs), path_type(other.schema, rhs)))).alias("_key"), *[F.col(c).alias(f"r_{c}") for c in other.columns])
    return left.join(right, F.col("_ref") == F.col("_key"), how).drop("_ref", "_key")


def nind_closure(deps: Iterable[tuple[str, str]], reflexive: bool = False) -> set[tuple[str, str]]:
    """All that reflexivity and transitivity imply; for exact dependencies (ratios do not compose)."""
    edges: dict[str, set[str]] = {}
    for a, b in deps:
        edges.setdefault(a, set()).add(b)
        edges.setdefault(b, set())
    out = set()
    for start in edges:
        todo, seen = list(edges[start]), set()
        while todo:
            x = todo.pop()
            if x not in seen:
                seen.add(x)
                todo += edges[x]
        out |= {(start, x) for x in seen if reflexive or x != start}
        if reflexive:
            out.add((start, start))
    return out


def nind_reduce(deps: Iterable[tuple[str, str]]) -> set[tuple[str, str]]:
    """A smallest set, greedily, with the same closure."""
    kept = {d for d in deps if d[0] != d[1]}
    for d in sorted(kept):
        rest = kept - {d}
        if d in nind_closure(rest):
            kept = rest
    return kept
