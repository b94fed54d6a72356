"""Mixing sources to target weights with a multivariate-hypergeometric splitting tree.

The mix takes `share` times all words.  Sources, by code point with null last,
have repeating weights; no source's target passes `stop` times its words, and
the excess is shared again by weight until none is above.

Documents of a source are dealt by hash into blocks of about `block_words`
words, and blocks are put in a hashed (permuted) order.  A target is whole
passes over the source plus a part of one more; the part takes blocks in their
permuted order and, within the last block, documents in hashed order, so that
exactly one document a source can be cut.  That gives each source an exact
quota of block draws.  A binary tree over the output shards splits the vector
of quotas: each node draws its left half from a multivariate hypergeometric
law with a seed that is a function of the node, so each shard finds its own
share alone, and shares are disjoint runs of the permuted order.  Rows within
a shard are ordered by a hash (the local shuffle).

Scale: only per-source totals come to the driver.  Blocks are bounded, so a
source with a third of all rows is many keys; running sums over blocks are
two-level.  The source table is broadcast only up to `MAX_BROADCAST` sources,
beyond that it is joined with salted keys.

Defined cases: a null or blank text has size 0 and is never taken; a null
source is a source of its own; rows that repeat an id are rows of their own;
reruns agree as nothing depends on row order; an empty table gives an empty
result; `mixed_documents` keeps all columns.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ._spark import written

WEIGHTS = (5.0, 2.0, 1.0)
BLOCK_WORDS = 1 << 16
SHARD_WORDS = 1 << 22
MAX_BROADCAST = 50_000
_SALTS = 32
_WORD = r"[^\x20\x09-\x0D]+"


def source_targets(sizes: list[tuple[str | None, int]], weights: tuple = WEIGHTS, share: float = 1.5, stop: float = 2.0) -> list[tuple[str | None, int, float]]:
    """(source, size, target) by code point, null last."""
    ranked = sorted(sizes, key=lambda s: (s[0] is None, s[0] or ""))
    size = np.array([n for _, n in ranked], dtype=float)
    weight = np.array([weights[i % len(weights)] for i in range(len(ranked))], dtype=float)
    target, free = np.zeros(len(ranked)), np.ones(len(ranked), dtype=bool)
    left = share * size.sum()
    while free.any():
        target[free] = left * weight[free] / weight[free].sum()
        above = free & (target > stop * size)
        if not above.any():
            break
        target[above] = stop * size[above]
        free &= ~above
        left = share * size.sum() - target[~free].sum()
    return [(s, n, float(t)) for (s, n), t in zip(ranked, target)]


def split_path(quotas: np.ndarray, shard: int, shards: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Offsets and counts of one shard's draws of each source, from the root down."""
    lo, hi = 0, shards
    offset, have = np.zeros_like(quotas), quotas.copy()
    while hi - lo > 1:
        mid = (lo + hi) // 2
        total = int(have.sum())
        rng = np.random.default_rng([seed, lo, hi])
        left = rng.multivariate_hypergeometric(have, total * (mid - lo) // (hi - lo), method="marginals") if total else have
        if shard < mid:
            hi, have = mid, left
        else:
            lo, offset, have = mid, offset + left, have - left
    return offset, have


def shard_shares(spark: SparkSession, quotas: list[int], shards: int, seed: int) -> DataFrame:
    """(sidx, draw, shard): which shard gets each draw of each source."""
    counts = np.array(quotas, dtype=np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for shard in batch.column("id").to_pylist():
                offset, have = split_path(counts, shard, shards, seed)
                some = np.flatnonzero(have)
                columns = some.astype(np.int32), offset[some], offset[some] + have[some] - 1, np.full(len(some), shard, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["sidx", "lo", "hi", "shard"])

    ranges = spark.range(shards).mapInArrow(run, "sidx int, lo long, hi long, shard long")
    return ranges.select("sidx", F.explode(F.sequence("lo", "hi")).alias("draw"), "shard")


def _with_sources(rows: DataFrame, sources: DataFrame, n: int) -> DataFrame:
    """Add the columns of each row's source; null sources meet too."""
    on = rows["source"].eqNullSafe(sources["s_source"])
    if n <= MAX_BROADCAST:
        return rows.join(F.broadcast(sources), on).drop("s_source")
    salted = sources.withColumn("s_salt", F.explode(F.sequence(F.lit(0), F.lit(_SALTS - 1))))
    rows = rows.withColumn("r_salt", F.pmod(F.col("rnd"), F.lit(_SALTS)).cast("int"))
    on = rows["source"].eqNullSafe(salted["s_source"]) & (rows["r_salt"] == salted["s_salt"])
    return rows.join(salted, on).drop("s_source", "s_salt", "r_salt")


def _clip(x: Column, lo: Column, hi: Column) -> Column:
    return F.greatest(lo, F.least(x, hi))


def plan_mix(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
    weights: tuple = WEIGHTS,
    share: float = 1.5,
    stop: float = 2.0,
    block_words: int = BLOCK_WORDS,
    shard_words: int = SHARD_WORDS,
    seed: int = 17,
    keep_row: bool = False,
) -> DataFrame:
    """One row per document: id, source, size, source_size, target, draws, taken.

    draws: array of (pass, shard, place, words); `place` orders rows within the shard.
    """
    spark = docs.sparkSession
    columns = [
        F.col(id_col).alias("id"),
        F.col(source_col).alias("source"),
        F.coalesce(F.regexp_count(F.col(text_col), F.lit(_WORD)), F.lit(0)).cast("long").alias("size"),
        F.xxhash64(F.lit(seed), F.col(id_col), F.col(text_col)).alias("rnd"),
    ]
    rows = docs.select(*columns, *([F.struct("*").alias("row")] if keep_row else []))
    narrow = written(docs.select(*columns), "sizes")
    totals = [(r[0], int(r[1])) for r in narrow.groupBy("source").agg(F.sum("size")).toLocalIterator()]
    found = source_targets(totals, weights, share, stop)
    table = []
    for k, (source, size, target) in enumerate(found):
        want = min(round(target), int(stop * size))
        full = want // size if size else 0
        table.append((k, source, size, target, full, want - full * size, max(1, -(-size // block_words))))
    sources = spark.createDataFrame(table, "sidx int, s_source string, source_size long, target double, full long, part long, blocks long")
    deal = F.pmod(F.col("rnd"), F.col("blocks"))
    dealt = _with_sources(narrow, sources, len(table)).withColumn("block", deal)
    blocks = dealt.groupBy("sidx", "block", "full", "part", "blocks").agg(F.sum("size").alias("words"))
    # The permuted order is the order of a hash; its leading bits make chunks for two-level running sums.
    blocks = blocks.withColumn("order", F.xxhash64(F.lit(seed + 1), "sidx", "block")).withColumn("chunk", F.shiftright("order", 52))
    blocks = written(blocks, "blocks")
    chunks = blocks.groupBy("sidx", "chunk").agg(F.sum("words").alias("c_words"), F.count(F.lit(1)).alias("c_blocks"))
    before = Window.partitionBy("sidx").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    chunks = chunks.select(
        "sidx", "chunk", F.coalesce(F.sum("c_words").over(before), F.lit(0)).alias("w0"), F.coalesce(F.sum("c_blocks").over(before), F.lit(0)).alias("b0")
    )
    inside = Window.partitionBy("sidx", "chunk").orderBy("order", "block").rowsBetween(Window.unboundedPreceding, -1)
    placed = blocks.join(chunks, ["sidx", "chunk"]).select(
        "sidx", "block", "full", "part", "words",
        (F.col("w0") + F.coalesce(F.sum("words").over(inside), F.lit(0))).alias("start"),
        (F.col("b0") + F.count(F.lit(1)).over(inside)).alias("rank"),
    )
    placed = written(placed, "placed")
    # Exact quotas: all blocks once for each whole pass, and those that the part reaches.
    reached = F.sum((F.col("start") < F.col("part")).cast("long"))
    quota = {r[0]: (int(r[1]), int(r[2])) for r in placed.groupBy("sidx").agg(F.max("full") * F.count(F.lit(1)), reached).toLocalIterator()}
    quotas = [sum(quota.get(k, (0, 0))) for k in range(len(table))]
    shards = max(1, round(sum(t[3] for t in table) / shard_words))
    shares = shard_shares(spark, quotas, shards, seed)
    count = {k: v[0] // max(1, table[k][4]) for k, v in quota.items()}
    n_blocks = spark.createDataFrame([(k, v) for k, v in count.items()] or [(-1, 0)], "sidx int, n_blocks long")
    passes = F.explode(F.sequence(F.lit(0).cast("long"), F.col("full")))
    draws = placed.join(F.broadcast(n_blocks) if len(table) <= MAX_BROADCAST else n_blocks, "sidx").withColumn("pass", passes)
    draws = draws.withColumn("quota", F.when(F.col("pass") < F.col("full"), F.col("words")).otherwise(_clip(F.col("part") - F.col("start"), F.lit(0), F.col("words"))))
    draws = draws.where("pass < full or start < part").withColumn("draw", F.col("pass") * F.col("n_blocks") + F.col("rank"))
    drawn = draws.join(shares, ["sidx", "draw"]).groupBy("sidx", "block").agg(F.collect_list(F.struct("pass", "shard", "quota")).alias("drawn"))
    every = _with_sources(rows, sources, len(table)).withColumn("block", deal)
    in_block = Window.partitionBy("sidx", "block").orderBy("rnd", "id", "size").rowsBetween(Window.unboundedPreceding, -1)
    out = every.join(drawn, ["sidx", "block"], "left").withColumn("at", F.coalesce(F.sum("size").over(in_block), F.lit(0)))
    take = lambda d: F.struct(
        d["pass"].alias("pass"), d["shard"].alias("shard"), F.xxhash64(F.lit(seed + 2), d["pass"], "rnd").alias("place"),
        _clip(d["quota"] - F.col("at"), F.lit(0), F.col("size")).alias("words"),
    )
    made = F.filter(F.transform(F.coalesce("drawn", F.array().cast("array<struct<pass:bigint,shard:bigint,quota:bigint>>")), take), lambda d: d["words"] > 0)
    out = out.withColumn("draws", made).withColumn("taken", F.aggregate("draws", F.lit(0).cast("long"), lambda n, d: n + d["words"]))
    return out.select("id", "source", "size", "source_size", "target", "draws", "taken", *(["row"] if keep_row else []))


def mixed_documents(docs: DataFrame, text_col: str = "text", **options) -> DataFrame:
    """Rows of the mix with the columns of docs: one per draw, the cut one with its first words only."""
    planned = plan_mix(docs, text_col=text_col, keep_row=True, **options).select("row", "size", F.explode("draws").alias("draw"))
    shuffled = planned.repartition("draw.shard").sortWithinPartitions("draw.shard", "draw.place")
    text = F.col(f"row.{text_col}")
    cut = F.array_join(F.slice(F.regexp_extract_all(text, F.lit(_WORD), F.lit(0)), F.lit(1), F.col("draw.words").cast("int")), " ")
    whole = F.col("draw.words") == F.col("size")
    return shuffled.select(*[F.when(whole, text).otherwise(cut).alias(c) if c == text_col else F.col("row")[c].alias(c) for c in docs.columns])
