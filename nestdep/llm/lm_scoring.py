"""Language-model scores by context-tree weighting over bytes, and a word baseline.

The model reads a text as lower-cased bytes and one end mark.  Each byte is
eight binary decisions.  For every context of 0 to `DEPTH` preceding bytes and
every decision there is a node with counts of both outcomes and their
Krichevsky-Trofimov probability; a node's weighted probability halves between
its own estimate and the product of its longer contexts.  The code length of a
text mixes the estimates of all depths by these weights.  A context that was
never seen predicts as the one above it.

How it scales: training counts (context, byte) strings, pre-aggregated in each
task, and these grow with the corpus; each depth is one grouped sum over the
next deeper one, and then one join with the depth above.  No node is left out:
strings counted often (at most `HEAD_STRINGS`) are looked up in the task, in a
shared file, not a driver object; all others are joined with the complete table
of strings, and those that were never counted with the nodes of every depth.

The baseline sums log10((c + 1) / (N + V + 1)) over words and one end token a
text.  Words counted often (at most `HEAD_WORDS`) are looked up in the task; all
other tokens are joined with the complete table of counts, so none is dropped.

Defined cases: a null text is empty and has the end token only; a null id is
not held out (the checksum of null is null); repeated rows get equal scores; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._spark import bounded_batches, give_back, scratch, written
from ._text import claim, lower_ascii, mix, slices, words_of
from .warc import _store

DEPTH = 5
HEAD_WORDS = 1 << 19
HEAD_STRINGS = 1 << 21
_END = 0xFF  # never a byte of UTF-8
_END_TOKEN = 0x0123456789ABCDEF  # stands for the end token among hashes of words
_CACHE = 1 << 21


def held_out(id_col: Column) -> Column:
    return F.coalesce(F.crc32(id_col.cast("string").cast("binary")) % 7 == 2, F.lit(False))


# -- counting ---------------------------------------------------------------


def strings_of(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Every byte with its DEPTH predecessors as one number, and its document; texts end in a mark."""
    n, size = len(offsets) - 1, np.diff(offsets)
    begin = offsets[:-1] + np.arange(n) * (DEPTH + 1)
    stream = np.full(len(raw) + n * (DEPTH + 1), _END, dtype=np.uint8)
    doc = np.repeat(np.arange(n), size)
    stream[np.arange(len(raw)) + (doc + 1) * (DEPTH + 1) - 1] = raw
    total = len(stream)
    packed = np.zeros(max(0, total - DEPTH), dtype=np.uint64)
    for k in range(DEPTH + 1):
        packed <<= np.uint64(8)
        packed |= stream[k : total - DEPTH + k]
    where = np.repeat(begin, size + 1) + np.arange(int((size + 1).sum())) - np.repeat(np.cumsum(size + 1) - (size + 1), size + 1)
    return packed[where], np.repeat(np.arange(n), size + 1)


def _summed(keys: np.ndarray, n: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    if n is None:
        keys = np.sort(keys)
    else:
        order = np.argsort(keys, kind="stable")
        keys, n = keys[order], n[order]
    edge = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
    if n is None:
        return keys[edge], np.diff(np.append(edge, len(keys)))
    return keys[edge], np.add.reduceat(n, edge) if len(edge) else n


class _Counter:
    """Sums of counts by key, merged now and then so that memory follows the distinct keys of the task."""

    def __init__(self, kind: int) -> None:
        self.kind, self.parts, self.size = kind, [], 0

    def add(self, keys: np.ndarray) -> Iterator[pa.RecordBatch]:
        self.parts.append(_summed(keys))
        self.size += len(self.parts[-1][0])
        if self.size > 4_000_000:
            self.parts = [_summed(*map(np.concatenate, zip(*self.parts)))]
            self.size = len(self.parts[0][0])
            if self.size > 3_000_000:
                yield from self.flush()

    def flush(self) -> Iterator[pa.RecordBatch]:
        if self.parts:
            keys, n = _summed(*map(np.concatenate, zip(*self.parts)))
            self.parts, self.size = [], 0
            for lo in range(0, len(keys), 500_000):
                k = keys[lo : lo + 500_000].view(np.int64)
                kind = pa.array(np.full(len(k), self.kind, np.int32))
                yield pa.RecordBatch.from_arrays([kind, pa.array(k), pa.array(n[lo : lo + 500_000].astype(np.int64))], names=["kind", "key", "n"])


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    strings, tokens = _Counter(0), _Counter(1)
    for batch in batches:
        for part in slices(batch, "text", 4 << 20):
            words = words_of(part.column("text"))
            yield from strings.add(strings_of(lower_ascii(words.raw), words.offsets)[0])
            ends = np.full(part.num_rows, _END_TOKEN, dtype=np.uint64)
            yield from tokens.add(np.concatenate([words.hashes(lower=True), ends]))
    yield from strings.flush()
    yield from tokens.flush()


def _log_gamma(x: np.ndarray) -> np.ndarray:
    """Stirling's series after eight steps of the recurrence."""
    shift = np.zeros_like(x)
    for _ in range(8):
        shift += np.log(x)
        x = x + 1
    return (x - 0.5) * np.log(x) - x + 0.5 * np.log(2 * np.pi) + 1 / (12 * x) - 1 / (360 * x**3) + 1 / (1260 * x**5) - shift


def kt_log(n0: np.ndarray, n1: np.ndarray) -> np.ndarray:
    """Log of the Krichevsky-Trofimov probability of a sequence with these counts."""
    return _log_gamma(n0 + 0.5) + _log_gamma(n1 + 0.5) - _log_gamma(n0 + n1 + 1.0) - np.log(np.pi)


def _kt_arrow(n0: pa.Array, n1: pa.Array) -> pa.Array:
    return pa.array(kt_log(n0.to_numpy(zero_copy_only=False).astype(float), n1.to_numpy(zero_copy_only=False).astype(float)))


def _kt(n0: str, n1: str) -> Column:
    return F.arrow_udf(_kt_arrow, "double")(F.col(n0), F.col(n1))


def tree_levels(strings: DataFrame) -> list[DataFrame]:
    """Nodes by depth, deepest first: key = context << 8 | marked bit prefix; n0, n1, stop, log_w."""
    bits = F.explode(F.array(*[F.struct(F.lit(j).alias("j")) for j in range(8)]))
    one = strings.select("key", "n", bits.alias("b"))
    context = F.shiftrightunsigned("key", 8)
    prefix = F.expr("cast(shiftright(256 | (key & 255), 8 - b.j) as bigint)")
    bit = F.expr("shiftright(key & 255, 7 - b.j) & 1")
    node = F.shiftleft(context, 8).bitwiseOR(prefix)
    deep = one.groupBy(node.alias("node")).agg(F.sum(F.when(bit == 0, F.col("n")).otherwise(0)).alias("n0"), F.sum(F.when(bit == 1, F.col("n")).otherwise(0)).alias("n1"))
    deep = deep.withColumn("log_w", _kt("n0", "n1")).withColumn("stop", F.lit(1.0))
    levels = [written(deep, "tree")]
    for d in range(DEPTH - 1, -1, -1):
        mask = (1 << 8 * d) - 1
        parent = F.shiftleft(F.shiftrightunsigned("node", 8).bitwiseAND(F.lit(mask)), 8).bitwiseOR(F.col("node").bitwiseAND(F.lit(255)))
        up = levels[-1].groupBy(parent.alias("node")).agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1"), F.sum("log_w").alias("below"))
        up = up.withColumn("own", _kt("n0", "n1"))
        high = F.greatest("own", "below")
        both = high + F.log(F.exp(F.col("own") - high) + F.exp(F.col("below") - high)) - F.log(F.lit(2.0))
        up = up.withColumn("log_w", both).withColumn("stop", F.exp(F.col("own") - F.log(F.lit(2.0)) - F.col("log_w")))
        levels.append(written(up.select("node", "n0", "n1", "log_w", "stop"), "tree"))
    return levels


def _cut(node: str, depth: int) -> Column:
    """The node of the last `depth` bytes of a node's context, same bit prefix."""
    return F.shiftleft(F.shiftrightunsigned(node, 8).bitwiseAND(F.lit((1 << 8 * depth) - 1)), 8).bitwiseOR(F.col(node).bitwiseAND(F.lit(255)))


def _few(nodes: DataFrame, depth: int) -> DataFrame:
    """Depths 0 and 1 have 65,535 nodes at most, each with many children."""
    return F.broadcast(nodes) if depth <= 1 else nodes


def mixed_levels(levels: list[DataFrame]) -> list[DataFrame]:
    """Nodes by depth, deepest first: node and prob, the mixed probability of a one where it is the deepest node."""
    one = (F.col("n1") + 0.5) / (F.col("n0") + F.col("n1") + 1.0)
    stop = F.least("stop", F.lit(1.0))
    out: list[DataFrame] = []
    for d, level in enumerate(reversed(levels)):
        rows = level.select("node", one.alias("one"), stop.alias("stop"))
        if out:
            above = out[-1].select(F.col("node").alias("up"), F.col("acc").alias("acc0"), F.col("left").alias("left0"))
            rows = rows.withColumn("up", _cut("node", d - 1)).join(_few(above, d - 1), "up")
        else:
            rows = rows.withColumns({"acc0": F.lit(0.0), "left0": F.lit(1.0)})
        rows = rows.withColumns({"acc": F.expr("acc0 + left0 * stop * one"), "left": F.expr("left0 * (1 - stop)")})
        out.append(written(rows.select("node", "acc", "left", F.expr("acc + left * one").alias("prob")), "mixed"))
    return [x.select("node", "prob") for x in reversed(out)]


def string_values(strings: DataFrame, mixed: list[DataFrame]) -> DataFrame:
    """key and value, the log10 of the mixed probability of each (context, byte) string; keys are distinct.

    Each of a string's eight nodes is looked up in the given depths, deepest first.
    """
    bits = F.explode(F.array(*[F.struct(F.lit(j).alias("j")) for j in range(8)]))
    prefix = F.expr("cast(shiftright(256 | (key & 255), 8 - b.j) as bigint)")
    node = F.shiftleft(F.shiftrightunsigned("key", 8), 8).bitwiseOR(prefix)
    rows = strings.select("key", bits.alias("b")).select("key", node.alias("node"), F.expr("shiftright(key & 255, 7 - b.j) & 1").alias("bit"))
    for k, level in enumerate(mixed):
        d = DEPTH - k
        rows = rows.withColumn("at", _cut("node", d)).join(_few(level.select(F.col("node").alias("at"), F.col("prob").alias(f"p{d}")), d), "at", "left").drop("at")
    prob = F.coalesce(*[f"p{DEPTH - k}" for k in range(len(mixed))], F.lit(0.5))
    return rows.groupBy("key").agg(F.sum(F.log10(F.when(F.col("bit") == 1, prob).otherwise(1 - prob))).alias("value"))


def _least_class(counted: DataFrame, room: int) -> int:
    """Keys of at least this count class (eighths of a power of two) are no more than room."""
    sizes = sorted(((r[0], r[1]) for r in counted.groupBy(F.expr(_CLASS).alias("c")).count().toLocalIterator()), reverse=True)
    least = 1 << 20
    for c, n in sizes:
        if n > room:
            break
        room, least = room - n, c
    return least


_CLASS = "cast(floor(log2(n) * 8) as int)"


# -- scoring ----------------------------------------------------------------


class Head:
    """The values of the strings counted most in memory, and a cache of strings looked up."""

    def __init__(self, path: str) -> None:
        fs, where = _store(path)
        keys, values = [np.zeros(0, np.uint64)], [np.zeros(0)]
        for name in sorted(f.path for f in fs.get_file_info(_selector(where)) if f.path.endswith(".parquet")):
            with fs.open_input_file(name) as file:
                for batch in pq.ParquetFile(file).iter_batches(batch_size=1 << 18):
                    keys.append(batch.column("key").to_numpy().view(np.uint64))
                    values.append(batch.column("value").to_numpy())
        key, value = np.concatenate(keys), np.concatenate(values)
        order = np.argsort(key)
        self.key, self.value = key[order], value[order]
        self.keys = np.full(_CACHE, np.uint64(0xFFFFFFFFFFFFFFFF))
        self.known = np.zeros(_CACHE)

    def log10_of(self, strings: np.ndarray) -> np.ndarray:
        """The value of each string; NaN for those that are not in the head."""
        at = (mix(strings) >> np.uint64(20)).astype(np.int64) & (_CACHE - 1)
        out = self.known[at]
        miss = np.flatnonzero(self.keys[at] != strings)
        if len(miss):
            new, back = np.unique(strings[miss], return_inverse=True)
            value = np.full(len(new), np.nan)
            if len(self.key):
                found = np.minimum(np.searchsorted(self.key, new), len(self.key) - 1)
                hit = self.key[found] == new
                value[hit] = self.value[found[hit]]
            out[miss] = value[back]
            place = (mix(new) >> np.uint64(20)).astype(np.int64) & (_CACHE - 1)
            # Of strings that share a place the last one stays in both arrays.
            self.keys[place], self.known[place] = new, value
        return out


def _selector(path: str):
    import pyarrow.fs as pafs

    return pafs.FileSelector(path)


_HEADS: dict[str, Head] = {}


def loaded(path: str) -> Head:
    if path not in _HEADS:
        _HEADS.clear()
        _HEADS[path] = Head(path)
    return _HEADS[path]


class Model:
    """What training leaves: nodes by depth, strings' values, the path of the frequent ones, token counts, the frequent ones, N and V."""

    def __init__(self, mixed: list[DataFrame], values: DataFrame, often: str, tokens: DataFrame, head: tuple[np.ndarray, np.ndarray], total: int, distinct: int) -> None:
        self.mixed, self.values, self.often = mixed, values, often
        self.tokens, self.head, self.total, self.distinct = tokens, head, total, distinct


def train(docs: DataFrame, text_col: str = "text") -> Model:
    """Count all texts of docs and build the model."""
    bounded_batches(docs.sparkSession)
    text = docs.select(F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    counts = written(text.mapInArrow(_count, "kind int, key long, n long").groupBy("kind", "key").agg(F.sum("n").alias("n")), "counts")
    tokens = counts.where("kind = 1").select("key", "n")
    strings = counts.where("kind = 0").select("key", "n")
    mixed = mixed_levels(tree_levels(strings))
    # All nodes of a counted string are there at full depth.
    values = written(string_values(strings, mixed[:1]), "values")
    often = scratch(docs.sparkSession, "often")
    frequent = strings.where(F.expr(_CLASS) >= _least_class(strings, HEAD_STRINGS)).select("key")
    values.join(frequent, "key").write.parquet(often)
    total, distinct = tokens.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1))).first()
    head = tokens.where(F.expr(_CLASS) >= _least_class(tokens, HEAD_WORDS)).toArrow().sort_by("key")
    keys, n = (head.column(c).to_numpy() for c in ("key", "n"))
    return Model(mixed, values, often, tokens, (keys, n), int(total), int(distinct))


def _per_document(keys: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (key, document) pairs and how often each occurs."""
    order = np.lexsort((keys, doc))
    keys, doc = keys[order], doc[order]
    edge = np.flatnonzero(np.concatenate([[True], (keys[1:] != keys[:-1]) | (doc[1:] != doc[:-1])])) if len(keys) else np.zeros(0, np.int64)
    return keys[edge], doc[edge], np.diff(np.append(edge, len(keys)))


def score_texts(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, held_out, n_tokens, n_known, train_tokens, base_score, score, bits_per_byte of each document."""
    bounded_batches(docs.sparkSession)
    give_back(docs.sparkSession)  # training leaves large heaps, scoring needs room for workers
    often, total, distinct = model.often, model.total, model.distinct
    shared = docs.sparkSession.sparkContext.broadcast(model.head)
    room = np.log10(total + distinct + 1.0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("lm", _HEADS.clear)
        keys, times = shared.value
        for batch in batches:
            model = loaded(often)
            for part in slices(batch, "text"):
                n = part.num_rows
                words = words_of(part.column("text"))
                strings, doc = strings_of(lower_ascii(words.raw), words.offsets)
                value = model.log10_of(strings)
                other = np.isnan(value)
                score = np.bincount(doc, weights=np.where(other, 0.0, value), minlength=n).astype(float)
                token = np.concatenate([words.hashes(lower=True), np.full(n, _END_TOKEN, np.uint64)]).view(np.int64)
                token_doc = np.concatenate([words.docs(), np.arange(n)])
                at = np.searchsorted(keys, token)
                at[at == len(keys)] = 0
                hit = keys[at] == token if len(keys) else np.zeros(len(token), bool)
                base = np.bincount(token_doc[hit], weights=np.log10(times[at[hit]] + 1.0) - room, minlength=n).astype(float) if len(keys) else np.zeros(n)
                known = np.bincount(token_doc[hit], minlength=n)
                size = np.diff(words.offsets)
                key, ids = part.column("key"), part.column("id")
                none = lambda kind, k: pa.nulls(k, kind)
                yield pa.RecordBatch.from_arrays(
                    [ids, key, pa.array(words.counts + 1), pa.array(known.astype(np.int64)), pa.array(base), pa.array(score), pa.array(size.astype(np.int64)), *[none(t, n) for t in (pa.int32(), pa.int64(), pa.int64())]],
                    names=_NAMES,
                )
                for kind, rare, rare_doc in ((0, strings[other].view(np.int64), doc[other]), (1, token[~hit], token_doc[~hit])):
                    rare, rare_doc, occurs = _per_document(rare, rare_doc)
                    if m := len(rare):
                        yield pa.RecordBatch.from_arrays(
                            [none(ids.type, m), key.take(pa.array(rare_doc)), *[none(t, m) for t in (pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.int64())], pa.array(np.full(m, kind, np.int32)), pa.array(rare), pa.array(occurs)],
                            names=_NAMES,
                        )

    # Two hashes of id and text make a row known: what is rare in it comes back by this key.
    ident = F.struct(F.xxhash64(F.col(id_col), F.col(text_col)).alias("a"), F.xxhash64(F.col(text_col), F.col(id_col), F.lit(1)).alias("b"))
    base = docs.select(F.col(id_col).alias("id"), ident.alias("key"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    schema = f"id {dict(base.dtypes)['id']}, key struct<a:long,b:long>, n_tokens long, known long, base double, score double, bytes long, kind int, token long, times long"
    out = written(base.mapInArrow(run, schema), "scores")
    rows = out.where("n_tokens is not null").drop("kind", "token", "times")
    copies = rows.groupBy("key").agg(F.count(F.lit(1)).alias("copies"))
    rare = out.where("kind = 1").select("key", "token", "times")
    met = rare.join(model.tokens.select(F.col("key").alias("token"), "n"), "token", "left")
    value = F.log10(F.coalesce("n", F.lit(0)) + 1.0) - F.lit(float(room))
    sums = met.groupBy("key").agg(F.sum(F.col("times") * value).alias("r_base"), F.sum(F.when(F.col("n").isNotNull(), F.col("times")).otherwise(0)).alias("r_known"))
    # Rows that repeat id and text share a key, and each gave its rare tokens and strings.
    sums = sums.join(copies, "key").select("key", (F.col("r_base") / F.col("copies")).alias("r_base"), (F.col("r_known") / F.col("copies")).cast("long").alias("r_known"))
    other = out.where("kind = 0").select("key", "token", "times")
    met = written(other.select("token").distinct().join(model.values.withColumnRenamed("key", "token"), "token", "left"), "met")
    new = string_values(met.where("value is null").select(F.col("token").alias("key")), model.mixed)
    priced = met.where("value is not null").unionByName(new.withColumnRenamed("key", "token"))
    scores = other.join(priced, "token").groupBy("key").agg(F.sum(F.col("times") * F.col("value")).alias("r_score"))
    scores = scores.join(copies, "key").select("key", (F.col("r_score") / F.col("copies")).alias("r_score"))
    rows = rows.join(scores, "key", "left").withColumn("score", F.col("score") + F.coalesce("r_score", F.lit(0.0)))
    done = rows.join(sums, "key", "left").select(
        F.col("id").alias(id_col),
        held_out(F.col("id")).alias("held_out"),
        "n_tokens",
        (F.col("known") + F.coalesce("r_known", F.lit(0))).alias("n_known"),
        F.lit(total).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("r_base", F.lit(0.0))).alias("base_score"),
        "score",
        (-F.col("score") * F.lit(float(np.log2(10))) / (F.col("bytes") + 1)).alias("bits_per_byte"),
    )
    return done


_NAMES = ["id", "key", "n_tokens", "known", "base", "score", "bytes", "kind", "token", "times"]
