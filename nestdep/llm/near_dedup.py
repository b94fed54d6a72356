"""Near-duplicate documents by BagMinHash signatures of five-word shingle bags.

A document is a bag of shingles: five consecutive words, with multiplicity.
Each shingle owns Poisson processes over its weight axis, arranged in dyadic
shells (0,1], (1,2], (2,4], (4,8] ...; a shell's process has the shell's length
as its rate, and each point has a time, a signature position and a place on
the weight axis.  A bag of weight w sees the points placed at or below w.  A
signature position keeps the earliest point it sees, so two signatures agree in
a position with exactly the weighted Jaccard similarity.  Points are generated
in time order only up to a bound that fills all positions.

Bands of the signature give candidate buckets.  In bounded blocks of a bucket
the pairs of different components are ranked by how many positions agree, and
only the best pair that joins two components is put forward (a maximum spanning
forest), so a block gives fewer pairs than it has rows.  In a second pass the
buckets that still hold several components compare all pairs across them, this
time by the bags themselves inside the block.  Every pair put forward is
verified by its exact multiset overlap on the texts; a class is a component of
verified links.  A pair at similarity 0.8 shares no band, or agrees in too few
positions, with probability below 1e-4.

Rows are known by their id and a 64-bit hash of their text together, and bags by
a 128-bit hash; nodes (distinct bags) get numbers of their own when they are
written, so no two of them can meet by chance.

How it scales: documents with equal bags are one node from the start; first
blocks split a bucket by hash; later a bucket's largest component stays where it
is and only rows of other components visit its blocks; texts travel only for
candidates.

Defined cases: a null or blank text has no shingles and is a class of its own;
a text of one to four words is one shingle; a null id counts as larger than any
other id; rows that repeat id and text are one class; ties cannot occur, as
equal bags are equal nodes; an empty table gives an empty result; `drop_near_copies`
keeps all columns.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ._spark import bounded_batches, forget_frame, written
from ._text import Words, claim, fold, mix, slices, span_hash, trim_memory, words_of

SHINGLE = 5
SIMILARITY = 0.8
BANDS, ROWS = 30, 5
POSITIONS = BANDS * ROWS
#: Signatures that agree in fewer positions belong to pairs below the similarity, but for two in 10**5;
#: in the second pass, where bags decide, but for four in 10**8.
LEAST_AGREE, LEAST_AGREE_BAGS = 99, 92
CHUNK = 512
BROADCAST_KEYS = 400_000
#: Links up to this number are joined to components in one task; more in rounds of joins.
LOCAL_LINKS = 1_000_000
_U = np.uint64


def bags(words: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, shingle hash, multiplicity), sorted by document and hash."""
    counts, docs, total = words.counts, words.docs(), len(words.starts)
    if not total:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.int64)
    sums = fold(words.hashes())
    at = np.arange(max(0, total - SHINGLE + 1))
    at = at[docs[at] == docs[at + SHINGLE - 1]] if len(at) else at
    short = np.flatnonzero((counts > 0) & (counts < SHINGLE))
    begin = np.concatenate([at, words.first[short]])
    end = np.concatenate([at + SHINGLE, words.first[short] + counts[short]])
    return counted(docs[begin], span_hash(sums, begin, end))


def counted(docs: np.ndarray, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    order = np.lexsort((hashes, docs))
    docs, hashes = docs[order], hashes[order]
    edge = np.flatnonzero(np.concatenate([[True], (docs[1:] != docs[:-1]) | (hashes[1:] != hashes[:-1])])) if len(docs) else np.zeros(0, np.int64)
    return docs[edge], hashes[edge], np.diff(np.append(edge, len(docs)))


def _uniform(x: np.ndarray) -> np.ndarray:
    return ((x >> _U(11)).astype(np.float64) + 0.5) * 2.0**-53


def signatures(docs: np.ndarray, hashes: np.ndarray, weights: np.ndarray, n_docs: int, positions: int = POSITIONS) -> np.ndarray:
    """(n_docs, positions): identity of the earliest point of each position; 0 for empty bags."""
    out = np.zeros((n_docs, positions), dtype=np.uint64)
    size = np.bincount(docs, weights=weights, minlength=n_docs)
    # One stream for each shell that a bag reaches: shell 0 is (0, 1], shell k is (2^(k-1), 2^k].
    shells = np.ceil(np.log2(np.maximum(weights, 1))).astype(np.int64) + 1
    element = np.repeat(np.arange(len(docs)), shells)
    shell = np.arange(len(element)) - np.repeat(np.cumsum(shells) - shells, shells)
    rate = np.where(shell == 0, 1.0, 2.0 ** (shell - 1.0))
    low = np.where(shell == 0, 0.0, rate)
    seed = mix(hashes[element] ^ mix(shell.astype(np.uint64) + _U(0x51ED270B)))
    owner, weight = docs[element], weights[element].astype(np.float64)
    todo = size > 0
    bound = np.where(todo, positions * (np.log(positions) + 4) / np.maximum(size, 1), 0.0)
    while todo.any():
        live = np.flatnonzero(todo[owner])
        time = np.zeros(len(live))
        earliest = np.full(n_docs * positions, np.inf)
        ident = np.zeros(n_docs * positions, dtype=np.uint64)
        step = 0
        while len(live):
            point = mix(seed[live] + _U(0x9E3779B97F4A7C15 * (step + 1) % (1 << 64)))
            time = time - np.log(_uniform(point)) / rate[live]
            on = time <= bound[owner[live]]
            live, time, point = live[on], time[on], point[on]
            other = mix(point ^ _U(0x2545F4914F6CDD1D))
            place = low[live] + (_uniform(mix(other ^ _U(0x1B873593)))) * rate[live]
            seen = place <= weight[live]
            slot = owner[live[seen]] * positions + (other[seen] >> _U(32)).astype(np.int64) % positions
            t, p = time[seen], point[seen]
            np.minimum.at(earliest, slot, t)
            first = earliest[slot] == t
            ident[slot[first]] = p[first]
            step += 1
        full = np.isfinite(earliest.reshape(n_docs, positions)).all(axis=1)
        done = todo & full
        out[done] = ident.reshape(n_docs, positions)[done]
        todo &= ~full
        bound[todo] *= 2
    return out


def band_keys(sig: np.ndarray) -> np.ndarray:
    parts = sig.reshape(len(sig), BANDS, ROWS)
    key = np.broadcast_to(np.arange(BANDS, dtype=np.uint64), parts.shape[:2]).copy()
    for r in range(ROWS):
        key = mix(key * _U(0x9E3779B97F4A7C15) + parts[:, :, r])
    return key


def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    claim("near_dedup")
    for batch in batches:
        for part in slices(batch, "text"):
            n = part.num_rows
            docs, hashes, weights = bags(words_of(part.column("text")))
            sig = signatures(docs, hashes, weights, n)
            one, two = np.zeros(n, np.uint64), np.zeros(n, np.uint64)
            begin = np.searchsorted(docs, np.arange(n))
            some = np.flatnonzero(np.bincount(docs, minlength=n))
            if len(some):
                w = weights.astype(np.uint64)
                one[some] = np.add.reduceat(mix(hashes) * w, begin[some])
                two[some] = np.add.reduceat(mix(hashes ^ _U(0xABCDEF)) * w, begin[some])
            bands = pa.FixedSizeListArray.from_arrays(pa.array(band_keys(sig).ravel().view(np.int64)), BANDS).cast(pa.list_(pa.int64()))
            small = (sig & _U(0xFF)).astype(np.uint8)
            raw = pa.Array.from_buffers(pa.binary(POSITIONS), n, [None, pa.py_buffer(small.tobytes())]).cast(pa.binary())
            size = np.bincount(docs, weights=weights, minlength=n).astype(np.int64)
            yield pa.RecordBatch.from_arrays(
                [part.column("id"), part.column("hash"), pa.array(one.view(np.int64)), pa.array(two.view(np.int64)), pa.array(size), bands, raw],
                names=["id", "hash", "d1", "d2", "size", "bands", "sig"],
            )
    trim_memory()


def overlaps(left: pa.Array, right: pa.Array) -> np.ndarray:
    """Exact weighted Jaccard similarity of the shingle bags of each pair of texts."""
    n = len(left)
    a, b = bags(words_of(left)), bags(words_of(right))
    docs, hashes = np.concatenate([a[0], b[0]]), np.concatenate([a[1], b[1]])
    weight = np.concatenate([a[2], b[2]])
    order = np.lexsort((hashes, docs))
    docs, hashes, weight = docs[order], hashes[order], weight[order]
    twin = np.flatnonzero((docs[1:] == docs[:-1]) & (hashes[1:] == hashes[:-1])) if len(docs) else np.zeros(0, np.int64)
    both = np.bincount(docs[twin], weights=np.minimum(weight[twin], weight[twin + 1]), minlength=n)
    total = np.bincount(docs, weights=weight, minlength=n)
    return both / np.maximum(total - both, 1)


def _verify(similarity: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "left"):
                near = overlaps(part.column("left"), part.column("right"))
                hit = pa.array(np.flatnonzero(near >= similarity))
                yield pa.RecordBatch.from_arrays([part.column("a").take(hit), part.column("b").take(hit)], names=["a", "b"])
        trim_memory()

    return run


def _texts(base: DataFrame, nodes: DataFrame, keys: DataFrame) -> DataFrame:
    """key and text of the given nodes: their rows are broadcast to the scan up to a number, joined beyond it."""
    rows = written(nodes.select("key", F.col("id").alias("n_id"), F.col("hash").alias("n_hash")).join(keys, "key", "left_semi"), "keys")
    on = base["id"].eqNullSafe(rows["n_id"]) & (base["hash"] == rows["n_hash"])
    return base.select("id", "hash", "text").join(F.broadcast(rows) if rows.count() <= BROADCAST_KEYS else rows, on).select("key", "text")


def _linked(pairs: DataFrame, base: DataFrame, nodes: DataFrame, similarity: float) -> DataFrame:
    """Pairs (a, b) whose texts have the similarity."""
    text = _texts(base, nodes, pairs.select(F.explode(F.array("a", "b")).alias("key")).distinct())
    right = text.select(F.col("key").alias("b"), F.col("text").alias("right"))
    left = text.select(F.col("key").alias("a"), F.col("text").alias("left"))
    # The member's text first: the join on the leader is then skewed in bytes, which Spark can split.
    rows = pairs.select("a", "b").join(right, "b").join(left, "a")
    return written(rows.select("a", "b", "left", "right").mapInArrow(_verify(similarity), "a long, b long").distinct(), "links")


def _joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, root) of all edges of one task, root being the smallest node."""
    parts = [(b.column("a").to_numpy(), b.column("b").to_numpy()) for b in batches if b.num_rows]
    if parts:
        a, b = (np.concatenate(x) for x in zip(*parts))
        nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
        root = minimum_labels(at[: len(a)], at[len(a) :], len(nodes))
        for lo in range(0, len(nodes), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(nodes[lo : lo + 100_000]), pa.array(nodes[root[lo : lo + 100_000]])], names=["node", "root"])


def minimum_labels(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """Smallest node of each node's component, for edges between 0 .. n - 1."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[a], root[b])
        before = root.copy()
        np.minimum.at(root, root[a], low)
        np.minimum.at(root, root[b], low)
        while not np.array_equal(root, root[root]):
            root = root[root]
        if np.array_equal(root, before):
            return root


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of all nodes of the edges (a, b)."""
    return star_components(edges) if edges.count() > LOCAL_LINKS else edges.select("a", "b").coalesce(1).mapInArrow(_joined, "node long, root long")


def star_components(edges: DataFrame) -> DataFrame:
    """The same in rounds of joins, for any number of edges: large and small stars in turn until nothing moves."""

    def ranked(df: DataFrame) -> DataFrame:
        return df.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct()

    now, before = written(ranked(edges), "stars"), None
    while True:
        state = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(20,0)"))).first()
        if state == before or not state[0]:
            break
        before = state
        both = now.unionAll(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = written(ranked(both.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))), "stars")
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a")
        small = small.select(F.col("b").alias("a"), F.col("m").alias("b")).unionAll(least.select("a", F.col("m").alias("b")))
        last, now = now, written(ranked(small), "stars")
        forget_frame(last)
        forget_frame(large)
    roots = now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct()
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionAll(roots)


def forest(score: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Indices of a maximum spanning forest of scored edges between components (rounds of best edges)."""
    names, at = np.unique(np.concatenate([left, right]), return_inverse=True)
    a, b = at[: len(left)], at[len(left) :]
    order = np.lexsort((np.arange(len(score)), -score))
    rank = np.empty(len(score), np.int64)
    rank[order] = np.arange(len(score))
    label, live, out = np.arange(len(names)), np.arange(len(score)), []
    while True:
        live = live[label[a[live]] != label[b[live]]]
        if not len(live):
            return np.unique(np.concatenate(out)) if out else np.zeros(0, np.int64)
        best = np.full(len(names), len(score))
        np.minimum.at(best, label[a[live]], rank[live])
        np.minimum.at(best, label[b[live]], rank[live])
        taken = order[np.unique(best[best < len(score)])]
        out.append(taken)
        label = minimum_labels(label[a[taken]], label[b[taken]], len(label))[label]


class _Bags:
    """Bags of a block's rows, as sets of hashed (shingle, occurrence), with an index from hash to rows."""

    def __init__(self, bags_: list[bytes]) -> None:
        parts = [np.frombuffer(b, np.uint32) for b in bags_]
        self.size = np.array([len(p) for p in parts])
        self.parts = parts
        flat = np.concatenate(parts)
        order = np.argsort(flat, kind="stable")
        self.hash = flat[order]
        self.row = np.repeat(np.arange(len(parts)), self.size)[order]

    def similarity(self, r: int) -> np.ndarray:
        """Jaccard similarity of row r to every row."""
        own = self.parts[r]
        lo, hi = np.searchsorted(self.hash, own, "left"), np.searchsorted(self.hash, own, "right")
        n = hi - lo
        at = np.arange(int(n.sum())) + np.repeat(lo - (np.cumsum(n) - n), n)
        both = np.bincount(self.row[at], minlength=len(self.parts))
        return both / np.maximum(self.size + self.size[r] - both, 1)


def _put_forward(similarity: float | None):
    """A forest of candidate pairs of each block (rows sorted by band, part, visit).

    With a similarity, rows hold their bags and only pairs that reach it, by the bags, count.
    """

    def pairs(block: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        key, comp = block.column("key").to_numpy(), block.column("comp").to_numpy()
        if len(key) < 2 or (comp == comp[0]).all():
            return
        home, guest = (np.flatnonzero(block.column(c).to_numpy(zero_copy_only=False)) for c in ("home", "guest"))
        if not len(home) or not len(guest):
            return
        sig = np.frombuffer(b"".join(block.column("sig").to_pylist()), np.uint8).reshape(len(key), POSITIONS)
        own, both = sig[home], np.isin(key[home], key[guest])
        index, found = None, []
        for r in guest.tolist():
            ok = (comp[home] != comp[r]) & ~(both & (key[home] <= key[r]))
            other = home[ok]
            if not len(other):
                continue
            score = (own[ok] == sig[r]).sum(axis=1)
            good = score >= (LEAST_AGREE if similarity is None else LEAST_AGREE_BAGS)
            if similarity is not None and good.any():
                index = index or _Bags(block.column("bag").to_pylist())
                score = index.similarity(r)[other]
                good &= score >= similarity - 0.005  # 32-bit hashes may collide; texts decide
            if good.any():
                found.append((np.full(int(good.sum()), r), other[good], score[good]))
        if found:
            a, b, score = (np.concatenate(x) for x in zip(*found))
            keep = forest(score, comp[a], comp[b])
            a, b = a[keep], b[keep]
            yield pa.RecordBatch.from_arrays([pa.array(np.maximum(key[a], key[b])), pa.array(np.minimum(key[a], key[b]))], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None
        for batch in batches:
            if not batch.num_rows:
                continue
            table = pa.Table.from_batches([batch]) if held is None else pa.concat_tables([held, pa.Table.from_batches([batch])])
            whole = table.combine_chunks().to_batches()[0]
            band, part, visit = (whole.column(c).to_numpy() for c in ("band", "part", "visit"))
            cut = np.flatnonzero((band[1:] != band[:-1]) | (part[1:] != part[:-1]) | (visit[1:] != visit[:-1])) + 1
            at = 0
            for end in cut.tolist():
                if end - at > 1:
                    yield from pairs(whole.slice(at, end - at))
                at = end
            held = pa.Table.from_batches([whole.slice(at)])
        if held is not None:
            yield from pairs(held.combine_chunks().to_batches()[0])
        held = None
        trim_memory()

    return run


_BLOCK = ["band", "part", "visit", "key", "comp", "home", "guest", "sig"]


def _blocks(rows: DataFrame, similarity: float | None = None) -> DataFrame:
    placed = rows.select(*_BLOCK, *(["bag"] if similarity is not None else []))
    placed = placed.repartition("band", "part", "visit").sortWithinPartitions("band", "part", "visit")
    return placed.mapInArrow(_put_forward(similarity), "a long, b long").distinct()


def _first_pairs(bands: DataFrame, nodes: DataFrame) -> DataFrame:
    """A forest of each bucket, large buckets being split by a hash that differs from band to band."""
    # Written before it is joined back, so that the join can be split where a band is hot.
    size = written(bands.groupBy("band").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "sizes")
    rows = bands.join(size, "band").withColumn("part", F.pmod(F.xxhash64("key", "band"), F.ceil(F.col("n") / CHUNK)).cast("int"))
    rows = rows.join(nodes.select("key", "sig"), "key")
    return _blocks(rows.withColumns({"visit": F.lit(0), "comp": F.col("key"), "home": F.lit(True), "guest": F.lit(True)}))


def _bag_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for part in slices(batch, "text"):
            docs, hashes, weights = bags(words_of(part.column("text")))
            each = np.repeat(np.arange(len(docs)), weights)
            turn = np.arange(len(each)) - np.repeat(np.cumsum(weights) - weights, weights)
            flat = (mix(hashes[each] + _U(0x9E3779B97F4A7C15) * turn.astype(np.uint64)) >> _U(32)).astype(np.uint32)
            edge = np.searchsorted(docs[each], np.arange(part.num_rows + 1))
            bag = pa.array([flat[edge[i] : edge[i + 1]].tobytes() for i in range(part.num_rows)], pa.binary())
            yield pa.RecordBatch.from_arrays([part.column("key"), bag], names=["key", "bag"])


def _more_pairs(bands: DataFrame, nodes: DataFrame, comps: DataFrame, base: DataFrame, similarity: float) -> DataFrame:
    """Pairs that reach the similarity across components, in buckets of three or more that hold several."""
    named = bands.join(comps.select(F.col("node").alias("key"), "root"), "key", "left").withColumn("comp", F.coalesce("root", "key")).drop("root")
    kinds = named.groupBy("band", "comp").agg(F.count(F.lit(1)).alias("m"))
    mixed = kinds.groupBy("band").agg(F.sum("m").alias("n"), F.max(F.struct("m", "comp")).alias("most")).where("n > 2 and n > most.m")
    mixed = written(mixed, "mixed")
    chunks, visits = F.ceil(F.col("n") / CHUNK).cast("int"), F.ceil((F.col("n") - F.col("most.m")) / CHUNK).cast("int")
    rows = named.join(mixed.select("band", F.col("most.comp").alias("major"), chunks.alias("chunks"), visits.alias("visits")), "band")
    one, two = (F.pmod(F.xxhash64(F.lit(k), "key", "band"), F.col(c)).cast("int") for k, c in ((1, "chunks"), (2, "visits")))
    minor = F.col("comp") != F.col("major")
    rows = rows.withColumns({"own_part": one, "own_visit": two, "guest_": minor})
    # A home row stands in its part for all visits; a guest visits all parts. Where both are one row, it is one.
    home = F.transform(F.sequence(F.lit(0), F.col("visits") - 1), lambda v: F.struct(F.col("own_part").alias("part"), v.alias("visit")))
    guest = F.transform(F.sequence(F.lit(0), F.col("chunks") - 1), lambda p: F.struct(p.alias("part"), F.col("own_visit").alias("visit")))
    rows = rows.withColumn("at", F.explode(F.when(minor, F.array_union(home, guest)).otherwise(home)))
    rows = rows.select("band", "key", "comp", "at.part", "at.visit", (F.col("at.part") == F.col("own_part")).alias("home"), (F.col("guest_") & (F.col("at.visit") == F.col("own_visit"))).alias("guest"))
    rows = written(rows, "visits")
    text = _texts(base, nodes, rows.select("key").distinct())
    bag = text.mapInArrow(_bag_rows, "key long, bag binary").dropDuplicates(["key"])
    return _blocks(rows.join(nodes.select("key", "sig"), "key").join(bag, "key"), similarity)


def near_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", similarity: float = SIMILARITY) -> DataFrame:
    """(id, hash, class_id, class_size, stays): one row per input row; `stays` marks the class's smallest document (and rows that repeat it)."""
    bounded_batches(docs.sparkSession)
    base = docs.select(F.col(id_col).alias("id"), F.xxhash64(F.col(text_col)).alias("hash"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    kind = dict(base.dtypes)["id"]
    signed = written(base.mapInArrow(_sign, f"id {kind}, hash long, d1 long, d2 long, size long, bands array<long>, sig binary"), "signed")
    # Nulls last: a null id counts as larger than any other.
    row = F.struct(F.col("id").isNull().alias("none"), "id", "hash")
    bag = signed.where("size > 0").groupBy("d1", "d2").agg(F.min(row).alias("row"), F.any_value("bands").alias("bands"), F.any_value("sig").alias("sig"))
    nodes = written(bag.select(F.monotonically_increasing_id().alias("key"), "d1", "d2", "row.id", "row.hash", "bands", "sig"), "nodes")
    bands = nodes.select("key", F.explode("bands").alias("band"))
    pairs = written(_first_pairs(bands, nodes), "pairs")
    links = _linked(pairs, base, nodes, similarity)
    comps = written(components(links), "comps")
    more = written(_more_pairs(bands, nodes, comps, base, similarity), "pairs")
    if more.take(1):
        links = links.unionAll(_linked(more, base, nodes, similarity))
        first, comps = comps, written(components(links), "comps")
        forget_frame(first)
    for done in (pairs, more, links):
        forget_frame(done)
    named = nodes.select("d1", "d2", "key").join(comps, F.col("key") == F.col("node"), "left").select("d1", "d2", F.coalesce("root", "key").alias("root"))
    rows = signed.select("id", "hash", "d1", "d2", "size")
    # A text without shingles is a class of its own: its class is its row.
    nobody = F.lit(None).cast(signed.select(row.alias("row")).schema["row"].dataType)
    member = rows.where("size > 0").join(named, ["d1", "d2"]).select("id", "hash", F.struct("root", nobody.alias("row")).alias("class"))
    alone = rows.where("size = 0").select("id", "hash", F.struct(F.lit(None).cast("long").alias("root"), row.alias("row")).alias("class"))
    member = member.unionAll(alone)
    least = written(member.groupBy("class").agg(F.min(row).alias("first"), F.count(F.lit(1)).alias("class_size")), "least")
    out = member.join(least, "class")
    stays = F.col("id").eqNullSafe(F.col("first.id")) & (F.col("hash") == F.col("first.hash"))
    return out.select("id", "hash", F.col("first.id").alias("class_id"), "class_size", stays.alias("stays"))


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", similarity: float = SIMILARITY) -> DataFrame:
    """The rows, with all columns, of the smallest document of each class; of rows that repeat id and text one."""
    # One struct is the key of the join and of the window, so that texts are exchanged once; null ids are equal within it.
    kept = near_classes(docs, id_col, text_col, similarity).where("stays").select(F.struct("id", "hash").alias("_key")).distinct()
    kind = dict(kept.dtypes)["_key"]
    ident = F.struct(F.col(id_col).alias("id"), F.xxhash64(F.col(text_col)).alias("hash")).cast(kind)  # the same type, or the exchange is not shared
    row = docs.select(F.struct("*").alias("_row"), ident.alias("_key"))
    one = F.row_number().over(Window.partitionBy("_key").orderBy(F.lit(0)))
    out = row.join(kept, "_key", "left_semi").withColumn("_n", one).where("_n = 1")
    return out.select(*[F.col("_row")[c].alias(c) for c in docs.columns])
