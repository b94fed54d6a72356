"""Toxicity scores by a bidirectional gated recurrent network with attention pooling.

A word enters as two vectors: one looked up by the hash of the word, one the
mean over its character n-grams (with word borders), so inflected and unseen
forms share what their stems teach.  A forward and a backward recurrent layer
read a window of words, attention pools their states, and a linear layer gives
the window's score.  All overlapping windows of the whole text are scored, one
starting every `STRIDE` words and `WINDOW` words long; the document's score is the largest, calibrated on the training sample.

The network is trained here in numpy, in one task, on at most
`SAMPLE_PER_CLASS` labelled documents of each class (those with the smallest
hash of their id).  The first coordinate of each embedding starts from the log
odds of its bucket in that sample.  Only the text is an input of a score.

Defined cases: a null or empty text has no words and gets the score of an
empty window; repeated rows get equal scores; texts are never cut, very long
ones have many windows; without labels of both classes all scores are 0; an
empty table gives an empty result; a null id is not held out; other columns are ignored by
`score_toxicity` and kept by `drop_toxic`.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._spark import bounded_batches
from ._text import Words, claim, fold, lower_ascii, mix, slices, span_hash, trim_memory, words_of

SAMPLE_PER_CLASS = 1_500
THRESHOLD = 0.7
WINDOW, STRIDE = 48, 24
BUCKETS, WORD_DIMS, CHAR_DIMS, HIDDEN, ATTEND = 1 << 15, 6, 10, 8, 8
_GRAMS = (3, 4, 5)


def _tanh(x: np.ndarray) -> np.ndarray:
    return np.tanh(x, out=x)


def _sigmoid(x: np.ndarray) -> np.ndarray:
    x *= 0.5
    np.tanh(x, out=x)
    x += 1
    x *= 0.5
    return x


class Inputs:
    """Distinct words of a slice as buckets: one for the word, several for its n-grams."""

    def __init__(self, words: Words) -> None:
        raw = lower_ascii(words.raw)
        sums = fold(raw.astype(np.uint64) + np.uint64(1))
        hashes = span_hash(sums, words.starts, words.ends)
        _, where, back = np.unique(hashes, return_index=True, return_inverse=True)
        self.of_token = back.astype(np.int32)
        start, end = words.starts[where], words.ends[where]
        self.word = (hashes[where] >> np.uint64(40)).astype(np.int64) % BUCKETS
        n, size = len(where), end - start
        rows, grams = [], []
        # Bordered forms: a mark stands before the first and after the last byte.
        for g in _GRAMS:
            for before, after, inner in ((0, 0, g), (1, 0, g - 1), (0, 1, g - 1), (1, 1, g - 2)):
                if before + after == 0:
                    count = np.maximum(size - inner + 1, 0)
                elif before + after == 1:
                    count = (size >= inner).astype(np.int64)
                else:
                    count = (size == inner).astype(np.int64)
                row = np.repeat(np.arange(n), count)
                step = np.arange(int(count.sum())) - np.repeat(np.cumsum(count) - count, count)
                first = end[row] - inner if after and not before else start[row] + step
                code = span_hash(sums, first, first + inner) ^ np.uint64(before + 2 * after)
                rows.append(row)
                grams.append(((mix(code) >> np.uint64(40)) % np.uint64(BUCKETS)).astype(np.int32))
        row, gram = np.concatenate(rows), np.concatenate(grams)
        order = np.argsort(row, kind="stable")
        self.gram = gram[order]
        self.count = np.bincount(row, minlength=n)
        self.begin = np.concatenate([[0], np.cumsum(self.count)])


def windows_of(words: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, first word, length) of all overlapping windows; each document has one at least."""
    n = words.counts
    count = np.maximum(1, -(-np.maximum(n - WINDOW, 0) // STRIDE) + 1)
    doc = np.repeat(np.arange(len(n)), count)
    k = np.arange(len(doc)) - np.repeat(np.cumsum(count) - count, count)
    at = np.minimum(k * STRIDE, np.maximum(n[doc] - WINDOW, 0))
    return doc, words.first[doc] + at, np.minimum(n[doc] - at, WINDOW)


class Network:
    """Parameters, forward pass and gradients."""

    def __init__(self, seed: int = 3) -> None:
        rng = np.random.default_rng(seed)
        f = np.float32
        d = WORD_DIMS + CHAR_DIMS
        self.p = {
            "word": rng.normal(scale=0.05, size=(BUCKETS, WORD_DIMS)).astype(f),
            "char": rng.normal(scale=0.05, size=(BUCKETS, CHAR_DIMS)).astype(f),
            "A": rng.normal(scale=0.4, size=(2 * HIDDEN, ATTEND)).astype(f),
            "a": np.zeros(ATTEND, f),
            "v": rng.normal(scale=0.4, size=ATTEND).astype(f),
            "o": rng.normal(scale=0.3, size=2 * HIDDEN).astype(f),
            "c": np.zeros(1, f),
        }
        for side in "fb":
            self.p["W" + side] = rng.normal(scale=0.3, size=(d, 3 * HIDDEN)).astype(f)
            self.p["U" + side] = rng.normal(scale=0.3, size=(HIDDEN, 3 * HIDDEN)).astype(f)
            self.p["B" + side] = np.zeros(3 * HIDDEN, f)
        self.scale, self.shift = 1.0, 0.0

    def embed(self, x: Inputs) -> np.ndarray:
        sums = np.zeros((len(x.word), CHAR_DIMS), np.float32)
        for lo in range(0, len(x.word), 4096):  # some words at a time: their n-grams are many
            some = lo + np.flatnonzero(x.count[lo : lo + 4096])
            if len(some):
                own = self.p["char"][x.gram[x.begin[some[0]] : x.begin[some[-1] + 1]]]
                sums[some] = np.add.reduceat(own, x.begin[some] - x.begin[some[0]], axis=0) / x.count[some, None]
        return np.concatenate([self.p["word"][x.word], sums], axis=1)

    def gates(self, embedded: np.ndarray, side: str) -> np.ndarray:
        return embedded @ self.p["W" + side] + self.p["B" + side]

    def states(self, gates: np.ndarray, tokens: np.ndarray, mask: np.ndarray, side: str, keep: list | None = None) -> np.ndarray:
        """(T, B, HIDDEN) states of one direction. gates: rows of distinct words; tokens, mask: (T, B)."""
        steps, batch = tokens.shape
        U, H = self.p["U" + side], HIDDEN
        out = np.empty((steps, batch, H), np.float32)
        h = np.zeros((batch, H), np.float32)
        full = mask.all(axis=1)
        for t in range(steps) if side == "f" else range(steps - 1, -1, -1):
            g = gates[tokens[t]]
            u = h @ U
            zr = _sigmoid(g[:, : 2 * H] + u[:, : 2 * H])
            z, r = zr[:, :H], zr[:, H:]
            n = _tanh(g[:, 2 * H :] + r * u[:, 2 * H :])
            if keep is not None:
                keep.append((t, h, z, r, n, u[:, 2 * H :]))
            step = z * (n - h)
            if not full[t]:
                step *= mask[t][:, None]
            h = h + step
            out[t] = h
        return out

    def pool(self, states: np.ndarray, mask: np.ndarray):
        """Attention over (T, B, 2H): weights, context, logit."""
        inner = _tanh(states @ self.p["A"] + self.p["a"])
        e = inner @ self.p["v"]
        e = np.where(mask, e, -1e9)
        e = np.exp(e - e.max(axis=0))
        e *= mask
        weight = e / np.maximum(e.sum(axis=0), 1e-9)
        context = np.einsum("tb,tbh->bh", weight, states)
        return inner, weight, context, context @ self.p["o"] + self.p["c"][0]

    def logits(self, x: Inputs, first: np.ndarray, size: np.ndarray, chunk: int = 1024) -> np.ndarray:
        if not len(x.word):  # empty windows only: nothing to attend to
            return np.full(len(first), self.p["c"][0], np.float32)
        embedded = self.embed(x)
        gf, gb = self.gates(embedded, "f"), self.gates(embedded, "b")
        out = np.empty(len(first), np.float32)
        for lo in range(0, len(first), chunk):
            tokens, mask = self.layout(x, first[lo : lo + chunk], size[lo : lo + chunk])
            both = np.concatenate([self.states(gf, tokens, mask, "f"), self.states(gb, tokens, mask, "b")], axis=2)
            out[lo : lo + chunk] = self.pool(both, mask)[3]
        return out

    @staticmethod
    def layout(x: Inputs, first: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        steps = max(1, int(size.max(initial=0)))
        at = np.arange(steps)[:, None]
        mask = at < size[None]
        if not len(x.of_token):
            return np.zeros((steps, len(first)), np.int64), mask
        return np.where(mask, x.of_token[np.minimum(first[None] + at, len(x.of_token) - 1)], 0), mask

    def gradients(self, x: Inputs, first: np.ndarray, size: np.ndarray, y: np.ndarray, w: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Weighted logistic loss of windows and its gradients."""
        p, H = self.p, HIDDEN
        tokens, mask = self.layout(x, first, size)
        used, local = np.unique(tokens, return_inverse=True)
        local = local.reshape(tokens.shape)
        part = _Part(x, used)
        embedded = self.embed(part)
        kept: dict[str, list] = {"f": [], "b": []}
        sides = [self.states(self.gates(embedded, s), local, mask, s, kept[s]) for s in "fb"]
        states = np.concatenate(sides, axis=2)
        inner, weight, context, logit = self.pool(states, mask)
        prob = 1 / (1 + np.exp(-logit.astype(np.float64)))
        loss = float(-(w * (y * np.log(prob + 1e-12) + (1 - y) * np.log(1 - prob + 1e-12))).sum() / w.sum())
        d = ((prob - y) * w / w.sum()).astype(np.float32)
        g = {k: np.zeros_like(v) for k, v in p.items()}
        g["c"][0] = d.sum()
        g["o"] = context.T @ d
        d_context = d[:, None] * p["o"]
        d_weight = np.einsum("tbh,bh->tb", states, d_context)
        d_states = weight[:, :, None] * d_context[None]
        d_e = weight * (d_weight - (weight * d_weight).sum(axis=0))
        g["v"] = np.einsum("tb,tbk->k", d_e, inner)
        d_inner = d_e[:, :, None] * p["v"] * (1 - inner**2)
        g["A"] = np.einsum("tbh,tbk->hk", states, d_inner, optimize=True)
        g["a"] = d_inner.sum(axis=(0, 1))
        d_states += d_inner @ p["A"].T
        d_embedded = np.zeros_like(embedded)
        for k, side in enumerate("fb"):
            U, dh = p["U" + side], np.zeros((len(first), H), np.float32)
            d_gates = np.zeros((len(used), 3 * H), np.float32)
            for t, h, z, r, n, un in reversed(kept[side]):
                dh = dh + d_states[t, :, k * H : (k + 1) * H]
                m = mask[t][:, None]
                dz, dn = dh * m * (n - h), dh * m * z
                dn *= 1 - n * n
                dr = dn * un
                pre = np.concatenate([dz * z * (1 - z), dr * r * (1 - r), dn], axis=1)
                through = pre.copy()
                through[:, 2 * H :] *= r
                g["U" + side] += h.T @ through
                dh = dh * (1 - m * z) + through @ U.T
                order = np.argsort(local[t], kind="stable")
                ids = local[t][order]
                edge = np.flatnonzero(np.concatenate([[True], ids[1:] != ids[:-1]]))
                d_gates[ids[edge]] += np.add.reduceat(pre[order], edge, axis=0)
            g["W" + side] = embedded.T @ d_gates
            g["B" + side] = d_gates.sum(axis=0)
            d_embedded += d_gates @ p["W" + side].T
        for c in range(WORD_DIMS):
            g["word"][:, c] = np.bincount(part.word, weights=d_embedded[:, c], minlength=BUCKETS)
        share = np.repeat(d_embedded[:, WORD_DIMS:] / np.maximum(part.count, 1)[:, None], part.count, axis=0)
        for c in range(CHAR_DIMS):
            g["char"][:, c] = np.bincount(part.gram, weights=share[:, c], minlength=BUCKETS)
        return loss, g


class _Part:
    """The chosen distinct words of an Inputs."""

    def __init__(self, x: Inputs, used: np.ndarray) -> None:
        if not len(x.word):
            self.word = np.zeros(len(used), np.int64)
            self.count = np.zeros(len(used), np.int64)
            self.gram = np.zeros(0, np.int64)
        else:
            self.word, self.count = x.word[used], x.count[used]
            start = np.repeat(x.begin[:-1][used] - (np.cumsum(self.count) - self.count), self.count)
            self.gram = x.gram[np.arange(int(self.count.sum())) + start]
        self.begin = np.concatenate([[0], np.cumsum(self.count)])


def _bucket_counts(doc: np.ndarray, bucket: np.ndarray, y: np.ndarray) -> np.ndarray:
    """(2, BUCKETS): documents of each class that have a bucket."""
    pair = np.unique(doc.astype(np.int64) * BUCKETS + bucket)
    d, b = pair // BUCKETS, pair % BUCKETS
    return np.stack([np.bincount(b, weights=w[d], minlength=BUCKETS) for w in (1 - y, y)])


def _log_odds(counts: np.ndarray, rate: float) -> np.ndarray:
    """Log odds of each bucket, shrunk to 0 for rare ones."""
    return np.clip(np.log((counts[1] * rate + 2) / (counts[0] + 2)), -2, 4).astype(np.float32)


class _Slice:
    """Some training texts: inputs, windows and labels."""

    def __init__(self, part: pa.RecordBatch) -> None:
        words = words_of(part.column("text"))
        self.x, self.token_doc = Inputs(words), words.docs()
        self.doc, self.first, self.size = windows_of(words)
        self.y = part.column("y").to_numpy(zero_copy_only=False).astype(np.float64)

    def counts(self) -> tuple[np.ndarray, np.ndarray]:
        """Bucket counts of words and of n-grams."""
        x = self.x
        if not len(x.word):
            return np.zeros((2, BUCKETS)), np.zeros((2, BUCKETS))
        seen = np.unique(self.token_doc * np.int64(len(x.word)) + x.of_token)
        at = seen % len(x.word)
        grams = np.zeros((2, BUCKETS))
        for lo in range(0, len(self.y), 64):  # some documents at a time: pairs of document and n-gram are many
            own = (seen >= lo * len(x.word)) & (seen < (lo + 64) * len(x.word))
            part = _Part(x, at[own])
            grams += _bucket_counts(np.repeat(seen[own] // len(x.word), part.count), part.gram, self.y)
        return _bucket_counts(self.token_doc, x.word[x.of_token], self.y), grams

    def hints(self, odds: np.ndarray, gram_odds: np.ndarray) -> np.ndarray:
        """A first guess at each window: the largest log odds of its words."""
        hint = (odds[self.x.word] + _mean_of(gram_odds, self.x))[self.x.of_token]
        edges = np.minimum(np.stack([self.first, self.first + np.maximum(self.size, 1)], axis=1).ravel(), len(hint))
        top = np.maximum.reduceat(np.append(hint, -9), edges)[::2]
        return np.where(self.size > 0, top, -9)

    def logits(self, net: Network) -> np.ndarray:
        return net.logits(self.x, self.first, self.size)


def train(texts: list[str | None], labels: list[int], epochs: int = 4, seed: int = 3) -> Network:
    """Fit on whole texts with 0/1 labels."""
    rows = pa.RecordBatch.from_arrays([pa.array(texts, pa.large_string()), pa.array(labels, pa.int64())], names=["text", "y"])
    parts = [_Slice(p) for p in slices(rows, "text")]
    net, rng = Network(seed), np.random.default_rng(seed)
    y = np.concatenate([s.y for s in parts])
    rate = max(1, (1 - y).sum()) / max(1, y.sum())
    words, grams = (sum(c) for c in zip(*(s.counts() for s in parts)))
    odds, gram_odds = _log_odds(words, rate), _log_odds(grams, rate)
    net.p["word"][:, 0] = odds / 2
    net.p["char"][:, 0] = gram_odds / 2
    state = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in net.p.items()}
    step = 0
    for epoch in range(epochs):
        pace = 0.02 * (1 - epoch / epochs)
        for s in (parts[i] for i in rng.permutation(len(parts))):
            chosen = _choose(s.doc, s.logits(net) if epoch else s.hints(odds, gram_odds), s.y, rng)
            rng.shuffle(chosen)
            label = s.y[s.doc[chosen]]
            share = min(max(label.mean(), 0.05), 0.95)
            balance = np.where(label > 0, 0.5 / share, 0.5 / (1 - share))
            for lo in range(0, len(chosen), 256):
                pick = chosen[lo : lo + 256]
                _, g = net.gradients(s.x, s.first[pick], s.size[pick], label[lo : lo + 256], balance[lo : lo + 256])
                step += 1
                for k, v in net.p.items():
                    m, q = state[k]
                    m += 0.1 * (g[k] - m)
                    q += 0.01 * (g[k] ** 2 - q)
                    v -= pace * (m / (1 - 0.9**step)) / (np.sqrt(q / (1 - 0.99**step)) + 1e-7)
    best = []
    for s in parts:
        top = np.full(len(s.y), -np.inf)
        np.maximum.at(top, s.doc, s.logits(net).astype(np.float64))
        best.append(top)
    net.scale, net.shift = _calibrated(np.concatenate(best), y)
    return net


def _mean_of(values: np.ndarray, x: Inputs) -> np.ndarray:
    out = np.zeros(len(x.word))
    some = np.flatnonzero(x.count)
    if len(some):
        out[some] = np.add.reduceat(values[x.gram], x.begin[:-1][some]) / x.count[some]
    return out


def _choose(doc: np.ndarray, value: np.ndarray, y: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    """Windows to learn from: of toxic documents the best, of others the best two and one at random."""
    order = np.lexsort((-value, doc))
    begin = np.searchsorted(doc[order], np.arange(len(y)))
    count = np.bincount(doc, minlength=len(y))
    out = [order[begin]]
    more = (y == 0) & (count > 1)
    out += [order[begin[more] + 1], order[begin[more] + rng.integers(0, count[more])]]
    return np.unique(np.concatenate(out))


def _calibrated(best: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Scale and shift of the logit so that the threshold lies between the classes."""
    order = np.argsort(best, kind="stable")
    ranked, toxic = best[order], y[order] > 0
    # right[i]: documents told rightly by a cut between ranks i and i + 1; of equal ones the widest gap wins.
    right = (np.cumsum(~toxic) + toxic.sum() - np.cumsum(toxic))[:-1]
    gap = np.diff(ranked)
    if not len(gap):
        return 1.0, 0.0
    at = np.lexsort((gap, np.where(gap > 0, right, -1)))[-1]
    cut = float(ranked[at] + 0.5 * gap[at])
    spread = max(1e-3, (best[y > 0].mean() - best[y == 0].mean()) / 2) if 0 < y.mean() < 1 else 1.0
    scale = float(np.clip(3 / spread, 0.2, 5))
    return scale, float(np.log(THRESHOLD / (1 - THRESHOLD)) - scale * cut)


def document_scores(net: Network | None, column: pa.Array) -> np.ndarray:
    words = words_of(column)
    if net is None:
        return np.zeros(len(column))
    doc, first, size = windows_of(words)
    logit = net.logits(Inputs(words), first, size).astype(np.float64)
    begin = np.searchsorted(doc, np.arange(len(column)))
    best = np.maximum.reduceat(logit, begin) if len(begin) else np.zeros(0)
    return 1 / (1 + np.exp(-(net.scale * best + net.shift)))


def held_out(id_col: Column) -> Column:
    return F.coalesce(F.crc32(id_col.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", per_class: int = SAMPLE_PER_CLASS) -> Network | None:
    """Train on at most per_class labelled documents of each class that are not held out."""
    bounded_batches(docs.sparkSession)
    known = labels.select(F.col(id_col).alias("l_id"), F.col(label_col).cast("int").alias("y")).where(F.col("y").isin(0, 1) & ~held_out(F.col("l_id")))
    known = known.groupBy("l_id").agg(F.max("y").alias("y"))
    parts = [known.where(F.col("y") == y).orderBy(F.xxhash64("l_id"), "l_id").limit(per_class) for y in (0, 1)]
    picked = F.broadcast(parts[0].unionAll(parts[1]))
    text = docs.select(F.col(id_col).alias("d_id"), F.col(text_col).alias("text"))
    rows = text.join(picked, text["d_id"] == picked["l_id"]).groupBy("d_id", "y").agg(F.min("text").alias("text"))
    made = rows.select(F.struct("d_id").alias("k"), "y", "text").coalesce(1).mapInArrow(_train_task, "model binary").collect()
    return pickle.loads(made[0][0]) if made else None


def _train_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Train on the rows of one task (the bounded sample) and return the network."""
    claim("toxicity")
    rows = [(k["d_id"], y, t) for b in batches for k, y, t in zip(*(b.column(c).to_pylist() for c in ("k", "y", "text")))]
    rows.sort(key=lambda r: (str(r[0]), r[1]))
    if len({r[1] for r in rows}) == 2:
        net = train([r[2] for r in rows], [r[1] for r in rows])
        trim_memory()
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(net)], pa.binary())], names=["model"])


def score_toxicity(docs: DataFrame, net: Network | None, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """One row per document: id, score, predicted."""
    bounded_batches(docs.sparkSession)
    base = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    shared = docs.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("toxicity")
        for batch in batches:
            for part in slices(batch, "text"):
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array(document_scores(shared.value, part.column("text")))], names=["id", "score"])
        trim_memory()

    kind = dict(base.dtypes)["id"]
    out = base.mapInArrow(run, f"id {kind}, score double")
    return out.withColumn("predicted", (F.col("score") >= threshold).cast("int")).withColumnRenamed("id", id_col)


def drop_toxic(docs: DataFrame, net: Network | None, text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """The rows, with all columns, that score below the threshold."""
    bounded_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        claim("toxicity")
        for batch in batches:
            for part in slices(batch, text_col):
                yield part.filter(pa.array(document_scores(shared.value, part.column(text_col)) < threshold))
        trim_memory()

    return docs.mapInArrow(run, docs.schema)
