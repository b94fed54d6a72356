"""Quality rules with tokeniser fertility bands.

Rules count words, symbols, repeated lines and repeated three-word windows.
Fertility measures come from public vocabularies: characters per token, share of
byte-fallback tokens and entropy of the document's tokens by a byte-fallback
vocabulary, and characters per token by a byte-level one.

Bands are those of a language (of a script, where the language is null or the
table has none) and a size class, as short texts spread wider and entropy grows
with length: the median of all documents of that language and class that pass
the base rule, less and plus `WIDTH` spreads, a spread being the distance of
the quartile on that side in standard deviations of a normal law.  Quartiles are
exact on a fixed grid (`percentile` over counted grid cells), so reruns agree and
what a group keeps in memory is bounded by the grid.  A group of fewer than
`LEAST_GROUP` documents has no quartiles worth the name; there, and as outer
limits everywhere, the wide bands of the script hold.

Words are tokenised one distinct word at a time: pieces of these vocabularies
never span white space here, so counts of a text are sums over its words.

Defined cases: a null or blank text has no words and fails the base rule;
documents with fewer tokens than `MIN_TOKENS` are not judged by bands (measures
of so few tokens say nothing); an empty table gives an empty result; repeated
rows get equal results; other columns are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._spark import bounded_batches, written
from ._text import fold, mix, slices, span_hash, words_of

MIN_TOKENS = 50
LEAST_GROUP = 60
WIDTH = 4.5
#: Grid step and least spread of the measures that have bands of their own.
GRID = {"chars_per_token": (0.002, 0.02), "byte_chars_per_token": (0.002, 0.02), "token_entropy": (0.005, 0.05)}
_QUARTILE = 0.6745  # standard deviations from the median to a quartile of a normal law
# Lowest and highest characters per token, highest byte-fallback
# share, lowest and highest token entropy in bits, by script.
BANDS = {
    "latin": (1.2, 9.0, 0.10, 2.0, 14.0),
    "cyrillic": (0.9, 9.0, 0.15, 2.0, 14.0),
    "greek": (0.6, 9.0, 0.30, 2.0, 14.0),
    "other": (0.2, 9.0, 0.95, 1.5, 14.0),
    "none": (1.2, 9.0, 0.10, 2.0, 14.0),
}
SCRIPTS = ("latin", "cyrillic", "greek", "other", "none")

_SYMBOL = np.zeros(256, dtype=bool)
_SYMBOL[list(b"#*$%&|<>")] = True
_CACHE_WORDS = 400_000


class _Pieces:
    """Token ids of words by hash; a bounded cache that only saves time."""

    def __init__(self, model: str, ranks: str | None) -> None:
        import base64

        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=model)
        self.other = None
        if ranks is not None:
            import tiktoken

            with open(ranks, "rb") as file:
                table = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, file)}
            # A word is one pre-token; its bytes are merged within it.
            self.other = tiktoken.Encoding("bytes", pat_str=r"\S+|\s+", mergeable_ranks=table, special_tokens={})
        self.byte = np.array([self.model.is_byte(i) for i in range(self.model.vocab_size())])
        self.clear()

    def clear(self) -> None:
        self.keys = np.zeros(0, dtype=np.uint64)
        self.begin = np.zeros(0, dtype=np.int64)
        self.size = np.zeros(0, dtype=np.int64)
        self.bytes_size = np.zeros(0, dtype=np.int64)
        self.pool = np.zeros(0, dtype=np.int32)

    def of(self, words, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For each word: where its ids begin in the pool, how many they are, and how many the byte-level vocabulary has."""
        keys, where, back = np.unique(hashes, return_index=True, return_inverse=True)
        at = np.searchsorted(self.keys, keys)
        at[at == len(self.keys)] = 0
        known = self.keys[at] == keys if len(self.keys) else np.zeros(len(keys), bool)
        if not known.all():
            if len(self.keys) > _CACHE_WORDS:
                self.clear()
                known[:] = False
            new = ~known
            raw = words.raw.tobytes()
            texts = [raw[s:e].decode("utf-8", "replace") for s, e in zip(words.starts[where[new]].tolist(), words.ends[where[new]].tolist())]
            ids = self.model.encode(texts, num_threads=1)
            size = np.fromiter(map(len, ids), dtype=np.int64, count=len(ids))
            more = np.fromiter((len(self.other.encode_ordinary(t)) if self.other else 0 for t in texts), dtype=np.int64, count=len(texts))
            flat = np.fromiter((i for x in ids for i in x), dtype=np.int32, count=int(size.sum()))
            begin = np.concatenate([[0], np.cumsum(size)[:-1]]) + len(self.pool)
            self.pool = np.concatenate([self.pool, flat])
            order = np.argsort(merged := np.concatenate([self.keys, keys[new]]), kind="stable")
            self.keys = merged[order]
            self.begin = np.concatenate([self.begin, begin])[order]
            self.size = np.concatenate([self.size, size])[order]
            self.bytes_size = np.concatenate([self.bytes_size, more])[order]
            at = np.searchsorted(self.keys, keys)
        return self.begin[at][back], self.size[at][back], self.bytes_size[at][back]


def _gather(begin: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Indices begin[i] .. begin[i] + size[i] - 1, one after another."""
    total = int(size.sum())
    shift = np.repeat(begin - np.concatenate([[0], np.cumsum(size)[:-1]]), size) if total else np.zeros(0, np.int64)
    return np.arange(total) + shift


def _repeats(groups: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each row: is (group, key) found twice or more; is it not the first."""
    both = mix(keys ^ mix(groups.astype(np.uint64) + np.uint64(7)))
    order = np.argsort(both, kind="stable")
    ranked = both[order]
    same = np.zeros(len(both), dtype=bool)
    same[1:] = ranked[1:] == ranked[:-1]
    twice = same.copy()
    twice[:-1] |= same[1:]
    again, often = np.zeros(len(both), dtype=bool), np.zeros(len(both), dtype=bool)
    again[order], often[order] = same, twice
    return often, again


def _scripts(raw: np.ndarray, per_byte_doc: np.ndarray, n: int) -> np.ndarray:
    """Index of the script with most letters, from lead bytes of UTF-8."""
    letter = ((raw | 32) >= 97) & ((raw | 32) <= 122) & (raw < 128)
    kinds = [letter | ((raw >= 0xC3) & (raw <= 0xC9)), (raw >= 0xD0) & (raw <= 0xD3), (raw >= 0xCD) & (raw <= 0xCF), raw >= 0xD4]
    counts = np.stack([np.bincount(per_byte_doc[k], minlength=n) for k in kinds], axis=1)
    return np.where(counts.sum(axis=1) == 0, 4, counts.argmax(axis=1))


def _measure(model: str, ranks: str | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = None
        for batch in batches:
            for part in slices(batch, "text"):
                pieces = pieces or _Pieces(model, ranks)
                yield _rows(part, pieces)

    return run


def _rows(part: pa.RecordBatch, pieces: _Pieces) -> pa.RecordBatch:
    column, n = part.column("text"), part.num_rows
    words = words_of(column)
    raw, offsets = words.raw, words.offsets
    docs = words.docs()
    hashes = words.hashes()
    byte_doc = np.repeat(np.arange(n), np.diff(offsets))
    lead = (raw & 0xC0) != 0x80
    chars = np.concatenate([[0], np.cumsum(lead)])
    word_chars = np.bincount(docs, weights=chars[words.ends] - chars[words.starts], minlength=n).astype(np.int64)
    symbols = np.bincount(byte_doc[_SYMBOL[raw]], minlength=n)

    # Lines: cut at \n and at document borders; a line counts if it has a word.
    cut = raw == 10
    line_of_byte = np.cumsum(cut) - cut
    if len(words.starts):
        new = np.ones(len(docs), dtype=bool)
        new[1:] = (line_of_byte[words.starts[1:]] != line_of_byte[words.starts[:-1]]) | (docs[1:] != docs[:-1])
        ends_at = np.flatnonzero(cut)
        first_word = words.starts[new]
        k = np.searchsorted(ends_at, first_word)
        begin = np.where(k > 0, ends_at[np.maximum(k - 1, 0)] + 1 if len(ends_at) else 0, 0)
        begin = np.maximum(begin, offsets[docs[new]])
        stop = np.where(k < len(ends_at), ends_at[np.minimum(k, len(ends_at) - 1)] if len(ends_at) else len(raw), len(raw))
        stop = np.minimum(stop, offsets[docs[new] + 1])
        sums = fold(raw.astype(np.uint64) + np.uint64(1))
        _, again = _repeats(docs[new], span_hash(sums, begin, stop))
        dup_lines = np.bincount(docs[new][again], minlength=n)
        repeat_words = np.zeros(n, dtype=np.int64)
        if len(hashes) >= 3:
            tri = mix(hashes[:-2] + np.uint64(3) * mix(hashes[1:-1] + np.uint64(5) * mix(hashes[2:])))
            ok = docs[:-2] == docs[2:]
            often = np.zeros(len(tri), dtype=bool)
            often[ok] = _repeats(docs[:-2][ok], tri[ok])[0]
            covered = np.zeros(len(hashes), dtype=bool)
            for shift in range(3):
                covered[shift : len(hashes) - 2 + shift] |= often
            repeat_words = np.bincount(docs[covered], minlength=n)
        where, size, more = pieces.of(words, hashes)
        byte_tokens = np.bincount(docs, weights=more, minlength=n)
        ids = pieces.pool[_gather(where, size)]
        token_doc = np.repeat(docs, size)
    else:
        dup_lines = repeat_words = np.zeros(n, dtype=np.int64)
        ids = token_doc = np.zeros(0, dtype=np.int64)
        byte_tokens = np.zeros(n)
    tokens = np.bincount(token_doc, minlength=n)
    fallback = np.bincount(token_doc, weights=pieces.byte[ids], minlength=n)
    pair = np.sort(token_doc.astype(np.int64) << 32 | ids)
    edge = np.flatnonzero(np.concatenate([[True], pair[1:] != pair[:-1]])) if len(pair) else np.zeros(0, np.int64)
    times = np.diff(np.concatenate([edge, [len(pair)]]))
    total = np.maximum(tokens, 1)
    entropy = np.log2(total) - np.bincount(pair[edge] >> 32, weights=times * np.log2(np.maximum(times, 1)), minlength=n) / total
    entropy[tokens == 0] = 0
    columns = {
        "id": part.column("id"),
        "lang": part.column("lang"),
        "n_words": pa.array(words.counts),
        "word_chars": pa.array(word_chars),
        "n_symbols": pa.array(symbols.astype(np.int64)),
        "n_dup_lines": pa.array(dup_lines.astype(np.int64)),
        "n_repeat_words": pa.array(repeat_words.astype(np.int64)),
        "n_tokens": pa.array(tokens.astype(np.int64)),
        "chars_per_token": pa.array(word_chars / total),
        "byte_chars_per_token": pa.array(word_chars / np.maximum(byte_tokens, 1)) if pieces.other else pa.nulls(n, pa.float64()),
        "byte_share": pa.array(fallback / total),
        "token_entropy": pa.array(entropy),
        "script": pa.array(np.array(SCRIPTS)[_scripts(raw, byte_doc, n)]),
    }
    return pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))


_SCHEMA = "lang string, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_tokens long, chars_per_token double, byte_chars_per_token double, byte_share double, token_entropy double, script string"


def quality_measures(docs: DataFrame, model: str, id_col: str = "doc_id", text_col: str = "text", lang_col: str | None = "lang", ranks: str | None = None) -> DataFrame:
    """One row per document; `model` is the byte-fallback vocabulary, `ranks` the byte-level one (without it that measure is null and never judged)."""
    bounded_batches(docs.sparkSession)
    lang = F.col(lang_col).cast("string") if lang_col in docs.columns else F.lit(None).cast("string")
    base = docs.select(F.col(id_col).alias("id"), lang.alias("lang"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    kind = dict(base.dtypes)["id"]
    out = base.mapInArrow(_measure(model, ranks), f"id {kind}, {_SCHEMA}")
    return out.withColumns(
        {
            "base_failed": (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words")),
            "judged": F.col("n_tokens") >= MIN_TOKENS,
            "kind": F.coalesce("lang", F.concat(F.lit("script "), "script")),
            "size_class": F.floor(F.log2(F.greatest("n_tokens", F.lit(1)))).cast("int"),
        }
    ).withColumnRenamed("id", id_col)


def quality_bands(measures: DataFrame, width: float = WIDTH) -> DataFrame:
    """(kind, size_class, <measure>_low, <measure>_high ...) from all judged documents that pass the base rule."""
    rows = measures.where(F.col("judged") & ~F.col("base_failed"))
    cells = F.explode(F.array(*[F.struct(F.lit(m).alias("measure"), F.round(F.col(m) / step).cast("long").alias("cell")) for m, (step, _) in GRID.items()]))
    counted = rows.select("kind", "size_class", cells.alias("c")).where("c.cell is not null").groupBy("kind", "size_class", "c.measure", "c.cell").agg(F.count(F.lit(1)).alias("n"))
    at = counted.groupBy("kind", "size_class", "measure").agg(F.expr("percentile(cell, array(0.25, 0.5, 0.75), n)").alias("q"), F.sum("n").alias("documents"))
    at = at.where(F.col("documents") >= LEAST_GROUP)
    of = lambda m: F.max(F.when(F.col("measure") == m, F.col("q")))
    wide = at.groupBy("kind", "size_class").agg(*[of(m).alias(m) for m in GRID])
    columns = []
    for m, (step, least) in GRID.items():
        low, mid, high = (F.col(m)[i] * step for i in range(3))
        columns.append((mid - width * F.greatest((mid - low) / _QUARTILE, F.lit(least))).alias(f"{m}_low"))
        columns.append((mid + width * F.greatest((high - mid) / _QUARTILE, F.lit(least))).alias(f"{m}_high"))
    return wide.select("kind", "size_class", *columns)


def quality_verdict(measures: DataFrame, bands: dict[str, tuple] = BANDS, width: float = WIDTH) -> DataFrame:
    """Adds the three band failures and kept; the measures are written once, as their quartiles come first."""
    measures = written(measures, "measures")
    keys = F.create_map(*[x for k, v in bands.items() for x in (F.lit(k), F.array(*[F.lit(float(y)) for y in v]))])
    band = F.element_at(keys, F.col("script"))
    # No hint: the bands are few where languages are few, and are joined by key where they are not.
    out = measures.join(quality_bands(measures, width), ["kind", "size_class"], "left")
    outside = lambda m: F.coalesce((F.col(m) < F.col(f"{m}_low")) | (F.col(m) > F.col(f"{m}_high")), F.lit(False))
    fertility = (F.col("chars_per_token") < band[0]) | (F.col("chars_per_token") > band[1]) | outside("chars_per_token") | outside("byte_chars_per_token")
    entropy = (F.col("token_entropy") < band[3]) | (F.col("token_entropy") > band[4]) | outside("token_entropy")
    failed = {"fertility_failed": fertility, "fallback_failed": F.col("byte_share") > band[2], "entropy_failed": entropy}
    out = out.withColumns({name: F.col("judged") & test for name, test in failed.items()})
    out = out.withColumn("kept", ~(F.col("base_failed") | F.col("fertility_failed") | F.col("fallback_failed") | F.col("entropy_failed")))
    return out.drop(*[f"{m}_{side}" for m in GRID for side in ("low", "high")])
