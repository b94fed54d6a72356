"""Removal of word passages that repeat across documents (Rabin-Karp windows).

Words are runs without ASCII white space.  Every window of `window` consecutive
words of one document has a rolling polynomial hash.  A word goes if a window
covering it has a word sequence that also starts in a document with a smaller
id; all windows are judged on the input texts.

How it scales: a window's smallest inner word-group hash (its minimiser) is a
function of the window's words alone, so equal windows have equal minimisers.
Only minimisers are counted first, about two for every `window` words.  Windows
whose minimiser stays within one document cannot repeat, and only the others
have their 128-bit hashes shuffled and counted.  Nothing is lost by this; it
is a filter without false negatives.  Exact copies of a smaller document are
told by their digest; all their windows repeat, so none is counted.  No group
of rows is ever gathered: the smallest document of a hash comes from a partial
aggregate and is joined back.  The two halves of a window's hash come from two
hashes of each word.  Ids are numbers, as the smaller one counts.

Defined cases: a null text is empty; a null id counts as larger than any other
id; rows that repeat id and text get equal results, and do not repeat each
other (their id is not smaller); documents shorter than a window stay whole;
an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._spark import bounded_batches, written
from ._text import fold, join_words, mix, slices, span_hash, words_of

BROADCAST_KEYS = 400_000
_LAST = 0x7FFFFFFFFFFFFFFF


def _sliding_min(values: np.ndarray, width: int) -> np.ndarray:
    """out[i] = min(values[i : i + width]) by doubling; ends short of a full width are cut."""
    best, span = values, 1
    while span * 2 <= width:
        best = np.minimum(best[: len(best) - span], best[span:])
        span *= 2
    rest = width - span
    return np.minimum(best[: len(best) - rest], best[rest:]) if rest else best


def _windows(column: pa.Array, window: int):
    """Words, word sums, starts of whole windows, their document and minimiser."""
    words = words_of(column)
    gram = max(1, window // 2)  # an edited word then spoils half of the minimisers of its windows
    total = len(words.starts)
    if total < window:
        return words, None, np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64)
    hashes = words.hashes()
    sums = fold(hashes)
    at = np.arange(total - gram + 1)
    grams = _hash_at(sums, at, gram)
    best = _sliding_min(grams, window - gram + 1)
    docs = words.docs()
    starts = np.flatnonzero(docs[: total - window + 1] == docs[window - 1 :])
    return words, hashes, starts, docs[starts], best[starts]


def _hash_at(sums: np.ndarray, at: np.ndarray, n: int) -> np.ndarray:
    return span_hash(sums, at, at + n)


def _minimisers(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                _, _, _, docs, best = _windows(part.column("text"), window)
                if not len(docs):
                    continue
                new = np.ones(len(docs), dtype=bool)
                new[1:] = (docs[1:] != docs[:-1]) | (best[1:] != best[:-1])
                at = docs[new]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(best[new].view(np.int64)), part.column("ord").take(pa.array(at)), part.column("key").take(pa.array(at))],
                    names=["mark", "ord", "key"],
                )

    return run


def _candidates(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                words, hashes, starts, docs, best = _windows(part.column("text"), window)
                if not len(starts):
                    continue
                marks = part.column("marks")
                lens = marks.value_lengths().to_numpy(zero_copy_only=False)
                flat = marks.flatten().to_numpy().view(np.uint64)
                salt = mix(np.arange(part.num_rows, dtype=np.uint64) + np.uint64(1))
                wanted = np.sort(flat ^ np.repeat(salt, lens))
                asked = best ^ salt[docs]
                found = np.searchsorted(wanted, asked)
                found[found == len(wanted)] = 0
                hit = wanted[found] == asked if len(wanted) else np.zeros(len(asked), bool)
                starts, docs = starts[hit], docs[hit]
                if not len(starts):
                    continue
                one = _hash_at(fold(hashes), starts, window)
                two = _hash_at(fold(words.hashes(other=True)), starts, window)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(one.view(np.int64)),
                        pa.array(two.view(np.int64)),
                        part.column("ord").take(pa.array(docs)),
                        part.column("key").take(pa.array(docs)),
                        pa.array((starts - words.first[docs]).astype(np.int32)),
                    ],
                    names=["h1", "h2", "ord", "key", "at"],
                )

    return run


_SPANS = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))


def _cut(window: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                words = words_of(part.column("text"))
                total = len(words.starts)
                found = part.column("found")
                lens = np.nan_to_num(found.value_lengths().to_numpy(zero_copy_only=False)).astype(np.int64)
                flat = found.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
                at = flat + np.repeat(words.first[:-1], lens)
                step = np.zeros(total + 1, dtype=np.int64)
                np.add.at(step, at, 1)
                np.add.at(step, at + window, -1)
                docs = words.docs()
                copy = part.column("copy").fill_null(False).to_numpy(zero_copy_only=False) & (words.counts >= window)
                gone = (np.cumsum(step[:-1]) > 0) | copy[docs]
                removed = np.bincount(docs[gone], minlength=part.num_rows)
                # Maximal runs of removed words, cut at the borders of documents.
                before = np.zeros(total, dtype=bool)
                before[1:] = gone[:-1] & (docs[1:] == docs[:-1])
                after = np.zeros(total, dtype=bool)
                after[:-1] = gone[1:] & (docs[1:] == docs[:-1])
                begin, end = np.flatnonzero(gone & ~before), np.flatnonzero(gone & ~after) + 1
                per = np.searchsorted(begin, words.first)
                base = words.first[docs[begin]] if len(begin) else begin
                spans = pa.ListArray.from_arrays(
                    pa.array(per.astype(np.int32)),
                    pa.StructArray.from_arrays(
                        [pa.array((begin - base).astype(np.int32)), pa.array((end - base).astype(np.int32))], fields=list(_SPANS.value_type)
                    ),
                )
                kept = pa.array(join_words(words, ~gone), type=pa.binary()).cast(pa.string())
                yield pa.RecordBatch.from_arrays(
                    [part.column("id"), pa.array(words.counts), pa.array(removed.astype(np.int64)), spans, kept],
                    names=["id", "n_words", "n_removed", "spans", "kept_text"],
                )

    return run


def remove_repeated_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = 50) -> DataFrame:
    """One row per input row: id, n_words, n_removed, spans (word intervals), kept_text."""
    bounded_batches(docs.sparkSession)
    ident = F.col(id_col).cast("long")
    base = docs.select(
        ident.alias("id"),
        F.coalesce(ident, F.lit(_LAST)).alias("ord"),
        F.xxhash64(ident, F.col(text_col)).alias("key"),
        F.coalesce(F.col(text_col), F.lit("")).alias("text"),
    )
    row = ["ord", "key"]  # a row is known by its id and a hash of id and text together
    # A whole copy of a smaller document goes as one: its windows need not be counted.
    narrow = written(base.select(*row, F.md5("text").alias("whole")), "wholes")
    # Smallest members are written before they are joined back: joins whose sides are both exchanges can be split where a key is hot.
    lowest = written(narrow.groupBy("whole").agg(F.min(F.struct(*row)).alias("one")), "lowest")
    copies = narrow.join(lowest, "whole").where("ord > one.ord").select(*row).distinct()
    marks = written(base.mapInArrow(_minimisers(window), "mark long, ord long, key long"), "marks")
    shared = marks.groupBy("mark").agg(F.min("ord").alias("lo"), F.max("ord").alias("hi")).where("lo < hi").select("mark")
    shared = written(shared, "shared")
    wanted = marks.join(shared, "mark").groupBy(*row).agg(F.collect_set("mark").alias("marks"))
    wanted = written(wanted.join(lowest.select("one.*"), row, "left_semi"), "wanted")
    copies = written(copies, "copies")
    # Texts of documents that share nothing stay where they are, if the others are few enough to be told to all tasks.
    keys = wanted.select(*row).unionAll(copies).distinct()
    few = keys.count() <= BROADCAST_KEYS
    some = base.join(F.broadcast(keys), row, "left_semi") if few else base
    # Both joins with the texts ask for the same columns, so that one exchange of the texts serves both.
    rows = some.join(wanted, row).mapInArrow(_candidates(window), "h1 long, h2 long, ord long, key long, at int")
    first = rows.groupBy("h1", "h2").agg(F.min("ord").alias("lo"), F.max("ord").alias("hi")).where("lo < hi").select("h1", "h2", "lo")
    first = written(first, "first")
    found = rows.join(first, ["h1", "h2"]).where("ord > lo").groupBy(*row).agg(F.collect_set("at").alias("found"))
    none = F.array().cast("array<int>")
    gone = found.select(*row, "found", F.lit(False).alias("copy")).unionByName(copies.select(*row, none.alias("found"), F.lit(True).alias("copy")))
    out = some.join(gone, row, "left")
    if few:
        rest = base.join(F.broadcast(keys), row, "left_anti")
        out = out.unionByName(rest.withColumns({"found": none, "copy": F.lit(False)}))
    done = out.mapInArrow(_cut(window), "id long, n_words long, n_removed long, spans array<struct<start:int,end:int>>, kept_text string")
    return done.withColumnRenamed("id", id_col)
