"""Vectorised text primitives over Arrow string buffers.

Every operator of this subpackage that must look at words does so here: the
UTF-8 buffer of an Arrow column is viewed as one byte array, word borders are
found with one table lookup, and word hashes are differences of a running
polynomial sum.  Nothing loops over words in Python.

Null texts count as empty.  A batch is cut into slices of about `SLICE_BYTES`
so that temporaries stay small whatever the batch size is; one text is never
cut, so a very long text makes one large slice.
"""

from __future__ import annotations

import ctypes
import sys
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 19

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, 9, 10, 11, 12, 13]] = True

_BASE = np.uint64(0x9E3779B97F4A7C15)
_U = np.uint64


def _inverse(base: int) -> int:
    """Inverse of an odd number modulo 2**64, by Newton's iteration."""
    x = base
    for _ in range(6):
        x = x * (2 - base * x) % (1 << 64)
    return x


class Powers:
    """Powers of an odd base modulo 2**64 and of its inverse, grown on demand."""

    def __init__(self, base: int) -> None:
        self.base, self.inv = _U(base), _U(_inverse(base))
        self.up = np.ones(1, dtype=np.uint64)
        self.down = np.ones(1, dtype=np.uint64)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            n = max(n, 1 << 16)
            with np.errstate(over="ignore"):
                self.up = np.cumprod(np.concatenate([[_U(1)], np.full(n, self.base)]), dtype=np.uint64)
                self.down = np.cumprod(np.concatenate([[_U(1)], np.full(n, self.inv)]), dtype=np.uint64)
        return self.up, self.down


_BYTE_POWERS = Powers(int(_BASE))


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads all bits (the public 64-bit murmur constants)."""
    x = x ^ (x >> _U(33))
    x = x * _U(0xFF51AFD7ED558CCD)
    x ^= x >> _U(33)
    x *= _U(0xC4CEB9FE1A85EC53)
    x ^= x >> _U(33)
    return x


_OTHER_BYTES = mix(np.arange(256, dtype=np.uint64) + _U(0xD6E8FEB86659FD93))


def fold(values: np.ndarray) -> np.ndarray:
    """Running polynomial sums: out[i] covers values[:i]."""
    up, _ = _BYTE_POWERS.upto(len(values) + 1)
    out = np.zeros(len(values) + 1, dtype=np.uint64)
    np.cumsum(values * up[: len(values)], out=out[1:])
    return out


def span_hash(sums: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hash of each [start, end) from running sums, independent of where it stands."""
    _, down = _BYTE_POWERS.upto(len(sums) + 1)
    return mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64))


@dataclass
class Words:
    """Words of the texts of one slice.

    raw: bytes of all texts; offsets: where each text starts in raw (n + 1);
    starts, ends: byte borders of each word; first: index of each text's first
    word (n + 1).
    """

    raw: np.ndarray
    offsets: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    first: np.ndarray

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def docs(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), self.counts)

    def hashes(self, lower: bool = False, other: bool = False) -> np.ndarray:
        """64-bit hashes of the words; `other` ones are of other byte values, so words that share one differ in the other."""
        raw = lower_ascii(self.raw) if lower else self.raw
        return span_hash(fold(_OTHER_BYTES[raw] if other else raw.astype(np.uint64) + _U(1)), self.starts, self.ends)

    def text(self, k: int) -> bytes:
        return self.raw[self.starts[k] : self.ends[k]].tobytes()


def trim_memory() -> None:
    """Give freed memory back to the system, Arrow's pool and, where it can, the C library's: workers outlive their tasks."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None) if sys.platform.startswith("linux") else None
    if trim is not None:
        trim(0)


_HELD: dict[str, Callable[[], None]] = {}


def claim(name: str, clear: Callable[[], None] | None = None) -> None:
    """A task of operator `name` starts in this worker: what other operators have cached here goes."""
    others = [k for k in _HELD if k != name]
    for k in others:
        _HELD.pop(k)()
    if others:
        trim_memory()
    if clear is not None:
        _HELD[name] = clear


def lower_ascii(raw: np.ndarray) -> np.ndarray:
    out = raw.copy()
    out[(raw >= 65) & (raw <= 90)] += 32
    return out


def raw_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column; nulls are empty texts."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    if not pa.types.is_large_string(column.type):
        column = column.cast(pa.large_string())
    _, offs, data = column.buffers()
    offsets = np.frombuffer(offs, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and len(data) else np.zeros(0, dtype=np.uint8)
    lo, hi = (int(offsets[0]), int(offsets[-1])) if len(offsets) else (0, 0)
    return raw[lo:hi], offsets - lo


def words_of(column: pa.Array) -> Words:
    raw, offsets = raw_of(column)
    inside = ~_SPACE[raw]
    edge = np.zeros(len(raw) + 1, dtype=bool)
    edge[0] = True
    edge[offsets] = True
    before = np.zeros(len(raw), dtype=bool)
    if len(raw):
        before[1:] = inside[:-1]
        before[edge[:-1]] = False
        begin = np.flatnonzero(inside & ~before)
        after = np.zeros(len(raw), dtype=bool)
        after[:-1] = inside[1:]
        after[edge[1:]] = False
        after[-1] = False
        end = np.flatnonzero(inside & ~after) + 1
    else:
        begin = end = np.zeros(0, dtype=np.int64)
    return Words(raw, offsets, begin, end, np.searchsorted(begin, offsets))


def slices(batch: pa.RecordBatch, column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Consecutive parts of a batch whose texts together hold about `limit` bytes."""
    if batch.num_rows == 0:
        return
    _, offsets = raw_of(batch.column(column))
    at = 0
    while at < batch.num_rows:
        stop = int(np.searchsorted(offsets, offsets[at] + limit, side="right")) - 1
        stop = min(max(stop, at + 1), batch.num_rows)
        yield batch.slice(at, stop - at)
        at = stop
    trim_memory()  # batches come one after the other; what they freed would stay with the worker


def join_words(words: Words, keep: np.ndarray) -> list[bytes]:
    """Texts of the kept words of each document, joined by one space."""
    n_docs = len(words.first) - 1
    size = np.where(keep, words.ends - words.starts + 1, 0)
    # A byte is written if it belongs to a kept word; a blank follows each kept word.
    flag = np.zeros(len(words.raw) + 1, dtype=np.int8)
    np.add.at(flag, words.starts[keep], 1)
    np.add.at(flag, words.ends[keep], -1)
    inside = np.cumsum(flag[:-1]).astype(bool)
    total = int(size.sum())
    out = np.full(total, 32, dtype=np.uint8)
    begin = np.concatenate([[0], np.cumsum(size)])
    blank = np.zeros(total, dtype=bool)
    kept_ends = begin[1:][keep] - 1
    blank[kept_ends] = True
    out[~blank] = words.raw[inside]
    doc_begin = begin[words.first]
    return [out[doc_begin[i] : max(doc_begin[i], doc_begin[i + 1] - 1)].tobytes() for i in range(n_docs)]
