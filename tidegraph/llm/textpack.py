"""Vectorised views of Arrow string columns: words, lines, windows and their 64-bit hashes.

A batch of texts is one byte array with document offsets. Every step is a numpy pass over it,
so cost is a few nanoseconds a byte and memory a small multiple of the batch. Words are maximal
runs of characters outside U+0020 and U+0009-U+000D; in UTF-8 these are single bytes, hence a
byte-wise cut is exact. A span's hash is a polynomial over random 64-bit byte values modulo 2^64,
read off prefix sums and finished by an avalanche mix: equal spans have equal hashes anywhere.
"""

from __future__ import annotations

import ctypes
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
BASE = 0x9E3779B97F4A7C15 | 1
INVERSE = pow(BASE, -1, 1 << 64)
_rng = np.random.Generator(np.random.PCG64(20240229))
PLAIN = _rng.integers(1, 1 << 63, 256, dtype=np.uint64) * U(2) + U(1)
FOLDED = PLAIN.copy()
FOLDED[65:91] = PLAIN[97:123]
SPACE = np.zeros(256, bool)
SPACE[[0x20, 9, 10, 11, 12, 13]] = True
_powers: list[np.ndarray] = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        size = 1 << int(n - 1).bit_length()
        for k, base in enumerate((BASE, INVERSE)):
            a = np.full(size, base, np.uint64)
            a[0] = 1
            _powers[k] = np.cumprod(a, dtype=np.uint64)
    return _powers[0][:n], _powers[1][:n]


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> U(30))) * U(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> U(27))) * U(0x94D049BB133111EB)
    return h ^ (h >> U(31))


def release() -> None:
    """Gives free memory back to the system; Arrow's pool and the C library else keep it for this process alone."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def text_bytes(column) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of a string column, and offsets (one more than rows); null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], column.type)
    column = pc.fill_null(column, "").cast(pa.large_string())
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offs = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + n + 1]
    raw = column.buffers()[2]
    data = np.frombuffer(raw, np.uint8)[offs[0] : offs[-1]] if raw is not None else np.zeros(0, np.uint8)
    return data, offs - offs[0]


def prefix_hash(data: np.ndarray, fold: bool = False) -> np.ndarray:
    g = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((FOLDED if fold else PLAIN)[data] * powers(len(data))[0], out=g[1:])
    return g


def span_hash(g: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    if not len(starts):
        return np.zeros(0, np.uint64)
    return mix((g[ends] - g[starts]) * powers(len(g))[1][starts] + (ends - starts).astype(np.uint64))


@dataclass
class Words:
    data: np.ndarray
    offs: np.ndarray  # bytes of document d: offs[d] to offs[d + 1]
    starts: np.ndarray
    ends: np.ndarray
    hashes: np.ndarray
    woff: np.ndarray  # words of document d: woff[d] to woff[d + 1]

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.woff)

    @property
    def doc(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.offs) - 1), self.counts)


def edges_of(inside: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of maximal runs of true, cut at document offsets."""
    n = len(inside)
    if n == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    at = offs[(offs > 0) & (offs < n)]
    before = np.zeros(n, bool)
    before[1:] = inside[:-1]
    before[at] = False
    starts = np.flatnonzero(inside & ~before)
    after = np.zeros(n, bool)
    after[:-1] = inside[1:]
    after[at - 1] = False
    return starts, np.flatnonzero(inside & ~after) + 1


def carried(keep: tuple[str, ...], text_col: str) -> list[str]:
    """Names of the keep columns on their way through an operator that has the text as _text: a kept text is that column, not a second copy."""
    return ["_text" if c == text_col else f"_k{i}" for i, c in enumerate(keep)]


def words_of(column, fold: bool = False) -> Words:
    data, offs = text_bytes(column)
    starts, ends = edges_of(~SPACE[data], offs)
    return Words(data, offs, starts, ends, span_hash(prefix_hash(data, fold), starts, ends), np.searchsorted(starts, offs))


def windows(w: Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all k-word windows inside documents, and the word index at which each starts."""
    n = len(w.hashes)
    if n < k:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    g = np.zeros(n + 1, np.uint64)
    fwd, back = powers(n + 1)
    np.cumsum(w.hashes * fwd[:n], out=g[1:])
    h = mix((g[k:] - g[:-k]) * back[: n - k + 1] + U(k))
    at = np.flatnonzero(np.arange(n - k + 1) + k <= np.repeat(w.woff[1:], w.counts)[: n - k + 1])
    return h[at], at


def covered(n: int, starts: np.ndarray, k: int) -> np.ndarray:
    """True for the words that one of the k-word windows at starts covers."""
    d = np.zeros(n + 1, np.int64)
    np.add.at(d, starts, 1) if len(starts) < 64 else np.add(d, np.bincount(starts, minlength=n + 1), out=d)
    d -= np.bincount(starts + k, minlength=n + 1)[: n + 1] if len(starts) else 0
    return np.cumsum(d[:-1]) > 0


def per_doc(values: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """Sums of values over each document's slice."""
    g = np.zeros(len(values) + 1, np.float64 if values.dtype.kind == "f" else np.int64)
    np.cumsum(values, out=g[1:])
    return g[offs[1:]] - g[offs[:-1]]


def pieces(batches, column: str, limit: int = 2_000_000):
    """Slices of record batches with about limit bytes of text each (one row at least)."""
    for batch in batches:
        offs = text_bytes(batch.column(column))[1]
        a = 0
        while a < batch.num_rows:
            b = max(a + 1, int(np.searchsorted(offs, offs[a] + limit, side="right")) - 1)
            yield batch.slice(a, b - a)
            a = b


def shingle_sets(w: Words, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(document, hash) of each document's distinct k-word windows, sorted; with fewer words the whole sequence is the one window."""
    h, at = windows(w, k)
    doc = w.doc[at]
    short = np.flatnonzero((w.counts > 0) & (w.counts < k))
    if len(short):
        g = np.zeros(len(w.hashes) + 1, np.uint64)
        fwd, back = powers(len(w.hashes) + 1)
        np.cumsum(w.hashes * fwd[:-1], out=g[1:])
        a, b = w.woff[short], w.woff[short + 1]
        h = np.concatenate([h, mix((g[b] - g[a]) * back[a] + (b - a).astype(np.uint64))])
        doc = np.concatenate([doc, short])
    order = by_doc(np.argsort(h), doc)
    h, doc = h[order], doc[order]
    first = np.append(True, (h[1:] != h[:-1]) | (doc[1:] != doc[:-1]))[: len(h)]
    return doc[first], h[first]


def by_doc(order: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """A stable sort of `order` by document; radix sort where document numbers fit 16 bits."""
    own = doc[order]
    small = own.astype(np.uint16) if len(own) and own.max() < 65536 else own
    return order[np.argsort(small, kind="stable")]
