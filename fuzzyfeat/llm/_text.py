"""Vectorised text primitives over Arrow batches: bytes, words, word hashes and shingle sets.

Everything works on the UTF-8 bytes of a run of documents at once, in numpy, so the cost is a few nanoseconds a byte.
Runs are bounded in bytes (a single longer text makes a run of its own), which bounds the memory of a worker.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

RUN_BYTES = 1 << 18
_U = np.uint64
_PRIME = _U(0x9E3779B97F4A7C15)
_INVERSE = _U(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_BYTE = np.random.default_rng(7).integers(0, 1 << 63, 256, dtype=np.int64).astype(_U) * _U(2) + _U(1)
_ORDER = np.random.default_rng(11).integers(0, 1 << 63, 64, dtype=np.int64).astype(_U) * _U(2) + _U(1)
SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_powers: dict[str, np.ndarray] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over all 64 output bits."""
    x = x.astype(_U, copy=True)
    x ^= x >> _U(30)
    x *= _U(0xBF58476D1CE4E5B9)
    x ^= x >> _U(27)
    x *= _U(0x94D049BB133111EB)
    x ^= x >> _U(31)
    return x


def runs(column: pa.Array, most: int = RUN_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets) of consecutive rows with at most `most` bytes together. Nulls count as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    size = np.dtype(np.int64 if wide else np.int32).itemsize
    offsets = np.frombuffer(column.buffers()[1], np.int64 if wide else np.int32, len(column) + 1, column.offset * size).astype(np.int64)
    data = np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] is not None and column.buffers()[2].size else np.zeros(0, np.uint8)
    row = 0
    while row < len(column):
        end = max(row + 1, int(np.searchsorted(offsets, offsets[row] + most, "right")) - 1)
        yield row, end, data[offsets[row] : offsets[end]], offsets[row : end + 1] - offsets[row]
        row = end


def _power(kind: str, base: np.uint64, n: int) -> np.ndarray:
    known = _powers.get(kind)
    if known is None or len(known) < n:
        known = np.full(max(n, RUN_BYTES + 1), base, _U)
        known[0] = 1
        known = np.cumprod(known, dtype=_U)
        if n <= 4 * RUN_BYTES:
            _powers[kind] = known
    return known[:n]


def spans(mask: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of True that lie within one document."""
    n = len(mask)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    before, after = np.zeros(n, bool), np.zeros(n, bool)
    before[1:] = mask[:-1]
    after[:-1] = mask[1:]
    before[edge[:-1]] = False
    after[edge[1:]] = False
    return np.flatnonzero(mask & ~before), np.flatnonzero(mask & ~after) + 1


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span of bytes, by differences of one running polynomial sum."""
    n = len(data)
    total = np.zeros(n + 1, _U)
    np.cumsum(_BYTE[data] * _power("up", _PRIME, n), out=total[1:])
    return mix((total[ends] - total[starts]) * _power("down", _INVERSE, n + 1)[starts])


def words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts, ends and hashes of the words (ASCII lower-cased, split at U+0020 and U+0009-U+000D)."""
    lowered = LOWER[data]
    starts, ends = spans(~SPACE[data], offsets)
    return starts, ends, span_hashes(lowered, starts, ends)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct k-word shingles of each document: hashes grouped by document and sorted within it, and the bounds of each document.

    A document of fewer than k words, but at least one, has its whole word sequence as its only shingle; one without words has none.
    """
    starts, _, hashes = words(data, offsets)
    first = np.searchsorted(starts, offsets)
    count = np.diff(first)
    n_docs = len(offsets) - 1
    combined = np.zeros(max(0, len(hashes) - k + 1), _U)
    for j in range(k):
        combined += hashes[j : len(hashes) - k + 1 + j] * _ORDER[j]
    doc_of = np.repeat(np.arange(n_docs), count)
    whole = doc_of[: len(combined)] == doc_of[k - 1 :] if len(combined) else np.zeros(0, bool)
    docs, values = doc_of[: len(combined)][whole], mix(combined[whole])
    short = np.flatnonzero((count > 0) & (count < k))
    if len(short):
        extra = np.array([np.sum(hashes[first[i] : first[i + 1]] * _ORDER[: count[i]], dtype=_U) for i in short], _U) + _ORDER[63] * count[short].astype(_U)
        docs, values = np.concatenate([docs, short]), np.concatenate([values, mix(extra)])
    order = np.lexsort((values, docs))
    docs, values = docs[order], values[order]
    keep = np.ones(len(docs), bool)
    keep[1:] = (docs[1:] != docs[:-1]) | (values[1:] != values[:-1])
    docs, values = docs[keep], values[keep]
    return values, np.searchsorted(docs, np.arange(n_docs + 1))
