"""Vectorised text kernels over Arrow buffers: words, their hashes, ragged gathers.

Words are the maximal runs outside ``\\x20 \\x09-\\x0D``; A-Z are lower-cased. Both rules are ASCII
only, so they hold on UTF-8 bytes. A word's hash is a polynomial in its bytes (64 bit, odd base,
random byte values), finalised with its length; equal words have equal hashes on every machine.
"""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SLICE_BYTES = 1 << 20
# A worker gives back what it frees: Arrow's own pools keep it for a process's life.
pa.set_memory_pool(pa.system_memory_pool())
_U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_INV = pow(_BASE, -1, 1 << 64)

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift, multiply); a bijection."""
    x = x.astype(_U, copy=True)
    x ^= x >> _U(33)
    x *= _U(0xFF51AFD7ED558CCD)
    x ^= x >> _U(33)
    x *= _U(0xC4CEB9FE1A85EC53)
    x ^= x >> _U(33)
    return x


_BYTE = mix(np.arange(1, 257, dtype=_U) * _U(0xA0761D6478BD642F))
_BYTE_LOWER = _BYTE[LOWER]


def give_back() -> None:
    """Return freed heap pages to the system, where the C library can."""
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass


_powers: dict[str, np.ndarray] = {"up": np.ones(1, _U), "down": np.ones(1, _U)}


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers["up"]) < n:
        size = -(-n // 65536) * 65536
        for key, base in (("up", _BASE), ("down", _INV)):
            steps = np.full(size, base, _U)
            steps[0] = 1
            _powers[key] = np.cumprod(steps, dtype=_U)
    return _powers["up"], _powers["down"]


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and row offsets (from 0) of a string or binary column; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_binary())
    if column.null_count:
        column = pc.fill_null(column, b"")
    _, where, data = column.buffers()
    offsets = np.frombuffer(where, np.int64)[column.offset : column.offset + len(column) + 1]
    body = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return body[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(batch: pa.RecordBatch, column: str, most: int = SLICE_BYTES):
    """Row ranges of a batch holding about ``most`` text bytes each (a longer text stands alone)."""
    body, offsets = text_buffer(batch.column(batch.schema.get_field_index(column)))
    n, i = len(offsets) - 1, 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + most, "right")) - 1)
        yield i, j, body[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        i = j
    del body, offsets
    give_back()


def words(body: np.ndarray, offsets: np.ndarray, lower: bool = True):
    """(hash, number of words per row, start, end) of all words, in order."""
    n = len(body)
    rows = len(offsets) - 1
    if not n:
        none = np.zeros(0, np.int64)
        return np.zeros(0, _U), np.zeros(rows, np.int64), none, none
    gap = SPACE[body]
    before = np.empty(n, bool)
    before[0] = True
    before[1:] = gap[:-1]
    heads = offsets[:-1][offsets[:-1] < n]
    before[heads] = True
    after = np.empty(n, bool)
    after[-1] = True
    after[:-1] = gap[1:]
    tails = offsets[1:][offsets[1:] > 0] - 1
    after[tails] = True
    start = np.flatnonzero(before & ~gap)
    end = np.flatnonzero(after & ~gap) + 1
    up, down = _power(n + 1)
    terms = (_BYTE_LOWER if lower else _BYTE)[body]
    terms *= up[:n]
    np.cumsum(terms, out=terms)
    value = terms[end - 1]
    inner = start > 0
    value[inner] -= terms[start[inner] - 1]
    value *= down[start]
    value += (end - start).astype(_U) * _U(0xE7037ED1A0B428DB)
    counts = np.diff(np.searchsorted(start, offsets))
    return mix(value), counts, start, end


def span_hashes(body: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A hash of each byte span (end > start), as words() forms them."""
    up, down = _power(len(body) + 1)
    terms = _BYTE[body]
    terms *= up[: len(body)]
    np.cumsum(terms, out=terms)
    value = terms[end - 1]
    inner = start > 0
    value[inner] -= terms[start[inner] - 1]
    value *= down[start]
    value += (end - start).astype(_U) * _U(0xE7037ED1A0B428DB)
    return mix(value)


def count_words(body: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Number of words of each row."""
    n = len(body)
    if not n:
        return np.zeros(len(offsets) - 1, np.int64)
    gap = SPACE[body]
    before = np.empty(n, bool)
    before[0] = True
    before[1:] = gap[:-1]
    before[offsets[:-1][offsets[:-1] < n]] = True
    return np.diff(np.searchsorted(np.flatnonzero(before & ~gap), offsets))


def spread(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Indices start, start+1, ... of each run, one run after the other."""
    lengths = np.asarray(lengths, np.int64)
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    shift = np.asarray(starts, np.int64) - (np.cumsum(lengths) - lengths)
    return np.repeat(shift, lengths) + np.arange(total)


def row_sums(values: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Sum of each row's run of values (0 for an empty run)."""
    ends = np.cumsum(counts)
    total = np.concatenate([np.zeros((1, *values.shape[1:])), np.cumsum(values, axis=0, dtype=np.float64)])
    return total[ends] - total[ends - counts]


def segment_sums(values: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """As row_sums, without the rounding of a long running total."""
    out = np.zeros((len(counts), *values.shape[1:]), np.float64)
    full = np.flatnonzero(counts)
    if len(full):
        at = (np.cumsum(counts) - counts)[full]
        out[full] = np.add.reduceat(values, at, axis=0)
    return out
