"""Words of whole texts as arrays of 64-bit hashes, straight from Arrow buffers.

A word is a maximal run of bytes other than space and the five control characters from tab to carriage return; in
UTF-8 that is the same as the pattern ``[^\\x20\\x09-\\x0D]+`` over code points.
"""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: The same words as a Java or Python pattern.
WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"

SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32

_BLOCK = 1 << 20
_BASE = 0x5851F42D4C957F2D
_INVERSE = pow(_BASE, -1, 1 << 64)
_U = np.uint64


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, dtype=_U)
    out[:1] = 1
    return np.multiply.accumulate(out)


_POWER = [_powers(_BASE, 1), _powers(_INVERSE, 1)]


def _power_tables(n: int) -> list[np.ndarray]:
    if len(_POWER[0]) < n:
        _POWER[:] = [_powers(_BASE, n), _powers(_INVERSE, n)]
    return _POWER


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """Finaliser of a 64-bit hash: every output bit depends on every input bit."""
    x = x + _U((salt * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & 0xFFFFFFFFFFFFFFFF)
    x ^= x >> _U(30)
    x *= _U(0xBF58476D1CE4E5B9)
    x ^= x >> _U(27)
    x *= _U(0x94D049BB133111EB)
    x ^= x >> _U(31)
    return x


def text_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string or binary column; a null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type):
        width = np.int64
    else:
        width = np.int32
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    if column.null_count:
        column = column.fill_null(b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    _, where, data = column.buffers()
    offsets = np.frombuffer(where, dtype=width)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def word_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, first word of each text): byte ranges of all words, no word across two texts."""
    n = len(data)
    if n == 0:
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(len(offsets), np.int64)
    inside = ~SPACE[data]
    begins = inside.copy()
    begins[1:] &= ~inside[:-1]
    stops = inside.copy()
    stops[:-1] &= ~inside[1:]
    cut = offsets[(offsets > 0) & (offsets < n)]
    begins[cut] = inside[cut]
    stops[cut - 1] = inside[cut - 1]
    starts, ends = np.flatnonzero(begins), np.flatnonzero(stops) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each word's bytes, in blocks of bounded memory."""
    out = np.empty(len(starts), dtype=_U)
    k = 0
    while k < len(starts):
        stop = max(k + 1, int(np.searchsorted(starts, starts[k] + _BLOCK)))
        lo, hi = int(starts[k]), int(ends[stop - 1])
        up, down = _power_tables(hi - lo + 1)
        total = np.empty(hi - lo + 1, dtype=_U)
        total[0] = 0
        np.cumsum((data[lo:hi].astype(_U) + _U(1)) * up[: hi - lo], out=total[1:])
        a, b = starts[k:stop] - lo, ends[k:stop] - lo
        out[k:stop] = mix((total[b] - total[a]) * down[a] + (b - a).astype(_U))
        k = stop
    return out


def slices(batch: pa.RecordBatch, column: str, most: int = 1 << 21) -> Iterator[pa.RecordBatch]:
    """The batch in runs of rows whose texts have about ``most`` bytes, so that arrays over them stay small."""
    i = batch.schema.get_field_index(column)
    _, offsets = text_buffers(batch.column(i))
    k = 0
    while k < batch.num_rows:
        stop = max(k + 1, int(np.searchsorted(offsets, offsets[k] + most, side="right")) - 1)
        yield batch.slice(k, stop - k)
        k = stop


def ngram_hashes(words: np.ndarray, k: int, salt: int = 0) -> np.ndarray:
    """Hash of every k consecutive words (none if there are fewer)."""
    n = len(words) - k + 1
    if n <= 0:
        return np.zeros(0, _U)
    part, width, out, done = mix(words, salt), 1, None, 0
    while k:
        step = _U(pow(_BASE, width, 1 << 64))
        if k & 1:
            piece = part[done : done + n]
            out = piece if out is None else out * step + piece
            done += width
        k >>= 1
        if k:
            part = part[:-width] * step + part[width:]
            width *= 2
    return mix(out, salt + 1)


def release() -> None:
    """Gives memory that a finished task has freed back to the system, since Python workers live on and are reused."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass
