"""Shingle sets of whole texts and their fast similarity sketches.

A sketch has ``T`` coordinates.  In round r each element of a set is thrown into one bin by a hash of its own, with a
value that is larger in every later round; in the second T rounds all elements go to bin r - T.  A bin keeps its
smallest value, so the rounds can stop as soon as every bin has one, which is sure after 2T rounds and for larger sets
comes after a few.  Two sets agree in a coordinate with the probability of their Jaccard similarity, and the share of
coordinates in which they agree is concentrated like that of independent draws.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa

from .words import LOWER, mix, ngram_hashes, text_buffers, word_hashes, word_spans

#: Coordinates of a sketch; the first ones make the bands.
T = 512
#: Probability that a pair just similar enough shares no band, and most bands of a document.
MISS, MOST_BANDS = 2.5e-9, 48
SHINGLE = 5

_U = np.uint64
_EMPTY = _U(0xFFFFFFFFFFFFFFFF)
#: Bits of a value that hold its round, of which there are 2T.
_ROUND_BITS = _U((2 * T - 1).bit_length())
_SHIFT = _U(64) - _ROUND_BITS


def shingle_sets(texts: pa.Array, lower: bool = True) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text: of 5 words, or the whole sequence of fewer; none without words."""
    data, offsets = text_buffers(texts)
    if lower:
        data = LOWER[data]
    starts, ends, first = word_spans(data, offsets)
    words = word_hashes(data, starts, ends)
    grams = ngram_hashes(words, SHINGLE)
    out = []
    for lo, hi in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        n = hi - lo
        if n >= SHINGLE:
            out.append(np.unique(grams[lo : hi - SHINGLE + 1]))
        elif n:
            out.append(ngram_hashes(words[lo:hi], n, salt=100 + n))
        else:
            out.append(np.zeros(0, _U))
    return out


def sketches(sets: list[np.ndarray]) -> np.ndarray:
    """Sketch of each set, one row each; rows of empty sets are left at the largest value."""
    out = np.full((len(sets), T), _EMPTY, dtype=_U)
    flat = out.reshape(-1)
    sizes = np.array([len(s) for s in sets])
    if not sizes.sum():
        return out
    owner = np.repeat(np.arange(len(sets)), sizes)
    items = np.concatenate(sets)
    for r in range(2 * T):
        value = mix(items, r + 1)
        bins = (value % _U(T)).astype(np.int64) if r < T else np.full(len(items), r - T, np.int64)
        np.minimum.at(flat, owner * T + bins, (_U(r) << _SHIFT) | (value >> _ROUND_BITS))
        open_ = (out == _EMPTY).any(axis=1)
        keep = open_[owner]
        if not keep.any():
            break
        owner, items = owner[keep], items[keep]
    return out


def banding(min_percent: int) -> tuple[int, int]:
    """(bands, rows) for pairs of at least this similarity: as many rows as ``MOST_BANDS`` bands allow, else one row each."""
    if not 1 <= min_percent <= 100:
        raise ValueError("a similarity between 1 and 100 percent is needed")
    p = min(min_percent / 100, 0.999)
    needed = {r: math.ceil(math.log(MISS) / math.log1p(-(p**r))) for r in range(1, 17)}
    rows = max((r for r, n in needed.items() if n <= MOST_BANDS and n * r <= T), default=1)
    if needed[rows] > T:
        raise ValueError(f"{T} coordinates don't make bands for {min_percent} percent")
    return needed[rows], rows


def band_hashes(sketch: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """One 64-bit hash per band, in which the band's number is mixed."""
    parts = sketch[:, : bands * rows].reshape(len(sketch), bands, rows)
    out = np.broadcast_to(np.arange(bands, dtype=_U) + _U(1), (len(sketch), bands)).copy()
    for k in range(rows):
        out = mix(out ^ parts[:, :, k], 7 + k)
    return out


def signatures(sketch: np.ndarray) -> np.ndarray:
    """The coordinates cut to one byte each, for estimates."""
    return (mix(sketch, 99) >> _U(56)).astype(np.uint8)


def set_digest(items: np.ndarray) -> bytes:
    return hashlib.blake2b(items.tobytes(), digest_size=16).digest()


def overlap(a: np.ndarray, b: np.ndarray) -> tuple[int, int]:
    """Sizes of intersection and union of two sorted distinct arrays."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both, len(a) + len(b) - both
