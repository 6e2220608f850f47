"""Word shingles of whole texts, hashed with numpy over many texts at a time."""

from __future__ import annotations

import numpy as np
import xxhash

from .common import mix64

_TABLE = np.arange(256, dtype=np.uint8)
_TABLE[ord("A") : ord("Z") + 1] += 32
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, 9, 10, 11, 12, 13]] = True

_SEEDS = (np.uint64(0x9E3779B97F4A7C55), np.uint64(0xC2B2AE3D27D4EB4F))
_MULTIPLIERS = (np.uint64(0xD6E8FEB86659FD93), np.uint64(0xA0761D6478BD642F))
_MASKS = np.array([(1 << 8 * n) - 1 for n in range(9)], np.uint64)
LONG_WORD = 64


def word_hashes(text: np.ndarray, lane: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """(begins, hashes) of the words in a byte array that starts and ends with white space. Words
    are mixed eight bytes at a time, each step over all words that go on; longer ones than
    LONG_WORD bytes have a library hash. `lane` 0 and 1 are two independent hashes."""
    low = np.zeros(len(text) + 8, np.uint8)
    low[: len(text)] = _TABLE[text]
    space = _SPACE[low[: len(text)]]
    edge = np.flatnonzero(space[1:] != space[:-1]) + 1
    begins, ends = edge[0::2], edge[1::2]
    eights = np.ndarray((len(text),), "<u8", low.data, strides=(1,))
    lengths = ends - begins
    hashes = mix64(lengths.astype(np.uint64) + _SEEDS[lane])
    going = np.flatnonzero(lengths <= LONG_WORD)
    at = 0
    while len(going):
        block = eights[begins[going] + at] & _MASKS[np.minimum(lengths[going] - at, 8)]
        hashes[going] = mix64((hashes[going] * _MULTIPLIERS[lane]) ^ block)
        at += 8
        going = going[lengths[going] > at]
    for i in np.flatnonzero(lengths > LONG_WORD):
        hashes[i] = xxhash.xxh3_64_intdigest(low[begins[i] : ends[i]].data, seed=int(_SEEDS[lane]))
    return begins, hashes


def _combine(parts: list[np.ndarray], tag: int, lane: int) -> np.ndarray:
    total = np.full(len(parts[0]), np.uint64(tag), np.uint64)
    for p in parts:
        total = total * _MULTIPLIERS[lane] + p
    return mix64(total)


def _rolled(texts: list[bytes], width: int, lane: int) -> list[np.ndarray]:
    """Shingle hashes of each text in order of place: `width` consecutive words, or the whole
    sequence where there are fewer; an empty array without words."""
    flat = np.frombuffer(b" " + b" ".join(texts) + b" ", np.uint8)
    begins, hashes = word_hashes(flat, lane)
    lengths = np.fromiter(map(len, texts), np.int64, len(texts))
    starts = 1 + np.concatenate([[0], np.cumsum(lengths + 1)[:-1]])
    first = np.searchsorted(begins, starts)
    last = np.searchsorted(begins, starts + lengths)
    n = max(len(hashes) - width + 1, 0)
    rolled = _combine([hashes[i : n + i] for i in range(width)], width, lane) if n else np.zeros(0, np.uint64)
    out = []
    for a, b in zip(first.tolist(), last.tolist(), strict=True):
        if b - a >= width:
            out.append(rolled[a : b - width + 1])
        elif b > a:
            out.append(_combine([hashes[i : i + 1] for i in range(a, b)], b - a, lane))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def shingle_hashes(texts: list[bytes], width: int = 3) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text."""
    return [np.unique(x) for x in _rolled(texts, width, 0)]


def wide_shingles(texts: list[bytes], width: int = 3):
    """For each text its sorted distinct shingle hashes and, beside each, the second lane: 128
    bits in all."""
    for run in grouped(texts):
        for x, y in zip(_rolled(run, width, 0), _rolled(run, width, 1), strict=True):
            distinct, at = np.unique(x, return_index=True)
            yield distinct, y[at]


def grouped(texts: list[bytes], limit: int = 1 << 19):
    """Runs of texts of about `limit` bytes; a longer text goes alone."""
    run: list[bytes] = []
    size = 0
    for t in texts:
        if run and size + len(t) > limit:
            yield run
            run, size = [], 0
        run.append(t)
        size += len(t)
    if run:
        yield run


def all_shingles(texts: list[bytes], width: int = 3):
    for run in grouped(texts):
        yield from shingle_hashes(run, width)
