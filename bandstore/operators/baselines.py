"""The structures that band systems are compared with.

Bloom filters are built in SQL: bits are OR-ed by partial aggregation. The others are built
by a kernel per shard, in the same exchange as band structures. All share one protocol:
`build(kind, df, cols, value, r)` gives a Baseline, and `query` adds a column to probes."""

from __future__ import annotations

import math
import pickle
import uuid
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import hashing
from ..sources.shared import keep
from . import build as band
from . import metadata
from .solve import Keys

_MASK32 = np.uint64(0xFFFFFFFF)


def _hash(x: np.ndarray, round_no: int) -> np.ndarray:
    return hashing.remix(x, 1000 + round_no)


def _scaled(x: np.ndarray, n: int | np.ndarray, round_no: int) -> np.ndarray:
    return (((_hash(x, round_no) >> np.uint64(32)) * np.asarray(n, np.uint64)) >> np.uint64(32)).astype(np.int64)


# ---- peeling ------------------------------------------------------------------------------


def peel(edges: np.ndarray, m: int, late: int | None = None) -> list[tuple[np.ndarray, np.ndarray]] | None:
    """Rounds of (keys, the slot that each owns); -1 pads an edge. None if a core remains.
    All keys with a slot of their own leave together; none of them touches another's slot. Slots
    from `late` on are only owned where no earlier one can be."""
    n, k = edges.shape
    flat, key = edges.reshape(-1), np.repeat(np.arange(n), k)
    real = flat >= 0
    degree = np.bincount(flat[real], minlength=m)
    mix = np.zeros(m, np.int64)
    np.bitwise_xor.at(mix, flat[real], key[real])
    alive, rounds, left = np.ones(n, bool), [], n
    slots = np.flatnonzero(degree == 1)
    waiting = np.zeros(0, np.int64)
    while len(slots) or len(waiting):
        if late is not None:
            slots = np.union1d(slots, waiting)
            slots = slots[degree[slots] == 1]
            early = slots < late
            some = max(1, len(slots) // 8)  # a few late ones, then early ones may be free again
            slots, waiting = (slots[early], slots[~early]) if early.any() else (slots[:some], slots[some:])
        keys, first = np.unique(mix[slots], return_index=True)
        own = slots[first]
        keep = alive[keys]
        keys, own = keys[keep], own[keep]
        if not len(keys):
            if late is None or not len(waiting):
                break
            slots = keys
            continue
        rounds.append((keys, own))
        alive[keys] = False
        left -= len(keys)
        gone = edges[keys]
        at, who = gone.reshape(-1), np.repeat(keys, k)
        ok = at >= 0
        np.subtract.at(degree, at[ok], 1)
        np.bitwise_xor.at(mix, at[ok], who[ok])
        touched = np.unique(at[ok])
        slots = touched[degree[touched] == 1]
    return rounds if left == 0 else None


def assign(edges: np.ndarray, rounds: list, values: np.ndarray, m: int) -> np.ndarray:
    """Slot values so that each edge's slots xor to its value, in reverse order of peeling."""
    z = np.zeros(m, np.uint64)
    for keys, own in reversed(rounds):
        e = edges[keys]
        others = np.where((e >= 0) & (e != own[:, None]), z[np.maximum(e, 0)], np.uint64(0))
        z[own] = values[keys] ^ np.bitwise_xor.reduce(others, axis=1)
    return z


def edges_xor(hi: np.ndarray, m: int, attempt: int, **_) -> np.ndarray:
    """Three slots, one in each third."""
    third = m // 3
    return np.stack([i * third + _scaled(hi, third, attempt * 8 + i) for i in range(3)], axis=1)


def edges_anywhere(hi: np.ndarray, m: int, attempt: int, **_) -> np.ndarray:
    """Three slots of the whole table, kept distinct."""
    a, b, c = (_scaled(hi, m - i, attempt * 8 + i) for i in range(3))
    b = b + (b >= a)
    low, high = np.minimum(a, b), np.maximum(a, b)
    c = c + (c >= low)
    c = c + (c >= high)
    return np.stack([a, b, c], axis=1)


def edges_fuse(hi: np.ndarray, m: int, attempt: int, segments: int = 100, **_) -> np.ndarray:
    """Three slots in three neighbouring segments of a random window; fewer segments for small
    tables, so that a segment keeps some dozens of slots."""
    segments = min(segments, max(1, m // 64))
    size = max(1, m // (segments + 2))
    s = _scaled(hi, segments, attempt * 8 + 5)
    return np.stack([(s + i) * size + _scaled(hi, size, attempt * 8 + i) for i in range(3)], axis=1)


def edges_coupled(hi: np.ndarray, m: int, attempt: int, k: int = 4, window: int = 40, **_) -> np.ndarray:
    """k slots within one window of a random position: spatially coupled."""
    size = max(min(m, 32 * k), m // window)
    base = _scaled(hi, max(1, m - size), attempt * 16 + 15)
    part = max(1, size // k)
    return np.stack([base + i * part + _scaled(hi, part, attempt * 16 + i) for i in range(k)], axis=1)


def edges_irregular(hi: np.ndarray, m: int, attempt: int, k: int = 12, **_) -> np.ndarray:
    """Degrees from 3 to k with probabilities falling as 1/(d(d-1)): few keys have many slots."""
    d = np.arange(3, k + 1)
    share = 1.0 / (d * (d - 1))
    share[0] *= 0.9
    cut = np.cumsum(share / share.sum())
    u = (_hash(hi, attempt * 64 + 63) >> np.uint64(11)).astype(np.float64) / 2.0**53
    degree = d[np.minimum(np.searchsorted(cut, u), len(d) - 1)]
    part = m // k
    # Slots come from random distinct parts, so an edge never has a slot twice.
    keys = np.stack([_hash(hi, attempt * 64 + i) for i in range(k)], axis=1)
    parts = np.argsort(keys, axis=1)
    slots = parts * part + np.stack([_scaled(hi, part, attempt * 64 + k + i) for i in range(k)], axis=1)
    return np.where(np.arange(k)[None, :] < degree[:, None], slots, -1)


#: kind: edges, first load of slots per key, growth per try.
PEELING: dict[str, tuple[Callable, float]] = {
    "xor": (edges_xor, 1.23),
    "xorplus": (edges_xor, 1.23),
    "fuse": (edges_fuse, 1.14),
    "peel3": (edges_anywhere, 1.23),
    "coupled": (edges_coupled, 1.10),
    "irregular": (edges_irregular, 1.23),
}


@dataclass
class Slots:
    """A table whose entries at an edge's slots xor to the value."""

    kind: str
    m: int
    attempt: int
    z: np.ndarray
    r: int

    def edges(self, hi: np.ndarray) -> np.ndarray:
        return PEELING[self.kind][0](hi, self.m, self.attempt)

    def value(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        e = self.edges(hi)
        return np.bitwise_xor.reduce(np.where(e >= 0, self.z[np.maximum(e, 0)], np.uint64(0)), axis=1)

    def bits(self) -> float:
        return self.m * self.r


RANK_SLOTS = 512


@dataclass
class RankedSlots(Slots):
    """Of the last third only the entries that are not zero are stored, found by a bit for each
    slot and the number of set bits before every RANK_SLOTS slots. z holds the first two thirds
    and then those entries; peeling prefers early slots, so that many late ones stay zero."""

    marks: np.ndarray | None = None
    ranks: np.ndarray | None = None

    @staticmethod
    def of(full: Slots) -> RankedSlots:
        head = 2 * (full.m // 3)
        tail = full.z[head:]
        padded = np.zeros(-(-len(tail) // RANK_SLOTS) * RANK_SLOTS, np.uint8)
        padded[: len(tail)] = tail != 0
        per = padded.reshape(-1, RANK_SLOTS).sum(axis=1, dtype=np.int64)
        z = np.concatenate([full.z[:head], tail[tail != 0]])
        return RankedSlots(full.kind, full.m, full.attempt, z, full.r, np.packbits(padded, bitorder="little"), (np.cumsum(per) - per).astype(np.uint32))

    def value(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        e = self.edges(hi)
        head = 2 * (self.m // 3)
        out = self.z[e[:, 0]] ^ self.z[e[:, 1]]
        at = e[:, 2] - head
        words = self.marks.view("<u8").reshape(-1, RANK_SLOTS // 64)
        block, inside = at // RANK_SLOTS, at % RANK_SLOTS
        word, bit = inside // 64, (inside % 64).astype(np.uint64)
        row = words[block]
        whole = np.bitwise_count(row).astype(np.int64)
        before = np.where(np.arange(row.shape[1]) < word[:, None], whole, 0).sum(axis=1)
        own = row[np.arange(len(at)), word]
        below = np.bitwise_count(own & ((np.uint64(1) << bit) - np.uint64(1))).astype(np.int64)
        here = (own >> bit) & np.uint64(1) == 1
        place = head + self.ranks[block].astype(np.int64) + before + below
        out[here] ^= self.z[place[here]]
        return out

    def bits(self) -> float:
        return len(self.z) * self.r + self.marks.nbytes * 8 + self.ranks.nbytes * 8


def build_peeling(kind: str, keys: Keys, r: int) -> Slots:
    make, load = PEELING[kind]
    n = len(keys)
    for attempt in range(60):
        m = int(math.ceil(load * (1 + 0.01 * attempt * (1 + attempt / 8)) * n)) + 96
        m += -m % 3
        edges = make(keys.hi, m, attempt)
        if (rounds := peel(edges, m, 2 * (m // 3) if kind == "xorplus" else None)) is not None:
            made = Slots(kind, m, attempt, assign(edges, rounds, keys.value, m), r)
            return RankedSlots.of(made) if kind == "xorplus" else made
    raise RuntimeError(f"{kind}: no peelable graph")


# ---- Gaussian elimination over small shards -----------------------------------------------


def gauss(rows: list[int], values: list[int], m: int) -> list[int] | None:
    """Solve rows over GF(2), rows and pivots as Python integers of m bits."""
    pivots: dict[int, tuple[int, int]] = {}
    for row, value in zip(rows, values, strict=True):
        while row:
            low = (row & -row).bit_length() - 1
            have = pivots.get(low)
            if have is None:
                pivots[low] = (row, value)
                break
            row, value = row ^ have[0], value ^ have[1]
        else:
            if value:
                return None
    z = [0] * m
    for low in sorted(pivots, reverse=True):
        row, value = pivots[low]
        row &= row - 1
        while row:
            at = (row & -row).bit_length() - 1
            value ^= z[at]
            row &= row - 1
        z[low] = value
    return z


def gauss_many(rows: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
    """gauss() of several systems: (solutions of m slots, whether there is one). `rows` has the bits
    of each row in 64-bit words and its value in the last one, and is overwritten. Eight columns
    go together: their pivots are found on one byte of each row, and a row then takes the sum
    of its pivots out of a table of all 256."""
    n_systems, n, words = rows.shape
    each = np.arange(n_systems)
    free, z = np.ones((n_systems, n), bool), np.zeros((n_systems, m), np.uint64)
    pivot_of = np.full((n_systems, m), -1, np.int64)
    octets = rows.view(np.uint8)
    for first in range(0, m, 8):
        byte, take = octets[:, :, first >> 3].copy(), np.zeros((n_systems, n), np.uint8)
        rest = slice(first >> 6, words)  # the words before are done with
        sums = np.zeros((n_systems, 256, words - (first >> 6)), np.uint64)
        for k in range(min(8, m - first)):
            bit = np.uint8(1 << k)
            has = (byte & bit).view(bool) if k == 0 else byte & bit != 0
            able = has & free
            row = able.argmax(axis=1)
            found = able[each, row]
            has[each, row] = False
            if not found.all():
                has &= found[:, None]
            at, own = each[found], row[found]
            pivot = np.zeros((n_systems, 1, sums.shape[2]), np.uint64)
            pivot[at, 0] = rows[at, own, rest] ^ sums[at, take[at, own]]
            np.bitwise_xor(sums[:, : 1 << k], pivot, out=sums[:, 1 << k : 2 << k])
            free[at, own] = False
            pivot_of[at, first + k] = own
            mine = pivot.view(np.uint8)[:, 0, (first >> 3) & 7]
            has = has.view(np.uint8)
            byte ^= has * mine[:, None]
            take |= has * bit
        for i in range(n_systems):
            rows[i, :, rest] ^= np.take(sums[i], take[i], axis=0)
    solvable = ~(free & (rows[:, :, -1] != 0)).any(axis=1)
    at, slot = np.nonzero(pivot_of >= 0)
    z[at, slot] = rows[at, pivot_of[at, slot], -1]
    return z, solvable


GAUSS_SHARD = 1024


@dataclass
class GaussTable:
    """Shards of about GAUSS_SHARD keys, each solved by elimination of sparse or two-block rows."""

    kind: str
    shards: int
    sizes: list[int]
    attempts: list[int]
    z: list[np.ndarray]
    r: int

    def value(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        """Rows of all shards that took as many tries go together."""
        shard = _scaled(hi, self.shards, 900)
        out = np.zeros(len(hi), np.uint64)
        sizes, attempts = np.asarray(self.sizes, np.int64), np.asarray(self.attempts, np.int64)
        base = np.cumsum(sizes) - sizes
        flat = np.concatenate([*self.z, np.zeros(BLOCK, np.uint64)])
        own = np.where(sizes[shard] > 0, attempts[shard], -1)
        for attempt in np.unique(own[own >= 0]).tolist():
            at = np.flatnonzero(own == attempt)
            m, first = sizes[shard[at]], base[shard[at]]
            if self.kind == "twoblock":
                for start, bits in two_blocks(hi[at], lo[at], m, attempt):
                    if self.r <= 8:
                        out[at] ^= window_sum(flat, first + start, bits, BLOCK)
                        continue
                    found = np.zeros(len(at), np.uint64)
                    for j in range(BLOCK):
                        found ^= np.where((bits >> np.uint64(j)) & np.uint64(1) == 1, flat[first + start + j], np.uint64(0))
                    out[at] ^= found
            else:
                edges = sparse_rows(self.kind, hi[at], m, attempt)
                out[at] = np.bitwise_xor.reduce(flat[first[:, None] + edges], axis=1)
        return out

    def bits(self) -> float:
        return sum(self.sizes) * self.r + 32 * self.shards


BLOCK = 32


def window_sum(z: np.ndarray, start: np.ndarray, bits: np.ndarray, size: int) -> np.ndarray:
    """Sum of those of the `size` values of a byte at most from each start on whose bit is set."""
    windows = np.lib.stride_tricks.sliding_window_view(z.astype(np.uint8), size)
    out = np.zeros(len(start), np.uint64)
    for a in range(0, len(start), WINDOW_ROWS):
        at = slice(a, a + WINDOW_ROWS)
        mask = np.unpackbits(np.ascontiguousarray(bits[at]).view(np.uint8).reshape(-1, 8)[:, : size // 8], axis=1, bitorder="little")
        found = np.bitwise_xor.reduce((windows[start[at]] * mask).view(np.uint64), axis=1)
        for shift in (32, 16, 8):
            found ^= found >> np.uint64(shift)
        out[at] = found & np.uint64(255)
    return out


WINDOW_ROWS = 1 << 13


def sparse_rows(kind: str, hi: np.ndarray, m: int | np.ndarray, attempt: int) -> np.ndarray:
    """Three or four slots of the shard; equal ones cancel."""
    k = 4 if kind == "sparse4" else 3
    return np.stack([_scaled(hi, m, 400 + attempt * 8 + i) for i in range(k)], axis=1)


def two_blocks(hi: np.ndarray, lo: np.ndarray, m: int | np.ndarray, attempt: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Two blocks of random bits at random places."""
    return [
        (_scaled(hi, np.maximum(1, m - BLOCK + 1), 700 + attempt * 4 + i), _hash(lo, 700 + attempt * 4 + i) & _MASK32)
        for i in range(2)
    ]


GAUSS_LOAD = {"sparse3": 1.10, "sparse4": 1.035, "twoblock": 1.005}


def build_gauss(kind: str, keys: Keys, r: int) -> GaussTable:
    shards = max(1, len(keys) // GAUSS_SHARD)
    shard = _scaled(keys.hi, shards, 900)
    order = np.argsort(shard, kind="stable")
    own = np.split(order, np.searchsorted(shard[order], np.arange(1, shards)))
    sizes, attempts, tables = [0] * shards, [0] * shards, [np.zeros(0, np.uint64)] * shards
    left = [i for i in range(shards) if len(own[i])]
    for attempt in range(100):
        again = []
        for some in (left[i : i + GAUSS_TOGETHER] for i in range(0, len(left), GAUSS_TOGETHER)):
            m = [max(BLOCK, int(math.ceil(GAUSS_LOAD[kind] * (1 + 0.002 * attempt) * len(own[i]))) + 2) for i in some]
            rows = np.zeros((len(some), max(len(own[i]) for i in some), -(-max(m) // 64) + 2), np.uint64)
            for at, (i, size) in enumerate(zip(some, m, strict=True)):
                _fill_rows(rows[at], kind, keys.take(own[i]), size, attempt)
            z, solvable = gauss_many(rows, max(m))
            for at, (i, size) in enumerate(zip(some, m, strict=True)):
                if solvable[at]:
                    sizes[i], attempts[i], tables[i] = size, attempt, z[at, :size].copy()
                else:
                    again.append(i)
        left = again
        if not left:
            return GaussTable(kind, shards, sizes, attempts, tables, r)
    raise RuntimeError(f"{kind}: a shard does not settle")


#: Systems eliminated together; some 150 KB each.
GAUSS_TOGETHER = 32


def _fill_rows(rows: np.ndarray, kind: str, keys: Keys, m: int, attempt: int) -> None:
    """The keys' rows for gauss_many()."""
    n, one, word = np.arange(len(keys)), np.uint64(1), np.uint64(63)
    rows[n, -1] = keys.value
    if kind == "twoblock":
        for start, bits in two_blocks(keys.hi, keys.lo, m, attempt):
            shift = start.astype(np.uint64) & word
            rows[n, start >> 6] ^= bits << shift
            rows[n, (start >> 6) + 1] ^= (bits >> one) >> (word - shift)
    else:
        for slot in sparse_rows(kind, keys.hi, m, attempt).T:
            rows[n, slot >> 6] ^= one << (slot.astype(np.uint64) & word)


# ---- sorted one-block elimination, bucket metadata, multilevel hashing ---------------------


@dataclass
class SortedGauss:
    """One dense block of 64 bits a row; rows sorted by start, then eliminated in one pass with
    pivots kept explicitly (conditional steps, no shifts)."""

    m: int
    attempt: int
    z: np.ndarray
    r: int

    def value(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        start, bits = self.rows(hi, lo, self.m, self.attempt)
        if self.r <= 8:
            return window_sum(self.z, start, bits, 64)
        out = np.zeros(len(hi), np.uint64)
        for j in range(64):
            out ^= np.where((bits >> np.uint64(j)) & np.uint64(1) == 1, self.z[start + j], np.uint64(0))
        return out

    @staticmethod
    def rows(hi: np.ndarray, lo: np.ndarray, m: int, attempt: int) -> tuple[np.ndarray, np.ndarray]:
        return _scaled(hi, m - 63, 800 + attempt), _hash(lo, 800 + attempt)

    def bits(self) -> float:
        return self.m * self.r


def build_sorted_gauss(kind: str, keys: Keys, r: int, eps: float = 0.1) -> SortedGauss:
    for attempt in range(30):
        m = int(len(keys) / (1 - eps) * (1 + 0.02 * attempt)) + 64
        start, bits = SortedGauss.rows(keys.hi, keys.lo, m, attempt)
        order = np.argsort(start, kind="stable")
        rows = [(int(bits[i]) << int(start[i]), int(keys.value[i])) for i in order] if m <= 4096 else None
        z = gauss([x for x, _ in rows], [y for _, y in rows], m) if rows is not None else _windowed(start[order], bits[order], keys.value[order], m)
        if z is not None:
            return SortedGauss(m, attempt, np.array(z, np.uint64), r)
    raise RuntimeError("no system")


def _windowed(start: np.ndarray, bits: np.ndarray, values: np.ndarray, m: int) -> list[int] | None:
    pivots: dict[int, tuple[int, int]] = {}
    for s, c, v in zip(start.tolist(), bits.tolist(), values.tolist(), strict=True):
        j = 0
        while c >> j:
            if (c >> j) & 1:
                have = pivots.get(s + j)
                if have is None:
                    pivots[s + j] = (c >> j, v)
                    break
                c ^= have[0] << j
                v ^= have[1]
            j += 1
        else:
            if v:
                return None
    z = [0] * (m + 64)
    for at in sorted(pivots, reverse=True):
        c, v = pivots[at]
        c >>= 1
        k = at + 1
        while c:
            if c & 1:
                v ^= z[k]
            c, k = c >> 1, k + 1
        z[at] = v
    return z


@dataclass
class MetaBuckets:
    """Keys in buckets of fixed capacity; a seed in each bucket's metadata maps its keys to
    distinct cells, and keys that find none are bumped to the next level."""

    levels: list[tuple[int, np.ndarray, np.ndarray]]  # buckets, seed by bucket, cells
    r: int
    capacity: int = 8

    def value(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        out, left = np.zeros(len(hi), np.uint64), np.arange(len(hi))
        for level, (n, seeds, cells) in enumerate(self.levels):
            if not len(left):
                break
            bucket = _scaled(hi[left], n, 500 + level)
            seed = seeds[bucket]
            cell = _cell(lo[left], seed, self.capacity)
            kept = (seed < 255) & (cell < self.capacity)
            at = left[kept]
            out[at] = cells[bucket[kept] * self.capacity + cell[kept]]
            left = left[~kept]
        return out

    def bits(self) -> float:
        return sum(n * (self.capacity * self.r + 8) for n, _, _ in self.levels)


def _cell(lo: np.ndarray, seed: np.ndarray, capacity: int) -> np.ndarray:
    """Cell under a bucket's seed, out of a quarter more than there are: those are bumped."""
    span = capacity + capacity // 4
    h = hashing.hash_long(lo, seed.astype(np.uint64) + np.uint64(77))
    return (((h >> np.uint64(32)) * np.uint64(span)) >> np.uint64(32)).astype(np.int64)


MAX_SPREAD = 1 << 12


def build_meta_buckets(kind: str, keys: Keys, r: int, capacity: int = 8) -> MetaBuckets:
    levels = []
    left, spread = keys, 1
    while len(left):
        n = max(1, round(spread * len(left) / (capacity * 1.05)))
        bucket = _scaled(left.hi, n, 500 + len(levels))
        best = np.full(n, -1, np.int64)
        seeds = np.full(n, 255, np.int64)
        for seed in range(255):  # all buckets try the same seed together; the best stays
            cell = _cell(left.lo, np.full(len(left), seed), capacity)
            inside = cell < capacity
            code = bucket * capacity + np.where(inside, cell, 0)
            used = np.bincount(code[inside], minlength=n * capacity).reshape(n, capacity)
            clash = (used > 1).any(axis=1)
            stored = np.where(clash, -1, (used == 1).sum(axis=1))
            better = stored > best
            best[better], seeds[better] = stored[better], seed
        cell = _cell(left.lo, seeds[bucket], capacity)
        kept = (seeds[bucket] < 255) & (cell < capacity)
        cells = np.zeros(n * capacity, np.uint64)
        cells[bucket[kept] * capacity + cell[kept]] = left.value[kept]
        if not kept.any():
            # A bucket of some more keys than cells may have no seed that parts them; more buckets do.
            spread *= 2
            if spread > MAX_SPREAD:
                raise RuntimeError("no key was placed; equal digests with different values?")
            continue
        spread = 1
        levels.append((n, seeds, cells))
        left = left.take(np.flatnonzero(~kept))
    return MetaBuckets(levels, r, capacity)


@dataclass
class Multilevel:
    """Tables that store whole digests with values, each of the keys that collided before."""

    levels: list[tuple[int, np.ndarray, np.ndarray, np.ndarray]]
    r: int

    def value(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        out = np.zeros(len(hi), np.uint64)
        for level, (m, kh, kl, v) in enumerate(self.levels):
            at = _scaled(hi, m, 600 + level)
            here = (kh[at] == hi) & (kl[at] == lo)
            out[here] = v[at[here]]
        return out

    def bits(self) -> float:
        return sum(m * (128 + self.r) for m, *_ in self.levels)


def build_multilevel(kind: str, keys: Keys, r: int) -> Multilevel:
    levels, left = [], keys
    while len(left):
        m = max(1, len(left))
        at = _scaled(left.hi, m, 600 + len(levels))
        _, first = np.unique(at, return_index=True)
        kh, kl, v = np.zeros(m, np.uint64), np.zeros(m, np.uint64), np.zeros(m, np.uint64)
        kh[at[first]], kl[at[first]], v[at[first]] = left.hi[first], left.lo[first], left.value[first]
        levels.append((m, kh, kl, v))
        rest = np.ones(len(left), bool)
        rest[first] = False
        left = left.take(np.flatnonzero(rest))
    return Multilevel(levels, r)


# ---- filters with fingerprints in tables: cuckoo and quotient -------------------------------


class Cuckoo:
    """Buckets of fingerprints; a key may be in either of two, tied by its fingerprint: from an
    even bucket an odd step leads on, from an odd one back. Keys come in batches: those that
    find room in a bucket enter together, the others displace one entry a bucket and round."""

    slots, load, extra_bits = 4, 0.94, 3  # 8 candidate slots cost 3 bits

    def __init__(self, n: int, r: int, seed: int = 1, max_rounds: int = 4000) -> None:
        self.r, self.max_rounds = r + self.extra_bits, max_rounds
        self.n = self.buckets_for(max(1, n))
        self.table = np.zeros((self.n, self.slots), np.uint64)
        self.used = np.zeros(self.n, np.int64)
        self.random = np.random.default_rng(seed)

    def buckets_for(self, n: int) -> int:
        return 2 * math.ceil(n / (2 * self.slots * self.load) + 1)

    def parts(self, hi: np.ndarray, lo: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        tag = np.asarray(lo, np.uint64) & np.uint64((1 << self.r) - 1)
        return _scaled(np.asarray(hi, np.uint64), self.n, 1200), np.maximum(tag, np.uint64(1))

    def other(self, bucket: np.ndarray, tag: np.ndarray) -> np.ndarray:
        step = 2 * _scaled(tag, max(1, self.n // 2), 1201) + 1
        return np.where(bucket % 2 == 0, bucket + step, bucket - step) % self.n

    def room(self, bucket: np.ndarray) -> np.ndarray:
        return self.slots - self.used[bucket]

    def _place(self, bucket: np.ndarray, tag: np.ndarray) -> np.ndarray:
        """Which of the entries found room; those of a bucket in their order."""
        order = np.argsort(bucket, kind="stable")
        b = bucket[order]
        rank = _rank_in_runs(b)
        ok = rank < self.room(b)
        at = b[ok]
        self.table[at, self.used[at] + rank[ok]] = tag[order[ok]]
        np.add.at(self.used, at, 1)
        placed = np.zeros(len(bucket), bool)
        placed[order[ok]] = True
        return placed

    def left(self, bucket: np.ndarray) -> None:
        """Entries of these buckets had to go to their other bucket."""

    def insert(self, hi: np.ndarray, lo: np.ndarray) -> bool:
        """False where the table is too full; it is then to be built anew, larger."""
        bucket, tag = self.parts(hi, lo)
        for turn in range(self.max_rounds):
            rest = np.flatnonzero(~self._place(bucket, tag))
            bucket, tag = bucket[rest], tag[rest]
            if not len(rest):
                return True
            self.left(bucket)
            if turn == 0:
                bucket = self.other(bucket, tag)
            else:
                bucket, tag = self._displace(bucket, tag)
        return False

    def _displace(self, bucket: np.ndarray, tag: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at, first = np.unique(bucket, return_index=True)
        able = self.used[at] > 0
        at, first = at[able], first[able]
        self.left(at)
        slot = (self.random.random(len(at)) * self.used[at]).astype(np.int64)
        out = self.table[at, slot].copy()
        self.table[at, slot] = tag[first]
        tag = tag.copy()
        bucket = bucket.copy()
        tag[first] = out
        bucket[first] = self.other(at, out)
        return bucket, tag

    def _hits(self, hi: np.ndarray, lo: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        bucket, tag = self.parts(hi, lo)
        other = self.other(bucket, tag)
        near, far = ((self.table[b] == tag[:, None]).sum(axis=1) for b in (bucket, other))
        return near, np.where(other == bucket, 0, far), tag

    def contains(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        near, far, _ = self._hits(hi, lo)
        return near + far > 0

    def count(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        near, far, _ = self._hits(hi, lo)
        return near + far

    def delete(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        """One entry of each key goes; its bucket's last entry takes its place."""
        bucket, tag = self.parts(hi, lo)
        other = self.other(bucket, tag)
        out = np.zeros(len(bucket), bool)
        for i in range(len(bucket)):
            for at in (int(bucket[i]), int(other[i])):
                found = np.flatnonzero(self.table[at, : self.used[at]] == tag[i])
                if len(found):
                    last = self.used[at] - 1
                    self.table[at, found[0]], self.table[at, last] = self.table[at, last], 0
                    self.used[at] = last
                    out[i] = True
                    break
        return out

    def bits(self) -> float:
        return self.n * self.slots * self.r


def _rank_in_runs(b: np.ndarray) -> np.ndarray:
    """Place of each entry within its run of equal values."""
    starts = np.flatnonzero(np.concatenate([[True], b[1:] != b[:-1]])) if len(b) else np.zeros(0, np.int64)
    return np.arange(len(b)) - np.repeat(starts, np.diff(np.append(starts, len(b))))


class Morton(Cuckoo):
    """A compressed cuckoo filter: blocks of 64 buckets of up to three entries share room for 46.
    Stored are, for each block, the entries without gaps in the order of buckets, a 2-bit counter
    of each bucket, and 16 overflow bits; a lookup goes on to the other bucket only where the
    first one's overflow bit says that an entry had to leave."""

    slots, load, extra_bits = 3, 0.9, 0  # about one entry is compared
    BLOCK, ROOM, OVERFLOW = 64, 46, 16

    def __init__(self, n: int, r: int, seed: int = 1, max_rounds: int = 4000) -> None:
        super().__init__(n, r, seed, max_rounds)
        self.block_used = np.zeros(self.n // self.BLOCK, np.int64)
        self.overflow = np.zeros((self.n // self.BLOCK, self.OVERFLOW), bool)
        self.entries: np.ndarray | None = None
        self.counters = b""

    def buckets_for(self, n: int) -> int:
        return self.BLOCK * math.ceil(n / (self.ROOM * self.load) + 0.5)

    def _place(self, bucket: np.ndarray, tag: np.ndarray) -> np.ndarray:
        order = np.argsort(bucket, kind="stable")
        b = bucket[order]
        fits = np.flatnonzero(_rank_in_runs(b) < self.slots - self.used[b])
        block = b[fits] // self.BLOCK
        inside = fits[_rank_in_runs(block) < self.ROOM - self.block_used[block]]
        at = b[inside]
        rank = _rank_in_runs(at)
        self.table[at, self.used[at] + rank] = tag[order[inside]]
        np.add.at(self.used, at, 1)
        np.add.at(self.block_used, at // self.BLOCK, 1)
        placed = np.zeros(len(bucket), bool)
        placed[order[inside]] = True
        self.entries = None
        return placed

    def _displace(self, bucket: np.ndarray, tag: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where its bucket is empty in a full block, an entry displaces one of the block's fullest
        bucket."""
        stuck = np.flatnonzero(self.used[bucket] == 0)
        self.entries = None
        bucket, tag = super()._displace(bucket, tag)
        for i in stuck.tolist():
            first = int(bucket[i]) // self.BLOCK * self.BLOCK
            full = first + int(self.used[first : first + self.BLOCK].argmax())
            last = self.used[full] - 1
            out = self.table[full, last].copy()
            self.table[full, last], self.used[full] = 0, last
            self.table[bucket[i], self.used[bucket[i]]] = tag[i]
            self.used[bucket[i]] += 1
            self.left(np.array([full]))
            bucket[i], tag[i] = self.other(np.array([full]), np.array([out]))[0], out
        return bucket, tag

    def left(self, bucket: np.ndarray) -> None:
        self.overflow[bucket // self.BLOCK, bucket % self.OVERFLOW] = True

    def compress(self) -> None:
        """The stored form."""
        n_blocks = self.n // self.BLOCK
        filled = np.arange(self.slots) < self.used[:, None]
        bucket, slot = np.nonzero(filled)
        block = bucket // self.BLOCK
        self.entries = np.zeros((n_blocks, self.ROOM), np.uint64)
        self.entries[block, _rank_in_runs(block)] = self.table[bucket, slot]
        self.counters = metadata.pack(self.used, 2)

    def __getstate__(self) -> dict:
        """What is stored: entries, counters and overflow bits, without the open table."""
        if self.entries is None:
            self.compress()
        return {k: v for k, v in self.__dict__.items() if k not in ("table", "used", "block_used")}

    def __setstate__(self, state: dict) -> None:
        self.__dict__.update(state)
        self.used = metadata.unpack(self.counters, 2, self.n).astype(np.int64)
        self.block_used = self.used.reshape(-1, self.BLOCK).sum(axis=1)
        self.table = np.zeros((self.n, self.slots), self.entries.dtype)
        bucket, slot = np.nonzero(np.arange(self.slots) < self.used[:, None])
        block = bucket // self.BLOCK
        self.table[bucket, slot] = self.entries[block, _rank_in_runs(block)]

    def _stored_hits(self, bucket: np.ndarray, tag: np.ndarray) -> np.ndarray:
        """Equal entries of a bucket, read from the stored form: its place follows from the
        counters of the buckets before it in its block."""
        if self.entries is None:
            self.compress()
        counts = self.used.reshape(-1, self.BLOCK)
        before = np.cumsum(counts, axis=1) - counts
        block, inside = bucket // self.BLOCK, bucket % self.BLOCK
        at, n = before[block, inside], counts[block, inside]
        out = np.zeros(len(bucket), np.int64)
        for j in range(self.slots):
            rows = np.flatnonzero(n > j)
            out[rows] += self.entries[block[rows], at[rows] + j] == tag[rows]
        return out

    def _hits(self, hi: np.ndarray, lo: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        bucket, tag = self.parts(hi, lo)
        near, far = self._stored_hits(bucket, tag), np.zeros(len(bucket), np.int64)
        other = self.other(bucket, tag)
        ask = np.flatnonzero(self.overflow[bucket // self.BLOCK, bucket % self.OVERFLOW] & (other != bucket))
        far[ask] = self._stored_hits(other[ask], tag[ask])
        return near, far, tag

    def delete(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        out = super().delete(hi, lo)
        self.block_used = self.used.reshape(-1, self.BLOCK).sum(axis=1)
        self.entries = None
        return out

    def bits(self) -> float:
        return self.n // self.BLOCK * (self.ROOM * self.r + 2 * self.BLOCK + self.OVERFLOW)


class Quotient:
    """Remainders in runs, sorted by quotient and then by remainder, each as near behind its
    quotient's slot as there is room. Three bits a slot (its quotient has a run; the entry goes
    on a run; it does not lie in its quotient's slot) give the runs back. Equal fingerprints are
    repeated. Batches are merged in sorted order, so a batch costs one pass."""

    flag_bits, load = 3, 0.9
    OCCUPIED, CONTINUED, SHIFTED, COUNTER = 1, 2, 4, 8

    def __init__(self, n: int, r: int) -> None:
        self.r, self.n = r, max(1, math.ceil(n / self.load))
        self.rest, self.flags = np.zeros(self.n, np.uint64), np.zeros(self.n, np.uint8)

    def parts(self, hi: np.ndarray, lo: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return _scaled(np.asarray(hi, np.uint64), self.n, 1300), np.asarray(lo, np.uint64) & np.uint64((1 << self.r) - 1)

    def entries_of(self, times: np.ndarray) -> np.ndarray:
        """Slots of a fingerprint that occurs so often."""
        return times

    def fill(self, at: np.ndarray, rest: np.ndarray, times: np.ndarray) -> None:
        """Write fingerprints from their first slots on."""
        n = self.entries_of(times)
        self.rest[np.repeat(at, n) + _rank_in_runs(np.repeat(np.arange(len(at)), n))] = np.repeat(rest, n)

    def store(self, quotient: np.ndarray, rest: np.ndarray, times: np.ndarray) -> None:
        """Distinct fingerprints, in order, with how often they occur."""
        n = self.entries_of(times)
        upto = np.cumsum(n) - n
        at = upto + np.maximum.accumulate(quotient - upto) if len(n) else upto
        slots = max(self.n, int((at + n).max(initial=0)))
        self.rest, self.flags = np.zeros(slots, np.uint64), np.zeros(slots, np.uint8)
        self.fill(at, rest, times)
        slot = np.repeat(at, n) + _rank_in_runs(np.repeat(np.arange(len(at)), n))
        owner = np.repeat(quotient, n)
        self.flags[slot] |= np.where(slot != owner, self.SHIFTED, 0).astype(np.uint8)
        self.flags[slot[1:][owner[1:] == owner[:-1]]] |= self.CONTINUED
        self.flags[np.unique(owner)] |= self.OCCUPIED
        # A slot that holds an entry of another quotient's run is never without a flag.
        self.__dict__.pop("_runs", None)

    def runs(self) -> tuple[np.ndarray, np.ndarray]:
        """(rank of each quotient's run, first slots of the runs): what scanning the flags gives."""
        if "_runs" not in self.__dict__:
            occupied = self.flags & self.OCCUPIED > 0
            # A slot holds an entry if it is shifted or continues, or lies where its run begins.
            begins = np.flatnonzero((self.flags & (self.CONTINUED | self.SHIFTED) == self.SHIFTED) | self._at_home(occupied))
            self._runs = np.cumsum(occupied) - 1, begins
        return self._runs

    def _at_home(self, occupied: np.ndarray) -> np.ndarray:
        """Occupied slots whose own run begins right there: neither shifted nor continued."""
        return occupied & (self.flags & (self.CONTINUED | self.SHIFTED) == 0)

    def walk(self, quotient: np.ndarray):
        """(rows, slots) of each step through the runs of these quotients."""
        rank, begins = self.runs()
        rows = np.flatnonzero(self.flags[quotient] & self.OCCUPIED)
        slot = begins[rank[quotient[rows]]] if len(rows) else rows
        while len(rows):
            yield rows, slot
            slot = slot + 1
            on = slot < len(self.flags)
            rows, slot = rows[on], slot[on]
            on = self.flags[slot] & self.CONTINUED > 0
            rows, slot = rows[on], slot[on]

    def count(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        quotient, rest = self.parts(hi, lo)
        out = np.zeros(len(quotient), np.int64)
        for rows, slot in self.walk(quotient):
            out[rows] += self.rest[slot] == rest[rows]
        return out

    def contains(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        return self.count(hi, lo) > 0

    def fingerprints(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(quotient, remainder, times) of all that is stored, in order."""
        every = np.flatnonzero(self.flags & self.OCCUPIED)
        rows, slots = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for r, s in self.walk(every):
            rows.append(r)
            slots.append(s)
        row, slot = np.concatenate(rows), np.concatenate(slots)
        order = np.argsort(slot)
        return self.grouped(every[row[order]], slot[order])

    def grouped(self, quotient: np.ndarray, slot: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return merged(quotient, self.rest[slot], np.ones(len(slot), np.int64))

    def change(self, hi: np.ndarray, lo: np.ndarray, times: np.ndarray) -> None:
        quotient, rest = self.parts(hi, lo)
        old = self.fingerprints()
        self.store(*merged(*(np.concatenate([x, y]) for x, y in zip(old, (quotient, rest, times), strict=True))))

    def insert(self, hi: np.ndarray, lo: np.ndarray, times: np.ndarray | None = None) -> bool:
        self.change(hi, lo, np.ones(len(hi), np.int64) if times is None else times)
        return True

    def delete(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        """One occurrence of each key that is there goes."""
        found = self.contains(hi, lo)
        self.change(np.asarray(hi)[found], np.asarray(lo)[found], np.full(int(found.sum()), -1, np.int64))
        return found

    def bits(self) -> float:
        return len(self.rest) * (self.r + self.flag_bits)


def merged(quotient: np.ndarray, rest: np.ndarray, times: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct fingerprints in order with their summed counts; those at 0 or below go."""
    order = np.lexsort((rest, quotient))
    q, x, n = quotient[order], rest[order], times[order]
    if not len(q):
        return q, x, n
    first = np.flatnonzero(np.concatenate([[True], (q[1:] != q[:-1]) | (x[1:] != x[:-1])]))
    total = np.add.reduceat(n, first)
    kept = first[total > 0]
    return q[kept], x[kept], total[total > 0]


class CountingQuotient(Quotient):
    """Counts above 1 follow their remainder as digits of r bits in slots of their own, marked by
    a fourth bit."""

    flag_bits = 4

    def entries_of(self, times: np.ndarray) -> np.ndarray:
        more = np.maximum(times - 1, 0)
        digits = np.zeros(len(times), np.int64)
        while (more > 0).any():
            digits += more > 0
            more = more >> min(self.r, 62)
        return 1 + digits

    def fill(self, at: np.ndarray, rest: np.ndarray, times: np.ndarray) -> None:
        self.rest[at] = rest
        more, slot = np.maximum(times - 1, 0).astype(np.uint64), at + 1
        while (more > 0).any():
            rows = more > 0
            self.rest[slot[rows]] = more[rows] & np.uint64((1 << self.r) - 1)
            self.flags[slot[rows]] |= self.COUNTER
            more, slot = more >> np.uint64(min(self.r, 63)), slot + 1

    def count(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        quotient, rest = self.parts(hi, lo)
        out, place = np.zeros(len(quotient), np.int64), np.full(len(quotient), -1, np.int64)
        for rows, slot in self.walk(quotient):
            digit = self.flags[slot] & self.COUNTER > 0
            hit = ~digit & (self.rest[slot] == rest[rows])
            # After its remainder a key's digits come until the next remainder.
            place[rows[~digit]] = -1
            out[rows[hit]], place[rows[hit]] = 1, 0
            more = digit & (place[rows] >= 0)
            at = rows[more]
            out[at] += (self.rest[slot[more]].astype(np.int64)) << (place[at] * self.r)
            place[at] += 1
        return out

    def grouped(self, quotient: np.ndarray, slot: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        digit = self.flags[slot] & self.COUNTER > 0
        head = np.flatnonzero(~digit)
        of = np.cumsum(~digit) - 1
        times = np.ones(len(head), np.int64)
        step = np.arange(len(slot)) - head[of] - 1 if len(head) else np.zeros(0, np.int64)
        np.add.at(times, of[digit], self.rest[slot[digit]].astype(np.int64) << (step[digit] * self.r))
        return quotient[head], self.rest[slot[head]], times


DYNAMIC = {"cuckoo": Cuckoo, "morton": Morton, "quotient": Quotient, "counting_quotient": CountingQuotient}


class DynamicTable:
    """value() protocol over a dynamic filter: 1 for members, or the count."""

    def __init__(self, kind: str, keys: Keys, r: int) -> None:
        self.counting = kind == "counting_quotient"
        for attempt in range(10):
            self.filter = DYNAMIC[kind](int(len(keys) * (1 + 0.05 * attempt)), r)
            if self.counting:
                self.filter.insert(keys.hi, keys.lo, keys.value.astype(np.int64))
                return
            if self.filter.insert(keys.hi, keys.lo):
                return
        raise RuntimeError(f"{kind} does not fit")

    def value(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        return (self.filter.count if self.counting else self.filter.contains)(hi, lo).astype(np.uint64)

    def bits(self) -> float:
        return self.filter.bits()


FUNCTION_KINDS = {
    **{k: build_peeling for k in PEELING}, **{k: build_gauss for k in GAUSS_LOAD}, "sorted_gauss": build_sorted_gauss,
    "meta_buckets": build_meta_buckets, "multilevel": build_multilevel,
}
KERNEL_KINDS = {**FUNCTION_KINDS, **{k: DynamicTable for k in DYNAMIC}}


@dataclass
class Baseline:
    """Built shards: (shard, n, bits, payload), kept in the shared folder. A payload is this
    module's own object, written and read by the same program only."""

    kind: str
    r: int
    n_shards: int
    is_filter: bool
    table: DataFrame


SHARD_KEYS = 1 << 18


def build(kind: str, df: DataFrame, cols: list[str], value: str | None = None, r: int = 8, n_shards: int | None = None) -> Baseline:
    """Any kernel kind; without a value column a filter of r bits. Shards have some SHARD_KEYS
    keys, so that a small table is one shard."""
    if n_shards is None:
        n_shards = band.n_shards_for(band.approximate_keys(df, cols, "xx128", 1), SHARD_KEYS)
    if value is None and kind != "counting_quotient":
        pairs = band.digests(df, cols, "xx128", 1).distinct().withColumn("value", hashing.fingerprint_column(F.col("lo"), r))
    elif kind == "counting_quotient":
        pairs = band.digests(df, cols, "xx128", 1).groupBy("hi", "lo").agg(F.count(F.lit(1)).alias("value"))
    else:
        pairs = band.unique_pairs(df, cols, value, r, "xx128", 1)
    dealt = pairs.select(hashing.shard_column(F.col("hi"), n_shards).alias("shard"), "hi", "lo", "value")
    dealt = dealt.repartition(n_shards, "shard").sortWithinPartitions("shard")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in band.shard_groups(batches):
            for s, keys in group.items():
                made = narrow(KERNEL_KINDS[kind](kind, keys, r))
                yield pa.record_batch(
                    [pa.array([s], pa.int32()), pa.array([len(keys)], pa.int64()), pa.array([float(made.bits())]), pa.array([pickle.dumps(made)], pa.binary())],
                    names=["shard", "n", "bits", "payload"],
                )

    return Baseline(kind, r, n_shards, value is None, keep(dealt.mapInArrow(run, "shard int, n long, bits double, payload binary"), kind))


#: Rows of an answer at a time: those of many shards, so that each shard has some thousands, and
#: those of one shard, so that what is computed of them stays in a core's cache.
ASKED_ROWS, BLOCK_ROWS = 1 << 18, 1 << 14

_held: dict[str, dict] = {}


def _loaded(name: str, shared) -> dict:
    """Tables of the broadcast, loaded once by a worker and not by each of its tasks."""
    if name not in _held:
        _held.clear()
        _held[name] = {s: pickle.loads(x) for s, x in shared.value.items()}
    return _held[name]


def _blocks(batches: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[tuple[pa.Array, pa.Array]]:
    """The same rows in the same order, some ASKED_ROWS at a time."""
    parts: list[tuple[pa.Array, pa.Array]] = []
    for batch in batches:
        parts.append(batch)
        if sum(len(hi) for hi, _ in parts) >= ASKED_ROWS:
            yield tuple(pa.concat_arrays(x) for x in zip(*parts, strict=True))
            parts = []
    if parts:
        yield tuple(pa.concat_arrays(x) for x in zip(*parts, strict=True))


def _narrowed(x: np.ndarray) -> np.ndarray:
    """The same numbers in as few bytes each as hold them."""
    return x.astype(np.min_scalar_type(int(x.max(initial=0)))) if x.dtype == np.uint64 else x


def narrow(made: object) -> object:
    """A table as it is stored: with entries no wider than they need."""
    if isinstance(made, DynamicTable):
        if isinstance(made.filter, Morton) and made.filter.entries is None:
            made.filter.compress()
        narrow(made.filter)
    for name in ("z", "table", "entries"):
        x = getattr(made, name, None)
        if x is not None:
            setattr(made, name, [_narrowed(y) for y in x] if isinstance(x, list) else _narrowed(x))
    return made


def _query_filters(bs: list[Baseline], df: DataFrame, cols: list[str], out: str) -> DataFrame:
    """Membership in each of some filters of as many shards, as an array: probes are digested and
    dealt to shards once for all of them."""
    from .lookup import BROADCAST_BYTES, HI, LO, OUT

    n_shards = bs[0].n_shards
    if not all(b.is_filter and b.kind != "counting_quotient" and b.n_shards == n_shards for b in bs) or len(bs) > 63:
        raise ValueError("up to 63 filters of as many shards go together")
    sizes = [b.table.agg(F.sum(F.length("payload"))).first()[0] or 0 for b in bs]
    if sum(sizes) > BROADCAST_BYTES:
        one = [f"_member{i}" for i in range(len(bs))]
        for b, name in zip(bs, one, strict=True):
            df = query(b, df, cols, name)
        return df.withColumn(out, F.array(*one)).drop(*one)
    payloads = {(i, r[0]): bytes(r[1]) for i, b in enumerate(bs) for r in b.table.select("shard", "payload").collect()}
    shared, name = df.sparkSession.sparkContext.broadcast(payloads), uuid.uuid4().hex
    kinds, widths = [b.kind for b in bs], [b.r for b in bs]

    @F.arrow_udf("bigint")
    def look(batches: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[pa.Array]:
        made = _loaded(name, shared)
        for hi, lo in _blocks(batches):
            null = np.asarray(hi.is_null())
            h, low = (np.asarray(x.fill_null(0)).astype(np.int64).view(np.uint64) for x in (hi, lo))
            value = np.zeros(len(h), np.uint64)
            for s, at in _by_shard(hashing.shard_of(h, n_shards)):
                own = h[at], low[at]
                for i, (kind, r) in enumerate(zip(kinds, widths, strict=True)):
                    if (i, s) in made:
                        got = made[i, s].value(*own)
                        value[at] |= (got == (1 if kind in DYNAMIC else hashing.fingerprint(own[1], r))).astype(np.uint64) << np.uint64(i)
            yield pa.array(value.view(np.int64), mask=null)

    got = hashing.with_digest(df, cols, "xx128", 1, HI, LO).withColumn(OUT, look(HI, LO))
    return got.withColumn(out, F.array(*[F.getbit(OUT, F.lit(i)) == 1 for i in range(len(bs))])).drop(HI, LO, OUT)


def _by_shard(shard: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(shard, rows), BLOCK_ROWS rows at most at a time."""
    order = np.argsort(shard, kind="stable")
    for rows in np.split(order, np.flatnonzero(np.diff(shard[order])) + 1):
        for part in np.split(rows, range(BLOCK_ROWS, len(rows), BLOCK_ROWS)):
            if len(part):
                yield int(shard[part[0]]), part


def query(b: Baseline | list[Baseline], df: DataFrame, cols: list[str], out: str = "value", strategy: str = "auto") -> DataFrame:
    """Value of a function; membership of a filter; count of a counting filter; an array of the
    memberships in several filters. Shards are broadcast within the limit of band lookups; beyond
    it probes meet them by shard."""
    from .lookup import BROADCAST_BYTES, HI, LO, OUT, SHARD, by_shard

    if isinstance(b, list):
        return _query_filters(b, df, cols, out)
    if strategy == "auto":
        size = b.table.agg(F.sum(F.length("payload"))).first()[0] or 0
        strategy = "broadcast" if size <= BROADCAST_BYTES else "shuffle"
    n_shards, r, kind, is_filter = b.n_shards, b.r, b.kind, b.is_filter

    def answers(made: dict, hi: pa.Array, lo: pa.Array, _=None) -> pa.Array:
        null = np.asarray(hi.is_null())
        h, low = (np.asarray(x.fill_null(0)).astype(np.int64).view(np.uint64) for x in (hi, lo))
        shard, value = hashing.shard_of(h, n_shards), np.zeros(len(h), np.uint64)
        for s, at in _by_shard(shard):
            if s in made:
                value[at] = made[s].value(h[at], low[at])
        if is_filter and kind not in DYNAMIC:
            value = (value == hashing.fingerprint(low, r)).astype(np.uint64)
        return pa.array(value.view(np.int64), mask=null)

    keyed = hashing.with_digest(df, cols, "xx128", 1, HI, LO)
    if strategy == "broadcast":
        shared = df.sparkSession.sparkContext.broadcast({r[0]: bytes(r[1]) for r in b.table.select("shard", "payload").collect()})
        name = uuid.uuid4().hex

        @F.arrow_udf("bigint")
        def look(batches: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[pa.Array]:
            made = _loaded(name, shared)
            for hi, lo in _blocks(batches):
                yield answers(made, hi, lo)

        got = keyed.withColumn(OUT, look(HI, LO))
    else:

        def decode(rows: pa.RecordBatch) -> dict:
            return {s: pickle.loads(x) for s, x in zip(rows.column("shard").to_pylist(), rows.column("payload").to_pylist(), strict=True)}

        keyed = keyed.withColumn(SHARD, hashing.shard_column(F.col(HI), n_shards))
        got = by_shard(b.table, keyed, SHARD, "bigint", decode, answers, n_shards).drop(SHARD)
    value = F.col(OUT) == 1 if is_filter and kind != "counting_quotient" else F.col(OUT)
    return got.withColumn(out, value).drop(HI, LO, OUT)


# ---- Bloom filters in SQL -------------------------------------------------------------------


@dataclass
class Bloom:
    """(word, bits) rows of a bit array of n_words 64-bit words. blocks: 0 for the plain kind,
    else how many 512-bit blocks a key's bits lie in."""

    n_words: int
    k: int
    blocks: int
    algo: str
    table: DataFrame


def bloom_positions(hi: Column, lo: Column, n_words: int, k: int, blocks: int) -> Column:
    """Positions of a key's k bits, from 31-bit parts of its digest (products fit a long)."""
    a, b = hi.bitwiseAND(F.lit((1 << 30) - 1)), lo.bitwiseAND(F.lit((1 << 30) - 1)).bitwiseOR(F.lit(1))
    if not blocks:
        return F.array(*[F.pmod(a + b * i + F.lit(i * i), F.lit(n_words * 64)) for i in range(k)])
    n_blocks = max(1, n_words // 8)
    out = []
    for i in range(k):
        block = F.pmod(F.shiftright(hi, 30) + F.lit(i % blocks) * F.shiftright(lo, 30), F.lit(n_blocks))
        out.append(block * 512 + F.pmod(a + b * i + F.lit(i * i), F.lit(512)))
    return F.array(*out)


def build_bloom(
    df: DataFrame, cols: list[str], bits_per_key: float = 12.0, k: int = 0, blocks: int = 0, algo: str = "md5", n: int | None = None
) -> Bloom:
    n = df.count() if n is None else n
    n_words = max(8, -(-int(math.ceil(n * bits_per_key)) // 64))
    n_words += -n_words % 8
    k = k or max(1, round(bits_per_key * math.log(2)))
    keyed = band.digests(df, cols, algo, 1)
    at = keyed.select(F.explode(bloom_positions(F.col("hi"), F.col("lo"), n_words, k, blocks)).alias("p"))
    one = F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod("p", F.lit(64)).cast("int"))
    table = at.groupBy(F.floor(F.col("p") / 64).alias("word")).agg(F.bit_or(one).alias("bits"))
    return Bloom(n_words, k, blocks, algo, table)


def query_bloom(b: Bloom, df: DataFrame, cols: list[str], out: str = "member") -> DataFrame:
    """Exact evaluation in SQL: positions that are set are counted by key digest. Probes meet
    the bit table by a join on the word."""
    keyed = hashing.with_digest(df, cols, b.algo, 1, "_hi", "_lo")
    probes = keyed.select("_hi", "_lo").where(F.col("_hi").isNotNull()).distinct()
    wanted = probes.select("_hi", "_lo", F.explode(bloom_positions(F.col("_hi"), F.col("_lo"), b.n_words, b.k, b.blocks)).alias("p"))
    bit = F.call_function("shiftrightunsigned", F.col("bits"), F.pmod("p", F.lit(64)).cast("int")).bitwiseAND(F.lit(1))
    missing = (
        wanted.withColumn("word", F.floor(F.col("p") / 64))
        .join(b.table, "word", "left")
        .withColumn("set", F.coalesce(bit, F.lit(0)))
        .groupBy("_hi", "_lo")
        .agg((F.min("set") == 1).alias(out))
    )
    return keyed.join(missing, ["_hi", "_lo"], "left").drop("_hi", "_lo")


def bloom_overhead(df: DataFrame, foreign: DataFrame, cols: list[str], n: int, blocks: int, bits_per_key: float = 12.0, k: int = 8) -> float:
    """Bits against n log2(1 / rate) by the rate among foreign keys, each under 8 further digests."""
    b = build_bloom(df, cols, bits_per_key, k, blocks, "xx128", n)
    probes, hits = 0, 0
    for i in range(8):
        away = foreign.select(*[(F.col(c) + F.lit(i * 7_000_000_007)).alias(c) for c in cols])
        got = query_bloom(b, away, cols, "m").agg(F.count(F.lit(1)), F.sum(F.col("m").cast("long"))).first()
        probes, hits = probes + got[0], hits + got[1]
    return b.n_words * 64 / (n * math.log2(probes / max(1, hits))) - 1


def count_after_deletes(df: DataFrame, cols: list[str], gone: Column, r: int) -> Baseline:
    """A counting filter over all rows, out of which the rows of `gone` are deleted again, each
    deletion a call on the filter."""
    n_shards = band.n_shards_for(band.approximate_keys(df, cols, "xx128", 1), SHARD_KEYS)
    keyed = hashing.with_digest(df.select(*cols, gone.alias("_gone")), cols).where(F.col("hi").isNotNull())
    counts = keyed.groupBy("hi", "lo").agg(F.count(F.lit(1)).alias("value"), F.sum(F.col("_gone").cast("long")).alias("gone"))
    dealt = counts.select(hashing.shard_column(F.col("hi"), n_shards).alias("shard"), "hi", "lo", "value", "gone").repartition(n_shards, "shard")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = list(batches)
        if not parts:
            return  # shards are dealt by a hash, so a partition may have none
        rows = pa.Table.from_batches(parts)  # some SHARD_KEYS keys a shard
        shards = rows.column("shard").to_numpy()
        for s in np.unique(shards):
            part = rows.filter(pa.array(shards == s))
            hi, lo = (part.column(c).to_numpy().view(np.uint64) for c in ("hi", "lo"))
            value, less = part.column("value").to_numpy(), part.column("gone").to_numpy().copy()
            made = DynamicTable("counting_quotient", Keys(hi, lo, value.view(np.uint64)), r)
            while (less > 0).any():
                made.filter.delete(hi[less > 0], lo[less > 0])
                less = less - (less > 0)
            yield pa.record_batch(
                [pa.array([s], pa.int32()), pa.array([len(hi)], pa.int64()), pa.array([float(made.bits())]), pa.array([pickle.dumps(made)], pa.binary())],
                names=["shard", "n", "bits", "payload"],
            )

    table = keep(dealt.mapInArrow(run, "shard int, n long, bits double, payload binary"), "counting")
    return Baseline("counting_quotient", r, n_shards, True, table)


def exact_lookup(pairs: DataFrame, df: DataFrame, cols: list[str], value: str) -> DataFrame:
    """The dictionary that stores keys: a join."""
    return df.join(pairs.select(*cols, value).dropDuplicates(cols), cols, "left")
