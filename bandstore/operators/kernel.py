"""Elimination and back-substitution over GF(2) band systems.

`ScalarEliminator` takes rows one by one, of any width. `eliminate` advances many independent
lanes (pieces of shards) together with numpy: every step does one row operation, or places
one row, in each lane. Both keep rows in echelon form and never change a stored row, so the
latest insertions can be taken back by emptying their slots."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field

import numpy as np

PLACED, REDUNDANT, BUMPED, FAILED = 1, 2, 3, 4
_ONE, _ZERO = np.uint64(1), np.uint64(0)


@dataclass
class ScalarEliminator:
    """m slots of (coefficients, value), coefficients as Python integers with bit 0 set."""

    m: int
    coefs: dict[int, int] = field(default_factory=dict)
    values: dict[int, int] = field(default_factory=dict)
    journal: list[int] = field(default_factory=list)
    row_ops: int = 0

    def insert(self, start: int, coef: int, value: int, dry: bool = False) -> tuple[int, int]:
        """(PLACED, slot), (REDUNDANT, -1) or (FAILED, -1). A dry run stores nothing."""
        while True:
            have = self.coefs.get(start)
            if have is None:
                if not dry:
                    self.coefs[start], self.values[start] = coef, value
                    self.journal.append(start)
                return PLACED, start
            coef, value = coef ^ have, value ^ self.values[start]
            self.row_ops += 1
            if coef == 0:
                return (REDUNDANT if value == 0 else FAILED), -1
            zeros = (coef & -coef).bit_length() - 1
            start, coef = start + zeros, coef >> zeros

    def mark(self) -> int:
        return len(self.journal)

    def rollback(self, mark: int) -> None:
        for slot in self.journal[mark:]:
            del self.coefs[slot], self.values[slot]
        del self.journal[mark:]

    def insert_all(self, rows: Iterable[tuple[int, int, int]]) -> bool:
        """Insert a group of rows as a whole; if one of them fails, none of them stays."""
        mark = self.mark()
        for row in rows:
            if self.insert(*row)[0] == FAILED:
                self.rollback(mark)
                return False
        return True

    def solve(self, free=lambda slot: 0) -> list[int]:
        """Values of all slots, from the right."""
        z = [0] * self.m
        for slot in range(self.m - 1, -1, -1):
            coef = self.coefs.get(slot)
            if coef is None:
                z[slot] = free(slot)
                continue
            total, at, coef = self.values[slot], slot + 1, coef >> 1
            while coef:
                zeros = (coef & -coef).bit_length() - 1
                at += zeros
                total ^= z[at]
                coef, at = coef >> (zeros + 1), at + 1
            z[slot] = total
        return z


def longest_prefix(rows: list[tuple[int, int, int]], m: int) -> int:
    """How many rows can be inserted, in order, before the first contradiction."""
    system = ScalarEliminator(m)
    for n, row in enumerate(rows):
        if system.insert(*row)[0] == FAILED:
            return n
    return len(rows)


def trailing_zeros(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count((x & (~x + _ONE)) - _ONE).astype(np.uint64)


@dataclass
class System:
    """Slots of all lanes; an empty slot has coefficient 0."""

    c: list[np.ndarray]
    v: np.ndarray

    @classmethod
    def empty(cls, m: int, words: int) -> System:
        return cls([np.zeros(m, np.uint64) for _ in range(words)], np.zeros(m, np.uint64))


@dataclass
class Outcome:
    status: np.ndarray
    slot: np.ndarray
    row_ops: int
    failed_lanes: np.ndarray


def eliminate(
    system: System,
    start: np.ndarray,
    c: list[np.ndarray],
    v: np.ndarray,
    lane: np.ndarray,
    bucket: np.ndarray,
    pos: np.ndarray,
    thresholds: np.ndarray,
    allowed: np.ndarray | None,
    must: np.ndarray | None = None,
    spill_limit: int = -1,
    bucket_end: np.ndarray | None = None,
) -> Outcome:
    """Insert rows into the system. Rows come sorted by lane, then bucket in the order of
    processing, then pos descending; lanes have slots of their own. At a contradiction the
    bucket's threshold becomes the least allowed one above the row's pos, and all rows of the
    bucket below it are bumped. Without `allowed`, or for a row in `must`, the lane fails.

    spill_limit >= 0: a bucket that fills slots further beyond its end than that is backed
    off by one allowed threshold (the cautious mode); bucket_end gives slot ends by bucket."""
    n, wide = len(start), len(c) == 2
    status, slot = np.zeros(n, np.int8), np.full(n, -1, np.int64)
    if not n:
        return Outcome(status, slot, 0, np.zeros(0, np.int64))
    new_lane = np.flatnonzero(np.diff(lane)) + 1
    begins, ends = np.concatenate([[0], new_lane]), np.concatenate([new_lane, [n]])
    cuts = np.flatnonzero((np.diff(bucket) != 0) | (np.diff(lane) != 0) | (np.diff(must.astype(np.int8)) != 0 if must is not None else False)) + 1
    first_row = np.zeros(n, np.int64)
    first_row[cuts] = cuts
    first_row = np.maximum.accumulate(first_row)
    edges = np.concatenate([cuts, [n]])
    next_row = edges[np.searchsorted(edges, np.arange(n), "right")]
    failed: list[int] = []

    def back_off(row: int, at: int, t: int) -> int:
        """Bump the bucket's rows below t; `at` is the row that comes next in its order."""
        a, z = int(first_row[row]), int(next_row[row])
        low = a + int(np.searchsorted(-pos[a:z], -t, "right"))
        thresholds[bucket[row]] = max(int(thresholds[bucket[row]]), t)
        gone = slot[low:at]
        gone = gone[gone >= 0]
        for word in system.c:
            word[gone] = 0
        system.v[gone] = 0
        slot[low:z], status[low:z] = -1, BUMPED
        return z

    cur, end = begins.copy(), ends.copy()
    i, x, y = start[cur], c[0][cur], v[cur]
    x1 = c[1][cur] if wide else None
    ops = 0
    while len(cur):
        have = system.c[0][i]
        empty = have == 0
        held = system.v[i]
        e = np.flatnonzero(empty)
        if e.size:
            at, rows = i[e], cur[e]
            system.c[0][at], system.v[at] = x[e], y[e]
            if wide:
                system.c[1][at] = x1[e]
            slot[rows], status[rows] = at, PLACED
        ops += len(cur) - e.size
        if wide:
            have1 = np.where(empty, _ZERO, system.c[1][i])
            x1 = x1 ^ have1
        x = x ^ have
        y = y ^ held
        void = ~empty & (x == 0)
        if wide:
            void &= x1 == 0
        done = empty | void
        if wide:
            far = (x == 0) & ~done
            j = trailing_zeros(np.where(far, x1, x))
            j = np.where(done, _ONE, j)
            low = np.where(far, x1, x)
            shifted = low >> j
            carry = np.where(far | (j == 0), _ZERO, x1 << ((np.uint64(64) - j) & np.uint64(63)))
            x = shifted | carry
            x1 = np.where(far, _ZERO, x1 >> j)
            i = i + np.where(done, 0, (j + np.where(far, np.uint64(64), _ZERO)).astype(np.int64))
        else:
            j = np.where(done, _ZERO, trailing_zeros(x))
            i = i + j.astype(np.int64)
            x = x >> j
        d = np.flatnonzero(done)
        if not d.size:
            continue
        following = cur[d] + 1
        z = void[d]
        if z.any():
            which = np.flatnonzero(z)
            redundant = y[d[which]] == 0
            status[cur[d[which[redundant]]]] = REDUNDANT
            for k in which[~redundant]:
                row = int(cur[d[k]])
                if allowed is None or (must is not None and must[row]):
                    status[row] = FAILED
                    failed.append(int(lane[row]))
                    following[k] = end[d[k]]
                else:
                    t = int(allowed[np.searchsorted(allowed, pos[row] + 1)])
                    following[k] = back_off(row, row, t)
        if spill_limit >= 0 and allowed is not None:
            for k in np.flatnonzero(following == next_row[cur[d]]):
                row = int(cur[d[k]])
                a, zz = int(first_row[row]), int(next_row[row])
                if must is not None and must[row]:
                    continue
                if zz > a and slot[a:zz].max(initial=-1) >= bucket_end[bucket[row]] + spill_limit:
                    t0 = int(thresholds[bucket[row]])
                    t = int(allowed[min(np.searchsorted(allowed, t0, "right"), len(allowed) - 1)])
                    back_off(row, zz, t)
        cur[d] = following
        alive = cur < end
        again = d[alive[d]]
        rows = cur[again]
        i[again], x[again], y[again] = start[rows], c[0][rows], v[rows]
        if wide:
            x1[again] = c[1][rows]
        if not alive.all():
            cur, end, i, x, y = cur[alive], end[alive], i[alive], x[alive], y[alive]
            if wide:
                x1 = x1[alive]
    return Outcome(status, slot, ops, np.unique(np.array(failed, np.int64)))


#: With fewer lanes than this, rows go one by one: a numpy step costs as much for one lane as
#: for a hundred.
LOCKSTEP_LANES = 96


def run_lanes(system: System, start, c, v, lane, bucket, pos, thresholds, allowed, must, spill_limit, bucket_end) -> Outcome:
    """eliminate(), or the same row by row for few lanes."""
    lanes = len(np.unique(lane)) if len(lane) else 0
    how = eliminate if lanes >= LOCKSTEP_LANES else eliminate_rows
    return how(system, start, c, v, lane, bucket, pos, thresholds, allowed, must, spill_limit, bucket_end)


def eliminate_rows(
    system: System, start, c, v, lane, bucket, pos, thresholds, allowed, must=None, spill_limit=-1, bucket_end=None
) -> Outcome:
    """The contract of eliminate(), with Python integers, one row after the other."""
    n = len(start)
    coefs, values = {}, {}
    rows_start = start.tolist()
    rows_c = c[0].tolist()
    if len(c) == 2:
        rows_c = [a | (b << 64) for a, b in zip(rows_c, c[1].tolist(), strict=True)]
    rows_v, rows_lane, rows_bucket, rows_pos = v.tolist(), lane.tolist(), bucket.tolist(), pos.tolist()
    rows_must = must.tolist() if must is not None else [False] * n
    steps = allowed.tolist() if allowed is not None else []
    status, slot = [0] * n, [-1] * n
    failed, ops, row = set(), 0, 0
    while row < n:
        first, here, needs = row, (rows_lane[row], rows_bucket[row], rows_must[row]), rows_must[row]
        end = row
        while end < n and (rows_lane[end], rows_bucket[end], rows_must[end]) == here:
            end += 1
        if here[0] in failed:
            row = end
            continue
        bump_below = 0
        while row < end:
            i, x, y = rows_start[row], rows_c[row], rows_v[row]
            while True:
                have = coefs.get(i)
                if have is None:
                    coefs[i], values[i] = x, y
                    slot[row], status[row] = i, PLACED
                    break
                x ^= have
                y ^= values[i]
                ops += 1
                if not x:
                    status[row] = FAILED if y else REDUNDANT
                    break
                zeros = (x & -x).bit_length() - 1
                i += zeros
                x >>= zeros
            if status[row] == FAILED:
                if allowed is None or needs:
                    failed.add(here[0])
                    row = end
                    break
                bump_below = next(t for t in steps if t > rows_pos[row])
                break
            row += 1
        if spill_limit >= 0 and allowed is not None and not needs and not bump_below:
            if max(slot[first:end], default=-1) >= bucket_end[here[1]] + spill_limit:
                now = int(thresholds[here[1]])
                bump_below = next((t for t in steps if t > now), steps[-1])
        if bump_below:
            thresholds[here[1]] = max(int(thresholds[here[1]]), bump_below)
            for k in range(first, end):
                if rows_pos[k] < bump_below:
                    if slot[k] >= 0:
                        del coefs[slot[k]], values[slot[k]]
                        slot[k] = -1
                    status[k] = BUMPED
        row = end
    if coefs:
        at = np.fromiter(coefs.keys(), np.int64, len(coefs))
        system.v[at] = np.fromiter(values.values(), np.uint64, len(values))
        if len(c) == 2:
            system.c[0][at] = np.fromiter((x & (1 << 64) - 1 for x in coefs.values()), np.uint64, len(coefs))
            system.c[1][at] = np.fromiter((x >> 64 for x in coefs.values()), np.uint64, len(coefs))
        else:
            system.c[0][at] = np.fromiter(coefs.values(), np.uint64, len(coefs))
    return Outcome(np.array(status, np.int8), np.array(slot, np.int64), ops, np.array(sorted(failed), np.int64))


def insert_until(end: int, start: list[int], coef: list[int], value: list[int]) -> tuple[list[int], list[int], list[tuple[int, int, int]]] | None:
    """Insert rows into slots 0 to end - 1: their coefficients and values, and the rows that got to
    `end` without a slot, as they were then. None at a contradiction."""
    coefs, values, over = [0] * end, [0] * end, []
    for i, x, y in zip(start, coef, value, strict=True):
        while i < end:
            have = coefs[i]
            if not have:
                coefs[i], values[i] = x, y
                break
            x ^= have
            y ^= values[i]
            if not x:
                if y:
                    return None
                break
            zeros = (x & -x).bit_length() - 1
            i += zeros
            x >>= zeros
        else:
            over.append((i, x, y))
    return coefs, values, over


def back_substitute(
    system: System, r: int, lo: np.ndarray, hi: np.ndarray, free: np.ndarray | None = None
) -> np.ndarray:
    """Solution of every slot as an r-bit number. Lane k owns slots lo[k]..hi[k]-1, and its
    rows touch no others. Lanes advance together, from the right; a lane keeps one window of
    solution bits for each value bit."""
    z = np.zeros(len(system.v), np.uint64) if free is None else np.where(system.c[0] == 0, free, _ZERO)
    order = np.argsort(lo - hi, kind="stable")  # longest lanes first
    lo, hi = lo[order], hi[order]
    length = hi - lo
    wide = len(system.c) == 2
    shifts = np.arange(r, dtype=np.uint64)[None, :]
    window = np.zeros((len(lo), r), np.uint64)
    window1 = np.zeros((len(lo), r), np.uint64) if wide else None
    n = len(lo)
    for step in range(int(length.max(initial=0))):
        while n and length[n - 1] <= step:
            n -= 1
        at = hi[:n] - 1 - step
        c0 = system.c[0][at]
        filled = c0 != 0
        low = c0 >> _ONE
        if wide:
            c1 = system.c[1][at]
            low = low | (c1 << np.uint64(63))
            parity = np.bitwise_count(low[:, None] & window[:n]) ^ np.bitwise_count((c1 >> _ONE)[:, None] & window1[:n])
        else:
            parity = np.bitwise_count(low[:, None] & window[:n])
        bits = (parity.astype(np.uint64) & _ONE) ^ ((system.v[at][:, None] >> shifts) & _ONE)
        if not filled.all():
            bits = np.where(filled[:, None], bits, (z[at][:, None] >> shifts) & _ONE)
        z[at] = (bits << shifts).sum(axis=1, dtype=np.uint64)
        if wide:
            window1[:n] = (window1[:n] << _ONE) | (window[:n] >> np.uint64(63))
        window[:n] = (window[:n] << _ONE) | bits
    return z


def interleave(z: np.ndarray, r: int) -> np.ndarray:
    """r words for each block of 64 slots; word q has bit q of the block's slots. One block of
    padding, as a window may reach into the next."""
    blocks = -(-len(z) // 64) + 2
    padded = np.zeros(blocks * 64, np.uint64)
    padded[: len(z)] = z
    out = np.empty((blocks, r), np.uint64)
    for q in range(r):
        bits = ((padded >> np.uint64(q)) & _ONE).astype(np.uint8)
        out[:, q] = np.packbits(bits, bitorder="little").view("<u8")
    return out.reshape(-1)
