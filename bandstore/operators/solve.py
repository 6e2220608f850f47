"""Solve all layers of the shards that a task holds, in numpy.

A layer's table of all shards is one flat system; each shard has its own range of slots, and
is cut into pieces whose first starts are bumped so that pieces do not touch. Shards and
pieces are the lanes of the kernel."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from ..functions import hashing
from ..params import BandParams
from . import kernel


@dataclass
class LayerTable:
    """One layer of one shard."""

    shard: int
    layer: int
    attempt: int
    w: int
    n_starts: int
    m: int
    z: np.ndarray
    thresholds: np.ndarray
    stats: dict


@dataclass
class Keys:
    hi: np.ndarray
    lo: np.ndarray
    value: np.ndarray

    def take(self, at: np.ndarray) -> Keys:
        return Keys(self.hi[at], self.lo[at], self.value[at])

    def __len__(self) -> int:
        return len(self.hi)

    @staticmethod
    def concat(parts: list[Keys]) -> Keys:
        return Keys(*[np.concatenate([getattr(p, f) for p in parts]) for f in ("hi", "lo", "value")])


def table_starts(n: int, eps: float, kind: str) -> int:
    """Number of legal starts for n keys."""
    size = n / (1 - eps) if kind in ("plain", "zero") else (1 + eps) * n
    return max(1, int(np.ceil(size)))


def position_of(start: np.ndarray, hi: np.ndarray, b: int, order: str, n_starts: int, layer: int, attempt: int) -> np.ndarray:
    """Place of a key within its bucket's processing, from b - 1 down: a key is bumped if its
    place lies below the bucket's threshold."""
    offset = start % b
    if order == "r2l":
        return offset
    if order == "l2r":
        return b - 1 - offset
    if order == "hash":
        return (hashing.remix(hi, hashing.layer_round(3, layer, attempt)) % np.uint64(b)).astype(np.int64)
    raise ValueError(f"unknown order {order}")


def gap(n_starts: int, p: BandParams, allowed: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    """(piece bounds as starts, thresholds forced at buckets): the first buckets of every
    piece but the first are bumped up to w - 1 starts or the next allowed threshold."""
    n_buckets = -(-n_starts // p.b)
    forced = np.zeros(n_buckets, np.int32)
    per_piece = max(1, p.piece_starts // p.b, -(-2 * p.w // p.b))
    bounds = np.arange(0, n_buckets, per_piece)
    if allowed is None or p.order != "r2l" or p.bucket_order != "l2r" or len(bounds) == 1:
        return np.array([0, n_starts]), forced
    if n_buckets - bounds[-1] < max(2, -(-p.w // p.b) + 1):
        bounds = bounds[:-1]
    for first in bounds[1:]:
        need, bucket = p.w - 1, first
        while need > 0 and bucket < n_buckets:
            t = p.b if need >= p.b else int(allowed[np.searchsorted(allowed, need)])
            forced[bucket] = t
            need, bucket = need - p.b, bucket + 1
    return np.concatenate([bounds * p.b, [n_starts]]), forced


def _free_values(p: BandParams, m: int, shard: int, layer: int) -> np.ndarray | None:
    if p.free == "zero":
        return None
    slots = np.arange(m, dtype=np.uint64)
    mask = np.uint64((1 << p.r) - 1)
    if p.free == "affine":
        return (slots * np.uint64(0x9E3779B97F4A7C15 | 1)) >> np.uint64(64 - p.r) & mask if p.r < 64 else slots
    return hashing.remix(slots + np.uint64(shard) * np.uint64(1 << 32), 100 + p.seed + layer) & mask


@dataclass
class Job:
    """One layer of one shard, to be solved."""

    keys: Keys
    layer: int
    attempt: int
    shard: int
    n_starts: int
    must: np.ndarray | None = None


def solve_layer(jobs: list[Job], p: BandParams, w: int, bumping: bool, values: bool = True) -> list[tuple[LayerTable | None, np.ndarray]]:
    """Solve many shards' layers together: (table, bumped mask) of each, or None for a table if
    a row had to fit and did not. Without `values` the tables stay empty: only figures are wanted."""
    allowed = np.array(p.thresholds()) if bumping else None
    columns: list[tuple] = []
    plans = []
    slot_base = bucket_base = lane_base = 0
    for job in jobs:
        n_starts, keys = job.n_starts, job.keys
        start = hashing.starts(keys.hi, n_starts, job.layer, job.attempt)
        c = hashing.coefficients(keys.lo, w, p.coef if w == p.w else "dense", job.layer, job.attempt)
        n_buckets = -(-n_starts // p.b)
        if bumping and job.must is None:
            bounds, forced = gap(n_starts, p, allowed)
        else:
            bounds, forced = np.array([0, n_starts]), np.zeros(n_buckets, np.int32)
        bucket = start // p.b
        pos = start % p.b
        if bumping:
            pos = position_of(start, keys.hi, p.b, p.order, n_starts, job.layer, job.attempt)
        before = pos < forced[bucket]
        piece = np.searchsorted(bounds, start, "right") - 1
        rank = bucket if p.bucket_order == "l2r" else n_buckets - 1 - bucket
        must = np.zeros(len(start), bool) if job.must is None else job.must
        order = np.lexsort((-pos, rank, ~must, piece))
        order = order[~before[order]]
        ends = slot_base + np.minimum((np.arange(n_buckets) + 1) * p.b, n_starts)
        columns.append(
            (start[order] + slot_base, [x[order] for x in c], keys.value[order], piece[order] + lane_base,
             bucket[order] + bucket_base, pos[order], forced, must[order], ends)
        )
        plans.append((slot_base, bucket_base, lane_base, bounds, before, order))
        slot_base += n_starts + w - 1
        bucket_base += n_buckets
        lane_base += len(bounds) - 1
    join = lambda k: np.concatenate([x[k] for x in columns])
    words = [np.concatenate([x[1][k] for x in columns]) for k in range(len(columns[0][1]))]
    system = kernel.System.empty(slot_base, len(words))
    thresholds, must = join(6), join(7)
    got = kernel.run_lanes(
        system, join(0), words, join(2), join(3), join(4), join(5), thresholds, allowed, must if must.any() else None,
        p.w // 2 if bumping and p.mode == "cautious" else -1, join(8),
    )
    failed = set(got.failed_lanes.tolist())
    lows, highs, owner = [], [], []
    results: list[tuple[LayerTable | None, np.ndarray]] = []
    row = 0
    for k, (job, (base, bucket0, lane0, bounds, bumped, order)) in enumerate(zip(jobs, plans, strict=True)):
        status = got.status[row : row + len(order)]
        row += len(order)
        pieces = len(bounds) - 1
        m = job.n_starts + w - 1
        if any(lane in failed for lane in range(lane0, lane0 + pieces)):
            results.append((None, bumped))
            continue
        bumped[order[status == kernel.BUMPED]] = True
        lo = base + np.concatenate([[0], bounds[1:-1] + w - 1])
        lows.append(lo)
        highs.append(np.concatenate([lo[1:], [base + m]]))
        owner.append(k)
        stats = {
            "n_in": len(job.keys), "n_bumped": int(bumped.sum()), "n_redundant": int((status == kernel.REDUNDANT).sum()),
            "empty": int((system.c[0][base : base + m] == 0).sum()), "row_ops": got.row_ops // len(jobs), "pieces": pieces,
        }
        own = thresholds[bucket0 : bucket0 + -(-job.n_starts // p.b)]
        results.append((LayerTable(job.shard, job.layer, job.attempt, w, job.n_starts, m, np.zeros(0), own, stats), bumped))
    if owner and values:
        free = None
        if p.free != "zero":
            free = np.zeros(slot_base, np.uint64)
            for k in owner:
                base, m = plans[k][0], jobs[k].n_starts + w - 1
                free[base : base + m] = _free_values(p, m, jobs[k].shard, jobs[k].layer)
        z = kernel.back_substitute(system, p.r, np.concatenate(lows), np.concatenate(highs), free)
        for k in owner:
            base, table = plans[k][0], results[k][0]
            own = z[base : base + table.m]
            table.z = own.copy() if p.layout == "contiguous" else kernel.interleave(own, p.r)
    return results


def in_span(hi: np.ndarray, lo: np.ndarray, p: BandParams, attempt: int, at: int, spans: int, sizes: list[int]) -> list[list[tuple[int, int]] | None]:
    """Of the plain systems with sizes[k] starts over all keys of a table, the span `at` of `spans`
    equal ones of the start hash, whose keys these are: None for a system with a contradiction, else
    the (coefficients, value) left over when the span's slots are eliminated. Coefficients are of
    the first w slots of the span and then of the next one. The whole systems have a solution
    if these rows of all spans have one, as no other row touches a span's other slots."""
    edge = [-(-(c << 32) // spans) for c in (at, at + 1)]
    rounds = hashing.remix(hi, hashing.layer_round(0, 0, attempt)) >> np.uint64(32)
    order = np.argsort(rounds, kind="stable")
    hi, lo = hi[order], lo[order]
    coefs = [x.tolist() for x in hashing.coefficients(lo, p.w, p.coef, 0, attempt)]
    coefs = [a | (b << 64) for a, b in zip(*coefs, strict=True)] if len(coefs) == 2 else coefs[0]
    values, found = hashing.fingerprint(lo, p.r).tolist(), []
    for n in sizes:
        first = edge[0] * n >> 32
        end = (n + p.w - 1 if at + 1 == spans else edge[1] * n >> 32) - first
        got = kernel.insert_until(end, (hashing.starts(hi, n, 0, attempt) - first).tolist(), coefs, values)
        found.append(_left_over(*got, p, at > 0) if got is not None else None)
    return found


def _left_over(coefs: list[int], values: list[int], over: list[tuple[int, int, int]], p: BandParams, inner: bool) -> list[tuple[int, int]] | None:
    """Rows on the w slots behind a span, and on its first w slots where a span lies before it: these
    stand in the values, above the r bits, and each of their slots gets a row of its own."""
    end, out, mask = len(coefs), [], (1 << p.r) - 1
    behind: dict[int, tuple[int, int]] = {}

    def leave(i: int, x: int, y: int) -> bool:
        """Whether the row is no contradiction."""
        while x:
            zeros = (x & -x).bit_length() - 1
            i, x = i + zeros, x >> zeros
            have = behind.get(i)
            if have is None:
                behind[i] = x, y
                return True
            x, y = x ^ have[0], y ^ have[1]
        if y > mask:
            out.append((y >> p.r, y & mask))
        return y > mask or not y

    if not all(leave(*row) for row in over):
        return None
    for j in range(p.w if inner else 0):
        i, x, y = j, 1, 1 << (p.r + j)
        while x and i < end:
            if not coefs[i]:
                coefs[i], values[i] = x, y
                break
            x, y = x ^ coefs[i], y ^ values[i]
            zeros = max(0, (x & -x).bit_length() - 1)
            i, x = i + zeros, x >> zeros
        else:
            leave(i, x, y)
    return out + [((y >> p.r) | (x << (p.w + i - end)), y & mask) for i, (x, y) in behind.items()]


def spans_fit(left: list[list[tuple[int, int]]], p: BandParams) -> bool:
    """Whether the rows that in_span() left over of all spans, in order, have a solution."""
    # Slots of the spans' first w, from the second span on; the first span has none before it.
    system = kernel.ScalarEliminator(p.w * len(left))
    for at, rows in enumerate(left):
        for coef, value in rows:
            zeros = (coef & -coef).bit_length() - 1
            if system.insert(p.w * at + zeros, coef >> zeros, value)[0] == kernel.FAILED:
                return False
    return True


def solve_shards(shards: dict[int, Keys], p: BandParams) -> list[LayerTable]:
    """All layers of some shards. Plain systems start over with new hashes until they fit; the
    last layer has at most 64 bits of width and grows by steps of 0.05 until it bumps none."""
    if p.kind == "twohop":
        return solve_two_hop(shards, p)
    if p.kind in ("plain", "zero"):
        return _until_fit(shards, p, 0, p.w, p.max_tries, lambda n, attempt: table_starts(n, p.eps, p.kind))
    tables: list[LayerTable] = []
    left = {s: k for s, k in shards.items() if len(k)}
    for layer in range(p.layers - 1):
        if not left:
            return tables
        again = dict(left)
        for attempt in range(p.max_tries):
            jobs = [Job(k, layer, attempt, s, table_starts(len(k), p.eps, "layered")) for s, k in again.items()]
            for job, (table, bumped) in zip(jobs, solve_layer(jobs, p, p.w, True), strict=True):
                if table.stats["empty"] > p.empty_limit * table.m and attempt + 1 < p.max_tries:
                    continue  # emptier than asked: start over with new hashes
                tables.append(table)
                left[job.shard] = job.keys.take(np.flatnonzero(bumped))
                del again[job.shard]
            if not again:
                break
        left = {s: k for s, k in left.items() if len(k)}
    return tables + _last_layer(left, p, p.layers - 1)


def _until_fit(shards: dict[int, Keys], p: BandParams, layer: int, w: int, tries: int, starts_for) -> list[LayerTable]:
    tables: list[LayerTable] = []
    left = {s: k for s, k in shards.items() if len(k)}
    for attempt in range(tries):
        jobs = [Job(k, layer, attempt, s, starts_for(len(k), attempt)) for s, k in left.items()]
        if not jobs:
            return tables
        for job, (table, _) in zip(jobs, solve_layer(jobs, p, w, False), strict=True):
            if table is not None:
                tables.append(table)
                del left[job.shard]
    if left:
        raise RuntimeError(f"shards {sorted(left)[:5]}: no system in {tries} tries; is eps {p.eps} too small, or are there equal keys with different values?")
    return tables


def _last_layer(shards: dict[int, Keys], p: BandParams, layer: int) -> list[LayerTable]:
    grow = lambda n, attempt: max(1, int(np.ceil((1 + 0.05 * attempt) * n)))
    return _until_fit(shards, p, layer, min(p.w, 64), 200, grow)


def primary_layer(hi: np.ndarray, alpha: float, layers: int) -> np.ndarray:
    """Leading zeros of a hash, up to the last layer but one; a share alpha of the keys that
    are not in the first layer move there."""
    h = hashing.remix(hi, hashing.POSITION_ROUND)
    top = h >> np.uint64(32)
    zeros = 31 - np.floor(np.log2(np.maximum(top, 1).astype(np.float64))).astype(np.int64)
    layer = np.minimum(zeros, layers - 2)
    moved = (h & np.uint64(0xFFFFFFFF)) < np.uint64(int(alpha * (1 << 32)))
    return np.where((layer > 0) & moved, 0, layer)


def solve_two_hop(shards: dict[int, Keys], p: BandParams) -> list[LayerTable]:
    """Keys live in their primary layer or the next one. Those bumped from the layer before
    are inserted first and must fit; otherwise the layer grows by (w + 1) / w."""
    alpha = max(0.0, -p.eps)
    primary = {s: primary_layer(k.hi, alpha, p.layers) for s, k in shards.items()}
    carried = {s: k.take(np.zeros(0, np.int64)) for s, k in shards.items()}
    tables: list[LayerTable] = []
    for layer in range(p.layers):
        both = {s: Keys.concat([carried[s], k.take(np.flatnonzero(primary[s] == layer))]) for s, k in shards.items()}
        for s in [s for s, k in both.items() if not len(k)]:
            # A later layer may have keys; an empty table keeps the numbering.
            nothing = np.zeros(64 + 128, np.uint64) if p.layout == "contiguous" else kernel.interleave(np.zeros(64, np.uint64), p.r)
            tables.append(LayerTable(s, layer, 0, min(p.w, 64), 1, 64, nothing, np.zeros(1, np.int32), _NOTHING))
            del both[s]
        if layer == p.layers - 1:
            return tables + _last_layer(both, p, layer)
        size = {s: (1 + p.eps) * len(k) for s, k in both.items()}
        if p.fixed_sizes:
            size = {s: (1 + p.eps) * len(shards[s]) * 2.0 ** -(layer + 1) * (1 + alpha) for s in both}
        for _ in range(400):
            if not both:
                break
            jobs = [
                Job(k, layer, 0, s, max(1, int(np.ceil(size[s]))), np.arange(len(k)) < len(carried[s])) for s, k in both.items()
            ]
            for job, (table, bumped) in zip(jobs, solve_layer(jobs, p, p.w, True), strict=True):
                if table is None:
                    size[job.shard] *= (p.w + 1) / p.w
                else:
                    tables.append(table)
                    carried[job.shard] = job.keys.take(np.flatnonzero(bumped))
                    del both[job.shard]
        else:
            raise RuntimeError("a layer does not settle")
    return tables


_NOTHING = {"n_in": 0, "n_bumped": 0, "n_redundant": 0, "empty": 64, "row_ops": 0, "pieces": 1}


def evaluate(
    tables: dict[tuple[int, int], LayerTable], hi: np.ndarray, lo: np.ndarray, shard: np.ndarray, p: BandParams
) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(value, layer that answered, found) for a batch of digests, straight from the tables."""
    n = len(hi)
    value, at_layer, found = np.zeros(n, np.uint64), np.full(n, -1, np.int32), np.zeros(n, bool)
    for s in np.unique(shard):
        rows = np.flatnonzero(shard == s)
        if p.kind == "twohop":
            first = primary_layer(hi[rows], max(0.0, -p.eps), p.layers)
            for layer in range(p.layers - 1):
                mine = rows[first == layer]
                table = tables.get((int(s), layer))
                if not len(mine) or table is None:
                    continue
                bumped = _bumped(table, hi[mine], p)
                _answer(table, mine[~bumped], hi, lo, p, value, at_layer, found)
                after = tables.get((int(s), layer + 1))
                if after is not None:
                    _answer(after, mine[bumped], hi, lo, p, value, at_layer, found)
            continue
        for layer in range(p.layers):
            table = tables.get((int(s), layer))
            if table is None or not len(rows):
                break
            bumped = _bumped(table, hi[rows], p) if p.kind == "layered" else np.zeros(len(rows), bool)
            _answer(table, rows[~bumped], hi, lo, p, value, at_layer, found)
            rows = rows[bumped]
    return value, at_layer, found


def _bumped(table: LayerTable, hi: np.ndarray, p: BandParams) -> np.ndarray:
    if not table.thresholds.any():
        return np.zeros(len(hi), bool)
    start = hashing.starts(hi, table.n_starts, table.layer, table.attempt)
    pos = position_of(start, hi, p.b, p.order, table.n_starts, table.layer, table.attempt)
    return pos < table.thresholds[start // p.b]


def window_words(words: np.ndarray, r: int, start: np.ndarray, q: int, shift: np.ndarray, k: int) -> np.ndarray:
    """64 bits of value bit q from slot start + 64 k on, out of interleaved words."""
    at = ((start >> 6) + k) * r + q
    low = words[at] >> shift
    high = np.where(shift == 0, np.uint64(0), words[at + r] << ((np.uint64(64) - shift) & np.uint64(63)))
    return low | high


def read_bits(table: LayerTable, start: np.ndarray, c: list[np.ndarray], p: BandParams, q: int) -> np.ndarray:
    shift = (start & 63).astype(np.uint64)
    total = np.bitwise_count(window_words(table.z, p.r, start, q, shift, 0) & c[0])
    if len(c) == 2:
        total = total ^ np.bitwise_count(window_words(table.z, p.r, start, q, shift, 1) & c[1])
    return total.astype(np.uint64) & np.uint64(1)


def _answer(table, rows, hi, lo, p, value, at_layer, found) -> None:
    if not len(rows):
        return
    start = hashing.starts(hi[rows], table.n_starts, table.layer, table.attempt)
    c = hashing.coefficients(lo[rows], table.w, p.coef if table.w == p.w else "dense", table.layer, table.attempt)
    if p.layout == "contiguous":
        out = np.zeros(len(rows), np.uint64)
        for k, word in enumerate(c):
            live = word.copy()
            while live.any():  # one step for each set bit; few with sparse rows
                some = live != 0
                j = kernel.trailing_zeros(live[some]).astype(np.int64)
                out[some] ^= table.z[start[some] + 64 * k + j]
                live[some] &= live[some] - np.uint64(1)
    else:
        out = np.zeros(len(rows), np.uint64)
        for q in range(p.r):
            out |= read_bits(table, start, c, p, q) << np.uint64(q)
    value[rows], at_layer[rows], found[rows] = out, table.layer, True


def matches(
    tables: dict[tuple[int, int], LayerTable], hi: np.ndarray, lo: np.ndarray, shard: np.ndarray, p: BandParams
) -> tuple[np.ndarray, np.ndarray]:
    """(member, bits read) of a filter, reading value bits one by one and stopping at the
    first that differs from the fingerprint. Interleaved layout."""
    want = hashing.fingerprint(lo, p.r)
    if p.kind == "zero":
        want = np.zeros(len(lo), np.uint64)
    n = len(hi)
    member, read = np.zeros(n, bool), np.zeros(n, np.int32)
    for s in np.unique(shard):
        rows = np.flatnonzero(shard == s)
        groups = []
        if p.kind == "twohop":
            first = primary_layer(hi[rows], max(0.0, -p.eps), p.layers)
            for layer in range(p.layers - 1):
                mine, table = rows[first == layer], tables.get((int(s), layer))
                if table is None or not len(mine):
                    continue
                bumped = _bumped(table, hi[mine], p)
                groups.append((table, mine[~bumped]))
                if (after := tables.get((int(s), layer + 1))) is not None:
                    groups.append((after, mine[bumped]))
        else:
            for layer in range(p.layers):
                table = tables.get((int(s), layer))
                if table is None or not len(rows):
                    break
                bumped = _bumped(table, hi[rows], p) if p.kind == "layered" else np.zeros(len(rows), bool)
                groups.append((table, rows[~bumped]))
                rows = rows[bumped]
        for table, mine in groups:
            start = hashing.starts(hi[mine], table.n_starts, table.layer, table.attempt)
            c = hashing.coefficients(lo[mine], table.w, p.coef if table.w == p.w else "dense", table.layer, table.attempt)
            live = np.arange(len(mine))
            for q in range(p.r):
                read[mine[live]] += 1
                bit = read_bits(table, start[live], [x[live] for x in c], p, q)
                live = live[bit == ((want[mine[live]] >> np.uint64(q)) & np.uint64(1))]
            member[mine[live]] = True
    return member, read
