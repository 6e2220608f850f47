"""The eliminator: a hand-made case, order invariance, rank, rollback, and both kernels alike."""

import itertools

import numpy as np
import pytest

from bandstore.functions import hashing
from bandstore.operators import kernel, solve
from bandstore.params import BandParams

# start, coefficients (bit 0 first), value; w = 4, m = 8, r = 2
GOLDEN = [(1, 0b1101, 0b01), (1, 0b1011, 0b10), (0, 0b0011, 0b11), (2, 0b0011, 0b11), (2, 0b0011, 0b01)]


def keys(n, r=8, seed=0):
    rng = np.random.default_rng(seed)
    hi, lo = (rng.integers(0, 1 << 63, n).astype(np.uint64) for _ in range(2))
    return solve.Keys(hi, lo, rng.integers(0, 1 << r, n).astype(np.uint64))


def test_golden_case():
    s = kernel.ScalarEliminator(8)
    got = [s.insert(*row) for row in GOLDEN]
    assert [g[0] for g in got] == [kernel.PLACED] * 3 + [kernel.REDUNDANT, kernel.FAILED]
    assert [g[1] for g in got[:3]] == [1, 2, 0]
    assert (s.coefs[2], s.values[2]) == (0b0011, 0b11)
    assert s.solve() == [0b10, 0b01, 0b11, 0, 0, 0, 0, 0]


def test_order_does_not_matter_for_slots():
    for order in itertools.permutations(range(5)):
        s = kernel.ScalarEliminator(8)
        placed = sum(s.insert(*GOLDEN[i])[0] == kernel.PLACED for i in order)
        assert placed == 3 and set(s.coefs) == {0, 1, 2}


def test_rollback_restores_the_state():
    s = kernel.ScalarEliminator(64)
    rng = np.random.default_rng(1)
    rows = [(int(rng.integers(0, 48)), int(rng.integers(0, 1 << 16)) | 1, int(rng.integers(0, 4))) for _ in range(60)]
    for row in rows[:25]:
        s.insert(*row)
    mark, before = s.mark(), (dict(s.coefs), dict(s.values))
    for row in rows[25:]:
        s.insert(*row)
    s.rollback(mark)
    assert (s.coefs, s.values) == before


def test_dry_run_stores_nothing():
    s = kernel.ScalarEliminator(8)
    s.insert(1, 0b1101, 1)
    assert s.insert(3, 1, 0, dry=True)[0] == kernel.PLACED and set(s.coefs) == {1}


def test_longest_prefix():
    assert kernel.longest_prefix(GOLDEN, 8) == 4


def test_numpy_hash_is_sparks(spark):
    from pyspark.sql import functions as F

    df = spark.range(-50, 50).select("id", F.xxhash64("id", F.lit(7).cast("long")).alias("h")).toPandas()
    want = hashing.remix(df["id"].to_numpy().view(np.uint64), 7).view(np.int64)
    assert (df["h"].to_numpy() == want).all()


@pytest.mark.parametrize(
    "options",
    [
        {}, {"scheme": "1plus"}, {"scheme": "plain"}, {"scheme": "cbit"}, {"scheme": "headtail"}, {"scheme": "single"},
        {"scheme": "2bit-even"}, {"w": 16}, {"w": 32}, {"w": 128, "r": 5}, {"order": "l2r"}, {"order": "hash"},
        {"bucket_order": "r2l"}, {"mode": "cautious"}, {"coef": "sparse:8", "layout": "contiguous", "r": 16},
        {"kind": "plain", "eps": 0.15}, {"kind": "twohop", "layers": 6}, {"kind": "twohop", "layers": 6, "fixed_sizes": True},
        {"piece_starts": 512}, {"free": "affine"}, {"free": "random"}, {"r": 1}, {"r": 63},
    ],
)
@pytest.mark.parametrize("n", [0, 1, 40, 3000])
def test_every_variant_returns_its_values(options, n):
    p = BandParams(**options).resolved()
    k = keys(n, p.r)
    tables = {(t.shard, t.layer): t for t in solve.solve_shards({0: k}, p)}
    value, layer, found = solve.evaluate(tables, k.hi, k.lo, np.zeros(n, np.int64), p)
    assert (value == k.value).all() and found.all()
    if p.kind == "layered" and n:
        assert sum(t.stats["n_in"] - t.stats["n_bumped"] for t in tables.values()) == n


def test_lockstep_equals_rows(monkeypatch):
    for options in ({"piece_starts": 256}, {"w": 128, "b": 128, "piece_starts": 256}, {"kind": "twohop", "layers": 5}):
        p = BandParams(**options).resolved()
        shards = {s: keys(3000, p.r, s) for s in range(3)}
        found = []
        for lanes in (1, 1 << 30):
            monkeypatch.setattr(kernel, "LOCKSTEP_LANES", lanes)
            found.append(solve.solve_shards(shards, p))
        for a, b in zip(*found, strict=True):
            assert (a.shard, a.layer, a.m) == (b.shard, b.layer, b.m)
            assert (a.z == b.z).all() and (a.thresholds == b.thresholds).all()


def test_pieces_change_no_value():
    k = keys(6000)
    for pieces in (512, 1 << 20):
        p = BandParams(piece_starts=pieces).resolved()
        tables = {(t.shard, t.layer): t for t in solve.solve_shards({0: k}, p)}
        value, _, _ = solve.evaluate(tables, k.hi, k.lo, np.zeros(len(k), np.int64), p)
        assert (value == k.value).all()


def test_thresholds_are_minimal_and_cover_failures():
    p = BandParams().resolved()
    allowed = p.thresholds()
    assert allowed == [0, 36, 78, 256]
    table = solve.solve_shards({0: keys(20000)}, p)[0]
    assert set(np.unique(table.thresholds)) <= set(allowed)


def test_two_hop_visits_primary_or_next():
    p = BandParams(kind="twohop", layers=6).resolved()
    k = keys(4000)
    tables = {(t.shard, t.layer): t for t in solve.solve_shards({0: k}, p)}
    _, layer, _ = solve.evaluate(tables, k.hi, k.lo, np.zeros(len(k), np.int64), p)
    assert set(np.unique(layer - solve.primary_layer(k.hi, -p.eps, 6))) <= {0, 1}


def test_contradicting_keys_raise():
    k = keys(10)
    both = solve.Keys.concat([k, solve.Keys(k.hi, k.lo, k.value ^ np.uint64(1))])
    with pytest.raises(RuntimeError):
        solve.solve_shards({0: both}, BandParams(kind="plain", max_tries=5).resolved())


def test_head_and_tail_are_groups():
    """Thresholds of the headtail scheme against inserting tails, then heads, as transactions."""
    from bandstore.operators import kernel

    rng = np.random.default_rng(8)
    keys = solve.Keys(*(rng.integers(0, 1 << 63, 4000).astype(np.uint64) for _ in range(2)), rng.integers(0, 8, 4000).astype(np.uint64))
    p = BandParams(r=3, w=32, scheme="headtail", piece_starts=1 << 40).resolved()
    n_starts = solve.table_starts(4000, p.eps, "layered")
    table, bumped = solve.solve_layer([solve.Job(keys, 0, 0, 0, n_starts)], p, p.w, True)[0]
    start = hashing.starts(keys.hi, n_starts, 0, 0)
    coef = hashing.coefficients(keys.lo, p.w, p.coef, 0, 0)[0]
    system, gone = kernel.ScalarEliminator(table.m), set()
    head = -(-3 * p.w // 8)
    for bucket in range(-(-n_starts // p.b)):
        at = np.flatnonzero(start // p.b == bucket)
        tail, first = (at[(start[at] % p.b >= head) == x].tolist() for x in (True, False))
        row = lambda i: (int(start[i]), int(coef[i]), int(keys.value[i]))
        if not system.insert_all(map(row, tail)):
            gone |= set(at.tolist())
        elif not system.insert_all(map(row, first)):
            gone |= set(first)
    assert set(np.flatnonzero(bumped).tolist()) == gone and 0 < len(gone) < 2000
    assert table.stats["empty"] == table.m - len(system.coefs)


def test_bucket_metadata_parts_a_bucket_with_more_keys_than_cells():
    """A dozen keys make one bucket, for which often no seed leaves every cell to one key at most."""
    from bandstore.operators import baselines

    for seed in range(20):
        k = keys(12, seed=seed)
        assert (baselines.build_meta_buckets("meta_buckets", k, 8).value(k.hi, k.lo) == k.value).all()


@pytest.mark.parametrize("kind", ["sparse3", "sparse4", "twoblock"])
def test_gauss_tables_answer_all_shards_of_one_try_together(kind, monkeypatch):
    """Keys of 20 shards, some of which took further tries; a step for each try, not for each shard."""
    from bandstore.operators import baselines

    k = keys(20 * baselines.GAUSS_SHARD + 7)
    table = baselines.build_gauss(kind, k, 8)
    steps, rows_of = [], getattr(baselines, "two_blocks" if kind == "twoblock" else "sparse_rows")
    monkeypatch.setattr(baselines, rows_of.__name__, lambda *a: steps.append(1) or rows_of(*a))
    assert (table.value(k.hi, k.lo) == k.value).all()
    assert len(steps) == len(set(table.attempts)) < table.shards


def test_figures_alone_need_no_back_substitution(monkeypatch):
    p = BandParams(kind="plain", w=64, r=1, eps=0.1).resolved()
    job = solve.Job(keys(2000, 1), 0, 0, 0, solve.table_starts(2000, 0.1, "plain"))
    whole = solve.solve_layer([job], p, 64, False)[0][0]
    monkeypatch.setattr(kernel, "back_substitute", None)
    assert solve.solve_layer([job], p, 64, False, values=False)[0][0].stats == whole.stats
