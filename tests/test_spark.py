"""Builds, lookups, stores, joins and streams on Spark."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from bandstore import model, params
from bandstore.operators import applications as apps
from bandstore.operators import baselines, build, lookup, metadata
from bandstore.params import BandParams
from bandstore.plans import metrics
from bandstore.sources import store

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def orders(spark):
    df = spark.read.parquet(f"{SF}/orders.parquet")
    return df.select("o_orderkey", F.substring("o_orderpriority", 1, 1).cast("long").alias("code")).cache()


@pytest.mark.parametrize("strategy", ["broadcast", "shuffle", "sql"])
@pytest.mark.parametrize("n_shards", [1, 3])
def test_strategies_agree(orders, strategy, n_shards):
    s = build.build(orders, ["o_orderkey"], "code", r=3, n_shards=n_shards)
    got = lookup.lookup(s, orders, ["o_orderkey"], strategy, "v")
    assert got.where("v is null or v <> code").count() == 0 and got.count() == orders.count()


def test_null_keys_empty_tables_and_repeated_rows(spark, orders):
    rows = spark.createDataFrame([(1, 5), (1, 5), (None, 3), (2, 6)], "k long, v long")
    s = build.build(rows, ["k"], "v", r=3)
    got = {(r["k"], r["w"]) for r in lookup.lookup(s, rows, ["k"], out="w").collect()}
    assert got == {(1, 5), (2, 6), (None, None)}
    empty = build.build(rows.limit(0), ["k"], "v", r=3)
    for strategy in ("broadcast", "shuffle", "sql"):
        assert lookup.lookup(empty, rows, ["k"], strategy, "w").where("w is not null").count() == 0


def test_conflicts_and_wide_values_raise(spark):
    rows = spark.createDataFrame([(1, 5), (1, 6)], "k long, v long")
    with pytest.raises(Exception, match="different values"):
        build.build(rows, ["k"], "v", r=3).table.collect()
    with pytest.raises(Exception, match="does not fit"):
        build.build(rows.limit(1), ["k"], "v", r=2).table.collect()


@pytest.mark.parametrize("kind", ["layered", "plain", "zero", "twohop"])
def test_filters(orders, kind):
    keys = orders.select("o_orderkey")
    s = build.build(keys, ["o_orderkey"], kind=kind, r=8, layers=6 if kind == "twohop" else 4)
    s.table = s.table.cache()
    assert lookup.probe(s, keys, ["o_orderkey"]).where("member").count() == keys.count()
    away = keys.select((F.col("o_orderkey") + 10**9).alias("o_orderkey"))
    got = metrics.measure_fpr(s, away, ["o_orderkey"]).first()
    assert metrics.within(got["probes"], got["hits"], 2**-8) and abs(got["bits_read"] - 2) < 0.2


def test_store_round_trip(spark, orders, tmp_path):
    s = build.build(orders, ["o_orderkey"], "code", r=3, n_shards=2)
    store.write(s, str(tmp_path / "f"))
    again = store.read(spark, str(tmp_path / "f"))
    assert again.params == s.params
    assert lookup.lookup(again, orders, ["o_orderkey"], out="v").where("v <> code").count() == 0
    with pytest.raises(Exception):
        store.write(s, str(tmp_path / "f"))
    store.register_source(spark)
    layers = spark.read.format("bandstore").option("path", str(tmp_path / "f")).load()
    assert layers.where("layer = 0").agg(F.sum("n_in")).first()[0] == orders.count()


def test_many_filters(spark):
    df = spark.read.parquet(f"{SF}/events.parquet").select("user_id", "event_id")
    s = build.build_many(df, ["user_id"], ["event_id"], r=8)
    assert lookup.probe(s, df, ["event_id"], group_cols=["user_id"]).where("not member").count() == 0


@pytest.mark.parametrize("how", ["inner", "left_semi", "left_anti"])
def test_prefilter_join_is_the_join(spark, how):
    big = spark.createDataFrame([(i, i * 2) for i in range(500)] + [(None, 1)], "k long, x long")
    small = spark.createDataFrame([(i,) for i in range(0, 500, 7)], "k long")
    got = apps.prefilter_join(big, small, ["k"], how)
    want = big.join(small, ["k"], how)
    assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0


def test_perfect_hash(orders):
    ph = apps.build_perfect_hash(orders, ["o_orderkey"], shard_keys=500)
    got = apps.perfect_hash(ph, orders).agg(F.countDistinct("id"), F.max("id"), F.min("id")).first()
    cells = ph.sizes.agg(F.sum("n_cells")).first()[0]
    assert got[0] == orders.count() and 0 <= got[2] and got[1] < cells <= 1.06 * orders.count() + 16


@pytest.mark.parametrize("kind", list(baselines.KERNEL_KINDS))
def test_baselines(orders, kind):
    keys = orders.select("o_orderkey")
    if kind in baselines.FUNCTION_KINDS:
        b = baselines.build(kind, orders, ["o_orderkey"], "code", r=3, n_shards=2)
        got = baselines.query(b, orders, ["o_orderkey"], "v")
        assert got.where("v <> code").count() == 0
    else:
        b = baselines.build(kind, keys, ["o_orderkey"], r=8, n_shards=2)
        got = baselines.query(b, keys, ["o_orderkey"], "v")
        assert got.where("v" if kind != "counting_quotient" else "v >= 1").count() == keys.count()


@pytest.mark.parametrize("kind", list(baselines.DYNAMIC))
def test_dynamic_filters(kind):
    """Batches in, out and in again; stored and read; false positives near their rate."""
    import pickle

    rng = np.random.default_rng(3)
    hi, lo, other_hi, other_lo = (rng.integers(0, 1 << 63, 30_000, dtype=np.int64).view(np.uint64) for _ in range(4))
    f = baselines.DYNAMIC[kind](30_000, 8)
    assert f.insert(hi[:10_000], lo[:10_000]) and f.insert(hi[10_000:], lo[10_000:])
    f = pickle.loads(pickle.dumps(f))
    assert f.contains(hi, lo).all() and (f.count(hi, lo) >= 1).all()
    assert 30_000 * 2.0**-8 / 4 < f.contains(other_hi, other_lo).sum() < 30_000 * 2.0**-8 * 1.4
    assert f.delete(hi[:5000], lo[:5000]).all()
    assert f.contains(hi[:5000], lo[:5000]).mean() < 0.02 and f.contains(hi[5000:], lo[5000:]).all()
    assert f.insert(hi[:5000], lo[:5000]) and f.contains(hi, lo).all()
    assert f.bits() / 30_000 < 14


@pytest.mark.parametrize("r", [3, 8, 40])
def test_counting_quotient_counts_exactly(r):
    rng = np.random.default_rng(4)
    n = 2000
    hi, lo = (rng.integers(0, 1 << 63, n, dtype=np.int64).view(np.uint64) for _ in range(2))
    times = rng.integers(1, 3000, n)
    f = baselines.CountingQuotient(n, r)
    quotient, rest = f.parts(hi, lo)
    f.insert(hi, lo, times)
    want = {}
    for q, x, c in zip(quotient.tolist(), rest.tolist(), times.tolist()):
        want[q, x] = want.get((q, x), 0) + c
    assert f.count(hi, lo).tolist() == [want[k] for k in zip(quotient.tolist(), rest.tolist())]
    f.delete(hi[:1], lo[:1])
    assert f.count(hi[:1], lo[:1])[0] == want[quotient[0], rest[0]] - 1


def test_baselines_by_shuffle(orders):
    b = baselines.build("xor", orders, ["o_orderkey"], "code", r=3, n_shards=3)
    assert baselines.query(b, orders, ["o_orderkey"], "v", "shuffle").where("v is null or v <> code").count() == 0


def test_shuffle_splits_a_hot_key(spark, orders):
    s = build.build(orders, ["o_orderkey"], "code", r=3)
    probes = spark.range(20_000).select(F.lit(7).cast("long").alias("o_orderkey"), "id")
    got = lookup.lookup(s, probes, ["o_orderkey"], "shuffle", "v").groupBy(F.spark_partition_id(), "v").count().collect()
    assert len({r["v"] for r in got}) == 1 and len(got) > 1 and sum(r["count"] for r in got) == 20_000


@pytest.mark.parametrize("scheme", params.SCHEMES)
@pytest.mark.parametrize("range_bits", [0, 8])
def test_stored_thresholds(scheme, range_bits):
    p = BandParams(scheme=scheme, b=128, range_bits=range_bits).resolved()
    rng = np.random.default_rng(1)
    for n in (1, 2, 7, 8, 9, 500):
        allowed = np.array(p.thresholds())
        t = rng.choice(allowed if scheme != "1plus" else np.concatenate([allowed[:2].repeat(20), allowed]), n)
        stored = metadata.encode(t, p)
        got = metadata.Thresholds.decode(*stored, n, p)
        assert (got[np.arange(n)] == t).all()
        assert len(stored[0]) in (0, -(-n * metadata.code_bits(p) // 8))
        if scheme == "1plus" and range_bits and (t > 0).any():
            plain = metadata.Thresholds.decode(stored[0], stored[1], b"", n, p)
            plain[np.arange(n)]
            assert got.searches <= plain.searches
    none = metadata.Thresholds.decode(*metadata.encode(np.zeros(5, int), p), 5, p)
    assert not none.any() and (none[np.arange(5)] == 0).all()


def test_space_is_what_is_stored(orders):
    s = build.build(orders, ["o_orderkey"], "code", r=3, b=64, scheme="1plus", range_bits=16)
    stored = s.table.agg(F.sum(sum((F.length(c) for c in build.STORED), F.lit(0))), F.count(F.lit(1))).first()
    got = metrics.space_report(s).first()
    assert got["bits"] == stored[0] * 8 + stored[1] * metrics.SHARD_BITS and got["n"] == orders.count()


def test_clashing_digests_start_over(spark):
    rows = spark.createDataFrame([(i, i % 8) for i in range(60)], "k long, v long")
    again = 0
    for first in range(1, 5):
        s = build.build(rows, ["k"], "v", r=3, algo="bits:11", key_seed=first)
        again += s.key_seed > first
        assert lookup.lookup(s, rows, ["k"], out="w").where("w <> v").count() == 0
    assert again
    with pytest.raises(Exception, match="clash"):
        build.build(rows, ["k"], "v", r=3, algo="bits:4")


def test_many_functions_conflict_and_share_no_keys(spark, monkeypatch):
    rows = spark.createDataFrame([(g, k, (g * 7 + k) % 8) for g in range(20) for k in range(30)], "g long, k long, v long")
    monkeypatch.setattr(build, "GROUP_SHARDS", 3)  # groups share shards
    s = build.build_many(rows, ["g"], ["k"], "v", r=3)
    assert lookup.lookup(s, rows, ["k"], out="w", group_cols=["g"]).where("w <> v").count() == 0
    with pytest.raises(Exception, match="different values"):
        build.build_many(rows.unionByName(rows.withColumn("v", (F.col("v") + 1) % 8)), ["g"], ["k"], "v", r=3)


def test_diagonals_and_classes():
    from bandstore.operators import kernel

    rng = np.random.default_rng(8)
    n, w, b, n_starts = 4000, 32, 64, 3900
    starts = rng.integers(0, n_starts, n)
    m = n_starts + w - 1
    s = kernel.ScalarEliminator(m)
    outcomes = []
    for x in np.sort(starts).tolist():
        got = s.insert(x, int(rng.integers(0, 1 << 32)) | 1, int(rng.integers(0, 2)))[0]
        outcomes.append((x, got != kernel.PLACED))
    slot, empty = metrics.abandoning_diagonal(starts, m, w)
    assert len(set(slot[slot >= 0].tolist())) == (slot >= 0).sum() == m - len(empty)
    assert ((slot[slot >= 0] - starts[slot >= 0]) < w).all()
    placed = [x for x, failed in outcomes if not failed]
    h = metrics.heights(sorted(s.coefs), placed, m)
    for room, rows, failures in metrics.failure_law(outcomes, np.concatenate([[0], h[:-1]]), w):
        if room >= 1:
            bound = rows * 2.0**-room
            assert failures <= 4 * bound + 6 * bound**0.5 + 3
    classes = metrics.bucket_classes(sorted(s.coefs), starts.tolist(), n_starts, m, b, w)
    assert classes["good"] + classes["recovery"] + classes["bad"] == -(-n_starts // b) and classes["empty"] <= classes["bound"]


def test_golomb_and_huffman():
    assert apps.golomb(5, 1) == "1101" and apps.huffman({"a": 5}) == {"a": "0"}
    codes = apps.huffman({"a": 8, "b": 4, "c": 2, "d": 1})
    assert sorted(map(len, codes.values())) == [1, 2, 3, 3]


def test_model_literals():
    assert model.expected_bits(8) == pytest.approx(2 - 2**-7)
    bounds = model.table_of_bounds(1 << 24, 8, 64)
    assert bounds["layered_band"] < 0.001 and bounds["peeling_3wise"] == 0.2218
    assert model.overhead(2.381e-4, 2, 8, 128) == pytest.approx(0.00219, abs=2e-5)


def test_parameter_formulas():
    assert [params.bucket_size(w, "2bit") for w in (16, 32, 64, 128)] == [32, 64, 256, 1024]
    assert [params.bucket_size(w, "1plus") for w in (16, 32, 64, 128)] == [16, 32, 128, 512]
    assert params.two_thresholds(64, 256, -4 / 64) == (36, 78)
    assert params.one_threshold(128, params.overload(64, "1plus", 128)) == 25


def test_empty_share_near_published(spark):
    """w = 64, b = 128, 2-bit at its default: 2.381e-4 published; enough slots to tell."""
    df = spark.range(60_000).select(F.xxhash64("id").alias("hi"), F.xxhash64("id", F.lit(1)).alias("lo"))
    row = metrics.sweep(df, [BandParams(b=64, eps=0.0), BandParams(b=256, eps=-0.0344, piece_starts=1 << 20)]).collect()
    e = {r["b"]: r["e"] for r in row}
    assert 9.624e-3 / 3 < e[64] < 9.624e-3 * 3 and 4.421e-3 / 3 < e[256] < 4.421e-3 * 3


def test_diagnostics():
    rng = np.random.default_rng(2)
    from bandstore.operators import kernel

    m = 600
    starts = rng.integers(0, m - 63, 500).tolist()
    s = kernel.ScalarEliminator(m)
    for x in starts:
        s.insert(x, int(rng.integers(0, 1 << 63)) | 1, 0)
    h = metrics.heights(sorted(s.coefs), starts, m)
    assert (h >= 0).all()
    for height, slots, empty in metrics.empty_law(sorted(s.coefs), starts, m):
        assert empty <= slots * 2.0**-height + 4 * (slots * 2.0**-height) ** 0.5 + 1
    assert s.row_ops <= 500 * 63


def test_streaming_window_filters(spark, tmp_path):
    from pyspark.sql import Row

    from bandstore.streaming import probes

    rows = [Row(ts=f"2024-01-01 0{h}:{m:02d}:00", k=h * 100 + m) for h in range(4) for m in range(0, 60, 10)]
    df = spark.createDataFrame(rows).select(F.to_timestamp("ts").alias("ts"), F.col("k").cast("long").alias("k"))
    df.coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(df.schema).parquet(str(tmp_path / "in"))
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        filters = probes.window_filters(stream, "ts", ["k"], "1 hour", "5 minutes")
        q = filters.writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "cp"))
        q.outputMode("append").trigger(availableNow=True).start().awaitTermination()
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    got = spark.read.parquet(str(tmp_path / "out")).collect()
    assert len(got) == 3 and all(r["n"] == 6 for r in got)


def test_rebuild_each_batch_is_idempotent(spark, orders, tmp_path):
    from bandstore.streaming import probes

    write = probes.rebuild_each_batch(str(tmp_path / "v"), ["o_orderkey"], BandParams(kind="zero", r=8))
    write(orders, 0)
    write(orders, 0)
    assert store.read(spark, str(tmp_path / "v"), "batch-0").params.kind == "zero"


def test_success_and_span_cover_the_table(spark):
    """Every key of the table is in a system, at any size and by shard."""
    df = spark.range(5000).withColumnRenamed("id", "k")
    p = [BandParams(kind="zero", r=8, eps=0.1).resolved()]
    got = metrics.zero_span(df, df.select((F.col("k") + 10**9).alias("k")), ["k"], p).collect()
    assert [(r["n_members"], r["n_foreign"]) for r in got] == [(5000, 5000)] and got[0]["inside"] <= 100
    for shard_keys in (1000, 1 << 20):
        curve = {r["eps"]: r["success"] for r in metrics.success_curve(df, ["k"], 64, [-0.2, 0.3], 4, shard_keys=shard_keys).collect()}
        assert curve[0.3] == 1.0 > curve[-0.2]


@pytest.mark.parametrize(
    "options",
    [{}, {"scheme": "1plus"}, {"w": 128, "mode": "cautious"}, {"w": 16, "layout": "contiguous"}, {"scheme": "headtail", "order": "l2r"}],
)
def test_streamed_build_is_the_build(orders, options):
    """Two buckets at a time give the tables that whole shards give, bit by bit."""
    from bandstore.operators import external

    streamed = external.build_streamed(orders, ["o_orderkey"], "code", n_shards=2, r=3, **options)
    whole = build.build(orders, ["o_orderkey"], "code", n_shards=2, r=3, piece_starts=1 << 40, **options)
    columns = [c for c in whole.table.columns if c not in ("row_ops", "n_redundant")]
    ordered = lambda s: s.table.select(*columns).orderBy("shard", "layer").collect()
    assert ordered(streamed) == ordered(whole)
    got = lookup.lookup(streamed, orders, ["o_orderkey"], "broadcast", out="v")
    assert got.where("v is null or v != code").count() == 0


def test_streamed_build_holds_two_buckets(orders):
    from bandstore.operators import external
    from bandstore.params import BandParams

    p = BandParams(r=1, n_shards=1, is_filter=True).resolved()
    pairs = build.digests(orders, ["o_orderkey"], "xx128", 1).selectExpr("0 AS shard", "hi", "lo", "0L AS value")
    n = pairs.count()
    sized = pairs.selectExpr("shard", f"{n}L AS n", "hi", "lo", "value").mapInArrow(external._placing(p, 0), external.PLACED)
    dealt = sized.coalesce(1).sortWithinPartitions("bucket", F.desc("pos"))
    rows = dealt.mapInArrow(external._forward(p, 0), external.ECHELON)
    assert n > 4 * p.b and rows.agg(F.max("resident")).first()[0] <= 2.5 * p.b


def test_streamed_build_of_odd_tables(spark, orders):
    from bandstore.operators import external

    nothing = external.build_streamed(orders.where("false"), ["o_orderkey"], "code", r=3)
    assert nothing.table.count() == 0
    few = spark.createDataFrame([(1, 5), (1, 5), (None, 3), (2, 0)], "k long, v long")
    got = lookup.lookup(external.build_streamed(few, ["k"], "v", r=3), few.where("k is not null"), ["k"], out="found")
    assert got.where("found != v").count() == 0
    with pytest.raises(ValueError):
        external.build_streamed(few, ["k"], kind="zero")


@pytest.mark.parametrize("strategy", ["broadcast", "shuffle", "sql"])
def test_head_and_tail_start_over(orders, strategy):
    """A layer emptier than asked starts over with new hashes; lookups follow."""
    easy = build.build(orders, ["o_orderkey"], "code", n_shards=2, r=3, scheme="headtail", constant=4.0)
    shares = sorted(r[0] for r in easy.table.where("layer = 0").selectExpr("empty / m").collect())
    limit = shares[0] * 0.97
    hard = build.build(orders, ["o_orderkey"], "code", n_shards=2, r=3, scheme="headtail", constant=4.0, empty_limit=limit)
    first = hard.table.where("layer = 0")
    assert first.where("attempt > 0").count() >= 1
    assert first.where(f"empty > {limit} * m and attempt < {hard.params.max_tries - 1}").count() == 0
    assert lookup.lookup(hard, orders, ["o_orderkey"], strategy, out="v").where("v != code").count() == 0


def test_counts_after_deletes_with_partitions_without_a_shard(spark, monkeypatch):
    """More shards than partitions that get one."""
    monkeypatch.setattr(baselines, "SHARD_KEYS", 100)
    rows = spark.range(2000).select((F.col("id") % 1000).alias("k"), (F.col("id") >= 1500).alias("gone"))
    b = baselines.count_after_deletes(rows, ["k"], F.col("gone"), 44)
    got = baselines.query(b, rows.select("k").distinct(), ["k"], "n")
    assert b.n_shards > 5 and {r["k"]: r["n"] for r in got.collect()} == {k: 2 if k < 500 else 1 for k in range(1000)}


def test_string_keys_that_repeat_or_are_null(spark, tmp_path):
    from bandstore import registry

    rows = [(1, "a"), (2, "b"), (3, "a"), (4, None), (5, None), (6, "")]
    spark.createDataFrame(rows, "page_id long, url string").write.parquet(str(tmp_path / "pages.parquet"))
    got = registry.queries()["lookup_string_keys"](spark, str(tmp_path)).collect()
    assert sorted((r["page_id"], r["url"]) for r in got) == rows


def test_sweep_by_shard_has_all_keys(spark):
    """No task has the whole table; figures stay near those of one system."""
    df = spark.range(40_000).select(F.xxhash64("id").alias("hi"), F.xxhash64("id", F.lit(1)).alias("lo"))
    grid = [BandParams(b=128, scheme=s) for s in ("2bit", "1plus", "plain")]
    one, many = (sorted(metrics.sweep(df, grid, shard_keys=k).collect()) for k in (1 << 20, 8000))
    assert [r["n"] for r in one] == [r["n"] for r in many] == [40_000] * 3
    assert all(abs(a["e"] - b["e"]) < 0.01 and abs(a["overhead"] - b["overhead"]) < 0.02 for a, b in zip(one, many))


@pytest.mark.parametrize("name", ["overhead_within_target", "smallest_by_value_bits"])
def test_space_queries_build_by_shard(spark, monkeypatch, name):
    from bandstore import registry

    seen = []
    monkeypatch.setattr(build, "n_shards_for", lambda n, *a: 3)
    for module in (build, baselines):
        made = module.build
        monkeypatch.setattr(module, "build", lambda *a, f=made, **b: seen.append(b["n_shards"]) or f(*a, **b))
    registry.queries()[name](spark, SF).collect()
    assert len(seen) >= 3 and set(seen) == {3}


def test_space_of_few_and_repeated_keys(spark, tmp_path):
    """A dozen keys are one bucket that no seed parts; repeated and null keys are no further keys."""
    from bandstore import registry

    keys, got = [(7 * i,) for i in range(12)], []
    for name, rows in (("once", keys), ("again", keys * 3 + [(None,)]), ("none", [])):
        spark.createDataFrame(rows, "o_orderkey long").write.parquet(str(tmp_path / name / "orders.parquet"))
        got.append({r["name"]: r["bits_per_key"] for r in registry.queries()["space_by_structure"](spark, str(tmp_path / name)).collect()})
    once, again, none = got
    assert len(once) == 8 + len(baselines.KERNEL_KINDS) and all(b > 0 for b in once.values())
    counting = again.pop("counting_quotient"), once.pop("counting_quotient")  # counts take slots
    assert again == once and counting[0] >= counting[1]
    assert set(none.values()) == {None}


@pytest.mark.parametrize("options", [{}, {"kind": "plain"}, {"kind": "twohop", "layers": 6}])
def test_shards_alone_are_shards_together(orders, options):
    stored = ["shard", "layer", "m", "z", "codes", "n_bumped"]
    together, alone = (build.build(orders, ["o_orderkey"], r=8, n_shards=5, group_keys=g, **options).table.select(*stored) for g in (1 << 22, 1))
    assert sorted(map(tuple, together.collect())) == sorted(map(tuple, alone.collect()))


def test_foreign_keys_are_dealt_out(spark, monkeypatch):
    from bandstore import registry

    seen = []
    monkeypatch.setattr(registry, "FPR_KINDS", ("quotient",))
    ask = baselines.query
    monkeypatch.setattr(baselines, "query", lambda b, df, *a: seen.append(df.rdd.getNumPartitions()) or ask(b, df, *a))
    assert [r["ok"] for r in registry.queries()["baseline_fpr_within_bound"](spark, SF).collect()] == [True]
    assert min(seen) >= spark.sparkContext.defaultParallelism > 1


@pytest.mark.parametrize("name, table", [("eliminator_invariants", "orders"), ("rank_oracle", "orders"), ("parameter_formulas", "orders"), ("pareto_front", "orders"), ("report_cube", "lineitem")])
def test_queries_read_their_table(spark, name, table):
    from bandstore import registry

    files = registry.queries()[name](spark, SF).inputFiles()
    assert any(f.endswith(f"{table}.parquet") for f in files)


def test_pareto_front_is_that_of_all_pairs(spark):
    rng = np.random.default_rng(2)
    rows = [(i, int(a), int(b)) for i, (a, b) in enumerate(rng.integers(0, 40, (300, 2)))] + [(900, None, 1), (901, 2, None)]
    beaten = lambda a: any(b[1] <= a[1] and b[2] <= a[2] and b[1:] != a[1:] for b in rows if None not in b)
    got = metrics.pareto(spark.createDataFrame(rows, "name long, cost long, time long"), "cost", "time", "name")
    assert sorted(r["name"] for r in got.collect()) == [a[0] for a in rows if None in a or not beaten(a)]


@pytest.mark.parametrize("w, shard_keys", [(64, 900), (128, 1500), (16, 30)])
def test_success_is_of_one_system_at_any_size(spark, w, shard_keys):
    """A seed fits if one system of all keys does, also where spans of it are eliminated in tasks."""
    from bandstore.functions import hashing
    from bandstore.operators import kernel, solve

    df = spark.range(4000 if w > 16 else 300).withColumnRenamed("id", "k")
    grid, seeds = {16: [0.02, 0.1, 0.25], 64: [0.004, 0.012, 0.03], 128: [-0.02, -0.012, -0.006]}[w], 4
    pairs = np.array(hashing.with_digest(df, ["k"]).select("hi", "lo").collect(), np.int64).view(np.uint64)
    keys = solve.Keys(pairs[:, 0], pairs[:, 1], hashing.fingerprint(pairs[:, 1], 1))

    def fits(eps, seed):
        n_starts = solve.table_starts(len(keys), eps, "plain")
        words = hashing.coefficients(keys.lo, w, "dense", 0, seed)
        coefs = [sum(int(x) << (64 * k) for k, x in enumerate(row)) for row in zip(*words)]
        rows = list(zip(hashing.starts(keys.hi, n_starts, 0, seed).tolist(), coefs, keys.value.tolist()))
        return kernel.longest_prefix(rows, n_starts + w - 1) == len(rows)

    want = {eps: sum(fits(eps, s) for s in range(seeds)) / seeds for eps in grid}
    assert any(0 < x < 1 for x in want.values())
    for size in (shard_keys, 1 << 20):
        assert {r["eps"]: r["success"] for r in metrics.success_curve(df, ["k"], w, grid, seeds, shard_keys=size).collect()} == want


def test_gauss_systems_together_are_each_alone():
    rng = np.random.default_rng(3)
    n, m = 40, 70
    bits, values = rng.integers(0, 2, (5, n, m)), rng.integers(0, 256, (5, n)).astype(np.uint64)
    bits[1, 7], values[1, 7] = bits[1, 3], values[1, 3] ^ np.uint64(1)  # no solution
    bits[2, 9], values[2, 9] = bits[2, 4], values[2, 4]  # a row twice
    bits[3, 30:], values[3, 30:] = 0, 0  # fewer rows
    rows = np.zeros((5, n, 3), np.uint64)
    for j in range(m):
        rows[:, :, j // 64] |= bits[:, :, j].astype(np.uint64) << np.uint64(j % 64)
    rows[:, :, 2] = values
    z, solvable = baselines.gauss_many(rows, m)
    for i in range(5):
        want = baselines.gauss([sum(int(b) << j for j, b in enumerate(row)) for row in bits[i]], values[i].tolist(), m)
        assert solvable[i] == (want is not None) and (want is None or z[i].tolist() == want)
    assert solvable.tolist() == [True, False, True, True, True]


def test_lookups_take_many_batches_together():
    import pyarrow as pa

    batches = [(pa.array([3 * i, None, 7], pa.int64()), pa.array([i, 1, 2], pa.int64())) for i in range(50)]
    got = list(baselines._blocks(iter(batches)))
    assert len(got) == 1 and [x.to_pylist() for x in got[0]] == [[v for b in batches for v in b[k].to_pylist()] for k in (0, 1)]
    rng = np.random.default_rng(4)
    z, start, bits = rng.integers(0, 256, 500).astype(np.uint64), rng.integers(0, 436, 300), rng.integers(0, 1 << 63, 300).astype(np.uint64)
    for size in (32, 64):
        want = [int(np.bitwise_xor.reduce([z[s + j] for j in range(size) if int(b) >> j & 1], initial=0)) for s, b in zip(start, bits)]
        assert baselines.window_sum(z, start, bits, size).tolist() == want


def test_filters_together_are_each_alone(spark, monkeypatch):
    """Also where their tables are too large to broadcast; a null key is in none."""
    df = spark.range(3000).withColumnRenamed("id", "k")
    asked = spark.range(2000, 9000).selectExpr("if(id = 5000, null, id) AS k")
    built = [baselines.build(kind, df, ["k"], r=8, n_shards=3) for kind in ("xor", "quotient")]
    alone = [sorted(map(str, baselines.query(b, asked, ["k"], "m").collect())) for b in built]
    for limit in (lookup.BROADCAST_BYTES, 0):
        monkeypatch.setattr(lookup, "BROADCAST_BYTES", limit)
        got = baselines.query(built, asked, ["k"], "m")
        for i in range(2):
            assert sorted(map(str, got.select("k", F.col("m")[i].alias("m")).collect())) == alone[i]
