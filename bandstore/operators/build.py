"""Build static functions and membership filters with one shuffle.

Keys are digested in the scan's stage, equal digests are merged by partial aggregation, and
rows go to shards by a hash of the digest. A task solves the shards of its partition, a few
million keys at a time, and returns one row for each layer of each shard. Which keys a shard
has depends on the keys alone and everything after is seeded, so a repeated task returns the
same row."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import codecs, hashing
from ..params import BandParams
from ..sources.shared import keep
from . import metadata, solve

TABLE_SCHEMA = (
    "shard int, layer int, attempt int, w int, n_starts long, m long, z binary, codes binary, exceptions binary, ranges binary, "
    "n_in long, n_bumped long, n_redundant long, empty long, row_ops long, pieces long"
)
STORED = ("z", "codes", "exceptions", "ranges")
STATS = ("n_in", "n_bumped", "n_redundant", "empty", "row_ops", "pieces")
ARROW_SCHEMA = pa.schema(
    [
        ("shard", pa.int32()), ("layer", pa.int32()), ("attempt", pa.int32()), ("w", pa.int32()), ("n_starts", pa.int64()),
        ("m", pa.int64()), *[(c, pa.binary()) for c in STORED], *[(c, pa.int64()) for c in STATS],
    ]
)
SHARD_KEYS, GROUP_KEYS = 1 << 20, 1 << 22


@dataclass
class BandStructure:
    """A built structure: its parameters, how keys are digested, and a table with a row for
    each layer of each shard. `table` is stored in the shared folder, so that queries read it and
    do not solve it anew; it can be written, read and queried like any other."""

    params: BandParams
    algo: str
    key_seed: int
    table: DataFrame

    @property
    def spark(self) -> SparkSession:
        return self.table.sparkSession


def n_shards_for(n: int, shard_keys: int = SHARD_KEYS) -> int:
    return max(1, -(-n // shard_keys))


def digests(df: DataFrame, cols: list[str], algo: str, key_seed: int) -> DataFrame:
    return hashing.with_digest(df.select(*cols), cols, algo, key_seed).select("hi", "lo").where(F.col("hi").isNotNull())


def unique_pairs(df: DataFrame, cols: list[str], value: str, r: int, algo: str, key_seed: int) -> DataFrame:
    """(hi, lo, value), a row for each digest. Keys that repeat with one value are merged;
    keys that repeat with different values are an error, found in the same aggregation."""
    types = list(dict.fromkeys([*cols, value]))
    keyed = hashing.with_digest(df.select(*types), cols, algo, key_seed).where(F.col("hi").isNotNull())
    found = keyed.groupBy("hi", "lo").agg(F.min(value).alias("least"), F.max(value).alias("most"))
    return found.select("hi", "lo", codecs.checked(_agreed("least", "most"), r).alias("value"))


CONFLICT = "a key has different values"


def _agreed(least: str, most: str) -> Column:
    return F.when(F.col(least).eqNullSafe(F.col(most)), F.col(least)).otherwise(F.raise_error(F.lit(CONFLICT)))


def conflicting(df: DataFrame, cols: list[str], value: str) -> bool:
    """Whether a key itself, and not its digest alone, has different values."""
    types = {f.name: f.dataType for f in df.schema.fields}
    keys = [hashing.canonical(F.col(c), types[c]).alias(f"_key{i}") for i, c in enumerate(cols)]
    found = df.select(*keys, F.col(value).alias("_v")).groupBy(*[f"_key{i}" for i in range(len(cols))])
    return bool(found.agg(F.min("_v").alias("least"), F.max("_v").alias("most")).where("not least <=> most").take(1))


def approximate_keys(df: DataFrame, cols: list[str], algo: str, key_seed: int) -> int:
    """Distinct keys within a few percent, by one scan and no shuffle of keys."""
    return int(digests(df, cols, algo, key_seed).agg(F.approx_count_distinct("hi", 0.02)).first()[0])


def build(
    df: DataFrame,
    cols: list[str],
    value: str | None = None,
    params: BandParams | None = None,
    algo: str = "xx128",
    key_seed: int = 1,
    n_shards: int | None = None,
    shard_keys: int = SHARD_KEYS,
    group_keys: int = GROUP_KEYS,
    **options,
) -> BandStructure:
    """A function of the key columns to `value`, or without one a membership filter. Where two
    keys of different values share a digest, the build starts over with other digests. A task
    solves shards together up to group_keys keys: more are faster and take more memory."""
    p = replace(params or BandParams(), **options)
    if n_shards is None:
        n_shards = n_shards_for(approximate_keys(df, cols, algo, key_seed), shard_keys)
    if value is None:
        p = replace(p, is_filter=True, n_shards=n_shards)
        if p.kind == "zero":
            p = replace(p, free="random" if p.free == "zero" else p.free)
        p = p.resolved()
        # Equal keys are redundant rows of a filter; merging them only makes the shuffle smaller.
        pairs = digests(df, cols, algo, key_seed).distinct()
        value_column = F.lit(0).cast("long") if p.kind == "zero" else hashing.fingerprint_column(F.col("lo"), p.r)
        return BandStructure(p, algo, key_seed, keep(solved(pairs.withColumn("value", value_column), p, group_keys), "band"))
    if p.kind == "zero":
        raise ValueError("the zero kind stores no values")
    p = replace(p, n_shards=n_shards).resolved()
    for seed in range(key_seed, key_seed + RESEEDS):
        try:
            table = keep(solved(unique_pairs(df, cols, value, p.r, algo, seed), p, group_keys), "band")
            return BandStructure(p, algo, seed, table)
        except Exception as e:
            if CONFLICT not in str(e) or conflicting(df, cols, value):
                raise
    raise RuntimeError(f"digests of {algo} clash under {RESEEDS} seeds")


RESEEDS = 8


def solved(pairs: DataFrame, p: BandParams, group_keys: int = GROUP_KEYS) -> DataFrame:
    """The table of (hi, lo, value) rows."""
    sharded = pairs.select(hashing.shard_column(F.col("hi"), p.n_shards).alias("shard"), "hi", "lo", "value")
    dealt = sharded.repartition(p.n_shards, "shard").sortWithinPartitions("shard")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in shard_groups(batches, group_keys):
            tables = solve.solve_shards(group, p)
            if tables:
                yield encode_tables(tables, p)

    return dealt.mapInArrow(run, TABLE_SCHEMA)


def shard_groups(batches: Iterable[pa.RecordBatch], group_keys: int = GROUP_KEYS) -> Iterator[dict[int, solve.Keys]]:
    """Whole shards out of rows sorted by shard, some group_keys keys at a time."""
    held: dict[int, list[solve.Keys]] = {}
    n = 0

    def merged() -> dict[int, solve.Keys]:
        return {s: solve.Keys.concat(parts) for s, parts in held.items()}

    for batch in batches:
        shard = batch.column(0).to_numpy()
        hi, lo, value = (batch.column(i).to_numpy().view(np.uint64) for i in (1, 2, 3))
        edges = [0, *(np.flatnonzero(np.diff(shard)) + 1).tolist(), len(shard)]
        for a, z in zip(edges, edges[1:], strict=False):
            if a == z:
                continue
            s = int(shard[a])
            if s not in held and n >= group_keys:
                yield merged()
                held, n = {}, 0
            held.setdefault(s, []).append(solve.Keys(hi[a:z], lo[a:z], value[a:z]))
            n += z - a
    if held:
        yield merged()


def encode_tables(tables: list[solve.LayerTable], p: BandParams) -> pa.RecordBatch:
    columns = [
        [t.shard for t in tables], [t.layer for t in tables], [t.attempt for t in tables], [t.w for t in tables],
        [t.n_starts for t in tables], [t.m for t in tables], [metadata.encode_entries(t.z, t.m, p) for t in tables],
        *zip(*[metadata.encode(t.thresholds, p) for t in tables], strict=True), *[[t.stats[c] for t in tables] for c in STATS],
    ]
    return pa.record_batch([pa.array(x, f.type) for x, f in zip(columns, ARROW_SCHEMA, strict=True)], schema=ARROW_SCHEMA)


def decode_rows(rows: pa.Table | pa.RecordBatch, p: BandParams) -> dict[tuple[int, int], solve.LayerTable]:
    out = {}
    get = {name: rows.column(name) for name in rows.schema.names}
    for i in range(rows.num_rows):
        at = {c: get[c][i].as_py() for c in ("shard", "layer", "attempt", "w", "n_starts", "m")}
        z, codes, exceptions, ranges = (get[c][i].as_py() for c in STORED)
        thresholds = metadata.Thresholds.decode(codes, exceptions, ranges, -(-at["n_starts"] // p.b), p)
        z = metadata.decode_entries(z, at["m"], p)
        stats = {c: get[c][i].as_py() for c in STATS if c in get}
        out[at["shard"], at["layer"]] = solve.LayerTable(z=z, thresholds=thresholds, stats=stats, **at)
    return out


def build_many(
    df: DataFrame, group_cols: list[str], cols: list[str], value: str | None = None, n_tasks: int | None = None, **options
) -> BandStructure:
    """One structure for each group, all in one table: a group's hash is its shard, and its
    columns are part of each key's digest, so groups of one hash share a system but no keys.
    Groups are solved together, as lanes of one system. A group lives in one task; its keys come
    in by partial aggregation, and duplicates are gone before the shuffle. A key with different
    values in its group is an error."""
    p = replace(BandParams(), **options)
    every = [*group_cols, *[c for c in cols if c not in group_cols]]
    keyed = hashing.with_digest(df.select(*dict.fromkeys([*every, *([value] if value else [])])), every)
    keyed = keyed.withColumn("shard", group_shard(group_cols)).where(F.col("hi").isNotNull())
    if value is None:
        p = replace(p, is_filter=True)
        if p.kind == "zero":
            p = replace(p, free="random" if p.free == "zero" else p.free)
        pairs = keyed.select("shard", "hi", "lo").distinct()
        zero = F.lit(0).cast("long")
        pairs = pairs.withColumn("value", zero if p.kind == "zero" else hashing.fingerprint_column(F.col("lo"), p.r))
    else:
        pairs = keyed.groupBy("shard", "hi", "lo").agg(F.min(value).alias("least"), F.max(value).alias("most"))
        pairs = pairs.select("shard", "hi", "lo", codecs.checked(_agreed("least", "most"), p.r).alias("value"))
    p = replace(p, n_shards=GROUP_SHARDS).resolved()
    dealt = pairs.select("shard", "hi", "lo", "value")
    dealt = (dealt.repartition(n_tasks, "shard") if n_tasks else dealt.repartition("shard")).sortWithinPartitions("shard")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for found in shard_groups(batches):
            tables = solve.solve_shards(found, p)
            if tables:
                yield encode_tables(tables, p)

    return BandStructure(p, "xx128", 1, keep(dealt.mapInArrow(run, TABLE_SCHEMA), "bands"))


GROUP_SHARDS = (1 << 31) - 1


def group_shard(group_cols: list[str]) -> Column:
    return F.pmod(F.xxhash64(*group_cols), F.lit(GROUP_SHARDS)).cast("int")
