"""Query structures: by broadcast, by shuffle, or in plain SQL expressions.

broadcast: the table's bytes, checked against a limit, go to every worker; an Arrow UDF reads
only the digest columns. shuffle: probes meet their shard's rows in one exchange, salted, so
neither side has a size limit. sql: joins on blocks of 64 slots and built-in functions."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import hashing
from ..params import BandParams
from ..sources.shared import keep
from . import build, solve

BROADCAST_BYTES = 256 << 20
ANSWER = "struct<value:bigint,layer:int,found:boolean,member:boolean,bits_read:int>"
ARROW_ANSWER = pa.struct(
    [("value", pa.int64()), ("layer", pa.int32()), ("found", pa.bool_()), ("member", pa.bool_()), ("bits_read", pa.int32())]
)
HI, LO, SHARD, OUT = "_band_hi", "_band_lo", "_band_shard", "_band_answer"


def table_bytes(s: build.BandStructure) -> int:
    """Stored bytes; the table lies in files, so this reads lengths and solves nothing."""
    got = s.table.agg(F.sum(sum((F.length(c) for c in build.STORED), F.lit(0)))).first()[0]
    return int(got or 0)


def _answers(tables, hi, lo, shard, p: BandParams) -> pa.Array:
    """Null digests (null keys) have null answers."""
    null = np.asarray(hi.is_null())
    h, low = (np.asarray(x.fill_null(0)).astype(np.int64).view(np.uint64) for x in (hi, lo))
    sh = np.asarray(shard.fill_null(-1)).astype(np.int64)
    n = len(h)
    value, layer, found = np.zeros(n, np.uint64), np.full(n, -1, np.int32), np.zeros(n, bool)
    member, read = np.zeros(n, bool), np.zeros(n, np.int32)
    if p.is_filter and p.layout == "interleaved":
        member, read = solve.matches(tables, h, low, sh, p)
    else:
        value, layer, found = solve.evaluate(tables, h, low, sh, p)
        if p.is_filter:
            want = np.zeros(n, np.uint64) if p.kind == "zero" else hashing.fingerprint(low, p.r)
            member, read = found & (value == want), np.where(found, p.r, 0)
    return pa.StructArray.from_arrays(
        [
            pa.array(value.view(np.int64), mask=null | ~found),
            pa.array(layer, mask=null | ~found),
            pa.array(found & ~null),
            pa.array(member, mask=null),
            pa.array(read.astype(np.int32), mask=null),
        ],
        names=[f.name for f in ARROW_ANSWER],
    )


def _with_answer(s: build.BandStructure, df: DataFrame, cols: list[str], strategy: str, group_cols: list[str] | None) -> DataFrame:
    p = s.params
    every = [*group_cols, *[c for c in cols if c not in group_cols]] if group_cols else cols
    keyed = hashing.with_digest(df, every, s.algo, s.key_seed, HI, LO)
    keyed = keyed.withColumn(SHARD, build.group_shard(group_cols) if group_cols else hashing.shard_column(F.col(HI), p.n_shards))
    size = table_bytes(s) if strategy in ("auto", "broadcast") else 0
    if strategy == "auto":
        strategy = "broadcast" if size <= BROADCAST_BYTES else "shuffle"
    if strategy == "broadcast":
        if size > BROADCAST_BYTES:
            raise ValueError(f"the table has {size} bytes; use the shuffle strategy")
        shared = s.spark.sparkContext.broadcast(build.decode_rows(s.table.toArrow(), p))

        @F.arrow_udf(ANSWER)
        def look(hi: pa.Array, lo: pa.Array, shard: pa.Array) -> pa.Array:
            return _answers(shared.value, hi, lo, shard, p)

        return keyed.withColumn(OUT, look(HI, LO, SHARD)).drop(HI, LO, SHARD)
    if strategy == "shuffle":
        got = by_shard(
            s.table, keyed, SHARD, ANSWER, lambda rows: build.decode_rows(rows, p), lambda held, hi, lo, sh: _answers(held, hi, lo, sh, p), p.n_shards
        )
        return got.drop(HI, LO, SHARD)
    if strategy == "sql":
        return _by_sql(s, keyed).drop(HI, LO, SHARD)
    raise ValueError(f"unknown strategy {strategy}")


#: A shard's table goes to this many tasks at least, so that a hot key's probes are split.
SALTS = 4


def by_shard(
    tables: DataFrame, keyed: DataFrame, shard: str, answer: str, decode: Callable[[pa.RecordBatch], dict],
    answers: Callable[[dict, pa.Array, pa.Array, pa.Array], pa.Array], n_shards: int,
) -> DataFrame:
    """Table rows and probes, each tagged, in one exchange by shard and salt; a task keeps one
    shard's tables, then its probes stream past. A shard's tables are repeated for each salt,
    and probes are salted by their rows, so neither few shards nor a hot key bound the tasks."""
    spark = keyed.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    salts = min(n, max(SALTS, -(-n // max(1, n_shards))))
    salt = F.pmod(F.xxhash64(F.spark_partition_id(), *[c for c in keyed.columns if c != shard and not _has_map(keyed.schema[c].dataType)]), F.lit(salts)).cast("int")
    probes = keyed.select(
        F.coalesce(shard, F.lit(-1)).alias("shard"), salt.alias("salt"), F.lit(1).alias("role"), F.lit(None).cast(tables.schema.simpleString()).alias("t"),
        F.struct(*keyed.columns).alias("row"),
    )
    held_rows = tables.select(
        "shard", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"), F.lit(0).alias("role"), F.struct(*tables.columns).alias("t"),
        F.lit(None).cast(keyed.schema.simpleString()).alias("row"),
    )
    both = held_rows.unionByName(probes).repartition(n, "shard", "salt").sortWithinPartitions("shard", "salt", "role")
    schema = keyed.select(F.struct("*").alias("row")).withColumn(OUT, F.lit(None).cast(answer)).schema

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict = {}
        at = None
        for batch in batches:
            key, role = batch.column(0).to_numpy().astype(np.int64) * (1 << 20) + batch.column(1).to_numpy(), batch.column(2).to_numpy()
            edges = [0, *(np.flatnonzero((np.diff(key) != 0) | (np.diff(role) != 0)) + 1).tolist(), len(key)]
            for a, z in zip(edges, edges[1:], strict=False):
                if a == z:
                    continue
                part = batch.slice(a, z - a)
                if key[a] != at:
                    held, at = {}, key[a]
                if role[a] == 0:
                    held |= decode(pa.RecordBatch.from_struct_array(part.column(3)))
                    continue
                row = part.column(4)
                hi, lo, sh = (row.field(row.type.get_field_index(c)) for c in (HI, LO, shard))
                yield pa.record_batch([row, answers(held, hi, lo, sh)], names=["row", OUT])

    return both.mapInArrow(run, schema).select("row.*", OUT)


def _has_map(kind: T.DataType) -> bool:
    return "map<" in kind.simpleString() or "variant" in kind.simpleString()


def _let(value: Column, body) -> Column:
    """body(value), with the value computed once."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _window(z: Column, r: int, start: Column, q: Column) -> Column:
    """64 bits of value bit q from a start on. JVM shifts are modulo 64, so the second word is
    left out where the shift is 0."""
    at = (F.shiftrightunsigned(start, 6) * r + q).cast("int")
    shift = start.bitwiseAND(F.lit(63)).cast("int")
    low = F.call_function("shiftrightunsigned", F.get(z, at), shift)
    high = F.call_function("shiftleft", F.get(z, at + r), F.lit(64) - shift)
    return F.when(shift == 0, low).otherwise(low.bitwiseOR(high))


def blocks(s: build.BandStructure) -> DataFrame:
    """(shard, layer, block, z, t): a row for each block of 64 slots, with its words and those of
    the block after, and beside them the thresholds of the block's buckets, so that one access
    gives both."""
    p = s.params

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for (shard, layer), table in build.decode_rows(batch, p).items():
                words = table.z.reshape(-1, p.r)
                n = -(-table.n_starts // 64)
                both = np.concatenate([words[:n], words[1 : n + 1]], axis=1)
                size = max(1, 64 // p.b)
                buckets = (np.arange(n) * 64 // p.b)[:, None] + np.arange(size)
                last = -(-table.n_starts // p.b) - 1
                t = table.thresholds[np.minimum(buckets, last).reshape(-1)]
                yield pa.record_batch(
                    [
                        pa.array(np.full(n, shard, np.int32)), pa.array(np.full(n, layer, np.int32)), pa.array(np.arange(n, dtype=np.int64)),
                        pa.FixedSizeListArray.from_arrays(pa.array(both.reshape(-1).view(np.int64)), 2 * p.r).cast(pa.list_(pa.int64())),
                        pa.FixedSizeListArray.from_arrays(pa.array(t.astype(np.int32)), size).cast(pa.list_(pa.int32())),
                    ],
                    names=["shard", "layer", "block", "z", "t"],
                )

    return s.table.mapInArrow(run, "shard int, layer int, block long, z array<bigint>, t array<int>")


def _by_sql(s: build.BandStructure, keyed: DataFrame) -> DataFrame:
    """Layer by layer a join on (shard, block) of the keys that no layer before has answered;
    the others get keys of their own, spread out, that match nothing. Blocks carry their
    buckets' thresholds. Dense rows up to w = 64, r2l order, interleaved layout."""
    p = s.params
    if p.w > 64 or p.coef != "dense" or p.layout != "interleaved" or p.order != "r2l" or p.kind == "twohop":
        raise ValueError("the sql strategy takes dense interleaved layers of w <= 64 in r2l order")
    # A row for each shard, without its bits.
    parts = s.table.groupBy(F.col("shard").alias("_band_key")).agg(
        F.map_from_entries(F.collect_list(F.struct("layer", F.struct("n_starts", "attempt")))).alias("_band_layers")
    )
    got = keyed.join(parts, F.col(SHARD) == F.col("_band_key"), "left").withColumns(
        {"_band_value": F.lit(None).cast("long"), "_band_layer": F.lit(None).cast("int")}
    )
    stored = keep(blocks(s), "band-blocks")
    for layer in range(p.layers):
        open_key = F.col("_band_layer").isNull() & F.col(HI).isNotNull()
        at = F.try_element_at("_band_layers", F.lit(layer))
        got = got.withColumn("_band_start", F.when(open_key, hashing.start_column(F.col(HI), at["n_starts"], F.lit(layer), at["attempt"])))
        got = got.withColumn("_band_attempt", at["attempt"])
        away = -1 - F.pmod(F.xxhash64(HI, LO, F.spark_partition_id()), F.lit(1 << 20))
        side = stored.where(F.col("layer") == layer).select(
            F.col("shard").alias("_b_shard"), F.col("block").alias("_b_block"), F.col("z").alias("_b_z"), F.col("t").alias("_b_t")
        )
        got = got.withColumns(
            {
                "_band_at": F.when(F.col("_band_start").isNotNull(), F.col(SHARD)).otherwise(away.cast("int")),
                "_band_block": F.coalesce(F.shiftright("_band_start", 6), F.lit(-1)),
            }
        )
        got = got.join(side, (F.col("_band_at") == F.col("_b_shard")) & (F.col("_band_block") == F.col("_b_block")), "left")
        start = F.col("_band_start")
        held = F.col("_b_z").isNotNull()
        if p.kind == "layered":
            here = F.get("_b_t", F.floor((start % 64) / p.b).cast("int")) if p.b < 64 else F.get("_b_t", F.lit(0))
            held = held & (start % p.b >= here)

        c = hashing.coefficient_column(F.col(LO), p.w, F.lit(layer), F.col("_band_attempt"))
        got = got.withColumns(
            {
                "_band_value": F.when(held, _let(c, lambda x: _value(F.col("_b_z"), p.r, F.col("_band_start"), x))).otherwise(F.col("_band_value")),
                "_band_layer": F.when(held, F.lit(layer)).otherwise(F.col("_band_layer")),
            }
        ).drop("_band_start", "_band_attempt", "_band_at", "_band_block", "_b_shard", "_b_block", "_b_z", "_b_t")
    value = F.col("_band_value")
    want = F.lit(0).cast("long") if p.kind == "zero" else hashing.fingerprint_column(F.col(LO), p.r)
    member = F.when(F.col(HI).isNull(), F.lit(None).cast("boolean")).otherwise(F.coalesce(value == want, F.lit(False)))
    packed = F.struct(
        value.alias("value"), F.col("_band_layer").alias("layer"), value.isNotNull().alias("found"),
        (member if p.is_filter else F.lit(None).cast("boolean")).alias("member"), F.lit(p.r).alias("bits_read"),
    )
    return got.withColumn(OUT, packed).drop("_band_layers", "_band_key", "_band_value", "_band_layer")


def _value(z: Column, r: int, start: Column, c: Column) -> Column:
    """The r value bits of a row that starts in the block of z."""

    def bit(q: Column) -> Column:
        parity = F.bit_count(_window(z, r, start.bitwiseAND(F.lit(63)), q).bitwiseAND(c)).bitwiseAND(F.lit(1))
        return F.call_function("shiftleft", parity.cast("long"), q)

    return F.aggregate(F.sequence(F.lit(0), F.lit(r - 1)), F.lit(0).cast("long"), lambda acc, q: acc.bitwiseOR(bit(q)))


def lookup(
    s: build.BandStructure, df: DataFrame, cols: list[str], strategy: str = "auto", out: str = "value",
    trace: bool = False, group_cols: list[str] | None = None,
) -> DataFrame:
    """Add the value of each row's key: null for a null key, arbitrary for a key that the
    function was not built on. trace adds `<out>_layer`."""
    got = _with_answer(s, df, cols, strategy, group_cols)
    added = {out: F.col(f"{OUT}.value")} | ({f"{out}_layer": F.col(f"{OUT}.layer")} if trace else {})
    return got.withColumns(added).drop(OUT)


def probe(
    s: build.BandStructure, df: DataFrame, cols: list[str], strategy: str = "auto", out: str = "member",
    count_bits: bool = False, group_cols: list[str] | None = None,
) -> DataFrame:
    """Add whether the filter holds each row's key: always true for its members, true by
    chance for others, null for a null key. count_bits adds `<out>_bits`, the bits read."""
    if not s.params.is_filter:
        raise ValueError("not a filter")
    got = _with_answer(s, df, cols, strategy, group_cols)
    added = {out: F.col(f"{OUT}.member")} | ({f"{out}_bits": F.col(f"{OUT}.bits_read")} if count_bits else {})
    return got.withColumns(added).drop(OUT)
