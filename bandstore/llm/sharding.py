"""Sharding by a two-pass external shuffle.

Pass one scatters records into buckets that fit a task's memory, by a seeded hash of the
whole record. Pass two orders each bucket by that hash, draws a Fisher-Yates permutation of
its positions from a generator seeded by (seed, bucket), and gives each record its place in
the global order: the bucket's offset plus its permuted position. Shards are equal cuts of
the global order, so their row counts differ by one at most.

Only a bucket's permutation (8 bytes a record) is held in a task; the records stream past in
sorted order, which Spark spills. Everything depends on the records and the seed alone, so a
repeated task gives the same bytes.

Defined results: a null text has size 1 and the crc of the empty text; equal rows are placed
one by one and get different slots; an empty table gives no shards; fewer rows than shards
leave the last shards empty; columns of any name stay as they are.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import fresh, seeded_hash, slices

BUCKET_BYTES = 64 << 20


def record_size(text: Column) -> Column:
    return (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("long")


def scatter(df: DataFrame, keys: list[str], seed: int, n_buckets: int) -> DataFrame:
    """Two more columns at the end, under names that the input does not have: hash and bucket."""
    h, bucket = fresh(df.columns, "shuffle_hash", "shuffle_bucket")
    return df.withColumn(h, seeded_hash(seed, *[F.col(k) for k in keys])).withColumn(bucket, (F.col(h) % n_buckets).cast("int"))


def external_shuffle(
    df: DataFrame,
    text: str = "text",
    keys: tuple[str, ...] = ("doc_id", "text"),
    seed: int = 31,
    bucket_bytes: int = BUCKET_BYTES,
    least_buckets: int | None = None,
    place: str = "place",
) -> tuple[DataFrame, int]:
    """The records with `place` (one of that name is replaced), their position in a seeded global order from 0, and their
    number. Two counts come to the driver: bytes, and rows by bucket (a row per bucket,
    that is per bucket_bytes of input)."""
    spark = df.sparkSession
    df = df.drop(place)
    names = df.columns
    n_bytes = df.agg(F.sum(record_size(F.col(text)))).first()[0] or 0
    least = least_buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
    n_buckets = max(least, -(-int(n_bytes) // bucket_bytes))
    scattered = scatter(df, list(keys), seed, n_buckets)
    h, bucket_name = scattered.columns[-2:]
    counts = {r[0]: r[1] for r in scattered.groupBy(bucket_name).count().collect()}
    offsets, total = {}, 0
    for b in range(n_buckets):
        offsets[b] = total
        total += counts.get(b, 0)
    shared = spark.sparkContext.broadcast((offsets, counts))  # two numbers per bucket
    dealt = scattered.repartitionById(n_buckets, F.col(bucket_name)).sortWithinPartitions(
        bucket_name, h, *[F.col(k) for k in keys], F.xxhash64(*[F.col(c) for c in names])
    )
    schema = df.withColumn(place, F.lit(0).cast("long")).schema
    at, n_keep = len(names) + 1, len(names)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        offsets, counts = shared.value
        bucket, order, seen = -1, np.zeros(0, np.int64), 0
        for whole in batches:
            for batch in slices(whole):
                of = batch.column(at).to_numpy()
                places = np.empty(len(of), np.int64)
                begin = 0
                while begin < len(of):
                    if of[begin] != bucket:
                        bucket, seen = int(of[begin]), 0
                        # Generator.permutation is a Fisher-Yates shuffle of the positions.
                        order = np.random.default_rng((seed, bucket)).permutation(counts[bucket]) + offsets[bucket]
                    end = begin + int(np.searchsorted(of[begin:], bucket, "right"))
                    places[begin:end] = order[seen : seen + end - begin]
                    seen, begin = seen + end - begin, end
                yield pa.record_batch([*batch.columns[:n_keep], pa.array(places)], schema=pa.schema([*[batch.schema.field(i) for i in range(n_keep)], pa.field(place, pa.int64())]))

    return dealt.mapInArrow(run, schema), total


def assign_shards(df: DataFrame, n_shards: int = 16, total: int = 0, place: str = "place") -> DataFrame:
    """Shard and slot by equal cuts of the order: the first total % n_shards shards have one
    row more than the others."""
    small, extra = divmod(total, n_shards)
    p, edge = F.col(place), extra * (small + 1)
    in_large = p < edge
    large_shard = F.floor(p / F.lit(max(small + 1, 1)))
    small_shard = F.lit(extra) + F.floor((p - F.lit(edge)) / F.lit(max(small, 1)))
    shard = F.when(in_large, large_shard).otherwise(small_shard).cast("int")
    slot = F.when(in_large, F.pmod(p, F.lit(small + 1))).otherwise(F.pmod(p - F.lit(edge), F.lit(max(small, 1))))
    return df.withColumns({"shard": shard, "slot": slot.cast("long")})


def shard_documents(
    df: DataFrame, n_shards: int = 16, text: str = "text", keys: tuple[str, ...] = ("doc_id", "text"), seed: int = 31
) -> DataFrame:
    """Records with shard and slot; columns of these names are replaced, all others stay."""
    df = df.drop("shard", "slot")
    place = fresh(df.columns, "place")[0]
    placed, total = external_shuffle(df, text, keys, seed, place=place)
    return assign_shards(placed, n_shards, total, place).drop(place)


def write_shards(df: DataFrame, path: str) -> None:
    """One folder for each shard, rows in slot order within their file parts."""
    (
        df.repartition(F.col("shard"), F.floor(F.col("slot") / F.lit(1 << 20)))
        .sortWithinPartitions("shard", "slot")
        .write.partitionBy("shard")
        .mode("errorifexists")
        .parquet(path)
    )
