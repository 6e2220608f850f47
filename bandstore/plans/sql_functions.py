"""Structures as SQL functions and table functions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..functions import hashing
from ..operators import build as band
from ..operators import lookup
from .metrics import layer_report


def register(spark: SparkSession, name: str, s: band.BandStructure) -> None:
    """After this, SQL has `<name>(hi, lo)`, the value of a digest (`<name>_contains` for a
    filter), the table function `<name>_layers()` and the view `<name>_report`. Digests come
    from xxhash64 with the structure's seeds, see `digest_sql`."""
    if (size := lookup.table_bytes(s)) > lookup.BROADCAST_BYTES:
        raise ValueError(f"{size} bytes are too many for a SQL function; use lookup()")
    p = s.params
    rows = s.table.toArrow()
    shared = spark.sparkContext.broadcast(band.decode_rows(rows, p))

    def answers(hi: pa.Array, lo: pa.Array) -> pa.StructArray:
        shard = hashing.shard_of(np.asarray(hi.fill_null(0)).astype(np.int64).view(np.uint64), p.n_shards)
        return lookup._answers(shared.value, hi, lo, pa.array(shard), p)

    if p.is_filter:

        @F.arrow_udf("boolean")
        def contains(hi: pa.Array, lo: pa.Array) -> pa.Array:
            return answers(hi, lo).field("member")

        spark.udf.register(f"{name}_contains", contains)
    else:

        @F.arrow_udf("bigint")
        def value(hi: pa.Array, lo: pa.Array) -> pa.Array:
            return answers(hi, lo).field("value")

        spark.udf.register(name, value)
    figures = [(r["shard"], r["layer"], r["m"], r["n_in"], r["n_bumped"], r["empty"]) for r in rows.drop(list(band.STORED)).to_pylist()]

    @F.udtf(returnType="shard int, layer int, m long, n_in long, n_bumped long, empty long")
    class Layers:
        def eval(self):
            yield from figures

    spark.udtf.register(f"{name}_layers", Layers)
    layer_report(s).createOrReplaceTempView(f"{name}_report")


def digest_sql(key_seed: int, *columns: str) -> tuple[str, str]:
    """SQL of the two digest words of integer or string key columns."""
    keys = ", ".join(columns)
    return f"xxhash64({key_seed}, {keys})", f"xxhash64({key_seed + 7919}, {keys})"
