"""Build a layered function with two buckets of keys in memory at a time.

A layer is a sort of its keys by bucket, a forward pass that eliminates bucket after bucket, and
a backward pass over the echelon rows that substitutes. Slots left of the bucket at hand are
final, so the forward pass hands them on at once; the backward pass keeps the last w solution
entries. Both passes are iterators over rows that Spark has sorted, on disk where they do not fit.
Echelon rows go to the shared folder, with the bumped keys of each bucket, which are the next
layer's input. Only the packed table of a shard, r bits a slot, is put together at the end, and
the last layer's few keys are solved in memory. The tables equal those of `build` in one piece."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import hashing
from ..params import BandParams
from ..sources.shared import keep
from . import build as band
from . import kernel, solve

PLACED = "shard int, bucket long, pos int, start long, n_starts long, hi long, lo long, value long"
ECHELON = (
    "shard int, bucket long, n_starts long, threshold int, c0 binary, c1 binary, v binary, "
    "n_in long, n_redundant long, row_ops long, resident long, hi binary, lo binary, value binary"
)
SOLVED = "shard int, bucket long, n_starts long, threshold int, z binary, n_in long, n_bumped long, n_redundant long, empty long, row_ops long"


def _schema(ddl: str) -> pa.Schema:
    kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
    return pa.schema([(f.split()[0], kinds[f.split()[1]]) for f in ddl.split(", ")])


def build_streamed(df: DataFrame, cols: list[str], value: str | None = None, n_shards: int = 1, **options) -> band.BandStructure:
    """What `build` returns, by streams. Layered kinds with buckets from the left and free slots
    of zero. A key with different values is an error."""
    p = replace(BandParams(), n_shards=n_shards, is_filter=value is None, **options).resolved()
    if p.kind != "layered" or p.bucket_order != "l2r" or p.free != "zero":
        raise ValueError("streams build layered structures, buckets from the left, free slots zero")
    if value is None:
        pairs = band.digests(df, cols, "xx128", 1).distinct().withColumn("value", hashing.fingerprint_column(F.col("lo"), p.r))
    else:
        pairs = band.unique_pairs(df, cols, value, p.r, "xx128", 1)
    return band.BandStructure(p, "xx128", 1, keep(solved_streamed(pairs, p), "streamed"))


def solved_streamed(pairs: DataFrame, p: BandParams) -> DataFrame:
    """The table of (hi, lo, value) rows: a sort and two passes a layer."""
    shard = hashing.shard_column(F.col("hi"), p.n_shards).alias("shard")
    left = keep(pairs.select(shard, "hi", "lo", "value"), "pairs")
    tables = []
    for layer in range(p.layers - 1):
        sized = left.join(left.groupBy("shard").agg(F.count(F.lit(1)).alias("n")), "shard").select("shard", "n", "hi", "lo", "value")
        placed = sized.mapInArrow(_placing(p, layer), PLACED).repartition(p.n_shards, "shard")
        echelon = keep(placed.sortWithinPartitions("shard", "bucket", F.desc("pos")).mapInArrow(_forward(p, layer), ECHELON), "echelon")
        back = echelon.repartition(p.n_shards, "shard").sortWithinPartitions("shard", F.desc("bucket"))
        blocks = keep(back.mapInArrow(_backward(p), SOLVED), "blocks")
        tables.append(blocks.groupBy("shard").applyInArrow(_assembling(p, layer), band.TABLE_SCHEMA))
        left = echelon.select("shard", "hi", "lo", "value").mapInArrow(_bumped_keys, "shard int, hi long, lo long, value long")

    def last(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in band.shard_groups(batches):
            yield band.encode_tables(solve._last_layer(group, p, p.layers - 1), p)

    out = left.repartition(p.n_shards, "shard").sortWithinPartitions("shard").mapInArrow(last, band.TABLE_SCHEMA)
    for table in tables:
        out = out.unionByName(table)
    return out


def _placing(p: BandParams, layer: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            shard, n = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            hi = batch.column(2).to_numpy().view(np.uint64)
            start, pos, n_starts = (np.zeros(len(shard), np.int64) for _ in range(3))
            for size in np.unique(n):
                at = np.flatnonzero(n == size)
                n_starts[at] = solve.table_starts(int(size), p.eps, "layered")
                start[at] = hashing.starts(hi[at], int(n_starts[at[0]]), layer, 0)
                pos[at] = solve.position_of(start[at], hi[at], p.b, p.order, int(n_starts[at[0]]), layer, 0)
            columns = [pa.array(shard), pa.array(start // p.b), pa.array(pos.astype(np.int32)), pa.array(start), pa.array(n_starts)]
            yield pa.record_batch([*columns, *batch.columns[2:]], schema=_schema(PLACED))

    return run


def _buckets(batches: Iterable[pa.RecordBatch]) -> Iterator[tuple[int, int, int, list[np.ndarray]]]:
    """(shard, bucket, starts of the shard, [pos, start, hi, lo, value]), one bucket held at a time."""
    held: list[list[np.ndarray]] = []
    key = None
    for batch in batches:
        shard, bucket, n_starts = (batch.column(i).to_numpy() for i in (0, 1, 4))
        rest = [batch.column(2).to_numpy(), batch.column(3).to_numpy(), *(batch.column(i).to_numpy().view(np.uint64) for i in (5, 6, 7))]
        edges = [0, *(np.flatnonzero((np.diff(shard) != 0) | (np.diff(bucket) != 0)) + 1).tolist(), len(shard)]
        for a, z in zip(edges, edges[1:], strict=False):
            if a == z:
                continue
            here = int(shard[a]), int(bucket[a]), int(n_starts[a])
            if key is not None and here != key:
                yield *key, [np.concatenate(x) for x in zip(*held, strict=True)]
                held = []
            key = here
            held.append([x[a:z] for x in rest])
    if key is not None:
        yield *key, [np.concatenate(x) for x in zip(*held, strict=True)]


def _forward(p: BandParams, layer: int):
    allowed = p.thresholds()
    spill = p.w // 2 if p.mode == "cautious" else None
    word = (1 << 64) - 1

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, at, done, rows = kernel.ScalarEliminator(0), None, 0, []
        notes: dict[int, dict] = {}

        def flush(upto: int) -> None:
            nonlocal done
            shard, n_starts = at
            m = n_starts + p.w - 1
            while done < upto:
                slots = range(done * p.b, min((done + 1) * p.b, m))
                c = [system.coefs.pop(s, 0) for s in slots]
                v = [system.values.pop(s, 0) for s in slots]
                row = {"shard": shard, "bucket": done, "n_starts": n_starts, "threshold": 0, "n_in": 0, "n_redundant": 0, "row_ops": 0}
                row |= {"resident": 0, "hi": b"", "lo": b"", "value": b"", "c1": b"", "v": np.array(v, np.uint64).tobytes()}
                row["c0"] = np.array([x & word for x in c], np.uint64).tobytes()
                if p.w > 64:
                    row["c1"] = np.array([x >> 64 for x in c], np.uint64).tobytes()
                rows.append(row | notes.pop(done, {}))
                done += 1

        def blocks() -> int:
            return -(-(at[1] + p.w - 1) // p.b)

        for shard, bucket, n_starts, (pos, start, hi, lo, value) in _buckets(batches):
            if at is not None and at[0] != shard:
                flush(blocks())
                system, done = kernel.ScalarEliminator(0), 0
            at = shard, n_starts
            flush(bucket)
            system.journal.clear()
            words = hashing.coefficients(lo, p.w, p.coef, layer, 0)
            coefs = words[0].tolist() if len(words) == 1 else [a | (b << 64) for a, b in zip(*(x.tolist() for x in words), strict=True)]
            before, marks, redundant, reach, t = system.row_ops, [], [], -1, 0
            for k, row in enumerate(zip(start.tolist(), coefs, value.tolist(), strict=True)):
                marks.append(system.mark())
                status, slot = system.insert(*row)
                if status == kernel.FAILED:
                    t = next(x for x in allowed if x > pos[k])
                    break
                redundant.append(status == kernel.REDUNDANT)
                reach = max(reach, slot)
            if not t and spill is not None and reach >= min((bucket + 1) * p.b, n_starts) + spill:
                t = next((x for x in allowed if x > 0), allowed[-1])
            resident = len(system.coefs) + len(pos)
            cut = int(np.searchsorted(-pos.astype(np.int64), -t, "right")) if t else len(pos)
            if cut < len(marks):
                system.rollback(marks[cut])
            notes[bucket] = {
                "threshold": int(t), "n_in": len(pos), "n_redundant": sum(redundant[:cut]), "row_ops": system.row_ops - before,
                "resident": resident, "hi": hi[cut:].tobytes(), "lo": lo[cut:].tobytes(), "value": value[cut:].tobytes(),
            }
            if len(rows) >= 64:
                yield pa.RecordBatch.from_pylist(rows, schema=_schema(ECHELON))
                rows = []
        if at is not None:
            flush(blocks())
        if rows:
            yield pa.RecordBatch.from_pylist(rows, schema=_schema(ECHELON))

    return run


def _backward(p: BandParams):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, window, mask = None, [0] * p.r, (1 << (p.w - 1)) - 1
        for batch in batches:
            rows = []
            for got in batch.to_pylist():
                if got["shard"] != shard:
                    shard, window = got["shard"], [0] * p.r
                c = np.frombuffer(got["c0"], np.uint64).tolist()
                if p.w > 64:
                    c = [a | (b << 64) for a, b in zip(c, np.frombuffer(got["c1"], np.uint64).tolist(), strict=True)]
                v = np.frombuffer(got["v"], np.uint64).tolist()
                z = [0] * len(c)
                for s in range(len(c) - 1, -1, -1):
                    total = 0
                    for q in range(p.r):
                        bit = ((((c[s] >> 1) & window[q]).bit_count() ^ (v[s] >> q)) & 1) if c[s] else 0
                        window[q] = ((window[q] << 1) | bit) & mask
                        total |= bit << q
                    z[s] = total
                kept = {x: got[x] for x in ("shard", "bucket", "n_starts", "threshold", "n_in", "n_redundant", "row_ops")}
                rows.append(kept | {"z": np.array(z, np.uint64).tobytes(), "n_bumped": len(got["hi"]) // 8, "empty": c.count(0)})
            yield pa.RecordBatch.from_pylist(rows, schema=_schema(SOLVED))

    return run


def _assembling(p: BandParams, layer: int):
    def run(table: pa.Table) -> pa.Table:
        got = table.sort_by("bucket")
        n_starts, shard = got["n_starts"][0].as_py(), got["shard"][0].as_py()
        z = np.concatenate([np.frombuffer(x, np.uint64) for x in got["z"].to_pylist()])
        thresholds = got["threshold"].to_numpy()[: -(-n_starts // p.b)].astype(np.int32)
        stats = {c: int(got[c].to_numpy().sum()) for c in ("n_in", "n_bumped", "n_redundant", "empty", "row_ops")} | {"pieces": 1}
        words = z.copy() if p.layout == "contiguous" else kernel.interleave(z, p.r)
        made = solve.LayerTable(shard, layer, 0, p.w, n_starts, len(z), words, thresholds, stats)
        return pa.Table.from_batches([band.encode_tables([made], p)])

    return run


def _bumped_keys(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        counts = [len(x) // 8 for x in batch.column(1).to_pylist()]
        keys = [np.frombuffer(b"".join(batch.column(i).to_pylist()), np.int64) for i in (1, 2, 3)]
        yield pa.record_batch([pa.array(np.repeat(batch.column(0).to_numpy(), counts), pa.int32()), *map(pa.array, keys)], ["shard", "hi", "lo", "value"])
