"""What static functions and filters are used for: perfect hashing, compact codes, variable
length values, and join prefilters."""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from ..functions import hashing
from ..sources.shared import keep
from . import build as band
from .lookup import lookup, probe
from .solve import Keys

# ---- perfect hashing ------------------------------------------------------------------------

CANDIDATES, LOAD = 4, 1.024


@dataclass
class PerfectHash:
    """A 2-bit function that says which of four cells a key has; cells of a shard follow those
    of the shards before. `sizes`: cells by shard, a number for each shard."""

    choice: band.BandStructure
    sizes: DataFrame
    cols: list[str]
    n_shards: int


def _cells(hi: np.ndarray, n_cells: int, attempt: int) -> np.ndarray:
    out = []
    for i in range(CANDIDATES):
        h = hashing.remix(hi, 5000 + attempt * CANDIDATES + i) >> np.uint64(32)
        out.append(((h * np.uint64(n_cells)) >> np.uint64(32)).astype(np.int64))
    return np.stack(out, axis=1)


def place(cells: np.ndarray, n_cells: int, seed: int = 1, max_steps: int = 200) -> np.ndarray | None:
    """The candidate of each key, all cells distinct, by random-walk insertion; None if stuck."""
    n = len(cells)
    owner, choice = np.full(n_cells, -1, np.int64).tolist(), [0] * n
    rows, rng = cells.tolist(), np.random.default_rng(seed)
    picks = rng.integers(0, CANDIDATES, 1 << 16).tolist()
    at = 0
    for key in range(n):
        current, came_from = key, -1
        for _ in range(max_steps + 20 * int(math.log2(n + 2)) * CANDIDATES):
            free = next((j for j, c in enumerate(rows[current]) if owner[c] < 0), None)
            if free is not None:
                owner[rows[current][free]], choice[current] = current, free
                break
            at = (at + 1) % len(picks)
            j = picks[at]
            if rows[current][j] == came_from:
                j = (j + 1) % CANDIDATES
            cell = rows[current][j]
            evicted, owner[cell], choice[current] = owner[cell], current, j
            current, came_from = evicted, cell
        else:
            return None
    return np.array(choice, np.int64)


def build_perfect_hash(df: DataFrame, cols: list[str], shard_keys: int = 1 << 16, **options) -> PerfectHash:
    """Shards of about shard_keys keys, each on LOAD times as many cells; a shard without a
    placement tries more cells. One shuffle; then the choices become a static function."""
    keys = hashing.with_digest(df.select(*cols), cols).where(F.col("hi").isNotNull()).select("hi", "lo").distinct()
    n_shards = band.n_shards_for(keys.count(), shard_keys)
    dealt = keys.select(hashing.shard_column(F.col("hi"), n_shards).alias("shard"), "hi", "lo", F.lit(0).cast("long").alias("value"))
    dealt = dealt.repartition(n_shards, "shard").sortWithinPartitions("shard", "hi", "lo")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in band.shard_groups(batches):
            for shard, k in group.items():
                choice, n_cells, attempt = _place_shard(k)
                n = len(k)
                yield pa.record_batch(
                    [pa.array(np.full(n, shard, np.int32)), pa.array(k.hi.view(np.int64)), pa.array(k.lo.view(np.int64)),
                     pa.array(choice), pa.array(np.full(n, n_cells)), pa.array(np.full(n, attempt))],
                    names=["shard", "hi", "lo", "value", "n_cells", "attempt"],
                )

    placed = keep(dealt.mapInArrow(run, "shard int, hi long, lo long, value long, n_cells long, attempt long"), "placed")
    p = band.replace(band.BandParams(), r=2, n_shards=n_shards, **options).resolved()
    choice = band.BandStructure(p, "xx128", 1, keep(band.solved(placed.select("hi", "lo", "value"), p), "choice"))
    per_shard = placed.groupBy("shard").agg(F.max("n_cells").alias("n_cells"), F.max("attempt").alias("attempt"))
    # A row for each shard: prefix sums over the shards' sizes.
    before = F.sum("n_cells").over(W.partitionBy(F.lit(0)).orderBy("shard").rowsBetween(W.unboundedPreceding, -1))
    sizes = per_shard.withColumn("base", F.coalesce(before, F.lit(0)).cast("long"))
    return PerfectHash(choice, sizes, cols, n_shards)


def _place_shard(k: Keys) -> tuple[np.ndarray, int, int]:
    for attempt in range(50):
        n_cells = max(CANDIDATES, math.ceil(len(k) * LOAD * (1 + 0.004 * attempt)))
        choice = place(_cells(k.hi, n_cells, attempt), n_cells)
        if choice is not None:
            return choice, n_cells, attempt
    raise RuntimeError("no placement; equal digests?")


def perfect_hash(ph: PerfectHash, df: DataFrame, out: str = "id") -> DataFrame:
    """Add an injective id below about 1.024 n for the keys that it was built on."""
    got = lookup(ph.choice, df, ph.cols, out="_choice")
    keyed = hashing.with_digest(got, ph.cols, "xx128", 1, "_hi", "_lo")
    keyed = keyed.withColumn("_shard", hashing.shard_column(F.col("_hi"), ph.n_shards))
    joined = keyed.join(F.broadcast(ph.sizes.withColumnRenamed("shard", "_shard")), "_shard", "left")  # a row per shard
    round_no = F.lit(5000) + F.col("attempt") * CANDIDATES + F.col("_choice")
    h = F.shiftrightunsigned(hashing.remix_column(F.col("_hi"), round_no), 32)
    cell = F.shiftrightunsigned(h * F.col("n_cells"), 32)
    return joined.withColumn(out, F.col("base") + cell).drop("_choice", "_hi", "_lo", "_shard", "n_cells", "attempt", "base")


# ---- order-preserving codes ------------------------------------------------------------------


def ordered_codes(df: DataFrame, col: str, out: str = "code") -> DataFrame:
    """(value, code): dense codes from 0 in the values' order. Distinct values are dealt by
    range and numbered within their partition; only counts by partition meet in one place."""
    values = df.select(col).where(F.col(col).isNotNull()).distinct()
    ranged = keep(values.repartitionByRange(col).withColumn("part", F.spark_partition_id()), "ranged")
    counts = ranged.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    before = F.sum("n").over(W.partitionBy(F.lit(0)).orderBy("part").rowsBetween(W.unboundedPreceding, -1))
    offsets = counts.withColumn("base", F.coalesce(before, F.lit(0))).select("part", "base")
    numbered = ranged.withColumn("i", F.row_number().over(W.partitionBy("part").orderBy(col)) - 1)
    return numbered.join(F.broadcast(offsets), "part").select(col, (F.col("base") + F.col("i")).cast("long").alias(out))


def build_codes(df: DataFrame, col: str, n_codes: int, **options) -> band.BandStructure:
    """A static function from a column's values to their order-preserving codes."""
    codes = ordered_codes(df, col)
    return band.build(codes, [col], "code", r=max(1, (n_codes - 1).bit_length()), **options)


# ---- values of variable length -----------------------------------------------------------------


def huffman(counts: dict) -> dict:
    """Bit strings of a prefix code."""
    heap = [(n, i, v) for i, (v, n) in enumerate(sorted(counts.items(), key=lambda x: (x[1], str(x[0]))))]
    if len(heap) == 1:
        return {heap[0][2]: "0"}
    heapq.heapify(heap)
    i, tree = len(heap), {}
    while len(heap) > 1:
        (na, _, a), (nb, _, b) = heapq.heappop(heap), heapq.heappop(heap)
        node = ("node", i)
        tree[node] = (a, b)
        heapq.heappush(heap, (na + nb, i, node))
        i += 1
    codes: dict = {}

    def walk(node, prefix: str) -> None:
        if node in tree:
            walk(tree[node][0], prefix + "0")
            walk(tree[node][1], prefix + "1")
        else:
            codes[node] = prefix

    walk(heap[0][2], "")
    return codes


def golomb(value: int, divisor_bits: int) -> str:
    """Unary quotient, then divisor_bits of the remainder."""
    q, rest = divmod(value, 1 << divisor_bits)
    return "1" * q + "0" + (format(rest, f"0{divisor_bits}b") if divisor_bits else "")


@dataclass
class VarLength:
    """Codes by value, and one function of (key, bit number), or one function per bit number."""

    codes: dict
    functions: list[band.BandStructure]
    cols: list[str]
    interleaved: bool

    @property
    def longest(self) -> int:
        return max(map(len, self.codes.values()))


def build_varlen(df: DataFrame, cols: list[str], value: str, code: str = "huffman", interleaved: bool = False, limit: int = 4096, **options) -> VarLength:
    """Prefix codes stored bit by bit. The code table, at most `limit` values, is on the driver."""
    counts = {r[0]: r[1] for r in df.groupBy(value).count().limit(limit + 1).collect()}
    if len(counts) > limit:
        raise ValueError(f"more than {limit} values")
    codes = huffman(counts) if code == "huffman" else {v: golomb(int(v), max(0, int(math.log2(max(1, sum(int(v) * n for v, n in counts.items()) / sum(counts.values())))))) for v in counts}
    table = F.create_map(*[x for v, c in codes.items() for x in (F.lit(v), F.lit(c))])
    bits = df.select(*cols, F.posexplode(F.split(F.element_at(table, F.col(value)), "")).alias("_k", "_bit"))
    bits = bits.where(F.col("_bit") != "").withColumn("_bit", F.col("_bit").cast("long"))
    if not interleaved:
        return VarLength(codes, [band.build(bits, [*cols, "_k"], "_bit", r=1, **options)], cols, False)
    longest = max(map(len, codes.values()))
    return VarLength(codes, [band.build(bits.where(F.col("_k") == k), cols, "_bit", r=1, **options) for k in range(longest)], cols, True)


def decode_varlen(v: VarLength, df: DataFrame, out: str = "value") -> DataFrame:
    """Read bits until they make a code."""
    got = df
    names = []
    for k in range(v.longest):
        name = f"_bit{k}"
        names.append(name)
        if v.interleaved:
            got = lookup(v.functions[k], got, v.cols, out=name)
        else:
            got = lookup(v.functions[0], got.withColumn("_k", F.lit(k)), [*v.cols, "_k"], out=name).drop("_k")
    bits = F.concat(*[F.coalesce(F.col(n).cast("string"), F.lit("0")) for n in names])
    result: Column = F.lit(None)
    for value, code in v.codes.items():
        result = F.when(F.substring(bits, 1, len(code)) == code, F.lit(value)).otherwise(result)
    return got.withColumn(out, result).drop(*names)


# ---- join prefilters ---------------------------------------------------------------------------


def prefilter_join(big: DataFrame, small: DataFrame, on: list[str], how: str = "inner", kind: str = "zero", r: int = 8, **options) -> DataFrame:
    """The exact join, after a filter over the small side has dropped most rows of the big one
    before its shuffle. inner, left_semi and left_anti; for the anti join rows that the filter
    rejects are results at once."""
    f = band.build(small, on, kind=kind, r=r, **options)
    probed = probe(f, big, on, out="_member")
    # Rows with a null key match nothing.
    passing = probed.where(F.col("_member")).drop("_member")
    if how in ("inner", "left_semi"):
        return passing.join(small if how == "inner" else small.select(*on), on, how)
    if how == "left_anti":
        rejected = probed.where(~F.coalesce(F.col("_member"), F.lit(False))).drop("_member")
        return rejected.unionByName(passing.join(small.select(*on), on, "left_anti"))
    raise ValueError(f"unknown join {how}")


def ngram_probe(docs: DataFrame, benchmark: DataFrame, n: int = 8, r: int = 12) -> DataFrame:
    """(doc_id, item_id) pairs that share n consecutive words: word n-grams of documents go
    through a filter over the items' n-grams, and what passes is joined exactly."""

    def grams(df: DataFrame, id_col: str) -> DataFrame:
        split = df.select(id_col, F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != "").alias("words"))
        count = F.size("words") - n + 1
        at = F.when(count > 0, F.sequence(F.lit(1), count)).otherwise(F.array().cast("array<int>"))
        text = F.transform(at, lambda i: F.array_join(F.slice("words", i, n), " "))
        return split.select(id_col, F.explode(F.array_distinct(text)).alias("gram"))

    items = grams(benchmark, "item_id")
    f = band.build(items, ["gram"], kind="zero", r=r)
    passing = probe(f, grams(docs, "doc_id"), ["gram"], out="_m").where("_m").drop("_m")
    return passing.join(items, "gram").select("doc_id", "item_id").distinct()
