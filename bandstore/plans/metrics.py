"""Space, accuracy and work measures of built structures; sweeps over parameters."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from .. import model
from ..functions import hashing
from ..operators import build as band
from ..operators import kernel, metadata, solve
from ..operators.lookup import probe
from ..params import BandParams
from ..sources.shared import keep

SHARD_BITS = 256  # shard, layer, try, width, starts and slots of a row, as they are stored


def layer_report(s: band.BandStructure) -> DataFrame:
    """For each layer: keys in, bumped, slots, empty share e, and the bits that are stored: of the
    table with its padding, of thresholds with their exceptions and range bits, of the rows."""
    p = s.params
    stored = {c: F.length(c).cast("long") * 8 for c in band.STORED}
    rows = s.table.withColumns(
        {"table_bits": stored["z"], "meta_bits": stored["codes"] + stored["exceptions"] + stored["ranges"], "exception_bits": stored["exceptions"],
         "buckets": F.ceil(F.col("n_starts") / p.b), "row_bits": F.lit(SHARD_BITS).cast("long")}
    )
    summed = ("n_in", "n_bumped", "n_redundant", "m", "empty", "row_ops", "buckets", "table_bits", "meta_bits", "exception_bits", "row_bits")
    return (
        rows.groupBy("layer")
        .agg(*[F.sum(c).alias(c) for c in summed])
        .withColumns({"e": F.col("empty") / F.col("m"), "bumped_share": F.col("n_bumped") / F.greatest(F.col("n_in"), F.lit(1))})
    )


def space_report(s: band.BandStructure, fpr: float | None = None) -> DataFrame:
    """Stored bits over all layers against n * r; of a filter with a measured rate also against
    n * log2(1 / fpr)."""
    p = s.params
    # Every key is served in one layer, so what comes in less what is bumped are all keys.
    out = layer_report(s).agg(
        F.sum(F.col("n_in") - F.col("n_bumped")).alias("n"),
        *[F.sum(c).alias(c) for c in ("table_bits", "meta_bits", "row_bits", "buckets", "empty", "m")],
    )
    bits = F.col("table_bits") + F.col("meta_bits") + F.col("row_bits")
    out = out.withColumns({"bits": bits, "overhead": bits / (F.col("n") * p.r) - 1})
    if fpr:
        out = out.withColumn("filter_overhead", F.col("bits") / (F.col("n") * -math.log2(fpr)) - 1)
    return out


def measure_fpr(s: band.BandStructure, negatives: DataFrame, cols: list[str]) -> DataFrame:
    """Positives among keys that the filter was not built on, and bits read."""
    got = probe(s, negatives, cols, out="m", count_bits=True)
    hits = F.sum(F.col("m").cast("long"))
    return got.agg(F.count(F.lit(1)).alias("probes"), hits.alias("hits"), F.avg("m_bits").alias("bits_read")).withColumn(
        "fpr", F.col("hits") / F.col("probes")
    )


def within(n: int, hits: int, p: float, sigmas: float = 4.0) -> bool:
    return abs(hits - n * p) <= sigmas * math.sqrt(n * p * (1 - p)) + 1


def zero_report(members: solve.Keys, foreign: solve.Keys, p: BandParams) -> dict:
    """Share of foreign rows that the span holds (dry insertions that vanish), and of redundant
    members, of one zero-right-hand-side system."""
    n_starts = solve.table_starts(len(members), p.eps, "zero")
    system = kernel.ScalarEliminator(n_starts + p.w - 1)
    redundant = 0
    for s, c in _rows(members, n_starts, p):
        redundant += system.insert(s, c, 0)[0] == kernel.REDUNDANT
    inside = sum(system.insert(s, c, 0, dry=True)[0] == kernel.REDUNDANT for s, c in _rows(foreign, n_starts, p))
    span = inside / max(1, len(foreign))
    return {"redundant": redundant / max(1, len(members)), "span": span, "fpr": model.false_positive_rate(span, p.r)}


def zero_span(members: DataFrame, foreign: DataFrame, cols: list[str], grid: list[BandParams]) -> DataFrame:
    """Per eps, zero_report over all keys of both tables: (eps, n_members, redundant, n_foreign,
    inside), each shard's system in a task of its own."""
    both = [hashing.with_digest(df.select(*cols), cols).where("hi is not null").select("hi", "lo").distinct() for df in (members, foreign)]
    n_shards = band.n_shards_for(both[0].count())
    shard = hashing.shard_column(F.col("hi"), n_shards).alias("shard")
    rows = both[0].select(shard, F.lit(True).alias("member"), "hi", "lo").unionByName(both[1].select(shard, F.lit(False).alias("member"), "hi", "lo"))
    which = F.explode(F.array(*[F.lit(i) for i in range(len(grid))])).alias("at")

    def run(table: pa.Table) -> pa.Table:
        member = table.column("member").to_numpy()
        hi, lo = (table.column(c).to_numpy().view(np.uint64) for c in ("hi", "lo"))
        own, other = (solve.Keys(hi[x], lo[x], np.zeros(int(x.sum()), np.uint64)) for x in (member, ~member))
        p = grid[table.column("at")[0].as_py()]
        got = zero_report(own, other, p)
        return pa.table({
            "eps": [p.eps], "n_members": [len(own)], "redundant": [round(got["redundant"] * len(own))],
            "n_foreign": [len(other)], "inside": [round(got["span"] * len(other))],
        })

    of_shards = rows.select("*", which).groupBy("shard", "at").applyInArrow(run, "eps double, n_members long, redundant long, n_foreign long, inside long")
    return of_shards.groupBy("eps").agg(*(F.sum(c).alias(c) for c in ("n_members", "redundant", "n_foreign", "inside")))


def _rows(keys: solve.Keys, n_starts: int, p: BandParams) -> Iterator[tuple[int, int]]:
    start = hashing.starts(keys.hi, n_starts, 0, 0)
    words = hashing.coefficients(keys.lo, p.w, p.coef, 0, 0)
    for i in range(len(start)):
        c = int(words[0][i])
        if len(words) == 2:
            c |= int(words[1][i]) << 64
        yield int(start[i]), c


# ---- diagnostics of starts, in SQL ---------------------------------------------------------


def start_rows(df: DataFrame, cols: list[str], n_starts: int, algo: str = "md5") -> DataFrame:
    """(digest, start) by the plain rule start = (h * P) >> 32 on 32 bits of the md5 digest,
    which other engines can repeat."""
    keyed = hashing.with_digest(df, cols, algo)
    h = F.shiftright("hi", 28) if algo == "md5" else F.shiftrightunsigned("hi", 32)
    return keyed.select("hi", "lo", F.shiftright(h * F.lit(n_starts), 32).alias("start"))


def bucket_histogram(starts: DataFrame, b: int) -> DataFrame:
    return starts.groupBy(F.floor(F.col("start") / b).alias("bucket")).agg(F.count(F.lit(1)).alias("n_keys"))


def ordered_parts(df: DataFrame, *order: str) -> DataFrame:
    """The rows with `_part`, a number of the range of `order` that they lie in; kept, as ranges
    come from a sample. Windows by part and offsets between parts then stand for one window over
    the whole table, which would be one task's."""
    return keep(df.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()), "ordered")


def simple_diagonal(starts: DataFrame) -> DataFrame:
    """First free slot of each key in start order: j + max over i <= j of (s_i - i)."""
    rows = ordered_parts(starts, "start", "hi", "lo")
    w = W.partitionBy("_part").orderBy("start", "hi", "lo")
    local = rows.withColumn("_i", (F.row_number().over(w) - 1).cast("long"))
    local = local.withColumn("_reach", F.max(F.col("start") - F.col("_i")).over(w.rowsBetween(W.unboundedPreceding, 0)))
    # A row for each part.
    parts = local.groupBy("_part").agg(F.count(F.lit(1)).alias("_n"), F.max(F.col("start") - F.col("_i")).alias("_top"))
    before = W.partitionBy(F.lit(0)).orderBy("_part").rowsBetween(W.unboundedPreceding, -1)
    parts = parts.withColumn("_base", F.coalesce(F.sum("_n").over(before), F.lit(0)).cast("long"))
    parts = parts.withColumn("_carried", F.max(F.col("_top") - F.col("_base")).over(before)).select("_part", "_base", "_carried")
    joined = local.join(F.broadcast(parts), "_part")
    rn = F.col("_base") + F.col("_i")
    reach = F.greatest(F.col("_reach") - F.col("_base"), F.coalesce("_carried", F.col("_reach") - F.col("_base")))
    return joined.withColumns({"rn": rn, "slot": (reach + rn).cast("long")}).drop("_part", "_i", "_reach", "_base", "_carried")


def queue_heights(starts: DataFrame, n_slots: int) -> DataFrame:
    """Height at each slot of a queue that serves one key a slot."""
    spark = starts.sparkSession
    slots = spark.range(n_slots).select(F.col("id").alias("slot"))
    arrivals = starts.groupBy(F.col("start").alias("slot")).agg(F.count(F.lit(1)).alias("a"))
    rows = ordered_parts(slots.join(arrivals, "slot", "left").select("slot", F.coalesce("a", F.lit(0)).alias("a")), "slot")
    w = W.partitionBy("_part").orderBy("slot").rowsBetween(W.unboundedPreceding, 0)
    local = rows.withColumn("_sum", F.sum("a").over(w)).withColumn("_d", F.col("_sum") - (F.col("slot") + 1))
    local = local.withColumn("_low", F.min("_d").over(w))
    parts = local.groupBy("_part").agg(F.max("_sum").alias("_n"), F.min("_d").alias("_least"))
    before = W.partitionBy(F.lit(0)).orderBy("_part").rowsBetween(W.unboundedPreceding, -1)
    parts = parts.withColumn("_base", F.coalesce(F.sum("_n").over(before), F.lit(0)).cast("long"))
    parts = parts.withColumn("_carried", F.min(F.col("_least") + F.col("_base")).over(before)).select("_part", "_base", "_carried")
    joined = local.join(F.broadcast(parts), "_part")  # a row for each part
    low = F.least(F.lit(0), F.col("_low") + F.col("_base"), F.coalesce("_carried", F.lit(0)))
    return joined.select("slot", (F.col("_d") + F.col("_base") - low).cast("long").alias("height"))


def duplicate_digests(df: DataFrame, cols: list[str], algo: str = "xx128") -> DataFrame:
    """Digests that more than one row has."""
    keyed = hashing.with_digest(df.select(*cols), cols, algo).where(F.col("hi").isNotNull())
    return keyed.groupBy("hi", "lo").agg(F.count(F.lit(1)).alias("n_rows")).where(F.col("n_rows") > 1)


def system_profile(keys: solve.Keys, p: BandParams, n_starts: int, order: np.ndarray | None = None) -> dict:
    """Filled slots, failures, row operations and the bound on them, of one plain system."""
    system = kernel.ScalarEliminator(n_starts + p.w - 1)
    rows = list(_rows(keys, n_starts, p))
    filled_for, failed = [], 0
    for i in order if order is not None else range(len(rows)):
        got, slot = system.insert(*rows[i], int(keys.value[i]))
        if got == kernel.PLACED:
            filled_for.append(slot - rows[i][0])
        elif got == kernel.FAILED:
            failed += 1
    filled = sorted(system.coefs)
    placed_starts = sum(f for f in filled) - sum(filled_for)
    return {"filled": filled, "failed": failed, "not_placed": len(rows) - len(filled), "row_ops": system.row_ops, "bound": sum(filled) - placed_starts}


SYSTEM_ROUND, SYSTEM_KEYS = 77, 1 << 16


def systems(df: DataFrame, cols: list[str], size: int, run: Callable[[solve.Keys], dict], ddl: str) -> DataFrame:
    """A row of run() for each of the systems of about `size` keys that the table's keys are cut
    into by hash. Values are one bit."""
    pairs = band.digests(df, cols, "xx128", 1).distinct()
    shard = hashing.shard_column(F.col("hi"), band.n_shards_for(band.approximate_keys(df, cols, "xx128", 1), SYSTEM_KEYS)).alias("shard")

    def solved(rows: pa.Table) -> pa.Table:
        hi, lo = (rows.column(c).to_numpy().view(np.uint64) for c in ("hi", "lo"))
        keys = solve.Keys(hi, lo, hashing.fingerprint(lo, 1))
        which = hashing.remix(hi, SYSTEM_ROUND) % np.uint64(max(1, round(len(keys) / size)))
        order = np.lexsort((lo, hi, which))
        cuts = np.flatnonzero(np.diff(which[order])) + 1
        return pa.Table.from_pylist([run(keys.take(own)) for own in np.split(order, cuts)], schema=_arrow(ddl))

    return pairs.select(shard, "hi", "lo").groupBy("shard").applyInArrow(solved, ddl)


def rank_profile(keys: solve.Keys, m: int) -> dict:
    """Rows that a band of 16 bits places in m slots, and the rank of the same rows by dense
    elimination."""
    system, dense = kernel.ScalarEliminator(m), {}
    p = BandParams(kind="plain", w=16, r=1).resolved()
    for s, c in _rows(keys, m - 15, p):
        system.insert(s, c, 0)
        row = c << s
        while row and (low := row & -row) in dense:
            row ^= dense[low]
        if row:
            dense[row & -row] = row
    return {"n": len(keys), "placed": len(system.coefs), "rank": len(dense)}


def heights(filled: list[int], starts: list[int], m: int) -> np.ndarray:
    """Keys that have arrived up to each slot less slots filled up to it."""
    arrived = np.bincount(np.asarray(starts, np.int64), minlength=m).cumsum()
    taken = np.zeros(m, np.int64)
    taken[np.asarray(filled, np.int64)] = 1
    return arrived - taken.cumsum()


def empty_law(filled: list[int], starts: list[int], m: int) -> list[tuple[int, int, int]]:
    """(height before a slot, slots, empty ones): the share is at most about 2**-height."""
    h = heights(filled, starts, m)
    taken = np.zeros(m, bool)
    taken[np.asarray(filled, np.int64)] = True
    before = np.concatenate([[0], h[:-1]])
    return [(int(k), int((before == k).sum()), int(((before == k) & ~taken).sum())) for k in np.unique(before)]


def abandoning_diagonal(starts: np.ndarray, m: int, w: int) -> tuple[np.ndarray, np.ndarray]:
    """(slot of each key or -1, empty slots) where a key takes the first free slot from its start
    on, in order of starts, and gives up after w slots."""
    order = np.argsort(starts, kind="stable")
    slot = np.full(len(starts), -1, np.int64)
    free = 0
    for i in order.tolist():
        at = max(int(starts[i]), free)
        if at < int(starts[i]) + w and at < m:
            slot[i], free = at, at + 1
    taken = np.zeros(m, bool)
    taken[slot[slot >= 0]] = True
    return slot, np.flatnonzero(~taken)


def failure_law(outcomes: list[tuple[int, bool]], heights_at: np.ndarray, w: int) -> list[tuple[int, int, int]]:
    """(room k, rows, failures) of rows by the room k = w - height at their start; with room k a
    row fails with a chance of at most 2**-k. outcomes: (start, failed) in order of insertion."""
    room = np.array([w - int(heights_at[s]) for s, _ in outcomes])
    failed = np.array([f for _, f in outcomes], bool)
    return [(int(k), int((room == k).sum()), int((failed & (room == k)).sum())) for k in np.unique(room)]


def bucket_classes(filled: list[int], starts: list[int], n_starts: int, m: int, b: int, w: int) -> dict:
    """Buckets that are good (all slots filled and a height of w / 4 or more at the end), bad
    (neither follows a good bucket nor is good) or recovering (the first ones after a bad run that
    are full again but not yet high), with the empty slots and the bound on them."""
    h = heights(filled, starts, m)
    taken = np.zeros(m, bool)
    taken[np.asarray(filled, np.int64)] = True
    n_buckets = -(-n_starts // b)
    ends = np.minimum((np.arange(n_buckets) + 1) * b, n_starts) - 1
    full = np.array([taken[i * b : e + 1].all() for i, e in enumerate(ends)])
    high = h[ends] >= w / 4
    good = full & high
    recovering = ~good & (full | high)
    bad = ~good & ~recovering
    x = int((~good).sum())
    return {"good": int(good.sum()), "recovery": int(recovering.sum()), "bad": int(bad.sum()), "empty": int((~taken).sum()), "bound": x * b + (x + 2) * (w - 1)}


# ---- sweeps ---------------------------------------------------------------------------------

#: So many rows, or one copy of the table, go to the tasks of a sweep: a small table once to each
#: configuration, a large one to each shard.
SWEEP_ROWS = 1 << 22


def sweep(pairs: DataFrame, configs: list[BandParams], shard_keys: int = band.SHARD_KEYS) -> DataFrame:
    """First-layer figures of every configuration on the same keys. A table of over `shard_keys`
    keys is solved by shard, as a build does; figures are then sums over shards, shares of them,
    or means by keys."""
    resolved = [c.resolved() for c in configs]
    pairs = pairs.where("hi is not null").select("hi", "lo")
    n = pairs.agg(F.approx_count_distinct("hi", 0.02)).first()[0]
    n_shards = band.n_shards_for(n, shard_keys)
    n_sets = max(1, min(len(resolved), SWEEP_ROWS // max(1, n)))
    shard, at = hashing.shard_column(F.col("hi"), n_shards).alias("shard"), F.explode(F.array(*[F.lit(i) for i in range(n_sets)])).alias("at")

    def run(rows: pa.Table) -> pa.Table:
        hi, lo = (rows.column(c).to_numpy().view(np.uint64) for c in ("hi", "lo"))
        own = range(rows.column("at")[0].as_py(), len(resolved), n_sets)
        return pa.Table.from_pylist([{"config": k} | _first_layer(hi, lo, resolved[k]) for k in own], schema=_arrow(SHARD_SWEEP))

    solved = pairs.distinct().select(shard, "hi", "lo").select("*", at).groupBy("shard", "at").applyInArrow(run, SHARD_SWEEP)
    same = [F.first(c).alias(c) for c in ("scheme", "w", "r", "b", "eps")]
    total = solved.groupBy("config").agg(*same, *[F.sum(c).alias(c) for c in ("n", "m", "bumped", "empty", "mu_buckets", "buckets", "row_ops")])
    e, mu = F.col("empty") / F.col("m"), F.col("mu_buckets") / F.col("buckets")
    costs = {k: f(e, mu, F.col("r"), F.col("b")).alias(k) for k, f in (("overhead", model.overhead_exact), ("overhead_model", model.overhead))}
    return total.select("scheme", "w", "r", "b", "eps", "n", "m", "bumped", e.alias("e"), mu.alias("mu"), *costs.values(), "row_ops")


SHARD_SWEEP = (
    "config int, scheme string, w int, r int, b int, eps double, n long, m long, bumped long, empty long, mu_buckets double, buckets long, row_ops long"
)


def _first_layer(hi: np.ndarray, lo: np.ndarray, p: BandParams) -> dict:
    keys = solve.Keys(hi, lo, hashing.fingerprint(lo, p.r))
    n_starts = solve.table_starts(len(keys), p.eps, "layered")
    table, bumped = solve.solve_layer([solve.Job(keys, 0, 0, 0, n_starts)], replace(p, r=1), p.w, True, values=False)[0]
    mu, n_buckets = p.meta_bits(), len(table.thresholds)
    if p.scheme == "1plus":
        over = float((table.thresholds > p.thresholds()[1]).mean())
        mu += over * sum(metadata.exception_bits(n_buckets, p.b))
    return {
        "scheme": p.scheme, "w": p.w, "r": p.r, "b": p.b, "eps": p.eps, "n": len(keys), "m": table.m, "bumped": int(bumped.sum()),
        "empty": table.stats["empty"], "mu_buckets": float(mu * n_buckets), "buckets": n_buckets, "row_ops": table.stats["row_ops"],
    }


def _arrow(ddl: str) -> pa.Schema:
    kinds = {"string": pa.string(), "int": pa.int32(), "long": pa.int64(), "double": pa.float64(), "boolean": pa.bool_(), "binary": pa.binary()}
    return pa.schema([(f.split()[0], kinds[f.split()[1]]) for f in ddl.split(", ")])


def tune_layer(pairs: DataFrame, base: BandParams, eps_grid: list[float], b_grid: list[int]) -> DataFrame:
    """Configurations of a grid by measured overhead, least first."""
    grid = [replace(base, eps=e, b=b) for e in eps_grid for b in b_grid]
    return sweep(pairs, grid).orderBy("overhead")


def success_curve(df: DataFrame, cols: list[str], w: int, eps_grid: list[float], seeds: int = 20, r: int = 1, shard_keys: int = band.SHARD_KEYS) -> DataFrame:
    """(eps, success): share of seeds for which one plain system of all the table's keys fits,
    whatever its size. A task eliminates a span of some `shard_keys` keys' starts and returns the
    few rows that reach beyond it; the rows of all spans then tell whether the system fits."""
    keyed = hashing.with_digest(df.select(*cols), cols).where("hi is not null").select("hi", "lo").distinct()
    n = keyed.count()
    spans = band.n_shards_for(n, shard_keys)
    grid = [BandParams(kind="plain", w=w, r=r, eps=eps).resolved() for eps in eps_grid]
    sizes = [solve.table_starts(n, eps, "plain") for eps in eps_grid]
    seeded = keyed.select("hi", "lo", F.explode(F.sequence(F.lit(0), F.lit(seeds - 1))).alias("seed"))
    span = hashing.start_column(F.col("hi"), F.lit(spans).cast("long"), 0, F.col("seed")).cast("int").alias("span")
    left_ddl = "seed int, at int, span int, fits boolean, coefs binary, vals binary"
    n_coef, n_value = w // 4, -(-r // 8)

    def run(table: pa.Table) -> pa.Table:
        hi, lo = (table.column(c).to_numpy().view(np.uint64) for c in ("hi", "lo"))
        seed, own = (table.column(c)[0].as_py() for c in ("seed", "span"))
        rows = []
        for k, left in enumerate(solve.in_span(hi, lo, grid[0], seed, own, spans, sizes)):
            coefs, values = (b"".join(x[i].to_bytes(size, "little") for x in left or ()) for i, size in ((0, n_coef), (1, n_value)))
            rows.append({"seed": seed, "at": k, "span": own, "fits": left is not None, "coefs": coefs, "vals": values})
        return pa.Table.from_pylist(rows, schema=_arrow(left_ddl))

    def whole(table: pa.Table) -> pa.Table:
        rows = table.sort_by("span").to_pylist()
        fits = all(x["fits"] for x in rows)
        if fits:
            left = {}
            for x in rows:
                parts = ((x["coefs"][i * n_coef : (i + 1) * n_coef], x["vals"][i * n_value : (i + 1) * n_value]) for i in range(len(x["coefs"]) // n_coef))
                left[x["span"]] = [(int.from_bytes(c, "little"), int.from_bytes(v, "little")) for c, v in parts]
            for own in set(range(spans)) - set(left):  # without keys
                left[own] = solve.in_span(*[np.zeros(0, np.uint64)] * 2, grid[0], rows[0]["seed"], own, spans, [sizes[rows[0]["at"]]])[0]
            fits = solve.spans_fit([left[own] for own in range(spans)], grid[0])
        return pa.table({"eps": [float(eps_grid[rows[0]["at"]])], "fits": [float(fits)]})

    solved = seeded.select("*", span).groupBy("seed", "span").applyInArrow(run, left_ddl)
    return solved.groupBy("seed", "at").applyInArrow(whole, "eps double, fits double").groupBy("eps").agg(F.avg("fits").alias("success"))


def pareto(report: DataFrame, cost: str, time: str, name: str) -> DataFrame:
    """Rows that no other row beats in both measures; rows without a measure are not beaten. A cost
    is on the front if its least time is below that of every lower cost: a running minimum over
    ranges of costs, in which rows are not compared in pairs."""
    known = F.col(cost).isNotNull() & F.col(time).isNotNull()
    least = ordered_parts(report.where(known).groupBy(cost).agg(F.min(time).alias(time)), cost)
    local = least.withColumn("_low", F.min(time).over(W.partitionBy("_part").orderBy(cost).rowsBetween(W.unboundedPreceding, -1)))
    before = W.partitionBy(F.lit(0)).orderBy("_part").rowsBetween(W.unboundedPreceding, -1)
    parts = least.groupBy("_part").agg(F.min(time).alias("_least"))  # a row for each part
    parts = parts.withColumn("_carried", F.min("_least").over(before)).select("_part", "_carried")
    low = F.least("_low", "_carried")
    front = local.join(F.broadcast(parts), "_part").where(low.isNull() | (F.col(time) < low)).select(cost, time)
    columns = [name, cost, time]
    return report.where(known).join(front, [cost, time]).select(*columns).unionByName(report.where(~known).select(*columns))


def heat_map(report: DataFrame, cell: float = 0.05) -> DataFrame:
    """Fastest structure for each cell of overhead and value bits."""
    return report.groupBy(F.floor(F.col("overhead") / cell).alias("cell"), "r").agg(
        F.min_by("name", "ns").alias("name"), F.min("ns").alias("ns")
    )


def entropy_bits(df: DataFrame, col: str) -> DataFrame:
    """n and n * H0 of a column's values."""
    counts = df.groupBy(col).agg(F.count(F.lit(1)).alias("c"))
    total = F.sum("c")
    return counts.agg(total.alias("n"), (total * F.log2(total) - F.sum(F.col("c") * F.log2("c"))).alias("bits"))
