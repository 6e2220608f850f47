"""Mixing overlapping sources to target weights by min-cost flow.

Documents are aggregated by membership pattern (the set of sources that hold them). Token
capacity flows from patterns to source quotas. A pattern's first use is free, each repeat
costs more than the one before (convex), so the flow spends fresh text before repeats and
leaves scarce patterns to the sources that have nothing else. The flow says how many tokens
each pattern gives; whole repetitions go to all of its documents, and the rest to documents
in the order of a seeded hash, the last one in part. That order's cut is found by radix
selection: sums per hash digit, one digit deeper each time, so no task ever sorts a source.

Defined results: null text has size 0 and is taken 0 times; a null source is a source of its
own, ordered last; rows with equal id and text share one hash and split what is cut through
them; an empty table gives an empty mix. repeat_documents gives the input's columns back,
whatever their names.
"""

from __future__ import annotations

import heapq
import json
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WORD, materialize, packed

HASH_BITS, DIGIT_BITS = 60, 10


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def capped_shares(total: float, weights: list[float], caps: list[float]) -> list[float]:
    """Share total by weight; who would pass its cap stops there, and the excess is shared
    again among the others by weight, until none is above."""
    share = [0.0] * len(weights)
    active = {i for i in range(len(weights)) if weights[i] > 0}
    left = float(total)
    while active:
        weight = sum(weights[i] for i in active)
        over = [i for i in active if left * weights[i] / weight > caps[i]]
        if not over:
            for i in active:
                share[i] = left * weights[i] / weight
            break
        for i in over:
            share[i] = caps[i]
        left -= sum(caps[i] for i in over)
        active -= set(over)
    return share


def min_cost_flow(
    capacity: list[list[int]], quotas: list[int], members: list[list[int]], costs: list[int]
) -> list[dict[int, int]]:
    """Flow from each pattern to the quotas of its sources, at the least cost among the
    largest flows. capacity[p][k] is the size of pattern p's k-th use, at costs[k] a token.
    Successive shortest paths over the residual graph with node potentials."""
    n_p, n_s = len(members), len(quotas)
    source, sink = n_p + n_s, n_p + n_s + 1
    graph: list[list[list[int]]] = [[] for _ in range(sink + 1)]  # to, capacity, cost, index of the reverse

    def edge(a: int, b: int, cap: int, cost: int) -> None:
        graph[a].append([b, cap, cost, len(graph[b])])
        graph[b].append([a, 0, -cost, len(graph[a]) - 1])

    for p in range(n_p):
        for k, cap in enumerate(capacity[p]):
            edge(source, p, cap, costs[k])
        for s in members[p]:
            edge(p, n_p + s, 1 << 62, 0)
    for s, q in enumerate(quotas):
        edge(n_p + s, sink, q, 0)
    potential = [0] * (sink + 1)
    while True:
        dist: list[float] = [float("inf")] * (sink + 1)
        via: list[tuple[int, int] | None] = [None] * (sink + 1)
        dist[source] = 0
        queue: list[tuple[float, int]] = [(0, source)]
        while queue:
            d, v = heapq.heappop(queue)
            if d > dist[v]:
                continue
            for i, (to, cap, cost, _) in enumerate(graph[v]):
                if cap > 0 and (nd := d + cost + potential[v] - potential[to]) < dist[to]:
                    dist[to], via[to] = nd, (v, i)
                    heapq.heappush(queue, (nd, to))
        if via[sink] is None:
            break
        potential = [p + int(d) if d < float("inf") else p for p, d in zip(potential, dist, strict=True)]
        push, v = 1 << 62, sink
        while v != source:
            a, i = via[v]
            push, v = min(push, graph[a][i][1]), a
        v = sink
        while v != source:
            a, i = via[v]
            graph[a][i][1] -= push
            graph[v][graph[a][i][3]][1] += push
            v = a
    return [{to - n_p: graph[to][back][1] for to, _, cost, back in graph[p] if n_p <= to < source and graph[to][back][1]} for p in range(n_p)]


@dataclass(frozen=True)
class Mix:
    """What a mix decides, a row for each pattern: whole repetitions, the hash at which the
    seeded order is cut, and the tokens that are left for the rows of that hash."""

    patterns: list[str]
    full: list[int]
    cut: list[tuple[int, int]]
    rest: list[int]
    rest_rows: list[int]
    targets: dict[str | None, float]
    sizes: dict[str | None, int]
    flows: list[dict[int, int]]
    sources: list[str | None]


def pattern_key(membership: Column) -> Column:
    """One string for a set of sources, as JSON, so that any name and null are told apart. No
    membership is that of null alone."""
    known = F.coalesce(membership, F.array(F.lit(None).cast("string")))
    return F.to_json(F.array_sort(F.array_distinct(F.when(F.size(known) > 0, known).otherwise(F.array(F.lit(None).cast("string"))))))


def row_hash(id_col: Column, text: Column, seed: int) -> Column:
    return F.shiftrightunsigned(F.xxhash64(F.lit(seed), id_col, text), 64 - HASH_BITS)


def plan_mix(
    sizes: DataFrame,
    targets_of: Callable[[dict], dict],
    max_uses: int = 3,
    max_patterns: int = 100_000,
) -> Mix:
    """sizes: pattern string, size long, h long. targets_of: size by source to target by
    source. What comes to the driver is one row per pattern, refused beyond `max_patterns`,
    and one row per pattern and hash digit for the cuts."""
    rows = sizes.groupBy("pattern").agg(F.sum("size").alias("n")).limit(max_patterns + 1).collect()
    if len(rows) > max_patterns:
        raise ValueError(f"more than {max_patterns} membership patterns")
    rows.sort(key=lambda r: r["pattern"])
    patterns = [r["pattern"] for r in rows]
    amount = [int(r["n"] or 0) for r in rows]
    held = [json.loads(p) for p in patterns]
    sources = sorted({s for x in held for s in x}, key=lambda s: (s is None, s or ""))
    index = {s: i for i, s in enumerate(sources)}
    size_of = {s: 0 for s in sources}
    for x, n in zip(held, amount, strict=True):
        for s in x:
            size_of[s] += n
    targets = targets_of(size_of)
    flows = min_cost_flow(
        [[n] * max_uses for n in amount],
        [round(targets[s]) for s in sources],
        [[index[s] for s in x] for x in held],
        [k * k for k in range(max_uses)],
    )
    taken = [sum(f.values()) for f in flows]
    full = [t // n if n else 0 for t, n in zip(taken, amount, strict=True)]
    need = [t - f * n for t, f, n in zip(taken, full, amount, strict=True)]
    cut, rest, rest_rows = _cuts(sizes, patterns, need)
    return Mix(patterns, full, cut, rest, rest_rows, targets, size_of, flows, sources)


def _cuts(
    sizes: DataFrame, patterns: list, need: list[int]
) -> tuple[list[tuple[int, int]], list[int], list[int]]:
    """For each pattern the least and greatest hash of the rows at its cut: those of smaller
    hashes sum to at most need. Also what is left of need there, and how many rows share it."""
    cut, rest, rest_rows = [(-1, -1)] * len(patterns), [0] * len(patterns), [1] * len(patterns)
    prefix = {i: 0 for i, n in enumerate(need) if n > 0}
    left = {i: need[i] for i in prefix}
    index = {p: i for i, p in enumerate(patterns)}
    for depth in range(1, HASH_BITS // DIGIT_BITS + 1):
        if not prefix:
            break
        shift = HASH_BITS - depth * DIGIT_BITS
        inside = sizes.where(F.col("size") > 0)
        if depth > 1:
            table = sizes.sparkSession.createDataFrame(
                [(patterns[i], p) for i, p in prefix.items()], "cut_pattern string, prefix long"
            )
            inside = inside.join(
                F.broadcast(table),  # at most one row per pattern
                F.col("pattern").eqNullSafe(F.col("cut_pattern"))
                & (F.shiftrightunsigned("h", shift + DIGIT_BITS) == F.col("prefix")),
                "left_semi",
            )
        sums: dict[int, list[tuple[int, int, int]]] = {i: [] for i in prefix}
        grouped = inside.groupBy("pattern", F.shiftrightunsigned("h", shift).alias("d")).agg(
            F.sum("size").alias("n"), F.count(F.lit(1)).alias("rows")
        )
        for r in grouped.collect():
            if (i := index[r["pattern"]]) in sums:
                sums[i].append((r["d"], r["n"], r["rows"]))
        for i in list(prefix):
            for d, n, rows in sorted(sums[i]):
                if n > left[i]:
                    break
                left[i] -= n
            else:
                raise AssertionError("a cut lies within its pattern")
            prefix[i] = d
            if rows == 1 or shift == 0:
                cut[i] = (d << shift, ((d + 1) << shift) - 1)
                rest[i], rest_rows[i] = left[i], rows
                del prefix[i]
    return cut, rest, rest_rows


def taken_column(df: DataFrame, mix: Mix, pattern: str, size: str, h: str) -> DataFrame:
    """Add taken: tokens that the mix takes of each row. The plan's table has a row for each
    pattern, bounded by plan_mix; it is joined by broadcast."""
    plan = df.sparkSession.createDataFrame(
        [
            (p, f, c[0], c[1], r, n)
            for p, f, c, r, n in zip(mix.patterns, mix.full, mix.cut, mix.rest, mix.rest_rows, strict=True)
        ],
        "mix_pattern string, mix_full long, mix_low long, mix_high long, mix_rest long, mix_rows long",
    )
    extra = (
        F.when(F.col(h) < F.col("mix_low"), F.col(size))
        .when(F.col(h) <= F.col("mix_high"), F.least(F.floor(F.col("mix_rest") / F.col("mix_rows")), F.col(size)))
        .otherwise(F.lit(0))
        .cast("long")
    )
    joined = df.join(F.broadcast(plan), df[pattern].eqNullSafe(plan["mix_pattern"]), "left")
    taken = F.coalesce(F.col("mix_full") * F.col(size) + extra, F.lit(0).cast("long"))
    return joined.withColumn("taken", taken).drop(*plan.columns)


def repeating_weights(size_of: dict, weights: tuple[float, ...] = (5.0, 2.0, 1.0), max_uses: int = 3) -> dict:
    """Targets by source: weights repeat over sources by code point, null last; all sizes are
    shared; a target stops at max_uses times its source's size."""
    sources = sorted(size_of, key=lambda s: (s is None, s or ""))
    shares = capped_shares(
        float(sum(size_of.values())),
        [weights[i % len(weights)] for i in range(len(sources))],
        [float(max_uses * size_of[s]) for s in sources],
    )
    return dict(zip(sources, shares, strict=True))


def size_table(df: DataFrame, text: str, source: str, id_col: str, seed: int, membership: str | None = None) -> DataFrame:
    """pattern, size and hash of each row, with its id and source; small, and written once."""
    key = pattern_key(F.array(F.col(source).cast("string")) if membership is None else F.col(membership))
    return materialize(
        df.select(
            F.col(id_col).alias("doc_id"),
            F.col(source).alias("source"),
            key.alias("pattern"),
            word_count(F.col(text)).alias("size"),
            row_hash(F.col(id_col), F.col(text), seed).alias("h"),
        ),
        "mix-sizes",
    )


def mix_sources(
    df: DataFrame,
    targets_of: Callable[[dict], dict] = repeating_weights,
    text: str = "text",
    source: str = "source",
    id_col: str = "doc_id",
    membership: str | None = None,
    max_uses: int = 3,
    seed: int = 29,
) -> tuple[DataFrame, Mix]:
    """(doc_id, source, size, taken) for every row, and the plan. membership names an array
    column of all sources that hold a row; without it a row belongs to its source alone."""
    sizes = size_table(df, text, source, id_col, seed, membership)
    mix = plan_mix(sizes, targets_of, max_uses)
    return taken_column(sizes, mix, "pattern", "size", "h").drop("h", "pattern"), mix


def repeat_documents(
    df: DataFrame, text: str = "text", source: str = "source", id_col: str = "doc_id", max_uses: int = 3, seed: int = 29
) -> DataFrame:
    """The mixed corpus itself: each row as often as the mix takes it, rounded to whole texts."""
    _, mix = mix_sources(df, text=text, source=source, id_col=id_col, max_uses=max_uses, seed=seed)
    of = {c: F.col(f"row.`{c}`") for c in (text, source, id_col)}
    marked = packed(df).withColumns(
        {"mix_size": word_count(of[text]), "mix_h": row_hash(of[id_col], of[text], seed), "mix_key": pattern_key(F.array(of[source].cast("string")))}
    )
    mixed = taken_column(marked, mix, "mix_key", "mix_size", "mix_h")
    copies = F.when(F.col("mix_size") > 0, F.round(F.col("taken") / F.col("mix_size"))).otherwise(0).cast("int")
    return (
        mixed.withColumn("mix_copies", copies)
        .where(F.col("mix_copies") > 0)
        .withColumn("mix_copy", F.explode(F.sequence(F.lit(1), F.col("mix_copies"))))
        .select("row.*")
    )
