"""MinHash near-duplicates by an inverted join of signature coordinates.

1. Each text becomes a set of word shingles; texts with equal sets form one class.
2. A class gets a signature of COORDINATES minima. A pair as similar as the threshold agrees
   on at least m coordinates but for a chance of MISS at most (binomial tail); m follows from
   the threshold: 34 at 80 percent (3.2e-7), 39 at 85 percent (6.3e-7).
3. Classes are posted under (coordinate, value) tokens. If two classes share m of their
   COORDINATES tokens, then the first COORDINATES - m + 1 tokens of each, in any common
   order, have one in common: only that prefix is posted. The order puts tokens last that are
   frequent over the table, so hot passages post few classes (their lists are skipped). Lists
   of the same members count once.
4. Where the members of a list meet, their collisions are counted over the whole signatures
   (a byte of each coordinate, so never too few), and pairs under m go. So do pairs whose
   parity sketches differ in more bits than the sets may differ in shingles, which loses no
   link: the bits are never more than the shingles.
5. First a list's likely pairs are cut to a forest of the most alike ones, a pair a member at
   most, and those are confirmed. Then only likely pairs of different components are left:
   lists within one component are closed, and in the others what lies outside the largest
   component meets all of the list, in groups of two blocks of BLOCK members, however long the
   list. All of these pairs are confirmed, so no link is lost to the forest.
6. Pairs are confirmed on full shingle sets of 128-bit hashes: the members' sets stream past
   their leader's, which is repeated for every BLOCK members, so a hot leader is many small
   groups.
7. Confirmed links join components by alternating large-star and small-star rounds.

No step collects links, classes or signatures; what reaches the driver are counts, the list of
frequent token buckets and a bit filter of wanted texts, which are bounded.

Defined results: null, empty and blank texts have an empty set and are linked with nothing;
repeated rows are in one component; rows with a null id follow their component, and are kept
only if it has no other row (then component_id is null). Columns of the input are never touched;
drop_near_duplicates gives them back whatever their names.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, give_back, map_arrow, mix64, packed, release, slices, small_batches, text_bytes
from .shingles import all_shingles, wide_shingles

COORDINATES, MISS = 64, 1e-6
BLOCK = 256
SKETCH_BITS = 512
BUCKET_BITS, MAX_FREQUENT = 20, 1 << 16

_MULTIPLIERS = mix64(np.arange(1, COORDINATES + 1, dtype=np.uint64) * np.uint64(0xA24BAED4963EE407)) | np.uint64(1)
_OFFSETS = mix64(np.arange(1, COORDINATES + 1, dtype=np.uint64) * np.uint64(0x9FB21C651E98DF25))


def matches_for(percent: int) -> int:
    """The most coordinates on which a pair of this similarity agrees but for a chance of MISS;
    1 at least, which leaves a larger chance below 20 percent."""
    p, below = percent / 100, 0.0
    for m in range(COORDINATES):
        below += comb(COORDINATES, m) * p**m * (1 - p) ** (COORDINATES - m)
        if below > MISS:
            return max(1, m)
    return COORDINATES


def signature(shingles: np.ndarray, step: int = 4096) -> np.ndarray:
    """uint32 minima of COORDINATES multiplicative hashes."""
    low = np.full(COORDINATES, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), step):
        values = shingles[at : at + step, None] * _MULTIPLIERS[None, :] + _OFFSETS[None, :]
        np.minimum(low, values.min(axis=0), out=low)
    return (low >> np.uint64(32)).astype(np.uint32)


def set_key(shingles: np.ndarray) -> bytes:
    """128-bit key of a set, independent of order."""
    a = mix64(shingles ^ np.uint64(0x243F6A8885A308D3)).sum(dtype=np.uint64)
    b = mix64(shingles ^ np.uint64(0x13198A2E03707344)).sum(dtype=np.uint64)
    return int(a).to_bytes(8, "big") + int(b).to_bytes(8, "big")


def tokens(signatures: np.ndarray) -> np.ndarray:
    """(row, coordinate) uint64 tokens of coordinate-value pairs."""
    keys = np.arange(COORDINATES, dtype=np.uint64) << np.uint64(32)
    return mix64(signatures.astype(np.uint64) | keys[None, :])


def sketch(shingles: np.ndarray) -> bytes:
    """Parities of the numbers of shingles in SKETCH_BITS hash classes."""
    at = mix64(shingles ^ np.uint64(0x452821E638D01377)) % np.uint64(SKETCH_BITS)
    return np.packbits((np.bincount(at.astype(np.int64), minlength=SKETCH_BITS) & 1).astype(bool)).tobytes()


def brief(signatures: np.ndarray) -> np.ndarray:
    """A byte of each coordinate's token: equal where the coordinates are."""
    return (tokens(signatures) & np.uint64(255)).astype(np.uint8)


def may_link(x: np.ndarray, y: np.ndarray, n_x: np.ndarray, n_y: np.ndarray, percent: int) -> np.ndarray:
    """Whether sets with these sketches and sizes can be as similar as asked. Sets that differ
    in d shingles are if d (100 + percent) <= (100 - percent) (n_x + n_y)."""
    differ = np.maximum(np.bitwise_count(x ^ y).sum(axis=1, dtype=np.int64), np.abs(n_x - n_y))
    return differ * (100 + percent) <= (100 - percent) * (n_x + n_y)


def _matrix(column: pa.Array, kind: type) -> np.ndarray:
    """A row for each of the column's binaries, all of one length."""
    return np.frombuffer(b"".join(column.to_pylist()), kind).reshape(len(column), -1)


def keyed_texts(df: DataFrame, text: str, id_col: str) -> DataFrame:
    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text).alias("text_key"), F.col(text).alias("text"))


def sets_table(df: DataFrame, text: str, id_col: str, width: int) -> DataFrame:
    """(doc_id, text_key, n_shingles, class, sig, brief, odd) of every row; the last four null for
    an empty set."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        n, made = [], []
        for s in all_shingles(text_bytes(batch.column(2)), width):
            n.append(len(s))
            if len(s):
                sig = signature(s)
                made.append((set_key(s), sig.tobytes(), brief(sig[None, :]).tobytes(), sketch(s)))
            else:
                made.append((None,) * 4)
        columns = [pa.array([m[i] for m in made], pa.binary()) for i in range(4)]
        return pa.record_batch(
            [batch.column(0), batch.column(1), pa.array(n, pa.int64()), *columns],
            names=["doc_id", "text_key", "n_shingles", "class", "sig", "brief", "odd"],
        )

    schema = "doc_id long, text_key long, n_shingles long, class binary, sig binary, brief binary, odd binary"
    return map_arrow(keyed_texts(df, text, id_col), run, schema)


def frequent_buckets(rows: DataFrame, tokens_of: Callable[[pa.RecordBatch], Iterable[np.ndarray]]) -> dict[int, int]:
    """Token buckets that many rows share, with a coarse level. Any common order of tokens
    gives whole results; this one only keeps lists short, so local counts may be cut: each
    task reports its heavy buckets, and the heaviest MAX_FREQUENT of all are kept."""

    def count(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        local = np.zeros(1 << BUCKET_BITS, np.int64)
        for whole in batches:
            for batch in slices(whole):
                waiting: list[np.ndarray] = []
                for t in tokens_of(batch):
                    waiting.append((t.reshape(-1) >> np.uint64(64 - BUCKET_BITS)).astype(np.int64))
                if waiting:
                    at, n = np.unique(np.concatenate(waiting), return_counts=True)
                    local[at] += n
        heavy = np.flatnonzero(local > max(8.0, 4.0 * local.mean()))
        yield pa.record_batch([pa.array(heavy), pa.array(local[heavy])], names=["bucket", "n"])

    found = (
        rows.mapInArrow(count, "bucket long, n long")
        .groupBy("bucket")
        .agg(F.sum("n").alias("n"))
        .orderBy(F.desc("n"), "bucket")
        .limit(MAX_FREQUENT)
        .collect()
    )
    return {r["bucket"]: int(r["n"]).bit_length() for r in found}


def postings(classes: DataFrame, percent: int) -> DataFrame:
    """(token, class): the prefix of each class in the common order."""
    levels = np.zeros(1 << BUCKET_BITS, np.uint8)
    for bucket, level in frequent_buckets(classes.select("sig"), lambda batch: [tokens(_matrix(batch.column(0), np.uint32))]).items():
        levels[bucket] = level
    shared = classes.sparkSession.sparkContext.broadcast(levels)  # 1 MB
    prefix = COORDINATES - matches_for(percent) + 1

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        t = tokens(_matrix(batch.column(1), np.uint32))
        level = shared.value[(t >> np.uint64(64 - BUCKET_BITS)).astype(np.int64)].astype(np.uint64)
        # Order by level, then by token; the token's low bits break ties of the packed key.
        order = np.argsort((level << np.uint64(56)) | (t >> np.uint64(8)), axis=1, kind="stable")[:, :prefix]
        chosen = np.take_along_axis(t, order, axis=1)
        return pa.record_batch(
            [pa.array(chosen.reshape(-1).view(np.int64)), batch.column(0).take(pa.array(np.repeat(np.arange(len(t)), prefix)))],
            names=["token", "class"],
        )

    return map_arrow(classes.select("class", "sig"), run, "token long, class binary")


def posting_lists(posted: DataFrame) -> DataFrame:
    """(token, class, members, leader) of the lists with two classes or more, each member set
    once (told by its length and two 64-bit sums). leader: the member of the least seeded hash."""
    dealt = posted.repartition("token")
    order = F.xxhash64(F.lit(17), "class")
    whole = dealt.groupBy("token").agg(
        F.count(F.lit(1)).alias("members"),
        F.bit_xor(F.xxhash64("class")).alias("mark"),
        F.bit_xor(F.xxhash64(F.lit(5), "class")).alias("other_mark"),
        F.min(order).alias("leader"),
    )
    first = whole.where("members > 1").groupBy("members", "mark", "other_mark").agg(F.min("token").alias("token"), F.min("leader").alias("leader"))
    rows = dealt.join(first.select("token", "members", "leader").hint("merge"), "token")
    return rows.withColumn("leader", order == F.col("leader"))


def first_groups(lists: DataFrame) -> DataFrame:
    """(token, block, class): lists cut into blocks of about BLOCK members by a hash, the leader in
    each, so that blocks hang together where it is alike."""
    blocks = F.ceil(2 * F.col("members") / BLOCK).cast("int")
    one = F.array(F.pmod(F.xxhash64(F.lit(31), "class"), blocks).cast("int"))
    at = F.when(F.col("members") <= BLOCK, F.array(F.lit(0))).when(F.col("leader"), F.sequence(F.lit(0), blocks - 1)).otherwise(one)
    return lists.select("token", "class", F.explode(at).alias("block")).withColumn("block", F.col("block").cast("long"))


def likely_pairs(grouped: DataFrame, classes: DataFrame, percent: int, forest: bool) -> DataFrame:
    """Pairs (a, b) of a group (token, block) that agree on enough coordinates and whose sketches
    allow a link: a forest of the most alike, or all of different components (column component).
    A group has some 4 BLOCK members at most and goes to one task in sorted order."""
    rows = grouped.join(classes.select("class", "n_shingles", "brief", "odd"), "class")
    keys = ["token", "block"]
    columns = [*keys, "class", "n_shingles", "brief", "odd"] + ([] if forest else ["component"])
    dealt = rows.select(*columns).repartition(*keys).sortWithinPartitions(*keys)
    least = matches_for(percent)

    def compare(table: pa.Table, starts: np.ndarray, lengths: np.ndarray) -> pa.RecordBatch | None:
        """table: whole groups of these starts and lengths."""
        n = table.num_rows
        sizes = table.column("n_shingles").to_numpy()
        briefs, odd = (_matrix(table.column(c).combine_chunks(), k) for c, k in (("brief", np.uint8), ("odd", np.uint64)))
        partners = np.repeat(starts + lengths, lengths) - np.arange(n) - 1
        upto = np.cumsum(partners)
        parts, at = [], 0
        while at < n:  # rows with about PAIRS_AT_ONCE pairs
            to = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + PAIRS_AT_ONCE, "right")))
            count = partners[at:to]
            left = np.repeat(np.arange(at, to), count)
            right = left + 1 + np.arange(len(left)) - np.repeat(np.cumsum(count) - count, count)
            kept = may_link(odd[left], odd[right], sizes[left], sizes[right], percent)
            left, right = left[kept], right[kept]
            agree = (briefs[left] == briefs[right]).sum(axis=1)
            parts.append([x[agree >= least] for x in (left, right, agree)])
            at = to
        left, right, agree = (np.concatenate(x) for x in zip(*parts, strict=True))
        if forest:
            chosen = _forest(left, right, np.bitwise_count(odd[left] ^ odd[right]).sum(axis=1, dtype=np.int64) - (agree << 16), n)
        else:
            own = table.column("component").combine_chunks().dictionary_encode().indices.to_numpy()
            chosen = np.flatnonzero(own[left] != own[right])
        if not len(chosen):
            return None
        names = np.array(table.column("class").to_pylist(), object)
        x, y = names[left[chosen]], names[right[chosen]]
        return pa.record_batch([pa.array(np.minimum(x, y), pa.binary()), pa.array(np.maximum(x, y), pa.binary())], names=["a", "b"])

    def whole_groups(table: pa.Table) -> Iterator[pa.RecordBatch]:
        edge = np.ones(table.num_rows, bool)
        edge[1:] = False
        for name in keys:
            column = table.column(name).to_numpy()
            edge[1:] |= column[1:] != column[:-1]
        starts = np.flatnonzero(edge)
        lengths = np.diff(np.append(starts, table.num_rows))
        upto = np.cumsum(lengths * (lengths - 1) // 2)
        at = 0
        while at < len(starts):  # groups with about PAIRS_AT_ONCE pairs
            to = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + PAIRS_AT_ONCE, "right")))
            part = table.slice(starts[at], lengths[at:to].sum())
            if (found := compare(part, starts[at:to] - starts[at], lengths[at:to])) is not None:
                yield found
            at = to

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_rows: pa.Table | None = None
        for batch in batches:
            if not batch.num_rows:
                continue
            table = pa.Table.from_batches([batch])
            if open_rows is not None:
                table = pa.concat_tables([open_rows, table])
            last = np.ones(table.num_rows, bool)  # rows of the group that the next batch may go on with
            for name in keys:
                column = table.column(name).to_numpy()
                last &= column == column[-1]
            cut = int(np.argmax(last))
            open_rows = table.slice(cut)
            if cut:
                yield from whole_groups(table.slice(0, cut))
        if open_rows is not None:
            yield from whole_groups(open_rows)
        give_back()

    small_batches(grouped.sparkSession)
    return dealt.mapInArrow(run, "a binary, b binary").where("a < b").distinct()


PAIRS_AT_ONCE = 1 << 16


def _forest(left: np.ndarray, right: np.ndarray, cost: np.ndarray, n: int) -> np.ndarray:
    """Indices of a spanning forest's pairs, cheapest first."""
    above = list(range(n))

    def top(x: int) -> int:
        while above[x] != x:
            above[x] = x = above[above[x]]
        return x

    chosen = []
    order = np.argsort(cost, kind="stable")
    for k, x, y in zip(order.tolist(), left[order].tolist(), right[order].tolist(), strict=True):
        x, y = top(x), top(y)
        if x != y:
            above[x] = y
            chosen.append(k)
    return np.array(chosen, np.int64)


def with_component(rows: DataFrame, placed: DataFrame) -> DataFrame:
    joined = rows.join(placed.withColumnRenamed("node", "class"), "class", "left")
    return joined.withColumn("component", F.coalesce("component", "class"))


def open_groups(lists: DataFrame, placed: DataFrame, scratch: Scratch) -> DataFrame:
    """(token, block, class, component): the groups in which the members outside a list's largest
    component meet all others. Lists within one component are closed. Members are cut into
    blocks by a hash, those of the largest component and the rest for themselves; a group holds
    two blocks, one of the rest at least. Blocks of the rest, mostly few, are larger, so that the
    many of the largest component are repeated seldom."""
    at = scratch.write(with_component(lists, placed).select("token", "class", "component"), "labelled")
    counts = at.groupBy("token", F.xxhash64("component").alias("label")).agg(F.count(F.lit(1)).alias("n"))
    tops = counts.groupBy("token").agg(F.max(F.struct("n", "label")).alias("top"), F.sum("n").alias("all"))
    open_lists = tops.where(F.col("top.n") < F.col("all")).select(
        "token",
        F.col("top.label").alias("largest"),
        F.ceil((F.col("all") - F.col("top.n")) / (2 * BLOCK)).cast("int").alias("rest_blocks"),
        F.ceil(F.col("top.n") / BLOCK).cast("int").alias("top_blocks"),
    )  # blocks of 2 BLOCK and of BLOCK members on average, as a hash deals them
    rows = at.join(open_lists, "token").withColumn("inside", F.xxhash64("component") == F.col("largest"))
    own = F.pmod(F.xxhash64(F.lit(31), "class"), F.when(F.col("inside"), F.col("top_blocks")).otherwise(F.col("rest_blocks")))
    rows = rows.withColumn("own", F.when(F.col("inside"), F.col("rest_blocks")).otherwise(0) + own)
    rest = F.sequence(F.lit(0), F.col("rest_blocks") - 1)
    every = F.sequence(F.lit(0), F.col("rest_blocks") + F.col("top_blocks") - 1)
    single = (F.col("rest_blocks") == 1) & (F.col("top_blocks") == 1)  # one group holds all
    others = F.when(single, F.array(F.lit(0))).when(F.col("inside"), rest).otherwise(every)
    met = rows.withColumn("other", F.explode(others))
    group = F.least("own", "other").cast("long") * (F.col("rest_blocks") + F.col("top_blocks")) + F.greatest("own", "other")
    return met.select("token", F.when(single, F.lit(-1).cast("long")).otherwise(group).alias("block"), "class", "component")


def confirm(pairs: DataFrame, classes: DataFrame, df: DataFrame, text: str, id_col: str, width: int, percent: int) -> DataFrame:
    """Links (a, b) whose full sets are as similar as asked. The set of a goes once to each block
    of its partners."""
    blocks = F.pmod(F.xxhash64(F.lit(5), "b"), F.greatest(F.lit(1), F.ceil(F.col("pairs") / BLOCK))).cast("int")
    counts = pairs.groupBy("a").agg(F.count(F.lit(1)).alias("pairs"))
    blocked = pairs.join(counts, "a").select("a", "b", blocks.alias("block"))
    roles = F.array(F.struct(F.lit(0).alias("role"), F.col("a").alias("class")), F.struct(F.lit(1).alias("role"), F.col("b").alias("class")))
    asked = blocked.select("a", "block", F.explode(roles).alias("x")).select("a", "block", "x.role", "x.class").distinct()
    rows = asked.join(classes.select("class", F.col("rep.doc_id").alias("rep_id"), F.col("rep.text_key").alias("rep_key")), "class")
    texts = maybe_texts(rows.select("rep_key"), df, text, id_col)
    same = F.col("rep_id").eqNullSafe(F.col("doc_id")) & (F.col("rep_key") == F.col("text_key"))
    fetched = rows.join(texts, same).select("a", "block", "role", "class", "text")
    grouped = fetched.repartition(F.col("a"), F.col("block")).sortWithinPartitions("a", "block", "role", "class")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        none = np.zeros(0, np.uint64)
        leader, key, last = (none, none), None, None
        for whole in batches:
            for batch in slices(whole):
                a, block, role, members = (batch.column(i).to_pylist() for i in range(4))
                out = []
                for i, s in enumerate(wide_shingles(text_bytes(batch.column(4)), width)):
                    if role[i] == 0:
                        leader, key, last = s, (a[i], block[i]), None
                        continue
                    if key != (a[i], block[i]) or members[i] == last:  # a repeated row of the class
                        continue
                    last = members[i]
                    common = _common(leader, s)
                    if 100 * common >= percent * (len(leader[0]) + len(s[0]) - common):
                        out.append((a[i], members[i]))
                if out:
                    yield pa.record_batch(
                        [pa.array([x for x, _ in out], pa.binary()), pa.array([x for _, x in out], pa.binary())], names=["a", "b"]
                    )
        give_back()

    return grouped.mapInArrow(run, "a binary, b binary")


def _common(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> int:
    """Size of the intersection of two sets of two-lane hashes, sorted by the first lane."""
    if not len(a[0]) or not len(b[0]):
        return 0
    at = np.searchsorted(a[0], b[0])
    at[at == len(a[0])] = 0
    return int(((a[0][at] == b[0]) & (a[1][at] == b[1])).sum())


FILTER_WORDS = 1 << 20


def key_filter(keys: DataFrame) -> np.ndarray:
    """Bits of hashed 64-bit keys, FILTER_WORDS words of 64 at most. One that many more keys fill
    lets every row pass; what uses it is exact without it."""
    n = keys.count()
    words = min(FILTER_WORDS, 1 << max(7, (max(n, 1) // 4).bit_length()))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = np.zeros(words, np.uint64)
        for batch in batches:
            for at, bit in _places(batch.column(0).to_numpy(), words):
                np.bitwise_or.at(own, at, bit)
        at = np.flatnonzero(own)
        yield pa.record_batch([pa.array(at), pa.array(own[at].view(np.int64))], names=["at", "v"])

    total = np.zeros(words, np.uint64)
    merged = keys.mapInArrow(run, "at long, v long").groupBy("at").agg(F.bit_or("v").alias("v")).toArrow()
    total[merged.column(0).to_numpy()] = merged.column(1).to_numpy().view(np.uint64)
    return total


def _places(keys: np.ndarray, words: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """(word, bit) of each key, twice."""
    h = mix64(keys.astype(np.int64).view(np.uint64))
    mask, six = np.uint64(words - 1), np.uint64(63)
    return [(((h >> np.uint64(s)) & mask).astype(np.int64), np.uint64(1) << ((h >> np.uint64(s + 26)) & six)) for s in (0, 32)]


def in_filter(keys: np.ndarray, words: np.ndarray) -> np.ndarray:
    found = np.ones(len(keys), bool)
    for at, bit in _places(keys, len(words)):
        found &= (words[at] & bit) != 0
    return found


def maybe_texts(keys: DataFrame, df: DataFrame, text: str, id_col: str) -> DataFrame:
    """(doc_id, text_key, text) of the rows whose text_key is among the keys, and a few more."""
    shared = df.sparkSession.sparkContext.broadcast(key_filter(keys))
    base = keyed_texts(df, text, id_col)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        return batch.take(pa.array(np.flatnonzero(in_filter(batch.column(1).to_numpy(), shared.value))))

    return map_arrow(base, run, base.schema)


def connect(links: DataFrame, scratch: Scratch, max_rounds: int = 60) -> DataFrame:
    """(node, component): the least node of each component, for all linked nodes. Every node hands
    its larger neighbours, then its smaller ones, to its least one (large and small stars), until
    no node has two smaller neighbours or lies between two. Least neighbours are plain minima
    with partial aggregation and meet the edges by a join, so a hub's edges need no one task."""
    edges = scratch.write(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "edges")
    for _ in range(max_rounds):
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        smaller = F.when(F.col("v") < F.col("u"), F.col("v"))
        least = both.groupBy("u").agg(F.min("v").alias("m"), F.max(smaller).alias("top"), F.max(F.col("v") > F.col("u")).alias("has_larger"))
        least = scratch.write(least, "least")
        if not least.where((F.col("top") != F.col("m")) | (F.col("top").isNotNull() & F.col("has_larger"))).take(1):
            return least.select(F.col("u").alias("node"), F.least("u", "m").alias("component"))
        low = least.select(F.col("u").alias("v"), F.least("u", "m").alias("m"))
        large = scratch.write(edges.join(low, "v").select("u", F.col("m").alias("v")), "large")
        least_small = large.groupBy("u").agg(F.min("v").alias("m"))
        moved = large.join(least_small, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        after = scratch.write(moved.unionByName(least_small.select("u", F.col("m").alias("v"))), "edges")
        scratch.drop(edges, least, large)
        edges = after
        release(links.sparkSession)
    raise RuntimeError("components did not settle")


def components(df: DataFrame, text: str = "text", id_col: str = "doc_id", width: int = 3, percent: int = 85) -> DataFrame:
    """(doc_id, text_key, n_shingles, component_id, kept) of every row. Rows are linked when
    100 * intersection >= percent * union of their shingle sets, and components are the
    closure; component_id is the least id of the component."""
    spark = df.sparkSession
    scratch = Scratch(spark, "near")
    rows = scratch.write(sets_table(df, text, id_col, width), "sets")
    found = rows.where(F.col("class").isNotNull()).groupBy("class")
    made = found.agg(F.min(F.struct("doc_id", "text_key")).alias("rep"), *(F.min(c).alias(c) for c in ("sig", "brief", "odd", "n_shingles")))
    classes = scratch.write(made, "classes")
    lists = scratch.write(posting_lists(postings(classes, percent)), "lists")
    release(spark)
    alike = scratch.write(likely_pairs(first_groups(lists), classes, percent, forest=True), "alike")
    links = scratch.write(confirm(alike, classes, df, text, id_col, width, percent), "links")
    release(spark)
    placed = connect(links, scratch)
    groups = open_groups(lists, placed, scratch)
    apart = likely_pairs(groups, classes, percent, forest=False).join(alike, ["a", "b"], "left_anti")
    apart = scratch.write(apart, "apart")
    release(spark)
    if apart.take(1):
        more = scratch.write(confirm(apart, classes, df, text, id_col, width, percent), "links")
        if more.take(1):
            placed = joined(placed, more, scratch)
        release(spark)
    scratch.drop(lists, alike, links, apart)
    labelled = with_component(classes.select("class", F.col("rep.doc_id").alias("least")), placed)
    least = labelled.groupBy("component").agg(F.min("least").alias("component_id"))
    of_class = labelled.join(least, "component").select("class", "component_id")
    out = rows.drop("sig", "brief", "odd").join(of_class, "class", "left")
    alone = F.col("class").isNull()
    component_id = F.when(alone, F.col("doc_id")).otherwise(F.col("component_id"))
    return out.select(
        "doc_id",
        "text_key",
        "n_shingles",
        component_id.alias("component_id"),
        F.coalesce(F.col("doc_id") == component_id, component_id.isNull()).alias("kept"),
    )


def joined(placed: DataFrame, links: DataFrame, scratch: Scratch) -> DataFrame:
    """Components after further links between them."""
    ends = links
    for x in "ab":
        ends = ends.join(placed.select(F.col("node").alias(x), F.col("component").alias(f"in_{x}")), x, "left")
    ends = ends.select(*(F.coalesce(f"in_{x}", x).alias(x) for x in "ab"))
    upper = connect(ends, scratch).select(F.col("node").alias("component"), F.col("component").alias("upper"))
    moved = placed.join(upper, "component", "left").select("node", F.coalesce("upper", "component").alias("component"))
    fresh = upper.join(placed, upper["component"] == placed["node"], "left_anti")
    return moved.unionByName(fresh.select(F.col("component").alias("node"), F.col("upper").alias("component")))


def drop_near_duplicates(df: DataFrame, text: str = "text", id_col: str = "doc_id", width: int = 5, percent: int = 80) -> DataFrame:
    """The input's rows, one of each component. Rows that share an id are told apart by text,
    and of rows equal in both one stays."""
    spark = df.sparkSession
    found = Scratch(spark, "near-found").write(components(df, text, id_col, width, percent), "components")
    gone = found.where(~F.col("kept")).select("doc_id", "text_key").distinct()
    same_id = found.where("kept").groupBy("doc_id").count().where("count > 1")
    repeated = bool(same_id.take(1))
    keyed = packed(df).select("row", F.col(f"row.`{id_col}`").cast("long").alias("id"), F.xxhash64(F.col(f"row.`{text}`")).alias("key"))
    rest = keyed.join(gone, F.col("id").eqNullSafe(F.col("doc_id")) & (F.col("key") == F.col("text_key")), "left_anti")
    if repeated:
        rest = rest.dropDuplicates(["id", "key"])
    return rest.select("row.*")
