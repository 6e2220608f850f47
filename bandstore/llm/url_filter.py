"""URL filters: a blocked Bloom filter, then an exact hash join; DataFrame functions only.

Listed entries are canonical URLs or rules: a host, which stands for all of its subdomains,
and a path prefix. A URL is looked up under every suffix of its host, on label borders, with
its path cut to each listed path length. Those keys go through a blocked Bloom filter of the
listed keys (one 512-bit block to a key, a bit in each of its eight words). Keys that pass
are joined exactly with the list, which removes false positives, and the longest listed key
wins. Rows without a passing key never enter the join.

The filter has 16 bits to an entry. Up to LITERAL_WORDS words it is a literal of the plan;
beyond, its block table is joined by block number, and Spark chooses the join by its size.

Defined results: a null URL or one without `://` has empty host and path, and no key; an
empty list, or no matching entry, leaves the method's default verdict. Ties of length go to
the longer host, then to `block`. Columns host, path, rule and verdict of the input are
replaced, all others stay.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, fresh

WORDS, BITS_PER_KEY, LITERAL_WORDS = 8, 16, 8192
URL_PARTS = "://([^/?#]*)([^?#]*)"


def host_of(url: Column) -> Column:
    return ascii_lower(F.coalesce(F.regexp_extract(url, URL_PARTS, 1), F.lit("")))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, URL_PARTS, 2), F.lit(""))


def with_parts(pages: DataFrame, url: str = "url") -> DataFrame:
    return pages.withColumns({"host": host_of(F.col(url)), "path": path_of(F.col(url))})


def block_of(key: Column, n_blocks: int) -> Column:
    return F.pmod(F.xxhash64(F.lit(11), key), F.lit(n_blocks)).cast("int")


def bit_of(key: Column, word: int) -> Column:
    """Bit number within one word of the key's block, six hash bits each."""
    h = F.xxhash64(F.lit(13), key)
    return F.shiftrightunsigned(h, 6 * word).bitwiseAND(F.lit(63)).cast("int")


def build_filter(listed: DataFrame, n_blocks: int) -> DataFrame:
    """(block, w0..w7): words of the blocks that have keys."""
    keyed = listed.select(
        block_of(F.col("key"), n_blocks).alias("block"),
        *[F.call_function("shiftleft", F.lit(1).cast("long"), bit_of(F.col("key"), j)).alias(f"m{j}") for j in range(WORDS)],
    )
    return keyed.groupBy("block").agg(*[F.bit_or(f"m{j}").alias(f"w{j}") for j in range(WORDS)])


def _passes_words(key: Column, words: list[Column]) -> Column:
    out = F.lit(True)
    for j, w in enumerate(words):
        bit = F.call_function("shiftrightunsigned", w, bit_of(key, j)).bitwiseAND(F.lit(1))
        out = out & (bit == 1)
    return out


def probe_keys(path_lengths: list[int]) -> Column:
    """Keys of a row with columns host and path; path_lengths: those of the list."""
    labels = F.split("host", r"\.")
    n = F.size(labels)
    hosts = F.transform(F.sequence(F.lit(1), n), lambda i: F.array_join(F.slice(labels, i, n - i + 1), "."))
    cuts = F.array(*[F.lit(x) for x in path_lengths]).cast("array<int>")
    fitting = F.filter(cuts, lambda c: c <= F.length("path"))
    paths = F.transform(fitting, lambda c: F.substring(F.col("path"), F.lit(1), c))
    keys = F.flatten(F.transform(hosts, lambda h: F.transform(paths, lambda p: F.concat(h, p))))
    return F.when((F.col("host") != "") & (F.lit(len(path_lengths)) > 0), keys).otherwise(
        F.array().cast("array<string>")
    )


def judge(pages: DataFrame, listed: DataFrame, default: str = "allow", url: str = "url") -> DataFrame:
    """Add host, path, rule and verdict to every row. listed: host, path, verdict strings, a
    row for an entry. Counts and distinct path lengths of the list come to the driver."""
    entries = listed.select(
        F.concat("host", "path").alias("key"),
        F.length("host").alias("host_length"),
        F.length("path").alias("path_length"),
        F.col("verdict").alias("listed_verdict"),
    )
    lengths = sorted(r[0] for r in entries.select("path_length").distinct().collect())
    n_listed = entries.count()
    names = [c for c in pages.columns if c not in ("host", "path", "rule", "verdict")]
    parts = with_parts(pages.select(*names), url)
    if not n_listed:
        return parts.withColumns({"rule": F.lit(None).cast("string"), "verdict": F.lit(default)})
    n_blocks = max(1, -(-n_listed * BITS_PER_KEY // (64 * WORDS)))
    blocks = build_filter(entries, n_blocks)
    probe = fresh(parts.columns, "probe")[0]
    probed = parts.withColumn(probe, probe_keys(lengths))
    if n_blocks * WORDS <= LITERAL_WORDS:
        words = [0] * (n_blocks * WORDS)
        for r in blocks.collect():  # at most LITERAL_WORDS numbers
            words[r["block"] * WORDS : (r["block"] + 1) * WORDS] = [r[f"w{j}"] for j in range(WORDS)]
        literal = F.array(*[F.lit(w).cast("long") for w in words])
        element = lambda k, j: F.element_at(literal, block_of(k, n_blocks) * WORDS + j + 1)
        hits = F.filter(probe, lambda k: _passes_words(k, [element(k, j) for j in range(WORDS)]))
        marked = probed.withColumn(probe, hits)
        passing = marked.where(F.size(probe) > 0).select("host", "path", F.explode(probe).alias("key")).distinct()
        some = F.size(probe) > 0
    else:
        marked, some = probed, F.size(probe) > 0
        exploded = probed.select("host", "path", F.explode(probe).alias("key")).distinct()
        passing = (
            exploded.withColumn("block", block_of(F.col("key"), n_blocks))
            .join(blocks, "block")
            .where(_passes_words(F.col("key"), [F.col(f"w{j}") for j in range(WORDS)]))
            .select("host", "path", "key")
        )
    order = F.struct(F.length("key"), F.col("host_length"), F.col("listed_verdict"))
    verdicts = (
        passing.join(entries, "key")
        .groupBy("host", "path")
        .agg(F.max_by(F.struct("key", "listed_verdict"), order).alias("won"))
        .select("host", "path", F.col("won.key").alias("rule"), F.col("won.listed_verdict").alias("verdict"))
    )
    matched = marked.where(some).join(verdicts, ["host", "path"], "left")
    without = marked.where(~some).withColumns({"rule": F.lit(None).cast("string"), "verdict": F.lit(default)})
    columns = [*names, "host", "path", "rule", "verdict"]
    return matched.withColumn("verdict", F.coalesce("verdict", F.lit(default))).select(*columns).unionByName(
        without.select(*columns)
    )
