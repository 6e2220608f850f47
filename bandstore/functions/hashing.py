"""Key digests and everything that derives from them, as Spark expressions and as numpy.

Keys are hashed once to two 64-bit words. Later hash values are remixed from those words by
round, with Spark's xxhash64 on longs, which numpy repeats bit by bit."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

# Primes of the public xxHash64 definition.
P1, P2, P3 = np.uint64(0x9E3779B185EBCA87), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9)
P4, P5 = np.uint64(0x85EBCA77C2B2AE63), np.uint64(0x27D4EB2F165667C5)
SPARK_SEED = 42

SHARD_ROUND, FINGERPRINT_ROUND, LAYER_ROUND, FREE_ROUND, POSITION_ROUND = 1, 2, 3, 4, 5


def _rotl(x: np.ndarray, n: int) -> np.ndarray:
    return (x << np.uint64(n)) | (x >> np.uint64(64 - n))


def hash_long(x: np.ndarray, seed: np.ndarray | np.uint64) -> np.ndarray:
    """xxHash64 of one 8-byte word, as Spark computes it."""
    h = seed + P5 + np.uint64(8)
    h = h ^ (_rotl(x * P2, 31) * P1)
    h = _rotl(h, 27) * P1 + P4
    h ^= h >> np.uint64(33)
    h *= P2
    h ^= h >> np.uint64(29)
    h *= P3
    return h ^ (h >> np.uint64(32))


def remix(x: np.ndarray, round_no: int) -> np.ndarray:
    """xxhash64(x, lit(round_no)) on uint64."""
    with np.errstate(over="ignore"):
        first = hash_long(x.astype(np.uint64, copy=False), np.uint64(SPARK_SEED))
        return hash_long(np.full(1, round_no, np.int64).view(np.uint64), first)


def remix_column(x: Column, round_no: Column | int) -> Column:
    r = F.lit(round_no) if isinstance(round_no, int) else round_no
    return F.xxhash64(x, r.cast("long"))


def layer_round(kind: int, layer: int, attempt: int) -> int:
    """A round number of its own for each use (0 start, 1 and 2 coefficients), layer and try."""
    return 16 + ((layer * 4096 + attempt) * 4 + kind)


def canonical(column: Column, kind: T.DataType) -> Column:
    """Key columns of any type in a form that xxhash64 takes: doubles and floats by value with
    one zero, timestamps as microseconds, maps as sorted entries, other types as they are."""
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        return F.when(column == 0, F.lit(0.0)).otherwise(column.cast("double"))
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(column)
    if isinstance(kind, T.TimestampNTZType):
        return column.cast("string")
    if isinstance(kind, T.MapType):
        return F.array_sort(F.map_entries(column))
    return column


def with_digest(df: DataFrame, cols: list[str], algo: str = "xx128", seed: int = 1, hi: str = "hi", lo: str = "lo") -> DataFrame:
    """Add the digest words; null for a row with a null key column.

    xx128 and xx64 use xxhash64 under two seeds; md5 takes 15 hex digits a word of the md5 of
    the key's text, which other engines can repeat; bits:n keeps n bits, to see clashes."""
    types = {f.name: f.dataType for f in df.schema.fields}
    keys = [canonical(F.col(c), types[c]) for c in cols]
    some_null = F.lit(False)
    for c in cols:
        some_null = some_null | F.col(c).isNull()
    if algo == "md5":
        text = F.md5(F.concat_ws("\x1f", *[F.col(c).cast("string") for c in cols]))
        words = [F.conv(F.substring(text, at, 15), 16, 10).cast("long") for at in (1, 16)]
    elif algo in ("xx128", "xx64"):
        first = F.xxhash64(F.lit(seed), *keys)
        second = F.xxhash64(F.lit(seed + 7919), *keys) if algo == "xx128" else F.xxhash64(first, F.lit(7919))
        words = [first, second]
    elif algo.startswith("bits:"):
        first = F.xxhash64(F.lit(seed), *keys).bitwiseAND(F.lit((1 << int(algo[5:])) - 1))
        words = [first, F.xxhash64(first, F.lit(7919))]
    else:
        raise ValueError(f"unknown digest {algo}")
    return df.withColumns({hi: F.when(~some_null, words[0]), lo: F.when(~some_null, words[1])})


def shard_column(hi: Column, n_shards: int) -> Column:
    return F.pmod(remix_column(hi, SHARD_ROUND), F.lit(n_shards)).cast("int")


def shard_of(hi: np.ndarray, n_shards: int) -> np.ndarray:
    return np.mod(remix(hi, SHARD_ROUND).view(np.int64), n_shards).astype(np.int32)


def starts(hi: np.ndarray, n_starts: np.ndarray | int, layer: int, attempt: int) -> np.ndarray:
    h = remix(hi, layer_round(0, layer, attempt)) >> np.uint64(32)
    return ((h * np.asarray(n_starts, np.uint64)) >> np.uint64(32)).astype(np.int64)


def start_column(hi: Column, n_starts: Column, layer: Column | int, attempt: Column | int) -> Column:
    h = F.shiftrightunsigned(remix_column(hi, _round_column(0, layer, attempt)), 32)
    return F.shiftrightunsigned(h * n_starts, 32)


def _round_column(kind: int, layer: Column | int, attempt: Column | int) -> Column:
    if isinstance(attempt, int) and isinstance(layer, int):
        return F.lit(layer_round(kind, layer, attempt))
    at = F.lit(layer) if isinstance(layer, int) else layer
    return (F.lit(16) + ((at * 4096 + attempt) * 4 + kind)).cast("long")


def coefficients(lo: np.ndarray, w: int, coef: str, layer: int, attempt: int) -> list[np.ndarray]:
    """Words of the coefficient bits; bit 0 is the start's and always set."""
    words = [remix(lo, layer_round(1, layer, attempt))]
    if w == 128:
        words.append(remix(lo, layer_round(2, layer, attempt)))
    if coef.startswith("sparse:"):
        return _sparse(words, w, int(coef.partition(":")[2]))
    if w < 64:
        words[0] = words[0] & np.uint64((1 << w) - 1)
    words[0] = words[0] | np.uint64(1)
    return words


def _sparse(words: list[np.ndarray], w: int, groups: int) -> list[np.ndarray]:
    """One bit in each of `groups` groups of w / groups; the first group's is bit 0."""
    size, bits = w // groups, (w // groups - 1).bit_length()
    if size * groups != w or size & (size - 1) or bits * groups > 64 * len(words):
        raise ValueError("sparse groups must divide w into powers of two")
    out = [np.zeros(len(words[0]), np.uint64) for _ in range(max(1, w // 64))]
    one = np.uint64(1)
    for g in range(groups):
        if g == 0:
            at = np.zeros(len(words[0]), np.uint64)
        else:
            word, shift = divmod(g * bits, 64)
            at = np.uint64(g * size) + ((words[word % len(words)] >> np.uint64(shift)) & np.uint64(size - 1))
        for k in range(len(out)):
            inside = (at >= np.uint64(64 * k)) & (at < np.uint64(64 * k + 64))
            out[k] |= np.where(inside, one << (at & np.uint64(63)), np.uint64(0))
    return out


def coefficient_column(lo: Column, w: int, layer: Column | int, attempt: Column | int) -> Column:
    """Dense coefficients for w up to 64."""
    c = remix_column(lo, _round_column(1, layer, attempt))
    if w < 64:
        c = c.bitwiseAND(F.lit((1 << w) - 1))
    return c.bitwiseOR(F.lit(1).cast("long"))


def fingerprint(lo: np.ndarray, r: int) -> np.ndarray:
    return remix(lo, FINGERPRINT_ROUND) & np.uint64((1 << r) - 1)


def fingerprint_column(lo: Column, r: int) -> Column:
    return remix_column(lo, FINGERPRINT_ROUND).bitwiseAND(F.lit((1 << r) - 1))
