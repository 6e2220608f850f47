"""Bucket metadata and table entries as they are stored: packed bits.

Thresholds become codes of 1, 2, c or log2 b bits, an index into the scheme's thresholds. With
1plus a code of 1 stands for the one threshold; buckets that bump more are in a sorted list of
exceptions, a bucket number and a threshold each, and range bits say which runs of buckets have
any, so that most lookups never search it. Lookups read the packed form."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from ..params import BandParams


def pack(values: np.ndarray, bits: int) -> bytes:
    """Little-endian bit fields, one after the other."""
    if not len(values) or not bits:
        return b""
    shifts = np.arange(bits, dtype=np.uint64)
    planes = ((np.asarray(values).astype(np.uint64)[:, None] >> shifts) & np.uint64(1)).astype(np.uint8)
    return np.packbits(planes.reshape(-1), bitorder="little").tobytes()


def unpack(raw: bytes, bits: int, n: int) -> np.ndarray:
    if not n or not bits:
        return np.zeros(n, np.uint64)
    planes = np.unpackbits(np.frombuffer(raw, np.uint8), bitorder="little", count=n * bits).reshape(n, bits)
    return (planes.astype(np.uint64) << np.arange(bits, dtype=np.uint64)).sum(axis=1, dtype=np.uint64)


def code_bits(p: BandParams) -> int:
    return 1 if p.scheme == "1plus" else max(1, (len(p.thresholds()) - 1).bit_length())


def exception_bits(n_buckets: int, b: int) -> tuple[int, int]:
    """Bits of the bucket number and of the threshold of one exception."""
    return max(1, (n_buckets - 1).bit_length()), b.bit_length()


COUNT = 4  # bytes of an exception list's length


def encode(thresholds: np.ndarray, p: BandParams) -> tuple[bytes, bytes, bytes]:
    """(codes, exceptions, range bits); all empty for a layer that bumps nothing."""
    if not thresholds.any():
        return b"", b"", b""
    levels = np.array(p.thresholds())
    if p.scheme != "1plus":
        codes = np.searchsorted(levels, thresholds)
        if (levels[codes] != thresholds).any():
            raise AssertionError("a threshold that the scheme cannot express")
        return pack(codes, code_bits(p)), b"", b""
    over = np.flatnonzero(thresholds > levels[1])
    of_bucket, of_threshold = exception_bits(len(thresholds), p.b)
    exceptions = len(over).to_bytes(COUNT, "little") + pack(over, of_bucket) + pack(thresholds[over], of_threshold) if len(over) else b""
    ranges = b""
    if p.range_bits:
        marked = np.zeros(-(-len(thresholds) // p.range_bits), np.uint64)
        marked[over // p.range_bits] = 1
        ranges = pack(marked, 1)
    return pack(thresholds > 0, 1), exceptions, ranges


@dataclass
class Thresholds:
    """Packed thresholds of n buckets; indexing with bucket numbers decodes those alone."""

    codes: np.ndarray
    bits: int
    levels: np.ndarray
    buckets: np.ndarray | None
    over: np.ndarray | None
    ranges: np.ndarray | None
    range_size: int
    searches: int = 0

    @staticmethod
    def decode(codes: bytes, exceptions: bytes, ranges: bytes, n: int, p: BandParams) -> Thresholds:
        raw = np.frombuffer(codes + b"\0\0\0", np.uint8) if codes else np.zeros(0, np.uint8)
        levels = np.array(p.thresholds()[:2] if p.scheme == "1plus" else p.thresholds(), np.int32) if codes else np.zeros(1, np.int32)
        buckets = over = None
        if exceptions:
            of_bucket, of_threshold = exception_bits(n, p.b)
            k = int.from_bytes(exceptions[:COUNT], "little")
            cut = COUNT + -(-k * of_bucket // 8)
            buckets = unpack(exceptions[COUNT:cut], of_bucket, k).astype(np.int64)
            over = unpack(exceptions[cut:], of_threshold, k).astype(np.int32)
        return Thresholds(raw, code_bits(p) if codes else 0, levels, buckets, over, np.frombuffer(ranges, np.uint8) if ranges else None, p.range_bits)

    def any(self) -> bool:
        return bool(len(self.codes))

    def __getitem__(self, bucket: np.ndarray) -> np.ndarray:
        if not len(self.codes):
            return np.zeros(len(bucket), np.int32)
        at = bucket * self.bits
        byte = at >> 3
        word = self.codes[byte].astype(np.uint32) | (self.codes[byte + 1].astype(np.uint32) << 8) | (self.codes[byte + 2].astype(np.uint32) << 16)
        out = self.levels[((word >> (at & 7).astype(np.uint32)) & np.uint32((1 << self.bits) - 1)).astype(np.int64)]
        if self.buckets is not None:
            ask = out > 0
            if self.ranges is not None:
                r = bucket // self.range_size
                ask &= ((self.ranges[r >> 3] >> (r & 7).astype(np.uint8)) & 1).astype(bool)
            rows = np.flatnonzero(ask)
            self.searches += len(rows)
            place = np.searchsorted(self.buckets, bucket[rows])
            place[place == len(self.buckets)] = 0
            hit = self.buckets[place] == bucket[rows]
            out[rows[hit]] = self.over[place[hit]]
        return out


def encode_entries(z: np.ndarray, m: int, p: BandParams) -> bytes:
    """Interleaved words without the padding after the last slot; contiguous entries of r bits."""
    if p.layout == "interleaved":
        return z[: -(-m // 64) * p.r].astype("<u8").tobytes()
    if p.r in (8, 16, 32):
        return z.astype(f"<u{p.r // 8}").tobytes()
    return pack(z, p.r)


def decode_entries(raw: bytes, m: int, p: BandParams) -> np.ndarray:
    if p.layout == "interleaved":
        return np.concatenate([np.frombuffer(raw, "<u8"), np.zeros(2 * p.r, np.uint64)])
    if p.r in (8, 16, 32):
        return np.frombuffer(raw, f"<u{p.r // 8}")
    return unpack(raw, p.r, len(raw) * 8 // p.r)
