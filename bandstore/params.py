"""Parameters of a band structure, with the defaults of each threshold scheme."""

from __future__ import annotations

import math
from dataclasses import asdict, dataclass, replace

SCHEMES = ("2bit", "2bit-even", "cbit", "plain", "1plus", "headtail", "single")


def bucket_size(w: int, scheme: str) -> int:
    """The greatest power of two up to w*w / (2 log2 w); half as much for 1plus."""
    bound = w * w / ((4 if scheme == "1plus" else 2) * math.log2(w))
    return 1 << int(math.floor(math.log2(bound)))


def overload(w: int, scheme: str, b: int) -> float:
    """Default eps = m/n - 1, negative for more keys than slots."""
    if scheme == "1plus":
        return -2 / 3 * w / (4 * b + w)
    return -(3 if w <= 32 else 4) / w


def head_tail(w: int, constant: float) -> tuple[int, float]:
    """Bucket size and eps of the analysed variant: w*w / (C log2 w), and n / m = 1 + C log2 w / (8 w)."""
    b = 1 << int(math.floor(math.log2(w * w / (constant * math.log2(w)))))
    return b, 1 / (1 + constant * math.log2(w) / (8 * w)) - 1


def two_thresholds(w: int, b: int, eps: float) -> tuple[int, int]:
    """The lower and upper threshold of the 2-bit scheme, linear in eps."""
    if w <= 32:
        return math.ceil((0.13 - eps / 2) * b), math.ceil((0.3 - eps / 2) * b)
    return math.ceil((0.09 - 0.75 * eps) * b), math.ceil((0.22 - 1.3 * eps) * b)


def one_threshold(b: int, eps: float) -> int:
    return math.ceil(-2 * eps * b + math.sqrt(b / (1 + eps)) / 2)


def thresholds(scheme: str, w: int, b: int, eps: float, c: int = 3) -> list[int]:
    """Thresholds that metadata can represent, ascending, 0 and b included. For 1plus all
    above the first are exceptions."""
    if scheme == "plain":
        out = [*range(b - 1), b]
    elif scheme == "1plus":
        t = one_threshold(b, eps)
        out = [0, *range(min(t, b), b + 1)]
    elif scheme in ("2bit", "single"):
        low, high = two_thresholds(w, b, eps)
        out = [0, low, high, b] if scheme == "2bit" else [0, low, b]
    elif scheme == "2bit-even":
        low = two_thresholds(w, b, eps)[0]
        out = [0, low, 2 * low, b]
    elif scheme == "cbit":
        n = (1 << c) - 1
        high = two_thresholds(w, b, eps)[1]
        out = [*[round(i * 1.5 * high / (n - 1)) for i in range(n)], b]
    elif scheme == "headtail":
        out = [0, math.ceil(3 * w / 8), b]
    else:
        raise ValueError(f"unknown scheme {scheme}")
    return sorted({min(max(0, t), b) for t in out} | {0, b})


@dataclass(frozen=True)
class BandParams:
    """w: band width; r: value bits; b: bucket size; eps: m/n - 1 of the overloaded layers
    (of all slots for plain and zero); kind: layered, plain, zero or twohop. constant: C of the
    headtail scheme; empty_limit: a layer with a greater share of empty slots starts over with
    new hashes, so none does at 1."""

    kind: str = "layered"
    r: int = 8
    w: int = 64
    b: int = 0
    eps: float = math.nan
    scheme: str = "2bit"
    c_bits: int = 3
    layers: int = 4
    coef: str = "dense"
    layout: str = "interleaved"
    order: str = "r2l"
    bucket_order: str = "l2r"
    mode: str = "greedy"
    free: str = "zero"
    piece_starts: int = 1 << 14
    seed: int = 1
    n_shards: int = 1
    max_tries: int = 40
    is_filter: bool = False
    range_bits: int = 0
    fixed_sizes: bool = False
    constant: float = 2.0
    empty_limit: float = 1.0

    def resolved(self) -> BandParams:
        """With b and eps filled in."""
        if self.w not in (16, 32, 64, 128) or not 1 <= self.r <= 63:
            raise ValueError("w must be 16, 32, 64 or 128, and 1 <= r <= 63")
        if self.kind in ("plain", "zero"):
            return replace(self, eps=0.1 if math.isnan(self.eps) else self.eps, b=self.b or 64, layers=1)
        if self.scheme == "headtail":
            b, eps = head_tail(self.w, self.constant)
            b, eps = self.b or b, eps if math.isnan(self.eps) else self.eps
        else:
            b = self.b or bucket_size(self.w, self.scheme)
            eps = overload(self.w, self.scheme, b) if math.isnan(self.eps) else self.eps
        return replace(self, b=b, eps=eps)

    def thresholds(self) -> list[int]:
        return thresholds(self.scheme, self.w, self.b, self.eps, self.c_bits)

    def meta_bits(self) -> float:
        """Bits of metadata for each bucket, exceptions aside."""
        if self.kind in ("plain", "zero"):
            return 0.0
        if self.scheme == "1plus":
            return 1.0 + (1.0 / self.range_bits if self.range_bits else 0.0)
        if self.scheme == "headtail" or self.scheme == "single":
            return 2.0
        return float({"2bit": 2, "2bit-even": 2, "cbit": self.c_bits}.get(self.scheme, math.ceil(math.log2(self.b))))

    def to_dict(self) -> dict:
        return asdict(self)
