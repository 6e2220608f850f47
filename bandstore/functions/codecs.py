"""Values to r-bit codes and back."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MAX_DICTIONARY = 1 << 16


def bits_for(n_codes: int) -> int:
    return max(1, (n_codes - 1).bit_length())


def checked(value: Column, r: int) -> Column:
    """The value as a long, or an error if it does not fit r bits."""
    v = value.cast("long")
    fits = (v >= 0) & (v <= F.lit((1 << r) - 1))
    return F.when(fits, v).when(v.isNull(), F.raise_error(F.lit("a value is null"))).otherwise(
        F.raise_error(F.concat(F.lit(f"a value does not fit {r} bits: "), v.cast("string")))
    )


@dataclass(frozen=True)
class Dictionary:
    """Codes of a column with few distinct values, in their order."""

    values: list = field(default_factory=list)

    @property
    def r(self) -> int:
        return bits_for(len(self.values))

    def encode(self, c: Column) -> Column:
        out = F.lit(None).cast("long")
        if len(self.values) <= 64:
            for i, v in reversed(list(enumerate(self.values))):
                out = F.when(c == F.lit(v), F.lit(i)).otherwise(out)
            return out
        return F.array_position(F.array(*[F.lit(v) for v in self.values]), c) - 1

    def decode(self, code: Column) -> Column:
        return F.get(F.array(*[F.lit(v) for v in self.values]), code.cast("int"))


def dictionary(df: DataFrame, col: str, limit: int = MAX_DICTIONARY) -> Dictionary:
    """Sorted distinct values; refused beyond `limit`, as they come to the driver."""
    rows = df.select(col).where(F.col(col).isNotNull()).distinct().limit(limit + 1).collect()
    if len(rows) > limit:
        raise ValueError(f"{col} has more than {limit} distinct values; use ordered_codes()")
    return Dictionary(sorted(r[0] for r in rows))
