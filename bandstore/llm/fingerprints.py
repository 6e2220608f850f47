"""Document fingerprints by a homomorphic multiset hash.

A text is a multiset of paragraphs (lines, and the clauses of a line). Each paragraph is
hashed to a wide vector of small signed numbers; a text's fingerprint is the sum of its
paragraphs' vectors, lane by lane modulo 2**64. Sums do not depend on order, and a paragraph
is inserted or deleted by adding or subtracting its vector. No text is long enough to wrap a
lane, so lanes read as signed numbers are the sums themselves. As lanes are independent and of
mean zero, the cosine of two fingerprints estimates the cosine of the paragraph multisets,
so the same sums also tell how alike two texts are.

A paragraph weighs in with the square root of its length (in steps), so likeness follows the
share of text and not of line counts.

Defined results: null and empty texts have the zero fingerprint; two empty multisets are
alike (1), an empty and another one not (0). Order and repetition within equal multisets
never change a fingerprint.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_arrow, mix64, seeded_hash, slices

LANES, LANE_BITS = 128, 64
_PARAGRAPH = re.compile(r"[^\n.!?,;:|]+[.!?,;:|]*|[.!?,;:|]+")
_LANE_KEYS = mix64(np.arange(1, LANES // 4 + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def paragraphs(text: str) -> list[str]:
    return [p for x in _PARAGRAPH.findall(text) if (p := x.strip())]


def vectors(parts: list[str]) -> np.ndarray:
    """(paragraph, lane) int32 vectors. Four 16-bit lanes come from each 64-bit hash; a lane
    is +-w for a paragraph's weight w, with the sign from the hash."""
    if not parts:
        return np.zeros((0, LANES), np.int32)
    h = np.fromiter((xxhash.xxh3_64_intdigest(p) for p in parts), np.uint64, len(parts))
    wide = mix64(h[:, None] ^ _LANE_KEYS[None, :])
    lanes = wide.view(np.int16).reshape(len(parts), LANES)
    # Signs from the top bit, magnitudes 1 to 4 from two further bits: equal sums of different
    # multisets stay unlikely.
    signed = ((lanes & 3) + 1) * np.where(lanes < 0, -1, 1).astype(np.int16)
    weight = np.fromiter((max(1, round(len(p) ** 0.5 / 2)) for p in parts), np.int32, len(parts))
    return signed * weight[:, None]


def fingerprint(text: str | None) -> np.ndarray:
    """Sum of paragraph vectors modulo 2**LANE_BITS, read as signed lanes."""
    return insert(np.zeros(LANES, np.int64), paragraphs(text or ""))


def insert(state: np.ndarray, parts: list[str], step: int = 1 << 14) -> np.ndarray:
    """Fingerprint after the paragraphs are added."""
    total = state.copy()
    for at in range(0, len(parts), step):
        total += vectors(parts[at : at + step]).sum(axis=0, dtype=np.int64)
    return total


def delete(state: np.ndarray, parts: list[str]) -> np.ndarray:
    """Fingerprint after the paragraphs are taken out."""
    return state - insert(np.zeros(LANES, np.int64), parts)


def digest(state: np.ndarray) -> str:
    return state.astype(">i8").tobytes().hex()


def parse(value: str) -> np.ndarray:
    return np.frombuffer(bytes.fromhex(value), ">i8").astype(np.int64)


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Cosine of two fingerprints, 0 when it is negative."""
    x, y = a.astype(np.float64), b.astype(np.float64)
    nx, ny = float(x @ x), float(y @ y)
    if nx == 0 and ny == 0:
        return 1.0
    if nx == 0 or ny == 0:
        return 0.0
    if np.array_equal(a, b):
        return 1.0
    return min(1.0, max(0.0, float(x @ y) / (nx * ny) ** 0.5))


def fingerprints(df: DataFrame, text: str = "text", out: str = "fingerprint") -> DataFrame:
    """Add the fingerprint of each row's whole text."""
    df = df.drop(out)
    at, names = df.columns.index(text), [*df.columns, out]
    schema = df.withColumn(out, F.lit("")).schema

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        values = [digest(fingerprint(t)) for t in batch.column(at).to_pylist()]
        return pa.record_batch([*batch.columns, pa.array(values, pa.string())], names=names)

    return map_arrow(df, run, schema)


def edited_text(text: str, following: str) -> str:
    """The last third of text's code points replaced by the first as many of following."""
    n = len(text) // 3
    return text[: len(text) - n] + following[:n]


def ranges(df: DataFrame, id_col: str, n: int) -> list[int]:
    """Up to n - 1 cut points of the ids, near their quantiles."""
    if n < 2:
        return []
    probabilities = [i / n for i in range(1, n)]
    got = df.where(F.col(id_col).isNotNull()).approxQuantile(id_col, probabilities, min(0.01, 0.2 / n))
    return sorted({int(x) for x in got})


def with_next(df: DataFrame, id_col: str, text: str, n_ranges: int) -> DataFrame:
    """Rows in descending order of id, dealt by ranges so that a task sees runs of the order;
    `ghost` rows repeat the first row of the next range for the last one of this. Ties of an
    id go by hash of the text. Columns: range_no, order keys, doc_id, text, ghost.

    A null id orders last; the row after the last is the first."""
    spark = df.sparkSession
    base = df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text).alias("text"))
    cuts = ranges(base, "doc_id", n_ranges)
    # Range 0 has the largest ids; a null id is in the last range.
    cut_of = F.lit(len(cuts))
    if cuts:
        # Of the sorted cuts, first every STEP-th is looked at, then those between two of them.
        literal = F.array(*[F.lit(c) for c in cuts])
        coarse = F.array(*[F.lit(c) for c in cuts[STEP - 1 :: STEP]]).cast("array<long>")
        whole = F.size(F.filter(coarse, lambda c: c < F.col("doc_id")))
        above = whole * STEP + F.size(F.filter(F.slice(literal, whole * STEP + 1, F.lit(STEP)), lambda c: c < F.col("doc_id")))
        cut_of = F.when(F.col("doc_id").isNull(), F.lit(len(cuts))).otherwise(F.lit(len(cuts)) - above)
    base = base.withColumn("range_no", cut_of.cast("int"))
    base = base.withColumn("tie", F.xxhash64("text"))
    # First row of each range: ids alone, a row per range comes back.
    order = F.struct(F.coalesce(F.col("doc_id").isNotNull(), F.lit(False)).alias("known"), "doc_id", "tie")
    firsts = {r[0]: r[1] for r in base.groupBy("range_no").agg(F.max(order).alias("first")).collect()}
    if not firsts:
        return base.withColumn("ghost", F.lit(False))
    used = sorted(firsts)
    ghost_for = {firsts_no: used[i - 1] for i, firsts_no in enumerate(used)}  # the first's ghost closes the ring
    table = spark.createDataFrame(
        [(no, ghost_for[no], firsts[no]["doc_id"], firsts[no]["tie"]) for no in used],
        "range_no int, ghost_in int, first_id long, first_tie long",
    )
    is_first = F.col("doc_id").eqNullSafe(F.col("first_id")) & (F.col("tie") == F.col("first_tie"))
    marked = base.join(F.broadcast(table), "range_no", "left")  # a row per range
    return marked.select(
        "doc_id",
        "text",
        "tie",
        F.explode(
            F.when(
                is_first,
                F.array(
                    F.struct(F.col("range_no").alias("range_no"), F.lit(False).alias("ghost")),
                    F.struct(F.col("ghost_in").alias("range_no"), F.lit(True).alias("ghost")),
                ),
            ).otherwise(F.array(F.struct(F.col("range_no").alias("range_no"), F.lit(False).alias("ghost"))))
        ).alias("place"),
    ).select("doc_id", "text", "tie", "place.range_no", "place.ghost")


STEP = 32

RESULT = (
    "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, "
    "near_edited double, near_next double"
)


def edit_report(df: DataFrame, id_col: str = "doc_id", text: str = "text", n_ranges: int | None = None) -> DataFrame:
    """Each text's fingerprint against that of its edited text (see edited_text, the next in
    descending id gives the new end) and against the next text's. Each text is shuffled once;
    a task keeps two texts."""
    spark = df.sparkSession
    n = n_ranges or int(spark.conf.get("spark.sql.shuffle.partitions"))
    placed = with_next(df, id_col, text, n)
    dealt = placed.repartitionById(n, F.col("range_no")).sortWithinPartitions(
        "range_no", "ghost", F.col("doc_id").desc_nulls_last(), F.col("tie").desc()
    )

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple | None = None  # doc_id, text, fingerprint, range
        rows: list[tuple] = []
        for whole in batches:
            for batch in slices(whole):
                columns = [batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("doc_id", "text", "range_no", "ghost")]
                for doc_id, value, range_no, ghost in zip(*columns, strict=True):
                    value = value or ""
                    print_ = fingerprint(value)
                    if held is not None and held[3] == range_no:
                        rows.append(_compare(held, value, print_))
                    held = None if ghost else (doc_id, value, print_, range_no)
                if rows:
                    yield pa.RecordBatch.from_pylist(rows, schema=OUT)
                    rows = []

    return dealt.mapInArrow(run, RESULT)


OUT = pa.schema(
    [
        ("doc_id", pa.int64()), ("n_chars", pa.int64()), ("edited_sha256", pa.string()), ("fingerprint", pa.string()),
        ("edited_fingerprint", pa.string()), ("near_edited", pa.float64()), ("near_next", pa.float64()),
    ]
)


def _compare(held: tuple, following: str, following_print: np.ndarray) -> dict:
    doc_id, value, own, _ = held
    edited = edited_text(value, following)
    edited_print = fingerprint(edited)
    return {
        "doc_id": doc_id,
        "n_chars": len(value),
        "edited_sha256": hashlib.sha256(edited.encode()).hexdigest(),
        "fingerprint": digest(own),
        "edited_fingerprint": digest(edited_print),
        "near_edited": likeness(own, edited_print),
        "near_next": likeness(own, following_print),
    }
