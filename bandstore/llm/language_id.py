"""Language identification by prediction by partial matching.

Each language has a tree of byte contexts of variable order, with the symbol counts seen
after each context. The cost of a byte is the exact code length of the escape method C: the
longest context that the language knows codes the byte, or codes an escape (as likely as
its distinct symbols against its total) and hands over to the next shorter context, down to
a uniform alphabet. Statistics are frozen after training, so the cost of a byte depends on
its context node and itself alone; all languages' costs are compiled into one table by
(node, symbol), and a text's code length is a sum of table rows.

Defined results: null text, empty text and text without a letter give `und` with score 0.
Repeated rows are scored alike; an empty training set gives `und` everywhere; further
columns of the input pass through untouched under `passthrough`.
"""

from __future__ import annotations

import json
import math
from collections import defaultdict
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import fresh, map_arrow, seeded_hash, text_bytes

UNDETERMINED = "und"
ORDER = 3


@dataclass(frozen=True)
class LanguageModel:
    """Code-length tables of all languages.

    symbol_of: 256 bytes to alphabet symbols (0 stands for the text's start).
    node_of: context of ORDER symbols to the node of its longest known suffix.
    nats: (node * alphabet + symbol, language) code lengths.
    """

    languages: list[str]
    alphabet: int
    symbol_of: np.ndarray
    node_of: np.ndarray
    nats: np.ndarray

    def code_lengths(self, texts: list[bytes], chunk: int = 4 << 20) -> np.ndarray:
        """Nats for each text and language."""
        out = np.zeros((len(texts), max(1, len(self.languages))))
        start, size = 0, 0
        for i, t in enumerate(texts):
            if len(t) > chunk:
                if start < i:
                    out[start:i] = self._batch(texts[start:i])
                out[i] = self._long(t, chunk)
                start, size = i + 1, 0
                continue
            size += len(t)
            if size > chunk:
                out[start : i + 1] = self._batch(texts[start : i + 1])
                start, size = i + 1, 0
        if start < len(texts):
            out[start:] = self._batch(texts[start:])
        return out

    def _long(self, text: bytes, chunk: int) -> np.ndarray:
        """A long text goes by pieces that overlap by one context."""
        total = np.zeros(len(self.languages))
        symbols = np.concatenate([np.zeros(ORDER, np.uint8), self.symbol_of[np.frombuffer(text, np.uint8)]])
        for at in range(ORDER, len(symbols), chunk):
            total += self._rows(symbols[at - ORDER : at + chunk]).sum(axis=0, dtype=np.float64)
        return total

    def _rows(self, symbols: np.ndarray) -> np.ndarray:
        a, s = self.alphabet, symbols.astype(np.int32)
        context = (s[:-3] * a + s[1:-2]) * a + s[2:-1]
        return self.nats[self.node_of[context] * a + s[3:]]

    def _batch(self, texts: list[bytes]) -> np.ndarray:
        pad = b"\0" * ORDER
        flat = self.symbol_of[np.frombuffer(pad + pad.join(texts) + pad, np.uint8)]
        lengths = np.fromiter(map(len, texts), np.int64, len(texts))
        rows = self._rows(flat)
        rows[flat[ORDER:] == 0] = 0.0
        begins = np.concatenate([[0], np.cumsum(lengths + ORDER)[:-1]])
        return np.add.reduceat(rows, begins, axis=0, dtype=np.float64)

    def predict(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Index of the cheapest language, and its tempered posterior."""
        nats = self.code_lengths(texts)
        n = np.maximum(np.fromiter(map(len, texts), np.int64, len(texts)), 1)
        rel = -(nats - nats.min(axis=1, keepdims=True)) / np.sqrt(n)[:, None]
        p = np.exp(rel)
        p /= p.sum(axis=1, keepdims=True)
        best = nats.argmin(axis=1)
        return best, p[np.arange(len(texts)), best]


def count_contexts(df: DataFrame, text: str, lang: str) -> DataFrame:
    """Counts of byte strings of ORDER + 1 bytes by language; a text begins after ORDER zero
    bytes. Counted per batch, summed by Spark."""

    def count(batch: pa.RecordBatch) -> pa.RecordBatch:
        by_lang: dict[str, list[bytes]] = defaultdict(list)
        for language, t in zip(batch.column(1).to_pylist(), text_bytes(batch.column(0)), strict=True):
            by_lang[language].append(t)
        langs, grams, counts = [], [], []
        for language, texts in by_lang.items():
            pad = b"\0" * ORDER
            flat = np.frombuffer(pad + pad.join(texts), np.uint8).astype(np.uint32)
            gram = (flat[:-3] << 24) | (flat[1:-2] << 16) | (flat[2:-1] << 8) | flat[3:]
            values, n = np.unique(gram[flat[3:] != 0], return_counts=True)
            langs += [language] * len(values)
            grams.append(values.astype(np.int64))
            counts.append(n.astype(np.int64))
        return pa.record_batch(
            [pa.array(langs, pa.string()), pa.array(np.concatenate(grams)), pa.array(np.concatenate(counts))],
            names=["language", "gram", "n"],
        )

    counted = map_arrow(df.select(text, lang), count, "language string, gram bigint, n bigint")
    return counted.groupBy("language", "gram").agg(F.sum("n").alias("n"))


def train(
    df: DataFrame,
    text: str = "text",
    lang: str = "lang",
    id_col: str = "doc_id",
    max_rows_per_language: int = 1500,
    max_text_bytes: int = 1 << 20,
    max_languages: int | None = None,
    max_cells: int = 1 << 25,
    max_nodes: int = 1 << 14,
    seed: int = 17,
) -> LanguageModel:
    """Fit on a bounded sample: about `max_rows_per_language` rows of each language, chosen
    by a seeded hash of the id, of texts up to `max_text_bytes`; all languages, or the
    `max_languages` most common; the `max_nodes` most visited contexts, fewer where contexts
    times symbols times languages would pass `max_cells` (4 bytes each), but all of order 1.
    What reaches the driver grows with the number of languages, not of rows."""
    usable = df.where(F.col(lang).isNotNull() & F.col(text).isNotNull() & (F.octet_length(text) <= max_text_bytes))
    found = usable.groupBy(lang).count().orderBy(F.desc("count"), lang)
    sizes = {
        r[0]: r[1]
        for r in (found if max_languages is None else found.limit(max_languages)).collect()
    }
    keep = F.lit(None).cast("double")
    for language, n in sizes.items():
        keep = F.when(F.col(lang) == language, F.lit(min(1.0, max_rows_per_language / n))).otherwise(keep)
    draw = seeded_hash(seed, F.col(id_col).cast("string")) / F.lit(float(1 << 62))
    counts = count_contexts(usable.where(draw < keep), text, lang)
    rows = counts.where(F.col("n") > 0).toArrow().to_pydict() if sizes else {"language": [], "gram": [], "n": []}
    return compile_model(rows["language"], rows["gram"], rows["n"], min(max_nodes, max_cells // (256 * max(1, len(sizes)))))


def compile_model(langs: list[str], grams: list[int], ns: list[int], max_nodes: int) -> LanguageModel:
    names = sorted(set(langs))
    lang_index = {x: i for i, x in enumerate(names)}
    seen = sorted({g & 255 for g in grams} | {(g >> s) & 255 for g in grams for s in (8, 16, 24)} - {0})
    seen = [b for b in seen if b]
    symbol_of = np.full(256, len(seen) + 1, np.uint8)  # one symbol stands for all unseen bytes
    symbol_of[0] = 0
    for i, b in enumerate(seen):
        symbol_of[b] = i + 1
    size = len(seen) + 2
    size = min(size, 256)
    if not names:
        return LanguageModel([], size, symbol_of, np.zeros(size**ORDER, np.int32), np.zeros((size, 1), np.float32))

    # Contexts are tuples of symbols, oldest first; tree[context][language][symbol] = count.
    tree: dict[tuple, dict[int, dict[int, int]]] = defaultdict(lambda: defaultdict(lambda: defaultdict(int)))
    visits: dict[tuple, int] = defaultdict(int)
    for language, gram, n in zip(langs, grams, ns, strict=True):
        k = lang_index[language]
        a, b, c, s = (int(symbol_of[(gram >> shift) & 255]) for shift in (24, 16, 8, 0))
        for context in ((), (c,), (b, c), (a, b, c)):
            tree[context][k][s] += n
            visits[context] += n
    must = [x for x in visits if len(x) < 2]
    rest = sorted((x for x in visits if len(x) >= 2), key=lambda x: (len(x) > 2, -visits[x], x))
    pairs, triples = [x for x in rest if len(x) == 2], [x for x in rest if len(x) == 3]
    nodes = (must + pairs + triples)[: max(max_nodes, len(must))]
    index = {x: i for i, x in enumerate(nodes)}

    nats = np.zeros((len(nodes), size, len(names)))
    for x in sorted(nodes, key=len):  # a node's row starts from the next shorter context's
        lower = nats[index[x[1:]]] if x else np.full((size, len(names)), math.log(size))
        row = np.array(lower)
        for k, symbols in tree[x].items():
            total, distinct = sum(symbols.values()), len(symbols)
            row[:, k] += math.log(total + distinct) - math.log(distinct)
            for s, n in symbols.items():
                row[s, k] = math.log(total + distinct) - math.log(n)
        nats[index[x]] = row

    node_of = np.zeros((size, size, size), np.int32)
    for x in nodes:
        if len(x) == 1:
            node_of[:, :, x[0]] = index[x]
    for x in nodes:
        if len(x) == 2:
            node_of[:, x[0], x[1]] = index[x]
    for x in nodes:
        if len(x) == 3:
            node_of[x] = index[x]
    return LanguageModel(
        names, size, symbol_of, node_of.reshape(-1), nats.reshape(-1, len(names)).astype(np.float32)
    )


def has_letter(text: Column) -> Column:
    return F.coalesce(text.rlike(r"\p{L}"), F.lit(False))


def identify(df: DataFrame, model: LanguageModel, text: str = "text", pred: str = "lang_pred", score: str = "score") -> DataFrame:
    """Add pred and score to every row (columns of these names are replaced); whole texts. The
    model is shipped by broadcast; its size is bounded by the parameters of train."""
    df = df.drop(pred, score)
    if not model.languages:
        return df.withColumns({pred: F.lit(UNDETERMINED), score: F.lit(0.0)})
    names = df.columns
    shared = df.sparkSession.sparkContext.broadcast(model)
    at = names.index(text)
    known = fresh(names, "has_letter")[0]
    schema = T.StructType(
        [*df.schema.fields, T.StructField(pred, T.StringType()), T.StructField(score, T.DoubleType())]
    )

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        m = shared.value
        ok = np.asarray(batch.column(len(names)).to_pylist(), bool)
        best, p = m.predict(text_bytes(batch.column(at)))
        best_names = [m.languages[b] if k else UNDETERMINED for b, k in zip(best, ok, strict=True)]
        columns = [batch.column(i) for i in range(len(names))]
        return pa.record_batch(
            [*columns, pa.array(best_names, pa.string()), pa.array(np.where(ok, p, 0.0))], names=schema.names
        )

    return map_arrow(df.withColumn(known, has_letter(F.col(text))), run, schema)


def describe(model: LanguageModel) -> str:
    return json.dumps({"languages": model.languages, "nodes": len(model.nats) // max(1, model.alphabet)})
