"""Toxicity by a weighted finite-state pattern grammar.

A tagger rewrites a text into tags: an automaton over all lexicon entries finds insults,
threats, targets, negations and verbs of reported speech (whole words, and learned word
stems). Its output is cut into clauses at punctuation. Five weighted transducers read the
tags of a clause: insults; threats, which need somebody they are aimed at; targets, which
strengthen a clause; negations, which weaken the hits after them; and reported speech or
quotation marks, which discount it. They are composed into one machine whose states are the
reachable combinations, so that a clause is read once. A text's score is a logistic function
of what its matched clauses add up to.

Insult weights are learned from labelled rows: Spark counts, for every word and word stem,
the labelled texts of each kind that have it, and keeps entries whose log odds stand out.
The rest of the grammar is a small fixed list, for several languages.

Defined results: null and empty texts match nothing and get the score of an empty match
list; an empty label set leaves the built-in lexicon and default coefficients. Columns score,
predicted and n_clauses of the input are replaced, all others stay.
"""

from __future__ import annotations

import functools
import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import map_arrow, materialize, seeded_hash

INSULT, THREAT, TARGET, NEGATION, REPORT = "insult", "threat", "target", "negation", "report"

# The built-in lexicon.
LEXICON = {
    INSULT: "idiot idiots moron morons stupid scum trash loser losers pathetic worthless disgusting clown dumb imbecile "
    "dummkopf trottel abschaum imbécile connard ordure abruti estúpido basura imbécil",
    THREAT: "kill hurt destroy beat burn smash töten umbringen schlagen tuer frapper matar golpear",
    TARGET: "you your you're he she they him her them this these that du dich ihr sie er dieser vous tu toi il elle ils "
    "cette tú usted él ella ellos este esta",
    NEGATION: "not no never isn't aren't don't without nicht kein keine nie pas jamais sans nunca sin",
    REPORT: "said says say wrote claimed quoted called reported sagte schrieb behauptete dit écrit affirmé dijo escribió",
}
CLAUSE_END = re.compile(r"[.!?;:\n|]")
WORD_RUN = re.compile(r"[^\W\d_]+(?:'[^\W\d_]+)?")
QUOTES = set("\"«»“”„")
STEM_LENGTHS = (4, 5, 6)


QUOTE, OTHER = "quote", "other"
TAGS = (OTHER, INSULT, THREAT, TARGET, NEGATION, REPORT, QUOTE)


@dataclass(frozen=True)
class Transducer:
    """A weighted transducer over the tags of a clause: after[state][tag] is the next state,
    gain[state][tag] what a hit of that tag is multiplied with, last[state] what the clause is
    multiplied with if it ends there. State 0 begins. A tag without an arc stays and weighs 1."""

    after: tuple[dict[str, int], ...]
    gain: tuple[dict[str, float], ...]
    last: tuple[float, ...]

    def step(self, state: int, tag: str) -> tuple[int, float]:
        return self.after[state].get(tag, state), self.gain[state].get(tag, 1.0)


def compose(a: Transducer, b: Transducer) -> Transducer:
    """Both run side by side over the same tags: states are the reachable pairs, weights multiply."""
    index, todo = {(0, 0): 0}, [(0, 0)]
    after, gain = [], []
    for x, y in todo:
        arcs, weights = {}, {}
        for tag in TAGS:
            (next_x, w_x), (next_y, w_y) = a.step(x, tag), b.step(y, tag)
            if (next_x, next_y) not in index:
                index[next_x, next_y] = len(index)
                todo.append((next_x, next_y))
            arcs[tag], weights[tag] = index[next_x, next_y], w_x * w_y
        after.append(arcs)
        gain.append(weights)
    return Transducer(tuple(after), tuple(gain), tuple(a.last[x] * b.last[y] for x, y in index))


def insults() -> Transducer:
    """Insults weigh what the lexicon says."""
    return Transducer(({},), ({},), (1.0,))


def threats(unaimed: float = 0.25) -> Transducer:
    """A threat counts in full after somebody it may be aimed at."""
    return Transducer(({TARGET: 1}, {}), ({THREAT: unaimed}, {}), (1.0, 1.0))


def targets(gain: float) -> Transducer:
    """A clause that has a target weighs more."""
    return Transducer(({TARGET: 1}, {}), ({}, {}), (1.0, gain))


def negations(loss: float, reach: int = 3) -> Transducer:
    """Hits among the `reach` words after a negation lose weight."""
    closing = tuple({**{tag: max(0, k - 1) for tag in TAGS if tag != NEGATION}, NEGATION: reach} for k in range(reach + 1))
    weak = {INSULT: loss, THREAT: loss}
    return Transducer(closing, ({}, *[weak] * reach), (1.0,) * (reach + 1))


def reports(loss: float) -> Transducer:
    """A clause that reports speech, or quotes, loses weight."""
    return Transducer(({REPORT: 1, QUOTE: 1}, {}), ({}, {}), (1.0, loss))


@dataclass(frozen=True)
class Grammar:
    """words and stems: entry to (tag, weight); coefficients of the logistic layer."""

    words: dict[str, tuple[str, float]]
    stems: dict[str, tuple[str, float]]
    coefficients: tuple[float, ...] = (-3.0, 1.6, 1.0, 0.8)
    target_gain: float = 1.25
    negation_loss: float = 0.5
    report_loss: float = 0.6

    def parts(self) -> list[Transducer]:
        return [insults(), threats(), targets(self.target_gain), negations(self.negation_loss), reports(self.report_loss)]

    @functools.cached_property
    def machine(self) -> Transducer:
        """The clause acceptor: all transducers composed into one."""
        return functools.reduce(compose, self.parts())

    def automaton(self) -> ahocorasick.Automaton:
        """Only entries that can start a match are searched for; a clause with a hit is
        tagged from its start to its end."""
        found = ahocorasick.Automaton()
        for word, (tag, weight) in self.words.items():
            if tag in (INSULT, THREAT):
                found.add_word(word, (word, tag, weight, True))
        for stem, (tag, weight) in self.stems.items():
            if stem not in self.words:
                found.add_word(stem, (stem, tag, weight, False))
        if len(found):
            found.make_automaton()
        return found


def default_grammar() -> Grammar:
    words = {w: (tag, 1.0) for tag, entries in LEXICON.items() for w in entries.split()}
    return Grammar(words, {})


def hits(text: str, automaton: ahocorasick.Automaton) -> Iterator[tuple[int, int, str, float]]:
    """Word-aligned lexicon hits (start, end of the word, tag, weight), one to a word."""
    if not len(automaton):
        return
    last = -1
    best: tuple[int, int, str, float] | None = None
    n = len(text)
    for end, (entry, tag, weight, whole) in automaton.iter(text):
        start = end - len(entry) + 1
        if start and (text[start - 1].isalpha()):
            continue
        stop = end + 1
        if whole:
            if stop < n and text[stop].isalpha():
                continue
        else:
            while stop < n and text[stop].isalpha():
                stop += 1
        if start == last and best is not None:
            if weight > best[3]:
                best = (start, stop, tag, weight)
            continue
        if best is not None:
            yield best
        last, best = start, (start, stop, tag, weight)
    if best is not None:
        yield best


def clause_weight(tags: list[tuple[str, float]], quoted: bool, g: Grammar) -> tuple[float, float]:
    """Run the composed machine over a clause: (weight, number of insults and threats)."""
    m, weight, count, state = g.machine, 0.0, 0, 0
    if quoted:
        state = m.after[state][QUOTE]
    for tag, w in tags:
        if tag in (INSULT, THREAT):
            weight += w * m.gain[state][tag]
            count += 1
        state = m.after[state][tag]
    return weight * m.last[state], count


def matched_clauses(text: str, g: Grammar, automaton: ahocorasick.Automaton) -> list[tuple[int, int, float, float]]:
    """Clauses that have an insult or threat: (start, end, weight, count)."""
    found: list[tuple[int, int, float, float]] = []
    pending: list[tuple[int, int, str, float]] = []
    clause = (-1, -1)

    def close() -> None:
        if not pending:
            return
        start, end = clause
        marks = {s: (tag, w) for s, _, tag, w in pending}
        tags = []
        for m in WORD_RUN.finditer(text, start, end):
            if m.start() in marks:
                tags.append(marks.pop(m.start()))
            else:
                entry = g.words.get(m.group())
                tags.append(entry if entry and entry[0] not in (INSULT, THREAT) else (OTHER, 0.0))
        tags += marks.values()
        quoted = bool(QUOTES & set(text[start:end]))
        found.append((start, end, *clause_weight(tags, quoted, g)))
        pending.clear()

    for hit in hits(text, automaton):
        if not (clause[0] <= hit[0] < clause[1]):
            close()
            before = max(text.rfind(c, clause[1] if clause[1] > 0 else 0, hit[0]) for c in ".!?;:\n|")
            after = CLAUSE_END.search(text, hit[1])
            clause = (before + 1, after.start() if after else len(text))
        pending.append(hit)
    close()
    return found


def features(clauses: list[tuple[int, int, float, float]]) -> list[float]:
    total = sum(c[2] for c in clauses)
    count = sum(c[3] for c in clauses)
    return [1.0, math.log1p(total), math.log1p(count), 1.0 if count >= 2 else 0.0]


def score_texts(texts: list[str | None], g: Grammar, automaton: ahocorasick.Automaton) -> np.ndarray:
    rows = np.array([features(matched_clauses((t or "").lower(), g, automaton)) for t in texts]).reshape(-1, 4)
    return 1.0 / (1.0 + np.exp(-np.clip(rows @ np.array(g.coefficients), -30, 30)))


def learn_lexicon(
    labelled: DataFrame, text: str, label: str, max_entries: int = 5000, min_count: int = 4
) -> tuple[dict[str, tuple[str, float]], dict[str, tuple[str, float]]]:
    """Words and stems whose texts are labelled 1 far more often than others. Counting is
    distributed over the rows given; `max_entries` bounds what is kept."""
    totals = {r[0]: r[1] for r in labelled.groupBy(label).count().collect()}
    ones, zeros = totals.get(1, 0), totals.get(0, 0)
    if not ones or not zeros:
        return {}, {}
    words = F.array_distinct(F.split(F.lower(F.col(text)), r"[^\p{L}]+"))
    per_text = labelled.select(F.col(label).alias("label"), words.alias("words"))
    entries = F.flatten(
        F.array(
            F.transform("words", lambda w: F.concat(F.lit("="), w)),
            *[
                F.array_distinct(
                    F.transform(
                        F.filter("words", lambda w, n=n: F.length(w) >= n), lambda w, n=n: F.substring(w, 1, n)
                    )
                )
                for n in STEM_LENGTHS
            ],
        )
    )
    counted = (
        per_text.select("label", F.explode(entries).alias("entry"))
        .groupBy("entry")
        .agg(F.sum("label").alias("ones"), F.sum(1 - F.col("label")).alias("zeros"))
        .where((F.col("ones") >= min_count) & (F.length("entry") >= 4))
    )
    # A rate of ones well above the base rate, with the zeros smoothed.
    odds = F.log((F.col("ones") + 0.5) / (ones + 1)) - F.log((F.col("zeros") + 0.5) / (zeros + 1))
    kept = (
        counted.withColumn("odds", odds)
        .where((F.col("odds") > math.log(30.0)) & (F.col("ones") > 4 * F.col("zeros")))
        .orderBy(F.desc(F.col("odds") * F.sqrt("ones")), "entry")
        .limit(max_entries)
        .collect()
    )
    top = max((r["odds"] for r in kept), default=1.0)
    found_words = {r["entry"][1:]: (INSULT, r["odds"] / top) for r in kept if r["entry"][0] == "="}
    found_stems = {r["entry"]: (INSULT, r["odds"] / top) for r in kept if r["entry"][0] != "="}
    # A stem stands only where it is worth more than any one word under it.
    support = {r["entry"]: r["ones"] for r in kept}
    stems = {}
    for stem, entry in found_stems.items():
        under = [support.get("=" + w, 0) for w in found_words if w.startswith(stem)]
        if support[stem] > 1.5 * max(under, default=0) and not any(stem.startswith(s) for s in stems if s != stem):
            stems[stem] = entry
    return found_words, stems


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, steps: int = 30) -> tuple[float, ...]:
    """Newton steps on the ridge-penalised logistic loss."""
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 1.0 / (1.0 + np.exp(-np.clip(x @ w, -30, 30)))
        gradient = x.T @ (p - y) + ridge * w
        hessian = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w))
        step = np.linalg.solve(hessian, gradient)
        w -= step
        if np.abs(step).max() < 1e-9:
            break
    return tuple(float(v) for v in w)


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, id_col: str, max_rows: int, seed: int) -> DataFrame:
    """Texts of about `max_rows` labelled rows, chosen by a seeded hash of the id. The chosen
    labels are broadcast: `max_rows` bounds them, and a few sigmas of chance."""
    known = labels.where(F.col(label).isNotNull() & F.col(id_col).isNotNull()).select(id_col, label)
    draw = seeded_hash(seed, F.col(id_col).cast("string")) / F.lit(float(1 << 62))
    chosen = known.where(draw < F.lit(min(1.0, max_rows / max(1, known.count()))))
    return docs.join(F.broadcast(chosen), id_col)


def train(
    docs: DataFrame,
    labels: DataFrame,
    text: str = "text",
    label: str = "toxic",
    id_col: str = "doc_id",
    max_fit_rows: int = 20_000,
    seed: int = 23,
) -> Grammar:
    """Learn lexicon and logistic layer on a bounded sample of about `max_fit_rows` labelled
    rows, whose texts are written once to the shared folder."""
    found = labelled_sample(docs.select(id_col, text), labels, label, id_col, max_fit_rows, seed)
    rows = materialize(found.where(F.col(text).isNotNull()), "toxic-sample")
    words, stems = learn_lexicon(rows, text, label)
    base = default_grammar()
    merged = {w: e for w, e in base.words.items()}
    if words:
        # A learned entry replaces the built-in weight; entries without support keep a little.
        merged = {w: ((tag, 0.25) if tag in (INSULT, THREAT) else (tag, weight)) for w, (tag, weight) in merged.items()}
        for w, e in words.items():
            if w not in merged or merged[w][0] == INSULT:
                merged[w] = e
    grammar = Grammar(merged, stems)
    sample = rows.select(text, label)

    def extract(batch: pa.RecordBatch) -> pa.RecordBatch:
        automaton = grammar.automaton()
        f = [features(matched_clauses((t or "").lower(), grammar, automaton)) for t in batch.column(0).to_pylist()]
        return pa.record_batch(
            [pa.array(f, pa.list_(pa.float64())), batch.column(1).cast(pa.float64())], names=["f", "y"]
        )

    got = map_arrow(sample, extract, "f array<double>, y double").groupBy("f", "y").count().toArrow().to_pydict()
    if not got["y"] or len(set(got["y"])) < 2:
        return grammar
    x = np.repeat(np.array(got["f"]), got["count"], axis=0)
    y = np.repeat(np.array(got["y"]), got["count"])
    return Grammar(merged, stems, fit_logistic(x, y))


def score(df: DataFrame, grammar: Grammar, text: str = "text") -> DataFrame:
    """Add score, predicted, n_clauses to every row; whole texts. The grammar is broadcast;
    its size is bounded by the lexicon's `max_entries`."""
    df = df.drop("score", "predicted", "n_clauses")
    names, at = df.columns, df.columns.index(text)
    shared = df.sparkSession.sparkContext.broadcast(grammar)
    added = [("score", T.DoubleType()), ("predicted", T.IntegerType()), ("n_clauses", T.LongType())]
    schema = T.StructType([*df.schema.fields, *(T.StructField(n, t) for n, t in added)])
    cache: dict[str, ahocorasick.Automaton] = {}

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        g = shared.value
        if "automaton" not in cache:
            cache["automaton"] = g.automaton()
        found = [matched_clauses((t or "").lower(), g, cache["automaton"]) for t in batch.column(at).to_pylist()]
        rows = np.array([features(c) for c in found]).reshape(-1, 4)
        p = 1.0 / (1.0 + np.exp(-np.clip(rows @ np.array(g.coefficients), -30, 30)))
        columns = [batch.column(i) for i in range(len(names))]
        return pa.record_batch(
            [
                *columns,
                pa.array(p),
                pa.array((p >= 0.5).astype(np.int32)),
                pa.array([len(c) for c in found], pa.int64()),
            ],
            names=schema.names,
        )

    return map_arrow(df, run, schema)
