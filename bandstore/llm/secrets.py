"""Secret scans with a battery of randomness tests; DataFrame functions only.

Base spans come from three patterns (assigned values, access keys, hex runs). Further spans
come from candidate tokens, runs of 20 or more characters of the encodings' alphabets that no
base span touches. For each candidate the smallest fitting encoding is inferred (hex, base32,
lower-case letters, letters and digits, base64), and three tests ask how it compares with
uniform draws from that alphabet: chi-squared of the symbol counts, the number of runs of
character classes, and the serial correlation of neighbouring symbols. A token must not
contradict randomness. Against the opposite null, that it is prose, two p-values (a chi-squared
this low although prose is uneven; this many class changes although prose has next to none)
are combined by Fisher's rule. Discoveries are controlled over all candidates of the table by
a weighted Benjamini-Hochberg rule, whose weights grow with the length, as short tokens have
little power. The rule needs one histogram (length class by p-value bin), which is all that
comes to the driver.

Positions are code points, ends exclusive. Match positions follow from the lengths of the
matches and of the pieces between them.

Defined results: a null text is the empty text, without spans; repeated rows are scanned one
by one; an empty table gives an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize

# The base patterns, in the order of kinds.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
KINDS = ("assign", "access", "hex", "random")
CANDIDATE = r"[A-Za-z0-9+/_-]{20,}={0,2}"

# Alphabets of the encodings, and the unevenness of prose over each (its
# chi-squared per character against a uniform alphabet).
ENCODINGS = [
    ("hex", r"^(?:[0-9a-f]+|[0-9A-F]+)$", "0123456789abcdef", 1.6),
    ("base32", r"^[A-Z2-7]+=*$", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", 1.1),
    ("lower", r"^[a-z]+$", "abcdefghijklmnopqrstuvwxyz", 0.75),
    ("alnum", r"^[A-Za-z0-9]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789", 3.1),
    ("base64", r"^[A-Za-z0-9+/_=-]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/", 3.2),
]
PROSE_CHANGES = 0.75
BIN, BINS, LENGTH_CLASSES = 0.25, 400, 12
SPAN = "array<struct<start:bigint,kind_no:int,end:bigint>>"


def _matches(text: Column, pattern: str, group: int = 0) -> Column:
    return F.regexp_extract_all(text, F.lit(pattern), F.lit(group))


def _starts(text: Column, pattern: str, found: Column) -> Column:
    """Start of each match: what lies before it, pieces and matches, summed up."""
    gaps = F.transform(F.split(text, pattern, -1), lambda x: F.length(x).cast("long"))
    sizes = F.transform(found, lambda x: F.length(x).cast("long"))
    steps = F.arrays_zip(F.slice(gaps, 1, F.size(sizes)).alias("gap"), sizes.alias("size"))
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<bigint>").alias("out"))
    return F.aggregate(
        steps,
        start,
        lambda acc, x: F.struct(
            (acc["at"] + x["gap"] + x["size"]).alias("at"),
            F.concat(acc["out"], F.array(acc["at"] + x["gap"])).alias("out"),
        ),
        lambda acc: acc["out"],
    )


def _spans(text: Column, pattern: str, kind_no: int, keep, group: int = 0) -> Column:
    """Spans of the matches that keep(text of the group) accepts; texts without any match of
    the pattern are not searched further."""
    found = _matches(text, pattern)
    parts = F.arrays_zip(
        _starts(text, pattern, found).alias("start"), found.alias("all"), _matches(text, pattern, group).alias("part")
    )
    spans = F.transform(
        F.filter(parts, lambda x: keep(x["part"])),
        lambda x: F.struct(
            x["start"].cast("long").alias("start"),
            F.lit(kind_no).alias("kind_no"),
            (x["start"] + F.length(x["all"])).cast("long").alias("end"),
        ),
    )
    return F.when(text.rlike(pattern), spans).otherwise(F.array().cast(SPAN)).cast(SPAN)


def base_spans(text: Column) -> dict[str, Column]:
    # Runs of the last two patterns are maximal, so their least length can stand in the
    # pattern; a failing assignment still uses up its match, so its length is tested after.
    return {
        "assign": _spans(text, ASSIGN, 0, lambda v: F.length(v) >= 6, 2),
        "access": _spans(text, ACCESS.replace("+", "{16,}"), 1, lambda v: F.length(v) >= 20),
        "hex": _spans(text, HEX.replace("+", "{24,}"), 2, lambda v: F.length(v) >= 24),
    }


def encoding_of(token: Column) -> Column:
    out = F.lit(len(ENCODINGS) - 1)
    for i in reversed(range(len(ENCODINGS))):
        out = F.when(token.rlike(ENCODINGS[i][1]), F.lit(i)).otherwise(out)
    return out


def _of_encoding(no: Column, values: list) -> Column:
    return F.element_at(F.array(*[F.lit(v) for v in values]), no + 1)


def _upper_normal(z: Column) -> Column:
    """Upper tail of the normal law, by a bound-keeping approximation (Chernoff for z > 0)."""
    return F.when(z > 0, F.exp(-(z * z) / 2) / 2).otherwise(1 - F.exp(-(z * z) / 2) / 2)


def battery(token: Column, no: Column) -> dict[str, Column]:
    """Statistics of one token under its inferred encoding."""
    bare = F.rtrim(token, F.lit("="))
    even = F.when(no == 0, F.lower(bare)).otherwise(F.translate(bare, "-_", "+/"))
    alphabet = _of_encoding(no, [e[2] for e in ENCODINGS])
    k = F.length(alphabet).cast("double")
    n = F.length(even).cast("double")
    squares = F.aggregate(
        F.split(alphabet, ""),
        F.lit(0.0),
        lambda s, c: s + F.pow(n - F.length(F.replace(even, c, F.lit(""))), F.lit(2.0)),
    )
    chi = squares * k / n - n
    runs = F.regexp_count(bare, F.lit("[a-z]+|[A-Z]+|[0-9]+|[+/_-]+")).cast("double") - 1
    place = F.transform(F.split(even, ""), lambda c: F.instr(alphabet, c).cast("double") - 1 - (k - 1) / 2)
    shifted = F.arrays_zip(
        F.slice(place, 1, F.greatest(F.size(place) - 1, F.lit(0))).alias("a"),
        F.slice(place, 2, F.greatest(F.size(place) - 1, F.lit(0))).alias("b"),
    )
    product = F.aggregate(shifted, F.lit(0.0), lambda s, x: s + x["a"] * x["b"])
    serial = product / F.sqrt(n - 1) / ((k * k - 1) / 12)
    return {"chi": chi, "changes": runs, "serial": serial, "k": k, "n": n}


def p_values(stats: dict[str, Column], no: Column) -> dict[str, Column]:
    """p_random: of uniform draws; p_prose: of prose, small for secrets."""
    n, k = stats["n"], stats["k"]
    z_chi = (stats["chi"] - (k - 1)) / F.sqrt(2 * (k - 1))
    shares = _of_encoding(no, [_repeat_share(e[0]) for e in ENCODINGS])
    expected = (n - 1) * (1 - shares)
    spread = F.sqrt((n - 1) * shares * (1 - shares) + 0.25)
    z_runs = (stats["changes"] - expected) / spread
    worst = F.greatest(z_chi, F.abs(z_runs), F.abs(stats["serial"]))
    p_random = F.least(F.lit(1.0), 3 * 2 * _upper_normal(worst))
    uneven = n * _of_encoding(no, [e[3] for e in ENCODINGS])
    z_low = ((k - 1 + uneven) - stats["chi"]) / F.sqrt(2 * (k - 1) + 4 * uneven)
    p_chi = _upper_normal(z_low)
    t = stats["changes"]
    p_changes = F.when(
        t > PROSE_CHANGES, F.exp(t - PROSE_CHANGES - t * F.log(t / F.lit(PROSE_CHANGES)))
    ).otherwise(F.lit(1.0))
    x = -2 * (F.log(F.greatest(p_chi, F.lit(1e-40))) + F.log(F.greatest(p_changes, F.lit(1e-40))))
    p_prose = F.exp(-x / 2) * (1 + x / 2)
    return {"p_random": p_random, "p_prose": p_prose}


def _repeat_share(name: str) -> float:
    """Chance that two uniform symbols share their character class."""
    classes = {
        "hex": (10, 6), "base32": (26, 6), "lower": (26,), "alnum": (26, 26, 10), "base64": (26, 26, 10, 2),
    }[name]
    total = sum(classes)
    return sum((c / total) ** 2 for c in classes)


def length_class(n: Column) -> Column:
    """Classes by powers of 1.5 from 20 on."""
    return F.least(F.floor(F.log(n / 20.0) / math.log(1.5)), F.lit(LENGTH_CLASSES - 1)).cast("int")


def candidates(text: Column, base: Column) -> Column:
    """Tested tokens that no base span touches: struct<start, end, class, strength, random>,
    strength = -ln p_prose."""
    found = _matches(text, CANDIDATE)
    zipped = F.arrays_zip(_starts(text, CANDIDATE, found).alias("start"), found.alias("token"))
    free = F.filter(
        zipped,
        lambda x: ~F.exists(
            base, lambda b: (b["start"] < x["start"] + F.length(x["token"])) & (x["start"] < b["end"])
        ),
    )
    numbered = F.transform(
        free, lambda x: F.struct(x["start"].alias("start"), x["token"].alias("token"), encoding_of(x["token"]).alias("no"))
    )

    def tested(x: Column) -> Column:
        stats = battery(x["token"], x["no"])
        return F.struct(
            x["start"].cast("long").alias("start"),
            (x["start"] + F.length(x["token"])).cast("long").alias("end"),
            length_class(stats["n"]).alias("length_class"),
            x["no"].alias("no"),
            stats["chi"].alias("chi"),
            stats["changes"].alias("changes"),
            stats["serial"].alias("serial"),
            stats["k"].alias("k"),
            stats["n"].alias("n"),
        )

    def judged(s: Column) -> Column:
        p = p_values({c: s[c] for c in ("chi", "changes", "serial", "k", "n")}, s["no"])
        return F.struct(
            s["start"].alias("start"),
            s["end"].alias("end"),
            s["length_class"].alias("length_class"),
            F.least(F.floor(-F.log(F.greatest(p["p_prose"], F.lit(1e-43))) / BIN), F.lit(BINS - 1)).cast("int").alias("bin"),
            (p["p_random"] >= F.lit(1e-3)).alias("random"),
        )

    kind = "array<struct<start:bigint,end:bigint,length_class:int,bin:int,random:boolean>>"
    return (
        F.when(text.rlike(CANDIDATE), F.transform(F.transform(numbered, tested), judged))
        .otherwise(F.array().cast(kind))
        .cast(kind)
    )


def discovery_bins(histogram: list[tuple[int, int, int]], q: float) -> dict[int, int]:
    """Weighted Benjamini-Hochberg over binned p-values: the least bin of each length class
    that is discovered. histogram: (length class, bin, count) of all candidates."""
    total = sum(c for _, _, c in histogram)
    if not total:
        return {}
    raw = {k: 1.5**k for k in range(LENGTH_CLASSES)}
    mean = sum(raw[k] * c for k, _, c in histogram) / total
    weight = {k: raw[k] / mean for k in raw}
    # A binned p-value counts as the upper end of its bin; its weighted value is p / weight.
    points = sorted((math.exp(-b * BIN) / weight[k], k, b, c) for k, b, c in histogram)
    passed, best = 0, 0.0
    for value, _, _, c in points:
        passed += c
        if value <= q * passed / total:
            best = value
    out: dict[int, int] = {}
    for value, k, b, _ in points:
        if value <= best:
            out[k] = min(out.get(k, BINS), b)
    return out


def scan(df: DataFrame, text: str = "text", id_col: str = "doc_id", q: float = 0.001) -> DataFrame:
    """(id, assign, access, hex, random): arrays of spans of each row. What the first pass
    finds is written to the shared folder (no texts), the discovery rule is set by one
    histogram of it, and the second pass only filters."""
    t = F.coalesce(F.col(text), F.lit(""))
    first = df.select(F.col(id_col).alias("doc_id"), t.alias("t")).select("doc_id", "t", *[c.alias(k) for k, c in base_spans(F.col("t")).items()])
    first = first.withColumn("tests", candidates(F.col("t"), F.concat("assign", "access", "hex"))).drop("t")
    kept = materialize(first, "secrets")
    bins = (
        kept.select(F.explode("tests").alias("x"))
        .groupBy("x.length_class", "x.bin")
        .agg(F.count(F.lit(1)).alias("n"))
        .collect()
    )
    least = discovery_bins([(r["length_class"], r["bin"], r["n"]) for r in bins], q)
    rule = F.array(*[F.lit(least.get(k, BINS)) for k in range(LENGTH_CLASSES)])
    chosen = F.filter("tests", lambda x: x["random"] & (x["bin"] >= F.element_at(rule, x["length_class"] + 1)))
    random = F.transform(
        chosen, lambda x: F.struct(x["start"].alias("start"), F.lit(3).alias("kind_no"), x["end"].alias("end"))
    ).cast(SPAN)
    return kept.select("doc_id", "assign", "access", "hex", random.alias("random"))


def joined(spans: Column) -> Column:
    """kind:start:end by start, then kind, comma-joined."""
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(
        F.transform(
            F.array_sort(spans),
            lambda x: F.concat_ws(":", F.element_at(names, x["kind_no"] + 1), x["start"].cast("string"), x["end"].cast("string")),
        ),
        ",",
    )


def report(found: DataFrame) -> DataFrame:
    base = F.concat("assign", "access", "hex")
    return found.select(
        "doc_id",
        F.size("assign").cast("long").alias("n_assign"),
        F.size("access").cast("long").alias("n_access"),
        F.size("hex").cast("long").alias("n_hex"),
        F.size("random").cast("long").alias("n_random"),
        F.sha2(joined(base), 256).alias("base_sha256"),
        joined(F.concat(base, F.col("random"))).alias("spans"),
    )
