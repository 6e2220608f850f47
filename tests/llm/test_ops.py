"""Each operator against brute force on small inputs, with odd rows: null and empty texts,
ties, repeated rows, empty tables, extra columns with clashing names."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from bandstore.llm import decontaminate, fingerprints, language_id, licenses, mixing, near_dup, queries, secrets, sharding, shingles, toxicity, url_filter

SF = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet").cache()


@pytest.fixture(scope="module")
def texts(docs):
    return {r["doc_id"]: r["text"] for r in docs.collect()}


@pytest.fixture(scope="module")
def odd(spark):
    """Odd rows, with columns named like the operators' own."""
    rng = random.Random(1)
    words = ["alpha", "beta", "gamma", "delta", "idiot", "the", "not", "you"]
    long = " ".join(rng.choice(words) for _ in range(20000))
    data = [
        (1, None, None, "a"), (2, "", "en", "a"), (3, "   \n\t", "en", None), (4, "12345 !!", "de", "b"), (5, long, "en", "a"),
        (5, long, "en", "a"), (6, "x", None, "b"), (None, "you are an idiot. truly you idiot", "en", "a"), (7, "x", "en", ""),
    ]
    rows = [(i, t, lang, s, len(t or ""), 0.5, "p", 1, 2) for i, t, lang, s in data]
    return spark.createDataFrame(rows, DOCS + ", score double, lang_pred string, shard int, fingerprint int").cache()


def plain(df):
    return [r.asDict(recursive=True) for r in df.collect()]


# ---- 1 language ID


def test_language_model_is_ppm():
    """Code lengths by hand: order-2 model of one language."""
    model = language_id.compile_model(["a"] * 3, [(0 << 24) | (0 << 16) | (0 << 8) | 97, 97 << 0 | 97 << 8, 97 | 97 << 8 | 97 << 16], [1, 1, 1], 100)
    assert model.languages == ["a"]
    got = model.code_lengths([b"aaa"])[0, 0]
    # Every context has one symbol seen once: 1 of 1 + 1.
    assert got == pytest.approx(3 * np.log(2), rel=1e-5)


def test_code_lengths_against_direct_prediction(spark):
    """Context trees counted from the texts, walked byte by byte with escapes."""
    rng = random.Random(2)
    texts = [("ab"[i % 2], "".join(rng.choice("abcde "[: 3 + 3 * (i % 2)]) for _ in range(rng.randrange(1, 40)))) for i in range(12)]
    df = spark.createDataFrame([(i, t, x) for i, (x, t) in enumerate(texts)], "doc_id long, text string, lang string")
    model = language_id.train(df)
    tree = defaultdict(Counter)
    symbols = {c: i for i, c in enumerate(sorted({c for _, t in texts for c in t}))}
    for language, t in texts:
        padded = "\0\0\0" + t
        for i in range(3, len(padded)):
            for order in range(4):
                tree[language, padded[i - order : i]][padded[i]] += 1

    def direct(language, text):
        padded, total = "\0\0\0" + text, 0.0
        for i in range(3, len(padded)):
            for order in (3, 2, 1, 0):
                seen = tree.get((language, padded[i - order : i]))
                if seen is None:
                    continue
                n = sum(seen.values()) + len(seen)
                if padded[i] in seen:
                    total += np.log(n / seen[padded[i]])
                    break
                total += np.log(n / len(seen))
            else:
                total += np.log(len(symbols) + 2)
        return total

    probes = ["abc", "edcba ab", "", "aaaa", " a e", "cabbage"]
    got = model.code_lengths([p.encode() for p in probes])
    assert model.languages == ["a", "b"]
    for p, row in zip(probes, got):
        assert row == pytest.approx([direct(x, p) for x in "ab"], rel=1e-4, abs=1e-6)


def test_language_id_held_out(spark, docs):
    got = plain(queries.op1_language_id(spark, SF))
    lang = {r["doc_id"]: r["lang"] for r in docs.collect()}
    held = [r for r in got if r["held_out"]]
    assert len(got) == len(lang) and sum(r["lang_pred"] == lang[r["doc_id"]] for r in held) >= 0.95 * len(held)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in got)
    assert all(0 <= r["score"] <= 1 for r in got)


def test_language_id_odd_rows(docs, odd):
    model = language_id.train(docs)
    got = plain(language_id.identify(odd, model))
    assert len(got) == odd.count()
    for r in got:
        if not any(c.isalpha() for c in r["text"] or ""):
            assert (r["lang_pred"], r["score"]) == ("und", 0.0)
    none = language_id.train(docs.limit(0))
    assert {r["lang_pred"] for r in plain(language_id.identify(odd, none))} == {"und"}
    assert language_id.identify(docs.limit(0), model).count() == 0


def test_long_texts_go_by_pieces(docs):
    model = language_id.train(docs)
    text = ("Das ist und der nicht. " * 3000).encode()
    whole, cut = model.code_lengths([text]), model.code_lengths([text], chunk=1000)
    assert np.allclose(whole, cut, rtol=1e-5)


# ---- 2 toxicity


def test_grammar_scores_clauses():
    g = toxicity.default_grammar()
    a = g.automaton()
    weight = lambda t: sum(c[2] for c in toxicity.matched_clauses(t.lower(), g, a))
    assert weight("you are an idiot") > weight("an idiot") > 0
    assert weight("you are not an idiot") < weight("you are an idiot")
    assert weight('he said "you are an idiot"') < weight("you are an idiot")
    assert weight("a fine day. idiots' lane") > 0 and weight("idiotic idiotx") == 0
    assert weight("i will kill you") > weight("kill the lights")
    assert len(toxicity.matched_clauses("idiot. fine. moron, you", g, a)) == 2
    assert toxicity.matched_clauses("", g, a) == []


def test_composed_machine_is_its_parts():
    """Random clauses: the composed machine against each transducer run by itself."""
    rng = random.Random(4)
    for g in (toxicity.default_grammar(), toxicity.Grammar({}, {}, target_gain=2.0, negation_loss=0.1, report_loss=0.3)):
        assert len(g.machine.last) == 16  # threats and targets move together
        for _ in range(500):
            clause = [(rng.choice(toxicity.TAGS[:-1]), rng.random()) for _ in range(rng.randrange(12))]
            quoted = rng.random() < 0.3
            tags = ([toxicity.QUOTE] if quoted else []) + [t for t, _ in clause]
            weights = ([0.0] if quoted else []) + [w if t in (toxicity.INSULT, toxicity.THREAT) else 0.0 for t, w in clause]
            paths = []
            for part in g.parts():
                state, gains = 0, []
                for t in tags:
                    gains.append(part.gain[state].get(t, 1.0))
                    state = part.after[state].get(t, state)
                paths.append((gains, part.last[state]))
            want = sum(w * np.prod([gains[i] for gains, _ in paths]) for i, w in enumerate(weights)) * np.prod([last for _, last in paths])
            hits = sum(t in (toxicity.INSULT, toxicity.THREAT) for t in tags)
            assert toxicity.clause_weight(clause, quoted, g) == (pytest.approx(want), hits)


def test_clauses_are_read_whole():
    """Targets, reports and quotation marks count however far from the hit they are."""
    g = toxicity.default_grammar()
    a = g.automaton()
    weight = lambda t: sum(c[2] for c in toxicity.matched_clauses(t.lower(), g, a))
    for far in ("", "word " * 30, "word " * 3000):
        assert weight(f"idiot {far}you") == pytest.approx(weight("idiot") * g.target_gain)
        assert weight(f"you {far}idiot {far}") == pytest.approx(weight("idiot") * g.target_gain)
        assert weight(f'"{far}idiot') == pytest.approx(weight("idiot") * g.report_loss)
        assert weight(f"idiot {far}said") == pytest.approx(weight("idiot") * g.report_loss)
        assert weight(f"you {far}kill") == pytest.approx(weight("you kill"))


def test_toxicity_held_out(spark):
    got = {r["doc_id"]: r for r in plain(queries.op2_toxicity(spark, "/root/testdata/sf0.01"))}
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet").collect()
    held = [r for r in labels if got[r["doc_id"]]["held_out"]]
    assert sum(got[r["doc_id"]]["predicted"] == r["toxic"] for r in held) >= 0.9 * len(held)
    assert all(r["predicted"] == int(r["score"] >= 0.5) and 0 <= r["score"] <= 1 for r in got.values())


def test_toxicity_odd_rows(spark, odd):
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    g = toxicity.train(odd, labels)
    got = plain(toxicity.score(odd, g))
    assert len(got) == odd.count() and all(r["score"] is not None for r in got)


# ---- 3 mixing


def brute_targets(size_of):
    names = sorted(size_of, key=lambda s: (s is None, s or ""))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    left, active, out = float(sum(size_of.values())), set(names), {}
    while active:
        w = sum(weight[s] for s in active)
        over = {s for s in active if left * weight[s] / w > 3 * size_of[s]}
        if not over:
            return out | {s: left * weight[s] / w for s in active}
        out |= {s: 3.0 * size_of[s] for s in over}
        left -= sum(3.0 * size_of[s] for s in over)
        active -= over
    return out


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_mixing(docs, odd, which):
    df = {"docs": docs, "odd": odd}[which]
    mixed, mix = mixing.mix_sources(df)
    got = plain(mixed)
    size_of, taken = defaultdict(int), defaultdict(int)
    for r in got:
        size_of[r["source"]] += r["size"]
        taken[r["source"]] += r["taken"]
        assert 0 <= r["taken"] <= 3 * r["size"]
    want = brute_targets(size_of)
    assert sum(size_of.values()) == sum(len(WORD.findall(r["text"] or "")) for r in df.collect())
    for s, t in want.items():
        assert mix.targets[s] == pytest.approx(t) and abs(taken[s] - t) <= 2 + df.count() * 0.01
    again = plain(mixing.mix_sources(df)[0])
    key = lambda r: (str(r["doc_id"]), r["size"], r["taken"])
    assert sorted(map(key, again)) == sorted(map(key, got))
    assert mixing.mix_sources(df.limit(0))[0].count() == 0


def test_flow_prefers_fresh_and_shares_overlap():
    flows = mixing.min_cost_flow([[10] * 3, [10] * 3, [10] * 3], [15, 15], [[0], [1], [0, 1]], [0, 1, 4])
    assert sum(flows[0].values()) == 10 and sum(flows[1].values()) == 10 and sum(flows[2].values()) == 10
    flows = mixing.min_cost_flow([[10] * 3], [25], [[0]], [0, 1, 4])
    assert flows == [{0: 25}]
    assert mixing.min_cost_flow([[10] * 3], [99], [[0]], [0, 1, 4]) == [{0: 30}]


def test_overlapping_membership(spark):
    rows = [(i, "w " * 10, "a", ["a"] if i < 5 else ["a", "b"]) for i in range(10)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, held array<string>")
    targets = lambda sizes: {"a": 50.0, "b": 50.0}
    mixed, mix = mixing.mix_sources(df, targets, membership="held")
    assert sum(r["taken"] for r in plain(mixed)) == 100 and all(r["taken"] == 10 for r in plain(mixed))


def test_sources_and_memberships_of_any_name(spark):
    """A source that holds a separator, null among sources, and columns named like the step's own."""
    rows = [(i, "w " * 10, s, h) for i, (s, h) in enumerate([("a\x1fb", ["a\x1fb"]), ("a", ["a", None]), (None, [None]), ("b", []), ('"q', None)] * 4)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, held array<string>")
    for membership in (None, "held"):
        mixed, mix = mixing.mix_sources(df, lambda sizes: {s: float(n) for s, n in sizes.items()}, membership=membership)
        got = plain(mixed)
        assert len(got) == 20 and set(mix.sources) == ({"a\x1fb", "a", None, "b", '"q'} if membership is None else {"a\x1fb", "a", None})
        assert all(r["taken"] >= 10 for r in got if membership is None)
    names = ["mix_size", "mix_h", "mix_key", "row", "taken", "mix_copy"]
    clashing = df.select("doc_id", "text", "source", *[F.lit(f"own {n}").alias(n) for n in names])
    got = plain(mixing.repeat_documents(clashing))
    assert got and all(r[n] == f"own {n}" for r in got for n in names)


def test_clashing_columns_stay(spark, odd):
    names = ["place", "place_", "shuffle_hash", "shuffle_bucket", "row", "id", "key", "doc_id_", "text_key", "leak_key", "near_key", "has_letter"]
    df = odd.select("doc_id", "text", "source", *[F.lit(f"own {n}").alias(n) for n in names])
    bench = spark.createDataFrame([(1, "one two three four five six seven")], "item_id long, text string")
    for got in (
        sharding.shard_documents(df, 4), decontaminate.remove_contaminated(df, bench), near_dup.drop_near_duplicates(df),
        language_id.identify(df, language_id.train(df.withColumn("lang", F.lit("xx")))), toxicity.score(df, toxicity.default_grammar()),
        fingerprints.fingerprints(df), licenses.scan(df), mixing.repeat_documents(df),
    ):
        found = plain(got)
        assert found and all(r[n] == f"own {n}" for r in found for n in names)
    pages = spark.createDataFrame([(1, "http://x.net/a", "mine", "kept")], "page_id long, url string, probe string, blocks string")
    listed = spark.createDataFrame(queries.URL_RULES, "verdict string, host string, path string")
    (r,) = plain(url_filter.judge(pages, listed))
    assert (r["probe"], r["blocks"], r["verdict"]) == ("mine", "kept", "block")


def test_repeat_documents_keeps_columns(docs):
    got = mixing.repeat_documents(docs)
    assert got.columns == docs.columns
    most = got.groupBy("doc_id").count().agg(F.max("count")).first()[0]
    assert 1 <= most <= 3


# ---- 4 fingerprints


def test_fingerprint_is_a_multiset_hash():
    a, b, c = "one first line", "a second line", "and a third"
    f = fingerprints.fingerprint
    assert (f(f"{a}\n{b}\n{c}") == f(f"{c}\n{a}\n{b}")).all()
    assert not (f(f"{a}\n{b}") == f(f"{a}\n{b}\n{b}")).all()
    assert (fingerprints.insert(f(f"{a}\n{b}"), [c]) == f(f"{a}\n{b}\n{c}")).all()
    assert (fingerprints.delete(f(f"{a}\n{b}\n{c}"), [b]) == f(f"{a}\n{c}")).all()
    assert (fingerprints.parse(fingerprints.digest(f(a))) == f(a)).all()
    assert fingerprints.likeness(f(""), f(None)) == 1.0 and fingerprints.likeness(f(a), f("")) == 0.0


@pytest.mark.parametrize("n_ranges", [1, 4])
def test_edit_report(docs, texts, n_ranges):
    got = {r["doc_id"]: r for r in plain(fingerprints.edit_report(docs, n_ranges=n_ranges))}
    ids = sorted(texts, reverse=True)
    better = 0
    for a, b in zip(ids, ids[1:] + ids[:1]):
        t, o, r = texts[a], texts[b], got[a]
        n = len(t) // 3
        edited = t[: len(t) - n] + o[:n]
        assert r["n_chars"] == len(t) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert r["fingerprint"] == fingerprints.digest(fingerprints.fingerprint(t))
        better += r["near_edited"] > r["near_next"]
    assert len(got) == len(ids) and better > 0.95 * len(ids)


def test_many_ranges_are_exact(spark):
    """Ids beyond what doubles tell apart, null among them, over more ranges than rows."""
    ids = [2**60 + i for i in range(300)] + [None, -5, 7]
    df = spark.createDataFrame([(i, f"text {i}") for i in ids], "doc_id long, text string")
    order = sorted(ids, key=lambda i: (i is None, -(i or 0)))
    want = {a: hashlib.sha256(fingerprints.edited_text(f"text {a}", f"text {b}").encode()).hexdigest() for a, b in zip(order, order[1:] + order[:1])}
    for n in (1, 40, 700):
        assert {r["doc_id"]: r["edited_sha256"] for r in plain(fingerprints.edit_report(df, n_ranges=n))} == want


def test_edit_report_odd_rows(odd):
    got = plain(fingerprints.edit_report(odd, n_ranges=3))
    assert len(got) == odd.count() and sorted(str(r["doc_id"]) for r in got) == sorted(str(r["doc_id"]) for r in odd.collect())
    assert fingerprints.edit_report(odd.limit(0)).count() == 0
    one = plain(fingerprints.edit_report(odd.where("doc_id = 6")))
    assert len(one) == 1 and one[0]["near_next"] == 1.0
    assert fingerprints.fingerprints(odd).where("fingerprint is null").count() == 0


def test_fingerprint_of_long_repetitive_text():
    """Tens of thousands of equal paragraphs: likeness is the cosine of the unwrapped sums."""
    line = "the same line of about sixty characters again and once more here"
    text = f"{line}\n" * 30000
    edited = fingerprints.edited_text(text, "another line, with other words and of another length\n" * 20000)
    sums = []
    for t in (text, edited):
        counts = defaultdict(int)
        for p in fingerprints.paragraphs(t):
            counts[p] += 1
        sums.append(sum(n * fingerprints.vectors([p])[0].astype(float) for p, n in counts.items()))
    x, y = sums
    want = (x @ y) / ((x @ x) * (y @ y)) ** 0.5
    a, b = fingerprints.fingerprint(text), fingerprints.fingerprint(edited)
    assert abs(a).max() > 1 << 15 and (a == x).all() and (b == y).all()
    assert want > 0.5 and abs(fingerprints.likeness(a, b) - want) < 1e-9
    assert (fingerprints.delete(a, fingerprints.paragraphs(text)) == 0).all()


# ---- 5 sharding


def test_sharding(spark, docs, texts):
    got = plain(queries.op5_sharding(spark, SF))
    by = defaultdict(list)
    for r in got:
        by[r["shard"]].append(r["slot"])
        raw = texts[r["doc_id"]].encode()
        assert (r["size"], r["text_crc32"]) == (len(raw) + 1, zlib.crc32(raw))
    assert set(by) == set(range(16)) and max(map(len, by.values())) - min(map(len, by.values())) <= 1
    assert all(sorted(s) == list(range(len(s))) for s in by.values())
    again = {(r["doc_id"], r["shard"], r["slot"]) for r in plain(queries.op5_sharding(spark, SF))}
    assert again == {(r["doc_id"], r["shard"], r["slot"]) for r in got}


@pytest.mark.parametrize("n", [0, 3, 9])
def test_sharding_odd_rows(odd, n):
    got = plain(sharding.shard_documents(odd.limit(n), n_shards=4))
    places = sorted((r["shard"], r["slot"]) for r in got)
    assert len(set(places)) == len(got) == min(n, odd.count())


def test_write_shards(spark, docs, tmp_path):
    sharding.write_shards(sharding.shard_documents(docs), str(tmp_path / "s"))
    assert spark.read.parquet(str(tmp_path / "s")).count() == docs.count()


# ---- 6 secrets


def brute_spans(text):
    text = text or ""
    assign = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
    out = [(m.start(), 0, m.end()) for m in assign.finditer(text) if len(m.group(2)) >= 6]
    out += [(m.start(), 1, m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", text) if m.end() - m.start() >= 20]
    out += [(m.start(), 2, m.end()) for m in re.finditer(r"[0-9a-f]+", text) if m.end() - m.start() >= 24]
    return ",".join(f"{('assign', 'access', 'hex')[k]}:{a}:{b}" for a, k, b in sorted(out))


HARD = [
    None, "", "token: abc", "secret=token: abcdef", 'é password = "hunter22" and API_KEY:\'x.y=z/1\'', "AKIA" + "A" * 15 + " AKIA" + "B" * 16,
    "deadbeef" * 3 + "g" + "0" * 23 + " " + "0" * 24, "pässwörter 😀 token=abcdef😀", "PASSWD:::aaaaaaa", "x" * 50, "secret  = = abcdefgh",
]


def test_secrets_base_spans(spark, docs):
    rows = spark.createDataFrame(list(enumerate(HARD)), "doc_id long, text string").unionByName(
        docs.select((F.col("doc_id") + 1000).alias("doc_id"), "text")
    )
    got = {r["doc_id"]: r for r in plain(secrets.report(secrets.scan(rows)))}
    for r in rows.collect():
        want = brute_spans(r["text"])
        assert got[r["doc_id"]]["base_sha256"] == hashlib.sha256(want.encode()).hexdigest(), r["text"]
        base = [x for x in got[r["doc_id"]]["spans"].split(",") if x and not x.startswith("random")]
        assert ",".join(base) == want


def test_secrets_randomness(spark):
    rng = random.Random(4)
    alphabet = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    keys = ["".join(rng.choice(alphabet) for _ in range(40)) for _ in range(60)]
    prose = ["internationalization" + w + "andsoonforeverthing" for w in ("er", "ation", "est", "ing", "ness") for _ in range(12)]
    rows = spark.createDataFrame([(i, f"see {t} there") for i, t in enumerate(keys + prose)], "doc_id long, text string")
    got = {r["doc_id"]: r["n_random"] for r in plain(secrets.report(secrets.scan(rows)))}
    assert sum(got[i] for i in range(60)) >= 50 and sum(got[i] for i in range(60, 120)) == 0


def test_discovery_control():
    assert secrets.discovery_bins([], 0.01) == {}
    found = secrets.discovery_bins([(0, 0, 900), (0, 100, 10), (3, 60, 5)], 0.01)
    assert found[0] == 100 and found[3] == 60


# ---- 7 URLs


def brute_verdict(url):
    rules = [("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/")]
    m = re.search(r"://([^/?#]*)([^?#]*)", url or "")
    host, path = ("", "") if not m else ("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in m[1]), m[2])
    fits = [(len(h + p), h + p, v) for v, h, p in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
    best = max(fits, default=None)
    return host, path, best and best[1], best[2] if best else "allow"


URLS = [
    None, "", "no scheme", "http://", "http://NET/", "https://a.b.Net/x", "http://net", "http://xnet/", "http://www.example.net/en/1?x#y", "http://example.net/en",
    "ftp://Ä.org/fr/", "http://example.com/de/#t", "http://example.com.org/fr/a", "a://b://c.net/", "http://u.net?/en/", "http://..net/", "http://example.com/de/", "http://example.com/de/",
]


def test_url_filter(spark):
    pages = spark.createDataFrame([(i, u, "h") for i, u in enumerate(URLS)], "page_id long, url string, host string")
    listed = spark.createDataFrame(queries.URL_RULES, "verdict string, host string, path string")
    for literal in (8192, 0):  # the filter as a literal, and as a joined table
        url_filter.LITERAL_WORDS, before = literal, url_filter.LITERAL_WORDS
        try:
            got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in plain(url_filter.judge(pages, listed))}
        finally:
            url_filter.LITERAL_WORDS = before
        assert got == {i: brute_verdict(u) for i, u in enumerate(URLS)}
    assert url_filter.judge(pages, listed.limit(0)).where("verdict <> 'allow'").count() == 0
    assert url_filter.judge(pages.limit(0), listed).count() == 0


# ---- 8 decontamination


def brute_leaks(texts, items):
    norm = lambda t: [w for w in re.split(r"[^\w]+|_", (t or "").lower()) if w]
    wanted = [(i, " " + " ".join(norm(t)) + " ") for i, t in items if len(norm(t)) >= 5]
    return {(d, i) for d, t in texts for i, w in wanted if w in " " + " ".join(norm(t)) + " "}


def test_decontamination(spark, docs, texts):
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    got = {(r["doc_id"], r["item_id"]) for r in plain(queries.op8_decontamination(spark, SF))}
    assert got == brute_leaks(texts.items(), items)


def weighted_similarity(a, b):
    count = lambda w: Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    x, y = count(a), count(b)
    letters = lambda s: sum(map(len, s))
    least = sum(letters(s) * min(x[s], y[s]) for s in x | y)
    return least / max(1, sum(letters(s) * max(x[s], y[s]) for s in x | y))


def test_decontamination_recall(spark):
    """Edited items in other text, against all windows of the items' sizes."""
    rng = random.Random(12)
    items = {r["item_id"]: re.findall(r"[^\W_]+", r["text"].lower()) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()}
    rows, want = [], set()
    for item, words in items.items():
        for k in range(10):
            edited = list(words)
            for at in rng.sample([0, 1, len(words) - 1, len(words) - 2, rng.randrange(len(words))], 1 + k % 3):
                edited[at] = rng.choice(["x", "longreplacementword", "abc"])
            if k % 4 == 0:
                del edited[rng.randrange(len(edited))]
            around = [f"f{rng.randrange(10**6)}" for _ in range(40)]
            text = around[:20] + edited + around[20:]
            n = len(words)
            if max(weighted_similarity(text[i : i + n], words) for i in range(len(text) - n + 1)) >= 0.8:
                want.add((len(rows), item))
            rows.append((len(rows), " ".join(text)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in plain(decontaminate.contaminated(docs, spark.read.parquet(f"{SF}/benchmark.parquet")))}
    assert len(want) > 100 and got <= want and len(got) >= 0.95 * len(want)


def test_decontamination_near_and_odd(spark, odd):
    item = " ".join(f"word{i}" for i in range(40))
    changed = item.replace("word39", "other").replace("word0 ", "Another ")
    far = item.replace("word20", "z").replace("word10", "z").replace("word30", "z")
    rows = [(1, f"before {item.upper()} after"), (2, f"{changed}"), (3, far), (4, None), (5, ""), (6, item), (6, item)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    bench = spark.createDataFrame([(1, item), (2, "too short"), (3, None)], "item_id long, text string")
    assert {r["doc_id"] for r in plain(decontaminate.contaminated(docs, bench))} == {1, 2, 6}
    assert {r["doc_id"] for r in plain(decontaminate.remove_contaminated(docs, bench))} == {3, 4, 5}
    assert decontaminate.remove_contaminated(odd, bench).count() == odd.count()
    assert decontaminate.contaminated(docs, bench.limit(0)).count() == 0
    assert decontaminate.contaminated(docs.limit(0), bench).count() == 0


# ---- 9 near duplicates


def brute_components(rows, width, percent):
    def shingles(t):
        t = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")
        w = WORD.findall(t)
        return frozenset(tuple(w[i : i + width]) for i in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else [])

    sets = {d: shingles(t) for d, t in rows}
    parent = {d: d for d in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            x, y = sets[a], sets[b]
            if x and y and 100 * len(x & y) >= percent * len(x | y):
                p, q = find(a), find(b)
                parent[max(p, q)] = min(p, q)
    return {d: (len(sets[d]), find(d)) for d in sets}


def test_near_dup_on_documents(docs, texts):
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in plain(near_dup.components(docs))}
    assert got == brute_components(texts.items(), 3, 85)


def test_near_dup_large_groups(spark, monkeypatch):
    """Groups around the threshold, with lists forced to be long."""
    rng = random.Random(3)
    vocabulary = [f"w{i}" for i in range(5000)]
    rows, n = [], 0
    for group in range(3):
        base = [rng.choice(vocabulary) for _ in range(90)]
        for _ in range(40):
            words = list(base)
            for _ in range(rng.choice([0, 1, 2, 3, 4, 6])):
                words[rng.randrange(90)] = rng.choice(vocabulary)
            rows.append((n, " ".join(words)))
            n += 1
    for t in (None, "", "a", "A", "a b", "A B", "one two three"):
        rows.append((n, t))
        n += 1
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute_components(rows, 3, 85)
    for block in (8, near_dup.BLOCK):
        monkeypatch.setattr(near_dup, "BLOCK", block)
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in plain(near_dup.components(df))}
        assert got == want


def test_near_dup_odd_rows(odd):
    got = plain(near_dup.components(odd))
    assert len(got) == odd.count()
    by = {(r["doc_id"], r["n_shingles"]): r for r in got}
    assert by[(6, 1)]["component_id"] == 6 and by[(7, 1)]["component_id"] == 6 and not by[(7, 1)]["kept"]
    assert near_dup.components(odd.limit(0)).count() == 0
    kept = plain(near_dup.drop_near_duplicates(odd, width=3, percent=85))
    assert sorted(str(r["doc_id"]) for r in kept) == ["1", "2", "3", "4", "5", "6", "None"]


# ---- 10 licenses


def test_alignment():
    assert licenses.longest_increasing([5, 1, 2, 9, 3, 4]) == [1, 2, 4, 5]
    a = "x x the quick fox jumps over the lazy dog y".split()
    b = "the quick brown fox jumps over a lazy dog".split()
    pairs = licenses.align(a, b)
    assert [a[i] for i, _ in pairs] == [b[j] for _, j in pairs] == "the quick fox jumps over lazy dog".split()


def test_longest_increasing_is_longest():
    rng = random.Random(6)
    for _ in range(300):
        values = [rng.randrange(12) for _ in range(rng.randrange(12))]
        best = [1] * len(values)
        for i in range(len(values)):
            best[i] += max((best[j] for j in range(i) if values[j] < values[i]), default=0)
        got = [values[i] for i in licenses.longest_increasing(values)]
        assert got == sorted(set(got)) and len(got) == max(best, default=0)


def test_license_scan(spark, odd):
    full = licenses.TEMPLATES["mit"]
    dropped = " ".join(w for i, w in enumerate(full.split()) if i % 12)
    rows = [(1, "intro words " * 50 + full + " outro " * 80), (2, dropped), (3, "Released under the MIT License."), (4, None), (5, ""), (6, "a license to the bank of the river")]
    got = {r["doc_id"]: r for r in plain(licenses.scan(spark.createDataFrame(rows, "doc_id long, text string")))}
    assert [got[i]["license"] for i in range(1, 7)] == ["mit", "mit", "mit-line", None, None, None]
    assert got[1]["coverage"] == 1.0 and 0.8 <= got[2]["coverage"] < 1 and got[4]["coverage"] == 0.0
    assert licenses.scan(odd).count() == odd.count() and licenses.scan(odd.limit(0)).count() == 0


def test_repeated_notices(spark):
    """A notice that occurs again near itself is found, each time, beside those of other templates."""
    line = "Released under the MIT License."
    full, bsd = licenses.TEMPLATES["mit"], licenses.TEMPLATES["bsd-2-clause"]
    edited = full.replace("free of charge, ", "").replace("including without limitation", "with")
    rows = [
        (1, f"foo bar {line} lorem ipsum. {line} dolor sit."),
        (2, f"{full} {full} {full}"),
        (3, f"A notice. {edited} Another. {edited} Third. {full} {bsd} {bsd} {line}"),
        (4, f"{line} " * 500),
    ]
    got = {r["doc_id"]: r for r in plain(licenses.scan(spark.createDataFrame(rows, "doc_id long, text string")))}
    assert [(got[i]["license"], got[i]["coverage"]) for i in range(1, 5)] == [("mit-line", 1.0), ("mit", 1.0), ("bsd-2-clause", 1.0), ("mit-line", 1.0)]
    names = {i: [x["license"] for x in r["notices"] if x["coverage"] == 1 or x["matched_words"] > 20] for i, r in got.items()}
    assert names[1] == ["mit-line"] * 2 and names[2] == ["mit"] * 3 and names[4] == ["mit-line"] * 500
    assert names[3] == ["mit"] * 3 + ["bsd-2-clause"] * 2 + ["mit-line"]
    n = len(licenses.words_of(full))
    assert [(x["first_word"], x["end_word"]) for x in got[2]["notices"]] == [(0, n), (n, 2 * n), (2 * n, 3 * n)]


def test_license_lines_in_documents(spark, texts):
    got = {r["doc_id"]: r["license"] for r in plain(queries.op10_licenses(spark, SF))}
    for d, t in texts.items():
        if "Released under the MIT License." in t:
            assert got[d] == "mit-line"
        elif "icense" not in t:
            assert got[d] is None


def test_near_dup_sketches_lose_no_link():
    rng = np.random.default_rng(5)
    for size in (1, 7, 90, 3000):
        base = np.unique(rng.integers(0, 1 << 63, size, dtype=np.int64).view(np.uint64))
        for changed in range(0, size + 1, max(1, size // 12)):
            new = rng.integers(0, 1 << 63, changed, dtype=np.int64).view(np.uint64)
            other = np.unique(np.concatenate([base[changed:], new]))
            common = len(np.intersect1d(base, other))
            linked = 100 * common >= 85 * (len(base) + len(other) - common)
            x, y = (np.frombuffer(near_dup.sketch(s), np.uint64)[None, :] for s in (base, other))
            assert not linked or near_dup.may_link(x, y, np.array([len(base)]), np.array([len(other)]), 85)[0]


def test_least_collisions_follow_the_threshold():
    for percent, want in ((80, 34), (85, 39), (100, 64)):
        assert near_dup.matches_for(percent) == want
    rng = np.random.default_rng(7)
    counts = rng.binomial(64, 0.8, 200_000)
    assert (counts < near_dup.matches_for(80)).sum() <= 3


def test_pairs_with_few_collisions_are_linked(spark):
    """Pairs at 80 percent that agree on few more coordinates than the least."""
    rows = []
    for seed in range(10**5):
        rng = random.Random(seed)
        words = [f"w{rng.randrange(10**6)}" for _ in range(120)]
        other = words[:]
        other[20], other[60], other[-2] = "x", "y", "z"
        x, y = (near_dup.signature(s) for s in near_dup.all_shingles([" ".join(words).encode(), " ".join(other).encode()], 5))
        if (x == y).sum() <= 41:
            rows += [(2 * seed, " ".join(words)), (2 * seed + 1, " ".join(other))]
            if len(rows) == 4:
                break
    got = plain(near_dup.components(spark.createDataFrame(rows, "doc_id long, text string"), width=5, percent=80))
    assert all(r["component_id"] == r["doc_id"] // 2 * 2 for r in got) and len(got) == 4


def test_long_words_that_a_polynomial_confuses(spark):
    """Two words of 2,048 letters whose letters follow a sequence and its complement are apart."""
    turns = [bin(i).count("1") % 2 for i in range(2048)]
    words = ["".join("ab"[t ^ flip] for t in turns) for flip in (0, 1)]
    rows = [(i, f"{w} one two three four") for i, w in enumerate(words)] + [(2, words[0]), (3, words[1]), (4, words[0].upper())]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in plain(near_dup.components(spark.createDataFrame(rows, "doc_id long, text string")))}
    assert got == brute_components(rows, 3, 85)


def test_links_that_the_forest_leaves_out(spark, monkeypatch):
    """A forest of failing pairs: what it leaves out is confirmed all the same."""
    rng = random.Random(11)
    rows = []
    for group in range(6):
        base = [f"g{group}w{i}" for i in range(60)]
        for k in range(8):
            words = list(base)
            for at in rng.sample(range(60), 2 + k % 4):
                words[at] = f"x{rng.randrange(10**9)}"
            rows.append((len(rows), " ".join(words)))
    want = brute_components(rows, 3, 60)

    def worst(left, right, cost, n, best=near_dup._forest):
        return best(left, right, -cost, n)

    df = spark.createDataFrame(rows, "doc_id long, text string")
    for forest in (near_dup._forest, worst):
        monkeypatch.setattr(near_dup, "_forest", forest)
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in plain(near_dup.components(df, percent=60))}
        assert got == want


def test_key_filter_loses_no_key(spark):
    keys = np.random.default_rng(3).integers(-(1 << 62), 1 << 62, 5000)
    words = near_dup.key_filter(spark.createDataFrame([(int(k),) for k in keys], "k long"))
    assert near_dup.in_filter(keys, words).all()
    other = np.random.default_rng(4).integers(-(1 << 62), 1 << 62, 5000)
    assert near_dup.in_filter(other, words).mean() < 0.05


def test_shingle_lanes():
    text = ("Ab cd " * 3 + "x" * 200 + " é\u00a0ü " + "y" * 64 + " " + "z" * 65 + " end").encode()
    words = text.lower().split()
    want = len(set(zip(words, words[1:], words[2:])))
    assert len(shingles.shingle_hashes([text])[0]) == want
    (low, high), = shingles.wide_shingles([text])
    assert (low == shingles.shingle_hashes([b"other words here", text])[1]).all() and len(high) == want and (low != high).all()
