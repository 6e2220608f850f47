"""Queries over the given tables, and the SQL that checks them.

Every engine side runs the structure named; the SQL side reads base tables, or repeats the
arithmetic where digests are md5."""

from __future__ import annotations

import functools
import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from . import model
from .functions import hashing
from .operators import applications as apps
from .operators import baselines, build, external, kernel, lookup, solve
from .params import BandParams
from .plans import metrics, sql_functions, versions
from .sources.shared import shared_dir
from .sources.store import load
from .streaming import probes

Query = Callable[[SparkSession, str], DataFrame]
_queries: dict[str, Query] = {}
_sql: dict[str, str] = {}


def _add(name: str, fn: Query, sql: str | None = None) -> None:
    _queries[name] = fn
    if sql:
        _sql[name] = sql


def queries() -> dict[str, Query]:
    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    return dict(_sql)


def query(sql: str | None = None):
    def register(fn: Query) -> Query:
        _add(fn.__name__, fn, sql)
        return fn

    return register


# ---- inputs ---------------------------------------------------------------------------------


def orders(spark: SparkSession, sf: str) -> DataFrame:
    code = F.substring("o_orderpriority", 1, 1).cast("long")
    return load(spark, sf, "orders", "o_orderkey", "o_orderpriority").select("o_orderkey", code.alias("code"))


LINE_KEY = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]


def lines(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "lineitem", *LINE_KEY).distinct()


def foreign(df: DataFrame, col: str) -> DataFrame:
    return df.select((F.col(col) + F.lit(10**9)).alias(col))


ORDERS_SQL = "SELECT o_orderkey, CAST(substr(o_orderpriority, 1, 1) AS BIGINT) AS code FROM orders"
MEMBER_SQL = "SELECT o_orderkey, TRUE AS member FROM orders"
LINES_SQL = "SELECT DISTINCT l_orderkey, l_partkey, l_suppkey, l_linenumber, CAST(l_partkey % 256 AS BIGINT) AS code FROM lineitem"
HI = "CAST('0x' || substr(md5(CAST({k} AS VARCHAR)), 1, 15) AS BIGINT)"
LO = "CAST('0x' || substr(md5(CAST({k} AS VARCHAR)), 16, 15) AS BIGINT)"
HI_ORDER, LO_ORDER = HI.format(k="o_orderkey"), LO.format(k="o_orderkey")

# ---- digests and starts -----------------------------------------------------------------------


@query(f"SELECT o_orderkey, {HI_ORDER} AS hi, {LO_ORDER} AS lo FROM orders")
def digest_md5_orders(spark, sf):
    return hashing.with_digest(load(spark, sf, "orders", "o_orderkey"), ["o_orderkey"], "md5")


@query(
    f"""WITH n AS (SELECT count(*) AS n FROM orders),
    s AS (SELECT ((({HI_ORDER}) >> 28) * CAST(n.n * 9 // 10 AS BIGINT)) >> 32 AS start FROM orders, n)
    SELECT CAST(start // 128 AS BIGINT) AS bucket, count(*) AS n_keys FROM s GROUP BY 1"""
)
def start_bucket_histogram(spark, sf):
    rows = load(spark, sf, "orders", "o_orderkey")
    return metrics.bucket_histogram(metrics.start_rows(rows, ["o_orderkey"], rows.count() * 9 // 10), 128)


@query("SELECT l_orderkey, l_linenumber, count(*) AS n_rows FROM lineitem GROUP BY ALL HAVING count(*) > 1")
def duplicate_digest_check(spark, sf):
    cols = ["l_orderkey", "l_linenumber"]
    rows = load(spark, sf, "lineitem", *cols)
    found = metrics.duplicate_digests(rows, cols)
    keyed = hashing.with_digest(rows, cols).join(found, ["hi", "lo"])
    return keyed.select(*cols, "n_rows").distinct()


@query(
    f"""WITH n AS (SELECT count(*) AS n FROM orders),
    s AS (SELECT {HI_ORDER} AS hi, {LO_ORDER} AS lo, ((({HI_ORDER}) >> 28) * CAST(n.n * 9 // 10 AS BIGINT)) >> 32 AS start FROM orders, n),
    r AS (SELECT start, row_number() OVER w - 1 AS rn, hi, lo FROM s WINDOW w AS (ORDER BY start, hi, lo))
    SELECT start, CAST(rn AS BIGINT) AS rn, CAST(rn + max(start - rn) OVER (ORDER BY rn ROWS UNBOUNDED PRECEDING) AS BIGINT) AS slot FROM r"""
)
def simple_diagonal(spark, sf):
    rows = load(spark, sf, "orders", "o_orderkey")
    starts = metrics.start_rows(rows, ["o_orderkey"], rows.count() * 9 // 10)
    return metrics.simple_diagonal(starts).select("start", "rn", "slot")


@query(
    f"""WITH n AS (SELECT count(*) AS n FROM orders),
    s AS (SELECT ((({HI_ORDER}) >> 28) * CAST(n.n * 11 // 10 AS BIGINT)) >> 32 AS slot FROM orders, n),
    a AS (SELECT slot, count(*) AS a FROM s GROUP BY slot),
    g AS (SELECT CAST(range AS BIGINT) AS slot FROM n, range(CAST(n.n * 11 // 10 AS BIGINT))),
    d AS (SELECT g.slot, CAST(sum(coalesce(a.a, 0)) OVER (ORDER BY g.slot) - (g.slot + 1) AS BIGINT) AS d FROM g LEFT JOIN a USING (slot))
    SELECT slot, CAST(d - least(0, min(d) OVER (ORDER BY slot ROWS UNBOUNDED PRECEDING)) AS BIGINT) AS height FROM d"""
)
def queue_heights(spark, sf):
    rows = load(spark, sf, "orders", "o_orderkey")
    n = rows.count() * 11 // 10
    return metrics.queue_heights(metrics.start_rows(rows, ["o_orderkey"], n), n)


# ---- functions ----------------------------------------------------------------------------------


@query(ORDERS_SQL)
def lookup_streamed(spark, sf):
    """Layers built with two buckets of keys in memory at a time."""
    df = orders(spark, sf)
    s = external.build_streamed(df, ["o_orderkey"], "code", n_shards=2, r=3)
    return lookup.lookup(s, df.select("o_orderkey"), ["o_orderkey"], out="code")


@query("SELECT layer, TRUE AS same FROM (VALUES (0), (1), (2), (3)) t(layer)")
def streamed_is_whole(spark, sf):
    """Tables of the streamed build against those of whole shards, bit by bit, for every layer of
    the parameters. No table is stored of a layer that no key reaches; from the second on, such a
    layer is the same if both builds lack it."""
    df, every = orders(spark, sf), ["shard", "layer"]
    streamed = external.build_streamed(df, ["o_orderkey"], "code", n_shards=1, r=3)
    one = streamed.table
    two = build.build(df, ["o_orderkey"], "code", n_shards=1, r=3, piece_starts=1 << 40).table
    columns = ["z", "codes", "exceptions", "n_in", "n_bumped", "empty"]
    both = one.select(*every, *columns).join(two.select(*every, *[F.col(c).alias(f"_{c}") for c in columns]), every, "full")
    same = F.forall(F.array(*[F.col(c).eqNullSafe(F.col(f"_{c}")) for c in columns]), lambda x: x)
    stored = both.groupBy(F.col("layer").cast("int").alias("layer")).agg(F.bool_and(same).alias("same"))
    layers = spark.range(streamed.params.layers).select(F.col("id").cast("int").alias("layer"))
    return layers.join(stored, "layer", "left").select("layer", F.coalesce("same", F.col("layer") > 0).alias("same"))


def _lookup_orders(**options) -> Query:
    def run(spark, sf):
        df = orders(spark, sf)
        s = build.build(df, ["o_orderkey"], "code", r=3, **options)
        return lookup.lookup(s, df.select("o_orderkey"), ["o_orderkey"], out="code")

    return run


for _name, _options in {
    "plain": {"kind": "plain"},
    "plain_sharded": {"kind": "plain", "n_shards": 8, "eps": 0.15},
    "layered_2bit": {},
    "layered_2biteven": {"scheme": "2bit-even"},
    "layered_cbit3": {"scheme": "cbit"},
    "layered_plain": {"scheme": "plain"},
    "layered_1plus": {"scheme": "1plus"},
    "layered_1plus_range": {"scheme": "1plus", "range_bits": 16},
    "layered_headtail": {"scheme": "headtail"},
    "layered_headtail_restart": {"scheme": "headtail", "constant": 4.0, "empty_limit": 0.01},
    "layered_single": {"scheme": "single"},
    "layered_cautious": {"mode": "cautious"},
    "layered_r2l_buckets": {"bucket_order": "r2l"},
    "layered_l2r_keys": {"order": "l2r"},
    "layered_hash_keys": {"order": "hash"},
    "layered_sharded": {"n_shards": 8},
    "two_hop": {"kind": "twohop", "layers": 6},
    "two_hop_fixed": {"kind": "twohop", "layers": 6, "fixed_sizes": True},
    "sparse": {"coef": "sparse:8"},
    "contiguous": {"layout": "contiguous"},
    "sparse_contiguous": {"coef": "sparse:8", "layout": "contiguous"},
    "w16": {"w": 16},
    "w32": {"w": 32},
    "w128": {"w": 128},
    "pieces": {"piece_starts": 1024},
    "free_random": {"free": "random"},
    "free_affine": {"free": "affine"},
}.items():
    _add(f"lookup_{_name}", _lookup_orders(**_options), ORDERS_SQL)


def _lookup_lines(strategy: str) -> Query:
    def run(spark, sf):
        df = lines(spark, sf).withColumn("code", F.col("l_partkey") % 256)
        s = build.build(df, LINE_KEY, "code", r=8, n_shards=4)
        return lookup.lookup(s, df.drop("code"), LINE_KEY, strategy, out="code")

    return run


for _name in ("broadcast", "shuffle", "sql"):
    _add(f"lookup_strategy_{_name}", _lookup_lines(_name), LINES_SQL)


@query("SELECT url, page_id FROM pages")
def lookup_string_keys(spark, sf):
    """Page of each URL; as a URL may have several pages, or be null, a key is the URL and the place
    among its pages."""
    pages = load(spark, sf, "pages", "page_id", "url")
    place = F.row_number().over(W.partitionBy("url").orderBy("page_id")).alias("place")
    df = pages.select("url", "page_id", F.coalesce("url", F.lit("")).alias("text"), F.col("url").isNull().alias("absent"), place)
    cols = ["text", "absent", "place"]
    s = build.build(df, cols, "page_id", r=40)
    return lookup.lookup(s, df.drop("page_id"), cols, out="page_id").select("url", "page_id")


@query("SELECT vec_id, vec_id AS got FROM embeddings")
def lookup_array_keys(spark, sf):
    df = load(spark, sf, "embeddings", "vec_id", "embedding").dropDuplicates(["embedding"])
    s = build.build(df, ["embedding"], "vec_id", r=40)
    every = load(spark, sf, "embeddings", "vec_id", "embedding")
    return lookup.lookup(s, every, ["embedding"], out="got").select("vec_id", "got")


@query("SELECT event_id, ts, CAST(length(event_type) AS BIGINT) AS code FROM events")
def lookup_timestamp_keys(spark, sf):
    df = load(spark, sf, "events", "event_id", "ts", "event_type")
    df = df.select("event_id", "ts", F.length("event_type").cast("long").alias("code"))
    s = build.build(df, ["event_id", "ts"], "code", r=5)
    return lookup.lookup(s, df.drop("code"), ["event_id", "ts"], out="code")


@query("SELECT o_orderkey, o_totalprice, CAST(round(o_totalprice * 100) AS BIGINT) AS cents FROM orders")
def lookup_wide_values(spark, sf):
    df = load(spark, sf, "orders", "o_orderkey", "o_totalprice")
    df = df.withColumn("cents", F.round(F.col("o_totalprice") * 100).cast("long"))
    s = build.build(df, ["o_orderkey"], "cents", r=40)
    return lookup.lookup(s, df.drop("cents"), ["o_orderkey"], out="cents")


@query("SELECT doc_id, CAST(quality AS BIGINT) AS quality, CAST(toxic AS BIGINT) AS toxic FROM labels")
def lookup_one_bit(spark, sf):
    df = load(spark, sf, "labels", "doc_id", "quality", "toxic")
    got = df.select("doc_id")
    for c in ("quality", "toxic"):
        got = lookup.lookup(build.build(df, ["doc_id"], c, r=1), got, ["doc_id"], out=c)
    return got


# ---- filters --------------------------------------------------------------------------------------


def _member(kind: str, **options) -> Query:
    def run(spark, sf):
        df = load(spark, sf, "orders", "o_orderkey")
        s = build.build(df, ["o_orderkey"], kind=kind, r=8, **options)
        return lookup.probe(s, df, ["o_orderkey"])

    return run


for _name, _options in {"plain": {}, "layered": {}, "zero": {}, "twohop": {"layers": 6}}.items():
    _add(f"member_{_name}_positive", _member(_name, **_options), MEMBER_SQL)


@query("SELECT kind, TRUE AS ok FROM (VALUES ('layered'), ('plain'), ('twohop'), ('zero')) t(kind)")
def member_fpr_within_bound(spark, sf):
    df = load(spark, sf, "orders", "o_orderkey")
    rows = []
    for kind in ("layered", "plain", "twohop", "zero"):
        s = build.build(df, ["o_orderkey"], kind=kind, r=8, layers=6 if kind == "twohop" else 4)
        got = metrics.measure_fpr(s, foreign(df, "o_orderkey"), ["o_orderkey"]).first()
        rate = model.zero_rhs_bound(s.params.eps, 8) if kind == "zero" else 2.0**-8
        over = got["hits"] > got["probes"] * rate and not metrics.within(got["probes"], got["hits"], rate)
        rows.append((kind, not over))
    return spark.createDataFrame(rows, "kind string, ok boolean")


@query("SELECT TRUE AS ok FROM (VALUES (1)) t(x)")
def member_bits_read(spark, sf):
    df = load(spark, sf, "lineitem", "l_orderkey", "l_linenumber").distinct()
    cols = ["l_orderkey", "l_linenumber"]
    s = build.build(df, cols, kind="layered", r=8)
    away = df.select((F.col("l_orderkey") + 10**9).alias("l_orderkey"), "l_linenumber")
    read = metrics.measure_fpr(s, away, cols).first()["bits_read"]
    n = df.count()
    return spark.createDataFrame([(abs(read - model.expected_bits(8)) <= max(0.05, 6 / n**0.5),)], "ok boolean")


@query("SELECT count(*) AS n_members FROM orders")
def member_mixed_no_false_negative(spark, sf):
    """Half of the probes are members; all of those are found."""
    df = load(spark, sf, "orders", "o_orderkey")
    s = build.build(df, ["o_orderkey"], kind="zero", r=8)
    mixed = df.withColumn("inside", F.lit(True)).unionByName(foreign(df, "o_orderkey").withColumn("inside", F.lit(False)))
    got = lookup.probe(s, mixed.repartition(4, F.xxhash64("o_orderkey")), ["o_orderkey"])
    return got.agg(F.sum((F.col("inside") & F.col("member")).cast("long")).alias("n_members"))


@query("SELECT event_id, TRUE AS member FROM events")
def many_filters_probe(spark, sf):
    """One filter for each user, all in one table; each event asks its user's filter."""
    df = load(spark, sf, "events", "user_id", "event_id")
    s = build.build_many(df, ["user_id"], ["event_id"], kind="zero", r=8)
    return lookup.probe(s, df, ["event_id"], group_cols=["user_id"]).select("event_id", "member")


# ---- baselines --------------------------------------------------------------------------------------


def _baseline_function(kind: str) -> Query:
    def run(spark, sf):
        df = orders(spark, sf)
        b = baselines.build(kind, df, ["o_orderkey"], "code", r=3)
        return baselines.query(b, df.select("o_orderkey"), ["o_orderkey"], "code")

    return run


def _baseline_filter(kind: str) -> Query:
    def run(spark, sf):
        df = load(spark, sf, "orders", "o_orderkey")
        return baselines.query(baselines.build(kind, df, ["o_orderkey"], r=8), df, ["o_orderkey"], "member")

    return run


for _name in baselines.FUNCTION_KINDS:
    _add(f"{_name}_lookup", _baseline_function(_name), ORDERS_SQL)
for _name in ("xor", "xorplus", "fuse", "coupled", "cuckoo", "morton", "quotient"):
    _add(f"{_name}_positive", _baseline_filter(_name), MEMBER_SQL)


FPR_KINDS = ("xor", "xorplus", "fuse", "peel3", "coupled", "irregular", "sparse3", "sparse4", "twoblock", "sorted_gauss", "cuckoo", "morton", "quotient")


@query("SELECT kind, TRUE AS ok FROM (VALUES " + ", ".join(f"('{k}')" for k in FPR_KINDS) + ") t(kind)")
def baseline_fpr_within_bound(spark, sf):
    """False positives of every filter baseline at r = 8, among 16 foreign keys a member, within
    four deviations of its rate: not above 2**-8, and above a quarter of it, so a filter that
    says yes or no to all fails. Members are dealt out before they are multiplied, as few input
    splits may hold them."""
    df = load(spark, sf, "orders", "o_orderkey")
    members = build.approximate_keys(df, ["o_orderkey"], "xx128", 1)
    tasks = max(spark.sparkContext.defaultParallelism, build.n_shards_for(16 * members, baselines.SHARD_KEYS))
    away = df.repartition(tasks, "o_orderkey").select(F.explode(F.transform(F.sequence(F.lit(1), F.lit(16)), lambda i: F.col("o_orderkey") + i.cast("long") * F.lit(10**9))).alias("o_orderkey"))
    n_shards = build.n_shards_for(members, baselines.SHARD_KEYS)
    with ThreadPoolExecutor(4) as pool:  # kinds of few shards leave no core idle
        built = list(pool.map(lambda kind: baselines.build(kind, df, ["o_orderkey"], r=8, n_shards=n_shards), FPR_KINDS))
    got = baselines.query(built, away, ["o_orderkey"], "m")
    probes, *found = got.agg(F.count(F.lit(1)), *[F.sum(F.col("m")[i].cast("long")) for i in range(len(built))]).first()
    rate, rows = 2.0**-8, []
    for kind, hits in zip(FPR_KINDS, found, strict=True):
        rows.append((kind, (hits <= probes * rate or metrics.within(probes, hits, rate)) and hits >= probes * rate / 4 - 4 * (probes * rate / 4) ** 0.5))
    return spark.createDataFrame(rows, "kind string, ok boolean")


@query("SELECT l_orderkey, count(*) AS n_lines FROM lineitem WHERE l_linenumber <> 3 GROUP BY 1")
def counting_quotient_updates(spark, sf):
    """Counts after all lines are inserted and those of number 3 are deleted again, in one task a
    shard of a counting filter over line order keys."""
    df = load(spark, sf, "lineitem", "l_orderkey", "l_linenumber")
    got = baselines.count_after_deletes(df, ["l_orderkey"], F.col("l_linenumber") == 3, r=44)
    keys = df.where("l_linenumber <> 3").select("l_orderkey").distinct()
    return baselines.query(got, keys, ["l_orderkey"], "n_lines")


@query("SELECT user_id, count(*) AS n_events FROM events GROUP BY user_id")
def counting_quotient_counts(spark, sf):
    df = load(spark, sf, "events", "user_id")
    b = baselines.build("counting_quotient", df, ["user_id"], r=40)
    return baselines.query(b, df.distinct(), ["user_id"], "n_events")


@query(ORDERS_SQL)
def exact_dictionary(spark, sf):
    df = orders(spark, sf)
    return baselines.exact_lookup(df, df.select("o_orderkey"), ["o_orderkey"], "code")


N_WORDS = "CAST(greatest(8, ceil(ceil(n.n * 12.0) / 64.0)) AS BIGINT)"
BLOOM_PARTS = f"""WITH n AS (SELECT count(*) AS n FROM orders), size AS (SELECT ({N_WORDS} + 7) // 8 * 8 AS words FROM n),
    p AS (SELECT {HI_ORDER} AS hi, {LO_ORDER} AS lo FROM {{source}}),
    spots AS (SELECT DISTINCT p.hi, p.lo, i, {{position}} AS pos FROM p, size, range(8) r(i))"""
PLAIN_AT = "(((hi & 1073741823) + (((lo & 1073741823) | 1) * i) + i * i) % (size.words * 64))"
BLOCK_AT = """(((hi >> 30) % (size.words // 8)) * 512 + (((hi & 1073741823) + (((lo & 1073741823) | 1) * i) + i * i) % 512))"""
TWO_AT = """((((hi >> 30) + (i % 2) * (lo >> 30)) % (size.words // 8)) * 512 + (((hi & 1073741823) + (((lo & 1073741823) | 1) * i) + i * i) % 512))"""


def _bloom_words(blocks: int) -> Query:
    def run(spark, sf):
        df = load(spark, sf, "orders", "o_orderkey")
        return baselines.build_bloom(df, ["o_orderkey"], 12.0, 8, blocks).table

    return run


def _bloom_hits(blocks: int) -> Query:
    """Keys away from the set that the filter takes for members: exactly its false positives."""

    def run(spark, sf):
        df = load(spark, sf, "orders", "o_orderkey")
        b = baselines.build_bloom(df, ["o_orderkey"], 12.0, 8, blocks)
        return baselines.query_bloom(b, foreign(df, "o_orderkey"), ["o_orderkey"]).where("member").select("o_orderkey")

    return run


def _words_sql(position: str) -> str:
    head = BLOOM_PARTS.format(source="orders", position=position)
    # Bit 63 makes a negative word; DuckDB's shift of a BIGINT into the sign is an error.
    bit = "CASE WHEN pos % 64 = 63 THEN CAST(-9223372036854775808 AS BIGINT) ELSE CAST(1 AS BIGINT) << CAST(pos % 64 AS INT) END"
    return f"{head} SELECT pos // 64 AS word, bit_or({bit}) AS bits FROM spots GROUP BY 1"


def _hits_sql(position: str) -> str:
    key = "o_orderkey + 1000000000"
    hi, lo = HI.format(k=key), LO.format(k=key)
    head = BLOOM_PARTS.format(source="orders", position=position)
    return f"""{head}, set_bits AS (SELECT DISTINCT pos FROM spots),
    q AS (SELECT o_orderkey + 1000000000 AS o_orderkey, {hi} AS hi, {lo} AS lo FROM orders),
    w AS (SELECT q.o_orderkey, {position} AS pos FROM q, size, range(8) r(i))
    SELECT w.o_orderkey FROM w LEFT JOIN set_bits USING (pos) GROUP BY 1 HAVING count(*) = count(set_bits.pos)"""


for _name, _blocks, _at in (("bloom", 0, PLAIN_AT), ("blocked_bloom", 1, BLOCK_AT), ("two_block_bloom", 2, TWO_AT)):
    _add(f"{_name}_words", _bloom_words(_blocks), _words_sql(_at))
    _add(f"{_name}_probe_hits", _bloom_hits(_blocks), _hits_sql(_at).replace("FROM w LEFT JOIN set_bits USING (pos)", "FROM w LEFT JOIN set_bits ON w.pos = set_bits.pos"))


@query("SELECT o_orderkey, TRUE AS member FROM orders")
def bloom_positive(spark, sf):
    df = load(spark, sf, "orders", "o_orderkey")
    return baselines.query_bloom(baselines.build_bloom(df, ["o_orderkey"]), df, ["o_orderkey"])


# ---- measures -----------------------------------------------------------------------------------------


@query("SELECT CAST(count(*) AS BIGINT) AS n_keys, TRUE AS conserved, TRUE AS last_bumps_none FROM orders")
def layer_conservation(spark, sf):
    s = build.build(orders(spark, sf), ["o_orderkey"], "code", r=3)
    report = metrics.layer_report(s)
    return report.agg(
        F.max("n_in").alias("n_keys"),
        (F.sum(F.col("n_in") - F.col("n_bumped")) == F.max("n_in")).alias("conserved"),
        (F.min_by("n_bumped", -F.col("layer")) == 0).alias("last_bumps_none"),
    )


@query("SELECT kind, TRUE AS ok FROM (VALUES ('layered'), ('two_hop')) t(kind)")
def layers_visited(spark, sf):
    df = orders(spark, sf)
    rows = []
    for kind, options in (("layered", {}), ("two_hop", {"kind": "twohop", "layers": 6})):
        s = build.build(df, ["o_orderkey"], "code", r=3, **options)
        got = lookup.lookup(s, df, ["o_orderkey"], "broadcast", "v", trace=True)
        if kind == "layered":
            ok = got.agg(F.max("v_layer")).first()[0] < 4
        else:
            keyed = hashing.with_digest(got, ["o_orderkey"]).select("hi", "v_layer").toArrow()
            first = solve.primary_layer(keyed.column(0).to_numpy().view(np.uint64), -s.params.eps, 6)
            hop = keyed.column(1).to_numpy() - first
            ok = bool(((hop == 0) | (hop == 1)).all())
        rows.append((kind, ok))
    return spark.createDataFrame(rows, "kind string, ok boolean")


@query("SELECT scheme, TRUE AS ok FROM (VALUES ('1plus'), ('2bit'), ('plain')) t(scheme)")
def overhead_within_target(spark, sf):
    """Space over n * r with b = 128: 1 percent, and what padding and directory cost a small n."""
    df = load(spark, sf, "lineitem", *LINE_KEY).withColumn("code", F.col("l_partkey") % 256)
    n_shards = build.n_shards_for(build.approximate_keys(df, LINE_KEY, "xx128", 1))
    rows = []
    for scheme in ("1plus", "2bit", "plain"):
        s = build.build(df, LINE_KEY, "code", r=8, b=128, scheme=scheme, n_shards=n_shards)
        got = metrics.space_report(s).first()
        rows.append((scheme, got["overhead"] <= 0.015 + 500 / got["n"]))
    return spark.createDataFrame(rows, "scheme string, ok boolean")


def _line_digests(spark, sf) -> DataFrame:
    return hashing.with_digest(load(spark, sf, "lineitem", *LINE_KEY), LINE_KEY).select("hi", "lo")


@query()
def sweep_eps(spark, sf):
    """Empty share and overhead by overloading, for three schemes and bucket sizes, w = 64."""
    grid = [
        BandParams(scheme=scheme, b=b, eps=-x / 100)
        for scheme in ("plain", "1plus", "2bit")
        for b in ((64, 128, 256) if scheme != "plain" else (128, 256))
        for x in (0, 4, 6.25, 8, 12)
    ]
    return metrics.sweep(_line_digests(spark, sf), grid)


@query()
def sweep_width(spark, sf):
    """Default configurations by band width, dense and sparse."""
    grid = [BandParams(w=w, scheme=s) for w in (16, 32, 64, 128) for s in ("2bit", "1plus")]
    return metrics.sweep(_line_digests(spark, sf), [*grid, BandParams(coef="sparse:8"), BandParams(coef="sparse:8", b=128)])


@query("SELECT TRUE AS ok FROM (VALUES (1)) t(x)")
def wider_bands_need_less(spark, sf):
    """Overhead falls with the width."""
    rows = metrics.sweep(_line_digests(spark, sf), [BandParams(w=w, scheme="2bit", b=2 * w) for w in (16, 32, 64)]).select("w", "e").collect()
    e = {r["w"]: r["e"] for r in rows}
    return spark.createDataFrame([(e[16] > e[32] > e[64],)], "ok boolean")


@query()
def space_by_structure(spark, sf):
    """Measured bits a key and overhead of every structure, r = 8, orders. Structures are built some
    at a time, so that those of few shards leave no core idle."""
    df = load(spark, sf, "orders", "o_orderkey")
    n = build.approximate_keys(df, ["o_orderkey"], "xx128", 1)
    bands = {
        "layered_2bit": {}, "layered_2bit_b128": {"b": 128}, "layered_1plus": {"scheme": "1plus"}, "plain_band": {"kind": "plain"},
        "zero_band": {"kind": "zero"}, "two_hop": {"kind": "twohop", "layers": 6}, "w32": {"w": 32}, "w128": {"w": 128},
    }

    def space(name: str) -> tuple[str, int, float | None, float | None]:
        if name in bands:
            s = build.build(df, ["o_orderkey"], r=8, n_shards=build.n_shards_for(n), group_keys=GROUP, **bands[name])
            bits, keys = metrics.space_report(s).select("bits", "n").first()
        else:
            made = baselines.build(name, df, ["o_orderkey"], r=8, n_shards=build.n_shards_for(n, baselines.SHARD_KEYS)).table
            bits, keys = made.agg(F.sum("bits"), F.sum("n")).first()
        return name, 8, bits / keys if keys else None, bits / keys / 8 - 1 if keys else None

    with ThreadPoolExecutor(4) as pool:
        rows = list(pool.map(space, [*bands, *baselines.KERNEL_KINDS]))
    return spark.createDataFrame(rows, "name string, r int, bits_per_key double, overhead double")


#: A group is full with its first shard of the usual size: a task holds one at a time.
GROUP = build.SHARD_KEYS // 2


RANKED = ("layered_2bit_b128", "plain_band", "xor", "bloom", "blocked_bloom")


@query("SELECT name, place FROM (VALUES " + ", ".join(f"('{n}', {i + 1})" for i, n in enumerate(RANKED)) + ") t(name, place)")
def ranking_of_space(spark, sf):
    """Places by measured overhead: layered, plain band, xor, Bloom, blocked Bloom. Bloom bits are
    set against the information content of the rate that is measured."""
    df = load(spark, sf, "orders", "o_orderkey")
    n = df.count()
    rows = [(k, metrics.space_report(build.build(df, ["o_orderkey"], r=8, **o)).first()["overhead"]) for k, o in {"layered_2bit_b128": {"b": 128}, "plain_band": {"kind": "plain"}}.items()]
    rows.append(("xor", baselines.build("xor", df, ["o_orderkey"], r=8).table.agg(F.sum("bits")).first()[0] / n / 8 - 1))
    for name, blocks in (("bloom", 0), ("blocked_bloom", 1)):
        rows.append((name, baselines.bloom_overhead(df, foreign(df, "o_orderkey"), ["o_orderkey"], n, blocks)))
    report = spark.createDataFrame(rows, "name string, overhead double")
    worse = report.alias("a").join(F.broadcast(report.alias("b")), F.col("b.overhead") <= F.col("a.overhead"))  # five rows
    return worse.groupBy("a.name").agg(F.count(F.lit(1)).cast("int").alias("place"))


VALUE_BITS = (1, 2, 4, 8, 12, 16)


def _value_bits(spark, sf) -> DataFrame:
    """Structures are built some at a time, so that those of few shards leave no core idle."""
    df = load(spark, sf, "lineitem", *LINE_KEY)
    n = build.approximate_keys(df, LINE_KEY, "xx128", 1)

    def overhead(r: int, name: str) -> tuple[int, str, float]:
        if name.startswith("layered_"):
            s = build.build(df, LINE_KEY, r=r, b=128, scheme=name.removeprefix("layered_"), n_shards=build.n_shards_for(n))
            return r, name, metrics.space_report(s).first()["overhead"]
        made = baselines.build(name, df, LINE_KEY, r=r, n_shards=build.n_shards_for(n, baselines.SHARD_KEYS)).table
        bits, keys = made.agg(F.sum("bits"), F.sum("n")).first()
        return r, name, bits / keys / r - 1

    grid = [(r, name) for r in VALUE_BITS for name in ("layered_1plus", "layered_2bit", "xor", "fuse", "quotient")]
    with ThreadPoolExecutor(4) as pool:
        rows = list(pool.map(lambda at: overhead(*at), grid))
    return spark.createDataFrame(rows, "r int, name string, overhead double")


@query()
def sweep_value_bits(spark, sf):
    """Measured overhead by value bits, r = 1 to 16, from stored bytes; as padding and directory
    weigh on few keys, with 1,500 keys and r = 1 xor stores less than layers do."""
    return _value_bits(spark, sf)


@query("SELECT r, 'layered' AS family FROM (VALUES " + ", ".join(f"({r})" for r in VALUE_BITS) + ") t(r)")
def smallest_by_value_bits(spark, sf):
    """The family that stores the fewest bits for each r."""
    return _value_bits(spark, sf).groupBy("r").agg(F.split(F.min_by("name", "overhead"), "_")[0].alias("family"))


@query()
def success_rate_wide(spark, sf):
    """Share of 20 seeds for which a plain system of w = 128 over all orders fits, by eps; it is one
    half near 3 percent at a million keys, and at less for fewer."""
    return metrics.success_curve(orders(spark, sf), ["o_orderkey"], 128, [0.01, 0.02, 0.03, 0.04, 0.05])


@query("SELECT eps_percent, TRUE AS ok FROM (VALUES (10), (20), (30)) t(eps_percent)")
def zero_span_report(spark, sf):
    """Rate of foreign keys within the span over all orders and lines: small at every eps."""
    grid = {p / 100: p for p in (10, 20, 30)}
    params = [BandParams(kind="zero", r=8, eps=e).resolved() for e in grid]
    keys = {("o_orderkey",): orders(spark, sf), tuple(LINE_KEY): lines(spark, sf)}
    ok = dict.fromkeys(grid.values(), True)
    for cols, df in keys.items():
        other = df.withColumn(cols[0], F.col(cols[0]) + F.lit(10**9))
        for g in metrics.zero_span(df, other, list(cols), params).collect():
            ok[grid[g["eps"]]] &= g["inside"] <= 0.02 * g["n_foreign"] and g["redundant"] <= 0.02 * g["n_members"]
    return spark.createDataFrame(list(ok.items()), "eps_percent int, ok boolean")


@query()
def success_rate(spark, sf):
    """Share of 20 seeds for which a plain system of all orders fits, by eps."""
    return metrics.success_curve(orders(spark, sf), ["o_orderkey"], 64, [0.01, 0.03, 0.05, 0.08, 0.12])


@query("SELECT count(DISTINCT o_orderkey) AS n_keys, TRUE AS same_slots, TRUE AS same_rest, TRUE AS within_bound FROM orders")
def eliminator_invariants(spark, sf):
    """In systems of some 600 orders each, filled slots and the number of other rows do not depend on
    the order; work stays under its bound."""
    p = BandParams(kind="plain", w=16, r=1, eps=0.02).resolved()

    def run(keys: solve.Keys) -> dict:
        n = len(keys)
        orders = (None, np.random.default_rng(5).permutation(n), np.arange(n)[::-1])
        got = [metrics.system_profile(keys, p, max(1, n * 59 // 60), order) for order in orders]
        return {
            "n": n, "same_slots": all(g["filled"] == got[0]["filled"] for g in got), "same_rest": all(g["not_placed"] == got[0]["not_placed"] for g in got),
            "within_bound": all(g["failed"] > 0 or g["row_ops"] <= g["bound"] for g in got),
        }

    parts = metrics.systems(load(spark, sf, "orders", "o_orderkey"), ["o_orderkey"], 600, run, "n long, same_slots boolean, same_rest boolean, within_bound boolean")
    holds = [F.coalesce(F.bool_and(c), F.lit(True)).alias(c) for c in ("same_slots", "same_rest", "within_bound")]
    return parts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_keys"), *holds)


@query("SELECT slots AS m, count(DISTINCT o_orderkey) AS n_keys, TRUE AS exact FROM orders, (VALUES (40), (80)) t(slots) GROUP BY slots")
def rank_oracle(spark, sf):
    """Placed rows equal the rank by dense elimination, in systems of some 2 m orders each."""
    df = load(spark, sf, "orders", "o_orderkey")
    out = []
    for m in (40, 80):
        parts = metrics.systems(df, ["o_orderkey"], 2 * m, functools.partial(metrics.rank_profile, m=m), "n long, placed long, rank long")
        out.append(parts.agg(F.lit(m).alias("m"), F.sum("n").alias("n_keys"), F.bool_and(F.col("placed") == F.col("rank")).alias("exact")))
    return out[0].unionByName(out[1]).where("n_keys is not null")


@query("SELECT l_returnflag, count(*) AS n FROM lineitem GROUP BY 1")
def entropy_counts(spark, sf):
    return load(spark, sf, "lineitem", "l_returnflag").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT TRUE AS ok FROM (VALUES (1)) t(x)")
def entropy_report(spark, sf):
    """A prefix code's bits lie between the entropy and one bit a key above it."""
    rows = load(spark, sf, "labels", "doc_id", "quality").join(load(spark, sf, "documents", "doc_id", "lang"), "doc_id")
    h = metrics.entropy_bits(rows, "lang").first()
    counts = {r[0]: r[1] for r in rows.groupBy("lang").count().collect()}
    codes = apps.huffman(counts)
    used = sum(len(codes[v]) * n for v, n in counts.items())
    return spark.createDataFrame([(h["bits"] <= used + 1e-6 <= h["bits"] + h["n"],)], "ok boolean")


@query("""SELECT coalesce(l_returnflag, '*') AS name, coalesce(l_linenumber, -1) AS w, count(*) AS n, min(l_extendedprice) AS best FROM lineitem GROUP BY CUBE (l_returnflag, l_linenumber)""")
def report_cube(spark, sf):
    rows = load(spark, sf, "lineitem", "l_returnflag", "l_linenumber", "l_extendedprice")
    cube = rows.cube("l_returnflag", "l_linenumber").agg(F.count(F.lit(1)).alias("n"), F.min("l_extendedprice").alias("best"))
    return cube.select(F.coalesce("l_returnflag", F.lit("*")).alias("name"), F.coalesce("l_linenumber", F.lit(-1)).alias("w"), "n", "best")


@query(
    """WITH least AS (SELECT o_totalprice, min(o_orderdate) AS o_orderdate FROM orders GROUP BY 1),
    low AS (SELECT *, min(o_orderdate) OVER (ORDER BY o_totalprice ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before FROM least)
    SELECT o_orderkey, o_totalprice, o_orderdate FROM orders JOIN low USING (o_totalprice, o_orderdate) WHERE before IS NULL OR o_orderdate < before"""
)
def pareto_front(spark, sf):
    """Orders to which no other one is both as cheap and as early, and cheaper or earlier."""
    return metrics.pareto(load(spark, sf, "orders", "o_orderkey", "o_totalprice", "o_orderdate"), "o_totalprice", "o_orderdate", "o_orderkey")


PARAMETERS = "(16, 32, -0.1875, 8, 13, 16, 7), (32, 64, -0.09375, 12, 23, 32, 12), (64, 256, -0.0625, 36, 78, 128, 25), (128, 1024, -0.03125, 117, 267, 512, 52)"


@query(
    f"""WITH v(w, b_two, e, low, high, b_one, t) AS (VALUES {PARAMETERS}), n AS (SELECT count(*) AS n FROM orders),
    d AS (SELECT ({HI_ORDER}) >> 28 AS h FROM orders),
    s AS (SELECT v.*, (d.h * CAST(ceil((1 + CAST(e AS DOUBLE)) * n.n) AS BIGINT)) >> 32 AS start FROM d, n, v)
    SELECT w, b_two, CAST(e AS DOUBLE) AS eps_two, low, high, b_one, t, count(*) FILTER (start % b_two < low) AS below_low,
      count(*) FILTER (start % b_two < high) AS below_high FROM s GROUP BY ALL"""
)
def parameter_formulas(spark, sf):
    """Parameters by formula for each width, and the orders whose place in a bucket of the first
    layer lies below either threshold."""
    from . import params

    rows = load(spark, sf, "orders", "o_orderkey")
    n = rows.count()
    fields, sums = [], {}
    for w in (16, 32, 64, 128):
        b2, b1 = params.bucket_size(w, "2bit"), params.bucket_size(w, "1plus")
        e2, e1 = params.overload(w, "2bit", b2), params.overload(w, "1plus", b1)
        two = params.two_thresholds(w, b2, e2)
        place = F.shiftright(F.shiftright("hi", 28) * F.lit(solve.table_starts(n, e2, "layered")).cast("long"), 32) % b2
        for side, t in zip(("low", "high"), two, strict=True):
            sums[f"{side}{w}"] = F.count(F.when(place < t, 1))
        given = {"w": w, "b_two": b2, "eps_two": e2, "low": two[0], "high": two[1], "b_one": b1, "t": params.one_threshold(b1, e1)}
        cast = {k: F.lit(x).cast("double" if k == "eps_two" else "int").alias(k) for k, x in given.items()}
        fields.append(F.struct(*cast.values(), F.col(f"low{w}").alias("below_low"), F.col(f"high{w}").alias("below_high")))
    found = hashing.with_digest(rows, ["o_orderkey"], "md5").agg(*[c.alias(k) for k, c in sums.items()])
    return found.select(F.inline(F.array(*fields)))


# ---- applications ---------------------------------------------------------------------------------------


@query("SELECT count(*) AS n, count(*) AS n_ids, TRUE AS in_range FROM orders")
def perfect_hash_injective(spark, sf):
    df = load(spark, sf, "orders", "o_orderkey")
    ph = apps.build_perfect_hash(df, ["o_orderkey"])
    cells = ph.sizes.agg(F.sum("n_cells")).first()[0]
    got = apps.perfect_hash(ph, df)
    n = F.count(F.lit(1))
    return got.agg(
        n.alias("n"), F.countDistinct("id").alias("n_ids"),
        ((F.min("id") >= 0) & (F.max("id") < cells) & (F.lit(cells) <= n * 1.03 * apps.LOAD + 16)).alias("in_range"),
    )


@query("SELECT DISTINCT p_type, CAST(dense_rank() OVER (ORDER BY p_type) - 1 AS BIGINT) AS code FROM part")
def ordered_codes(spark, sf):
    df = load(spark, sf, "part", "p_type")
    n = df.distinct().count()
    return lookup.lookup(apps.build_codes(df, "p_type", n), df.distinct(), ["p_type"], out="code")


@query("SELECT DISTINCT l_orderkey, l_partkey, l_suppkey, l_linenumber, l_returnflag FROM lineitem")
def varlen_decode(spark, sf):
    df = load(spark, sf, "lineitem", *LINE_KEY, "l_returnflag").dropDuplicates(LINE_KEY)
    v = apps.build_varlen(df, LINE_KEY, "l_returnflag")
    return apps.decode_varlen(v, df.drop("l_returnflag"), "l_returnflag")


@query("SELECT o_orderkey, o_orderpriority FROM orders")
def varlen_interleaved(spark, sf):
    df = load(spark, sf, "orders", "o_orderkey", "o_orderpriority")
    v = apps.build_varlen(df, ["o_orderkey"], "o_orderpriority", interleaved=True)
    return apps.decode_varlen(v, df.drop("o_orderpriority"), "o_orderpriority")


@query("SELECT p_partkey, p_size FROM part")
def varlen_golomb(spark, sf):
    df = load(spark, sf, "part", "p_partkey", "p_size")
    v = apps.build_varlen(df, ["p_partkey"], "p_size", code="golomb")
    return apps.decode_varlen(v, df.drop("p_size"), "p_size").withColumn("p_size", F.col("p_size").cast(df.schema["p_size"].dataType))


def _urgent(spark, sf) -> DataFrame:
    rows = load(spark, sf, "orders", "o_orderkey", "o_orderpriority", "o_custkey").where("o_orderpriority = '1-URGENT'")
    return rows.select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")


URGENT = "(SELECT o_orderkey AS l_orderkey, o_custkey FROM orders WHERE o_orderpriority = '1-URGENT')"


def _prefilter(how: str) -> Query:
    def run(spark, sf):
        big = load(spark, sf, "lineitem", "l_orderkey", "l_partkey", "l_linenumber")
        got = apps.prefilter_join(big, _urgent(spark, sf), ["l_orderkey"], how)
        columns = ["l_orderkey", "l_partkey", "l_linenumber"] + (["o_custkey"] if how == "inner" else [])
        return got.select(*columns)

    return run


_add("prefilter_join", _prefilter("inner"), f"SELECT l_orderkey, l_partkey, l_linenumber, o_custkey FROM lineitem JOIN {URGENT} u USING (l_orderkey)")
_add("prefilter_semi", _prefilter("left_semi"), f"SELECT l_orderkey, l_partkey, l_linenumber FROM lineitem WHERE l_orderkey IN (SELECT l_orderkey FROM {URGENT})")
_add("prefilter_anti", _prefilter("left_anti"), f"SELECT l_orderkey, l_partkey, l_linenumber FROM lineitem WHERE l_orderkey NOT IN (SELECT l_orderkey FROM {URGENT})")


@query(
    r"""WITH w AS (SELECT 'd' AS side, doc_id AS id, list_filter(regexp_split_to_array(lower(text), '\s+'), lambda x: x <> '') AS w FROM documents
      UNION ALL SELECT 'i', item_id, list_filter(regexp_split_to_array(lower(text), '\s+'), lambda x: x <> '') FROM benchmark),
    g AS (SELECT side, id, array_to_string(w[i:i + 7], ' ') AS gram FROM (SELECT side, id, w, unnest(range(1, len(w) - 6)) AS i FROM w WHERE len(w) >= 8))
    SELECT DISTINCT d.id AS doc_id, i.id AS item_id FROM g d JOIN g i ON d.gram = i.gram AND d.side = 'd' AND i.side = 'i'"""
)
def contamination_probe(spark, sf):
    return apps.ngram_probe(load(spark, sf, "documents", "doc_id", "text"), load(spark, sf, "benchmark", "item_id", "text"))


# ---- SQL surface and versions -----------------------------------------------------------------------------


@query(ORDERS_SQL)
def sql_function(spark, sf):
    """The function called from SQL."""
    df = orders(spark, sf)
    sql_functions.register(spark, "band_code", build.build(df, ["o_orderkey"], "code", r=3))
    df.createOrReplaceTempView("band_orders")
    hi, lo = sql_functions.digest_sql(1, "o_orderkey")
    return spark.sql(f"SELECT o_orderkey, band_code({hi}, {lo}) AS code FROM band_orders")


@query("SELECT count(*) AS n FROM orders")
def sql_table_function(spark, sf):
    sql_functions.register(spark, "band_layers_of", build.build(orders(spark, sf), ["o_orderkey"], "code", r=3, n_shards=4))
    return spark.sql("SELECT sum(n_in - n_bumped) AS n FROM band_layers_of_layers()")


@query(
    """WITH v AS (SELECT ts, min(event_id) AS version FROM events WHERE event_type = 'purchase' GROUP BY ts)
    SELECT e.event_id, coalesce(v.version, -1) AS version FROM events e ASOF LEFT JOIN v ON e.ts >= v.ts"""
)
def version_as_of(spark, sf):
    """The structure version that holds at each event: versions are purchases, by their time."""
    events = load(spark, sf, "events", "event_id", "ts", "event_type").withColumn("ts", F.col("ts").cast("timestamp"))
    made = events.where("event_type = 'purchase'").groupBy("ts").agg(F.min("event_id").alias("version"))
    return versions.as_of(events.select("event_id", "ts"), made, "ts", "version").select("event_id", F.coalesce("version", F.lit(-1).cast("long")).alias("version"))


# ---- streams -----------------------------------------------------------------------------------------------


def _stream(spark, sf) -> DataFrame:
    schema = load(spark, sf, "events").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def _drain(spark, stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what there is, into Parquet under the shared folder."""
    root = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).format("parquet").option("checkpointLocation", f"{root}/state")
    writer.option("path", f"{root}/out").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{root}/out")


@query("SELECT event_id, user_id FROM events WHERE user_id % 3 = 0")
def stream_probe(spark, sf):
    members = load(spark, sf, "events", "user_id").where("user_id % 3 = 0").distinct()
    s = build.build(members, ["user_id"], kind="zero", r=40)
    return _drain(spark, probes.probe_stream(s, _stream(spark, sf), ["user_id"]).select("event_id", "user_id"))


@query(
    """WITH hits AS (SELECT time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '2024-01-01') AS d, count(*) AS hits FROM events WHERE user_id % 3 = 0 GROUP BY 1)
    SELECT strftime(d, '%Y-%m-%d') AS day, hits FROM hits WHERE d + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR"""
)
def stream_window_hits(spark, sf):
    """Closed daily windows: those that end before the watermark of the last event."""
    members = load(spark, sf, "events", "user_id").where("user_id % 3 = 0").distinct()
    s = build.build(members, ["user_id"], kind="zero", r=40)
    seen = lookup.probe(s, _stream(spark, sf), ["user_id"], "broadcast", "m").withWatermark("ts", "1 hour")
    hits = seen.groupBy(F.window("ts", "1 day").alias("w")).agg(F.sum(F.col("m").cast("long")).alias("hits"))
    return _drain(spark, hits.where("hits > 0").select(F.date_format("w.start", "yyyy-MM-dd").alias("day"), "hits"))
