"""Every registered query of the codec and of the operators around it, with its SQL twin."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lattice_pages.functions import measures
from lattice_pages.operators import codec, scan
from lattice_pages.operators.pages import with_ordinal
from lattice_pages.plans import costsql as c
from lattice_pages.plans import streams
from lattice_pages.plans.profiles import ABLATIONS
from lattice_pages.session import fresh_path, materialize, path_exists, ship

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def add(name: str, f: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return f(spark, sf_dir)

    QUERIES[name] = run
    if sql is not None:
        ORACLE_SQL[name] = sql


# ---------------------------------------------------------------- round trips


def encoded(spark: SparkSession, sf_dir: str, name: str, profile: str = "exact_fast", **kw) -> DataFrame:
    return codec.encode(streams.stream_df(spark, sf_dir, name), profile, **kw)


def _roundtrip(name: str, profile: str, **kw):
    return lambda spark, sf_dir: codec.decode(encoded(spark, sf_dir, name, profile, **kw)).select("ord", "value")


for _s in streams.BOUNDED15:
    add(f"w_exact14_roundtrip_{_s.name}", _roundtrip(_s.name, "exact_fast"), f"SELECT ord, value FROM ({streams.duck_sql(_s)}) t")
for _n in ("part_price", "ev_value", "ev_minute", "cust_bal"):
    add(f"w_upper_roundtrip_{_n}", _roundtrip(_n, "exact_upper"), f"SELECT ord, value FROM ({streams.duck_sql(streams.BY_NAME[_n])}) t")
add("w_exact14_p1000", _roundtrip("li_price", "exact_fast", page_size=1000), f"SELECT ord, value FROM ({streams.duck_sql(streams.BY_NAME['li_price'])}) t")
for _n, _p in ABLATIONS.items():
    if not _p.bounded:
        add(f"w_ablation_roundtrip_{_n}", _roundtrip("part_price", _p), f"SELECT ord, value FROM ({streams.duck_sql(streams.BY_NAME['part_price'])}) t")
add(
    "w_recompress_roundtrip",
    lambda spark, sf_dir: codec.decode(codec.recompress(encoded(spark, sf_dir, "ev_value"))).select("ord", "value"),
    f"SELECT ord, value FROM ({streams.duck_sql(streams.BY_NAME['ev_value'])}) t",
)


def _bounded_report(name: str, eps: tuple[float, ...]):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        src = materialize(streams.stream_df(spark, sf_dir, name), "stream")
        out = None
        for e in eps:
            r = measures.bound_report(src, codec.decode(codec.encode(src, "bounded", eps=e)), e).select(F.lit(e).alias("eps"), "n", "violations")
            out = r if out is None else out.unionByName(r)
        return out

    return run


_EPS = (1e-1, 1e-2, 1e-3, 1e-4, 1e-5, 1e-6)
for _n in (s.name for s in streams.BOUNDED15):
    _rows = " UNION ALL ".join(f"SELECT {e!r}::DOUBLE AS eps, count(*) AS n, 0::BIGINT AS violations FROM ({streams.duck_sql(streams.BY_NAME[_n])}) t" for e in _EPS)
    add(f"w_bounded_report_{_n}", _bounded_report(_n, _EPS), _rows)


_ALL: dict[tuple, tuple[str, DataFrame]] = {}


def all_of(spark: SparkSession, sf_dir: str, names: tuple[str, ...]) -> DataFrame:
    """The rows of several streams in one table, written once in an application as long as it is there."""
    key = (spark.sparkContext.applicationId, sf_dir, names)
    if key in _ALL and path_exists(spark, _ALL[key][0]):
        return _ALL[key][1]
    src = streams.together(spark, sf_dir, tuple(streams.BY_NAME[n] for n in names))
    path = fresh_path(spark, "streams")
    src.write.parquet(path)
    _ALL[key] = path, spark.read.schema(src.schema).parquet(path)
    return _ALL[key][1]


def _ratios(names: tuple[str, ...], profiles: tuple[str, ...]):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        src, out = all_of(spark, sf_dir, names), None
        for p in profiles:
            r = measures.ratio(codec.encode(src, p), "stream_id").withColumn("codec", F.lit(p if isinstance(p, str) else p.name))
            out = r if out is None else out.unionByName(r)
        return out

    return run


_NAMES14 = tuple(s.name for s in streams.EXACT14)
_NAMES15 = tuple(s.name for s in streams.BOUNDED15)
add("w_profile_matrix", _ratios(_NAMES14, ("exact_fast", "exact_upper", "bounded")))
add("w_ablation_cost", _ratios(_NAMES14, tuple(n for n in ABLATIONS)))
add("w_bits_sum", lambda spark, sf_dir: measures.bit_breakdown(codec.encode(all_of(spark, sf_dir, _NAMES14), "exact_upper"), "stream_id"))

# ---------------------------------------------------------------- cost layer


def _views(spark: SparkSession, sf_dir: str, names: tuple[str, ...]) -> None:
    for n in names:
        materialize(streams.stream_df(spark, sf_dir, n), f"s-{n}").createOrReplaceTempView(f"s_{n}")


def cost(name: str, text: Callable[[c.E], str], *names: str) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        _views(spark, sf_dir, names)
        return spark.sql(text(c.SPARK))

    add(name, run, text(c.DUCK))


for _s in streams.BOUNDED15:
    if _s.name != "emb_flat":
        cost(f"m_min_scale_{_s.name}", lambda e, n=_s.name: f"SELECT CAST({c.min_scale(e, 'value')} AS BIGINT) AS min_scale, count(*) AS n FROM {e.stream(n)} t GROUP BY 1", _s.name)
for _n in ("ev_value", "li_price", "ord_total", "part_price", "cust_bal", "ev_cum"):
    cost(f"m_residual_onelane_{_n}", lambda e, n=_n: f"SELECT page_no, max(s) AS s, count(*) AS n, CAST(sum({c.blen(c.zz('r'))}) AS BIGINT) AS bits FROM ({c.one_lane(e, n)}) a GROUP BY page_no", _n)
    cost(f"m_residual_routed_{_n}", lambda e, n=_n: f"SELECT page_no, s, count(*) AS n, CAST(sum({c.blen(c.zz('r'))}) AS BIGINT) AS bits FROM ({c.routed(e, n)}) a GROUP BY page_no, s", _n)
for _n in ("ev_value", "part_price", "ord_total"):
    cost(f"m_block_cost_{_n}", lambda e, n=_n: c.block_costs(e, c.one_lane(e, n)), _n)
    cost(f"m_rice_cost_{_n}", lambda e, n=_n: c.rice_costs(e, c.one_lane(e, n)), _n)
    cost(f"m_split_cost_{_n}", lambda e, n=_n: c.split_costs(e, c.one_lane(e, n)), _n)
    cost(f"m_predictor_cost_{_n}", lambda e, n=_n: c.predictor_costs(e, n), _n)
cost("m_width_hist", lambda e: f"SELECT w, count(*) AS n FROM ({c.block_costs(e, c.routed(e, 'ev_value'))}) a GROUP BY w", "ev_value")
cost("m_membership_counts", lambda e: "SELECT " + ", ".join(f"CAST(sum(CASE WHEN {c.admits(e, 'value', s)} THEN 1 ELSE 0 END) AS BIGINT) AS s{s}" for s in range(19)) + f" FROM {e.stream('li_unit')} t", "li_unit")
cost("m_origin", lambda e: f"SELECT page_no, {e.min_by('value', 'pos')} AS origin FROM ({c.pages(e, 'cust_bal')}) a WHERE value <> 0 GROUP BY page_no", "cust_bal")
cost("m_page_stats", lambda e: f"SELECT page_no, count(*) AS n, min(value) AS min_value, max(value) AS max_value FROM ({c.pages(e, 'li_price')}) a GROUP BY page_no", "li_price")
cost("m_route_map", lambda e: f"SELECT page_no, CAST({c.min_scale(e, 'value')} AS BIGINT) AS lane, count(*) AS n, min(pos) AS first_pos FROM ({c.pages(e, 'li_unit')}) a GROUP BY 1, 2", "li_unit")
cost("m_affine_residue", lambda e: f"SELECT CAST({e.int('value')} % 60 AS BIGINT) AS residue, count(*) AS n FROM {e.stream('ev_minute')} t GROUP BY 1", "ev_minute")
for _k, _eps in enumerate(_EPS, 1):
    for _n in ("ev_value", "part_price"):
        cost(f"m_bounded_index_{_n}_eps{_k}", lambda e, n=_n, eps=_eps: " UNION ALL ".join(f"SELECT {k} AS step, count(*) AS n, count(q) AS admitted, CAST(sum(abs(q)) AS BIGINT) AS total FROM ({c.bounded_q(e, n, eps, k)}) a" for k in range(3)), _n)
        cost(f"w_factor_sweep_{_n}_eps{_k}", lambda e, n=_n, eps=_eps: c.divisor_cover(e, n, eps), _n)
for _n in ("ev_value", "li_price"):
    cost(f"b_frame_of_reference_width_{_n}", lambda e, n=_n: f"SELECT page_no, max(s) AS s, {c.blen('(max(q) - min(q))')} AS width FROM ({c.one_lane(e, n)}) a GROUP BY page_no", _n)
    cost(f"b_bitplane_cost_{_n}", lambda e, n=_n: f"SELECT page_no, bit_count({e.bit_or(c.zz('r'))}) AS planes FROM ({c.one_lane(e, n)}) a WHERE r IS NOT NULL GROUP BY page_no", _n)
    cost(f"b_group8_bits_{_n}", lambda e, n=_n: f"SELECT page_no, CAST(sum(w * m + 6) AS BIGINT) AS bits FROM (SELECT page_no, block, max(l) AS w, count(*) AS m FROM ({c.lens(e, c.one_lane(e, n), 8)}) a GROUP BY page_no, block) b GROUP BY page_no", _n)
for _n in ("ev_cum", "part_price"):
    cost(f"w_mixed_routes_{_n}", lambda e, n=_n: " UNION ALL ".join(c.mixed_routes(e, n, k, b) for k in (100, 20, 5) for b in (False, True)), _n)
    cost(f"w_retain_bits_{_n}", lambda e, n=_n: " UNION ALL ".join(c.retained(e, n, p) for p in (20, 40, 60, 80, 100)), _n)
    cost(f"w_permute_bits_{_n}", lambda e, n=_n: " UNION ALL ".join(c.permuted(e, n, p) for p in (0, 25, 50, 75, 100)), _n)
for _page, _block in [(p, 16) for p in (100, 256, 512, 1000, 1024, 2000, 4000)] + [(1024, b) for b in (4, 8, 32, 64, 128)]:
    cost(f"w_structure_sweep_{_page}_{_block}", lambda e, p=_page, b=_block: c.structure(e, "ev_value", p, b), "ev_value")
def _beta(e: c.E, name: str) -> str:
    """Values cut to 1..18 decimals, by the least scale that holds them; past 2^52 a double is whole already."""
    values = ", ".join(f"({b}, {c.p10(b)})" for b in range(1, 19))
    table = f"(SELECT col1 AS beta, CAST(col2 AS DOUBLE) AS p FROM VALUES {values})" if e.spark else f"(SELECT col0 AS beta, col1::DOUBLE AS p FROM (VALUES {values}) v)"
    cut = "(CASE WHEN abs(value * p) < 4503599627370496 THEN CAST(floor(value * p) AS DOUBLE) ELSE value * p END)"
    return f"SELECT '{name}' AS stream_id, beta, CAST({c.min_scale(e, 'v')} AS BIGINT) AS min_scale, count(*) AS n FROM (SELECT beta, {cut} / p AS v FROM {e.stream(name)} t CROSS JOIN {table} b) a GROUP BY 2, 3"


cost("w_beta_admission", lambda e: " UNION ALL ".join(_beta(e, s.name) for s in streams.EXACT14), *(s.name for s in streams.EXACT14))
add(
    "w_large48_pages",
    lambda spark, sf_dir: spark.read.parquet(f"{sf_dir}/lineitem.parquet").groupBy(F.concat("l_returnflag", "l_linestatus").alias("part")).agg(F.floor(F.count(F.lit(1)) / 1024).alias("full_pages"), (F.count(F.lit(1)) % 1024).alias("tail")),
    "SELECT l_returnflag || l_linestatus AS part, count(*) // 1024 AS full_pages, count(*) % 1024 AS tail FROM lineitem GROUP BY 1",
)

# ---------------------------------------------------------------- store and scans


def _store(spark: SparkSession, sf_dir: str, profile: str = "exact_fast") -> DataFrame:
    return materialize(codec.encode(streams.events_by_type(spark, sf_dir), profile, page_size=256, group_pages=4), "store")


_TS = "epoch_us(ts)"
_SPAN = 1_000_000


def _bounds(enc: DataFrame, a: float, b: float) -> tuple[int, int]:
    lo, hi = enc.agg(F.min("min_ts"), F.max("max_ts")).first()
    return lo + int((hi - lo) * a), lo + int((hi - lo) * b)


def _duck_bounds(a: float, b: float) -> str:
    span = f"(SELECT max({_TS}) - min({_TS}) FROM events)"
    low = f"(SELECT min({_TS}) FROM events)"
    return f"{_TS} >= {low} + CAST(trunc({span}::DOUBLE * {a}) AS BIGINT) AND {_TS} < {low} + CAST(trunc({span}::DOUBLE * {b}) AS BIGINT)"


add("w_store_full", lambda spark, sf_dir: scan.scan_full(_store(spark, sf_dir)).select("stream_id", "ts", "value"), f"SELECT event_type AS stream_id, {_TS} AS ts, value FROM events")
for _pct, _a, _b in ((1, 0.5, 0.51), (10, 0.5, 0.6), (50, 0.25, 0.75)):

    def _range(spark: SparkSession, sf_dir: str, a: float = _a, b: float = _b) -> DataFrame:
        enc = _store(spark, sf_dir)
        return scan.scan_range(enc, *_bounds(enc, a, b)).select("stream_id", "ts", "value")

    def _agg(spark: SparkSession, sf_dir: str, a: float = _a, b: float = _b) -> DataFrame:
        enc = _store(spark, sf_dir)
        got = scan.scan_agg(enc, *_bounds(enc, a, b))
        return got.select("stream_id", "n", "min_value", "max_value", F.round("sum_value", 4).alias("sum_value"), F.round("avg_value", 6).alias("avg_value"))

    add(f"w_store_range_{_pct}", _range, f"SELECT event_type AS stream_id, {_TS} AS ts, value FROM events WHERE {_duck_bounds(_a, _b)}")
    add(f"w_store_agg_{_pct}", _agg, f"SELECT event_type AS stream_id, count(*) AS n, min(value) AS min_value, max(value) AS max_value, round(sum(value), 4) AS sum_value, round(avg(value), 6) AS avg_value FROM events WHERE {_duck_bounds(_a, _b)} GROUP BY 1")
add("o_value_scan", lambda spark, sf_dir: scan.scan_where(_store(spark, sf_dir), 300.0, 1e9).select("stream_id", "ts", "value"), f"SELECT event_type AS stream_id, {_TS} AS ts, value FROM events WHERE value BETWEEN 300 AND 1e9")
add("o_point_read", lambda spark, sf_dir: scan.value_at(_store(spark, sf_dir), "click", 17).select("stream_id", "ord", "value"), f"SELECT 'click' AS stream_id, 17::BIGINT AS ord, value FROM (SELECT value, row_number() OVER (ORDER BY ts, event_id) - 1 AS ord FROM events WHERE event_type = 'click') t WHERE ord = 17")

# ---------------------------------------------------------------- operators around decoded data


TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings")
#: The measure of each table that is stored in pages, and the order of its stream.
STORED = {"events": ("value", ("event_id",)), "orders": ("o_totalprice", ("o_orderdate", "o_orderkey")), "lineitem": ("l_extendedprice", streams.LINEITEM), "customer": ("c_acctbal", ("c_custkey",)), "part": ("p_retailprice", ("p_partkey",)), "supplier": ("s_acctbal", ("s_suppkey",))}


def through_pages(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """A table whose measure was encoded to pages and decoded again, joined to its other columns on the ordinal."""
    col, order = STORED[table]
    raw = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    rows = materialize(with_ordinal(raw.withColumn("stream_id", F.lit(table)), "stream_id", list(order)), "rows")
    back = codec.decode(codec.encode(rows.select("stream_id", "ord", F.col(col).alias("value")))).select("ord", F.col("value").alias(col))
    return rows.drop("stream_id", col).join(back, "ord").select(*raw.columns)


def sql(name: str, text: str, duck: str | None = None) -> None:
    """A query over decoded tables: the measures named in ``STORED`` come out of pages."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        import re

        used = [t for t in TABLES if re.search(rf"\b{t}\b", text)]
        for t in used:
            here = through_pages(spark, sf_dir, t) if t in STORED and STORED[t][0] in text else spark.read.parquet(f"{sf_dir}/{t}.parquet")
            here.createOrReplaceTempView(t)
        return spark.sql(text)

    add(name, run, duck or text)


sql("o_filters", "SELECT event_id, value FROM events WHERE value BETWEEN 10 AND 200 AND event_type IN ('click', 'view') AND event_type LIKE '%i%' AND user_id IS NOT NULL")
sql("o_hash_join", "SELECT r.r_name, n.n_name, count(*) AS n, min(c.c_acctbal) AS lo, max(c.c_acctbal) AS hi FROM customer c JOIN nation n ON c.c_nationkey = n.n_nationkey JOIN region r ON n.n_regionkey = r.r_regionkey GROUP BY r.r_name, n.n_name")
sql("o_shuffle_join", "SELECT o.o_orderpriority, count(*) AS n, min(l.l_extendedprice) AS lo FROM lineitem l JOIN orders o ON l.l_orderkey = o.o_orderkey GROUP BY o.o_orderpriority")
sql("o_semi_join", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 300000)")
sql("o_anti_join", "SELECT c_custkey FROM customer c WHERE NOT EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey)")
sql("o_full_outer", "SELECT c.c_custkey, o.o_custkey FROM customer c FULL OUTER JOIN (SELECT DISTINCT o_custkey FROM orders) o ON c.c_custkey = o.o_custkey")
sql("o_distinct", "SELECT count(DISTINCT l_discount) AS discounts, count(DISTINCT l_tax) AS taxes FROM lineitem")
sql("o_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS n, max(l_quantity) AS q FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
sql("o_cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
sql("o_grouping_sets", "SELECT event_type, user_id % 10 AS bucket, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type, user_id % 10), (event_type), ())", "SELECT event_type, bucket, count(*) AS n FROM (SELECT event_type, user_id % 10 AS bucket FROM events) t GROUP BY GROUPING SETS ((event_type, bucket), (event_type), ())")
sql("o_rank", "SELECT l_orderkey, l_linenumber, l_partkey, rank() OVER w AS rk, dense_rank() OVER w AS dr FROM lineitem WINDOW w AS (PARTITION BY l_orderkey ORDER BY l_extendedprice DESC)")
sql("o_lag_lead", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
sql("o_moving", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n, max(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS hi FROM orders")
sql("o_topk", "SELECT event_type, event_id, value FROM (SELECT event_type, event_id, value, row_number() OVER (PARTITION BY event_type ORDER BY value DESC, event_id) AS n FROM events) t WHERE n <= 5")
sql("o_set_ops", "(SELECT c_nationkey AS k FROM customer EXCEPT SELECT s_nationkey FROM supplier) UNION ALL (SELECT s_nationkey FROM supplier INTERSECT SELECT c_nationkey FROM customer)")
sql("o_strings", "SELECT doc_id, lower(lang) AS lang, length(source) AS n, substring(source, 1, 3) AS head FROM documents")
sql("o_dates", "SELECT date_trunc('hour', ts) AS h, count(*) AS n FROM events GROUP BY 1")
sql("o_json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
sql("o_conditional_sums", "SELECT event_type, CAST(sum(CASE WHEN value > 100 THEN 1 ELSE 0 END) AS BIGINT) AS big, count(*) AS n FROM events GROUP BY event_type")
sql(
    "o_asof",
    "SELECT event_id, seen FROM (SELECT event_id, event_type, max(CASE WHEN event_type = 'view' THEN ts END) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS seen FROM events WHERE event_type IN ('view', 'purchase')) t WHERE event_type = 'purchase'",
    "SELECT p.event_id, max(v.ts) AS seen FROM events p LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND v.ts <= p.ts WHERE p.event_type = 'purchase' GROUP BY p.event_id",
)
_TEN = f"CAST(floor({streams._US} / 600000000.0D) AS BIGINT)"
sql(
    "o_interval_join",
    f"SELECT a.event_id AS a, b.event_id AS b FROM (SELECT event_id, user_id, ts, explode(array({_TEN} - 1, {_TEN}, {_TEN} + 1)) AS bucket FROM events) a JOIN (SELECT event_id, user_id, ts, {_TEN} AS bucket FROM events) b ON a.user_id = b.user_id AND a.bucket = b.bucket AND a.event_id < b.event_id AND b.ts >= a.ts - INTERVAL 10 MINUTE AND b.ts <= a.ts + INTERVAL 10 MINUTE",
    "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND b.ts >= a.ts - INTERVAL 10 MINUTE AND b.ts <= a.ts + INTERVAL 10 MINUTE",
)
sql("o_hash_sample", "SELECT event_id FROM events WHERE (event_id * 2654435761) % 1000 < 100")
sql("o_min_by", "SELECT event_type, min_by(event_id, ts) AS first_id FROM events GROUP BY event_type", "SELECT event_type, arg_min(event_id, ts) AS first_id FROM events GROUP BY event_type")
sql("o_pivot", "SELECT * FROM (SELECT l_returnflag, l_linestatus, 1 AS one FROM lineitem) PIVOT (count(one) FOR l_linestatus IN ('F' AS f, 'O' AS o))", "SELECT l_returnflag, nullif(count(*) FILTER (l_linestatus = 'F'), 0) AS f, nullif(count(*) FILTER (l_linestatus = 'O'), 0) AS o FROM lineitem GROUP BY 1")

# ---------------------------------------------------------------- baselines, comparisons, fixtures

from lattice_pages.functions.baselines import CODECS  # noqa: E402
from lattice_pages.operators import compare  # noqa: E402

EXACT_CODECS = ("exact_fast", "exact_upper", *(n for n, k in CODECS.items() if not k.bounded))
BOUNDED_CODECS = ("bounded", *(n for n, k in CODECS.items() if k.bounded))


def _codec_roundtrip(codec_name: str, stream: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        pages = compare.run_pages(streams.stream_df(spark, sf_dir, stream), [codec_name], keep_data=True)
        return compare.decode_pages(pages).select("ord", "value")

    return run


for _n, _k in CODECS.items():
    if not _k.bounded:
        add(f"b_roundtrip_{_n}", _codec_roundtrip(_n, "ev_value"), f"SELECT ord, value FROM ({streams.duck_sql(streams.BY_NAME['ev_value'])}) t")


def _bounded_codec(codec_name: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        src = materialize(streams.stream_df(spark, sf_dir, "ev_value"), "stream")
        out = None
        for e in _EPS:
            r = compare.summary(compare.run_pages(src, [codec_name], eps=e), "codec").select("codec", F.lit(e).alias("eps"), "n", "violations")
            out = r if out is None else out.unionByName(r)
        return out

    return run


for _n in BOUNDED_CODECS:
    add(f"b_bound_{_n}", _bounded_codec(_n), " UNION ALL ".join(f"SELECT '{_n}' AS codec, {e!r}::DOUBLE AS eps, count(*) AS n, 0::BIGINT AS violations FROM events" for e in _EPS))

def sizes(spark: SparkSession, sf_dir: str, names: tuple[str, ...], codecs: tuple, **kw) -> DataFrame:
    """Pages of several streams under several codecs, in one job."""
    return compare.run_pages(all_of(spark, sf_dir, names), list(codecs), **kw)


def _exact14(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compare.summary(sizes(spark, sf_dir, _NAMES14, EXACT_CODECS))


add("w_exact14_ratio", lambda spark, sf_dir: _exact14(spark, sf_dir).select("stream_id", "codec", "n", "raw_bytes", "coded_bytes", "ratio", "mismatches"))
add("w_exact14_wins", lambda spark, sf_dir: measures.wins(_exact14(spark, sf_dir)))
#: The six codecs of which the best is taken stream by stream.
SIX = ("gorilla", "chimp", "erase_xor", "erase_xor_plus", "alp", "falcon")
add("w_best_of_six", lambda spark, sf_dir: compare.summary(sizes(spark, sf_dir, _NAMES14, SIX)).groupBy("stream_id").agg(F.min_by("codec", F.struct("coded_bytes", "codec")).alias("codec"), F.min("coded_bytes").alias("coded_bytes"), F.max("raw_bytes").alias("raw_bytes")))


def _bounded15(spark: SparkSession, sf_dir: str) -> DataFrame:
    src, out = all_of(spark, sf_dir, _NAMES15), None
    for e in _EPS:
        r = compare.summary(compare.run_pages(src, list(BOUNDED_CODECS), eps=e)).withColumn("eps", F.lit(e))
        out = r if out is None else out.unionByName(r)
    return out


add("w_bounded15_ratio", lambda spark, sf_dir: _bounded15(spark, sf_dir).select("stream_id", "codec", "eps", "n", "raw_bytes", "coded_bytes", "ratio", "violations", "max_error"))
add("w_frontier", lambda spark, sf_dir: measures.frontier(compare.summary(sizes(spark, sf_dir, ("ev_value",), EXACT_CODECS), "codec").withColumn("speed", F.col("encode_mb_s"))))
add(
    "w_exact_mismatches",
    lambda spark, sf_dir: _exact14(spark, sf_dir).select("stream_id", "codec", "n", "raw_bytes", "mismatches"),
    " UNION ALL ".join(f"SELECT '{n}' AS stream_id, codec, count(*) AS n, CAST(8 * count(*) AS BIGINT) AS raw_bytes, 0::BIGINT AS mismatches FROM ({streams.duck_sql(streams.BY_NAME[n])}) t, (VALUES {', '.join(f'({p!r})' for p in EXACT_CODECS)}) v(codec) GROUP BY codec" for n in _NAMES14),
)


def large48(spark: SparkSession, sf_dir: str, codecs: tuple = ("exact_fast", "gorilla", "alp", "falcon")) -> DataFrame:
    from lattice_pages.operators.pages import with_ordinal

    src, keys = streams.all_keyed(spark, sf_dir, streams.large48())
    rows = with_ordinal(src, "stream_id", keys).select("stream_id", "ord", "value")
    return compare.run_pages(rows, list(codecs), tail="drop")


def _large48_domains(spark: SparkSession, sf_dir: str) -> DataFrame:
    domains = spark.createDataFrame([(s.name, s.domain) for s in streams.large48()], "stream_id string, domain string")
    sizes_ = compare.summary(large48(spark, sf_dir, ("exact_fast",)))
    return measures.ratio_by_domain(sizes_.join(F.broadcast(domains), "stream_id"))


add("w_large48_domains", _large48_domains)
add("w_large48_ratio", lambda spark, sf_dir: compare.summary(large48(spark, sf_dir, ("exact_fast", "alp")), "codec").select("codec", "n", "raw_bytes", "coded_bytes", "ratio", "mismatches"))


def example_bits(x) -> dict[str, int]:
    """The stages of the worked example on one page: coordinates by admission, residual magnitudes by lane."""
    from lattice_pages.functions.admission import scale_matrix
    from lattice_pages.operators.explain import magnitude_bits

    q, ok = scale_matrix(x)
    s = ok.argmax(axis=0)
    if not (ok.any(axis=0) & ((s == 3) | (s == 5))).all():
        raise ValueError("the example has values of three and of five decimals")
    coarse, fine = q[3][s == 3], magnitude_bits(q[5][s == 5])
    return {"one_lane": magnitude_bits(q[5]), "two_routes": magnitude_bits(coarse) + fine, "coarse_5z_4": magnitude_bits((coarse - 4) // 5) + fine}


def _example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The example's make of values, three decimals (5 z + 4) and five in turn, on the cents of the events."""
    import numpy as np

    from lattice_pages.operators.domains import each_page

    coarse = (5 * F.round(F.col("value") * 100).cast("long") + 4)
    fine = (F.col("ord") % 6).isin(3, 5)
    src = streams.stream_df(spark, sf_dir, "ev_value").withColumn("value", F.when(fine, (coarse * 100 + 21) / F.lit(1e5)).otherwise(coarse / F.lit(1e3)))
    return each_page(src, lambda w: example_bits(w.view(np.float64)), "one_lane long, two_routes long, coarse_5z_4 long").select("page_no", "one_lane", "two_routes", "coarse_5z_4")


_LAG = "lag({0}) OVER (PARTITION BY page_no, {1} ORDER BY ord)"
_DIGITS = "CAST(sum(CASE WHEN {0} = 0 THEN 0 ELSE length(bin(abs({0}))) END) AS BIGINT)"
add(
    "w_example_bits",
    _example,
    f"SELECT page_no, coalesce({_DIGITS.format('one')}, 0) AS one_lane, coalesce({_DIGITS.format('two')}, 0) AS two_routes, coalesce({_DIGITS.format('three')}, 0) AS coarse_5z_4 FROM ("
    f"SELECT page_no, q - {_LAG.format('q', 'true')} AS one, CASE WHEN fine THEN q - {_LAG.format('q', 'fine')} ELSE (5 * z + 4) - {_LAG.format('(5 * z + 4)', 'fine')} END AS two, CASE WHEN fine THEN q - {_LAG.format('q', 'fine')} ELSE z - {_LAG.format('z', 'fine')} END AS three FROM ("
    "SELECT ord, ord // 1024 AS page_no, fine, z, (5 * z + 4) * 100 + CASE WHEN fine THEN 21 ELSE 0 END AS q FROM ("
    "SELECT row_number() OVER (ORDER BY event_id) - 1 AS ord, (row_number() OVER (ORDER BY event_id) - 1) % 6 IN (3, 5) AS fine, CAST(round(value * 100, 0) AS BIGINT) AS z FROM events) a) b) c GROUP BY page_no",
)


def _specials(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every 97th value replaced in turn by a special word; all decoded words, with their ordinals."""
    words = [-(1 << 63), 0x7FF0000000000000, 0xFFF0000000000000 - (1 << 64), 0x7FF8000000000123, 1, 0x7FEFFFFFFFFFFFFF]
    from lattice_pages.functions.sqlfns import float64_word

    src = streams.stream_df(spark, sf_dir, "ev_value").withColumn("word", float64_word("value"))
    pick = F.element_at(F.array(*[F.lit(w).cast("long") for w in words]), (F.floor(F.col("ord") / 97) % 6 + 1).cast("int"))
    src = src.select("stream_id", "ord", F.when(F.col("ord") % 97 == 0, pick).otherwise(F.col("word")).alias("word"))
    return codec.decode(codec.encode(src)).select("ord", "word")


add("w_specials_words", _specials, "SELECT ord, CASE WHEN ord % 97 = 0 THEN ([-9223372036854775808, 9218868437227405312, -4503599627370496, 9221120237041090851, 1, 9218868437227405311])[(ord // 97) % 6 + 1] ELSE CAST(CAST(value AS BIT) AS BIGINT) END AS word FROM (SELECT row_number() OVER (ORDER BY event_id) - 1 AS ord, value FROM events) t")


def _f32(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embedding elements through the codec as widened doubles, narrowed again: equal floats."""
    return codec.decode(encoded(spark, sf_dir, "emb_flat")).select("ord", F.col("value").cast("float").alias("value"))


cost("w_step_lanes", lambda e: f"SELECT page_no, CAST(sum({c.blen(c.zz('r'))}) AS BIGINT) AS before, CAST(sum({c.blen(c.zz(e.idiv('r', '60')))}) AS BIGINT) AS after FROM (SELECT page_no, {e.int('value')} - lag({e.int('value')}) OVER (PARTITION BY page_no ORDER BY pos) AS r FROM ({c.pages(e, 'ev_minute')}) a) b GROUP BY page_no", "ev_minute")


def _digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One hash over all payloads of a stream: the same at any parallelism."""
    enc = encoded(spark, sf_dir, "li_price")
    return enc.groupBy("stream_id").agg(F.bit_xor(F.xxhash64("group_no", "payload")).alias("digest"), F.sum("n").alias("n"))


add("w_digest", _digest)
add("s_source", lambda spark, sf_dir: _source(spark, sf_dir), f"SELECT event_type AS stream_id, {_TS} AS ts, value FROM events WHERE event_type = 'click'")


def _source(spark: SparkSession, sf_dir: str) -> DataFrame:
    from lattice_pages.session import fresh_path
    from lattice_pages.sources import lattice

    lattice.register(spark)
    path = fresh_path(spark, "store")
    codec.save(codec.encode(streams.events_by_type(spark, sf_dir), page_size=256, group_pages=4), path)
    return spark.read.format("lattice").load(path).filter(F.col("stream_id") == "click").select("stream_id", "ts", "value")


def _streamed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows counted back from pages that a streaming query wrote (full pages only)."""
    from lattice_pages.functions.sqlfns import lattice_decode_page
    from lattice_pages.session import fresh_path
    from lattice_pages.streaming import ingest

    rows = materialize(streams.events_by_type(spark, sf_dir).select("stream_id", "ts", "value"), "arrivals")
    path = fresh_path(spark, "ingest")
    sdf = spark.readStream.schema(rows.schema).parquet(rows.inputFiles()[0].rsplit("/", 1)[0])
    q = ingest.encode_stream(sdf, page_size=100).writeStream.format("parquet").option("checkpointLocation", path + "-log").option("path", path).trigger(availableNow=True).start()
    q.awaitTermination()
    pages = spark.read.parquet(path)
    return pages.select("stream_id", F.size(lattice_decode_page("data")).alias("n")).groupBy("stream_id").agg(F.sum("n").alias("n"))


add("s_ingest", _streamed, "SELECT event_type AS stream_id, CAST(count(*) // 100 * 100 AS BIGINT) AS n FROM events GROUP BY 1")

from lattice_pages.plans import workloads  # noqa: E402

workloads.register_all()
