"""Workloads and operators around the codec, registered beside those of ``queries``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lattice_pages.functions import measures
from lattice_pages.operators import codec, compare, domains, scan
from lattice_pages.operators.pages import with_ordinal
from lattice_pages.plans import costsql as c
from lattice_pages.plans import streams
from lattice_pages.session import fresh_path, materialize

NAMES14 = tuple(s.name for s in streams.EXACT14)
#: Values that a page has at least where the lanes of ``w_magnitude_resolution`` are foretold.
LONG = 64
EPS = (1e-1, 1e-2, 1e-3, 1e-4, 1e-5, 1e-6)
#: The frame and block settings of the structure sweep (13 runs a stream).
SWEEP = tuple(("frame", p, 16) for p in (100, 256, 512, 1000, 1024, 2000, 4000)) + tuple(("block", 1024, b) for b in (4, 8, 16, 32, 64, 128))


def _duck(name: str) -> str:
    return streams.duck_sql(streams.BY_NAME[name])


def register_all() -> None:
    from lattice_pages.plans.queries import add, all_of, cost, sql, through_pages

    # ------------------------------------------------ kernels against the cost layer
    def lane_bits(name: str):
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            return domains.by_domain(streams.stream_df(spark, sf_dir, name)).select("page_no", "one_integer_stream", "routed_lanes")

        return run

    def lane_sql(name: str) -> str:
        one = f"SELECT page_no, CAST(sum({c.blen(c.zz('r'))}) AS BIGINT) AS one_integer_stream FROM ({c.one_lane(c.DUCK, name)}) a GROUP BY page_no"
        routed = f"SELECT page_no, CAST(sum({c.blen(c.zz('r'))}) AS BIGINT) AS routed_lanes FROM ({c.routed(c.DUCK, name)}) a GROUP BY page_no"
        return f"SELECT page_no, coalesce(one_integer_stream, 0) AS one_integer_stream, coalesce(routed_lanes, 0) AS routed_lanes FROM ({one}) x JOIN ({routed}) y USING (page_no)"

    for n in ("ev_value", "part_price", "ord_total", "cust_bal", "li_price", "ev_cum"):
        add(f"m_kernel_lane_bits_{n}", lane_bits(n), lane_sql(n))
    add("w_domain_bits", lambda spark, sf_dir: domains.by_domain(all_of(spark, sf_dir, NAMES14)).groupBy("stream_id").agg(*[(F.sum(d) / F.sum("n")).alias(d) for d in domains.DOMAINS], F.sum("n").alias("n")))
    add("w_lane_stats", lambda spark, sf_dir: domains.lane_stats(all_of(spark, sf_dir, NAMES14)).groupBy("stream_id").agg(F.count(F.lit(1)).alias("pages"), F.avg("lanes").alias("lanes"), (F.sum("largest") / F.sum("n")).alias("coverage"), (F.sum("raw") / F.sum("n")).alias("raw_share"), F.avg("entropy").alias("entropy")))
    rules = ("lossless", "parts", "affine", "factor")
    add(
        "m_invariants",
        lambda spark, sf_dir: domains.invariants(all_of(spark, sf_dir, NAMES14)).groupBy("stream_id").agg(F.count(F.lit(1)).alias("pages"), *[F.sum(r).cast("long").alias(r) for r in rules]),
        " UNION ALL ".join(f"SELECT '{n}' AS stream_id, CAST(ceil(count(*) / 1024.0) AS BIGINT) AS pages, " + ", ".join(f"0::BIGINT AS {r}" for r in rules) + f" FROM ({_duck(n)}) t" for n in NAMES14),
    )
    for n in NAMES14:
        if n not in ("emb_flat",):
            cost(f"w_admission_profile_{n}", lambda e, n=n: "SELECT " + ", ".join(f"CAST(sum(CASE WHEN {c.admits(e, 'value', s)} THEN 1 ELSE 0 END) AS BIGINT) AS s{s}" for s in range(19)) + f" FROM {e.stream(n)} t", n)

    def jumps(spark: SparkSession, sf_dir: str) -> DataFrame:
        """A jump of magnitude needs wider residuals, one of resolution another lane: on the keys of the events, as hundredths.

        Pages shorter than ``LONG`` values, a stream's last, have null lanes: there a lane may cost more than it saves.
        """
        streams.register(spark, sf_dir, ("events",))
        rows = with_ordinal(spark.sql("SELECT event_id, 'events' AS s FROM events"), "s", ["event_id"])
        far = F.when(F.col("ord") % 1024 >= 512, 10_000_000).otherwise(0)
        fine = (F.col("event_id") * 100_000 + 123) / F.lit(1e7)
        both = {"magnitude": (F.col("event_id") + far) / F.lit(100.0), "resolution": F.when(F.col("ord") % 10 == 0, fine).otherwise(F.col("event_id") / F.lit(100.0))}
        df = rows.select("ord", F.explode(F.array(*[F.struct(F.lit(k).alias("stream_id"), v.alias("value")) for k, v in both.items()])).alias("x")).select("x.stream_id", "ord", "x.value")
        long = F.col("n") >= LONG
        return domains.lane_stats(df).select("stream_id", "page_no", "n", F.when(long, F.col("lanes")).alias("lanes"), F.when(long, F.col("raw")).alias("raw"))

    add(
        "w_magnitude_resolution",
        jumps,
        f"SELECT stream_id, page_no, n, CASE WHEN n >= {LONG} THEN lanes END AS lanes, CASE WHEN n >= {LONG} THEN 0::BIGINT END AS raw FROM "
        "(SELECT page_no, count(*) AS n FROM (SELECT (row_number() OVER (ORDER BY event_id) - 1) // 1024 AS page_no FROM events) e GROUP BY page_no) p, (VALUES ('magnitude', 1::BIGINT), ('resolution', 2::BIGINT)) t(stream_id, lanes)",
    )

    # ------------------------------------------------ sweeps through the codec
    def sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
        from lattice_pages.plans.profiles import EXACT_FAST, profile

        pages = compare.run_settings(all_of(spark, sf_dir, NAMES14), [(page, profile(EXACT_FAST, block=block)) for _, page, block in SWEEP])
        got = pages.groupBy("setting", "stream_id").agg(F.sum("n").alias("n"), F.sum("mismatches").alias("mismatches"), (F.sum("raw_bytes") / F.sum("coded_bytes")).alias("ratio"))
        kinds = F.element_at(F.array(*[F.struct(F.lit(kind).alias("sweep"), F.lit(page).alias("page"), F.lit(block).alias("block")) for kind, page, block in SWEEP]), F.col("setting") + 1)
        return got.select(kinds.alias("k"), "stream_id", "n", "mismatches", "ratio").select("k.*", "stream_id", "n", "mismatches", "ratio")

    add(
        "w_structure_sweep",
        lambda spark, sf_dir: sweep(spark, sf_dir).select("sweep", "page", "block", "stream_id", "n", (F.col("mismatches") == 0).alias("passed")),
        f"SELECT sweep, page, block, stream_id, n, true AS passed FROM (VALUES {', '.join(str(x) for x in SWEEP)}) v(sweep, page, block), (" + " UNION ALL ".join(f"SELECT '{n}' AS stream_id, count(*) AS n FROM ({_duck(n)}) t" for n in NAMES14) + ") s",
    )
    add("w_structure_ratio", lambda spark, sf_dir: sweep(spark, sf_dir).groupBy("sweep", "page", "block").agg(F.avg("ratio").alias("ratio"), F.min("ratio").alias("least")))

    def variants(spark: SparkSession, made: dict[str, DataFrame], codecs: tuple[str, ...], **kw) -> DataFrame:
        out = None
        for name, df in made.items():
            one = df.withColumn("stream_id", F.concat("stream_id", F.lit(":" + name)))
            out = one if out is None else out.unionByName(one)
        got = compare.summary(compare.run_pages(materialize(out, "variants"), list(codecs), **kw))
        return got.select(F.substring_index("stream_id", ":", 1).alias("stream"), F.substring_index("stream_id", ":", -1).alias("variant"), "codec", "n", "ratio", "mismatches")

    def beta(spark: SparkSession, sf_dir: str) -> DataFrame:
        src = materialize(streams.stream_df(spark, sf_dir, "li_unit"), "stream")
        cut = lambda b: F.when(F.abs(F.col("value") * F.lit(10.0**b)) < 2.0**52, F.floor(F.col("value") * F.lit(10.0**b)).cast("double")).otherwise(F.col("value") * F.lit(10.0**b)) / F.lit(10.0**b)
        return variants(spark, {str(b): src.withColumn("value", cut(b)) for b in range(1, 19)}, ("exact_fast", "erase_xor", "decimal_neighbor", "gorilla"), page_size=1000)

    add("w_beta_ratio", beta)

    def mixed(spark: SparkSession, sf_dir: str) -> DataFrame:
        made = {}
        for k in (100, 20, 5):
            for burst in (False, True):
                hit = (F.floor(F.col("ord") / 16) if burst else F.col("ord")) % k == 0
                made[f"{'burst' if burst else 'interleaved'} 1 in {k}"] = F.when(hit, F.round(F.col("value") + 0.00003, 5)).otherwise(F.col("value"))
        out = None
        for n in ("li_price", "ev_cum", "part_price"):
            src = streams.stream_df(spark, sf_dir, n)
            for k, v in made.items():
                one = src.withColumns({"value": v, "stream_id": F.lit(f"{n}:{k}")})
                out = one if out is None else out.unionByName(one)
        got = compare.summary(compare.run_pages(materialize(out, "mixed"), ["exact_fast", "one_lane", "reset_state", "erase_xor", "decimal_neighbor"]))
        return got.select(F.substring_index("stream_id", ":", 1).alias("stream"), F.substring_index("stream_id", ":", -1).alias("variant"), "codec", "n", "ratio", "mismatches")

    add("w_mixed_ratio", mixed)

    def reordered(how: str):
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            made = {}
            for n in ("ev_cum", "part_price"):
                src = materialize(streams.stream_df(spark, sf_dir, n), "stream")
                place = F.pmod(F.xxhash64("ord"), F.lit(100))
                for pct in (20, 40, 60, 80, 100) if how == "retain" else (0, 25, 50, 75, 100):
                    if how == "retain":  # the kept rows stay in order
                        rows = src.filter(place < pct).select("stream_id", "value", F.col("ord").alias("k"))
                    else:
                        n_rows = F.broadcast(src.groupBy("stream_id").agg(F.count(F.lit(1)).alias("n")))  # one row
                        rows = src.join(n_rows, "stream_id").select("stream_id", "value", F.when(place < pct, F.pmod(F.xxhash64("ord", F.lit("to")), F.col("n"))).otherwise(F.col("ord")).alias("k"))
                    made[f"{n} {pct}"] = with_ordinal(rows, "stream_id", ["k", "value"]).select("stream_id", "ord", "value")
            return variants(spark, made, ("exact_fast", "one_lane", "erase_xor", "gorilla"))

        return run

    add("w_retain_ratio", reordered("retain"))
    add("w_permute_ratio", reordered("permute"))

    def factoring(spark: SparkSession, sf_dir: str) -> DataFrame:
        src, out = all_of(spark, sf_dir, ("ev_value", "ord_total", "part_price", "ev_epoch")), None
        for e in EPS:
            r = compare.summary(compare.run_pages(src, ["bounded", "bounded_one_lane", "bounded_no_factor"], eps=e)).select("stream_id", "codec", F.lit(e).alias("eps"), "coded_bytes", "violations")
            out = r if out is None else out.unionByName(r)
        return out.groupBy("stream_id", "eps").pivot("codec", ["bounded", "bounded_one_lane", "bounded_no_factor"]).agg(F.max("coded_bytes")).withColumn("saving", 1 - F.col("bounded") / F.col("bounded_no_factor"))

    add("w_factor_bytes", factoring)

    def large(spark: SparkSession, sf_dir: str) -> DataFrame:
        src, keys = streams.all_keyed(spark, sf_dir, streams.large48())
        rows = with_ordinal(src, "stream_id", keys).select("stream_id", "ord", "value")
        return codec.decode(codec.encode(rows, tail="drop")).select("stream_id", "ord", "value")

    add("w_large48_roundtrip", large, " UNION ALL ".join(f"SELECT '{s.name}' AS stream_id, ord, value FROM (SELECT *, count(*) OVER () AS total FROM ({_large_duck(s)}) t) u WHERE ord < total // 1024 * 1024" for s in streams.large48()))

    # ------------------------------------------------ nulls, types, binary32
    def holes(spark: SparkSession, sf_dir: str) -> DataFrame:
        src = streams.stream_df(spark, sf_dir, "ev_value")
        return codec.decode(codec.encode(src.withColumn("value", F.when(F.col("ord") % 5 != 0, F.col("value"))))).select("ord", "value")

    add("w_null_roundtrip", holes, f"SELECT ord, CASE WHEN ord % 5 <> 0 THEN value END AS value FROM ({_duck('ev_value')}) t")

    def hole_words(spark: SparkSession, sf_dir: str) -> DataFrame:
        src = streams.stream_df(spark, sf_dir, "ev_value").select("stream_id", "ord", F.when(F.col("ord") % 3 != 1, F.col("ord") * 1000003 - 17).alias("word"))
        return codec.decode(codec.recompress(codec.encode(src))).select("ord", "word")

    add("w_null_words", hole_words, f"SELECT ord, CASE WHEN ord % 3 <> 1 THEN ord * 1000003 - 17 END AS word FROM ({_duck('ev_value')}) t")

    def typed(table: str, col: str, order: tuple[str, ...], kind: str | None = None):
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            raw = spark.read.parquet(f"{sf_dir}/{table}.parquet")
            value = F.col(col).cast(kind) if kind else F.col(col)
            rows = with_ordinal(raw.select(F.lit(col).alias("stream_id"), value.alias("value"), *[F.col(o).alias(f"k{i}") for i, o in enumerate(order)]), "stream_id", [f"k{i}" for i in range(len(order))])
            coded = codec.encode(codec.to_words(rows.select("stream_id", "ord", "value")), domain="integer")
            return codec.from_words(codec.decode(coded), dict(rows.dtypes)["value"]).select("ord", "value")

        return run

    for name, table, col, order, kind, duck in (
        ("int", "part", "p_size", ("p_partkey",), None, "p_size"), ("timestamp", "events", "ts", ("event_id",), None, "ts"), ("date", "orders", "o_orderdate", ("o_orderdate", "o_orderkey"), "date", "CAST(o_orderdate AS DATE)"),
        ("decimal", "lineitem", "l_extendedprice", streams.LINEITEM, "decimal(18,2)", "CAST(l_extendedprice AS DECIMAL(18,2))"), ("key", "lineitem", "l_orderkey", streams.LINEITEM, None, "l_orderkey"),
    ):
        add(f"w_{name}_roundtrip", typed(table, col, order, kind), f"SELECT row_number() OVER (ORDER BY {', '.join(order)}) - 1 AS ord, {duck} AS value FROM {table}")

    def floats(spark: SparkSession, sf_dir: str) -> DataFrame:
        return streams.stream_df(spark, sf_dir, "emb_flat").withColumn("value", F.col("value").cast("float"))

    add("w_f32_roundtrip", lambda spark, sf_dir: codec.decode(codec.encode(floats(spark, sf_dir))).select("ord", F.col("value").cast("float").alias("value")), f"SELECT ord, value::FLOAT AS value FROM ({_duck('emb_flat')}) t")

    def f32_bounded(spark: SparkSession, sf_dir: str) -> DataFrame:
        src, out = materialize(floats(spark, sf_dir), "floats"), None
        wide = src.withColumn("value", F.col("value").cast("double"))
        for e in EPS:
            r = measures.bound_report(wide, codec.decode(codec.encode(src, "bounded", eps=e)), e).select(F.lit(e).alias("eps"), "n", "violations")
            out = r if out is None else out.unionByName(r)
        return out

    add("w_f32_bounded", f32_bounded, " UNION ALL ".join(f"SELECT {e!r}::DOUBLE AS eps, count(*) AS n, 0::BIGINT AS violations FROM ({_duck('emb_flat')}) t" for e in EPS))

    # ------------------------------------------------ aggregates over odd values
    def agg(with_ts: bool):
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            rows = streams.events_by_type(spark, sf_dir)
            rows = rows.withColumn("value", F.when(F.col("ord") % 7 == 0, F.lit(float("nan"))).when(F.col("ord") % 11 == 0, F.lit(None)).otherwise(F.col("value")))
            enc = codec.encode(rows if with_ts else rows.drop("ts"), page_size=256, group_pages=4)
            return scan.scan_agg(enc).select("stream_id", "n", "n_values", "min_value", "max_value", F.round("sum_value", 4).alias("sum_value"))

        return run

    odd = "SELECT event_type AS stream_id, count(*) AS n, count(v) AS n_values, min(v) AS min_value, max(v) AS max_value, round(sum(v), 4) AS sum_value FROM (SELECT event_type, CASE WHEN ord % 7 <> 0 AND ord % 11 <> 0 THEN value END AS v FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY ts, event_id) - 1 AS ord FROM events) t) u GROUP BY 1"
    add("o_agg_nan", agg(True), odd)
    add("o_agg_no_ts", agg(False), odd)

    # ------------------------------------------------ sources and joins
    def ingest(kind: str):
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            path = fresh_path(spark, kind)
            src = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "value")
            src.write.format(kind).save(path)
            back = spark.read.schema("event_id long, value double").format(kind).load(path)
            rows = with_ordinal(back.withColumn("stream_id", F.lit("events")), "stream_id", ["event_id"])
            return codec.decode(codec.encode(rows.select("stream_id", "ord", "value"))).select("ord", "value")

        return run

    for kind in ("csv", "json", "orc"):
        add(f"o_ingest_{kind}", ingest(kind), f"SELECT ord, value FROM ({_duck('ev_value')}) t")

    def verified(spark: SparkSession, sf_dir: str) -> DataFrame:
        src = materialize(streams.stream_df(spark, sf_dir, "li_price"), "stream")
        back = codec.decode(codec.encode(src)).select("stream_id", "ord", F.col("value").alias("back"))
        return src.hint("merge").join(back, ["stream_id", "ord"]).groupBy("stream_id").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("value") != F.col("back")).alias("different"))

    add("o_merge_join", verified, "SELECT 'li_price' AS stream_id, count(*) AS n, 0::BIGINT AS different FROM lineitem")

    def hashed(spark: SparkSession, sf_dir: str) -> DataFrame:
        line, orders = through_pages(spark, sf_dir, "lineitem"), through_pages(spark, sf_dir, "orders")
        return line.join(orders.hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.max("l_extendedprice").alias("hi"), F.min("o_totalprice").alias("lo"))

    add("o_shuffle_hash_join", hashed, "SELECT o_orderpriority, count(*) AS n, max(l_extendedprice) AS hi, min(o_totalprice) AS lo FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")

    def ranges(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Every customer's key as an ordinal of the store: the page that holds it, by an equi-join on the bucket."""
        enc = materialize(codec.encode(streams.stream_df(spark, sf_dir, "ev_value"), page_size=256), "store")
        pages = enc.select(F.explode("directory").alias("d")).select(F.col("d.page_no").alias("page_no"), (F.col("d.page_no") * 256).alias("first"), F.col("d.n").alias("n"), F.explode(F.sequence(F.floor(F.col("d.page_no") * 256 / 1024), F.floor((F.col("d.page_no") * 256 + F.col("d.n") - 1) / 1024))).alias("bucket"))
        keys = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("k"), F.floor(F.col("c_custkey") / 1024).alias("bucket"))
        return keys.join(pages, "bucket").filter("k >= first AND k < first + n").select("k", "page_no")

    add("o_range_join", ranges, "SELECT c_custkey AS k, c_custkey // 256 AS page_no FROM customer WHERE c_custkey >= 0 AND c_custkey < (SELECT count(*) FROM events)")

    def file_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
        path = fresh_path(spark, "files")
        codec.save(codec.encode(streams.events_by_type(spark, sf_dir)), path)
        files = codec.load(spark, path).select(F.col("_metadata.file_name").alias("file"), F.col("_metadata.file_size").alias("bytes"), "raw_bytes", "coded_bytes")
        return files.groupBy("file").agg(F.max("bytes").alias("bytes"), F.sum("raw_bytes").alias("raw_bytes"), F.sum("coded_bytes").alias("coded_bytes"))

    add("o_file_sizes", file_sizes)
    sql("o_statistics", "SELECT event_type, percentile(value, 0.5) AS median, round(stddev_samp(value), 6) AS sd, round(corr(value, CAST(event_id AS DOUBLE)), 6) AS r FROM events GROUP BY event_type", "SELECT event_type, quantile_cont(value, 0.5) AS median, round(stddev_samp(value), 6) AS sd, round(corr(value, event_id::DOUBLE), 6) AS r FROM events GROUP BY event_type")
    sql("o_array_agg", "SELECT o_custkey, to_json(transform(array_sort(collect_list(struct(o_orderkey, o_totalprice))), x -> x.o_orderkey)) AS keys, max(o_totalprice) AS hi FROM orders GROUP BY o_custkey", "SELECT o_custkey, to_json(list(o_orderkey ORDER BY o_orderkey))::VARCHAR AS keys, max(o_totalprice) AS hi FROM orders GROUP BY o_custkey")
    sql("o_array_functions", "SELECT o_custkey, size(filter(p, x -> x > 100000)) AS big, aggregate(p, CAST(0 AS DOUBLE), (a, x) -> greatest(a, x)) AS hi, element_at(slice(p, 1, 1), 1) AS lo FROM (SELECT o_custkey, array_sort(collect_list(o_totalprice)) AS p FROM orders GROUP BY o_custkey) t", "SELECT o_custkey, count(*) FILTER (o_totalprice > 100000) AS big, max(o_totalprice) AS hi, min(o_totalprice) AS lo FROM orders GROUP BY o_custkey")
    sql("o_map_functions", "SELECT event_type, k AS bucket, v AS n FROM (SELECT event_type, explode(transform_values(map_from_entries(collect_list(struct(b, n))), (k, v) -> v * 2)) AS (k, v) FROM (SELECT event_type, CAST(floor(value / 100) AS BIGINT) AS b, count(*) AS n FROM events GROUP BY 1, 2) t GROUP BY event_type) u", "SELECT event_type, CAST(floor(value / 100) AS BIGINT) AS bucket, count(*) * 2 AS n FROM events GROUP BY 1, 2")
    sql("s_session_windows", "SELECT user_id, session_window.start AS start, count(*) AS n, max(value) AS hi FROM events GROUP BY user_id, session_window(ts, '30 minutes')", "SELECT user_id, min(ts) AS start, count(*) AS n, max(value) AS hi FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS fresh FROM events) t) u GROUP BY user_id, s")


def _large_duck(s: streams.Stream) -> str:
    """``ord, value`` of one of the 48 streams in DuckDB."""
    if s.name.endswith("_gap"):
        us = streams._DUCK_US
        kind = s.name.split("_")[1]
        return f"SELECT row_number() OVER (ORDER BY event_id) - 1 AS ord, gap::DOUBLE / 1000000.0::DOUBLE AS value FROM (SELECT event_id, event_type, {us} - lag({us}) OVER (PARTITION BY event_type ORDER BY event_id) AS gap FROM events) g WHERE event_type = '{kind}' AND gap IS NOT NULL"
    return s.duck_sql().replace(f"CAST({streams._US} AS DOUBLE) / 1000000.0D", f"{streams._DUCK_US}::DOUBLE / 1000000.0::DOUBLE")
