"""Validity bits, statistics over odd values, typed and binary32 pages, reports of bad pages."""

import math
from datetime import date, datetime
from decimal import Decimal

import numpy as np
import pytest
from pyspark.sql import functions as F

from lattice_pages.functions.frame import PageFormatError, decode_page, encode_page
from lattice_pages.operators import codec, scan
from lattice_pages.plans.profiles import profile

NAN, INF = float("nan"), float("inf")


def test_null_words_come_back(spark):
    words = [4611686018427387904, None, 4607182418800017409, None, -1, 0, None]
    df = spark.createDataFrame([("s", i, w) for i, w in enumerate(words)], "stream_id string, ord long, word long")
    for p in ("exact_fast", "exact_upper"):
        enc = codec.encode(df, p, page_size=3)
        assert [r.word for r in codec.decode(enc).orderBy("ord").collect()] == words
        assert [r.word for r in codec.decode(codec.recompress(enc)).orderBy("ord").collect()] == words


def test_null_values_and_refused_nulls(spark):
    values = [None, None, 1.5, None, NAN, 2.25, INF, None]
    df = spark.createDataFrame([("s", i, v) for i, v in enumerate(values)], "stream_id string, ord long, value double")
    got = [r.value for r in codec.decode(codec.encode(df, page_size=4)).orderBy("ord").collect()]
    assert [v is None for v in got] == [v is None for v in values] and got[2] == 1.5 and math.isnan(got[4]) and got[6] == INF
    nothing = spark.createDataFrame([("s", i, None) for i in range(5)], "stream_id string, ord long, value double")
    assert [r.value for r in codec.decode(codec.encode(nothing)).collect()] == [None] * 5
    for bad in (df.withColumn("ord", F.when(F.col("ord") > 3, F.col("ord"))), df.withColumn("ts", F.lit(None).cast("long"))):
        with pytest.raises(Exception, match="must not be null"):
            codec.encode(bad).collect()


def test_aggregates_with_and_without_times(spark):
    rows = [("a", i, i * 10, v) for i, v in enumerate([1.0, NAN, 7.0, None, -2.0, INF, 3.0])] + [("b", 0, 5, NAN)]
    df = spark.createDataFrame(rows, "stream_id string, ord long, ts long, value double")
    enc = codec.encode(df, page_size=2, group_pages=2)
    for lo, hi in ((None, None), (0, 50), (15, 45), (900, 901)):
        both = [sorted(map(tuple, scan.scan_agg(enc, lo, hi, use_stats=u).collect())) for u in (True, False)]
        assert both[0] == both[1]
        want = {}
        for s, _, t, v in rows:
            if lo is None or lo <= t < hi:
                n, xs = want.setdefault(s, [0, []])
                want[s][0] += 1
                if v is not None and not math.isnan(v):
                    xs.append(v)
        assert both[0] == sorted((s, n, len(xs), min(xs, default=None), max(xs, default=None), sum(xs) if xs else None, sum(xs) / len(xs) if xs else None) for s, (n, xs) in want.items())
    plain = codec.encode(df.filter("stream_id = 'a'").drop("ts"), page_size=2)
    assert [r.n for r in scan.scan_agg(plain).collect()] == [7] and scan.scan_agg(plain, 0, 100).count() == 0


@pytest.mark.parametrize("p", ["exact_fast", "exact_upper"])
def test_binary32_pages(p):
    x = np.round(np.cumsum(np.random.default_rng(1).normal(size=1000)), 2).astype(np.float32)
    x[::97] = [np.nan, np.inf, -0.0, 1e-42, 3.1415927, -np.inf, 0, 1e30, 5, 6, 7]
    w = x.view(np.uint32).astype(np.int64)
    own = profile(p, domain="binary32")
    meta, body, _ = encode_page(w, own)
    assert (decode_page(meta, body, "exact32") == w).all() and len(meta) + len(body) < 2000
    with pytest.raises(PageFormatError):
        decode_page(meta, body, "exact")


@pytest.mark.parametrize("eps", [1e-1, 1e-3, 1e-5])
def test_bounded_binary32(eps):
    x = np.cumsum(np.random.default_rng(2).normal(size=1000)).astype(np.float32)
    x[5] = np.inf
    p = profile("bounded", eps, domain="binary32")
    back = decode_page(*encode_page(x.view(np.uint32).astype(np.int64), p)[:2]).astype(np.uint32).view(np.float32)
    fine = np.isfinite(x)
    assert (np.abs(back[fine].astype(float) - x[fine].astype(float)) <= eps).all() and back[5] == np.inf


@pytest.mark.parametrize("p", ["exact_fast", "exact_upper"])
def test_integer_pages(p):
    r = np.random.default_rng(3)
    for w in (np.arange(1000) * 60 + 7, r.integers(-(1 << 63), (1 << 63) - 1, 500), np.array([-(1 << 63), (1 << 63) - 1, 0, -1]), np.array([5])):
        w = w.astype(np.int64)
        assert (decode_page(*encode_page(w, profile(p, domain="integer"))[:2], "exact_integer") == w).all()
    with pytest.raises(ValueError):
        profile("bounded", domain="integer")


def test_typed_columns(spark):
    rows = [(0, 5, Decimal("12.30"), Decimal("7"), date(1969, 12, 30), datetime(2024, 1, 2, 3, 4, 5, 678901), True), (1, -7, Decimal("-0.05"), Decimal("-9"), date(2030, 1, 1), datetime(1960, 1, 1), False), (2, None, None, None, None, None, None)]
    df = spark.createDataFrame(rows, "ord long, i int, d decimal(18,2), e decimal(5,0), day date, t timestamp, b boolean")
    kinds = dict(df.dtypes)
    for c in df.columns[1:]:
        src = df.select(F.lit("s").alias("stream_id"), "ord", F.col(c).alias("value"))
        back = codec.from_words(codec.decode(codec.encode(codec.to_words(src), domain="integer")), kinds[c])
        assert [r.value for r in back.orderBy("ord").collect()] == [r.value for r in src.orderBy("ord").collect()], c
        assert dict(back.dtypes)["value"] == kinds[c]
    with pytest.raises(ValueError):
        codec.to_words(df.select(F.col("d").cast("decimal(38,2)").alias("value")))


def test_report_of_bad_pages(spark):
    df = spark.range(1000).select(F.lit("s").alias("stream_id"), F.col("id").alias("ord"), (F.col("id") / 4).alias("value"))
    enc = codec.encode(df, page_size=100, group_pages=5).cache()
    broken = enc.withColumn("payload", F.when(F.col("group_no") == 1, F.expr("substring(payload, 1, 40)")).otherwise(F.col("payload")))
    got = codec.decode(broken, on_corrupt="report")
    assert got.filter("error IS NULL").count() == 500 and sorted(r.ord for r in got.filter("error IS NOT NULL").collect()) == [500, 600, 700, 800, 900]
    assert codec.decode(broken, on_corrupt="skip").count() == 500
    with pytest.raises(Exception):
        codec.decode(broken).count()


def test_writer_of_the_source(spark):
    from lattice_pages.session import fresh_path
    from lattice_pages.sources import lattice

    lattice.register(spark)
    df = spark.range(1000).select(F.concat(F.lit("s"), F.col("id") % 2).alias("stream_id"), F.floor(F.col("id") / 2).alias("ord"), F.col("id").alias("ts"), (F.col("id") / 4).alias("value"))
    path = fresh_path(spark, "written").removeprefix("file://")
    codec.encode(df, page_size=50, group_pages=2).write.format("lattice").mode("append").save(path)
    read = lambda: sorted((r.stream_id, r.ord, r.value) for r in spark.read.format("lattice").load(path).collect())
    want = sorted((r.stream_id, r.ord, r.value) for r in df.collect())
    assert read() == want
    codec.encode(df, page_size=50, group_pages=2).write.format("lattice").mode("overwrite").save(path)
    assert read() == want
    spark.sql(f"CREATE TEMPORARY VIEW lattice_written USING lattice OPTIONS (path '{path}')")
    assert spark.sql("SELECT count(*) AS n FROM lattice_written WHERE ts < 100").first().n == 100
