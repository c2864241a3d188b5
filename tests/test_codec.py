import numpy as np
import pytest
from pyspark.sql import functions as F

from lattice_pages.functions import measures
from lattice_pages.operators import codec, scan
from lattice_pages.plans import streams
from lattice_pages.session import ship


@pytest.fixture(scope="module")
def rows(spark, sf):
    ship(spark)
    return streams.events_by_type(spark, sf).cache()


@pytest.fixture(scope="module")
def enc(rows):
    return codec.encode(rows, page_size=64, group_pages=2).cache()


def test_ordinals_agree(spark, sf):
    a = streams.stream_df(spark, sf, "li_price", "range").collect()
    b = streams.stream_df(spark, sf, "li_price", "window").collect()
    assert sorted(a) == sorted(b) and sorted(r.ord for r in a) == list(range(len(a)))


def test_round_trip(rows, enc):
    want = sorted((r.stream_id, r.ord, r.ts, r.value) for r in rows.collect())
    assert sorted((r.stream_id, r.ord, r.ts, r.value) for r in codec.decode(enc).collect()) == want
    dense = codec.recompress(enc)
    assert sorted((r.stream_id, r.ord, r.ts, r.value) for r in codec.decode(dense).collect()) == want
    assert measures.ratio(dense).first().ratio > measures.ratio(enc).first().ratio > 1.5
    words = codec.decode(enc)
    assert all(r.mismatches == 0 for r in measures.word_mismatches(words, codec.decode(dense)).collect())


def test_bounded_and_tails(rows):
    for eps in (1e-1, 1e-4):
        got = codec.decode(codec.encode(rows, "bounded", eps=eps, page_size=64))
        assert all(r.violations == 0 and r.max_error <= eps for r in measures.bound_report(rows, got, eps).collect())
    full = codec.encode(rows, page_size=64, tail="drop").agg(F.sum("n")).first()[0]
    assert full == sum(r["count"] // 64 * 64 for r in rows.groupBy("stream_id").count().collect())


def test_same_bytes_at_any_parallelism(rows):
    digest = lambda d: sorted((r.stream_id, r.group_no, bytes(r.payload)) for r in d.collect())
    assert digest(codec.encode(rows.repartition(1))) == digest(codec.encode(rows.repartition(7).orderBy(F.rand(3))))


def test_scans(rows, enc):
    data = [(r.stream_id, r.ord, r.ts, r.value) for r in rows.collect()]
    ts = sorted(d[2] for d in data)
    lo, hi = ts[len(ts) // 3], ts[len(ts) // 2]
    inside = [d for d in data if lo <= d[2] < hi]
    tup = lambda df: sorted((r.stream_id, r.ord, r.ts, r.value) for r in df.collect())
    assert tup(scan.scan_range(enc, lo, hi)) == sorted(inside)
    assert tup(scan.scan_range(enc, 5, 9, on="ord")) == sorted(d for d in data if 5 <= d[1] < 9)
    assert tup(scan.scan_where(enc, 100.0, 120.0)) == sorted(d for d in data if 100 <= d[3] <= 120)
    for stats in (True, False):
        got = {r.stream_id: (r.n, r.min_value, r.max_value) for r in scan.scan_agg(enc, lo, hi, stats).collect()}
        for s in {d[0] for d in inside}:
            v = [d[3] for d in inside if d[0] == s]
            assert got[s] == (len(v), min(v), max(v))
    s = data[0][0]
    assert scan.value_at(enc, s, 17).first().value == next(d[3] for d in data if d[:2] == (s, 17))
    assert 0 < scan.sample_pages(enc, 0.5).count() < len(data)


def test_store_and_damage(spark, enc, tmp_path):
    codec.save(enc, str(tmp_path / "s"))
    back = codec.load(spark, str(tmp_path / "s"))
    assert codec.decode(back).count() == codec.decode(enc).count()
    plan = scan.scan_range(back, 0, 1)._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(max_ts)" in plan.replace("IsNotNull(min_ts), ", "") or "GreaterThanOrEqual(max_ts" in plan
    broken = enc.withColumn("payload", F.expr("cast(concat(substring(cast(payload as string), 1, 1), 'zz') as binary)"))
    with pytest.raises(Exception, match="not a page group"):
        codec.decode(broken).count()


def test_words_with_nan_payloads(spark):
    w = np.array([0x7FF8000000000123, 0x8000000000000000, 1, 0x7FF0000000000000], np.uint64).view(np.int64).tolist() * 5
    df = spark.createDataFrame([("s", i, x) for i, x in enumerate(w)], "stream_id string, ord long, word long")
    assert [r.word for r in codec.decode(codec.encode(df)).orderBy("ord").collect()] == w
