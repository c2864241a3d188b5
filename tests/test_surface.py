import numpy as np
import pytest
from pyspark.sql import functions as F

from lattice_pages.functions import measures, sqlfns
from lattice_pages.functions.baselines import CODECS
from lattice_pages.functions.frame import decode_page, split_frame
from lattice_pages.operators import codec, compare
from lattice_pages.plans import streams
from lattice_pages.session import ship
from lattice_pages.sources import lattice
from lattice_pages.streaming import ingest


@pytest.fixture(scope="module")
def rows(spark, sf):
    ship(spark)
    return streams.events_by_type(spark, sf).cache()


def test_source(spark, rows, tmp_path):
    lattice.register(spark)
    codec.save(codec.encode(rows, page_size=64, group_pages=2), str(tmp_path / "s"))
    df = spark.read.format("lattice").load(str(tmp_path / "s"))
    want = sorted((r.stream_id, r.ord, r.ts, r.value) for r in rows.collect())
    assert sorted((r.stream_id, r.ord, r.ts, r.value) for r in df.collect()) == want
    mid = sorted(w[2] for w in want)[500]
    got = df.filter((F.col("ts") >= mid) & (F.col("stream_id") == "click"))
    assert sorted((r.stream_id, r.ord, r.ts, r.value) for r in got.collect()) == [w for w in want if w[2] >= mid and w[0] == "click"]


def test_all_codecs(rows):
    names = ["exact_fast", "exact_upper", "bounded", *CODECS]
    pages = compare.run_pages(rows, names, eps=1e-3, page_size=256, keep_data=True).cache()
    got = {r.codec: r for r in compare.summary(pages, "codec").collect()}
    assert set(got) == set(names)
    for n, r in got.items():
        assert r.violations == 0 and (r.mismatches == 0 or n == "bounded" or n in CODECS and CODECS[n].bounded)
    assert got["exact_upper"].ratio > got["exact_fast"].ratio > got["gorilla"].ratio
    back = compare.decode_pages(pages.filter("codec = 'chimp'"), 256)
    assert back.count() == rows.count()
    assert sum(r.wins for r in measures.wins(compare.summary(pages)).collect()) == rows.select("stream_id").distinct().count()


def test_streaming_ingest(spark, rows, tmp_path):
    parts = rows.select("stream_id", "ts", "value").orderBy("ts").coalesce(1).sortWithinPartitions("ts")
    parts.write.option("maxRecordsPerFile", 150).parquet(str(tmp_path / "in"))
    sdf = spark.readStream.schema(parts.schema).option("maxFilesPerTrigger", 2).parquet(str(tmp_path / "in"))
    q = ingest.encode_stream(sdf, page_size=50).writeStream.format("parquet").option("checkpointLocation", str(tmp_path / "cp")).option("path", str(tmp_path / "out")).trigger(availableNow=True).start()
    q.awaitTermination()
    pages = spark.read.parquet(str(tmp_path / "out")).collect()
    by = {}
    for r in rows.collect():
        by.setdefault(r.stream_id, []).append(r.value)
    for s, values in by.items():
        own = sorted((p for p in pages if p.stream_id == s), key=lambda p: p.page_no)
        got = np.concatenate([decode_page(*split_frame(p.data)).view(np.float64) for p in own])
        assert len(got) == len(values) // 50 * 50 and sorted(got) == sorted(got) and set(got) <= set(values)
        assert [p.first_ord for p in own] == [50 * i for i in range(len(own))]


def test_streaming_windows(spark, rows, tmp_path):
    src = rows.withColumn("at", F.timestamp_micros("ts")).select("at", "value", "event_id")
    src.write.parquet(str(tmp_path / "in"))
    sdf = spark.readStream.schema(src.schema).parquet(str(tmp_path / "in"))
    q = ingest.windowed(ingest.dedup(sdf, ["event_id"], "at"), "at", "value", "1 hour", late=None).writeStream.format("memory").queryName("w").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    done = {r.start: r.n for r in spark.table("w").collect()}
    want = {r.s: r["count"] for r in src.groupBy(F.window("at", "1 hour").start.alias("s")).count().collect()}
    assert done and all(want[k] == n for k, n in done.items())


def test_functions(spark):
    ship(spark)
    sqlfns.register(spark)
    r = spark.sql("SELECT zigzag(-3L) AS z, bit_len(9L) AS b, min_scale(12.5D) AS s, word_float64(float64_word(0.1D)) AS x").first()
    assert (r.z, r.b, r.s, r.x) == (5, 4, 1, 0.1)
    df = spark.createDataFrame([([4611686018427387904, 4607182418800017408],)], "w array<long>")
    got = df.select(sqlfns.lattice_encode_page("w", F.lit("exact_fast"), F.lit(0.0)).alias("d")).select(sqlfns.lattice_decode_page("d").alias("w"), sqlfns.lattice_page_info("d").alias("i")).first()
    assert got.w == [4611686018427387904, 4607182418800017408] and got.i.n == 2 and got.i.contract == "exact"
