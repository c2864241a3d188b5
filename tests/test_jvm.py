"""The JVM's page kernels: the same bytes as the numpy ones, in a small part of the time."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from lattice_pages.functions.frame import PARTS, encode_page
from lattice_pages.jvm import udf
from lattice_pages.operators import codec, compare
from lattice_pages.plans.profiles import EXACT_FAST, EXACT_UPPER, profile


def _pages() -> list[np.ndarray]:
    rng = np.random.default_rng(5)
    cents = np.round(rng.random(1024) * 1e5, 2)
    odd = np.array([0.0, -0.0, np.nan, np.inf, -np.inf, 1e300, 5e-324, 2.0**63, -(2.0**63), 9.2e18, 0.1, 123456789.25] * 9)
    values = [cents, cents / rng.integers(1, 50, 1024), odd, rng.permutation(odd), rng.integers(-50, 50, 700) * 0.25, np.cumsum(rng.integers(0, 3, 500) * 70.0), np.where(rng.random(400) < 0.1, rng.random(400), cents[:400])]
    words = [v.view(np.int64) for v in values] + [rng.integers(-(2**63), 2**63 - 1, 200)]
    return words + [w[:n] for w in words[:3] for n in (1, 2, 3, 17)]


@pytest.mark.parametrize("p", [EXACT_FAST, EXACT_UPPER, *map(profile, ("no_prediction", "one_lane", "reset_state", "no_rice", "no_split", "no_resgcd")), replace(EXACT_FAST, block=128), replace(EXACT_UPPER, block=5, alpha=0.05)], ids=str)
def test_jvm_and_numpy_write_the_same_bytes(spark, p):
    pages = _pages()
    df = spark.createDataFrame([(i, w.astype("<i8").tobytes()) for i, w in enumerate(pages)], "i int, words binary")
    for i, data in df.select("i", udf.coded(spark, "words", udf.spec(p, True))).collect():
        meta, payload, bits, _, _, different = udf.unpack(bytes(data))
        want = encode_page(np.ascontiguousarray(pages[i]), p)
        assert (meta, payload, dict(zip(PARTS, bits.tolist()))) == want and different == 0


def test_jvm_plans_are_fast(spark):
    """Pages of quotients, which no scale covers, took numpy 230 ms each to plan densely."""
    df = spark.range(40_000).select(F.lit("s").alias("stream_id"), F.col("id").alias("ord"), (F.round(F.rand(3) * 1e5, 2) / F.floor(F.rand(4) * 50 + 1)).alias("value"))
    pages = compare.run_pages(df, ["exact_upper"])
    s = pages.agg(F.count("*"), F.sum("encode_s"), F.sum("mismatches")).first()
    assert s[0] == 40 and s[1] / s[0] < 0.1 and s[2] == 0


def test_encode_in_the_jvm_keeps_times_and_nulls(spark):
    df = spark.range(5000).select(F.lit("s").alias("stream_id"), F.col("id").alias("ord"), F.when(F.col("id") % 7 != 0, F.col("id") / 100).alias("value"), (F.col("id") * 3).alias("ts"))
    enc = codec.encode(df, group_pages=2)
    assert "lattice_page" in enc._jdf.queryExecution().optimizedPlan().toString()
    back = codec.decode(enc).select("stream_id", "ord", "value", "ts")
    assert back.count() == 5000 and back.exceptAll(df).count() == 0
    assert enc.count() == 3 and enc.filter("valid is null or ts is null").count() == 0
    assert not udf.covers(profile("bounded")) and not udf.covers(replace(EXACT_FAST, domain="integer"))
