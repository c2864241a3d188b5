"""Kernels work on arrays, and pages spread over the tasks: counted, not timed."""

import numpy as np
import pytest

from lattice_pages.functions import baselines, bits, frame, rawlane, residuals
from lattice_pages.operators import compare
from lattice_pages.plans.profiles import profile


def unit_prices(n=1024):
    r = np.random.default_rng(7)
    return (np.round(r.uniform(900, 90000, n), 2) / r.integers(1, 51, n)).view(np.int64)


def test_upper_profile_costs_all_predictors_at_once(monkeypatch):
    calls, words, was = [0], unit_prices(), residuals.bit_length

    def counted(v):
        calls[0] += 1
        return was(v)

    monkeypatch.setattr(residuals, "bit_length", counted)
    meta, body, _ = frame.encode_page(words, profile("exact_upper"))
    assert (frame.decode_page(meta, body) == words).all()
    assert calls[0] < 1500  # one call for each predictor, divisor and form made many thousand


@pytest.mark.parametrize("name", ["gorilla", "chimp", "erase_xor", "erase_xor_plus"])
def test_codecs_read_fields_together(name, monkeypatch):
    calls, words, was = [0], np.round(np.random.default_rng(8).normal(0, 50, 1024), 2).view(np.int64), bits.Reader.get

    def counted(self, width):
        calls[0] += 1
        return was(self, width)

    monkeypatch.setattr(bits.Reader, "get", counted)
    codec = baselines.get(name)
    assert (codec.decode_page(codec.encode_page(words)) == words).all()
    assert calls[0] < len(words)  # window headers only


def test_windows_and_ranges_equal_plain_search():
    r = np.random.default_rng(9)
    x = r.integers(1, 2**63, 400).astype(np.uint64) >> r.integers(0, 40, 400).astype(np.uint64) << r.integers(0, 20, 400).astype(np.uint64)
    x = x[x > 0]
    fresh, lead, tail = rawlane.windows(x)
    now = None
    for v, f, a, b in zip(x.tolist(), fresh, lead, tail):
        c, d = 64 - v.bit_length(), (v & -v).bit_length() - 1
        new = now is None or c < now[0] or d < now[1]
        now = (c, d) if new else now
        assert new == f and now == (a, b)
    values = np.concatenate([r.normal(0, 1, 50), r.normal(0, 1e-3, 50), [0.0, -0.0, 0.1, -0.1, 1e308, -1e308]])
    for eps in (1e-1, 1e-3, 1e300):
        for v, a, b in zip(values, *baselines._within(values, eps)):
            for rank, near in ((a, True), (b, True), (a - 1, False), (b + 1, False)):
                if abs(rank) <= int(baselines._TOP):
                    assert (abs(v - baselines._unrank(np.array([rank], np.int64))[0]) <= eps) == near


def test_pages_are_not_merged_into_few_tasks(spark):
    df = spark.range(40 * 1024).selectExpr("'s' AS stream_id", "id AS ord", "id / 4.0D AS value")
    pages = compare.run_pages(df, ["plain"])
    pages.count()
    tasks = pages.selectExpr("spark_partition_id() AS p", "page_no").distinct().collect()
    assert len(tasks) == 40 and len({t.p for t in tasks}) > 2
    assert pages.rdd.getNumPartitions() >= 4 * spark.sparkContext.defaultParallelism
