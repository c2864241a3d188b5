"""Streams that are numbered together, and settings that share an exchange."""

import pytest
from pyspark.sql import functions as F

from lattice_pages.functions import admission, baselines
from lattice_pages.operators import compare
from lattice_pages.plans import streams
from lattice_pages.plans.profiles import EXACT_FAST, EXACT_UPPER, profile

SF = "/root/testdata/sf0.001"


def test_together_gives_the_rows_of_each_stream(spark):
    many = [streams.BY_NAME[n] for n in ("li_tax", "part_price", "li_unit", "ev_value", "ev_cum", "ev_epoch")]
    got = streams.together(spark, SF, tuple(many))
    for s in many:
        want, mine = streams.stream_df(spark, SF, s), got.filter(F.col("stream_id") == s.name)
        assert mine.count() == want.count() and mine.exceptAll(want).count() == 0


def test_settings_give_the_sizes_of_single_runs(spark):
    df = streams.stream_df(spark, SF, "ev_epoch").localCheckpoint()
    settings = [(100, EXACT_FAST), (256, EXACT_UPPER), (1000, profile(EXACT_FAST, block=4)), (1024, EXACT_FAST)]
    got = {r[0]: tuple(r)[1:] for r in compare.run_settings(df, settings).groupBy("setting").agg(F.sum("n"), F.sum("coded_bytes"), F.sum("mismatches"), F.count("*")).collect()}
    for k, (size, p) in enumerate(settings):
        want = compare.run_pages(df, [p], page_size=size).agg(F.sum("n"), F.sum("coded_bytes"), F.sum("mismatches"), F.count("*")).first()
        assert got[k] == tuple(want)
    with pytest.raises(ValueError):
        compare.run_settings(df, [(100, profile("bounded"))])


def test_codecs_of_a_page_share_its_scales():
    import numpy as np

    words = np.round(np.arange(1024) / 7, 2).view(np.int64)
    admission._matrix.cache_clear()
    for name in ("alp", "falcon", "erase_xor", "erase_xor_plus", "decimal_neighbor"):
        c = baselines.get(name)
        assert (c.decode_page(c.encode_page(words)) == words).all()
    assert admission._matrix.cache_info().misses == 1
