"""Registered queries cover their whole input."""

from lattice_pages.plans.queries import QUERIES


def test_full_outer_has_every_key(spark, sf):
    got = QUERIES["o_full_outer"](spark, sf).collect()
    customers = {r[0] for r in spark.read.parquet(f"{sf}/customer.parquet").select("c_custkey").collect()}
    ordering = {r[0] for r in spark.read.parquet(f"{sf}/orders.parquet").select("o_custkey").collect()}
    assert {r.c_custkey for r in got} - {None} == customers and {r.o_custkey for r in got} - {None} == ordering


def test_specials_returns_every_word(spark, sf):
    got = QUERIES["w_specials_words"](spark, sf).select("ord").collect()
    assert sorted(r.ord for r in got) == list(range(spark.read.parquet(f"{sf}/events.parquet").count()))


def test_beta_covers_streams_precisions_and_rows(spark, sf):
    got = QUERIES["w_beta_admission"](spark, sf).groupBy("stream_id", "beta").sum("n").collect()
    assert len(got) == 14 * 18
    lines = spark.read.parquet(f"{sf}/lineitem.parquet").count()
    assert {r[2] for r in got if r.stream_id == "li_unit"} == {lines} and lines > 5000
