"""Jumps of magnitude and of resolution are laid over every event."""

from lattice_pages.plans.queries import QUERIES


def test_jumps_cover_the_events(spark, sf):
    events = spark.read.parquet(f"{sf}/events.parquet").count()
    got = QUERIES["w_magnitude_resolution"](spark, sf).groupBy("stream_id").sum("n").collect()
    assert {tuple(r) for r in got} == {("magnitude", events), ("resolution", events)}
