"""The worked example: its published figures, and the same job on the events."""

import numpy as np

from lattice_pages.plans.queries import QUERIES, example_bits


def test_worked_example_and_its_table(spark, sf):
    assert list(example_bits(np.array([12.579, 12.589, 12.594, 12.59621, 12.599, 12.60381])).values()) == [45, 20, 14]
    events = spark.read.parquet(f"{sf}/events.parquet").count()
    assert QUERIES["w_example_bits"](spark, sf).select("page_no").distinct().count() == -(-events // 1024)
