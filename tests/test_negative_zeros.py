"""Odd values of the given tables."""

import os

import duckdb

from lattice_pages.plans.queries import ORACLE_SQL, QUERIES


def test_negative_zeros_have_a_scale(spark, sf, tmp_path):
    db, name = duckdb.connect(), "m_kernel_lane_bits_cust_bal"
    for f in os.listdir(sf):
        if f != "customer.parquet":
            os.symlink(f"{sf}/{f}", tmp_path / f)
    odd = "CASE c_custkey % 7 WHEN 3 THEN -0.0::DOUBLE WHEN 4 THEN 0.0::DOUBLE ELSE c_acctbal END"
    db.execute(f"COPY (SELECT * REPLACE ({odd} AS c_acctbal) FROM '{sf}/customer.parquet') TO '{tmp_path}/customer.parquet'")
    db.execute(f"CREATE VIEW customer AS SELECT * FROM '{tmp_path}/customer.parquet'")
    want = db.execute(ORACLE_SQL[name]).fetchall()
    assert sorted(tuple(r) for r in QUERIES[name](spark, str(tmp_path)).collect()) == sorted(want)
