"""Scans of stored groups: full, by range, by value, aggregates, points and samples.

Predicates become predicates on the statistics of a group (columns that Parquet can
skip row groups by), then of a page (the directory), then of the rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lattice_pages.operators.codec import NEEDED, ROW_DDL, decode, decoder
from lattice_pages.plans.profiles import PAGE

_COLUMNS = NEEDED


def scan_full(enc: DataFrame) -> DataFrame:
    return decode(enc)


def scan_range(enc: DataFrame, lo: int, hi: int, on: str = "ts") -> DataFrame:
    """Rows with lo <= ts (or ord) < hi."""
    if on == "ts":
        hit = enc.filter((F.col("max_ts") >= lo) & (F.col("min_ts") < hi))
        keep = lambda d: d["max_ts"] >= lo and d["min_ts"] < hi
    else:
        hit = enc.filter((F.col("first_ord") < hi) & (F.col("first_ord") + F.col("n") > lo))
        keep = None
    return hit.select(*_COLUMNS).mapInArrow(decoder(keep=keep), ROW_DDL).filter((F.col(on) >= lo) & (F.col(on) < hi))


def scan_where(enc: DataFrame, lo: float, hi: float) -> DataFrame:
    """Rows with lo <= value <= hi, from pages whose value range meets it."""
    hit = enc.filter((F.col("max_value") >= lo) & (F.col("min_value") <= hi))
    keep = lambda d: d["max_value"] is not None and d["max_value"] >= lo and d["min_value"] <= hi
    return hit.select(*_COLUMNS).mapInArrow(decoder(keep=keep), ROW_DDL).filter(F.col("value").between(lo, hi))


def scan_agg(enc: DataFrame, lo: int | None = None, hi: int | None = None, use_stats: bool = True) -> DataFrame:
    """Rows ``n``, numbers ``n_values``, and their min, max, sum and avg per stream over lo <= ts < hi.

    Pages inside the range are answered by their statistics. Nulls and NaN are counted in ``n`` alone.
    Without a range every row counts, also of streams without ``ts``; a range never holds such a stream's
    rows. Sums of pages are correctly rounded, so they can differ in the last digits from a running sum.
    """
    whole = lo is None and hi is None
    lo, hi = -(1 << 63) if lo is None else lo, (1 << 63) - 1 if hi is None else hi
    fits = lambda d: whole or (d["min_ts"] is not None and d["min_ts"] >= lo and d["max_ts"] < hi)
    meets = lambda d: d["min_ts"] is not None and d["max_ts"] >= lo and d["min_ts"] < hi
    hit = enc if whole else enc.filter((F.col("max_ts") >= lo) & (F.col("min_ts") < hi))

    def read(keep) -> DataFrame:
        rows = hit.select(*_COLUMNS).mapInArrow(decoder(keep=keep), ROW_DDL)
        rows = rows if whole else rows.filter((F.col("ts") >= lo) & (F.col("ts") < hi))
        v = F.when(~F.isnan("value"), F.col("value"))
        return rows.select("stream_id", F.lit(1).cast("long").alias("n"), v.isNotNull().cast("long").alias("n_values"), v.alias("lo"), v.alias("hi"), v.alias("total"))

    if use_stats:
        pages = hit.select("stream_id", F.explode("directory").alias("d"))
        pages = pages if whole else pages.filter((F.col("d.min_ts") >= lo) & (F.col("d.max_ts") < hi))
        parts = pages.select("stream_id", F.col("d.n").cast("long").alias("n"), (F.col("d.n") - F.col("d.n_null") - F.col("d.n_nan")).cast("long").alias("n_values"), F.col("d.min_value").alias("lo"), F.col("d.max_value").alias("hi"), F.col("d.sum_value").alias("total"))
        if not whole:
            parts = parts.unionByName(read(lambda d: meets(d) and not fits(d)))
    else:
        parts = read(None if whole else meets)
    return parts.groupBy("stream_id").agg(F.sum("n").alias("n"), F.sum("n_values").alias("n_values"), F.min("lo").alias("min_value"), F.max("hi").alias("max_value"), F.sum("total").alias("sum_value")).withColumn("avg_value", F.col("sum_value") / F.col("n_values"))


def value_at(enc: DataFrame, stream_id: str, ord_: int) -> DataFrame:
    return scan_range(enc.filter(F.col("stream_id") == stream_id), ord_, ord_ + 1, on="ord")


def sample_pages(enc: DataFrame, share: float, seed: int = 0) -> DataFrame:
    """Rows of hash-chosen pages: the same pages at any parallelism."""
    cut, mod = int(share * 10_000), 10_000

    def keep(d: dict) -> bool:
        return (d["page_no"] * 2654435761 + seed * 40503 + 12345) % 4294967296 % mod < cut

    return enc.select(*_COLUMNS).mapInArrow(decoder(keep=keep), ROW_DDL)


__all__ = ["PAGE", "sample_pages", "scan_agg", "scan_full", "scan_range", "scan_where", "value_at"]
