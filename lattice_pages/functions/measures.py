"""Cost and accuracy measures of encoded streams."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lattice_pages.functions.frame import PARTS


def ratio(enc: DataFrame, *by: str) -> DataFrame:
    """Pooled ratio: raw bytes over complete coded bytes, framing and directory included."""
    return enc.groupBy(*by).agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("coded_bytes").alias("coded_bytes"), (F.sum("raw_bytes") / F.sum("coded_bytes")).alias("ratio"))


def saving(a: float, b: float) -> float:
    """Share of b's bytes that a saves."""
    return 1 - a / b


def growth(a: float, b: float) -> float:
    """By how much a is larger than b."""
    return a / b - 1


def word_mismatches(src: DataFrame, dec: DataFrame) -> DataFrame:
    """Positions that differ in any bit, are missing or extra, by stream. Zero for an exact codec.

    Both sides need ``stream_id, ord, word``; they are joined on position.
    """
    j = src.select("stream_id", "ord", F.col("word").alias("a")).join(dec.select("stream_id", "ord", F.col("word").alias("b")), ["stream_id", "ord"], "full_outer")
    return j.groupBy("stream_id").agg(F.count_if(~F.col("a").eqNullSafe(F.col("b"))).alias("mismatches"), F.count(F.lit(1)).alias("n"))


def bound_report(src: DataFrame, dec: DataFrame, eps: float) -> DataFrame:
    """Violations of the bound, largest and mean error, by stream."""
    j = src.select("stream_id", "ord", F.col("value").alias("a")).join(dec.select("stream_id", "ord", F.col("value").alias("b")), ["stream_id", "ord"], "full_outer")
    e = F.abs(F.col("a") - F.col("b"))
    finite = ~F.isnan("a") & (F.abs("a") != float("inf"))
    return j.groupBy("stream_id").agg(F.count(F.lit(1)).alias("n"), F.count_if(finite & ~(e <= eps) | F.col("b").isNull() | F.col("a").isNull()).alias("violations"), F.max(F.when(finite, e)).alias("max_error"), F.avg(F.when(finite, e)).alias("mean_error"))


def bit_breakdown(enc: DataFrame, *by: str) -> DataFrame:
    """Written bits by category, before grouping."""
    return enc.groupBy(*by).agg(*[F.sum(F.col("bits")[i]).alias(k) for i, k in enumerate(PARTS)], F.sum("n").alias("n"))


def wins(results: DataFrame, by: str = "stream_id", codec: str = "codec", size: str = "coded_bytes") -> DataFrame:
    """How many streams each codec compresses best (ties: by name)."""
    from pyspark.sql import Window

    first = results.withColumn("_r", F.row_number().over(Window.partitionBy(by).orderBy(size, codec))).filter("_r = 1")
    return first.groupBy(codec).agg(F.count(F.lit(1)).alias("wins"))


def frontier(results: DataFrame, codec: str = "codec") -> DataFrame:
    """Codecs that no other beats in both ratio and speed."""
    a, b = results.alias("a"), results.alias("b")
    worse = (F.col("b.ratio") >= F.col("a.ratio")) & (F.col("b.speed") >= F.col("a.speed")) & ((F.col("b.ratio") > F.col("a.ratio")) | (F.col("b.speed") > F.col("a.speed")))
    return a.join(b, worse, "left_anti").select(f"a.{codec}", "a.ratio", "a.speed")


def ratio_by_domain(results: DataFrame) -> DataFrame:
    """Pooled ratio by domain, and over all (domain null)."""
    return results.rollup("domain").agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("coded_bytes").alias("coded_bytes"), F.count(F.lit(1)).alias("streams")).withColumn("ratio", F.col("raw_bytes") / F.col("coded_bytes"))
