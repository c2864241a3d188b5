"""Dense ordinals and page groups of ordered streams, without a single-task window.

A stream table has ``stream_id string, ord bigint, value double`` and optionally
``word bigint`` (the 64 bits, where NaN payloads matter) and ``ts`` (microseconds).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from lattice_pages.plans.profiles import PAGE
from lattice_pages.session import materialize

GROUP_PAGES = 64
#: Pages that are measured alone travel in smaller groups, so that slow streams spread over the tasks.
FEW_PAGES = 8


def with_ordinal(df: DataFrame, stream_col: str, order_cols: list[str], method: str = "range") -> DataFrame:
    """Adds ``ord``: 0, 1, 2, ... within each stream, in the order of ``order_cols``.

    ``range``: range-partition by (stream, keys), number rows within each partition, add
    what the earlier partitions hold of the stream; the table of such counts has one row
    for each stream and partition. ``window``: one window per stream, for small streams.
    """
    if method == "window":
        return df.withColumn("ord", F.row_number().over(Window.partitionBy(stream_col).orderBy(*order_cols)).cast("long") - 1)
    parts = materialize(df.repartitionByRange(stream_col, *order_cols).withColumn("_part", F.spark_partition_id()), "ordinals")
    inside = F.row_number().over(Window.partitionBy(stream_col, "_part").orderBy(*order_cols)).cast("long")
    sizes = parts.groupBy(stream_col, "_part").agg(F.count(F.lit(1)).alias("_n"))
    earlier = Window.partitionBy(stream_col).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    base = sizes.select(stream_col, "_part", F.coalesce(F.sum("_n").over(earlier), F.lit(0)).alias("_base"))
    return parts.withColumn("_in", inside).join(base, [stream_col, "_part"]).withColumn("ord", F.col("_base") + F.col("_in") - 1).drop("_part", "_in", "_base")


def across(df: DataFrame, order_cols: list[str], col: str) -> DataFrame:
    """Adds ``running`` (the sum of ``col`` up to and with the row) and ``previous`` (the row before's).

    Rows are range-partitioned; what crosses partitions comes from a table with one row for each of
    them, so no task reads the whole table.
    """
    parts = materialize(df.repartitionByRange(*order_cols).withColumn("_part", F.spark_partition_id()), "across")
    sums = parts.groupBy("_part").agg(F.sum(col).alias("_s"), F.max_by(F.struct(F.col(col).alias("v")), F.struct(*order_cols)).alias("_l"))
    earlier = Window.orderBy("_part")
    base = sums.select("_part", F.coalesce(F.sum("_s").over(earlier.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_base"), F.lag("_l").over(earlier)["v"].alias("_last"))
    inside = Window.partitionBy("_part").orderBy(*order_cols)
    got = parts.withColumns({"_sum": F.sum(col).over(inside.rowsBetween(Window.unboundedPreceding, 0)), "_lag": F.lag(col).over(inside), "_at": F.row_number().over(inside)})
    got = got.join(F.broadcast(base), "_part")  # one row a partition
    return got.withColumns({"running": F.col("_base") + F.col("_sum"), "previous": F.when(F.col("_at") == 1, F.col("_last")).otherwise(F.col("_lag"))}).drop("_part", "_s", "_base", "_last", "_sum", "_lag", "_at")


def with_page(df: DataFrame, page_size: int = PAGE) -> DataFrame:
    return df.withColumns({"page_no": F.floor(F.col("ord") / page_size), "pos": F.col("ord") % page_size})


def keep_tails(df: DataFrame, tail: str, page_size: int = PAGE) -> DataFrame:
    """``tail='drop'`` leaves only full pages; no page ever spans two streams."""
    if tail == "keep":
        return df
    if tail != "drop":
        raise ValueError("tail must be 'keep' or 'drop'")
    n = df.groupBy("stream_id").agg((F.floor(F.count(F.lit(1)) / page_size) * page_size).alias("_full"))
    return df.join(n, "stream_id").filter(F.col("ord") < F.col("_full")).drop("_full")


def grouped(df: DataFrame, page_size: int = PAGE, group_pages: int = GROUP_PAGES) -> DataFrame:
    """Rows of a page group together in one partition, in order: one exchange, no arrays.

    The number of partitions is given, as adaptive execution would merge partitions by their bytes,
    and pages cost far more time than bytes.
    """
    n = 4 * df.sparkSession.sparkContext.defaultParallelism
    g = F.floor(F.col("ord") / (page_size * group_pages)).cast("long")
    return df.withColumn("group_no", g).repartition(n, "stream_id", "group_no").sortWithinPartitions("stream_id", "group_no", "ord")
