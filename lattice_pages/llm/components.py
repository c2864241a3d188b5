"""Connected components with DataFrame operations only.

Alternates two star operations on a table of distinct edges until it no longer
changes: every node is linked to the least node it can see, first through its larger
neighbours, then through its smaller ones. The edges end as one star per component,
after a number of rounds that grows with the logarithm of the longest path. Every
round is written to shared storage, so lineage stays short and a lost executor costs
one round at most. A node with very many edges is no single task's work: minima are
pre-aggregated and the joins are plain equi-joins that adaptive execution can split.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from lattice_pages.session import drop_path, materialize


def _least_neighbour(e: DataFrame) -> DataFrame:
    return e.groupBy("hi").agg(F.min("lo").alias("least"))


def _round(e: DataFrame) -> DataFrame:
    both = e.select("hi", "lo").unionByName(e.select(F.col("lo").alias("hi"), F.col("hi").alias("lo")))
    least = both.groupBy(F.col("hi").alias("node")).agg(F.min("lo").alias("m")).select("node", F.least("node", "m").alias("m"))
    # large star: larger neighbours of a node move to the least node it sees
    large = e.select(F.col("lo").alias("node"), F.col("hi").alias("far")).join(least, "node").select(F.col("far").alias("hi"), F.col("m").alias("lo")).distinct()
    # small star: smaller neighbours and the node itself move to the least of them
    small = _least_neighbour(large)
    moved = large.join(small, "hi").select(F.col("lo").alias("hi"), F.col("least").alias("lo")).filter("hi <> lo")
    return moved.unionByName(small.select("hi", F.col("least").alias("lo"))).distinct()


def _state(e: DataFrame) -> tuple:
    return tuple(e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first())


def components(edges: DataFrame, a: str = "a", b: str = "b", name: str = "cc") -> DataFrame:
    """``node, root`` for every node that has an edge to another node; root: the least node.

    Null ends, loops and repeated edges are ignored; no edges give an empty table. Nodes
    may be of any type with an order.
    """
    e = edges.select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo"), F.col(a).isNotNull().alias("_a"), F.col(b).isNotNull().alias("_b"))
    e = materialize(e.filter("_a and _b and hi <> lo").select("hi", "lo").distinct(), name)
    was = _state(e)
    while was[0]:
        nxt = materialize(_round(e), name)
        now = _state(nxt)
        drop_path(e.sparkSession, e)
        e = nxt
        if now == was:
            break
        was = now
    return e.select(F.col("hi").alias("node"), F.col("lo").alias("root")).unionByName(e.select(F.col("lo").alias("node"), F.col("lo").alias("root")).distinct())
