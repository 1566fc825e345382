"""Connected components by alternating large and small stars, in DataFrame joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorcount.llm.scratch import Scratch


def _large_star(edges: DataFrame) -> DataFrame:
    """Each node's larger neighbours are hung on the smallest of the node and its neighbours."""
    both = edges.unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy(F.col("a").alias("u")).agg(F.min("b").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.filter("b > a").join(least, F.col("a") == F.col("u")).select(F.col("m").alias("a"), "b").filter("a < b")


def _small_star(edges: DataFrame) -> DataFrame:
    """Each node and its smaller neighbours are hung on the smallest of them."""
    least = edges.groupBy(F.col("b").alias("u")).agg(F.min("a").alias("m"))
    moved = edges.join(least, F.col("b") == F.col("u")).select(F.col("m").alias("x"), F.col("a").alias("y"))
    return least.select(F.col("m").alias("a"), F.col("u").alias("b")).unionAll(moved.filter("x < y").toDF("a", "b")).distinct()


def components(edges: DataFrame, a: str, b: str, scratch: Scratch, name: str = "components") -> DataFrame:
    """Rows (node, component): the smallest node reachable by the edges, for every node with an edge to another.

    Nodes are of one orderable type; null ends and loops are left out. A node with very many edges meets only counts by
    partial aggregation and joins that split. Each round is written, so lost executors cost one round.
    """
    now = edges.select(F.least(a, b).alias("a"), F.greatest(a, b).alias("b"), F.col(a).isNull() | F.col(b).isNull()).toDF("a", "b", "none")
    now = scratch.keep(now.filter("not none and a < b").select("a", "b").distinct(), f"{name}-0")
    number = 0
    if now.isEmpty():
        return now.select(F.col("b").alias("node"), F.col("a").alias("component"))
    while True:
        number += 1
        now = scratch.keep(_small_star(_large_star(now)), f"{name}-{number}")
        scratch.drop(f"{name}-{number - 1}")
        # done once every node but the smallest of each component hangs on one node, which hangs on none
        met = now.select(F.col("b").alias("n"), F.lit(1).alias("hangs"), F.lit(0).alias("holds")).unionAll(now.select("a", F.lit(0), F.lit(1)))
        if met.groupBy("n").agg(F.sum("hangs").alias("hangs"), F.max("holds").alias("holds")).filter("hangs + holds > 1").isEmpty():
            break
    leaves = now.select(F.col("b").alias("node"), F.col("a").alias("component"))
    return leaves.unionAll(now.select(F.col("a").alias("node"), F.col("a").alias("component")).distinct())
