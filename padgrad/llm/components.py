"""Connected components of an edge table by contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from padgrad.shared import written


def components(edges: DataFrame) -> DataFrame:
    """``(node, root)`` for every node of ``edges`` (``a``, ``b`` of any ordered type).

    In each round a node hangs below its least neighbour, edges are carried over to
    the new names, and edges within one name go. The rounds' tables (each far smaller
    than the one before) are joined to the nodes at the end. Every table is written, so
    a round reads only the last one. A hub costs one partial minimum a task; joins on a
    hub are plain shuffled joins, which adaptive execution splits.
    """
    live = written(edges.where("a <> b").select("a", "b").distinct(), "cc-edges")
    names = live.select(F.col("a").alias("node")).union(live.select("b")).distinct().withColumn("root", F.col("node"))
    while not live.isEmpty():
        both = live.union(live.select("b", "a"))
        up = written(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("v"), F.least("a", "m").alias("up")), "cc-up")
        names = names.join(up, F.col("root") == F.col("v"), "left").select("node", F.coalesce("up", "root").alias("root"))
        ua, ub = up.select(F.col("v").alias("a"), F.col("up").alias("x")), up.select(F.col("v").alias("b"), F.col("up").alias("y"))
        moved = live.join(ua, "a").join(ub, "b").where("x <> y")
        live = written(moved.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), "cc-edges")
    return written(names, "cc-names")


def merged(names: DataFrame, more: DataFrame) -> DataFrame:
    """``names`` of components after the edges ``more`` are added: only the roots they join are named anew."""
    a, b = names.select(F.col("node").alias("a"), F.col("root").alias("x")), names.select(F.col("node").alias("b"), F.col("root").alias("y"))
    ends = more.join(a, "a", "left").join(b, "b", "left").select(F.coalesce("x", "a").alias("a"), F.coalesce("y", "b").alias("b"))
    again = components(ends)
    moved = names.join(again.select(F.col("node").alias("root"), F.col("root").alias("to")), "root", "left").select("node", F.coalesce("to", "root").alias("root"))
    fresh = again.join(names.select("node"), "node", "left_anti").select("node", "root")
    return moved.unionByName(fresh)
