"""Connected components of an edge table, by turns of large-star and small-star on the cluster."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nzspan.session import discard, settle, written


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, component) for every node of edges(a, b); component is the smallest node reachable.

    Each turn links every larger neighbour of a node to its smallest neighbour (large star), then every smaller
    neighbour likewise (small star). Groups only need a minimum, so a node with very many neighbours is
    first reduced where it lies. Self-links and repeated edges are harmless; no edges give no rows.
    A turn's edges are written, and those of the turn before, with their shuffles, go. Turns end once all edges lead to centres.
    """
    edges = written(edges.where("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct(), "edges")
    for turn in range(max_rounds + 1):
        if _are_stars(edges):
            break
        if turn == max_rounds:
            raise RuntimeError("connected_components did not settle")
        both = edges.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(edges.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        large = both.where("v > u").join(least, "u").where("v <> m").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct()
        small_least = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(small_least, "hi")
        small = small.where("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo")).unionByName(small_least.select("hi", F.col("m").alias("lo")))
        old, edges = edges, written(small.distinct(), "edges")
        discard(old)
        settle(edges.sparkSession)
    pairs = edges.select(F.col("hi").alias("node"), F.col("lo").alias("component"))
    return pairs.unionByName(edges.select(F.col("lo").alias("node"), F.col("lo").alias("component")).distinct())


def _are_stars(edges: DataFrame) -> bool:
    """Whether each node of edges(hi, lo) either has one edge to a smaller one or is such a smaller one, which then is its group's least."""
    ends = edges.select(F.col("hi").alias("node"), F.lit(1).alias("up"), F.lit(0).alias("down")).unionByName(edges.select(F.col("lo").alias("node"), F.lit(0).alias("up"), F.lit(1).alias("down")))
    others = ends.groupBy("node").agg(F.sum("up").alias("up"), F.max("down").alias("down")).where("up > 1 OR up = 1 AND down = 1")
    return others.agg(F.count(F.lit(1))).first()[0] == 0


def first_of_each(df: DataFrame, key: str, order: str) -> DataFrame:
    """One row for each key, the one with the smallest order."""
    return df.withColumn("_n", F.row_number().over(Window.partitionBy(key).orderBy(order))).where("_n = 1").drop("_n")
