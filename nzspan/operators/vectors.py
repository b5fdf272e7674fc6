"""Long vectors in the overlapped layout: (part, col, x, is_home), a zone's coefficient on each of its parts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .layout import Distributed, place


def spread(vector: DataFrame, d: Distributed) -> DataFrame:
    """vector(col, x) laid out over the parts; the lowest part of a zone is its coefficient's home.

    Only the vector moves: to where the entries lie, by the same placement, so that products and vector operations join in place.
    """
    held = d.placed.select("part", "col").distinct()
    return spread_cover(vector, d).join(held, ["part", "col"])  # held has each place once; a semi join would be moved below the placement


def spread_cover(vector: DataFrame, d: Distributed) -> DataFrame:
    """As spread, but columns without entries have a place too, by the parts' covers.

    Covers are told by equal spans of columns, four to a part, so that a column meets only parts whose cover is in its span; these are at
    most five rows for each part, and broadcast.
    """
    width = max(1, d.matrix.n // max(1, 4 * d.n_parts))
    spans = F.explode(F.sequence(F.expr(f"cover_lo div {width}"), F.expr(f"cover_hi div {width}")))
    cover = F.broadcast(d.parts.select("part", "cover_lo", "cover_hi", spans.alias("_span")))
    laid = vector.withColumn("_span", F.expr(f"col div {width}")).join(cover, "_span").where("col >= cover_lo AND col <= cover_hi")
    laid = laid.join(F.broadcast(d.zones.select("col", "part_lo")), "col", "left")
    laid = laid.select("part", "col", "x", (F.col("part_lo").isNull() | (F.col("part") == F.col("part_lo"))).alias("is_home"))
    return place(laid, d.n_parts)


def gather(vector: DataFrame, value: str = "x") -> DataFrame:
    """One value for each column, that of its home."""
    return vector.where("is_home").select("col", value)


def copies_agree(vector: DataFrame, value: str = "x", tolerance: float = 0.0) -> bool:
    spread_ = vector.groupBy("col").agg((F.max(value) - F.min(value)).alias("gap"))
    return spread_.where(F.col("gap") > tolerance).limit(1).count() == 0


def scale(a: float, x: DataFrame) -> DataFrame:
    return x.withColumn("x", F.lit(a) * F.col("x"))


def axpy(a: float, x: DataFrame, y: DataFrame) -> DataFrame:
    """a * x + y of two vectors of one layout; a coefficient that one lacks counts as 0."""
    other = y.select("part", "col", F.col("x").alias("_y"), F.col("is_home").alias("_home"))
    both = x.join(other, ["part", "col"], "full_outer")
    value = F.lit(a) * F.coalesce("x", F.lit(0.0)) + F.coalesce("_y", F.lit(0.0))
    return both.select("part", "col", value.alias("x"), F.coalesce("is_home", "_home").alias("is_home"))


def add(x: DataFrame, y: DataFrame) -> DataFrame:
    return axpy(1.0, x, y)


def dot(x: DataFrame, y: DataFrame) -> DataFrame:
    """One row, dot: the inner product, each coefficient counted once, at its home."""
    other = y.select("part", "col", F.col("x").alias("_y"))
    return x.where("is_home").join(other, ["part", "col"]).agg(F.sum(F.col("x") * F.col("_y")).alias("dot"))


def norm2(x: DataFrame) -> DataFrame:
    """One row, norm2: the sum of squares over homes."""
    return x.where("is_home").agg(F.sum(F.col("x") * F.col("x")).alias("norm2"))


def complete(vector: DataFrame, n: int, value: str = "x") -> DataFrame:
    """vector(col, value) with 0 for the columns of 0..n-1 that it lacks."""
    every = vector.sparkSession.range(n).withColumnRenamed("id", "col")
    return every.join(vector, "col", "left").select("col", F.coalesce(value, F.lit(0.0)).alias(value))


def vector_imbalance(d: Distributed) -> DataFrame:
    """One row (stored_ratio, home_ratio): the most coefficients of a part, stored or at home, by the mean over parts."""
    balance = vector_balance(d)
    ratio = lambda c: F.round(F.max(c) * F.count(F.lit(1)) / F.sum(c), 4)
    return balance.agg(ratio("stored").alias("stored_ratio"), ratio("home").alias("home_ratio"))


def vector_balance(d: Distributed) -> DataFrame:
    """(part, stored, home): coefficients that each part stores, and those whose home it is."""
    laid = d.placed.select("part", "col").distinct().join(F.broadcast(d.zones.select("col", "part_lo")), "col", "left")
    home = (F.col("part_lo").isNull() | (F.col("part") == F.col("part_lo"))).cast("long")
    return laid.groupBy("part").agg(F.count(F.lit(1)).alias("stored"), F.sum(home).alias("home"))
