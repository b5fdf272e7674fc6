"""Generated matrices: random ones of nearly even columns, and the shapes that splits find hard."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nzspan.session import ship

from .matrix import SparseMatrix

#: Strides of the arithmetic generator, primes above its number of rows.
STRIDES = (10007, 10009, 10037, 10039, 10061, 10067, 10069, 10079)


def bounds(m: int, density: float, slack_lo: int, slack_hi: int) -> tuple[int, int]:
    """Least and most entries of a column."""
    return max(0, math.floor(density * m) - slack_lo), min(m, math.ceil(density * m) + slack_hi)


def random_matrix(spark: SparkSession, m: int, n: int, density: float = 0.274, slack: float = 0.24, method: str = "arithmetic", seed: int = 42) -> SparseMatrix:
    """m by n, the count of each column even between bounds, rows without repeats, and every row in use.

    arithmetic: counts and rows from integer congruences, the same in any engine. drawn: from a generator keyed by seed and column,
    rows as runs of a shuffled order, so that with enough entries each row is used.
    """
    lo, hi = bounds(m, density, math.floor(slack * m), math.floor(slack * m))
    if method == "arithmetic":
        if m > min(STRIDES):
            raise ValueError("the strides are primes above 10,000")
        stride = F.element_at(F.array(*map(F.lit, STRIDES)), (F.col("col") % 8 + 1).cast("int"))
        count = F.lit(lo) + (F.col("col") * 7919 + 104729) % 100003 % (hi - lo + 1)
        cols = spark.range(n).select(F.col("id").alias("col"), count.alias("count"), stride.alias("stride")).where("count > 0")
        each = cols.select("col", "stride", F.explode(F.sequence(F.lit(0).cast("long"), F.col("count") - 1)).alias("i"))
        rows = each.select(((F.col("col") + F.col("i") * F.col("stride")) % m).alias("row"), "col")
        return SparseMatrix(rows.withColumn("val", (1 + (F.col("row") + F.col("col")) % 9).cast("double")), m, n)
    ship(spark)

    def draw(batches):
        for batch in batches:
            rows, cols = [], []
            for c in batch.column(0).to_pylist():
                rng = np.random.Generator(np.random.Philox(key=[seed, c]))
                order = np.random.Generator(np.random.Philox(key=[seed, c // 64 + (1 << 40)])).permutation(m)
                first = (c % 64) * hi  # columns of a block go on in the block's order of rows
                count = int(rng.integers(lo, hi + 1))
                rows.append(order[(first + np.arange(count)) % m])
                cols.append(np.full(count, c))
            row, col = np.concatenate(rows), np.concatenate(cols)
            yield pa.RecordBatch.from_arrays([pa.array(row), pa.array(col), pa.array(1.0 + (row + col) % 9)], names=["row", "col", "val"])

    return SparseMatrix(spark.range(n).mapInArrow(draw, "row long, col long, val double"), m, n)


def from_columns(spark: SparkSession, columns: dict[int, list[int]], m: int, n: int, value: float = 1.0) -> SparseMatrix:
    """A small matrix from the rows of each column."""
    data = [(r, c, value) for c, rows in columns.items() for r in rows]
    return SparseMatrix(spark.createDataFrame(data, "row long, col long, val double"), m, n)


#: Fixed values of the worked example: one-based rows of each of eight columns.
EXAMPLE = {1: [1, 5], 2: [1, 3, 4, 5], 3: [1, 4], 4: [1, 2, 3, 4, 5], 5: [2], 6: [1, 2, 3, 5], 7: [5], 8: [1, 4]}


def example(spark: SparkSession) -> SparseMatrix:
    """The worked example, its one-based rows and columns kept."""
    return from_columns(spark, EXAMPLE, 6, 9)


def shape(spark: SparkSession, kind: str, m: int, n: int) -> SparseMatrix:
    """Shapes for tests: dense_column, singles (one entry in each column), full, gaps (every third column empty), empty."""
    rows = list(range(m))
    columns = {
        "dense_column": {0: rows} | {c: [c % m] for c in range(1, n)},
        "singles": {c: [c % m] for c in range(n)},
        "full": dict.fromkeys(range(n), rows),
        "gaps": {c: [c % m, (c + 1) % m] for c in range(n) if c % 3},
        "empty": {},
    }[kind]
    return from_columns(spark, {c: sorted(set(r)) for c, r in columns.items()}, m, n)


def with_constant_column(matrix: SparseMatrix) -> SparseMatrix:
    """The matrix with one more column, dense, in front."""
    spark = matrix.entries.sparkSession
    ones: DataFrame = spark.range(matrix.m).select(F.col("id").alias("row"), F.lit(0).cast("long").alias("col"), F.lit(1.0).alias("val"))
    return SparseMatrix(matrix.entries.withColumn("col", F.col("col") + 1).unionByName(ones), matrix.m, matrix.n + 1)
