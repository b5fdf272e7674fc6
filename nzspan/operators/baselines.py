"""What the even split is compared with: spans of whole columns or rows, balanced whole columns, blocks, serial products."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nzspan.session import few_rows, written

from .layout import Distributed, part_bounds, place
from .matrix import SparseMatrix


def _whole_columns(matrix: SparseMatrix, entries: DataFrame, n_parts: int) -> Distributed:
    placed = place(entries.select("part", "row", "col", "val"), n_parts).persist()
    parts = few_rows(part_bounds(placed, matrix.n))
    none = matrix.entries.sparkSession.createDataFrame([], "zone int, col long, part_lo int, part_hi int, size int, parity int")
    return Distributed(matrix, n_parts, placed, parts, none)


def partition_columns(matrix: SparseMatrix, n_parts: int) -> Distributed:
    """Contiguous spans of n / P whole columns; no zones, so a transposed product needs no sum."""
    return _whole_columns(matrix, matrix.entries.withColumn("part", F.expr(f"col * {n_parts} div {max(matrix.n, 1)}").cast("int")), n_parts)


def partition_columns_balanced(matrix: SparseMatrix, n_parts: int) -> Distributed:
    """Whole columns, even in entries as far as the densest column lets them.

    The dense head, columns of over Z / (8 P) entries and so at most 8 P, is packed on the driver, the longest first into the least
    loaded part. The tail is dealt out in turns by its order of counts, back and forth, on the cluster.
    """
    from .matrix import global_rank

    counts = written(matrix.entries.groupBy("col").agg(F.count(F.lit(1)).alias("nnz")), "counts")
    limit = max(1, matrix.nnz // (8 * n_parts))
    head = counts.where(F.col("nnz") > limit).orderBy(F.col("nnz").desc(), "col").collect()
    load, chosen = np.zeros(n_parts), []
    for r in head:
        part = int(load.argmin())
        load[part] += r["nnz"]
        chosen.append((r["col"], part))
    spark = matrix.entries.sparkSession
    by_load = spark.createDataFrame([(i, int(p)) for i, p in enumerate(np.argsort(load, kind="stable"))], "slot int, part int")
    ranked = global_rank(counts.where(F.col("nnz") <= limit), F.col("nnz").desc(), F.col("col").asc(), name="at")
    turn, step = F.floor(F.col("at") / n_parts), (F.col("at") % n_parts).cast("int")
    tail = ranked.withColumn("slot", F.when(turn % 2 == 0, step).otherwise(F.lit(n_parts - 1) - step)).join(F.broadcast(by_load), "slot").select("col", "part")
    where = tail if not chosen else tail.unionByName(spark.createDataFrame(chosen, "col long, part int"))
    return _whole_columns(matrix, matrix.entries.join(where, "col"), n_parts)


def partition_rows(matrix: SparseMatrix, n_parts: int) -> Distributed:
    """Contiguous spans of whole rows: forward products need no sum over parts, but the whole long vector everywhere."""
    return _whole_columns(matrix, matrix.entries.withColumn("part", F.expr(f"row * {n_parts} div {max(matrix.m, 1)}").cast("int")), n_parts)


def partition_blocks(matrix: SparseMatrix, grid: tuple[int, int]) -> Distributed:
    """A grid of row and column spans, for matrices of blocks."""
    down, across = grid
    part = F.expr(f"(row * {down} div {max(matrix.m, 1)}) * {across} + col * {across} div {max(matrix.n, 1)}").cast("int")
    return _whole_columns(matrix, matrix.entries.withColumn("part", part), down * across)


def forward_spans(d: Distributed, x: DataFrame) -> DataFrame:
    """(row, y) over spans, x(col, x) joined where its columns lie; partial sums by part, then over parts."""
    met = d.placed.join(x, "col")
    return met.groupBy("part", "row").agg(F.sum(F.col("val") * F.col("x")).alias("partial")).groupBy("row").agg(F.sum("partial").alias("y"))


def transposed_spans(d: Distributed, v: DataFrame, shared: bool = False) -> DataFrame:
    """(col, u) over spans of whole columns; shared: spans of rows, whose long partial vectors must be summed."""
    from .products import replicated

    local = d.placed.join(replicated(v, d.matrix.m), "row").groupBy("part", "col").agg(F.sum(F.col("val") * F.col("v")).alias("u"))
    return local.groupBy("col").agg(F.sum("u").alias("u")) if shared else local.select("col", "u")


def forward_serial(rows: np.ndarray, cols: np.ndarray, vals: np.ndarray, x: np.ndarray, m: int) -> np.ndarray:
    return np.bincount(rows, vals * x[cols], minlength=m)


def transposed_serial(rows: np.ndarray, cols: np.ndarray, vals: np.ndarray, v: np.ndarray, n: int) -> np.ndarray:
    return np.bincount(cols, vals * v[rows], minlength=n)


