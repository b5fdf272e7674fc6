"""UDFs, UDTFs and aggregates around the products."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

WORDS = r"[^\p{L}\p{N}]+"


@F.udtf(returnType=T.StructType([T.StructField("place", T.IntegerType()), T.StructField("token", T.StringType())]))
class Tokens:
    """The tokens of a text, lower case, with their places."""

    def eval(self, text: str):
        import regex

        for place, token in enumerate(t for t in regex.split(WORDS, (text or "").lower()) if t):
            yield place, token


def part_of_key(borders: Sequence[tuple[int, int]]):
    """A vectorised UDF (col, row) -> part: the number of borders at or below the key. borders: ascending first keys of parts 1, 2, ..."""
    cols = np.array([c for c, _ in borders], np.int64)
    rows = np.array([r for _, r in borders], np.int64)

    @F.pandas_udf(T.IntegerType())
    def part(col: pd.Series, row: pd.Series) -> pd.Series:
        c, r = col.to_numpy(np.int64), row.to_numpy(np.int64)
        lo, hi = np.searchsorted(cols, c, "left"), np.searchsorted(cols, c, "right")
        out = lo.copy()
        for k in np.flatnonzero(hi > lo):  # keys in a column that a border cuts
            out[k] = lo[k] + np.searchsorted(rows[lo[k] : hi[k]], r[k], "right")
        return pd.Series(out, dtype="int32")

    return part


def part_of_key_expression(borders: Sequence[tuple[int, int]]) -> Column:
    """As part_of_key, of columns col and row, as a search tree of built-in expressions."""

    def within(lo: int, hi: int) -> Column:
        """The part, known to be from lo to hi."""
        if lo == hi:
            return F.lit(lo)
        middle = (lo + hi) // 2
        c, r = borders[middle]  # the first key of part middle + 1
        below = (F.col("col") < c) | ((F.col("col") == c) & (F.col("row") < r))
        return F.when(below, within(lo, middle)).otherwise(within(middle + 1, hi))

    return within(0, len(borders)).cast("int")


@F.pandas_udf(T.DoubleType())
def dot(a: pd.Series, b: pd.Series) -> float:
    """Inner product as a grouped aggregate."""
    return float(np.dot(a.to_numpy(float), b.to_numpy(float)))


def tokens(text: Column) -> Column:
    """Tokens by built-in functions: lower case, split at what is no letter or digit, no empty ones."""
    return F.filter(F.split(F.lower(text), WORDS), lambda t: t != "")


def register(spark: SparkSession) -> None:
    """The functions under SQL names."""
    spark.udtf.register("nz_tokens", Tokens)
    spark.udf.register("nz_dot", dot)
