"""Measures of balance and communication, sweeps over numbers of parts, and the choice of a plan."""

from __future__ import annotations

import math
import time
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nzspan.operators.layout import Distributed
from nzspan.operators.matrix import SparseMatrix, global_rank
from nzspan.operators.products import SHORT_BYTES, forward, transposed
from nzspan.session import checkpointed

PARTS = tuple(2**k for k in range(10))


def imbalance(d: Distributed) -> DataFrame:
    """(parts, delta_pct): P times the spread of entries over parts, by the number of entries, in percent; empty parts count as 0."""
    every = d.placed.sparkSession.range(d.n_parts).select(F.col("id").cast("int").alias("part"))
    sizes = every.join(F.broadcast(d.parts), "part", "left").select(F.coalesce("nnz", F.lit(0)).alias("nnz"))
    spread = F.max("nnz") - F.min("nnz")
    return sizes.agg(F.lit(d.n_parts).alias("parts"), F.round(spread * 100.0 * d.n_parts / F.sum("nnz"), 2).alias("delta_pct"))


def zone_stats(zones: DataFrame) -> DataFrame:
    """(zones, largest, copies): number of zones, most parts of one, and coefficients held more than once."""
    return zones.agg(F.count(F.lit(1)).alias("zones"), F.coalesce(F.max("size"), F.lit(0)).alias("largest"), F.coalesce(F.sum(F.col("size") - 1), F.lit(0)).alias("copies"))


def column_profile(matrix: SparseMatrix) -> DataFrame:
    """(col, nnz, lo, hi): ranks [lo, hi) of each non-empty column's entries, by a two-level running sum; kept."""
    counts = matrix.entries.groupBy("col").agg(F.count(F.lit(1)).alias("nnz"))
    ordered = global_rank(counts, "col", name="at").withColumn("block", F.floor(F.col("at") / 65536))
    along = Window.partitionBy("block").orderBy("at").rowsBetween(Window.unboundedPreceding, 0)
    summed = ordered.withColumn("upto", F.sum("nnz").over(along))
    per = summed.groupBy("block").agg(F.max("upto").alias("size"))  # a row for 65,536 columns
    offsets = per.select("block", F.coalesce(F.sum("size").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("offset"))
    summed = summed.join(F.broadcast(offsets), "block").withColumn("hi", F.col("offset") + F.col("upto"))
    return checkpointed(summed.select("col", "nnz", (F.col("hi") - F.col("nnz")).alias("lo"), "hi"))


def sweep_imbalance(profile: DataFrame, n: int, parts: tuple[int, ...] = PARTS) -> DataFrame:
    """(parts, delta_pct) of spans of whole columns for every number of parts, from the columns' counts alone."""
    spark = profile.sparkSession
    sizes = F.explode(F.array(*map(F.lit, parts)))
    loads = profile.select(sizes.alias("parts"), "col", "nnz").withColumn("part", F.expr(f"col * parts div {max(n, 1)}"))
    loads = loads.groupBy("parts", "part").agg(F.sum("nnz").alias("nnz"))
    every = spark.range(max(parts)).select(F.col("id").alias("part"), sizes.alias("parts")).where("part < parts")
    full = every.join(loads, ["parts", "part"], "left").select("parts", F.coalesce("nnz", F.lit(0)).alias("nnz"))
    delta = (F.max("nnz") - F.min("nnz")) * 100.0 * F.col("parts") / F.sum("nnz")
    return full.groupBy("parts").agg(F.round(delta, 2).alias("delta_pct"))


def sweep_zones(profile: DataFrame, parts: tuple[int, ...] = PARTS) -> DataFrame:
    """(parts, zones, largest, copies) of the even split for every number of parts: a column is in the parts of its first to its last entry."""
    total = profile.agg(F.max("hi").alias("z"))
    each = profile.crossJoin(F.broadcast(total)).select("lo", "hi", "z", F.explode(F.array(*map(F.lit, parts))).alias("parts"))
    extra = each.withColumn("extra", F.expr("(hi - 1) * parts div z - lo * parts div z"))
    is_zone = F.col("extra") > 0
    return extra.groupBy("parts").agg(F.sum(is_zone.cast("long")).alias("zones"), F.max(F.when(is_zone, F.col("extra") + 1).otherwise(0)).alias("largest"), F.sum("extra").alias("copies"))


def profile(matrix: SparseMatrix) -> DataFrame:
    """One row: m, n, z, mean_nnz, dense_columns (at least half of the rows), densest and the tenth densest column's counts."""
    counts = checkpointed(matrix.entries.groupBy("col").agg(F.count(F.lit(1)).alias("nnz")))
    top = counts.orderBy(F.col("nnz").desc()).limit(10).agg(F.max("nnz").alias("densest"), F.min("nnz").alias("tenth"))
    dense = F.sum((F.col("nnz") * 2 >= matrix.m).cast("long"))
    one = counts.agg(F.lit(matrix.m).cast("long").alias("m"), F.lit(matrix.n).cast("long").alias("n"), F.sum("nnz").alias("z"), F.round(F.sum("nnz") / F.lit(matrix.n), 4).alias("mean_nnz"), dense.alias("dense_columns"))
    return one.crossJoin(F.broadcast(top))


def max_error(got: DataFrame, exact: DataFrame, key: str, value: str) -> DataFrame:
    """One row (compared, max_abs, max_rel): the largest difference of two vectors, a missing value being 0, and by the largest exact value."""
    other = exact.select(key, F.col(value).alias("_exact"))
    both = got.select(key, F.col(value).alias("_got")).join(other, key, "full_outer").na.fill(0.0, ["_got", "_exact"])
    gap = F.max(F.abs(F.col("_got") - F.col("_exact")))
    return both.agg(F.count(F.lit(1)).alias("compared"), gap.alias("max_abs"), (gap / F.greatest(F.max(F.abs("_exact")), F.lit(1e-300))).alias("max_rel"))


def identity_gap(d: Distributed, x: DataFrame, v: DataFrame) -> DataFrame:
    """One row (v_ax, va_x, gap): v times (A x), and (v A) times x with each coefficient counted at its home; they are equal."""
    y = forward(d, x).join(v, "row").agg(F.sum(F.col("y") * F.col("v")).alias("v_ax"))
    u = transposed(d, v).where("is_home").join(x.select("part", "col", "x"), ["part", "col"]).agg(F.sum(F.col("u") * F.col("x")).alias("va_x"))
    return y.crossJoin(u).withColumn("gap", F.abs(F.col("v_ax") - F.col("va_x")))


def setup_ratio(d: Distributed, v: DataFrame, repeats: int = 3) -> DataFrame:
    """One row (setup_s, product_s, ratio): the least seconds of a whole zone setup and of a transposed product."""
    from nzspan.operators.layout import setup_zones
    from nzspan.sources import drain

    def least(run) -> float:
        took = []
        for _ in range(repeats):
            began = time.perf_counter()
            run()
            took.append(time.perf_counter() - began)
        return min(took)

    setup, product = least(lambda: setup_zones(d.placed, d.parts).collect()), least(lambda: drain(transposed(d, v)))
    return d.placed.sparkSession.createDataFrame([(setup, product, setup / product)], "setup_s double, product_s double, ratio double")


def speed_ups(seconds: dict[int, float]) -> list[tuple[int, float, float, float]]:
    """(cores, seconds, speed-up, efficiency) against the least number of cores."""
    least = min(seconds)
    return [(c, s, seconds[least] / s, seconds[least] * least / (s * c)) for c, s in sorted(seconds.items())]


def moved_values(d: Distributed, scheme: str) -> DataFrame:
    """(scheme, forward_values, transposed_values): partial short values of all parts, and values summed in zones."""
    ahead = d.placed.select("part", "row").distinct().agg(F.count(F.lit(1)).alias("forward_values"))
    zones = d.zones.agg(F.coalesce(F.sum("size"), F.lit(0)).cast("long").alias("transposed_values"))
    return ahead.crossJoin(F.broadcast(zones)).select(F.lit(scheme).alias("scheme"), "forward_values", "transposed_values")


@dataclass
class Stats:
    m: int
    n: int
    nnz: int
    densest: int
    largest_zone: int = 1


def cost_model(s: Stats, n_parts: int) -> list[tuple[str, str, float]]:
    """(scheme, operation, cost): the growth terms of each scheme, with constants of one and logarithms to base two."""
    p, log_p, log_v = n_parts, math.log2(max(n_parts, 1)) if n_parts > 1 else 0.0, math.log2(max(s.largest_zone, 1))
    even, worst = s.nnz / p, s.n * s.m / p
    return [
        ("even_entries", "forward", even + s.m * log_p),
        ("even_entries", "transposed", even + log_v),
        ("even_entries", "long_vector", min(even, float(s.n))),
        ("even_entries", "inner_product", min(even, float(s.n)) + log_p),
        ("even_entries", "setup", log_p),
        ("column_spans", "forward", min(worst, float(s.nnz)) + s.m * log_p),
        ("column_spans", "transposed", min(worst, float(s.nnz))),
        ("column_spans", "long_vector", s.n / p),
        ("column_spans", "inner_product", s.n / p + log_p),
        ("general_split", "setup", float(p)),
    ]


@dataclass
class Choice:
    orientation: str
    split: str
    short: str
    reduction: str
    kernel: str


def choose(s: Stats, n_parts: int, span_delta_pct: float, short_limit: int = SHORT_BYTES // 16) -> Choice:
    """A plan for products: spans of columns do where their imbalance is small; short vectors are broadcast while they may be; arrays of
    partial sums pay where parts meet most rows; packed columns pay where columns are long."""
    m, n = min(s.m, s.n), max(s.m, s.n)
    per_part = s.nnz / max(n_parts, 1)
    return Choice(
        "wide" if s.n >= s.m else "tall",
        "columns" if span_delta_pct <= 5.0 else "even",
        "broadcast" if m <= short_limit else "shuffle",
        "dense" if per_part >= m else ("tree" if n_parts > 4096 else "flat"),
        "blocks" if m <= short_limit and s.nnz / max(n, 1) >= 8 else "join",
    )
