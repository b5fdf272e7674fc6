"""Even splits of the column-major stream of entries, and the columns that parts share.

With Z entries and P parts, the entry of rank r in (col, row) order lies in part floor(r * P / Z). A column whose
entries lie in several parts is a zone. Zones follow from the first and last columns of the parts
alone, by flags towards the neighbours and scans along the parts.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from nzspan.functions import part_of_key, part_of_key_expression
from nzspan.session import checkpointed, few_rows, ship

from .matrix import SparseMatrix, global_rank


#: Borders that a search tree of expressions places entries by; more take a vectorised function.
EXPRESSION = 256
#: Buckets of columns whose counts tell where borders fall.
BUCKETS = 65_536


@dataclass
class Distributed:
    """A matrix whose entries lie by part: placed(part, row, col, val), parts and zones. n_parts is at most the number of entries."""

    matrix: SparseMatrix
    n_parts: int
    placed: DataFrame
    parts: DataFrame
    zones: DataFrame
    packed: DataFrame | None = None  # entries by whole columns, once a solver has asked for them


def place(entries: DataFrame, n_parts: int) -> DataFrame:
    """Entries with a part column, moved so that part i is partition i."""
    return entries.repartitionById(n_parts, "part")


def even_parts(matrix: SparseMatrix, n_parts: int) -> DataFrame:
    """Entries with rank and part; exact by a global sort."""
    total = max(matrix.nnz, 1)
    ranked = global_rank(matrix.entries, "col", "row")
    return ranked.withColumn("part", F.expr(f"rank * {n_parts} div {total}").cast("int"))


def border_keys(matrix: SparseMatrix, n_parts: int) -> list[tuple[int, int]]:
    """First (col, row) of parts 1 to P - 1, without a sort of entries or columns.

    Counts of up to BUCKETS equal spans of columns, summed on the driver, tell in which span each border falls; counts of the columns of
    those spans, at most P - 1, tell the column; and only the columns that a border cuts are ranked.
    """
    total = matrix.nnz
    if not total:
        return []
    spark = matrix.entries.sparkSession
    starts = [-(-i * total // n_parts) for i in range(1, n_parts)]  # rank of each part's first entry
    width = max(1, -(-matrix.n // BUCKETS))
    bucket = F.expr(f"col div {width}")
    counted = matrix.entries.groupBy(bucket.alias("bucket")).agg(F.count(F.lit(1)).alias("n")).collect()  # at most BUCKETS rows
    keys = np.array(sorted((r["bucket"], r["n"]) for r in counted), np.int64).reshape(-1, 2)
    upto = np.cumsum(keys[:, 1])
    at = np.searchsorted(upto, starts, "right")
    wanted = [(int(keys[k, 0]), int(upto[k] - keys[k, 1]), start) for k, start in zip(at, starts, strict=True)]
    if not wanted:
        return []
    spans = spark.createDataFrame(wanted, "bucket long, before long, start long")
    held = matrix.entries.select("col", "row", bucket.alias("bucket")).join(F.broadcast(spans.select("bucket", "before").distinct()), "bucket")
    along = Window.partitionBy("bucket").orderBy("col").rowsBetween(Window.unboundedPreceding, 0)
    columns = held.groupBy("bucket", "before", "col").agg(F.count(F.lit(1)).alias("n")).withColumn("hi", F.col("before") + F.sum("n").over(along))
    columns = columns.withColumn("lo", F.col("hi") - F.col("n"))
    cut = few_rows(columns.join(F.broadcast(spans.select("bucket", "start")), "bucket").where("start >= lo AND start < hi").select("col", "start", "lo"))
    numbered = matrix.entries.select("col", "row").join(F.broadcast(cut.select("col", "lo").distinct()), "col")
    numbered = numbered.withColumn("rank", F.col("lo") + F.row_number().over(Window.partitionBy("col").orderBy("row")) - 1)
    found = numbered.join(F.broadcast(cut.select("start")), F.col("rank") == F.col("start")).select("start", "col", "row").collect()  # P - 1 rows
    by_start = {r["start"]: (r["col"], r["row"]) for r in found}
    return [by_start[s] for s in starts if s in by_start]


def partition_even(matrix: SparseMatrix, n_parts: int, by: str = "rank", zones: str = "window") -> Distributed:
    """The even split. by: rank sorts all entries; borders finds the border keys only; range takes sampled borders, for sizes nearly even."""
    n_parts = max(1, min(n_parts, matrix.nnz))
    if by == "rank":
        entries = even_parts(matrix, n_parts).drop("rank")
    elif by == "borders":
        borders = border_keys(matrix, n_parts)
        if len(borders) < EXPRESSION:
            part = part_of_key_expression(borders)
        else:
            ship(matrix.entries.sparkSession)
            part = part_of_key(borders)("col", "row")
        entries = matrix.entries.withColumn("part", part)
    elif by == "range":
        entries = checkpointed(matrix.entries.repartitionByRange(n_parts, "col", "row").withColumn("part", F.spark_partition_id()))
    else:
        raise ValueError(f"no way {by}")
    return distribute(matrix, entries.select("part", "row", "col", "val"), n_parts, zones)


def distribute(matrix: SparseMatrix, entries: DataFrame, n_parts: int, zones: str = "window") -> Distributed:
    """Place entries by their part column, keep them, and find parts and zones."""
    placed = place(entries, n_parts).sortWithinPartitions("part", "col", "row").persist()
    parts = few_rows(part_bounds(placed, matrix.n))
    return Distributed(matrix, n_parts, placed, parts, few_rows(setup_zones(placed, parts, zones)))


def part_bounds(placed: DataFrame, n: int) -> DataFrame:
    """(part, nnz, rank_lo, rank_hi, first_col, last_col, cover_lo, cover_hi) of the parts that hold entries.

    Columns without entries belong to the part on their left, those before all entries to the first.
    """
    parts = placed.groupBy("part").agg(F.count(F.lit(1)).alias("nnz"), F.min("col").alias("first_col"), F.max("col").alias("last_col"))
    along = Window.orderBy("part")
    parts = parts.withColumn("rank_hi", F.sum("nnz").over(along) - 1).withColumn("rank_lo", F.col("rank_hi") - F.col("nnz") + 1)
    after = F.lead("first_col").over(along)
    lo = F.when(F.lag("part").over(along).isNull(), F.lit(0)).otherwise(F.col("first_col"))
    hi = F.when(after.isNull(), F.lit(n - 1)).otherwise(F.greatest("last_col", after - 1))
    parts = parts.withColumn("cover_lo", lo.cast("long")).withColumn("cover_hi", hi.cast("long"))
    return parts.select("part", "nnz", "rank_lo", "rank_hi", "first_col", "last_col", "cover_lo", "cover_hi")


# --- setup: scans along the parts, P rows


def neighbour_flags(parts: DataFrame) -> DataFrame:
    """parts with shares_prev and shares_next: whether the first or last column is shared with the part before or after."""
    along = Window.orderBy("part")
    shares_prev = F.coalesce((F.col("first_col") == F.lag("last_col").over(along)).cast("int"), F.lit(0))
    shares_next = F.coalesce((F.col("last_col") == F.lead("first_col").over(along)).cast("int"), F.lit(0))
    return parts.withColumn("shares_prev", shares_prev).withColumn("shares_next", shares_next)


def closing_mark(setup: DataFrame) -> DataFrame:
    """setup with closes_left: the part is the last of those that share its first column."""
    goes_on = (F.col("shares_next") == 1) & (F.col("first_col") == F.col("last_col"))
    return setup.withColumn("closes_left", ((F.col("shares_prev") == 1) & ~goes_on).cast("int"))


def group_ranks(setup: DataFrame) -> DataFrame:
    """setup with right_rank and left_rank: the numbers of the zones at a part's last and first columns."""
    upto = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, 0)
    setup = setup.withColumn("right_rank", F.sum("closes_left").over(upto).cast("int"))
    return setup.withColumn("left_rank", (F.col("right_rank") - F.col("closes_left")).cast("int"))


def seg_add(a: tuple[int, int], b: tuple[int, int]) -> tuple[int, int]:
    """Addition of (value, key) pairs that starts anew where the key changes; associative as long as equal keys are neighbours, not commutative."""
    return (a[0] + b[0] if a[1] == b[1] else b[0], b[1])


def segmented_scan(df: DataFrame, value: str, key: str, order: str, out: str, reverse: bool = False) -> DataFrame:
    """df with a running seg_add of (value, key) along order. Equal keys must be neighbours, so a sum within each key does."""
    along = F.col(order).desc() if reverse else F.col(order).asc()
    window = Window.partitionBy(key).orderBy(along).rowsBetween(Window.unboundedPreceding, 0)
    return df.withColumn(out, F.sum(value).over(window).cast("int"))


def scan_blocks(df: DataFrame, value: str, key: str, order: str, out: str, block: int = 4096, reverse: bool = False) -> DataFrame:
    """As segmented_scan, in two levels for very many parts: scans within blocks, then of the blocks' totals, then both joined.

    `order` counts from 0. A block's total is a pair as well, and whether the block has a change of key says if what comes before it matters.
    """
    ship(df.sparkSession)
    sign = -1 if reverse else 1
    blocked = df.withColumn("_block", (F.floor(F.col(order) / block) * sign).cast("long"))
    schema = blocked.schema

    def within(rows):
        import pandas as pd

        rows = rows.sort_values(order, ascending=not reverse)
        keys, values = rows[key].to_numpy(), rows[value].to_numpy()
        total = np.cumsum(values)
        new = np.r_[True, keys[1:] != keys[:-1]]
        base = np.maximum.accumulate(np.where(new, np.arange(len(rows)), 0))
        out_rows = rows[[c.name for c in schema]].copy()
        out_rows["_sum"] = (total - total[base] + values[base]).astype("int64")
        out_rows["_first"] = pd.Series(base == 0, index=rows.index)
        return out_rows

    from pyspark.sql import types as T

    scanned = checkpointed(blocked.groupBy("_block").applyInPandas(within, T.StructType([*schema, T.StructField("_sum", T.LongType()), T.StructField("_first", T.BooleanType())])))
    ends = scanned.groupBy("_block").agg(
        F.max_by(F.struct(F.col("_sum").alias("s"), F.col(key).alias("k"), F.col("_first").alias("whole")), F.col(order) * sign).alias("end")
    ).orderBy("_block").collect()  # one row for each block
    carry, table = None, []
    for r in ends:
        table.append((r["_block"], None if carry is None else carry[0], None if carry is None else carry[1]))
        here = (r["end"]["s"], r["end"]["k"])
        carry = seg_add(carry, here) if carry is not None and r["end"]["whole"] else here
    into = df.sparkSession.createDataFrame(table, "_block long, _carry long, _key long")
    joined = scanned.join(F.broadcast(into), "_block")
    add = F.when(F.col("_first") & (F.col("_key") == F.col(key)), F.col("_carry")).otherwise(0)
    return joined.withColumn(out, (F.col("_sum") + F.coalesce(add, F.lit(0))).cast("int")).select(*df.columns, out)


def parts_before(setup: DataFrame, engine: str = "window") -> DataFrame:
    scan = segmented_scan if engine == "window" else scan_blocks
    return scan(setup, "shares_prev", "left_rank", "part", "parts_before")


def parts_after(setup: DataFrame, engine: str = "window") -> DataFrame:
    scan = segmented_scan if engine == "window" else scan_blocks
    return scan(setup, "shares_next", "right_rank", "part", "parts_after", reverse=True)


def full_setup(parts: DataFrame, engine: str = "window") -> DataFrame:
    setup = group_ranks(closing_mark(neighbour_flags(parts)))
    setup = parts_after(parts_before(setup, engine), engine)
    return setup.select("part", "first_col", "last_col", "shares_prev", "shares_next", "closes_left", "right_rank", "left_rank", "parts_before", "parts_after")


def zones_from_setup(setup: DataFrame) -> DataFrame:
    """(zone, col, part_lo, part_hi, size, parity) from the parts that open or close a zone; parts_before and parts_after count only where the flags are set."""
    opens = setup.where("shares_next = 1 AND NOT (shares_prev = 1 AND first_col = last_col)")
    zones = opens.select(F.col("right_rank").alias("zone"), F.col("last_col").alias("col"), F.col("part").alias("part_lo"), (F.col("part") + F.col("parts_after")).alias("part_hi"))
    return with_size(zones)


def with_size(zones: DataFrame) -> DataFrame:
    zones = zones.withColumn("size", (F.col("part_hi") - F.col("part_lo") + 1).cast("int")).withColumn("parity", (F.col("zone") % 2).cast("int"))
    return zones.select(F.col("zone").cast("int"), "col", F.col("part_lo").cast("int"), F.col("part_hi").cast("int"), "size", "parity")


def zones_by_grouping(placed: DataFrame) -> DataFrame:
    """Zones by grouping all entries by column, as a general group split would: the costly comparison."""
    held = placed.groupBy("col").agg(F.min("part").alias("part_lo"), F.max("part").alias("part_hi")).where("part_hi > part_lo")
    return with_size(held.withColumn("zone", F.row_number().over(Window.orderBy("col")) - 1))


def setup_zones(placed: DataFrame, parts: DataFrame, engine: str = "window") -> DataFrame:
    """Zones of the placed entries; engine: window or blocks scan along the parts, grouping looks at all entries."""
    return zones_by_grouping(placed) if engine == "grouping" else zones_from_setup(full_setup(parts, engine))


def zone_schedule(zones: DataFrame, mode: str = "even_odd") -> list[DataFrame]:
    """Zones in rounds: even_odd has two, in each of which no part is in two zones; single has all at once."""
    return [zones] if mode == "single" else [zones.where("parity = 0"), zones.where("parity = 1")]


def schedule_clashes(zones: DataFrame) -> DataFrame:
    """(parity, clashes): parts that are in more than one zone of a round."""
    held = zones.select("parity", F.explode(F.sequence("part_lo", "part_hi")).alias("part")).groupBy("parity", "part").agg(F.count(F.lit(1)).alias("n"))
    return held.groupBy("parity").agg(F.sum((F.col("n") > 1).cast("long")).alias("clashes"))
