"""The forward product y = A x and the transposed product u = v A over a distributed matrix."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nzspan.session import checkpointed, release, ship

from .layout import Distributed, place
from .matrix import SparseMatrix

#: Bytes of a short vector, two numbers a row, that may be broadcast; beyond them joins shuffle.
SHORT_BYTES = 256 << 20
#: Entries of a packed block.
BLOCK = 1 << 20


def replicated(vector: DataFrame, m: int) -> DataFrame:
    """A short vector for every task, while its m rows take at most SHORT_BYTES."""
    return F.broadcast(vector) if 16 * m <= SHORT_BYTES else vector


def short_frame(spark: SparkSession, values: np.ndarray, name: str = "v") -> DataFrame:
    """(row, name) of an array on the driver, handed over as Arrow."""
    values = np.asarray(values, float)
    return spark.createDataFrame(pa.table({"row": np.arange(len(values)), name: values}))


# --- forward


def forward_local(d: Distributed, x: DataFrame) -> DataFrame:
    """(part, row, partial) from x(part, col, x) in the overlapped layout, part by part; nothing moves, as x is placed like the entries."""
    met = d.placed.join(x.select("part", "col", "x"), ["part", "col"])
    return met.groupBy("part", "row").agg(F.sum(F.col("val") * F.col("x")).alias("partial"))


def allreduce_short(partials: DataFrame, m: int, method: str = "flat", fanout: int = 4, n_parts: int | None = None) -> DataFrame:
    """(row, y), the sum of the parts' short vectors.

    flat: one aggregate. tree: groups of `fanout` parts at a time, for very many parts. dense: each task adds up an array of m
    values, which pays where most rows have a partial sum.
    """
    if method == "flat":
        return partials.groupBy("row").agg(F.sum("partial").alias("y"))
    if method == "tree":
        left = n_parts or 1
        while left > fanout:
            partials = partials.withColumn("part", F.floor(F.col("part") / fanout)).groupBy("part", "row").agg(F.sum("partial").alias("partial"))
            left = -(-left // fanout)
        return partials.groupBy("row").agg(F.sum("partial").alias("y"))
    if method == "dense":
        ship(partials.sparkSession)

        def add(batches):
            total, seen = np.zeros(m), np.zeros(m, bool)
            for batch in batches:
                rows = batch.column("row").to_numpy()
                np.add.at(total, rows, batch.column("partial").to_numpy())
                seen[rows] = True
            at = np.flatnonzero(seen)
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], names=["row", "partial"])

        return partials.select("row", "partial").mapInArrow(add, "row long, partial double").groupBy("row").agg(F.sum("partial").alias("y"))
    raise ValueError(f"no method {method}")


def forward(d: Distributed, x: DataFrame, method: str = "flat", fanout: int = 4) -> DataFrame:
    """(row, y); rows without a stored entry that meets x are left out."""
    return allreduce_short(forward_local(d, x), d.matrix.m, method, fanout, d.n_parts)


# --- transposed


def transposed_local(d: Distributed, v: DataFrame, zones_only: bool = False) -> DataFrame:
    """(part, col, u) of each part from v(row, v); zones_only: of the shared columns, fewer than parts, which are broadcast."""
    entries = d.placed.join(F.broadcast(d.zones.select("col")), "col", "left_semi") if zones_only else d.placed
    met = entries.join(replicated(v, d.matrix.m), "row")
    return met.groupBy("part", "col").agg(F.sum(F.col("val") * F.col("v")).alias("u"))


def zone_reduce(local: DataFrame, zones: DataFrame, mode: str = "single", shared: DataFrame | None = None) -> DataFrame:
    """local(part, col, u) with the sums over zones in place of their parts' shares, and is_home on the lowest part of each.

    Zones are fewer than parts, so they and their sums are broadcast. even_odd sums in two rounds, in each of which no part is
    in two zones; single takes all at once, as a shuffle has no conflict between them. shared: what local has on zones, where that is
    cheaper to get than local as a whole; without it local is computed twice unless it is kept.
    """
    shared = (local if shared is None else shared).join(F.broadcast(zones), "col").select("zone", "parity", "col", "part_lo", "u")
    rounds = [shared] if mode == "single" else [shared.where("parity = 0"), shared.where("parity = 1")]
    sums = None
    for one in rounds:
        total = one.groupBy("col", "part_lo").agg(F.sum("u").alias("total"))
        sums = total if sums is None else sums.unionByName(total)
    out = local.join(F.broadcast(sums), "col", "left")
    home = F.col("part_lo").isNull() | (F.col("part") == F.col("part_lo"))
    return out.select("part", "col", F.coalesce("total", "u").alias("u"), home.alias("is_home"))


def transposed(d: Distributed, v: DataFrame, mode: str = "single") -> DataFrame:
    """(part, col, u, is_home) in the overlapped layout; columns that v does not meet are left out. Nothing is kept."""
    return zone_reduce(transposed_local(d, v), d.zones, mode, transposed_local(d, v, zones_only=True))


# --- plain relational products


def forward_plain(matrix: SparseMatrix, x: DataFrame) -> DataFrame:
    """(row, y) by a join on col, without placement; x(col, x)."""
    return matrix.entries.join(x, "col").groupBy("row").agg(F.sum(F.col("val") * F.col("x")).alias("y"))


def transposed_plain(matrix: SparseMatrix, v: DataFrame) -> DataFrame:
    """(col, u) by a join on row, without placement."""
    return matrix.entries.join(v, "row").groupBy("col").agg(F.sum(F.col("val") * F.col("v")).alias("u"))


# --- packed columns


BLOCKS = "part int, chunk int, col_ids array<long>, col_ptr array<int>, row_ids array<long>, vals array<double>"


def pack_blocks(d: Distributed, max_entries: int = BLOCK) -> DataFrame:
    """Entries of each part packed by non-empty columns, in chunks of up to max_entries; a column may go on in the next chunk."""
    ship(d.placed.sparkSession)

    def pack(batches):
        held: list[tuple] = []
        chunk, current, size = 0, None, 0

        def block():
            cols, rows, vals = (np.concatenate([h[i] for h in held]) for i in (0, 1, 2))
            ids, ptr = np.unique(cols, return_index=True)
            ptr = np.append(ptr, len(cols)).astype(np.int32)
            arrays = [pa.array([current], pa.int32()), pa.array([chunk], pa.int32())]
            arrays += [pa.array([a.tolist()], t) for a, t in ((ids, pa.list_(pa.int64())), (ptr, pa.list_(pa.int32())), (rows, pa.list_(pa.int64())), (vals, pa.list_(pa.float64())))]
            return pa.RecordBatch.from_arrays(arrays, names=["part", "chunk", "col_ids", "col_ptr", "row_ids", "vals"])

        for batch in batches:
            parts = batch.column("part").to_numpy()
            for lo, hi in _runs(parts, max_entries):
                if current is not None and (parts[lo] != current or size + hi - lo > max_entries):
                    yield block()
                    chunk, held, size = (chunk + 1 if parts[lo] == current else 0), [], 0
                current = int(parts[lo])
                held.append(tuple(batch.column(c).to_numpy()[lo:hi] for c in ("col", "row", "val")))
                size += hi - lo
        if held:
            yield block()

    ordered = d.placed.select("part", "row", "col", "val").sortWithinPartitions("part", "col", "row")
    return place(ordered.mapInArrow(pack, BLOCKS), d.n_parts)


def _runs(keys: np.ndarray, most: int):
    cuts = np.flatnonzero(keys[1:] != keys[:-1]) + 1
    edges = [0, *cuts.tolist(), len(keys)]
    for a, b in zip(edges, edges[1:], strict=False):
        for lo in range(a, b, most):
            yield lo, min(b, lo + most)


def kernel_forward(blocks: DataFrame, x: DataFrame) -> DataFrame:
    """(part, row, partial) of packed blocks from x(part, col, x), by vector arithmetic; each part gets its own slice of x."""
    ship(blocks.sparkSession)
    packed = x.groupBy("part").agg(F.array_sort(F.collect_list(F.struct("col", "x"))).alias("own"))
    met = blocks.join(packed.select("part", F.col("own.col").alias("x_cols"), F.col("own.x").alias("x_vals")), "part")

    def run(batches):
        names = ("col_ids", "col_ptr", "row_ids", "vals", "x_cols", "x_vals")
        for batch in batches:
            for i in range(batch.num_rows):
                ids, ptr, rows, vals, cols, values = (batch.column(c)[i].values.to_numpy() for c in names)
                at = np.minimum(np.searchsorted(cols, ids), max(len(cols) - 1, 0))
                known = cols[at] == ids if len(cols) else np.zeros(len(ids), bool)
                size = np.diff(ptr)
                taken = np.repeat(known, size)
                held, place = np.unique(rows[taken], return_inverse=True)
                y = np.bincount(place, np.repeat(np.where(known, values[at] if len(cols) else 0.0, 0.0), size)[taken] * vals[taken], minlength=len(held))
                part = np.full(len(held), batch.column("part")[i].as_py(), np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(held), pa.array(y)], names=["part", "row", "partial"])

    return met.mapInArrow(run, "part int, row long, partial double")


def kernel_transposed(blocks: DataFrame, v: np.ndarray) -> DataFrame:
    """(part, col, u) of packed blocks; the chunks of a part that share a column add up."""
    ship(blocks.sparkSession)
    held = blocks.sparkSession.sparkContext.broadcast(np.asarray(v, float))

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                ids, ptr, rows, vals = (batch.column(c)[i].values.to_numpy() for c in ("col_ids", "col_ptr", "row_ids", "vals"))
                u = np.add.reduceat(held.value[rows] * vals, ptr[:-1])
                part = np.full(len(ids), batch.column("part")[i].as_py(), np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(ids), pa.array(u)], names=["part", "col", "u"])

    return blocks.mapInArrow(run, "part int, col long, u double").groupBy("part", "col").agg(F.sum("u").alias("u"))


# --- both products at once


#: Entries of a row of whole columns.
COLUMNS = 1 << 18
#: Partial sums of 16 bytes that the driver takes from all parts.
FEW = 1 << 20


def pack_columns(d: Distributed, max_entries: int = COLUMNS) -> DataFrame:
    """(part, zone, col_ptr, row_ids, vals): each part's entries by whole columns, as the bytes of arrays.

    A row takes columns up to max_entries, or one that has more, of m entries at most. What a part has of a shared column is a row of its
    own with the number of its zone, which is -1 for all others.
    """
    ship(d.placed.sparkSession)
    shared = {r["col"]: r["zone"] for r in d.zones.select("col", "zone").collect()}  # fewer than parts
    width = np.int32 if d.matrix.m < 1 << 31 else np.int64

    def rows_of(part, cols, rows, vals):
        first = np.flatnonzero(np.append(True, cols[1:] != cols[:-1])) if len(cols) else np.zeros(0, np.int64)
        ends = np.append(first, len(cols))[1:]
        zone = np.array([shared.get(c, -1) for c in cols[first].tolist()] if shared else np.full(len(first), -1), np.int32)
        for k in [-1, *zone[zone >= 0].tolist()]:
            mine = zone == k
            if mine.any():
                size = (ends - first)[mine]
                taken = np.repeat(mine, ends - first)
                ptr = np.append(0, np.cumsum(size)).astype(np.int64)
                held = (ptr.tobytes(), rows[taken].astype(width).tobytes(), vals[taken].astype(float).tobytes())
                arrays = [pa.array([part], pa.int32()), pa.array([k], pa.int32()), *[pa.array([b], pa.binary()) for b in held]]
                yield pa.RecordBatch.from_arrays(arrays, names=["part", "zone", "col_ptr", "row_ids", "vals"])

    def pack(batches):
        held: list[tuple] = []
        current, size, room = None, 0, max_entries

        def whole():
            return [np.concatenate([h[i] for h in held]) for i in (0, 1, 2)]

        for batch in batches:
            parts = batch.column("part").to_numpy()
            for lo, hi in _runs(parts, max_entries):
                if held and parts[lo] != current:
                    yield from rows_of(current, *whole())
                    held, size, room = [], 0, max_entries
                current = int(parts[lo])
                held.append(tuple(batch.column(c).to_numpy()[lo:hi] for c in ("col", "row", "val")))
                size += hi - lo
                if size >= room:
                    arrays = whole()
                    cut = int(np.searchsorted(arrays[0], arrays[0][-1]))  # the last column may go on
                    if cut:
                        yield from rows_of(current, *[a[:cut] for a in arrays])
                    held = [tuple(a[cut:] for a in arrays)]
                    size -= cut
                    room = max(max_entries, 2 * size)
        if held:
            yield from rows_of(current, *whole())

    ordered = d.placed.select("part", "row", "col", "val").sortWithinPartitions("part", "col", "row")
    return ordered.mapInArrow(pack, "part int, zone int, col_ptr binary, row_ids binary, vals binary")


def normal(d: Distributed, packed: DataFrame, w: np.ndarray, few: int = FEW) -> np.ndarray:
    """A times A transposed times w, from pack_columns(d); w and the result, m values, are arrays on the driver.

    A column that lies in one part meets w and gives its share of the result at once. Of shared columns the parts' sums with w are added up
    first, a number for each, and a second pass over their entries alone gives the rest. Up to `few` sums of all parts are added up on the driver.
    """
    spark, m = packed.sparkSession, d.matrix.m
    ship(spark)
    width = np.int32 if m < 1 << 31 else np.int64

    def entries(batch):
        for zone, *held in zip(*(batch.column(c) for c in ("zone", "col_ptr", "row_ids", "vals")), strict=True):
            ptr, rows, vals = (np.frombuffer(b.as_buffer(), kind) for b, kind in zip(held, (np.int64, width, np.float64), strict=True))
            yield zone.as_py(), ptr, rows.astype(np.intp), vals

    def told(at, values):
        return pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(values, pa.float64())], names=["at", "value"])

    def added(table: DataFrame, run, values: np.ndarray):
        """Sums by place of what run tells with values in every task: the places and the sums."""
        held = spark.sparkContext.broadcast(values)
        try:
            found = table.mapInArrow(lambda batches: run(batches, held.value), "at long, value double")
            if (d.n_parts + 2) * m > few:  # else the driver adds up what comes, without a shuffle
                found = found.groupBy("at").agg(F.sum("value").alias("value"))
            found = found.toArrow()
        finally:
            held.destroy()
        at, back = np.unique(found.column("at").to_numpy(), return_inverse=True)
        return at, np.bincount(back, found.column("value").to_numpy(), len(at))

    def inner(batches, w):
        y, zones = np.zeros(m), []
        for batch in batches:
            for zone, ptr, rows, vals in entries(batch):
                met = w[rows] * vals
                if zone >= 0:
                    zones.append((-1 - zone, met.sum()))  # below all rows
                else:
                    u = np.add.reduceat(met, ptr[:-1])
                    np.add.at(y, rows, np.repeat(u, np.diff(ptr)) * vals)
        at = np.flatnonzero(y)
        yield told(np.append(at, np.array([z for z, _ in zones], np.int64)), np.append(y[at], [s for _, s in zones]))

    def outer(batches, sums):
        y = np.zeros(m)
        for batch in batches:
            for zone, _, rows, vals in entries(batch):
                np.add.at(y, rows, sums[zone] * vals)
        at = np.flatnonzero(y)
        yield told(at, y[at])

    y = np.zeros(m)
    at, value = added(packed, inner, np.asarray(w, float))
    y[at[at >= 0]] = value[at >= 0]
    zones = at < 0
    if zones.any():
        sums = np.zeros(int(-at.min()))
        sums[-1 - at[zones]] = value[zones]
        at, value = added(packed.where("zone >= 0"), outer, sums)
        y[at] += value
    return y


# --- repeated pairs


def dense(vector: DataFrame, key: str, value: str, size: int) -> np.ndarray:
    """A short vector as an array on the driver; m values."""
    out = np.zeros(size)
    rows = vector.select(key, value).toArrow()
    out[rows.column(key).to_numpy()] = rows.column(value).to_numpy()
    return out


def product_pairs(d: Distributed, x: DataFrame, v: DataFrame, repeats: int, mode: str = "chained") -> tuple[DataFrame, DataFrame, list[float]]:
    """(y, u, seconds of each turn) of repeated forward and transposed products.

    independent feeds the same x(part, col, x) and v(row, v) each time. chained feeds y, divided by its largest value, into the
    transposed product and its result into the next forward product. y, m values, passes the driver in each turn; u stays where it lies.
    """
    spark = d.placed.sparkSession
    seconds, y, u = [], None, None
    for _ in range(repeats):
        began = time.perf_counter()
        y_dense = dense(forward(d, x), "row", "y", d.matrix.m)
        y = short_frame(spark, y_dense, "y")
        if mode == "chained":
            peak = np.abs(y_dense).max() or 1.0
            v = short_frame(spark, y_dense / peak)
        before, u = u, checkpointed(transposed(d, v))  # keeps its placement, and no lineage
        if before is not None:
            release(before)
        if mode == "chained":
            x = u.select("part", "col", F.col("u").alias("x"))
        seconds.append(time.perf_counter() - began)
    return y, u, seconds
