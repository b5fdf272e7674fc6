"""Sparse matrices as DataFrames of (row, col, val), and how to build them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from nzspan.functions import tokens
from nzspan.session import written
from nzspan.sources import as_entries


@dataclass
class SparseMatrix:
    """entries(row, col, val) with m rows and n columns, zero-based."""

    entries: DataFrame
    m: int
    n: int

    @property
    def nnz(self) -> int:
        if not hasattr(self, "_nnz"):
            self._nnz = self.entries.count()
        return self._nnz

    def transpose(self) -> SparseMatrix:
        e = self.entries
        return SparseMatrix(e.select(F.col("col").alias("row"), F.col("row").alias("col"), "val"), self.n, self.m)

    @property
    def orientation(self) -> str:
        return "wide" if self.n >= self.m else "tall"


def canonical(entries: DataFrame) -> DataFrame:
    """Entries with repeated places summed and zeros dropped; those with a null are left out (see quarantine). NaN stays."""
    summed = as_entries(entries).where("row IS NOT NULL AND col IS NOT NULL AND val IS NOT NULL").groupBy("row", "col").agg(F.sum("val").alias("val"))
    return summed.where((F.col("val") != 0) | F.isnan("val"))


def quarantine(entries: DataFrame) -> DataFrame:
    """Entries that canonical() rejects: those with a null index or value."""
    return entries.where(F.col("row").isNull() | F.col("col").isNull() | F.col("val").isNull())


def global_rank(df: DataFrame, *keys: str | Column, name: str = "rank") -> DataFrame:
    """df with the zero-based place of each row in the order of the keys, which should tell all rows apart.

    Rows are range-partitioned and sorted where they lie; a running number within each partition and the
    partitions' sizes give the rank. The numbered rows are written once, as a range shuffle run anew may cut elsewhere.
    """
    spread = df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("_at", F.monotonically_increasing_id())
    spread = written(spread, "ranked")
    task = F.shiftright("_at", 33)
    sizes = spread.groupBy(task.alias("_task")).agg(F.count(F.lit(1)).alias("n")).orderBy("_task").collect()  # one row for each partition
    offsets, total = [], 0
    for row in sizes:
        offsets.append((row["_task"], total))
        total += row["n"]
    table = df.sparkSession.createDataFrame(offsets or [(0, 0)], "_task long, _before long")
    ranked = spread.withColumn("_task", task).join(F.broadcast(table), "_task")
    return ranked.withColumn(name, F.col("_before") + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))).drop("_task", "_before", "_at")


def term_counts(documents: DataFrame, text: str = "text", row: str = "doc_id") -> DataFrame:
    """(row, term, val): how often each term occurs in each document."""
    words = documents.select(F.col(row).cast("long").alias("row"), F.explode(tokens(F.col(text))).alias("term"))
    return words.groupBy("row", "term").agg(F.count(F.lit(1)).cast("double").alias("val"))


def ngram_counts(documents: DataFrame, k: int = 2, text: str = "text", row: str = "doc_id") -> DataFrame:
    """(row, term, val) for runs of k tokens, joined by spaces."""
    words = documents.select(F.col(row).cast("long").alias("row"), tokens(F.col(text)).alias("t")).where(F.size("t") >= k)
    runs = F.transform(F.sequence(F.lit(1), F.size("t") - F.lit(k - 1)), lambda i: F.array_join(F.slice("t", i, k), " "))
    return words.select("row", F.explode(runs).alias("term")).groupBy("row", "term").agg(F.count(F.lit(1)).cast("double").alias("val"))


#: Orders of labelled columns: keys of a ranking over (term, nnz, first_row).
ORDERS = {
    "dense_first": lambda: (F.col("nnz").desc(), F.col("term").asc()),
    "native": lambda: (F.col("first_row").asc(), F.col("term").asc()),
    "label": lambda: (F.col("term").asc(),),
    "hashed": lambda: (F.md5(F.col("term").cast("binary")).asc(), F.col("term").asc()),
    "dense_last": lambda: (F.col("nnz").asc(), F.col("term").asc()),
}


def index_labels(counts: DataFrame, order: str = "dense_first") -> DataFrame:
    """(term, col, nnz): places of the labels of counts(row, term, val) in the given order."""
    stats = counts.groupBy("term").agg(F.count(F.lit(1)).alias("nnz"), F.min("row").alias("first_row"))
    return global_rank(stats, *ORDERS[order](), name="col").select("term", "col", "nnz")


def label_matrix(counts: DataFrame, order: str, m: int) -> SparseMatrix:
    """A matrix of counts(row, term, val), its terms placed in the given order."""
    index = index_labels(counts, order)
    return SparseMatrix(counts.join(index, "term").select("row", "col", "val"), m, index.count())


def pair_matrix(df: DataFrame, row: str | Column, col: str | Column, val: str | Column) -> DataFrame:
    """Entries from two key columns and a value, repeated places summed."""
    one = lambda x: F.col(x) if isinstance(x, str) else x
    return canonical(df.select(one(row).alias("row"), one(col).alias("col"), one(val).alias("val")))


def array_matrix(df: DataFrame, key: str, array: str) -> DataFrame:
    """Entries (dimension, key, value) of a vector column: one column of the matrix for each vector."""
    return df.select(F.posexplode(array).alias("row", "val"), F.col(key).alias("col")).select(F.col("row").cast("long"), F.col("col").cast("long"), F.col("val").cast("double"))


def weight(matrix: SparseMatrix, scheme: str) -> SparseMatrix:
    """Values by a scheme: tf, binary, log (1 + ln tf), or tfidf (tf * ln(m / columns' counts))."""
    e = matrix.entries
    if scheme == "binary":
        e = e.withColumn("val", F.lit(1.0))
    elif scheme == "log":
        e = e.withColumn("val", 1 + F.log("val"))
    elif scheme == "tfidf":
        df = e.groupBy("col").agg(F.count(F.lit(1)).alias("df"))
        e = e.join(df, "col").select("row", "col", (F.col("val") * F.log(F.lit(float(matrix.m)) / F.col("df"))).alias("val"))
    elif scheme != "tf":
        raise ValueError(f"no scheme {scheme}")
    return SparseMatrix(e, matrix.m, matrix.n)


# --- algebra over entries


def scale(e: DataFrame, a: float) -> DataFrame:
    return e.withColumn("val", F.col("val") * F.lit(a))


def add(a: DataFrame, b: DataFrame) -> DataFrame:
    return canonical(a.unionByName(b))


def hadamard(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.join(b.withColumnRenamed("val", "other"), ["row", "col"]).select("row", "col", (F.col("val") * F.col("other")).alias("val"))


def scale_rows(e: DataFrame, d: DataFrame) -> DataFrame:
    """Entries with each row multiplied by d(row, v)."""
    return e.join(d, "row").select("row", "col", (F.col("val") * F.col("v")).alias("val"))


def scale_cols(e: DataFrame, d: DataFrame) -> DataFrame:
    """Entries with each column multiplied by d(col, x)."""
    return e.join(d, "col").select("row", "col", (F.col("val") * F.col("x")).alias("val"))


def row_stats(e: DataFrame) -> DataFrame:
    return e.groupBy("row").agg(F.count(F.lit(1)).alias("nnz"), F.sum("val").alias("total"), F.sum(F.col("val") * F.col("val")).alias("square"))


def col_stats(e: DataFrame) -> DataFrame:
    return e.groupBy("col").agg(F.count(F.lit(1)).alias("nnz"), F.sum("val").alias("total"), F.sum(F.col("val") * F.col("val")).alias("square"))


def gram(e: DataFrame, block: int = 1024) -> DataFrame:
    """A times its transpose, for a matrix with few rows.

    An entry goes to each pair of its block of rows and a block that has entries in its column, and the pair's products are summed where
    its entries lie, so that products are not shuffled; where pairs are fewer than tasks, a pair's columns are dealt to several. Half of
    the result is summed and mirrored; it has up to the square of the rows, as the matrix asked for has.
    """
    last = e.agg(F.max(F.floor(F.col("row") / block))).first()[0] or 0
    pieces = -(-int(e.sparkSession.conf.get("spark.sql.shuffle.partitions")) * 2 // ((last + 1) * (last + 2)))
    own = F.floor(F.col("row") / block)
    cells = e.select("row", "col", "val", own.alias("own"))
    held = cells.groupBy("col").agg(F.collect_set("own").alias("blocks"))
    sent = cells.join(held, "col").select("row", "col", "val", "own", F.explode("blocks").alias("met"))
    where = ["one", "two", "piece"]
    sent = sent.select("row", "col", "val", "own", F.least("own", "met").alias("one"), F.greatest("own", "met").alias("two"), F.pmod(F.xxhash64("col"), F.lit(pieces)).alias("piece")).repartition(*where)
    entry = F.struct("row", "val")
    lists = sent.groupBy(*where, "col").agg(F.collect_list(F.when(F.col("own") == F.col("one"), entry)).alias("left"), F.collect_list(F.when(F.col("own") == F.col("two"), entry)).alias("right"))
    pairs = lists.select(*where, F.explode("left").alias("l"), "right").select(*where, "l", F.explode("right").alias("r")).where("l.row <= r.row")
    sums = pairs.groupBy(*where, F.col("l.row").alias("row"), F.col("r.row").alias("other")).agg(F.sum(F.col("l.val") * F.col("r.val")).alias("val"))
    if pieces > 1:
        sums = sums.groupBy("row", "other").agg(F.sum("val").alias("val"))
    there, back = F.struct("row", "other"), F.struct(F.col("other").alias("row"), F.col("row").alias("other"))
    return sums.select(F.explode(F.when(F.col("row") == F.col("other"), F.array(there)).otherwise(F.array(there, back))).alias("at"), "val").select("at.row", "at.other", "val")


def outer(v: DataFrame, x: DataFrame) -> DataFrame:
    """Entries of the product of a short vector and a long one."""
    return x.crossJoin(F.broadcast(v)).select("row", "col", (F.col("v") * F.col("x")).alias("val"))


def to_dense(e: DataFrame, columns: list[int]) -> DataFrame:
    """A row of the given columns' values for each row of the matrix; 0 where there is no entry."""
    return e.groupBy("row").pivot("col", columns).agg(F.sum("val")).na.fill(0.0)
