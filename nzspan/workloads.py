"""The queries of the library on the given tables, each with the SQL that gives the same rows where SQL can.

Products take x = 1 + col mod 7 and v = 1 + row mod 5 and whole values, so that sums are exact in any order. The SQL never uses parts
for a product's value: it is the plain join and sum.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nzspan import plans
from nzspan.operators import baselines, generators, layout, matrix, products, solvers, vectors
from nzspan.operators.layout import Distributed
from nzspan.operators.matrix import SparseMatrix
from nzspan.session import checkpointed, written
from nzspan.sources import load_table

P = 8
_KEPT: dict[tuple, object] = {}


def kept(spark: SparkSession, sf_dir: str, name: str, make: Callable):
    """What make() builds, built once for an application and a folder of tables."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _KEPT:
        _KEPT[key] = make()
    return _KEPT[key]


# --- matrices, and the SQL that makes their entries e(row, col, val)

_TERMS = r"""WITH tok AS (SELECT doc_id AS row, unnest(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+')) AS term FROM documents),
tf AS (SELECT row, term, CAST(count(*) AS BIGINT) AS val FROM tok WHERE term <> '' GROUP BY row, term),
st AS (SELECT term, count(*) AS nnz, min(row) AS first_row FROM tf GROUP BY term),
idx AS (SELECT term, nnz, row_number() OVER (ORDER BY {order}) - 1 AS col FROM st),
e AS (SELECT tf.row, idx.col, tf.val FROM tf JOIN idx USING (term))"""
_BIGRAMS = r"""WITH tk AS (SELECT doc_id AS row, list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS t FROM documents),
b AS (SELECT row, unnest(list_transform(range(1, len(t)), lambda i: t[i] || ' ' || t[i + 1])) AS term FROM tk WHERE len(t) >= 2),
tf AS (SELECT row, term, CAST(count(*) AS BIGINT) AS val FROM b GROUP BY row, term),
st AS (SELECT term, count(*) AS nnz FROM tf GROUP BY term),
idx AS (SELECT term, nnz, row_number() OVER (ORDER BY nnz DESC, term) - 1 AS col FROM st),
e AS (SELECT tf.row, idx.col, tf.val FROM tf JOIN idx USING (term))"""
_PAIRS = "WITH e AS (SELECT {row} AS row, {col} AS col, CAST(sum(l_quantity) AS BIGINT) AS val FROM lineitem GROUP BY ALL)"
#: Rows and columns of the random matrix up to a number of documents: small, middling, and the experiment's size.
RANDOM_SIZES = ((200, 200, 1000), (1000, 400, 10_000), (None, 2000, 100_000))


def _by_documents(k: int) -> str:
    small, middle, full = RANDOM_SIZES
    return f"(SELECT CASE WHEN count(*) <= {small[0]} THEN {small[k]} WHEN count(*) <= {middle[0]} THEN {middle[k]} ELSE {full[k]} END FROM documents)"


# slack and density as in generators.random_matrix
_RANDOM = f"""WITH z AS (SELECT CAST({_by_documents(1)} AS BIGINT) AS m, CAST({_by_documents(2)} AS BIGINT) AS n),
s AS (SELECT m, n, greatest(0, CAST(floor(0.274 * m) AS BIGINT) - CAST(floor(0.24 * m) AS BIGINT)) AS lo, least(m, CAST(ceil(0.274 * m) AS BIGINT) + CAST(floor(0.24 * m) AS BIGINT)) AS hi FROM z),
c AS (SELECT range AS col, m, lo + (range * 7919 + 104729) % 100003 % (hi - lo + 1) AS n, {list(generators.STRIDES)}[CAST(range % 8 + 1 AS INTEGER)] AS stride FROM s, range((SELECT n FROM z))),
i AS (SELECT col, m, stride, unnest(range(n)) AS i FROM c),
e AS (SELECT CAST((col + i * stride) % m AS BIGINT) AS row, col, 1 + ((col + i * stride) % m + col) % 9 AS val FROM i)"""
ENTRIES = {
    "dense_first": _TERMS.replace("{order}", "nnz DESC, term"),
    "native": _TERMS.replace("{order}", "first_row, term"),
    "balanced": _PAIRS.format(row="l_suppkey", col="l_partkey"),
    "tall": _PAIRS.format(row="l_orderkey", col="l_partkey"),
    "random": _RANDOM,
    "bigrams": _BIGRAMS,
    "label": _TERMS.replace("{order}", "term"),
    "hashed": _TERMS.replace("{order}", "md5(term), term"),
    "dense_last": _TERMS.replace("{order}", "nnz, term"),
    "user_type": "WITH kinds AS (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS row FROM (SELECT DISTINCT event_type FROM events)), e AS (SELECT row, user_id AS col, CAST(count(*) AS BIGINT) AS val FROM events JOIN kinds USING (event_type) GROUP BY ALL)",
    "brand_order": "WITH kinds AS (SELECT p_brand, row_number() OVER (ORDER BY p_brand) - 1 AS row FROM (SELECT DISTINCT p_brand FROM part)), e AS (SELECT row, l_orderkey AS col, CAST(sum(l_quantity) AS BIGINT) AS val FROM lineitem JOIN part ON l_partkey = p_partkey JOIN kinds USING (p_brand) GROUP BY ALL)",
    "customer_part": "WITH e AS (SELECT o_custkey AS row, l_partkey AS col, CAST(sum(l_quantity) AS BIGINT) AS val FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL)",
    "pages": _TERMS.replace("doc_id", "page_id").replace("lower(text)", "lower(html)").replace("FROM documents", "FROM pages").replace("{order}", "nnz DESC, term"),
    "conversations": _TERMS.replace("doc_id", "conv_id").replace("FROM documents", "FROM conversations").replace("{order}", "nnz DESC, term"),
    "benchmark": _TERMS.replace("doc_id", "item_id").replace("FROM documents", "FROM benchmark").replace("{order}", "nnz DESC, term"),
}
_SIZE = {
    "dense_first": ("(SELECT max(doc_id) + 1 FROM documents)", "(SELECT count(*) FROM idx)"),
    "native": ("(SELECT max(doc_id) + 1 FROM documents)", "(SELECT count(*) FROM idx)"),
    "bigrams": ("(SELECT max(doc_id) + 1 FROM documents)", "(SELECT count(*) FROM idx)"),
    "balanced": ("(SELECT max(l_suppkey) + 1 FROM lineitem)", "(SELECT max(l_partkey) + 1 FROM lineitem)"),
    "tall": ("(SELECT max(l_orderkey) + 1 FROM lineitem)", "(SELECT max(l_partkey) + 1 FROM lineitem)"),
    "random": (_by_documents(1), _by_documents(2)),
} | {k: ("(SELECT max(doc_id) + 1 FROM documents)", "(SELECT count(*) FROM idx)") for k in ("label", "hashed", "dense_last")}


def _lineitem(spark: SparkSession, sf_dir: str, key: str) -> SparseMatrix:
    df = load_table(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey", "l_partkey", "l_quantity")
    sizes = df.agg(F.max(key), F.max("l_partkey")).first()
    e = matrix.pair_matrix(df, key, "l_partkey", "l_quantity")
    return SparseMatrix(e, sizes[0] + 1, sizes[1] + 1)


#: Matrices whose rows are the few values of a column: table and column of the values; and of those whose rows are texts: table, key and text.
_KINDS = {"user_type": ("events", "event_type"), "brand_order": ("part", "p_brand")}
_TEXTS = {"pages": ("pages", "page_id", "html"), "conversations": ("conversations", "conv_id", "text"), "benchmark": ("benchmark", "item_id", "text")}


def random_size(spark: SparkSession, sf_dir: str) -> tuple[int, int]:
    """Rows and columns of the random matrix for a folder of tables."""
    documents = load_table(spark, sf_dir, "documents", "doc_id").count()
    return next((m, n) for most, m, n in RANDOM_SIZES if most is None or documents <= most)


def _of_kinds(spark: SparkSession, sf_dir: str, name: str) -> SparseMatrix:
    """Few rows, one for each value of a column in its order; dense in every one."""
    table, column = _KINDS[name]
    values = [r[0] for r in load_table(spark, sf_dir, table, column).distinct().orderBy(column).collect()]  # few by their nature
    kinds = F.broadcast(spark.createDataFrame(list(enumerate(values)), f"row long, {column} string"))
    if name == "user_type":
        e = matrix.pair_matrix(load_table(spark, sf_dir, "events", "user_id", column).join(kinds, column), "row", "user_id", F.lit(1.0))
    else:
        lines = load_table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_quantity").join(load_table(spark, sf_dir, "part", "p_partkey", column), F.col("l_partkey") == F.col("p_partkey"))
        e = matrix.pair_matrix(lines.join(kinds, column), "row", "l_orderkey", "l_quantity")
    e = written(e, "kinds")
    return SparseMatrix(e, len(values), e.agg(F.max("col")).first()[0] + 1)


def get_matrix(spark: SparkSession, sf_dir: str, name: str) -> SparseMatrix:
    def make() -> SparseMatrix:
        if name == "random":
            found = generators.random_matrix(spark, *random_size(spark, sf_dir))
        elif name in _KINDS:
            found = _of_kinds(spark, sf_dir, name)
        elif name in _TEXTS:
            table, row, text = _TEXTS[name]
            counts = matrix.term_counts(load_table(spark, sf_dir, table), text, row)
            found = matrix.label_matrix(written(counts, "counts"), "dense_first", load_table(spark, sf_dir, table).agg(F.max(row)).first()[0] + 1)
        elif name == "customer_part":
            joined = load_table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_quantity").join(load_table(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
            e = written(matrix.pair_matrix(joined, "o_custkey", "l_partkey", "l_quantity"), "pairs")
            found = SparseMatrix(e, *[k + 1 for k in e.agg(F.max("row"), F.max("col")).first()])
        elif name == "balanced":
            found = _lineitem(spark, sf_dir, "l_suppkey")
        elif name == "tall":
            found = _lineitem(spark, sf_dir, "l_orderkey")
        else:
            docs = load_table(spark, sf_dir, "documents", "doc_id", "text")
            m = docs.agg(F.max("doc_id")).first()[0] + 1
            counts = matrix.ngram_counts(docs) if name == "bigrams" else matrix.term_counts(docs)
            found = matrix.label_matrix(written(counts, "counts"), "dense_first" if name == "bigrams" else name, m)
        return SparseMatrix(written(found.entries, "matrix"), found.m, found.n)

    return kept(spark, sf_dir, f"matrix {name}", make)


def get_even(spark: SparkSession, sf_dir: str, name: str = "dense_first", by: str = "rank", zones: str = "window") -> Distributed:
    return kept(spark, sf_dir, f"even {name} {by} {zones}", lambda: layout.partition_even(get_matrix(spark, sf_dir, name), P, by, zones))


def long_x(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(n).select(F.col("id").alias("col"), (1 + F.col("id") % 7).cast("double").alias("x"))


def short_v(spark: SparkSession, m: int) -> DataFrame:
    return spark.range(m).select(F.col("id").alias("row"), (1 + F.col("id") % 5).cast("double").alias("v"))


def _x(d: Distributed) -> DataFrame:
    return vectors.spread(long_x(d.placed.sparkSession, d.matrix.n), d)


def _v(d: Distributed) -> DataFrame:
    return short_v(d.placed.sparkSession, d.matrix.m)


def _whole(df: DataFrame, *columns: str) -> DataFrame:
    return df.select(*[F.col(c).cast("long") if c in ("x", "y", "u", "val", "dot", "norm2") else F.col(c) for c in columns])


_FORWARD = " SELECT row, CAST(sum(val * (1 + col % 7)) AS BIGINT) AS y FROM e GROUP BY row"
_TRANSPOSED = " SELECT col, CAST(sum(val * (1 + row % 5)) AS BIGINT) AS u FROM e GROUP BY col"


def _parts(p: int = P) -> str:
    """SQL from e on: entries by rank r, by part p, and the parts' first and last columns."""
    return f""", r AS (SELECT row, col, val, row_number() OVER (ORDER BY col, row) - 1 AS rank, count(*) OVER () AS z FROM e),
p AS (SELECT row, col, val, rank, CAST(rank * {p} // z AS INTEGER) AS part FROM r),
parts AS (SELECT part, count(*) AS nnz, min(col) AS first_col, max(col) AS last_col FROM p GROUP BY part)"""


_SETUP = """, f AS (SELECT part, first_col, last_col, coalesce(CAST(first_col = lag(last_col) OVER (ORDER BY part) AS INTEGER), 0) AS shares_prev,
  coalesce(CAST(last_col = lead(first_col) OVER (ORDER BY part) AS INTEGER), 0) AS shares_next FROM parts),
g AS (SELECT *, CAST(shares_prev = 1 AND NOT (shares_next = 1 AND first_col = last_col) AS INTEGER) AS closes_left FROM f),
h AS (SELECT *, CAST(sum(closes_left) OVER (ORDER BY part) AS INTEGER) AS right_rank FROM g),
k AS (SELECT *, CAST(right_rank - closes_left AS INTEGER) AS left_rank FROM h),
s AS (SELECT *, CAST(sum(shares_prev) OVER (PARTITION BY left_rank ORDER BY part) AS INTEGER) AS parts_before,
  CAST(sum(shares_next) OVER (PARTITION BY right_rank ORDER BY part DESC) AS INTEGER) AS parts_after FROM k)"""
_SETUP_COLUMNS = "part, first_col, last_col, shares_prev, shares_next, closes_left, right_rank, left_rank, parts_before, parts_after"
_ZONES = """, c AS (SELECT col, min(part) AS part_lo, max(part) AS part_hi FROM p GROUP BY col HAVING min(part) < max(part)),
zones AS (SELECT CAST(row_number() OVER (ORDER BY col) - 1 AS INTEGER) AS zone, col, part_lo, part_hi, CAST(part_hi - part_lo + 1 AS INTEGER) AS size FROM c)"""
_EXAMPLE = "WITH e AS (SELECT DISTINCT CAST(l_linenumber AS BIGINT) AS row, l_partkey AS col, 1 AS val FROM lineitem)"

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    """Register a function (spark, sf_dir) -> DataFrame under a name, with its SQL."""

    def add(make):
        QUERIES[name] = make
        if sql:
            SQL[name] = sql
        return make

    return add


# --- worked example: few rows and many columns, cut into seven parts; the small one of generators.example is held in the tests


def _example(spark: SparkSession, sf_dir: str) -> Distributed:
    """Places of line numbers and parts, each of value 1; built for each query, so that each reads the table."""
    lines = load_table(spark, sf_dir, "lineitem", "l_linenumber", "l_partkey").select(F.col("l_linenumber").cast("long").alias("row"), F.col("l_partkey").alias("col"))
    e = written(lines.distinct().withColumn("val", F.lit(1.0)), "example")
    return layout.partition_even(SparseMatrix(e, *[k + 1 for k in e.agg(F.max("row"), F.max("col")).first()]), 7)


def _example_layout(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _whole(_x(_example(spark, sf_dir)), "part", "col", "x")


def _example_forward(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = _example(spark, sf_dir)
    x = spark.range(d.matrix.n).select(F.col("id").alias("col"), F.col("id").cast("double").alias("x"))
    return _whole(products.forward(d, vectors.spread(x, d)), "row", "y")


def _example_transposed(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = _example(spark, sf_dir)
    v = spark.range(d.matrix.m).select(F.col("id").alias("row"), F.col("id").cast("double").alias("v"))
    return _whole(vectors.gather(products.transposed(d, v), "u"), "col", "u")


query("ex_parts", _EXAMPLE + _parts(7) + " SELECT part, nnz, first_col, last_col FROM parts")(lambda s, d: _example(s, d).parts.select("part", "nnz", "first_col", "last_col"))
query("ex_setup", _EXAMPLE + _parts(7) + _SETUP + f" SELECT {_SETUP_COLUMNS} FROM s")(lambda s, d: layout.full_setup(_example(s, d).parts))
query("ex_zones", _EXAMPLE + _parts(7) + _ZONES + " SELECT zone, col, part_lo, part_hi, size FROM zones")(lambda s, d: _example(s, d).zones.drop("parity"))
query("ex_layout", _EXAMPLE + _parts(7) + " SELECT DISTINCT part, col, 1 + col % 7 AS x FROM p")(_example_layout)
query("ex_forward", _EXAMPLE + " SELECT row, CAST(sum(col) AS BIGINT) AS y FROM e GROUP BY row")(_example_forward)
query("ex_transposed", _EXAMPLE + " SELECT col, CAST(sum(row) AS BIGINT) AS u FROM e GROUP BY col")(_example_transposed)

# --- splits

query("rank_entries", ENTRIES["balanced"] + _parts() + " SELECT row, col, rank FROM p")(lambda s, d: matrix.global_rank(get_matrix(s, d, "balanced").entries, "col", "row").select("row", "col", "rank"))
for _name, _key, _by in (("parts_even", "native", "rank"), ("parts_even_dense_first", "dense_first", "rank"), ("parts_borders", "native", "borders"), ("parts_even_balanced", "balanced", "rank"), ("parts_even_random", "random", "rank")):
    query(_name, ENTRIES[_key] + _parts() + " SELECT part, nnz, first_col, last_col FROM parts")(lambda s, d, k=_key, b=_by: get_even(s, d, k, b).parts.select("part", "nnz", "first_col", "last_col"))
query("parts_even_tall", ENTRIES["tall"].replace("l_orderkey AS row, l_partkey AS col", "l_partkey AS row, l_orderkey AS col") + _parts() + " SELECT part, nnz, first_col, last_col FROM parts")(
    lambda s, d: _tall(s, d).parts.select("part", "nnz", "first_col", "last_col")
)


def _tall(spark: SparkSession, sf_dir: str) -> Distributed:
    return kept(spark, sf_dir, "tall", lambda: layout.partition_even(get_matrix(spark, sf_dir, "tall").transpose(), P))


@query("parts_range")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = get_even(spark, sf_dir, "dense_first", "range")
    return d.parts.agg(F.count(F.lit(1)).alias("parts"), F.sum("nnz").alias("total"), F.round(F.max("nnz") / F.avg("nnz"), 3).alias("max_to_mean"))


def _spans(kind: str, name: str) -> Callable:
    make = {"columns": baselines.partition_columns, "rows": baselines.partition_rows, "balanced": baselines.partition_columns_balanced}[kind]
    return lambda s, d: kept(s, d, f"spans {kind} {name}", lambda: make(get_matrix(s, d, name), P))


query("parts_columns", ENTRIES["dense_first"] + f" SELECT CAST(col * {P} // {_SIZE['dense_first'][1]} AS INTEGER) AS part, count(*) AS nnz FROM e GROUP BY 1")(lambda s, d: _spans("columns", "dense_first")(s, d).parts.select("part", "nnz"))
query("parts_rows", ENTRIES["dense_first"] + f" SELECT CAST(row * {P} // {_SIZE['dense_first'][0]} AS INTEGER) AS part, count(*) AS nnz FROM e GROUP BY 1")(lambda s, d: _spans("rows", "dense_first")(s, d).parts.select("part", "nnz"))
query("parts_columns_balanced")(lambda s, d: plans.imbalance(_spans("balanced", "dense_first")(s, d)))
query("parts_blocks", ENTRIES["balanced"] + f" SELECT CAST((row * 2 // {_SIZE['balanced'][0]}) * 4 + col * 4 // {_SIZE['balanced'][1]} AS INTEGER) AS part, count(*) AS nnz FROM e GROUP BY 1")(
    lambda s, d: baselines.partition_blocks(get_matrix(s, d, "balanced"), (2, 4)).parts.select("part", "nnz")
)

# --- setup


def _setup(upto: str) -> Callable:
    def make(s, d):
        df = layout.neighbour_flags(get_even(s, d).parts)
        df = df if upto == "flags" else layout.closing_mark(df)
        return df if upto in ("flags", "marks") else layout.group_ranks(df)

    return make


_SHOWN = {"flags": ["shares_prev", "shares_next"], "marks": ["closes_left"], "group_ranks": ["right_rank", "left_rank"], "extents": ["parts_before", "parts_after"]}
for _name in ("flags", "marks", "group_ranks"):
    query(_name, ENTRIES["dense_first"] + _parts() + _SETUP + f" SELECT part, {', '.join(_SHOWN[_name])} FROM s")(lambda s, d, k=_name: _setup(k)(s, d).select("part", *_SHOWN[k]))
_S = ENTRIES["dense_first"] + _parts() + _SETUP
query("extents", _S + " SELECT part, parts_before, parts_after FROM s")(lambda s, d: layout.full_setup(get_even(s, d).parts).select("part", "parts_before", "parts_after"))
query("setup_full", _S + f" SELECT {_SETUP_COLUMNS} FROM s")(lambda s, d: layout.full_setup(get_even(s, d).parts))
query("scan_forward", _S + " SELECT part, parts_before AS value FROM s")(lambda s, d: layout.parts_before(_setup("group_ranks")(s, d)).select("part", F.col("parts_before").alias("value")))
query("scan_backward", _S + " SELECT part, parts_after AS value FROM s")(lambda s, d: layout.parts_after(_setup("group_ranks")(s, d)).select("part", F.col("parts_after").alias("value")))
query("scan_blocks", _S + " SELECT part, parts_before AS value FROM s")(
    lambda s, d: layout.scan_blocks(_setup("group_ranks")(s, d), "shares_prev", "left_rank", "part", "value", block=3).select("part", "value")
)
for _engine in ("window", "blocks", "grouping"):
    query(f"zones_{_engine}", ENTRIES["dense_first"] + _parts() + _ZONES + " SELECT zone, col, part_lo, part_hi, size FROM zones")(
        lambda s, d, g=_engine: layout.setup_zones(get_even(s, d).placed, get_even(s, d).parts, g).drop("parity")
    )
query("schedule_even_odd", ENTRIES["dense_first"] + _parts() + _ZONES + " SELECT CAST(zone % 2 AS INTEGER) AS parity, CAST(0 AS BIGINT) AS clashes FROM zones GROUP BY 1")(lambda s, d: layout.schedule_clashes(get_even(s, d).zones))

# --- products

for _method in ("flat", "tree", "dense"):
    query(f"forward_{_method}", ENTRIES["dense_first"] + _FORWARD)(lambda s, d, k=_method: _whole(products.forward(get_even(s, d), _x(get_even(s, d)), k, 2), "row", "y"))
for _mode in ("single", "even_odd"):
    query(f"transposed_{_mode}", ENTRIES["dense_first"] + _TRANSPOSED)(lambda s, d, k=_mode: _whole(vectors.gather(products.transposed(get_even(s, d), _v(get_even(s, d)), k), "u"), "col", "u"))


def _blocks(s, d):
    return kept(s, d, "blocks", lambda: products.pack_blocks(get_even(s, d), 5000).persist())


@query("forward_blocks", ENTRIES["dense_first"] + _FORWARD)
def _(spark, sf_dir):
    d = get_even(spark, sf_dir)
    partials = products.kernel_forward(_blocks(spark, sf_dir), _x(d))
    return _whole(products.allreduce_short(partials, d.matrix.m), "row", "y")


@query("transposed_blocks", ENTRIES["dense_first"] + _TRANSPOSED)
def _(spark, sf_dir):
    d = get_even(spark, sf_dir)
    local = kept(spark, sf_dir, "blocks local", lambda: products.kernel_transposed(_blocks(spark, sf_dir), 1.0 + np.arange(d.matrix.m) % 5).persist())
    return _whole(vectors.gather(products.zone_reduce(local, d.zones), "u"), "col", "u")


query("transposed_copies", ENTRIES["dense_first"] + _parts() + _ZONES + ", t AS (SELECT col, CAST(sum(val * (1 + row % 5)) AS BIGINT) AS u FROM e GROUP BY col) SELECT DISTINCT p.part, p.col, t.u FROM p JOIN zones USING (col) JOIN t USING (col)")(
    lambda s, d: _whole(products.transposed(get_even(s, d), _v(get_even(s, d))).join(F.broadcast(get_even(s, d).zones.select("col")), "col"), "part", "col", "u")
)
for _kind in ("columns", "rows", "balanced"):
    query(f"forward_{_kind}", ENTRIES["dense_first"] + _FORWARD)(lambda s, d, k=_kind: _whole(baselines.forward_spans(_spans(k, "dense_first")(s, d), long_x(s, get_matrix(s, d, "dense_first").n)), "row", "y"))
    query(f"transposed_{_kind}", ENTRIES["dense_first"] + _TRANSPOSED)(
        lambda s, d, k=_kind: _whole(baselines.transposed_spans(_spans(k, "dense_first")(s, d), short_v(s, get_matrix(s, d, "dense_first").m), k == "rows"), "col", "u")
    )
for _name in ("dense_first", "native", "balanced", "random", "bigrams"):
    _as = "" if _name == "dense_first" else f"_{_name}"
    query(f"forward_plain{_as}", ENTRIES[_name] + _FORWARD)(lambda s, d, k=_name: _whole(products.forward_plain(get_matrix(s, d, k), long_x(s, get_matrix(s, d, k).n)), "row", "y"))
    query(f"transposed_plain{_as}", ENTRIES[_name] + _TRANSPOSED)(lambda s, d, k=_name: _whole(products.transposed_plain(get_matrix(s, d, k), short_v(s, get_matrix(s, d, k).m)), "col", "u"))
for _name, _label in (
    ("native", "w2"), ("random", "w3"), ("balanced", "w3b"), ("user_type", "w5_user_type"), ("bigrams", "w8"), ("brand_order", "w11_brand_order"), ("customer_part", "w11_customer_part"),
    ("pages", "w11_pages"), ("conversations", "w11_conversations"), ("benchmark", "w11_benchmark"), ("label", "order_label"), ("hashed", "order_hashed"), ("dense_last", "order_dense_last"),
):
    query(f"{_label}_forward", ENTRIES[_name] + _FORWARD)(lambda s, d, k=_name: _whole(products.forward(get_even(s, d, k), _x(get_even(s, d, k))), "row", "y"))
    query(f"{_label}_transposed", ENTRIES[_name] + _TRANSPOSED)(lambda s, d, k=_name: _whole(vectors.gather(products.transposed(get_even(s, d, k), _v(get_even(s, d, k))), "u"), "col", "u"))
# a tall matrix takes its forward product as the transposed one of its transpose, and the other way round
query("tall_forward", ENTRIES["tall"] + _FORWARD)(
    lambda s, d: products.transposed(_tall(s, d), s.range(_tall(s, d).matrix.m).select(F.col("id").alias("row"), (1 + F.col("id") % 7).cast("double").alias("v"))).where("is_home").select(F.col("col").alias("row"), F.col("u").cast("long").alias("y"))
)
query("tall_transposed", ENTRIES["tall"] + _TRANSPOSED)(
    lambda s, d: products.forward(_tall(s, d), vectors.spread(s.range(_tall(s, d).matrix.n).select(F.col("id").alias("col"), (1 + F.col("id") % 5).cast("double").alias("x")), _tall(s, d))).select(F.col("row").alias("col"), F.col("y").cast("long").alias("u"))
)


@query("w6_forward", ENTRIES["dense_first"] + ", w AS (SELECT row, col + 1 AS col, val FROM e UNION ALL SELECT range, 0, 1 FROM range((SELECT max(doc_id) + 1 FROM documents))) SELECT row, CAST(sum(val * (1 + col % 7)) AS BIGINT) AS y FROM w GROUP BY row")
def _(spark, sf_dir):
    d = kept(spark, sf_dir, "constant", lambda: layout.partition_even(generators.with_constant_column(get_matrix(spark, sf_dir, "dense_first")), P))
    return _whole(products.forward(d, _x(d)), "row", "y")


@query("w6_transposed", ENTRIES["dense_first"] + ", w AS (SELECT row, col + 1 AS col, val FROM e UNION ALL SELECT range, 0, 1 FROM range((SELECT max(doc_id) + 1 FROM documents))) SELECT col, CAST(sum(val * (1 + row % 5)) AS BIGINT) AS u FROM w GROUP BY col")
def _(spark, sf_dir):
    d = kept(spark, sf_dir, "constant", lambda: layout.partition_even(generators.with_constant_column(get_matrix(spark, sf_dir, "dense_first")), P))
    return _whole(vectors.gather(products.transposed(d, _v(d)), "u"), "col", "u")


def _vectors(spark: SparkSession, sf_dir: str) -> Distributed:
    def make() -> Distributed:
        e = written(matrix.array_matrix(load_table(spark, sf_dir, "embeddings"), "vec_id", "embedding"), "vectors")
        return layout.partition_even(SparseMatrix(e, 64, e.agg(F.max("col")).first()[0] + 1), P)

    return kept(spark, sf_dir, "vectors", make)


_DENSE = "WITH e AS (SELECT unnest(range(64)) AS row, vec_id AS col, unnest(embedding) AS val FROM embeddings)"
query("w9_forward", _DENSE + " SELECT row, round(sum(CAST(val AS DOUBLE) * (1 + col % 7)), 4) AS y FROM e GROUP BY row")(
    lambda s, d: products.forward(_vectors(s, d), _x(_vectors(s, d))).select("row", F.round("y", 4).alias("y"))
)
query("w9_transposed", _DENSE + " SELECT col, round(sum(CAST(val AS DOUBLE) * (1 + row % 5)), 4) AS u FROM e GROUP BY col")(
    lambda s, d: vectors.gather(products.transposed(_vectors(s, d), _v(_vectors(s, d))), "u").select("col", F.round("u", 4).alias("u"))
)


def _supplier_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each supplier's whole cents, as a short vector."""
    return load_table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("row"), F.round(F.col("s_acctbal") * 100).alias("v"))


query("w11_supplier_balance", ENTRIES["balanced"] + " SELECT col, CAST(sum(val * CAST(round(s_acctbal * 100) AS BIGINT)) AS BIGINT) AS u FROM e JOIN supplier ON s_suppkey = row GROUP BY col")(
    lambda s, d: _whole(vectors.gather(products.transposed(get_even(s, d, "balanced"), _supplier_balance(s, d)), "u"), "col", "u")
)


def _grid(spark: SparkSession, sf_dir: str) -> Distributed:
    return kept(spark, sf_dir, "grid", lambda: baselines.partition_blocks(get_matrix(spark, sf_dir, "balanced"), (2, 4)))


query("forward_grid", ENTRIES["balanced"] + _FORWARD)(lambda s, d: _whole(baselines.forward_spans(_grid(s, d), long_x(s, get_matrix(s, d, "balanced").n)), "row", "y"))
query("transposed_grid", ENTRIES["balanced"] + _TRANSPOSED)(lambda s, d: _whole(baselines.transposed_spans(_grid(s, d), short_v(s, get_matrix(s, d, "balanced").m), shared=True), "col", "u"))


def _pairs_sql(turns: int) -> str:
    """The turns of chained products one after the other, by plain joins."""
    text = ", x0 AS (SELECT DISTINCT col, CAST(1 + col % 7 AS DOUBLE) AS x FROM e)"
    for k in range(1, turns + 1):
        text += f""", y{k} AS (SELECT row, sum(val * x) AS y FROM e JOIN x{k - 1} USING (col) GROUP BY row), v{k} AS (SELECT row, y / (SELECT max(abs(y)) FROM y{k}) AS v FROM y{k}),
x{k} AS (SELECT col, sum(val * v) AS x FROM e JOIN v{k} USING (row) GROUP BY col)"""
    return text + f", every AS (SELECT range AS row FROM range((SELECT max(doc_id) + 1 FROM documents))) SELECT every.row, round(coalesce(v, 0), 8) AS y FROM every LEFT JOIN v{turns} USING (row)"


def _pairs(spark: SparkSession, sf_dir: str, turns: int, name: str = "dense_first") -> DataFrame:
    """The last short vector of chained turns, by its largest value."""
    d = get_even(spark, sf_dir, name)
    y, _, _ = products.product_pairs(d, _x(d), _v(d), turns)
    return y.crossJoin(F.broadcast(y.agg(F.max(F.abs("y")).alias("peak")))).select("row", F.round(F.col("y") / F.col("peak"), 8).alias("y"))


query("pairs_chained_2", ENTRIES["dense_first"] + _pairs_sql(2))(lambda s, d: _pairs(s, d, 2))
query("w2_pairs", ENTRIES["native"] + _pairs_sql(3))(lambda s, d: _pairs(s, d, 3, "native"))


@query("w1_pairs", ENTRIES["dense_first"] + ", t AS (SELECT col, CAST(sum(val * (1 + row % 5)) AS BIGINT) AS u FROM e GROUP BY col) SELECT col, u FROM t")
def _(spark, sf_dir):
    d = get_even(spark, sf_dir)
    _, u, _ = products.product_pairs(d, _x(d), _v(d), 2, "independent")
    return _whole(vectors.gather(u, "u"), "col", "u")


# --- vectors in the overlapped layout

_LAID = ENTRIES["dense_first"] + _parts() + ", l AS (SELECT part, col, min(part) OVER (PARTITION BY col) = part AS home, 1 + col % 7 AS x FROM (SELECT DISTINCT part, col FROM p))"
query("vec_spread", _LAID + " SELECT part, col, x FROM l")(lambda s, d: _whole(_x(get_even(s, d)), "part", "col", "x"))
query("vec_gather", _LAID + " SELECT col, x FROM l WHERE home")(lambda s, d: _whole(vectors.gather(_x(get_even(s, d))), "col", "x"))
query("vec_add", _LAID + " SELECT part, col, 2 * x AS x FROM l")(lambda s, d: _whole(vectors.add(_x(get_even(s, d)), _x(get_even(s, d))), "part", "col", "x"))
query("vec_scale", _LAID + " SELECT part, col, 3 * x AS x FROM l")(lambda s, d: _whole(vectors.scale(3.0, _x(get_even(s, d))), "part", "col", "x"))
query("vec_axpy", _LAID + " SELECT part, col, 6 * x AS x FROM l")(lambda s, d: _whole(vectors.axpy(5.0, _x(get_even(s, d)), _x(get_even(s, d))), "part", "col", "x"))
query("vec_dot", _LAID + " SELECT CAST(sum(3 * x * x) AS BIGINT) AS dot FROM l WHERE home")(lambda s, d: _whole(vectors.dot(_x(get_even(s, d)), vectors.scale(3.0, _x(get_even(s, d)))), "dot"))
query("vec_norm2", _LAID + " SELECT CAST(sum(x * x) AS BIGINT) AS norm2 FROM l WHERE home")(lambda s, d: _whole(vectors.norm2(_x(get_even(s, d))), "norm2"))
query("vec_complete", ENTRIES["balanced"] + f" SELECT range AS col, coalesce((SELECT max(1 + e.col % 7) FROM e WHERE e.col = range AND e.col % 2 = 0), 0) AS x FROM range({_SIZE['balanced'][1]})")(
    lambda s, d: _whole(vectors.complete(vectors.gather(_x(get_even(s, d, "balanced"))).where("col % 2 = 0"), get_matrix(s, d, "balanced").n), "col", "x")
)
query("vec_balance", _LAID + " SELECT part, count(*) AS stored, count(*) FILTER (WHERE home) AS home FROM l GROUP BY part")(lambda s, d: vectors.vector_balance(get_even(s, d)))

query("vector_imbalance", _LAID + ", b AS (SELECT part, count(*) AS stored, count(*) FILTER (WHERE home) AS home FROM l GROUP BY part) SELECT round(max(stored) * count(*) / CAST(sum(stored) AS DOUBLE), 4) AS stored_ratio, round(max(home) * count(*) / CAST(sum(home) AS DOUBLE), 4) AS home_ratio FROM b")(
    lambda s, d: vectors.vector_imbalance(get_even(s, d))
)

# --- measures and sweeps

_PS = "(SELECT unnest([1, 2, 4, 8, 16, 32, 64, 128, 256, 512]) AS parts)"
for _name in ("dense_first", "native", "balanced", "random", "bigrams", "label", "hashed", "dense_last"):
    _prof = lambda s, d, k=_name: kept(s, d, f"profile {k}", lambda: plans.column_profile(get_matrix(s, d, k)))
    query(
        f"sweep_imbalance_{_name}",
        ENTRIES[_name]
        + f""", cc AS (SELECT col, count(*) AS nnz FROM e GROUP BY col), ps AS {_PS},
l AS (SELECT parts, col * parts // {_SIZE[_name][1]} AS part, sum(nnz) AS nnz FROM cc, ps GROUP BY ALL),
a AS (SELECT parts, unnest(range(parts)) AS part FROM ps),
f AS (SELECT a.parts, coalesce(l.nnz, 0) AS nnz FROM a LEFT JOIN l ON a.parts = l.parts AND a.part = l.part)
SELECT CAST(parts AS INTEGER) AS parts, round(CAST((max(nnz) - min(nnz)) * 100.0 * parts AS DOUBLE) / CAST(sum(nnz) AS DOUBLE), 2) AS delta_pct FROM f GROUP BY parts""",
    )(lambda s, d, k=_name, f=_prof: plans.sweep_imbalance(f(s, d), get_matrix(s, d, k).n))
    query(
        f"sweep_zones_{_name}",
        ENTRIES[_name]
        + f""", cc AS (SELECT col, count(*) AS nnz FROM e GROUP BY col), hi AS (SELECT sum(nnz) OVER (ORDER BY col) AS hi, nnz, sum(nnz) OVER () AS z FROM cc), ps AS {_PS},
x AS (SELECT parts, (hi - 1) * parts // z - (hi - nnz) * parts // z AS extra FROM hi, ps)
SELECT CAST(parts AS INTEGER) AS parts, count(*) FILTER (WHERE extra > 0) AS zones, CAST(max(CASE WHEN extra > 0 THEN extra + 1 ELSE 0 END) AS BIGINT) AS largest, CAST(sum(extra) AS BIGINT) AS copies FROM x GROUP BY parts""",
    )(lambda s, d, f=_prof: plans.sweep_zones(f(s, d)))
    query(
        f"profile_{_name}",
        ENTRIES[_name]
        + f""", cc AS (SELECT col, count(*) AS nnz FROM e GROUP BY col), t AS (SELECT nnz FROM cc ORDER BY nnz DESC LIMIT 10)
SELECT CAST({_SIZE[_name][0]} AS BIGINT) AS m, CAST({_SIZE[_name][1]} AS BIGINT) AS n, CAST(sum(nnz) AS BIGINT) AS z, round(CAST(sum(nnz) AS DOUBLE) / {_SIZE[_name][1]}, 4) AS mean_nnz,
CAST(count(*) FILTER (WHERE nnz * 2 >= {_SIZE[_name][0]}) AS BIGINT) AS dense_columns, (SELECT max(nnz) FROM t) AS densest, (SELECT min(nnz) FROM t) AS tenth FROM cc""",
    )(lambda s, d, k=_name: plans.profile(get_matrix(s, d, k)))
query("imbalance_even", ENTRIES["dense_first"] + _parts() + f" SELECT CAST({P} AS INTEGER) AS parts, round(CAST((max(nnz) - min(nnz)) * 100.0 * {P} AS DOUBLE) / CAST(sum(nnz) AS DOUBLE), 2) AS delta_pct FROM parts")(lambda s, d: plans.imbalance(get_even(s, d)))
query("zone_stats", ENTRIES["dense_first"] + _parts() + _ZONES + " SELECT count(*) AS zones, max(size) AS largest, CAST(sum(size - 1) AS BIGINT) AS copies FROM zones")(lambda s, d: plans.zone_stats(get_even(s, d).zones))
query(
    "moved_values",
    ENTRIES["dense_first"] + _parts() + _ZONES + f""" SELECT 'even_entries' AS scheme, (SELECT count(*) FROM (SELECT DISTINCT part, row FROM p)) AS forward_values, (SELECT CAST(sum(size) AS BIGINT) FROM zones) AS transposed_values
UNION ALL SELECT 'column_spans', (SELECT count(*) FROM (SELECT DISTINCT col * {P} // {_SIZE['dense_first'][1]}, row FROM e)), 0""",
)(lambda s, d: plans.moved_values(get_even(s, d), "even_entries").unionByName(plans.moved_values(_spans("columns", "dense_first")(s, d), "column_spans")))


@query(
    "cost_model",
    ENTRIES["balanced"] + f""", st AS (SELECT CAST({_SIZE['balanced'][0]} AS DOUBLE) AS m, CAST({_SIZE['balanced'][1]} AS DOUBLE) AS n, CAST(count(*) AS DOUBLE) AS z FROM e)
SELECT 'even_entries' AS scheme, 'forward' AS operation, round(z / 8 + m * 3, 3) AS cost FROM st UNION ALL SELECT 'even_entries', 'transposed', round(z / 8 + 1, 3) FROM st
UNION ALL SELECT 'even_entries', 'long_vector', round(least(z / 8, n), 3) FROM st UNION ALL SELECT 'even_entries', 'inner_product', round(least(z / 8, n) + 3, 3) FROM st
UNION ALL SELECT 'even_entries', 'setup', CAST(3 AS DOUBLE) UNION ALL SELECT 'column_spans', 'forward', round(least(n * m / 8, z) + m * 3, 3) FROM st
UNION ALL SELECT 'column_spans', 'transposed', round(least(n * m / 8, z), 3) FROM st UNION ALL SELECT 'column_spans', 'long_vector', round(n / 8, 3) FROM st
UNION ALL SELECT 'column_spans', 'inner_product', round(n / 8 + 3, 3) FROM st UNION ALL SELECT 'general_split', 'setup', CAST(8 AS DOUBLE)""",
)
def _(spark, sf_dir):
    m = get_matrix(spark, sf_dir, "balanced")
    rows = plans.cost_model(plans.Stats(m.m, m.n, m.nnz, 0, 2), P)
    return spark.createDataFrame([(a, b, round(c, 3)) for a, b, c in rows], "scheme string, operation string, cost double")


query("random_matrix", _RANDOM + " SELECT row, col, CAST(val AS BIGINT) AS val FROM e")(lambda s, d: _whole(get_matrix(s, d, "random").entries, "row", "col", "val"))
query("max_error_forward", ENTRIES["dense_first"] + " SELECT count(DISTINCT row) AS compared, CAST(0 AS DOUBLE) AS max_abs, CAST(0 AS DOUBLE) AS max_rel FROM e")(
    lambda s, d: plans.max_error(products.forward(get_even(s, d), _x(get_even(s, d))), products.forward_plain(get_matrix(s, d, "dense_first"), long_x(s, get_matrix(s, d, "dense_first").n)), "row", "y")
)
query("max_error_transposed", ENTRIES["dense_first"] + " SELECT count(DISTINCT col) AS compared, CAST(0 AS DOUBLE) AS max_abs, CAST(0 AS DOUBLE) AS max_rel FROM e")(
    lambda s, d: plans.max_error(vectors.gather(products.transposed(get_even(s, d), _v(get_even(s, d))), "u"), products.transposed_plain(get_matrix(s, d, "dense_first"), _v(get_even(s, d))), "col", "u")
)
query("identity_gap", ENTRIES["dense_first"] + " SELECT CAST(sum(val * (1 + col % 7) * (1 + row % 5)) AS DOUBLE) AS v_ax, CAST(sum(val * (1 + col % 7) * (1 + row % 5)) AS DOUBLE) AS va_x, CAST(0 AS DOUBLE) AS gap FROM e")(
    lambda s, d: plans.identity_gap(get_even(s, d), _x(get_even(s, d)), _v(get_even(s, d)))
)
query("setup_ratio")(lambda s, d: plans.setup_ratio(get_even(s, d), _v(get_even(s, d))))
query("mx_terms", _TERMS.replace("{order}", "term") + " SELECT row, term, val FROM tf")(lambda s, d: _whole(matrix.term_counts(load_table(s, d, "documents")), "row", "term", "val"))
query("mx_bigrams", _BIGRAMS + " SELECT row, term, val FROM tf")(lambda s, d: _whole(matrix.ngram_counts(load_table(s, d, "documents")), "row", "term", "val"))
query("mx_col_index", _TERMS.replace("{order}", "nnz DESC, term") + " SELECT term, col, nnz FROM idx")(lambda s, d: matrix.index_labels(matrix.term_counts(load_table(s, d, "documents"))))

# --- solvers


def _labels(spark: SparkSession, sf_dir: str) -> tuple[Distributed, np.ndarray]:
    """Rows of labelled documents only, and quality less one half as the right-hand side."""

    def make():
        base = get_matrix(spark, sf_dir, "dense_first")
        labels = load_table(spark, sf_dir, "labels", "doc_id", "quality").where("quality IS NOT NULL")
        numbered = checkpointed(matrix.global_rank(labels.groupBy("doc_id").agg(F.max("quality").alias("b")), "doc_id", name="at"))
        e = base.entries.join(F.broadcast(numbered.select(F.col("doc_id").alias("row"), "at")), "row").select(F.col("at").alias("row"), "col", F.least("val", F.lit(1.0)).alias("val"))
        b = products.dense(numbered.select(F.col("at").alias("row"), (F.col("b") - 0.5).alias("b")), "row", "b", numbered.count())
        return layout.partition_even(SparseMatrix(checkpointed(e), len(b), base.n), P), b

    return kept(spark, sf_dir, "labels", make)


# each stops at its tolerance; the last of the rows tells whether it was reached before the limit of iterations
query("cg_ridge")(lambda s, d: solvers.conjugate_gradient(*_labels(s, d), ridge=10.0, tol=1e-6, max_iter=50).frame(s))
query("spectral_ridge")(lambda s, d: solvers.spectral_gradient(*_labels(s, d), ridge=10.0, tol=1e-2, max_iter=15).frame(s))
query("projected_spectral")(lambda s, d: solvers.projected_spectral_gradient(*_labels(s, d), -0.01, 0.01, ridge=10.0, tol=1e-2, max_iter=15).frame(s))
query("gradient_fixed")(lambda s, d: solvers.gradient_descent(*_labels(s, d), ridge=10.0, max_iter=20).frame(s))
query("top_singular")(lambda s, d: solvers.largest_singular_value(_labels(s, d)[0], 20).frame(s))
