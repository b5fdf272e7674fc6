"""Operators around the products, each on the given tables: relational steps, functions, windows, streams and UDFs.

Where Spark and the checking engine read the same SQL, one text serves both.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from nzspan import functions, streaming
from nzspan.operators import layout, matrix, products, vectors
from nzspan.sources import load_table
from nzspan.workloads import ENTRIES, P, _x, get_even, get_matrix, kept, long_x, query, short_v

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def run_sql(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    """A SQL text over views of the given tables."""
    for name in TABLES:
        if f"{name} " in f"{text} ".replace("\n", " ").replace(",", " ").replace(")", " "):
            load_table(spark, sf_dir, name).createOrReplaceTempView(name)
    return spark.sql(text)


def both(name: str, text: str, other: str | None = None) -> None:
    """Register a query by one SQL text, or by Spark's and the checking engine's."""
    query(name, other or text)(lambda s, d: run_sql(s, d, text))


# the matrix of suppliers and parts as entries, for SQL
_E = "WITH e AS (SELECT l_suppkey AS row, l_partkey AS col, CAST(sum(l_quantity) AS BIGINT) AS val FROM lineitem GROUP BY l_suppkey, l_partkey)"


def _entries(s: SparkSession, d: str) -> DataFrame:
    return get_matrix(s, d, "balanced").entries


def _long(df: DataFrame) -> DataFrame:
    return df.withColumn("val", F.col("val").cast("long"))


both("src_parquet", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
query("mx_supplier_part", _E + " SELECT row, col, val FROM e")(lambda s, d: _long(_entries(s, d)))
query("mx_order_part", ENTRIES["tall"] + " SELECT row, col, val FROM e")(lambda s, d: _long(get_matrix(s, d, "tall").entries))
query("mx_user_type", ENTRIES["user_type"] + " SELECT row, col, val FROM e")(lambda s, d: _long(get_matrix(s, d, "user_type").entries))
query("mx_brand_order", ENTRIES["brand_order"] + " SELECT row, col, val FROM e")(lambda s, d: _long(get_matrix(s, d, "brand_order").entries))
query("mx_customer_part", "SELECT o_custkey AS row, l_partkey AS col, CAST(sum(l_quantity) AS BIGINT) AS val FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2")(
    lambda s, d: _long(matrix.pair_matrix(load_table(s, d, "lineitem").join(load_table(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")), "o_custkey", "l_partkey", "l_quantity"))
)
query("mx_embeddings", "SELECT CAST(unnest(range(64)) AS BIGINT) AS row, vec_id AS col, round(CAST(unnest(embedding) AS DOUBLE), 6) AS val FROM embeddings")(
    lambda s, d: matrix.array_matrix(load_table(s, d, "embeddings"), "vec_id", "embedding").withColumn("val", F.round("val", 6))
)
query("mx_canonical", "WITH e AS (SELECT l_orderkey AS row, l_linenumber AS col, CAST(sum(l_quantity - 25) AS BIGINT) AS val FROM lineitem WHERE l_quantity > 20 GROUP BY 1, 2) SELECT row, CAST(col AS BIGINT) AS col, val FROM e WHERE val <> 0")(
    lambda s, d: _long(matrix.canonical(load_table(s, d, "lineitem").select(F.col("l_orderkey").alias("row"), F.col("l_linenumber").alias("col"), F.when(F.col("l_quantity") > 20, F.col("l_quantity") - 25).alias("val"))))
)
query("mx_tfidf", _E + ", df AS (SELECT col, count(*) AS n FROM e GROUP BY col) SELECT row, col, round(val * ln(CAST((SELECT max(l_suppkey) + 1 FROM lineitem) AS DOUBLE) / n), 6) AS val FROM e JOIN df USING (col)")(
    lambda s, d: matrix.weight(get_matrix(s, d, "balanced"), "tfidf").entries.withColumn("val", F.round("val", 6))
)
query("mx_log_tf", _E + " SELECT row, col, round(1 + ln(val), 6) AS val FROM e")(lambda s, d: matrix.weight(get_matrix(s, d, "balanced"), "log").entries.withColumn("val", F.round("val", 6)))
query("mx_pivot", _E + " SELECT row, " + ", ".join(f"CAST(coalesce(sum(val) FILTER (WHERE col = {c}), 0) AS BIGINT) AS c{c}" for c in range(4)) + " FROM e GROUP BY row")(
    lambda s, d: matrix.to_dense(_entries(s, d), [0, 1, 2, 3]).select("row", *[F.col(str(c)).cast("long").alias(f"c{c}") for c in range(4)])
)

# matrix algebra
query("al_subset", _E + " SELECT row, col, val FROM e WHERE row IN (1, 3, 5) AND col BETWEEN 10 AND 99")(lambda s, d: _long(_entries(s, d).where(F.col("row").isin(1, 3, 5) & F.col("col").between(10, 99))))
query("al_threshold", _E + " SELECT row, col, val FROM e WHERE val > 50")(lambda s, d: _long(_entries(s, d).where("val > 50")))
query("al_semi", _E + " SELECT row, col, val FROM e WHERE col IN (SELECT p_partkey FROM part WHERE p_size > 40)")(lambda s, d: _long(_entries(s, d).join(load_table(s, d, "part").where("p_size > 40").select(F.col("p_partkey").alias("col")), "col", "left_semi").select("row", "col", "val")))
query("al_anti", _E + " SELECT row, col, val FROM e WHERE col NOT IN (SELECT p_partkey FROM part WHERE p_size > 10)")(lambda s, d: _long(_entries(s, d).join(load_table(s, d, "part").where("p_size > 10").select(F.col("p_partkey").alias("col")), "col", "left_anti").select("row", "col", "val")))
query("al_transpose", _E + " SELECT col AS row, row AS col, val FROM e")(lambda s, d: _long(get_matrix(s, d, "balanced").transpose().entries))
query("al_add", _E + " SELECT row, col, 3 * val AS val FROM e")(lambda s, d: _long(matrix.add(_entries(s, d), matrix.scale(_entries(s, d), 2.0))))
query("al_hadamard", _E + " SELECT row, col, val * val AS val FROM e")(lambda s, d: _long(matrix.hadamard(_entries(s, d), _entries(s, d))))
query("al_row_stats", _E + " SELECT row, count(*) AS nnz, CAST(sum(val) AS BIGINT) AS total, CAST(sum(val * val) AS BIGINT) AS square FROM e GROUP BY row")(lambda s, d: matrix.row_stats(_entries(s, d)).select("row", "nnz", F.col("total").cast("long"), F.col("square").cast("long")))
query("al_col_stats", _E + " SELECT col, count(*) AS nnz, CAST(sum(val) AS BIGINT) AS total, CAST(sum(val * val) AS BIGINT) AS square FROM e GROUP BY col")(lambda s, d: matrix.col_stats(_entries(s, d)).select("col", "nnz", F.col("total").cast("long"), F.col("square").cast("long")))
query("al_scale_rows", _E + " SELECT row, col, val * (1 + row % 5) AS val FROM e")(lambda s, d: _long(matrix.scale_rows(_entries(s, d), F.broadcast(short_v(s, get_matrix(s, d, "balanced").m)))))
query("al_scale_cols", _E + " SELECT row, col, val * (1 + col % 7) AS val FROM e")(lambda s, d: _long(matrix.scale_cols(_entries(s, d), long_x(s, get_matrix(s, d, "balanced").n))))
query("al_gram", _E + " SELECT a.row, b.row AS other, CAST(sum(a.val * b.val) AS BIGINT) AS val FROM e a JOIN e b ON a.col = b.col GROUP BY a.row, b.row")(lambda s, d: _long(matrix.gram(_entries(s, d))))
query("al_outer", "SELECT CAST(r_regionkey AS BIGINT) AS row, c_custkey AS col, CAST((1 + r_regionkey % 5) * (1 + c_custkey % 7) AS BIGINT) AS val FROM region, customer")(
    lambda s, d: _long(
        matrix.outer(
            load_table(s, d, "region", "r_regionkey").select(F.col("r_regionkey").cast("long").alias("row"), (1 + F.col("r_regionkey") % 5).cast("double").alias("v")),
            load_table(s, d, "customer", "c_custkey").select(F.col("c_custkey").alias("col"), (1 + F.col("c_custkey") % 7).cast("double").alias("x")),
        )
    )
)
_PAT = ("SELECT l_suppkey AS row, l_partkey AS col FROM lineitem WHERE l_quantity > 25", "SELECT l_suppkey AS row, l_partkey AS col FROM lineitem WHERE l_quantity < 40")
both("al_intersect", f"{_PAT[0]} INTERSECT {_PAT[1]}")
both("al_except", f"{_PAT[0]} EXCEPT {_PAT[1]}")
both("al_union", f"{_PAT[0]} UNION {_PAT[1]}")
both("al_distinct", "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem")

# joins
for _hint in ("broadcast", "merge", "shuffle_hash"):
    query(f"jn_{_hint}", _E + " SELECT row, CAST(sum(val * (1 + col % 7)) AS BIGINT) AS y FROM e GROUP BY row")(
        lambda s, d, h=_hint: _entries(s, d).join(long_x(s, get_matrix(s, d, "balanced").n).hint(h), "col").groupBy("row").agg(F.sum(F.col("val") * F.col("x")).cast("long").alias("y"))
    )
for _how in ("left", "right", "full"):
    _text = f"SELECT c_custkey, o_orderkey FROM customer {_how.upper()} JOIN (SELECT * FROM orders WHERE o_orderstatus = 'F') o ON c_custkey = o_custkey AND c_acctbal > 0"
    both(f"jn_{_how}", _text)
query("jn_range", ENTRIES["balanced"] + f", r AS (SELECT col, row_number() OVER (ORDER BY col, row) - 1 AS rank, count(*) OVER () AS z FROM e), p AS (SELECT CAST(rank * {P} // z AS INTEGER) AS part, min(col) AS lo, max(col) AS hi FROM r GROUP BY 1) SELECT part, count(*) AS n FROM p JOIN range(0, (SELECT max(hi) + 1 FROM p)) t ON t.range BETWEEN lo AND hi GROUP BY part")(
    lambda s, d: vectors.spread_cover(long_x(s, get_matrix(s, d, "balanced").n), get_even(s, d, "balanced")).groupBy("part").agg(F.count(F.lit(1)).alias("n"))
)
both("jn_theta", "SELECT a.n_name AS left_name, b.n_name AS right_name FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
both("jn_cross", "SELECT r_name, n_name FROM region CROSS JOIN nation")
_ASOF = "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before_id FROM events"
query("jn_asof", _ASOF)(
    lambda s, d: load_table(s, d, "events").select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)).alias("before_id"))
)


@query("jn_interval", "SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _(spark, sf_dir):
    """Events of a user within an hour: equal keys on user and hour, each event also looking into the next hour."""
    e = load_table(spark, sf_dir, "events", "event_id", "user_id", "ts")
    hour = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000)
    a = e.select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("a_ts"), F.explode(F.array(hour, hour + 1)).alias("h"))
    b = e.select(F.col("event_id").alias("second_id"), "user_id", F.col("ts").alias("b_ts"), hour.alias("h"))
    within = (F.col("b_ts") > F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr("INTERVAL 1 HOUR"))
    return a.join(b, ["user_id", "h"]).where(within).select("first_id", "second_id")


# aggregates
both("ag_sum", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS quantity, round(avg(l_discount), 6) AS discount FROM lineitem GROUP BY l_returnflag, l_linestatus")
both("ag_minmax_string", "SELECT c_mktsegment, min(c_name) AS lo, max(c_name) AS hi FROM customer GROUP BY c_mktsegment")
both("ag_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_returnflag")
query("ag_distinct_approx")(lambda s, d: load_table(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts")))
both("ag_rollup", "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY ROLLUP (lang, source)")
both("ag_cube", "SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
both("ag_gsets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
both("ag_percentile", "SELECT lang, percentile(n_chars, 0.5) AS median FROM documents GROUP BY lang", "SELECT lang, quantile_cont(n_chars, 0.5) AS median FROM documents GROUP BY lang")
both("ag_pack", "SELECT c_nationkey, array_join(sort_array(collect_list(c_custkey)), ',') AS keys FROM customer GROUP BY c_nationkey", "SELECT c_nationkey, string_agg(CAST(c_custkey AS VARCHAR), ',' ORDER BY c_custkey) AS keys FROM customer GROUP BY c_nationkey")
both("ag_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 15")

# windows, top-k, subqueries
both("wn_rank", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr FROM (SELECT o_orderkey, o_custkey, o_orderpriority FROM orders) t WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority, o_orderkey)", "SELECT o_orderkey, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority, o_orderkey)")
both("wn_ntile", f"SELECT c_custkey, ntile({P}) OVER (PARTITION BY c_nationkey ORDER BY c_custkey) AS part FROM customer", f"SELECT c_custkey, CAST(ntile({P}) OVER (PARTITION BY c_nationkey ORDER BY c_custkey) AS INTEGER) AS part FROM customer")
both("wn_cume", "SELECT c_custkey, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_custkey)")
both("wn_lag_lead", "SELECT event_id, lag(event_id) OVER w AS before_id, lead(event_id, 2) OVER w AS after_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
both("wn_first_last", "SELECT event_id, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER w AS last_id, nth_value(event_id, 2) OVER w AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
both("wn_rows", "SELECT l_orderkey, l_linenumber, CAST(sum(l_quantity) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS BIGINT) AS moving FROM lineitem")
both("wn_range", "SELECT c_custkey, CAST(count(*) OVER (PARTITION BY c_nationkey ORDER BY c_custkey RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS BIGINT) AS near FROM customer")
both("wn_reverse", "SELECT c_custkey, CAST(sum(c_custkey) OVER (PARTITION BY c_nationkey ORDER BY c_custkey DESC ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS total FROM customer")
both("tk_global", "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 25")
both("tk_offset", "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 10 OFFSET 20")
both("tk_group", "SELECT c_nationkey, c_custkey FROM (SELECT c_nationkey, c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS n FROM customer) t WHERE n <= 3")
both("sq_scalar", _E + ", c AS (SELECT col, count(*) AS nnz FROM e GROUP BY col) SELECT col, nnz FROM c WHERE nnz > (SELECT avg(nnz) FROM c)")
both("sq_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'P')")

# functions
both(
    "fn_string",
    r"SELECT c_custkey, lower(c_name) AS lo, upper(c_mktsegment) AS up, trim(concat('  ', c_name, ' ')) AS tr, regexp_replace(c_name, '[0-9]+', '#') AS rr, regexp_extract(c_name, '([0-9]+)', 1) AS re, length(c_name) AS n, substring(c_name, 2, 4) AS sub, concat_ws('-', c_name, c_mktsegment) AS cw, instr(c_name, 'r') AS at, lpad(c_mktsegment, 12, '*') AS lp FROM customer",
    r"SELECT c_custkey, lower(c_name) AS lo, upper(c_mktsegment) AS up, trim(concat('  ', c_name, ' ')) AS tr, regexp_replace(c_name, '[0-9]+', '#', 'g') AS rr, regexp_extract(c_name, '([0-9]+)', 1) AS re, CAST(length(c_name) AS INTEGER) AS n, substring(c_name, 2, 4) AS sub, concat_ws('-', c_name, c_mktsegment) AS cw, CAST(instr(c_name, 'r') AS INTEGER) AS at, lpad(c_mktsegment, 12, '*') AS lp FROM customer",
)
both(
    "fn_date",
    "SELECT event_id, date_format(date_trunc('hour', ts), 'yyyy-MM-dd HH:mm') AS h, year(ts) AS y, month(ts) AS m, dayofmonth(ts) AS dm, hour(ts) AS hr, datediff(CAST(ts AS DATE), DATE'2024-01-01') AS dd FROM events",
    "SELECT event_id, strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M') AS h, CAST(year(ts) AS INTEGER) AS y, CAST(month(ts) AS INTEGER) AS m, CAST(day(ts) AS INTEGER) AS dm, CAST(hour(ts) AS INTEGER) AS hr, CAST(CAST(ts AS DATE) - DATE '2024-01-01' AS INTEGER) AS dd FROM events",
)
both("fn_math", "SELECT p_partkey, CAST(floor(p_retailprice) AS BIGINT) AS fl, CAST(ceil(p_retailprice) AS BIGINT) AS ce, p_partkey % 7 AS md, round(ln(1 + p_retailprice), 6) AS lg, round(sqrt(p_retailprice), 6) AS sq, abs(p_size - 25) AS ab, greatest(p_size, 10) AS gr, least(p_size, 10) AS le, round(power(p_size, 2), 6) AS pw FROM part")
both("fn_array", "SELECT vec_id, size(filter(embedding, x -> x > 0)) AS pos, round(aggregate(transform(embedding, x -> CAST(x AS DOUBLE)), CAST(0 AS DOUBLE), (a, x) -> a + x), 6) AS total, round(CAST(element_at(embedding, 3) AS DOUBLE), 6) AS third FROM embeddings", "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS pos, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE))), 6) AS total, round(CAST(embedding[3] AS DOUBLE), 6) AS third FROM embeddings")
both("fn_array_dot", "SELECT vec_id, round(aggregate(zip_with(embedding, embedding, (x, y) -> CAST(x AS DOUBLE) * CAST(y AS DOUBLE)), CAST(0 AS DOUBLE), (a, x) -> a + x), 6) AS dot FROM embeddings", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 6) AS dot FROM embeddings")
both("fn_map", "SELECT n_regionkey, CAST(size(map_keys(m)) AS BIGINT) AS n, element_at(m, min_key) AS first_name FROM (SELECT n_regionkey, map_from_entries(collect_list(struct(n_nationkey, n_name))) AS m, min(n_nationkey) AS min_key FROM nation GROUP BY n_regionkey) t", "SELECT n_regionkey, count(*) AS n, min_by(n_name, n_nationkey) AS first_name FROM nation GROUP BY n_regionkey")
both("fn_json", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
both("fn_cond", "SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 1000 THEN 'low' ELSE 'high' END AS kind, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS segment, try_cast(substring(c_name, 1, 2) AS INT) AS bad FROM customer")
both("fn_struct", "SELECT c_custkey, s.a AS a, s.b AS b FROM (SELECT c_custkey, named_struct('a', c_nationkey, 'b', c_mktsegment) AS s FROM customer) t", "SELECT c_custkey, s.a AS a, s.b AS b FROM (SELECT c_custkey, {'a': c_nationkey, 'b': c_mktsegment} AS s FROM customer) t")


# UDF surface
@query("udtf_tokens", r"SELECT item_id, count(*) AS n FROM (SELECT item_id, unnest(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+')) AS t FROM benchmark) WHERE t <> '' GROUP BY item_id")
def _(spark, sf_dir):
    from nzspan.session import ship

    ship(spark)
    functions.register(spark)
    load_table(spark, sf_dir, "benchmark").createOrReplaceTempView("benchmark")
    return spark.sql("SELECT item_id, count(*) AS n FROM benchmark, LATERAL nz_tokens(text) GROUP BY item_id")


@query("udf_part", ENTRIES["balanced"] + f", r AS (SELECT row, col, row_number() OVER (ORDER BY col, row) - 1 AS rank, count(*) OVER () AS z FROM e) SELECT CAST(rank * {P} // z AS INTEGER) AS part, count(*) AS n FROM r GROUP BY 1")
def _(spark, sf_dir):
    from nzspan.session import ship

    ship(spark)
    m = get_matrix(spark, sf_dir, "balanced")
    part = functions.part_of_key(layout.border_keys(m, P))
    return m.entries.select(part("col", "row").alias("part")).groupBy("part").agg(F.count(F.lit(1)).alias("n"))


@query("udaf_dot", "SELECT l_suppkey, CAST(sum(l_quantity * l_linenumber) AS BIGINT) AS dot FROM lineitem GROUP BY l_suppkey")
def _(spark, sf_dir):
    from nzspan.session import ship

    ship(spark)
    return load_table(spark, sf_dir, "lineitem").groupBy("l_suppkey").agg(functions.dot("l_quantity", "l_linenumber").cast("long").alias("dot"))


@query("sql_forward", ENTRIES["dense_first"] + " SELECT row, CAST(sum(val * (1 + col % 7)) AS BIGINT) AS y FROM e GROUP BY row")
def _(spark, sf_dir):
    d = get_even(spark, sf_dir)
    d.placed.createOrReplaceTempView("nz_entries")
    _x(d).createOrReplaceTempView("nz_x")
    return spark.sql("SELECT row, CAST(sum(y) AS BIGINT) AS y FROM (SELECT part, row, sum(val * x) AS y FROM nz_entries JOIN nz_x USING (part, col) GROUP BY part, row) GROUP BY row")


@query("sql_transposed", ENTRIES["dense_first"] + " SELECT col, CAST(sum(val * (1 + row % 5)) AS BIGINT) AS u FROM e GROUP BY col")
def _(spark, sf_dir):
    d = get_even(spark, sf_dir)
    d.placed.createOrReplaceTempView("nz_entries")
    d.zones.createOrReplaceTempView("nz_zones")
    short_v(spark, d.matrix.m).createOrReplaceTempView("nz_v")
    # the local product is read twice, so it is kept
    spark.sql("SELECT part, col, sum(val * v) AS u FROM nz_entries JOIN nz_v USING (row) GROUP BY part, col").persist().createOrReplaceTempView("nz_local")
    return spark.sql(
        "WITH shared AS (SELECT col, sum(u) AS u FROM nz_local JOIN nz_zones USING (col) GROUP BY col) "
        "SELECT col, CAST(u AS BIGINT) AS u FROM shared UNION ALL SELECT l.col, CAST(l.u AS BIGINT) FROM nz_local l LEFT ANTI JOIN nz_zones z ON l.col = z.col"
    )


# streams
_DAY = "CAST(epoch(date_trunc('day', ts)) AS BIGINT)"
query("st_tumbling", f"SELECT {_DAY} AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")(lambda s, d: _epoch(streaming.finish(streaming.tumbling(streaming.stream_events(s, d)))))
query("st_sliding", "WITH w AS (SELECT CAST(epoch(ts) AS BIGINT) // 43200 * 43200 AS b, event_type FROM events), x AS (SELECT b AS start, event_type FROM w UNION ALL SELECT b - 43200, event_type FROM w) SELECT start, event_type, count(*) AS n FROM x GROUP BY 1, 2")(
    lambda s, d: _epoch(streaming.finish(streaming.sliding(_whole_seconds(streaming.stream_events(s, d)))))
)
query("st_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 1 DAY THEN 0 ELSE 1 END AS new FROM events), c AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT CAST(epoch_us(min(ts)) AS BIGINT) AS start, user_id, count(*) AS n FROM c GROUP BY user_id, k")(
    lambda s, d: streaming.finish(streaming.sessions(streaming.stream_events(s, d))).select(F.unix_micros("start").alias("start"), "user_id", "n")
)
query("st_dedup", "SELECT count(*) AS n FROM (SELECT DISTINCT event_id FROM events)")(
    lambda s, d: streaming.finish_to_files(streaming.deduplicated(streaming.stream_events(s, d).select("event_id"), ["event_id"], None)).agg(F.count(F.lit(1)).alias("n"))
)


def _whole_seconds(events: DataFrame) -> DataFrame:
    """Event times to the nearest second, halves to the even one, as the SQL's cast of seconds to whole numbers has them."""
    return events.withColumn("ts", F.timestamp_seconds(F.rint(F.unix_micros("ts") / 1e6).cast("long")))


def _epoch(df: DataFrame) -> DataFrame:
    return df.select(F.unix_seconds("start").alias("start"), "event_type", "n")


def _stream_entries(s: SparkSession, d: str) -> DataFrame:
    return streaming.stream_events(s, d, table="lineitem").select(F.col("l_suppkey").alias("row"), F.col("l_partkey").alias("col"), F.col("l_quantity").alias("val"))


query("st_forward", "SELECT l_suppkey AS row, CAST(sum(l_quantity * (1 + l_partkey % 7)) AS BIGINT) AS y FROM lineitem GROUP BY 1")(lambda s, d: streaming.finish(streaming.running_forward(_stream_entries(s, d), long_x(s, get_matrix(s, d, "balanced").n))).select("row", F.col("y").cast("long")))
query("st_transposed", "SELECT l_partkey AS col, CAST(sum(l_quantity * (1 + l_suppkey % 5)) AS BIGINT) AS u FROM lineitem GROUP BY 1")(lambda s, d: streaming.finish(streaming.running_transposed(_stream_entries(s, d), short_v(s, get_matrix(s, d, "balanced").m))).select("col", F.col("u").cast("long")))
query("st_col_counts", "SELECT l_partkey AS col, count(*) AS nnz FROM lineitem GROUP BY 1")(lambda s, d: streaming.finish(streaming.running_counts(_stream_entries(s, d))))

# remaining tables as matrices
for _name, _table, _row, _text in (("w11_pages_tokens", "pages", "page_id", "html"), ("w11_conversations_tokens", "conversations", "conv_id", "text"), ("w11_benchmark_tokens", "benchmark", "item_id", "text")):
    query(_name, rf"SELECT {_row} AS row, CAST(count(*) AS BIGINT) AS total FROM (SELECT {_row}, unnest(regexp_split_to_array(lower({_text}), '[^\p{{L}}\p{{N}}]+')) AS t FROM {_table}) WHERE t <> '' GROUP BY 1")(
        lambda s, d, t=_table, r=_row, x=_text: matrix.term_counts(load_table(s, d, t), x, r).groupBy("row").agg(F.sum("val").cast("long").alias("total"))
    )
query("w11_nation_part", "SELECT c_nationkey AS row, CAST(sum(l_quantity * (1 + l_partkey % 7)) AS BIGINT) AS y FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1")(
    lambda s, d: kept(s, d, "nation part", lambda: _nation_part(s, d)).select(F.col("row").cast("int"), F.col("y").cast("long"))
)


def _nation_part(s: SparkSession, d: str) -> DataFrame:
    joined = load_table(s, d, "lineitem").join(load_table(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(load_table(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    m = get_matrix(s, d, "balanced")
    even = layout.partition_even(matrix.SparseMatrix(matrix.pair_matrix(joined, "c_nationkey", "l_partkey", "l_quantity"), 25, m.n), P)
    return products.forward(even, _x(even))
