"""The worked example, and what holds for every split."""

import numpy as np
import pytest

from nzspan import plans
from nzspan.operators import baselines, generators, layout, products, vectors
from nzspan.operators.matrix import canonical, quarantine

SETUP = [
    # first_col, last_col, shares_prev, shares_next, closes_left, right_rank, left_rank, parts_before, parts_after
    (1, 2, 0, 1, 0, 0, 0, 0, 1),
    (2, 2, 1, 0, 1, 1, 0, 1, 2),
    (3, 4, 0, 1, 0, 1, 1, 0, 2),
    (4, 4, 1, 1, 0, 1, 1, 1, 1),
    (4, 6, 1, 1, 1, 2, 1, 2, 1),
    (6, 6, 1, 0, 1, 3, 2, 1, 0),
    (7, 8, 0, 0, 0, 3, 3, 0, 0),
]


def arrays(matrix):
    rows = matrix.entries.select("row", "col", "val").toPandas()
    return rows["row"].to_numpy(), rows["col"].to_numpy(), rows["val"].to_numpy()


def spread(d, x):
    spark = d.placed.sparkSession
    return vectors.spread(spark.createDataFrame(list(enumerate(map(float, x))), "col long, x double"), d)


def short(d, v):
    return d.placed.sparkSession.createDataFrame(list(enumerate(map(float, v))), "row long, v double")


def by_key(df, key, value, n):
    out = np.zeros(n)
    for r in df.collect():
        out[r[key]] = r[value]
    return out


def test_example(spark):
    d = layout.partition_even(generators.example(spark), 7)
    setup = [tuple(r)[1:] for r in layout.full_setup(d.parts).orderBy("part").collect()]
    assert setup == SETUP
    zones = [tuple(r)[:4] for r in d.zones.orderBy("zone").collect()]
    assert zones == [(0, 2, 0, 1), (1, 4, 2, 4), (2, 6, 4, 5)]
    assert spread(d, range(9)).count() == 12
    y = by_key(products.forward(d, spread(d, range(9))), "row", "y", 6)
    u = by_key(vectors.gather(products.transposed(d, short(d, range(6))), "u"), "col", "u", 9)
    assert y[1:].tolist() == [24, 15, 12, 17, 20]
    assert u[1:].tolist() == [6, 13, 5, 15, 2, 11, 5, 5]


@pytest.mark.parametrize("kind", ["dense_column", "singles", "full", "gaps"])
@pytest.mark.parametrize("n_parts", [3, 1000])
def test_any_shape(spark, kind, n_parts):
    m, n = 6, 17
    a = generators.shape(spark, kind, m, n)
    d = layout.partition_even(a, n_parts)
    sizes = [r["nnz"] for r in d.parts.collect()]
    assert sum(sizes) == a.nnz and max(sizes) - min(sizes) <= 1 and len(sizes) == min(n_parts, a.nnz)
    zones = d.zones.collect()
    assert len(zones) <= d.n_parts - 1 and sum(z["size"] for z in zones) <= 2 * max(d.n_parts - 1, 1)
    assert all(r["clashes"] == 0 for r in layout.schedule_clashes(d.zones).collect())
    key = lambda df: sorted(map(tuple, df.collect()))
    assert key(d.zones) == key(layout.zones_by_grouping(d.placed)) == key(layout.setup_zones(d.placed, d.parts, "blocks"))
    rows, cols, vals = arrays(a)
    rng = np.random.default_rng(1)
    x, v = rng.integers(-9, 9, n).astype(float), rng.integers(-9, 9, m).astype(float)
    y = baselines.forward_serial(rows, cols, vals, x, m)
    u = baselines.transposed_serial(rows, cols, vals, v, n)
    assert by_key(products.forward(d, spread(d, x)), "row", "y", m).tolist() == y.tolist()
    result = products.transposed(d, short(d, v), "even_odd")
    assert by_key(vectors.gather(result, "u"), "col", "u", n).tolist() == u.tolist()
    assert vectors.copies_agree(result, "u")
    # v · (A x) = (v A) · x, coefficients counted at their homes only
    assert vectors.dot(result.withColumnRenamed("u", "x"), spread(d, x)).first()["dot"] == float(v @ y)


def test_empty_matrix(spark):
    d = layout.partition_even(generators.shape(spark, "empty", 3, 4), 5)
    assert d.parts.count() == 0 and d.zones.count() == 0
    assert products.forward(d, spread(d, range(4))).count() == 0


def test_borders_agree_with_ranks(spark):
    a = generators.random_matrix(spark, 40, 60)
    for p in (2, 7, 64):
        ranked = layout.even_parts(a, p).select("row", "col", "part")
        d = layout.partition_even(a, p, by="borders")
        assert sorted(map(tuple, ranked.collect())) == sorted(map(tuple, d.placed.select("row", "col", "part").collect()))


def test_placement_costs_no_second_shuffle(spark):
    d = layout.partition_even(generators.random_matrix(spark, 40, 60), 8)
    plan = products.transposed_local(d, short(d, range(40)))._jdf.queryExecution().executedPlan().toString()
    above = plan.split("InMemoryTableScan")[0]
    assert "Exchange hashpartitioning" not in above and "BroadcastHashJoin" in above


def test_long_vectors_meet_entries_in_place(spark):
    d = layout.partition_even(generators.random_matrix(spark, 40, 60), 8)
    key = "spark.sql.autoBroadcastJoinThreshold"
    before = spark.conf.get(key)
    spark.conf.set(key, "-1")
    try:
        x = spread(d, range(60)).persist()
        x.count()
        other = vectors.scale(2.0, x).persist()
        other.count()
        for df in (products.forward_local(d, x), vectors.axpy(3.0, x, other), vectors.dot(x, other)):
            plan = df._jdf.queryExecution().executedPlan().toString().split("InMemoryRelation")[0]
            assert "SortMergeJoin" in plan and "Exchange hashpartitioning" not in plan and "passthrough" not in plan
        # only the vector is shuffled to be laid out
        plan = spread(d, range(60))._jdf.queryExecution().executedPlan().toString().split("InMemoryRelation")[0]
        assert plan.count("Exchange shufflepartitionidpassthrough") == 1 and "Exchange hashpartitioning" not in plan
    finally:
        spark.conf.set(key, before)
        for df in (x, other):
            df.unpersist()


def test_pairs_leave_nothing_behind(spark):
    d = layout.partition_even(generators.random_matrix(spark, 12, 30), 3)
    x, v = spread(d, np.ones(30)), short(d, np.ones(12))
    held = lambda: spark.sparkContext._jsc.sc().getPersistentRDDs().size()
    before = held()
    y, u, seconds = products.product_pairs(d, x, v, 5)
    assert held() == before and len(seconds) == 5
    rows, cols, vals = arrays(d.matrix)
    want_x, want_v = np.ones(30), None
    for _ in range(5):
        want = baselines.forward_serial(rows, cols, vals, want_x, 12)
        want_x = baselines.transposed_serial(rows, cols, vals, want / want.max(), 30)
    assert np.allclose(by_key(y, "row", "y", 12), want) and np.allclose(by_key(vectors.gather(u, "u"), "col", "u", 30), want_x)


def test_gram(spark):
    a = generators.random_matrix(spark, 12, 30)
    rows, cols, vals = arrays(a)
    full = np.zeros((12, 30))
    full[rows, cols] = vals
    from nzspan.operators.matrix import gram

    for block in (1024, 5):
        got = np.zeros((12, 12))
        for r in gram(a.entries, block).collect():
            got[r["row"], r["other"]] = r["val"]
        assert np.allclose(got, full @ full.T)


def test_operator_laws():
    rng = np.random.default_rng(2)
    for _ in range(200):
        keys = sorted(rng.integers(0, 3, 3).tolist())  # equal keys are neighbours
        a, b, c = zip(rng.integers(0, 9, 3).tolist(), keys, strict=True)
        assert layout.seg_add(layout.seg_add(a, b), c) == layout.seg_add(a, layout.seg_add(b, c))
    assert layout.seg_add((1, 0), (1, 1)) != layout.seg_add((1, 1), (1, 0))


def test_canonical(spark):
    nan = float("nan")
    df = spark.createDataFrame([(0, 0, 1.0), (0, 0, -1.0), (0, 1, 2.0), (None, 1, 3.0), (1, 1, None), (2, 2, nan)], "row long, col long, val double")
    kept = {(r["row"], r["col"]) for r in canonical(df).collect()}
    assert kept == {(0, 1), (2, 2)} and quarantine(df).count() == 2


def test_generators(spark):
    for method in ("arithmetic", "drawn"):
        a = generators.random_matrix(spark, 50, 80, method=method)
        lo, hi = generators.bounds(50, 0.274, 12, 12)
        counts = [r["count"] for r in a.entries.groupBy("col").count().collect()]
        assert min(counts) >= lo and max(counts) <= hi
        assert a.entries.distinct().count() == a.nnz and a.entries.select("row").distinct().count() == 50


def test_spans_and_measures(spark):
    a = generators.random_matrix(spark, 50, 80)
    profile = plans.column_profile(a)
    for p in (1, 4, 32):
        spans = baselines.partition_columns(a, p)
        measured = plans.imbalance(spans).first()["delta_pct"]
        swept = plans.sweep_imbalance(profile, a.n, (p,)).first()["delta_pct"]
        assert measured == swept
        even = layout.partition_even(a, p)
        assert plans.sweep_zones(profile, (p,)).first()["zones"] == even.zones.count()
        assert plans.imbalance(even).first()["delta_pct"] <= 100 * p / a.nnz + 0.01
    assert plans.imbalance(baselines.partition_columns_balanced(a, 8)).first()["delta_pct"] < plans.imbalance(baselines.partition_columns(a, 8)).first()["delta_pct"] + 5
    assert plans.choose(plans.Stats(10, 1000, 5000, 10), 8, 1.0).split == "columns"
    assert plans.choose(plans.Stats(10, 1000, 5000, 10), 8, 900.0).split == "even"


def test_gram_sends_entries_to_blocks_that_share_a_column(spark):
    """A block of rows whose columns no other block has: each entry goes to one pair, whatever the number of blocks."""
    import collections

    from nzspan.operators.matrix import gram

    rows = [(r, r // 4 * 10 + c, float(1 + (r + c) % 3)) for r in range(64) for c in range(6)]
    want = collections.Counter()
    for r, c, v in rows:
        for s, k, w in rows:
            if c == k:
                want[r, s] += v * w
    result = gram(spark.createDataFrame(rows, "row long, col long, val double"), 4)
    assert {(r["row"], r["other"]): r["val"] for r in result.collect()} == dict(want)
    plan = result._jdf.queryExecution().executedPlan().toString()
    assert "collect_set" in plan and "sequence" not in plan
