import numpy as np
import pytest

from nzspan.operators import generators, layout, products, solvers
from nzspan.operators.vectors import gather


@pytest.fixture(scope="module")
def problem(spark):
    a = generators.random_matrix(spark, 12, 40)
    rows = a.entries.toPandas()
    full = np.zeros((a.m, a.n))
    full[rows["row"], rows["col"]] = rows["val"]
    return layout.partition_even(a, 4), full, np.random.default_rng(3).normal(size=a.m)


def solution(x, n):
    out = np.zeros(n)
    for r in gather(x).collect():
        out[r["col"]] = r["x"]
    return out


def test_conjugate_gradient(problem):
    d, a, b = problem
    trace = solvers.conjugate_gradient(d, b, ridge=5.0, tol=1e-10, max_iter=15)
    exact = a.T @ np.linalg.solve(a @ a.T + 5.0 * np.eye(len(b)), b)
    assert np.allclose(solution(trace.x, a.shape[1]), exact, atol=1e-6)
    assert trace.residuals[-1] < 1e-8


def test_spectral_gradient(problem):
    d, a, b = problem
    trace = solvers.spectral_gradient(d, b, ridge=50.0, max_iter=12)
    exact = a.T @ np.linalg.solve(a @ a.T + 50.0 * np.eye(len(b)), b)
    least = 0.5 * np.sum((a @ exact - b) ** 2) + 25.0 * exact @ exact
    assert trace.values[-1] <= least * 1.05 + 1e-9


def test_box(problem):
    d, a, b = problem
    trace = solvers.projected_spectral_gradient(d, b, -0.01, 0.01, ridge=1.0, max_iter=4)
    x = solution(trace.x, a.shape[1])
    assert np.abs(x).max() <= 0.01 + 1e-12 and trace.values[-1] <= 0.5 * b @ b


def test_singular_value_and_fixed_steps(problem):
    d, a, b = problem
    top = solvers.largest_singular_value(d, 8).values[-1]
    assert abs(top - np.linalg.norm(a, 2)) / top < 0.01
    trace = solvers.gradient_descent(d, b, ridge=1.0, max_iter=4)
    assert all(x >= y for x, y in zip(trace.values, trace.values[1:], strict=False))


@pytest.mark.parametrize(("parts", "most"), [(1, 1000), (4, 1000), (4, 3), (30, 1)])
def test_both_products_at_once(spark, parts, most):
    a = generators.random_matrix(spark, 12, 40)
    rows = a.entries.toPandas()
    full = np.zeros((a.m, a.n))
    full[rows["row"], rows["col"]] = rows["val"]
    d = layout.partition_even(a, parts)
    packed = products.pack_columns(d, most)
    assert packed.where("zone >= 0").select("zone").distinct().count() == d.zones.count()
    w = np.random.default_rng(5).normal(size=a.m)
    for few in (0, products.FEW):
        assert np.allclose(products.normal(d, packed, w, few), full @ (full.T @ w))


def test_a_step_takes_two_jobs_at_most(problem, spark):
    d, a, b = problem
    pair = solvers.Pair(d)
    assert np.allclose(pair.normal(b), a @ (a.T @ b))
    spark.sparkContext.setJobGroup("step", "one step")
    try:
        pair.normal(b)
        jobs = spark.sparkContext.statusTracker().getJobIdsForGroup("step")
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert 1 <= len(jobs) <= 2
