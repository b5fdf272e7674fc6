"""Every registered query of the library against its SQL, on the smallest tables."""

import pytest

from nzspan import surroundings, workloads  # noqa: F401

DATA = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", sorted(workloads.SQL))
def test_same_as_sql(name, same_rows):
    same_rows(workloads.QUERIES[name], workloads.SQL[name])


@pytest.mark.parametrize("name", sorted(set(workloads.QUERIES) - set(workloads.SQL) - {"spectral_ridge", "projected_spectral"}))
def test_runs(name, spark):
    assert workloads.QUERIES[name](spark, DATA).count() > 0


@pytest.mark.parametrize("name", ["al_outer", "ex_forward", "ex_layout", "ex_parts", "ex_setup", "ex_transposed", "ex_zones"])
def test_reads_a_given_table(name, spark, monkeypatch):
    seen = []
    for module in (surroundings, workloads):
        load = module.load_table
        monkeypatch.setattr(module, "load_table", lambda s, d, table, *columns, load=load: seen.append(table) or load(s, d, table, *columns))
    for _ in range(2):  # also when it has run before
        seen.clear()
        assert workloads.QUERIES[name](spark, DATA).count() > 0 and seen
