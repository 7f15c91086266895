import pytest

from vpcoreset import queries as registry
from vpcoreset.plans import methods

from .oracle import same


@pytest.fixture(autouse=True)
def two_repeats(monkeypatch):
    """The grids with all sizes and methods, but two repeats."""
    monkeypatch.setattr(methods, "REPEATS", 2)


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_twin(spark, sf, name):
    same(spark, sf, registry.QUERIES[name], registry.ORACLES[name])


@pytest.mark.parametrize("name", sorted(set(registry.QUERIES) - set(registry.ORACLES)))
def test_runs(spark, sf, name):
    assert registry.QUERIES[name](spark, sf).count() >= 1


#: Queries that once made up their data: each fails where the tables are missing.
READS = [
    "op_report_sink",
    "op_map_coefs",
    "op_lateral_replicates",
    "op_endpoint_source",
    "hard_kmeans_hidden_point",
    "hard_regression_hidden_row",
    "comm_published_reconstruction",
    "ledger_server_view",
    "ledger_rollup",
    "ledger_table_policy",
    "ledger_strict",
]


@pytest.mark.parametrize("name", READS)
def test_reads_a_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        registry.QUERIES[name](spark, str(tmp_path)).collect()


def test_every_twin_has_a_query():
    assert set(registry.ORACLES) <= set(registry.QUERIES)


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())
