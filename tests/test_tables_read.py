"""Queries that give constants of the method read a given table for them."""

import pytest

from taskmesh.plans.queries import QUERIES

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["kappa_by_task", "rounds_bounds", "sigma_cluster_rules"])
def test_reads_a_table(spark, name, monkeypatch):
    read = []
    monkeypatch.setattr("taskmesh.plans.queries.load", lambda s, d, table, columns=None: read.append(table) or s.read.parquet(f"{d}/{table}.parquet").select(*columns))
    assert QUERIES[name](spark, SF).count() and read
