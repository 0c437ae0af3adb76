"""Every query of the catalogue beside its SQL twin, on the smallest tables."""

import oracle
import pytest

from meterpack import queries

#: These take long and have no twin; the experiment tests and the bench run them.
HEAVY = {"scaling_batch_and_block", "kmeans_global", "table_cr_means", "recompress_first_stages", "stage_ablation"}


@pytest.fixture(scope="module")
def con(sf):
    return oracle.duck(sf)


@pytest.mark.parametrize("name", sorted(queries.SQL))
def test_twin(spark, sf, con, name):
    assert oracle.differences(queries.QUERIES[name](spark, sf), con, queries.SQL[name]) == ""


@pytest.mark.parametrize("name", sorted(set(queries.QUERIES) - set(queries.SQL) - HEAVY))
def test_rows(spark, sf, name):
    assert queries.QUERIES[name](spark, sf).count() > 0


def test_entry(spark):
    import __spark_entry__

    assert {"batch_id", "cluster_id", "cr_total", "cr_payload"} <= set(__spark_entry__.entry(spark).columns)
    assert set(queries.QUERIES) <= set(__spark_entry__.queries())
