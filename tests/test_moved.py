"""Queries that made their data up read a given table now: they fail without it, and follow it where it is another one."""

import duckdb
import pytest

from overlapsolve import oracles
from overlapsolve import queries as q
from tests.compare import differences

MOVED = ["box_owner", "coarse_geometric_weights", "contraction_report", "detection_report", "geometric_members", "grid2d_entries", "imbalanced_owner", "overlap_member", "owned_mask", "partition_of_unity", "partition_stats", "comm_bench_report"]


@pytest.fixture(scope="module")
def few(tmp_path_factory):
    """A lattice with holes, and the events of some users."""
    at = tmp_path_factory.mktemp("few")
    for table, kept in (("lineitem", "l_orderkey % 5 > 0"), ("events", "user_id % 3 < 2")):
        duckdb.execute(f"COPY (SELECT * FROM '/root/testdata/sf0.001/{table}.parquet' WHERE {kept}) TO '{at}/{table}.parquet'")
    return str(at)


@pytest.mark.parametrize("name", MOVED)
def test_query_reads_its_table(spark, few, tmp_path, name):
    assert differences(spark, q.QUERIES[name], oracles.ORACLES[name], few) == []
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        q.QUERIES[name](spark, str(tmp_path)).count()
