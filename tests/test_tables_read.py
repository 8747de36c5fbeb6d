"""Bounds, churn and networks follow the given tables."""

import pytest

from fadegossip import catalog

NETWORKS = ("graph_complete", "graph_hashed", "graph_preferential", "graph_ring")
OTHERS = ("alive_at_end", "bounds", "churn_report", "counters_per_site", "deviation_bound", "empty_grid", "fail_probabilities", "fail_stop_timeline")


@pytest.mark.parametrize("name", OTHERS)
def test_reads_a_table(spark, small, name):
    assert catalog.queries()[name](spark, small).inputFiles()


def test_networks_are_of_the_sites_reached(spark, small, tmp_path):
    spark.read.parquet(f"{small}/lineitem.parquet").where("l_orderkey % 64 < 10").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = {name: catalog.queries()[name](spark, str(tmp_path)).first() for name in NETWORKS}
    assert (got["graph_complete"].sites, got["graph_complete"].edges) == (10, 45)
    assert (got["graph_ring"].edges, got["graph_ring"].min_degree) == (9, 1)
    assert all(r.sites <= 10 and r.one_way == 0 for r in got.values())
