"""The driver contract: queries against their DuckDB twins on the smallest tables."""

import os
from collections import Counter

import duckdb
import pytest

from deltamatch import oracles, workloads

FAST = ["copurchase_stream_90_10", "mixed_stream_70_30", "nlf_candidates", "ball_triangles", "hub_excluded_components", "spectral_moments", "bound_rules", "delta_diamond", "level_intermediates_nlf", "gate_counts_fire", "deletion_gate", "trade_rings", "event_sessions", "zipf_label_counts", "dominance_candidates", "list_driven_matches", "list_driven_scans", "reverse_compaction", "update_triggers", "intermediates_per_update", "homomorphic_matches", "distinct_subgraphs", "periodic_checks"]


@pytest.fixture(scope="module")
def twin(sf):
    con = duckdb.connect()
    for name in os.listdir(sf):
        con.execute(f"CREATE VIEW {name.split('.')[0]} AS SELECT * FROM '{sf}/{name}'")
    return con


@pytest.mark.parametrize("name", FAST)
def test_query_equals_its_twin(spark, sf, twin, name):
    df = workloads.QUERIES[name](spark, sf)
    names = sorted(df.columns)
    got = Counter(tuple(r[c] for c in names) for r in df.collect())
    asked = twin.execute(oracles.ORACLES[name])
    columns = [c[0] for c in asked.description]
    assert sorted(columns) == names
    assert got == Counter(tuple(r[columns.index(c)] for c in names) for r in asked.fetchall())


@pytest.mark.parametrize("name", ["decoy_workload", "decoy_control", "random_graph_utility", "small_world_utility"])
def test_experiments_need_the_given_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="lineitem"):
        workloads.QUERIES[name](spark, str(tmp_path))


@pytest.mark.parametrize("name", ["decoy_workload", "decoy_control"])
def test_decoys_of_orders_equal_their_twin(spark, sf, twin, name):
    test_query_equals_its_twin(spark, sf, twin, name)


def test_every_twin_has_a_query_and_entry_runs(spark):
    import __spark_entry__

    assert set(oracles.ORACLES) <= set(workloads.QUERIES)
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
    assert __spark_entry__.entry(spark).count() > 0
