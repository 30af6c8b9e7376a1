"""Plans and results that only matter above the test tables' size."""

import pytest

from taskmap import objective as ob
from taskmap.config import Config
from taskmap.plans.iterate import barrier
from taskmap.plans.multisection import multisection
from taskmap.queries import QUERIES
from taskmap.sources.generators import grid
from taskmap.topology import Topology

#: Findings of round 2: these built tables with a row for each vertex on the driver.
NOT_BROADCAST = ["apply_moves", "best_share", "cached_proposals", "connectivity_delta", "connectivity_rebuild", "contract_graph", "locked_second_round", "moved_except", "performance_profile", "seed_average"]


@pytest.mark.parametrize("name", NOT_BROADCAST)
def test_vertex_tables_are_not_broadcast(spark, tiny, name):
    plan = QUERIES[name](spark, tiny)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Broadcast" not in plan


def test_cached_proposals_makes_the_graph_once(spark, tiny):
    plan = QUERIES["cached_proposals"](spark, tiny)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("explode(") == plan.count("explode(array(struct(pe, pe_old") > 0  # of moves; the graph's are in what is stored


def test_a_recursion_has_no_limit_of_rows_or_levels(spark, tiny):
    names = ("spark.sql.cteRecursionLevelLimit", "spark.sql.cteRecursionRowLimit")
    before = [spark.conf.get(n) for n in names]
    want = sorted(map(tuple, QUERIES["components"](spark, tiny).collect()))
    try:
        for n in names:
            spark.conf.set(n, "3")
        assert sorted(map(tuple, QUERIES["components_recursive"](spark, tiny).collect())) == want
        assert [spark.conf.get(n) for n in names] == ["3", "3"]
    finally:
        for n, value in zip(names, before):
            spark.conf.set(n, value)


#: Findings of round 2: these read no table.
READS = {"exact_tiny": "lineitem", "one_to_one_exact": "lineitem", "pe_coordinates": "lineitem", "pe_distance": "lineitem", "pe_matrix": "lineitem", "phase_shares": "events", "phase_table": "events", "topology_pes": "lineitem"}


@pytest.mark.parametrize("name", READS)
def test_reads_a_given_table(spark, tiny, name):
    assert any(f.endswith(f"/{READS[name]}.parquet") for f in QUERIES[name](spark, tiny).inputFiles())
