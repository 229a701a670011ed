"""Runs inside one task against the distributed plans and the recorded counts."""

import duckdb
import pytest

import __spark_entry__ as entry
from ordwork.core.machine import run, shortest_paths
from ordwork.core.ordering import by_distance, chaotic, distance_bands, level_bands
from ordwork.core.tiers import TierTree, tiered, tiered_tree
from ordwork.graph.model import EdgeSet
from ordwork.plans import single
from ordwork.sources.graphs import GRAPHS
from ordwork.store import Store

COUNTED = "classes rounds processed accepted emitted remote".split()
CONFIGS = [
    *[(o, "lockstep", None) for o in (chaotic(), distance_bands(3), level_bands(2), by_distance())],
    *[(o, "drain", tiered(o, t)) for o, t in ((chaotic(), "task"), (distance_bands(7), "socket"), (level_bands(3), "host"), (distance_bands(2.5), "host"))],
    (chaotic(), "lockstep", tiered(chaotic(), "task")),
    (chaotic(), "lockstep", tiered_tree(chaotic(), TierTree(order={"host": distance_bands(5), "task": by_distance()}))),
]


def states(result):
    return sorted((r["v"], r["dist"]) for r in result.state.collect())


def jobs(spark, name, of):
    """What `of` returns, and how many Spark jobs it started."""
    spark.sparkContext.setJobGroup(name, name)
    try:
        return of(), len(spark.sparkContext.statusTracker().getJobIdsForGroup(name))
    finally:
        spark.sparkContext._jsc.clearJobGroup()


def stored(spark, frame):
    return EdgeSet(Store(spark, "test").save(frame, "edges"))


@pytest.mark.parametrize("k", range(len(CONFIGS)))
def test_same_rounds_and_counts_as_distributed(spark, sf, k, monkeypatch):
    ordering, mode, tiers = CONFIGS[k]
    graph = stored(spark, GRAPHS["trade"](spark, sf).edges)
    monkeypatch.setattr(single, "TOGETHER", 50)
    monkeypatch.setattr(single, "FEW", 20)
    got = single.together(spark, graph.edges, [(0, shortest_paths(graph, 0, ordering), mode, tiers)])[0]
    want = run(spark, shortest_paths(graph, 0, ordering), mode, tiers)
    assert states(got) == states(want)
    assert [got.measures.row()[c] for c in COUNTED] == [want.measures.row()[c] for c in COUNTED]
    assert [x["processed"] for x in got.measures.trace] == [x["processed"] for x in want.measures.trace]


def test_only_what_the_seeds_reach_is_gathered(spark, sf, monkeypatch):
    """Copies with shifted keys are not reached; where too much is, the distributed plans run."""
    one = GRAPHS["trade"](spark, sf).edges
    both = stored(spark, one.unionByName(one.selectExpr("src + 1000000 AS src", "dst + 1000000 AS dst", "w")))
    n = one.count()
    config = [(chaotic(), "drain", tiered(chaotic(), "task"))]
    want = states(run(spark, shortest_paths(both, 0, chaotic())))
    monkeypatch.setattr(single, "MOST_EDGES", n)
    assert single.reached(spark, both, (0,)).count() == n
    assert states(single.runs(spark, both, config)[0]) == want
    monkeypatch.setattr(single, "MOST_EDGES", n - 1)
    assert single.reached(spark, both, (0,)) is None
    assert states(single.runs(spark, both, config)[0]) == want


def test_edges_that_do_not_fit_are_left_to_the_distributed_plans(spark):
    rows = [(0, 1, 2.5), (1, 2, float("inf"))]
    graph = stored(spark, spark.createDataFrame(rows, "src long, dst long, w double"))
    assert single.together(spark, graph.edges, [(0, shortest_paths(graph, 0, chaotic()), "lockstep", None)]) == {}
    assert states(single.runs(spark, graph, [(chaotic(), "lockstep", None)])[0])[:2] == [(0, 0.0), (1, 2.5)]


def test_a_source_without_edges(spark):
    graph = stored(spark, spark.createDataFrame([(5, 6, 1)], "src long, dst long, w long"))
    assert states(single.runs(spark, graph, [(chaotic(), "drain", tiered(chaotic(), "host"))])[0]) == [(0, 0)]


@pytest.mark.parametrize("name", ["root_work_trade", "root_work_rmat1", "tier_work_delta7_rmat1", "tier_work_delta7_trade", "tier_work_kla3_trade", "tier_work_chaotic_trade", "tier_work_kla1_trade", "tier_work_kla1_rmat1", "tier_work_kla3_rmat1", "tier_work_chaotic_rmat1"])
def test_recorded_work_in_few_jobs(spark, name):
    """A job a round made these fail by time."""
    frame, n = jobs(spark, name, lambda: entry.queries()[name](spark, "/root/testdata/sf0.01"))
    want = duckdb.connect().execute(entry.oracle_sql()[name]).fetchall()
    assert sorted(tuple(r) for r in frame.collect()) == sorted(want)
    assert n <= 20


def test_disagreements_count_as_both_ways_of_except_all(spark):
    from ordwork.workloads.queries import disagreements

    frame = lambda rows: spark.createDataFrame(rows, "v long, dist long")
    want = frame([(0, 0), (1, 4), (2, 5)])
    found = {"same": frame([(2, 5), (1, 4), (0, 0)]), "other": frame([(0, 0), (1, 3), (2, 5), (2, 5)]), "none": frame([])}
    both = {name: got.exceptAll(want).union(want.exceptAll(got)).count() for name, got in found.items()}
    assert {r["config"]: r["differences"] for r in disagreements(want, found).collect()} == both == {"same": 0, "other": 3, "none": 3}


def test_runs_over_one_graph_are_tasks_of_their_own(spark, sf):
    """Spark 4.1 puts single partitions of a union into one task, where the runs would follow one another."""
    graph = stored(spark, GRAPHS["trade"](spark, sf).edges)
    found = single.together(spark, graph.edges, [(k, shortest_paths(graph, 0, chaotic()), "lockstep", None) for k in range(3)])
    files = {f for r in found.values() for f in r.state.inputFiles()}
    assert len(files) == 3 and len({tuple(states(r)) for r in found.values()}) == 1
