"""Runs over edges in a task's file against the runs over arrays, and large graphs in few jobs."""

import numpy as np
import pytest

from ordwork.core.machine import shortest_paths
from ordwork.core.ordering import by_distance, chaotic, distance_bands, level_bands
from ordwork.core.tiers import tiered
from ordwork.graph.model import EdgeSet
from ordwork.plans import held, single
from ordwork.sources.graphs import GRAPHS
from ordwork.store import Store

COUNTED = "classes rounds processed accepted emitted remote".split()
CONFIGS = [
    *[(o, "lockstep", None) for o in (chaotic(), distance_bands(3), level_bands(2), by_distance())],
    *[(o, "drain", tiered(o, t)) for o in (chaotic(), distance_bands(7), level_bands(3), distance_bands(2.5)) for t in ("task", "host")],
    *[(chaotic(), "lockstep", tiered(chaotic(), t)) for t in ("task", "host")],
    *[(o, "drain", tiered(o, None)) for o in (chaotic(), distance_bands(7), level_bands(3))],
]


def stored(spark, frame):
    return EdgeSet(Store(spark, "test").save(frame, "edges"))


def in_process(graph, ordering, mode, tiers):
    """The run's loop here, where limits can be changed."""
    about = held.survey(graph)
    machine = shortest_paths(graph, 0, ordering)
    edges = held.Held(held.blocks(graph, about).toArrow().to_batches(), (0,), about)
    rounds = held.rounds(edges, ordering, "level" in machine.rule.attrs, mode, tiers)
    rounds.run((0,))
    known = np.flatnonzero(rounds.state != rounds.top)
    return edges, list(zip(edges.ids[known].tolist(), rounds.state[known].tolist(), strict=True)), rounds.measures


@pytest.fixture(scope="module")
def small(spark, sf):
    """The trade and lattice graphs, and what the runs over arrays give for each configuration."""
    out = {}
    for name in ("trade", "lattice"):
        graph = stored(spark, GRAPHS[name](spark, sf).edges)
        found = single.together(spark, graph.edges, [(k, shortest_paths(graph, 0, o), mode, tiers) for k, (o, mode, tiers) in enumerate(CONFIGS)])
        out[name] = graph, [(sorted((r["v"], r["dist"]) for r in found[k].state.collect()), found[k].measures) for k in range(len(CONFIGS))]
    return out


@pytest.mark.parametrize("limits", [{}, {"TOGETHER": 20, "IN_MEMORY": 0, "GAP": 3, "SPAN": 0}])
@pytest.mark.parametrize("name", ["trade", "lattice"])
def test_same_rounds_and_counts(small, name, limits, monkeypatch):
    for limit, value in limits.items():
        monkeypatch.setattr(held, limit, value)
    graph, wanted = small[name]
    for config, (state, measures) in zip(CONFIGS, wanted, strict=True):
        edges, got, counted = in_process(graph, *config)
        assert got == state
        assert [counted.row()[c] for c in COUNTED] == [measures.row()[c] for c in COUNTED]
        assert [x["processed"] for x in counted.trace] == [x["processed"] for x in measures.trace]
        assert (edges.arrays is None) == bool(limits)


def test_weights_and_ids_of_any_size(spark):
    far = 1 << 40
    rows = [(0, far, 0), (far, -5, 300), (0, -5, 70_000), (-5, 7, 1 << 33), (far, 7, 0)]
    graph = stored(spark, spark.createDataFrame(rows, "src long, dst long, w long"))
    want = [(-5, 300), (0, 0), (7, 0), (far, 0)]
    for ordering, mode, tiers in [x for x in CONFIGS if x[0].name in ("chaotic", "delta")]:
        assert in_process(graph, ordering, mode, tiers)[1] == want
    # items of weight 0 under levels and the distance order are left to the other plans
    config = [(level_bands(3), "drain", tiered(level_bands(3), "task"))]
    assert sorted((r["v"], r["dist"]) for r in single.runs(spark, graph, config)[0].state.collect()) == want


@pytest.mark.parametrize("rows", [[(0, 1, None), (1, 2, 3)], [(0, 1, -1)], []])
def test_edges_that_do_not_suit_are_not_held(spark, rows):
    assert held.prepared(spark, EdgeSet(spark.createDataFrame(rows, "src long, dst long, w long"))) is None


#: Configurations by finding, with their graph.
LARGE = {
    "F1": ("copurchase", chaotic(), "drain", tiered(chaotic(), "host")),
    "F2": ("copurchase", distance_bands(25), "drain", tiered(distance_bands(25), "task")),
    "F3": ("trade", chaotic(), "lockstep", tiered(chaotic(), "task")),
    "F4": ("trade", chaotic(), "drain", tiered(chaotic(), "task")),
    "F7": ("lattice", chaotic(), "drain", tiered(chaotic(), "task")),
    "F5": ("trade", distance_bands(7), "drain", tiered(distance_bands(7), "task")),
    "F6": ("trade", level_bands(3), "drain", tiered(level_bands(3), "task")),
    "F8": ("trade", level_bands(2), "drain", tiered(level_bands(2), None)),
}


@pytest.mark.parametrize("finding", sorted(LARGE))
def test_connected_graphs_beyond_the_arrays_run_in_few_jobs(spark, sf, finding, monkeypatch):
    """Graphs of which the seeds reach more edges than the arrays may hold took a job and a shuffle a round, with a group's edges in one table."""
    monkeypatch.setattr(single, "MOST_EDGES", 10)
    name, ordering, mode, tiers = LARGE[finding]
    graph = stored(spark, GRAPHS[name](spark, sf).edges)
    spark.sparkContext.setJobGroup(finding, finding)
    try:
        got = single.runs(spark, graph, [(ordering, mode, tiers)])[0]
        n = len(spark.sparkContext.statusTracker().getJobIdsForGroup(finding))
    finally:
        spark.sparkContext._jsc.clearJobGroup()
    assert n <= 10 and got.measures.accepted >= got.state.count() > 1
