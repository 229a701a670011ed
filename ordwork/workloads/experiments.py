"""The experiments as plans over graphs, orderings and tiers; each yields rows of measures.

Shapes to expect: local orders cut processed items; more classes cost more rounds; the unordered root without a
local order does the most redundant work and gains most from one; larger bands mean fewer classes and more work.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession

from ordwork import measure
from ordwork.core.machine import LimitReached, Limits, run, shortest_paths
from ordwork.core.ordering import Ordering, by_distance, chaotic, distance_bands, level_bands
from ordwork.core.tiers import TierTree, tiered
from ordwork.graph.model import EdgeSet
from ordwork.sources.graphs import GRAPHS, RMAT, rmat
from ordwork.store import Store

TIERS = (None, "task", "socket", "host")
#: Band widths of each graph that stands for a real one: of the distance and of the level.
REAL = {"trade": (3, 1), "handoff": (3, 1), "lattice": (25, 10), "copurchase": (10, 5)}


def stored(spark: SparkSession, sf_dir: str, name: str) -> EdgeSet:
    """Matrix graphs grow with the rows here; as queries they have the scale of their SQL."""
    graph = rmat(spark, sf_dir, name, None) if name in RMAT else GRAPHS[name](spark, sf_dir)
    return EdgeSet(Store(spark, f"exp-{name}").save(graph.edges, "edges"))


def configuration(spark: SparkSession, graph: EdgeSet, name: str, ordering: Ordering, tier: str | None, repeat: int = 0, tree: TierTree | None = None, limits: Limits | None = None, mode: str = "drain") -> dict:
    machine, config = shortest_paths(graph, 0, ordering), tiered(ordering, tier, tree)
    try:
        return measure.row(run(spark, machine, mode, config, limits), machine, config, mode, name, repeat)
    except LimitReached as stop:
        return {"graph": name, "root": ordering.name, "param": ordering.parameter, "tier": config.label, "mode": mode, "stopped": str(stop)} | stop.measures


def band_widths(spark, sf_dir, quick=True) -> Iterator[dict]:
    """Three widths of distance bands by four tiers on both matrix graphs."""
    for g in ("rmat1", "rmat2"):
        graph = stored(spark, sf_dir, g)
        for delta in (7,) if quick else (3, 5, 7):
            for tier in TIERS:
                yield {"experiment": "band_widths"} | configuration(spark, graph, g, distance_bands(delta), tier)


def level_widths(spark, sf_dir, quick=True) -> Iterator[dict]:
    for g in ("rmat1", "rmat2"):
        graph = stored(spark, sf_dir, g)
        for k in (1, 3) if quick else (1, 2, 3):
            for tier in TIERS:
                yield {"experiment": "level_widths"} | configuration(spark, graph, g, level_bands(k), tier)


def unordered(spark, sf_dir, quick=True) -> Iterator[dict]:
    """No root order: work may explode without a local one, so it has a limit."""
    for g in ("rmat1", "rmat2"):
        graph = stored(spark, sf_dir, g)
        for tier in TIERS:
            yield {"experiment": "unordered"} | configuration(spark, graph, g, chaotic(), tier, limits=Limits(max_items=50_000_000))


def weak_scaling(spark, sf_dir, quick=True) -> Iterator[dict]:
    """Work that grows with the number of tasks: a share of the edges by hash for each task count."""
    from pyspark.sql import functions as F

    full, times = stored(spark, sf_dir, "rmat1"), {}
    for tasks in (1, 2, 4, 8):
        part = EdgeSet(Store(spark, "weak").save(full.edges.where(F.pmod(F.xxhash64("src", "dst"), F.lit(8)) < tasks), "edges"))
        row = configuration(spark, part, f"rmat1/{tasks}", chaotic(), "task", tree=TierTree(1, 1, tasks))
        times[tasks] = row["wall_s"]
        yield {"experiment": "weak_scaling", "tasks": tasks, "efficiency": measure.weak_efficiency(times)[tasks]} | row


def real_graphs(spark, sf_dir, quick=True, repeats: int = 3) -> Iterator[dict]:
    """Twelve configurations on four graphs: mean and standard deviation of the seconds."""
    for g, (delta, k) in REAL.items():
        if quick and g not in ("trade", "copurchase"):
            continue
        graph, rows = stored(spark, sf_dir, g), []
        for ordering in (distance_bands(delta), level_bands(k), chaotic()):
            for tier in TIERS:
                rows += [configuration(spark, graph, g, ordering, tier, r) for r in range(1 if quick else repeats)]
        yield from ({"experiment": "real_graphs"} | x for x in measure.summary(rows))


def one_or_many_tasks(spark, sf_dir, quick=True) -> Iterator[dict]:
    graph = stored(spark, sf_dir, "rmat1")
    for tree in (TierTree(1, 1, 1), TierTree()):
        for tier in (None, "task"):
            yield {"experiment": "one_or_many_tasks", "tasks": tree.tasks} | configuration(spark, graph, "rmat1", distance_bands(7 if not quick else 25), tier, tree=tree)


def ablation(spark, sf_dir, quick=True) -> Iterator[dict]:
    """Orders on and off, in both modes: synchronisation against work."""
    graph = stored(spark, sf_dir, "trade")
    for mode in ("lockstep", "drain"):
        for ordering in (chaotic(), level_bands(1), distance_bands(7), *(() if quick else (by_distance(),))):
            yield {"experiment": "ablation"} | configuration(spark, graph, "trade", ordering, None, mode=mode)


PLANS = [band_widths, level_widths, unordered, weak_scaling, real_graphs, one_or_many_tasks, ablation]


def everything(spark: SparkSession, sf_dir: str, quick: bool = True) -> Iterator[dict]:
    for plan in PLANS:
        yield from plan(spark, sf_dir, quick)
