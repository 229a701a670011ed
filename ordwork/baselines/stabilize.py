"""Self-stabilizing shortest paths: every vertex pulls from its in-neighbours until no rule applies, from any start.

Source rule: the source's value becomes 0. Relax rule: any other vertex takes the minimum over its in-neighbours of their value plus
the edge. A demon picks which vertices that violate their rule move in a step: all (synchronous), a share
(distributed) or one (central). Moves read one snapshot, so a step is atomic.

Weights must be positive. A value beyond `bound` counts as unreachable; without one, too small values on a cycle that the
source doesn't reach would count up for ever, so the default is (number of vertices) times the largest weight.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordwork.core.machine import Limits, RunMeasures, RunResult
from ordwork.graph.model import EdgeSet, GraphError
from ordwork.store import Store


@dataclass(frozen=True)
class Synchronous:
    """Every vertex that violates its rule moves."""

    def chosen(self, violating: DataFrame, step: int) -> DataFrame:
        return violating


@dataclass(frozen=True)
class Distributed:
    """A share of them, drawn anew by hash in each step; if the draw is empty, the smallest id."""

    fraction: float = 0.5
    seed: int = 0

    def chosen(self, violating: DataFrame, step: int) -> DataFrame:
        drawn = F.pmod(F.xxhash64("v", F.lit(self.seed), F.lit(step)), F.lit(1000)) < int(1000 * self.fraction)
        least = violating.agg(F.min("v").alias("least"))
        return violating.crossJoin(F.broadcast(least)).where(drawn | (F.col("v") == F.col("least"))).drop("least")


@dataclass(frozen=True)
class Central:
    """The one with the smallest id: a step for every move, for tiny graphs."""

    def chosen(self, violating: DataFrame, step: int) -> DataFrame:
        return violating.orderBy("v").limit(1)


def starts(graph: EdgeSet, kind: str) -> DataFrame:
    """(v, dist) to start from: `zero`, `huge`, `random` (by md5 of the id) or `infinite` (null)."""
    vertices = graph.vertices()
    value = {
        "zero": F.lit(0),
        "huge": F.lit(10**12),
        "random": F.conv(F.substring(F.md5(F.col("v").cast("string").cast("binary")), 1, 6), 16, 10).cast("long") % 1000,
        "infinite": F.lit(None),
    }[kind]
    return vertices.select("v", value.cast(graph.weight_type).alias("dist"))


def pulled(graph: EdgeSet, state: DataFrame, source: int, bound) -> DataFrame:
    """(v, dist, want): what the rules give each vertex on this snapshot; values beyond the bound are null."""
    offers = state.where("dist is not null").join(graph.edges, state.v == graph.edges.src).groupBy(F.col("dst").alias("u")).agg(F.min(F.col("dist") + F.col("w")).alias("offer"))
    want = F.when(F.col("v") == source, F.lit(0).cast(graph.weight_type)).otherwise(F.when(F.col("offer") <= F.lit(bound), F.col("offer")))
    return state.join(offers, state.v == offers.u, "left").select("v", "dist", want.alias("want"))


def violations(graph: EdgeSet, state: DataFrame, source: int) -> DataFrame:
    """One row: how many vertices aren't at their rule's value; state holds the reached vertices only."""
    every = graph.vertices().join(state, "v", "left").select("v", "dist")
    bad = pulled(graph, every, source, 2**62 if graph.weight_type.typeName() == "long" else float("inf")).where(~F.col("dist").eqNullSafe(F.col("want")))
    return bad.agg(F.count("*").alias("violations"))


def stabilize(spark: SparkSession, graph: EdgeSet, source: int, init: DataFrame | str = "infinite", demon=None, bound=None, limits: Limits | None = None) -> RunResult:
    demon, limits, store, m = demon or Synchronous(), limits or Limits(), Store(spark, "stabilize"), RunMeasures()
    facts = graph.edges.agg(F.min("w").alias("least"), F.max("w").alias("most")).first()
    if facts["least"] is not None and facts["least"] <= 0:
        raise GraphError("self-stabilization needs positive weights")
    graph = EdgeSet(store.save(graph.edges, "edges"))
    if bound is None:
        bound = graph.vertices().count() * (facts["most"] or 0)
    state = store.save((starts(graph, init) if isinstance(init, str) else init).select("v", F.col("dist").cast(graph.weight_type).alias("dist")), "state")
    while True:
        want = store.save(pulled(graph, state, source, bound), "want")
        violating = want.where(~F.col("dist").eqNullSafe(F.col("want")))
        count = violating.count()
        if not count:
            break
        m.rounds += 1
        moving = demon.chosen(violating, m.rounds).select("v", F.col("want").alias("new"), F.lit(True).alias("moved"))
        moved = want.join(moving, "v", "left").select("v", F.when(F.col("moved"), F.col("new")).otherwise(F.col("dist")).alias("dist"), F.coalesce("moved", F.lit(False)).alias("moved"))
        old = state
        moved = store.save(moved, "state")
        n = moved.where("moved").count()
        m.processed += count
        m.accepted += n
        m.trace.append({"class_key": "0", "round": m.rounds, "seconds": 0.0, "processed": count, "accepted": n, "emitted": 0})
        state = moved.select("v", "dist")
        del old
        limits.check(m)
    m.classes, m.wall_s = 1, time.time() - m.began
    return RunResult(state.where("dist is not null"), m)
