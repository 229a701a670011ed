"""The ordered-work machine: graph, rule, ordering and seeds; how it runs is a plan of ordwork.plans."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from ordwork.core.ordering import Ordering
from ordwork.core.rule import ItemSchema, Rule, leveled_sssp_rule, sssp_rule
from ordwork.core.tiers import Tiered
from ordwork.graph.model import EdgeSet


class LimitReached(RuntimeError):
    """A run went beyond its limits; measures holds what it had done."""

    def __init__(self, what: str, measures: dict):
        super().__init__(what)
        self.measures = measures


@dataclass(frozen=True)
class Limits:
    max_rounds: int = 100_000
    max_items: int | None = None
    max_seconds: float | None = None
    check_forward: bool = False

    def check(self, run: RunMeasures) -> None:
        for what, now, most in (("rounds", run.rounds, self.max_rounds), ("items", run.processed, self.max_items), ("seconds", time.time() - run.began, self.max_seconds)):
            if most is not None and now > most:
                raise LimitReached(f"more than {most} {what}", run.row())


@dataclass
class RunMeasures:
    """What a run did, and a trace with a row a round."""

    began: float = field(default_factory=time.time)
    classes: int = 0
    rounds: int = 0
    processed: int = 0
    accepted: int = 0
    emitted: int = 0
    remote: int = 0
    max_queue: int = 0
    backward: int = 0
    wall_s: float = 0.0
    trace: list[dict] = field(default_factory=list)

    def row(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k not in ("began", "trace")}


@dataclass(frozen=True)
class Machine:
    """seeds: frame of (v, dist), or a list of vertices that start at 0."""

    graph: EdgeSet
    rule: Rule
    ordering: Ordering
    seeds: DataFrame | tuple[int, ...]

    def __post_init__(self):
        missing = set(self.ordering.attrs) - set(self.rule.attrs)
        if missing:
            raise ValueError(f"the ordering needs {sorted(missing)}, which the rule does not populate")

    def schema(self) -> ItemSchema:
        return ItemSchema(self.graph.weight_type, self.rule.attrs)

    def seed_items(self, spark: SparkSession) -> DataFrame:
        from pyspark.sql import functions as F

        rows = self.seeds if isinstance(self.seeds, DataFrame) else spark.createDataFrame([(int(v), 0) for v in self.seeds], "v long, dist long")
        columns = [F.col("v").cast("long").alias("v"), F.col("dist").cast(self.graph.weight_type).alias("dist")]
        return rows.select(*columns, *[F.lit(0).cast("long").alias(a) for a in self.rule.attrs], F.lit(1).cast("long").alias("n"))


@dataclass
class RunResult:
    """state: (v, dist) of every vertex that was reached."""

    state: DataFrame
    measures: RunMeasures

    def measures_frame(self, spark: SparkSession, **labels) -> DataFrame:
        return spark.createDataFrame([labels | self.measures.row()])


def shortest_paths(graph: EdgeSet, source: int | tuple[int, ...], ordering: Ordering) -> Machine:
    """The machine of single- or multi-source shortest paths under an ordering; levels are carried only where it needs them."""
    sources = (source,) if isinstance(source, int) else tuple(source)
    return Machine(graph, leveled_sssp_rule() if "level" in ordering.attrs else sssp_rule(), ordering, sources)


def run(spark: SparkSession, machine: Machine, mode: str = "lockstep", tiers: Tiered | None = None, limits: Limits | None = None) -> RunResult:
    """mode `lockstep` (DataFrame rounds) or `drain` (queues inside tasks)."""
    from ordwork.plans import drain, lockstep

    if tiers is not None and not tiers.extends(machine.ordering):
        raise ValueError("a tiered machine must keep the root ordering")
    return {"lockstep": lockstep.run, "drain": drain.run}[mode](spark, machine, tiers, limits or Limits())
