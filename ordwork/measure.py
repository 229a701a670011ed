"""Cost and accuracy measures of runs, as rows that experiments collect."""

from __future__ import annotations

from statistics import mean, stdev

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordwork.core.machine import Machine, RunResult
from ordwork.core.tiers import Tiered

COLUMNS = "run_id graph root param tier mode repeat classes rounds processed accepted rejected redundant reached emitted remote_items max_queue wall_s"


def row(result: RunResult, machine: Machine, tiers: Tiered | None, mode: str, graph: str, repeat: int = 0) -> dict:
    m, reached = result.measures, result.state.count()
    return {
        "run_id": f"{graph}/{machine.ordering.name}{machine.ordering.parameter}/{tiers.label if tiers else 'fifo'}/{mode}/{repeat}",
        "graph": graph, "root": machine.ordering.name, "param": machine.ordering.parameter, "tier": tiers.label if tiers else "fifo", "mode": mode, "repeat": repeat,
        "classes": m.classes, "rounds": m.rounds, "processed": m.processed, "accepted": m.accepted, "rejected": m.processed - m.accepted, "redundant": m.accepted - reached,
        "reached": reached, "emitted": m.emitted, "remote_items": m.remote, "max_queue": m.max_queue, "wall_s": m.wall_s,
    }


def class_profile(spark: SparkSession, result: RunResult) -> DataFrame:
    """(class_key, rounds, items, accepted) in the order visited; a row for each class, from the driver's trace."""
    rows = spark.createDataFrame(result.measures.trace or [{"class_key": "", "round": 0, "seconds": 0.0, "processed": 0, "accepted": 0, "emitted": 0}])
    return rows.groupBy("class_key").agg(F.count("*").alias("rounds"), F.sum("processed").alias("items"), F.sum("accepted").alias("accepted"))


def summary(rows: list[dict]) -> list[dict]:
    """Mean and standard deviation of the wall seconds over repeats of a configuration, with its speed-up over its base; runs that a limit stopped are left out."""
    groups: dict[tuple, list[dict]] = {}
    for r in rows:
        if "stopped" in r:
            continue
        groups.setdefault((r["graph"], r["root"], r["param"], r["tier"], r["mode"]), []).append(r)
    out = []
    for (graph, root, param, tier, mode), some in groups.items():
        seconds = [r["wall_s"] for r in some]
        out.append({"graph": graph, "root": root, "param": param, "tier": tier, "mode": mode, "n": len(some), "wall_mean_s": mean(seconds), "wall_sd_s": stdev(seconds) if len(seconds) > 1 else 0.0} | {k: some[0][k] for k in ("classes", "rounds", "processed", "accepted", "redundant", "reached", "remote_items")})
    base = {(x["graph"], x["root"], x["param"], x["mode"]): x["wall_mean_s"] for x in out if x["tier"] == "fifo"}
    return [x | {"speedup": base.get((x["graph"], x["root"], x["param"], x["mode"]), x["wall_mean_s"]) / max(x["wall_mean_s"], 1e-9)} for x in out]


def weak_efficiency(times: dict[int, float]) -> dict[int, float]:
    """Time on the fewest cores over time on c cores, for work that grows with the cores."""
    first = times[min(times)]
    return {c: first / t for c, t in times.items()}
