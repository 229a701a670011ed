"""Drain rounds: in each round every task runs its own queue to empty, then items for other tasks are exchanged.

Vertices are placed on groups (tasks, sockets or hosts, see core.tiers); a group's edges, state and items meet in one cogroup. Inside,
a heap ordered by (distance, level, vertex), or a first-in-first-out queue without a sub-order, is drained of all items of the running class,
including those that it sends itself. The function depends on its inputs alone, so a task that is run again gives the same rows.

Group labels are chosen so that hash partitioning gives each group a partition of its own. Edges are kept in that partitioning, so a round
shuffles items and state only, and groups without items get no edges. Under the distance order, or without a sub-order, items
that can't act any more are counted but not queued, and what a group sends to one vertex in one class travels as its least
item and a count: neither changes what is processed, accepted or sent.
"""

from __future__ import annotations

import heapq
from collections import deque

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import LongType, StructField, StructType

from ordwork.core.machine import Limits, Machine, RunResult
from ordwork.core.rule import lower
from ordwork.core.tiers import Tiered, tiered
from ordwork.graph.model import gathered
from ordwork.plans.loop import ACCEPTED, LATER, METRIC, SAME, Loop

def labels(spark: SparkSession, groups: int) -> list[int]:
    """For each group the smallest whole number that hashes to its partition."""
    rows = spark.range(64 * groups + 64).groupBy(F.pmod(F.hash(F.col("id").cast("int")), F.lit(groups)).alias("p")).agg(F.min("id").alias("label")).collect()
    found = {r["p"]: r["label"] for r in rows}
    return [found.get(p, 64 * groups + 64 + p) for p in range(groups)]


class Queue:
    """One group's work in one round."""

    def __init__(self, edges: pa.Table, work: pa.Table, heap: bool, leveled: bool, folds: bool, sub=None):
        """sub(dist, level): keys of the ordered tiers, outermost first; the distance order is the heap's own. folds: whether items that can't act may be counted only."""
        v, n, dist = work["v"].to_pylist(), work["n"].to_pylist(), work["dist"].to_pylist()
        level = work["level"].to_pylist() if leveled else [0] * len(v)
        self.state: dict = {}
        self.sub, self.heap, self.folds = sub or (lambda dist, level: ()), heap, folds
        best: dict = {}
        items = []
        self.counted = 0
        for x, k, d, up in zip(v, n, dist, level, strict=True):
            if not k:
                if x not in self.state or d < self.state[x]:
                    self.state[x] = d
            elif folds:
                self.counted += k
                if x not in best or (d, up) < best[x]:
                    best[x] = (d, up)
            else:
                items += [(self.sub(d, up), d, up, x)] * k
        if folds:
            items = [((), d, up, x) for x, (d, up) in best.items() if x not in self.state or d < self.state[x]]
            self.counted -= len(items)
        items.sort()
        self.items = items if heap else deque(items)  # a sorted list is a heap
        self.any = bool(items) or self.counted > 0
        self.edges = edges

    def prepare(self, mine: int, group_of) -> None:
        lists = self.edges["nbrs"].combine_chunks()
        offsets = lists.offsets.to_numpy() - lists.offsets[0].as_py() if len(lists) else np.zeros(1, int)
        flat = lists.flatten()
        dst, w = flat.field("dst"), flat.field("w")
        self.dst = dst.to_numpy(zero_copy_only=False)
        self.w = w if pa.types.is_decimal(w.type) else w.to_numpy(zero_copy_only=False)
        self.here = group_of(self.dst) == mine
        self.starts: dict = {}
        for x, a, b in zip(self.edges["v"].to_pylist(), offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
            self.starts.setdefault(x, []).append((a, b))

    def drain(self, statements, class_of, by_edge: bool, key, mine: int, group_of) -> dict:
        """by_edge: whether the class of an item depends on more than its level."""
        self.prepare(mine, group_of)
        sent, delta = {}, {}
        processed, accepted, remote, longest = self.counted, 0, 0, 0
        items, state, starts, sub, heap, folds = self.items, self.state, self.starts, self.sub, self.heap, self.folds
        loose = []
        while items:
            longest = max(longest, len(items))
            _, d, level, v = heapq.heappop(items) if heap else items.popleft()
            processed += 1
            old = state.get(v)
            firing = [s for s in statements if s.fires_local(d, old)]
            if not firing:
                continue
            if any(s.updates for s in firing):
                state[v] = delta[v] = d
                accepted += 1
            for s in firing:
                above, send = level + 1 if s.levels else level, s.local
                fixed = None if by_edge else class_of(d, above) == key
                for a, b in starts.get(v, ()):
                    weights = self.w[a:b].to_pylist() if isinstance(self.w, pa.Array) else self.w[a:b].tolist()
                    for to, w, here in zip(self.dst[a:b].tolist(), weights, self.here[a:b].tolist(), strict=True):
                        value = send(d, w)
                        cls = class_of(value, above) if by_edge else None
                        same = cls == key if by_edge else fixed
                        if not here:
                            remote += 1
                        elif same:
                            if folds and to in state and not value < state[to]:
                                processed += 1  # it can't act when its turn comes
                            elif heap:
                                heapq.heappush(items, (sub(value, above), value, above, to))
                            else:
                                items.append(((), value, above, to))
                            continue
                        if not folds:
                            loose.append((to, value, above, 1, SAME if same else LATER))
                            continue
                        place = (to, cls if by_edge else same)
                        found = sent.get(place)
                        if found is None:
                            sent[place] = [value, above, 1, SAME if same else LATER]
                        else:
                            found[2] += 1
                            if (value, above) < (found[0], found[1]):
                                found[0], found[1] = value, above
        out = loose + [(to, *rest) for (to, _), rest in sent.items()]
        return {"out": out, "delta": delta, "processed": processed, "accepted": accepted, "remote": remote, "longest": longest}


def run(spark: SparkSession, machine: Machine, tiers: Tiered | None, limits: Limits) -> RunResult:
    tiers = tiers or tiered(machine.ordering, None)
    tier, tree = tiers.tier or "task", tiers.tree
    groups, heap = tree.groups(tier), tiers.tier is not None
    loop = Loop(spark, machine, limits, "drain")
    names = labels(spark, groups)
    lookup = F.array(*[F.lit(x).cast("int") for x in names])
    label = lambda v: F.element_at(lookup, (tree.group_of(v, tier) + 1).cast("int"))
    group_named = {x: k for k, x in enumerate(names)}
    dealt = machine.graph.dealt().withColumn("label", label(F.col("v"))).repartition(groups, "label")
    edges = loop.keep(gathered(dealt, "label"), "label")
    leveled = "level" in machine.rule.attrs
    extra = StructType([*loop.rows.fields, StructField("accepted_here", LongType()), StructField("remote", LongType()), StructField("longest", LongType())])
    arrow, rule, ordering = to_arrow_schema(extra), machine.rule, machine.ordering
    inner = [o for _, o in tiers.ordered()]
    plain_distance = [o.name for o in inner] in ([], ["dijkstra"])
    sub = None if plain_distance else (lambda dist, up: tuple(o.local(dist, up) for o in inner))
    fields = [f.name for f in extra.fields]

    statements, class_of = rule.statements, ordering.local
    folds = plain_distance and all(s.updates and s.holds is lower for s in statements)
    by_edge = ordering.name not in ("chaotic", "kla")
    attrs = ["level"] if leveled else []
    of_item = [label(F.col("v")).alias("label"), "v", "dist", *attrs, "n"]
    of_state = [label(F.col("v")).alias("label"), "v", "dist", *[F.lit(0).cast("long").alias(a) for a in attrs], F.lit(0).cast("long").alias("n")]
    counts = [F.sum(F.when(F.col("kind") == METRIC, F.col("v"))).alias("processed"), F.sum("accepted_here").alias("accepted_all"), F.sum("remote").alias("remote"), F.max("longest").alias("longest")]
    counts.append(F.collect_set(F.when(F.col("kind") == SAME, label(F.col("v")))).alias("groups"))  # a number a group
    kept_columns = [f.name for f in loop.rows.fields]
    busy: list[list[int] | None] = [None]

    def step(items: DataFrame, key, seen: dict) -> DataFrame:
        plain = tuple(key) if isinstance(key, tuple) else key
        rows = items.select(*of_item)
        if loop.state_paths:
            rows = rows.union(loop.state().select(*of_state))

        def each(group_key, left: pa.Table, right: pa.Table) -> pa.Table:
            queue = Queue(left, right, heap, leveled, folds, sub)
            if not queue.any:
                return arrow.empty_table()
            mine = group_named[group_key[0].as_py()]
            got = queue.drain(statements, class_of, by_edge, plain, mine, lambda v: tree.local_group(v, tier))
            lines = [(v, d, 0, 1, ACCEPTED, 0, 0, 0) for v, d in got["delta"].items()]
            lines += [(v, d, up, n, kind, 0, 0, 0) for v, d, up, n, kind in got["out"]]
            columns = dict(zip(("v", "dist", "level", "n", "kind", "accepted_here", "remote", "longest"), map(list, zip(*lines, strict=True)) if lines else [[] for _ in range(8)], strict=True))
            for c, x in (("v", got["processed"]), ("dist", None), ("level", 0), ("n", 0), ("kind", METRIC), ("accepted_here", got["accepted"]), ("remote", got["remote"]), ("longest", got["longest"])):
                columns[c].append(x)
            return pa.table([pa.array(columns[c], arrow.field(c).type) for c in fields], schema=arrow)

        seen["work"] = Observation()
        mine = edges if busy[0] is None else edges.where(F.col("label").isin(busy[0]))
        out = mine.groupBy("label").cogroup(rows.groupBy("label")).applyInArrow(each, extra)
        return out.observe(seen["work"], *counts).select(*kept_columns)

    def finish(got: dict, seen: dict) -> dict:
        done = dict(seen["work"].get)
        busy[0] = list(done["groups"] or []) or None
        return {"processed": done["processed"] or 0, "accepted": done["accepted_all"] or 0, "remote": done["remote"] or 0, "max_queue": done["longest"] or 0}

    loop.finish = finish
    return loop.run(step)
