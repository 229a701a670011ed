"""Lock-step rounds as DataFrame plans: every pending item of the class (or, with a sub-order, those with their
group's smallest distance) is processed against one snapshot of the state.

A round is: items and what was accepted lately -> one shuffle by vertex with map-side minima -> join with the base of the state -> condition ->
join with the adjacency -> explode into the accepted value and the items for the neighbours. State base and adjacency are
kept partitioned and sorted by vertex, so neither is shuffled again: what a round moves is its frontier. Edges of very large hubs
are kept by (vertex, part) instead and joined by a second, smaller shuffle, so no vertex is a task of its own.
"""

from __future__ import annotations

from functools import cache

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from ordwork.core.machine import Limits, Machine, RunResult
from ordwork.core.tiers import Tiered
from ordwork.graph.model import gathered
from ordwork.plans.loop import ACCEPTED, LATER, SAME, Loop, literal

#: Parts of a vertex's edges (see EdgeSet.adjacency) that stay with the vertex; further ones are spread over tasks.
NEAR_PARTS = 16
#: Groups of a tier that may be broadcast, a row each.
MOST_GROUPS = 1_000_000


def kept_adjacency(loop: Loop, dealt: DataFrame) -> tuple[DataFrame, DataFrame | None]:
    """Adjacency by vertex, and what is beyond NEAR_PARTS of hubs by (hub, hub_part), or None; each is shuffled once a run."""
    beyond = dealt.where(F.col("part") >= NEAR_PARTS)
    near = loop.keep(gathered(loop.placed(dealt.where(F.col("part") < NEAR_PARTS), "v")), "v")
    far = None
    if beyond.limit(1).count():
        far = loop.keep(gathered(loop.placed(beyond, "v", "part")).withColumnsRenamed({"v": "hub", "part": "hub_part"}), "hub", "hub_part")
    return near, far


def run(spark: SparkSession, machine: Machine, tiers: Tiered | None, limits: Limits) -> RunResult:
    loop = Loop(spark, machine, limits, "lockstep", skips=tiers is None or not tiers.tier)
    near, far = kept_adjacency(loop, machine.graph.dealt())
    leveled = "level" in machine.rule.attrs
    kind_of = machine.graph.weight_type
    whole = isinstance(kind_of, LongType)
    level = F.col("level") if leveled else F.lit(0).cast("long")
    columns = [f.name for f in loop.items.fields]
    nothing = F.array().cast(near.schema["nbrs"].dataType)
    rule, ordered = machine.rule, tiers is not None and bool(tiers.tier)

    # columns over names only, made once: a round puts them together
    dist, old = F.col("dist"), F.col("old")
    acts, sets = rule.acts(dist, old), rule.sets(dist, old)
    no_old, part = F.lit(None).cast(kind_of).alias("old"), F.coalesce("part", F.lit(0)).alias("part")
    minima = [F.min("best").alias("best"), F.min("old").alias("old")]
    own = F.struct(F.lit(True).alias("own"), F.col("v").alias("v"), dist.alias("dist"), level.cast("long").alias("level"))
    sent = F.flatten(F.transform(F.coalesce("nbrs", nothing), lambda e: F.transform(rule.emitted(dist, old, level, e), lambda x: F.struct(F.lit(False).alias("own"), x["v"].alias("v"), x["dst_value"].cast(kind_of).alias("dist"), x["level"].cast("long").alias("level")))))
    both = F.explode(F.when((F.col("part") == 0) & sets, F.concat(F.array(own), sent)).otherwise(sent)).alias("x")
    item = [F.col(f"x.{c}").alias(c) if c != "n" else F.lit(1).cast("long").alias("n") for c in columns] + [F.col("x.own").alias("own")]
    state_level = F.lit(0).cast("long").alias("level")

    @cache
    def shape(bits: int) -> tuple[Column, Column, list[Column]]:
        """(best, its null, [dist, level] from best): value and level as one number where they fit, which makes the minimum a hash aggregate."""
        if bits:
            best, empty = F.shiftleft("dist", bits) + F.col("level"), "long"
            parts = [F.shiftright("best", bits).alias("dist"), F.col("best").bitwiseAND(F.lit((1 << bits) - 1)).alias("level")]
        elif leveled:
            best, empty = F.struct("dist", "level"), f"struct<dist:{kind_of.simpleString()},level:bigint>"
            parts = [F.col("best.dist").alias("dist"), F.col("best.level").alias("level")]
        else:
            best, empty, parts = F.col("dist"), kind_of, [F.col("best").alias("dist"), state_level]
        best = F.when(F.col("now"), best) if ordered else best
        return best.alias("best"), F.lit(None).cast(empty).alias("best"), parts

    def split(items: DataFrame, work: Observation) -> DataFrame:
        """items with `now`: whether their group's ordered tiers let them act in this round."""
        marked = items.withColumn("now", F.lit(True))
        for place, (tier, ordering) in enumerate(tiers.ordered()):
            marked = marked.withColumn("g", tiers.tree.group_of(F.col("v"), tier)).withColumn("k", ordering.key(marked))
            least = marked.where("now").groupBy("g").agg(F.min("k").alias("least")).withColumnRenamed("g", f"g{place}")
            least = F.broadcast(least) if tiers.tree.groups(tier) <= MOST_GROUPS else least  # a row a group
            marked = marked.join(least, F.col("g") == F.col(f"g{place}"), "left")
            marked = marked.withColumn("now", F.col("now") & (F.col("k") == F.col("least"))).drop("g", "k", "least", f"g{place}")
        marked = marked.observe(work, F.sum(F.when(F.col("now"), F.col("n"))).alias("processed"), F.sum(F.when(~F.col("now"), F.col("n"))).alias("deferred"))
        # deferred items take the way of the others, so that the frame is read once; they come back as they were
        return marked.withColumn("deferred", F.when(~F.col("now"), F.struct(*[F.col(c) for c in items.columns])))

    def step(items: DataFrame, key, seen: dict) -> DataFrame:
        work = seen["work"] = Observation()
        items = split(items, work) if ordered else items.observe(work, loop.counted)
        best, empty, parts = shape(loop.level_bits() if leveled and whole else 0)
        rows = items.select("v", best, no_old)
        base, recent = loop.base_and_recent()
        if recent is not None:
            rows = rows.union(recent.select("v", empty, dist.alias("old")))
        merged = rows.groupBy("v").agg(*minima).where("best is not null")
        if base is not None:
            merged = merged.join(base.hint("merge"), F.col("v") == F.col("base_v"), "left").select("v", "best", F.least("old", "base_dist").alias("old"))
        joined = merged.select("v", *parts, "old").where(acts).join(near.hint("merge"), "v", "left").select("v", "dist", "level", "old", part, "parts", "nbrs")
        out = joined.select(both)
        if far is not None:
            hubs = joined.where((F.col("part") == 0) & (F.col("parts") > NEAR_PARTS)).select("v", "dist", "level", "old", F.explode(F.sequence(F.lit(NEAR_PARTS), F.col("parts") - 1)).alias("p"))
            beyond = hubs.join(far.select("hub", "hub_part", "nbrs").hint("merge"), (F.col("v") == F.col("hub")) & (F.col("p") == F.col("hub_part")))
            out = out.union(beyond.select(F.explode(sent).alias("x")))
        kind = F.when(F.col("own"), ACCEPTED).when(loop.class_key == literal(key), SAME).otherwise(LATER).alias("kind")
        out = out.select(*item).select(*columns, kind)
        if ordered:
            out = out.unionByName(items.where("deferred is not null").select("deferred.*").select(*columns, F.lit(SAME).alias("kind")))
        return out

    return loop.run(step)
