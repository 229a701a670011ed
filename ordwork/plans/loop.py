"""The driver loop that both plans share: take the smallest class, run rounds until it is empty, take the next.

Everything between rounds is append-only Parquet: accepted values (kind 0), items of the running class (kind 1) and
items of later classes (kind 2). The state is the minimum over all accepted values, later items are read again when their
class comes up. The log of accepted values is folded into a base when it has grown by half of it (or every COMPACT rounds), the later items every
COMPACT rounds. A round is one Spark job; what the driver needs to know of it (counts, the next smallest key) is observed while it runs.

States only fall, so an item that can't act now never will. After a class in which nothing was accepted, one pass over the later items
finds the next class with an item that can act; the classes before it are counted as visited, without a job for each.
"""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, Observation, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from ordwork.core.machine import Limits, Machine, RunMeasures, RunResult
from ordwork.store import Store

COMPACT = 24
#: Accepted values that a round may shuffle along with its items before they are folded into the base.
RECENT = 200_000
ACCEPTED, SAME, LATER, METRIC = 0, 1, 2, 3


def literal(key) -> Column:
    """A key value of the driver as a column, structs included."""
    if isinstance(key, Row):
        return F.struct(*[literal(x).alias(n) for n, x in key.asDict(recursive=False).items()])
    return F.lit(key)


class Loop:
    """Runs a machine with `step`, which turns (items of a round, state, class key) into rows with a kind."""

    def __init__(self, spark: SparkSession, machine: Machine, limits: Limits, name: str, skips: bool = True):
        self.spark, self.machine, self.limits, self.store = spark, machine, limits, Store(spark, name)
        self.items = machine.schema().struct()
        self.values = StructType(self.items.fields[:2])
        self.rows = StructType([*self.items.fields, StructField("kind", IntegerType())])
        self.state_paths: list[str] = []
        self.later_paths: list[str] = []
        self.measures = RunMeasures()
        self.skips, self.keeps_base = skips, name == "lockstep"
        self.base: DataFrame | None = None
        self.base_rows = self.recent_rows = 0
        self.kept: list[DataFrame] = []
        # columns over names only, made once
        self.class_key = machine.ordering.key(spark.createDataFrame([], self.items))
        self.counted = F.sum("n").alias("processed")
        sent, later = F.col("kind").isin(SAME, LATER), F.col("kind") == LATER
        self.about = [
            F.count_if(F.col("kind") == ACCEPTED).alias("accepted"),
            F.coalesce(F.sum(F.when(sent, F.col("n"))), F.lit(0)).alias("emitted"),
            F.count_if(F.col("kind") == SAME).alias("same"),
            F.count_if(later).alias("later"),
            F.min(F.when(later, self.class_key)).alias("next"),
            *self.bounds(self.items.names, sent),
        ]
        #: Bounds of all values and levels of items so far.
        self.least, self.most, self.top_level = 0, 0, 0

    def state(self) -> DataFrame:
        return self.store.read(self.state_paths, self.values)

    def settled(self) -> DataFrame:
        return self.state().groupBy("v").agg(F.min("dist").alias("dist"))

    def placed(self, frame: DataFrame, *keys: str) -> DataFrame:
        """frame hash-partitioned by keys as the shuffles of the rounds are."""
        return frame.repartition(int(self.spark.conf.get("spark.sql.shuffle.partitions")), *keys)

    def keep(self, placed: DataFrame, *keys: str) -> DataFrame:
        """placed rows, sorted by keys, on the executors' memory and disks; parts that are lost are made again from stored tables."""
        out = placed.sortWithinPartitions(*keys).persist(StorageLevel.MEMORY_AND_DISK)
        self.kept.append(out)
        return out

    def release(self) -> None:
        for frame in self.kept:
            frame.unpersist()
        self.kept = []

    def base_and_recent(self) -> tuple[DataFrame | None, DataFrame | None]:
        """The state as its kept base (base_v, base_dist) and the frame of values accepted since."""
        recent = self.state_paths[1:] if self.base is not None else self.state_paths
        return self.base, self.store.read(recent, self.values) if recent else None

    def level_bits(self) -> int:
        """Bits for the level in a LONG that holds value and level; 0 if the items seen don't fit."""
        bits = max(int(self.top_level).bit_length(), 1)
        return bits if self.least >= 0 and int(self.most).bit_length() + bits <= 62 else 0

    def bounds(self, names: list[str], which: Column | None = None) -> list[Column]:
        pick = (lambda c: F.when(which, F.col(c))) if which is not None else F.col
        top = F.max(pick("level")) if "level" in names else F.lit(0)
        return [F.min(pick("dist")).alias("least"), F.max(pick("dist")).alias("most"), top.alias("top_level")]

    def widen(self, got) -> None:
        if got["most"] is not None:
            self.least, self.most, self.top_level = min(self.least, got["least"]), max(self.most, got["most"]), max(self.top_level, got["top_level"] or 0)

    def compact(self, key) -> None:
        if len(self.state_paths) > COMPACT or self.recent_rows > max(RECENT, self.base_rows // 2):
            path = self.store.write(self.settled(), "state")
            self.state_paths, self.recent_rows = [path], 0
            if self.base is not None:
                self.base.unpersist()
                self.kept = [x for x in self.kept if x is not self.base]
            frame = self.store.read(path, self.values)
            self.base = self.keep(self.placed(frame.select(F.col("v").alias("base_v"), F.col("dist").alias("base_dist")), "base_v"), "base_v") if self.keeps_base else None
            self.base_rows = self.base.count() if self.base is not None else frame.count()
        if len(self.later_paths) > COMPACT:
            later = self.store.read(self.later_paths, self.items)
            rest = later.groupBy(*[c for c in later.columns if c != "n"]).agg(F.sum("n").alias("n")).select(*later.columns)
            path = self.store.write(rest.where(self.class_key >= literal(key)), "later")  # those of this class may still be due
            self.later_paths = [path]

    def ahead(self, key):
        """Count the classes from key on whose items can't act, as visited; returns the key of the first class that holds one which can."""
        later = self.store.read(self.later_paths, self.items)
        later = later.withColumn("class_key", self.class_key).where(F.col("class_key") >= literal(key))
        state = self.settled().select(F.col("v").alias("state_v"), F.col("dist").alias("state_dist"))
        known = later.join(state, F.col("v") == F.col("state_v"), "left")
        acts = F.coalesce(self.machine.rule.acts(F.col("dist"), F.col("state_dist")), F.lit(False))
        rows = self.store.save(known.groupBy("class_key").agg(F.sum("n").alias("n"), F.max(acts).alias("acts")), "ahead")
        following = rows.where("acts").agg(F.min("class_key").alias("k")).first()["k"]
        idle = rows.where(F.col("class_key") < literal(following)) if following is not None else rows
        for r in idle.orderBy("class_key").collect():  # a row a class, as in the trace
            m = self.measures
            m.classes, m.rounds, m.processed = m.classes + 1, m.rounds + 1, m.processed + r["n"]
            m.trace.append({"class_key": str(r["class_key"]), "round": m.rounds, "seconds": 0.0, "processed": r["n"], "accepted": 0, "emitted": 0})
        self.limits.check(self.measures)
        return following

    def run(self, step: Callable[[DataFrame, object, dict], DataFrame]) -> RunResult:
        try:
            return self.rounds(step)
        finally:
            self.release()

    def rounds(self, step: Callable[[DataFrame, object, dict], DataFrame]) -> RunResult:
        m = self.measures
        first = self.store.write(self.machine.seed_items(self.spark), "seeds")
        self.later_paths.append(first)
        seeds = self.store.read(first, self.items)
        got = seeds.agg(F.min(self.class_key).alias("k"), *self.bounds(self.items.names)).first()
        key = got["k"]
        self.widen(got)
        while key is not None:
            m.classes += 1
            following = []
            current: list[str] | None = None  # paths of the round's items, None: those of later_paths in this class
            before = m.accepted
            while True:
                self.compact(key)
                seen: dict = {}
                if current is None:
                    rest = Observation()
                    later = self.store.read(self.later_paths, self.items)
                    later = later.observe(rest, F.min(F.when(self.class_key > literal(key), self.class_key)).alias("next"))
                    items = later.where(self.class_key == literal(key))
                    seen["rest"] = rest
                else:
                    items = self.store.read(current, self.items)
                began = time.time()
                got = self.round(items, key, step, seen)
                m.rounds += 1
                m.processed += got["processed"]
                m.accepted += got["accepted"]
                m.emitted += got["emitted"]
                m.remote += got.get("remote", 0)
                m.max_queue = max(m.max_queue, got.get("max_queue", 0))
                m.backward += got["backward"]
                m.trace.append({"class_key": str(key), "round": m.rounds, "seconds": time.time() - began} | {k: got[k] for k in ("processed", "accepted", "emitted")})
                if got["backward"] and self.limits.check_forward:
                    raise AssertionError(f"{got['backward']} items of an earlier class than {key}")
                following += [x for x in (got["next"], seen["rest"].get["next"] if "rest" in seen else None) if x is not None]
                self.limits.check(m)
                if not got["same"]:
                    break
                current = [f"{got['path']}/kind={SAME}"]
            key = min(following) if following else None
            if key is not None and self.skips and m.accepted == before:
                key = self.ahead(key)
        m.wall_s = time.time() - m.began
        state = self.settled() if self.state_paths else self.spark.createDataFrame([], self.values)
        result = self.store.save(state, "result")
        return RunResult(result, m)

    def round(self, items: DataFrame, key, step, seen: dict) -> dict:
        """Run one round; returns its counts and the path of its rows."""
        out, about = step(items, key, seen), Observation()
        backward = F.count_if((F.col("kind") == LATER) & (self.class_key < literal(key))).alias("backward")
        out = out.observe(about, *self.about, backward)
        path = self.store.write(out, "round", "kind")
        got = dict(about.get) | {"path": path}
        self.widen(got)
        self.recent_rows += got["accepted"]
        if got["accepted"]:
            self.state_paths.append(f"{path}/kind={ACCEPTED}")
        if got["later"]:
            self.later_paths.append(f"{path}/kind={LATER}")
        return got | self.finish(got, seen)

    def finish(self, got: dict, seen: dict) -> dict:
        done = dict(seen["work"].get)
        deferred = done.get("deferred") or 0
        return {"processed": done["processed"] or 0, "emitted": got["emitted"] - deferred}
