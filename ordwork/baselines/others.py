"""Other algorithms on the same machine or beside it: sequential search, components, trees, ranks, independent sets, colours."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import LongType, StructField, StructType

from ordwork.core.machine import Machine, RunResult, run, shortest_paths
from ordwork.core.ordering import chaotic, level_bands
from ordwork.core.rule import bfs_rule, component_rule
from ordwork.graph.model import EdgeSet
from ordwork.store import Store


def narrow(column: pa.Array) -> np.ndarray:
    """Values in as few bytes as the whole numbers of a batch need."""
    if pa.types.is_decimal(column.type):
        return np.array(column.to_pylist(), object)
    values = column.to_numpy(zero_copy_only=False)
    if values.dtype.kind != "i" or not len(values):
        return values
    low, high = values.min(), values.max()  # signed kinds only, so that batches of several kinds stay whole numbers together
    return values.astype(next((k for k in (np.int8, np.int16, np.int32) if np.iinfo(k).min <= low and high <= np.iinfo(k).max), np.int64))


def search(batches: Iterator[pa.RecordBatch], source: int) -> dict:
    """Distance by vertex over batches of edges (src, dst, w), sorted by src as far as may be: edges are flat arrays, vertices have ranges of them."""
    starts: dict[int, list[tuple[int, int]]] = {}
    to, weight, n = [], [], 0
    for batch in batches:
        src = batch.column(0).to_numpy()
        first = np.flatnonzero(np.concatenate(([True], src[1:] != src[:-1]))) if len(src) else np.zeros(0, int)
        for v, a, b in zip(src[first].tolist(), (first + n).tolist(), (np.append(first[1:], len(src)) + n).tolist(), strict=True):
            starts.setdefault(v, []).append((a, b))
        to.append(narrow(batch.column(1)))
        weight.append(narrow(batch.column(2)))
        n += len(src)
    if not n:
        return {}
    to = np.concatenate(to)
    weight = np.concatenate(weight)
    out: dict = {}
    best: dict = {source: 0}
    heap = [(0, source)]
    while heap:
        d, v = heapq.heappop(heap)
        if v in out:
            continue
        out[v] = d
        for a, b in starts.get(v, ()):
            for t, w in zip(to[a:b].tolist(), weight[a:b].tolist(), strict=True):
                if t not in out and (t not in best or d + w < best[t]):
                    best[t] = d + w
                    heapq.heappush(heap, (d + w, t))
    return out


def dijkstra_local(graph: EdgeSet, source: int) -> DataFrame:
    """(v, dist) by a sequential heap in one task: a reference for small graphs, by design not distributed.

    The task gets the edges in batches and keeps about eight bytes of each, where ids and weights are small.
    """
    kind = StructType([StructField("v", LongType()), StructField("dist", graph.weight_type)])
    schema = to_arrow_schema(kind)

    def each(batches):
        found = search(batches, source)
        if found:
            yield pa.RecordBatch.from_arrays([pa.array(list(found), schema.field("v").type), pa.array(list(found.values()), schema.field("dist").type)], schema=schema)

    return graph.edges.select("src", "dst", "w").repartition(1).sortWithinPartitions("src").mapInArrow(each, kind)


def level_synchronous(spark: SparkSession, graph: EdgeSet, source: int) -> RunResult:
    """Frontier relaxation, level by level."""
    return run(spark, shortest_paths(graph, source, level_bands(1)))


def bfs(spark: SparkSession, graph: EdgeSet, source: int | tuple[int, ...]) -> RunResult:
    ones = EdgeSet(graph.edges.select("src", "dst", F.lit(1).cast("long").alias("w")))
    return run(spark, Machine(ones, bfs_rule(), chaotic(), (source,) if isinstance(source, int) else source))


def components(spark: SparkSession, graph: EdgeSet) -> RunResult:
    """dist is the smallest vertex id of the weakly connected component."""
    both = EdgeSet(graph.symmetric().edges.select("src", "dst", F.lit(0).cast("long").alias("w")))
    return run(spark, Machine(both, component_rule(), chaotic(), both.vertices().select("v", F.col("v").alias("dist"))))


def parents(state: DataFrame, graph: EdgeSet) -> DataFrame:
    """(v, parent): the smallest in-neighbour on a shortest path of each reached vertex; sources have none."""
    a = state.select(F.col("v").alias("src"), F.col("dist").alias("from"))
    b = state.select(F.col("v").alias("dst"), F.col("dist").alias("to"))
    tight = graph.edges.join(a, "src").join(b, "dst").where(F.col("from") + F.col("w") == F.col("to"))
    return tight.groupBy(F.col("dst").alias("v")).agg(F.min("src").alias("parent"))


def pagerank(spark: SparkSession, graph: EdgeSet, iterations: int = 10, damping: float = 0.85, digits: int = 9) -> DataFrame:
    """(v, rank): power iteration from the uniform vector; vertices without out-edges keep nothing for others."""
    store = Store(spark, "pagerank")
    edges = graph.edges.select("src", "dst")
    degree = edges.groupBy("src").agg(F.count("*").alias("degree"))
    shares = store.save(edges.join(degree, "src").select("src", "dst", "degree"), "shares")
    vertices = store.save(graph.vertices(), "vertices")
    n = vertices.count()
    rank = vertices.withColumn("rank", F.lit(1.0 / max(n, 1)))
    for _ in range(iterations):
        sent = shares.join(rank, shares.src == rank.v).groupBy(F.col("dst").alias("u")).agg(F.sum(F.col("rank") / F.col("degree")).alias("got"))
        rank = store.save(vertices.join(sent, vertices.v == sent.u, "left").select("v", (F.lit((1 - damping) / n) + damping * F.coalesce("got", F.lit(0.0))).alias("rank")), "rank")
    return rank.select("v", F.round("rank", digits).alias("rank"))


def priority(v):
    return F.struct(F.md5(F.col(v).cast("string").cast("binary")).alias("h"), F.col(v).alias("x"))


def maximal_independent_set(spark: SparkSession, graph: EdgeSet) -> DataFrame:
    """(v): vertices that come first by hashed id among their undecided neighbours join; neighbours leave; repeat.

    It is the set that a greedy scan in the order of the hash would take.
    """
    store = Store(spark, "mis")
    edges = store.save(graph.symmetric().edges.select("src", "dst"), "edges")
    left, chosen = store.save(graph.vertices(), "left"), None
    while left.limit(1).count():
        inner = edges.join(left.withColumnRenamed("v", "src"), "src", "left_semi").join(left.withColumnRenamed("v", "dst"), "dst", "left_semi")
        first = inner.groupBy(F.col("src").alias("v")).agg(F.min(priority("dst")).alias("other"))
        join = store.save(left.join(first, "v", "left").where(F.col("other").isNull() | (priority("v") < F.col("other"))).select("v"), "join")
        gone = edges.join(join.withColumnRenamed("v", "src"), "src", "left_semi").select(F.col("dst").alias("v")).union(join).distinct()
        left = store.save(left.join(gone, "v", "left_anti"), "left")
        chosen = join if chosen is None else store.save(chosen.union(join), "chosen")
    return chosen if chosen is not None else left


def coloring(spark: SparkSession, graph: EdgeSet) -> DataFrame:
    """(v, color): neighbours differ; color k is the k-th independent set taken from what is left."""
    store = Store(spark, "color")
    edges, left, out, k = graph.symmetric(), store.save(graph.vertices(), "left"), None, 0
    while left.limit(1).count():
        inner = edges.edges.join(left.withColumnRenamed("v", "src"), "src", "left_semi").join(left.withColumnRenamed("v", "dst"), "dst", "left_semi")
        inner = EdgeSet(store.save(inner.select("src", "dst", "w"), "inner"))
        alone = left.join(inner.edges.select(F.col("src").alias("v")), "v", "left_anti")
        now = store.save(maximal_independent_set(spark, inner).union(alone).withColumn("color", F.lit(k).cast("long")), "now")
        out = now if out is None else store.save(out.union(now), "out")
        left, k = store.save(left.join(now, "v", "left_anti"), "left"), k + 1
    return out if out is not None else left.withColumn("color", F.lit(0).cast("long"))
