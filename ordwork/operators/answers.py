"""Questions on a state (v, dist) of a finished run."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ordwork.baselines.others import parents
from ordwork.graph.model import EdgeSet


def reach_within(state: DataFrame, most) -> DataFrame:
    return state.where(F.col("dist") <= most)


def nearest(state: DataFrame, k: int) -> DataFrame:
    return state.orderBy("dist", "v").limit(k)


def histogram(state: DataFrame, width: int) -> DataFrame:
    """(band, n)."""
    return state.groupBy(F.expr(f"dist div {int(width)}").alias("band")).agg(F.count("*").alias("n"))


def by_group(state: DataFrame, groups: DataFrame, name: str) -> DataFrame:
    """(name, n, least, most, total): distances of the vertices of each group; groups: (v, name)."""
    return state.join(groups, "v").groupBy(name).agg(F.count("*").alias("n"), F.min("dist").alias("least"), F.max("dist").alias("most"), F.sum("dist").alias("total"))


def nearest_by_group(state: DataFrame, groups: DataFrame, name: str, k: int) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy(name).orderBy("dist", "v"))
    return state.join(groups, "v").withColumn("r", rank.cast("long")).where(F.col("r") <= k).select(name, "v", "dist", "r")


def shortest_path_tree(state: DataFrame, graph: EdgeSet) -> DataFrame:
    return parents(state, graph)


def path_to(state: DataFrame, graph: EdgeSet, target: int, most_hops: int = 10_000) -> list[int]:
    """Vertices of one shortest path to target, by tight edges and smallest ids; needs positive weights. One lookup a hop."""
    tree = parents(state, graph).cache()
    path = [target]
    try:
        if not state.where(F.col("v") == target).limit(1).count():
            return []
        while len(path) <= most_hops:
            found = tree.where(F.col("v") == path[-1]).select("parent").first()
            if found is None:
                break
            path.append(found["parent"])
    finally:
        tree.unpersist()
    return path[::-1]
