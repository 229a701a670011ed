"""Shortest paths from SQL: a table or view of edges in, a view of distances out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ordwork.core.machine import run, shortest_paths
from ordwork.core.ordering import by_distance, chaotic, distance_bands, level_bands
from ordwork.graph.model import EdgeSet
from ordwork.store import Store

ORDERS = {"chaotic": lambda _: chaotic(), "dijkstra": lambda _: by_distance(), "delta": distance_bands, "kla": level_bands}


def sssp(spark: SparkSession, edges: str, source: int, order: str = "delta", parameter=1, view: str = "sssp") -> DataFrame:
    """Runs over the edges (src, dst, w) that a table, view or subquery gives, and registers the distances (v, dist) as a view.

    PySpark can't extend the parser, so this is a call and not a table function; its result is used in SQL by the view's name.
    """
    source_rows = spark.sql(edges) if edges.lstrip().lower().startswith(("select", "with")) else spark.table(edges)
    graph = EdgeSet(Store(spark, "sql").save(EdgeSet.of(source_rows).collapse().validate().edges, "edges"))
    state = run(spark, shortest_paths(graph, source, ORDERS[order](parameter))).state
    state.createOrReplaceTempView(view)
    return state
