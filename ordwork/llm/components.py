"""Connected components by repeated contraction.

In each round every node points at the neighbour (or itself) that comes first in an order drawn by hashing, all nodes
are replaced by what they point at, and links inside one node go. With a random order a constant share of the nodes
goes each round, so rounds grow as the logarithm of the longest chain, whatever the ids look like. Each round is a
few shuffles of what links are left; hubs meet a partial aggregate and splittable joins; nothing is collected.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordwork.llm.common import Scratch


def components(scratch: Scratch, links: DataFrame) -> DataFrame:
    """(node, root) for every node of the undirected links (u, v); root is one node of the component."""
    both = links.select("u", "v").union(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    edges = scratch.save(both.where("u <> v").distinct(), "edges")
    named, k = None, 0
    while edges.limit(1).count():
        k += 1
        # the draw differs from round to round, so no input order is bad for all of them
        draw = lambda c: F.struct(F.xxhash64(F.lit(k), c).alias("h"), F.col(c).alias("x"))  # noqa: B023, E731
        to = edges.groupBy("u").agg(F.min(draw("v")).alias("m")).select("u", F.least("m", draw("u"))["x"].alias("to"))
        to = scratch.save(to, f"to{k}")
        left = edges.join(to, "u").select(F.col("to").alias("a"), "v")
        right = left.join(to.select(F.col("u").alias("v"), F.col("to").alias("b")), "v").where("a <> b")
        smaller = scratch.save(right.select(F.col("a").alias("u"), F.col("b").alias("v")).distinct(), f"edges{k}")
        if named is None:
            new = to.select(F.col("u").alias("node"), F.col("to").alias("root"))
        else:
            new = named.join(to, F.col("root") == F.col("u"), "left").select("node", F.coalesce("to", "root").alias("root"))
        new = scratch.save(new, f"named{k}")
        for old in [edges, to, *([named] if named is not None else [])]:
            scratch.drop(old)
        edges, named = smaller, new
    return named if named is not None else edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
