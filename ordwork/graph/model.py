"""Weighted directed graphs as DataFrames of edges (src LONG, dst LONG, w LONG | DOUBLE | DECIMAL)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DecimalType, DoubleType, LongType

#: Out-edges of a vertex are stored in rows of at most so many, so that hubs are many rows, not one.
CHUNK = 4096


class GraphError(ValueError):
    """Edges that the methods are not defined for."""


@dataclass(frozen=True)
class EdgeSet:
    """Edges of a graph. Parallel edges are allowed until ``collapse``; loops never shorten a path."""

    edges: DataFrame

    @staticmethod
    def of(frame: DataFrame, src: str = "src", dst: str = "dst", w: str | Column | None = "w") -> EdgeSet:
        weight = F.lit(1).cast("long") if w is None else F.col(w) if isinstance(w, str) else w
        rows = frame.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst"), weight.alias("w"))
        kind = rows.schema["w"].dataType
        if not isinstance(kind, (LongType, DoubleType, DecimalType)):
            rows = rows.withColumn("w", F.col("w").cast("double" if kind.typeName() == "float" else "long"))
        return EdgeSet(rows)

    @property
    def weight_type(self):
        return self.edges.schema["w"].dataType

    def collapse(self) -> EdgeSet:
        """The lightest of parallel edges, without loops."""
        return EdgeSet(self.edges.where("src <> dst").groupBy("src", "dst").agg(F.min("w").alias("w")))

    def validate(self) -> EdgeSet:
        """Raises GraphError on null ends, null, negative or NaN weights; one aggregate."""
        nan = F.isnan("w") if isinstance(self.weight_type, DoubleType) else F.lit(False)
        bad = self.edges.agg(
            F.count_if(F.col("src").isNull() | F.col("dst").isNull()).alias("ends"),
            F.count_if(F.col("w").isNull() | nan | (F.col("w") < 0)).alias("weights"),
        ).first()
        if bad["ends"] or bad["weights"]:
            raise GraphError(f"{bad['ends']} edges without an end, {bad['weights']} with a weight that is null, negative or NaN")
        return self

    def symmetric(self) -> EdgeSet:
        return EdgeSet(self.edges.union(self.edges.select(F.col("dst"), F.col("src"), "w"))).collapse()

    def reversed(self) -> EdgeSet:
        return EdgeSet(self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))

    def vertices(self) -> DataFrame:
        return self.edges.select(F.col("src").alias("v")).union(self.edges.select("dst")).distinct()

    def out_degrees(self) -> DataFrame:
        return self.edges.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("degree"))

    def in_degrees(self) -> DataFrame:
        return self.edges.groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("degree"))

    def out_edges(self, items: DataFrame) -> DataFrame:
        """Items joined with the edges that leave their vertex."""
        return items.join(self.edges, items.v == self.edges.src)

    def dealt(self, chunk: int = CHUNK) -> DataFrame:
        """(v, part, parts, dst, w): edges with the row of `adjacency` that they go to; hubs have several."""
        sizes = self.edges.groupBy("src").count().where(F.col("count") > chunk).select(F.col("src").alias("hub"), F.ceil(F.col("count") / (chunk / 2)).cast("int").alias("parts"))
        rows = self.edges.join(sizes, F.col("src") == F.col("hub"), "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
        part = F.when(F.col("parts") > 1, F.pmod(F.xxhash64("dst"), F.col("parts").cast("long"))).otherwise(0)
        return rows.select(F.col("src").alias("v"), part.cast("int").alias("part"), "parts", "dst", "w")

    def adjacency(self, chunk: int = CHUNK) -> DataFrame:
        """(v, part, parts, nbrs): out-edges as arrays of (dst, w), hubs over several rows."""
        return gathered(self.dealt(chunk))


def gathered(dealt: DataFrame, *extra: str) -> DataFrame:
    return dealt.groupBy(*extra, "v", "part", "parts").agg(F.collect_list(F.struct("dst", "w")).alias("nbrs"))


def encode_vertices(frame: DataFrame, *columns: str) -> DataFrame:
    """frame with string keys replaced by 63-bit hashes of their text; equal texts get equal ids on every machine."""
    return frame.withColumns({c: F.xxhash64(c).bitwiseAND(F.lit((1 << 63) - 1)) for c in columns})
