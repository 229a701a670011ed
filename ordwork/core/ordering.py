"""Orderings of work items: strict weak orders, given by a key so that a comes before b exactly if key(a) < key(b)."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType


@dataclass(frozen=True)
class Ordering:
    """key is a column over the names of the item's columns (the frame only tells their types); local is the same on Python values (dist, level); attrs: columns it needs."""

    name: str
    key: Callable[[DataFrame], Column]
    local: Callable[[object, int], object]
    attrs: tuple[str, ...] = ()
    parameter: str = ""

    def smallest(self, items: DataFrame):
        """Key of the first class, or None without items; a partial aggregate."""
        return items.agg(F.min(self.key(items)).alias("k")).first()["k"]

    def with_class(self, items: DataFrame) -> DataFrame:
        return items.withColumn("class_key", self.key(items))


def chaotic() -> Ordering:
    """No order: one class."""
    return Ordering("chaotic", lambda items: F.lit(0).cast("long"), lambda dist, level: 0)


def by_distance() -> Ordering:
    """Least distance first."""
    return Ordering("dijkstra", lambda items: F.col("dist"), lambda dist, level: dist)


def distance_bands(delta) -> Ordering:
    """Bands of width delta > 0 of the distance."""
    if not delta > 0:
        raise ValueError("delta must be positive")
    whole = float(delta).is_integer()

    def key(items: DataFrame) -> Column:
        if whole and isinstance(items.schema["dist"].dataType, LongType):
            return F.expr(f"dist div {int(delta)}L")
        return F.floor(F.col("dist").cast("double") / F.lit(float(delta)))

    def local(dist, level):  # the same division of doubles as in the key
        return dist // int(delta) if whole and isinstance(dist, int) else math.floor(float(dist) / float(delta))

    return Ordering("delta", key, local, parameter=f"{delta:g}" if isinstance(delta, float) else str(delta))


def level_bands(k: int) -> Ordering:
    """Bands of k levels: hops from the source."""
    if not (k >= 1 and int(k) == k):
        raise ValueError("k must be a whole number from 1")
    return Ordering("kla", lambda items: F.expr(f"level div {int(k)}L"), lambda dist, level: level // int(k), ("level",), str(k))


def then(first: Ordering, second: Ordering) -> Ordering:
    """Lexicographic: second decides inside the classes of first."""
    return Ordering(
        f"{first.name}+{second.name}",
        lambda items: F.struct(first.key(items).alias("a"), second.key(items).alias("b")),
        lambda dist, level: (first.local(dist, level), second.local(dist, level)),
        tuple(dict.fromkeys(first.attrs + second.attrs)),
        ",".join(x for x in (first.parameter, second.parameter) if x),
    )


@dataclass(frozen=True)
class Relation:
    """A comparison that need not be an order, to show that the checker finds faults."""

    name: str
    less: Callable[[Column, Column], Column]
    attrs: tuple[str, ...] = field(default=())


def less(ordering: Ordering | Relation, a: str, b: str, items: DataFrame) -> Column:
    if isinstance(ordering, Relation):
        return ordering.less(F.col(a), F.col(b))
    return F.col(f"{a}.class_key") < F.col(f"{b}.class_key")


AXIOMS = ("irreflexive", "asymmetric", "transitive", "incomparability_transitive")


def check_strict_weak(spark: SparkSession, ordering: Ordering | Relation, items: DataFrame, most: int = 500) -> DataFrame:
    """(axiom, violations) over all triples of a small set of items; cubic, so more than `most` items are refused."""
    if items.limit(most + 1).count() > most:
        raise ValueError(f"the check looks at all triples; give it at most {most} items")
    rows = ordering.with_class(items) if isinstance(ordering, Ordering) else items
    packed = F.struct(*rows.columns)
    of = lambda name: rows.select(packed.alias(name))
    triples = of("a").crossJoin(of("b")).crossJoin(of("c"))
    lt = lambda x, y: F.coalesce(less(ordering, x, y, rows), F.lit(False))
    same = lambda x, y: ~lt(x, y) & ~lt(y, x)
    one = triples.agg(
        F.count_if(lt("a", "a")).alias(AXIOMS[0]),
        F.count_if(lt("a", "b") & lt("b", "a")).alias(AXIOMS[1]),
        F.count_if(lt("a", "b") & lt("b", "c") & ~lt("a", "c")).alias(AXIOMS[2]),
        F.count_if(same("a", "b") & same("b", "c") & ~same("a", "c")).alias(AXIOMS[3]),
    )
    return one.select(F.explode(F.array(*[F.struct(F.lit(x).alias("axiom"), F.col(x).cast("long").alias("violations")) for x in AXIOMS])).alias("x")).select("x.*")


def induced_less(ordering: Ordering, one: DataFrame, other: DataFrame) -> bool:
    """Whether every item of class one comes before every item of class other."""
    last = one.agg(F.max(ordering.key(one)).alias("k")).first()["k"]
    first = other.agg(F.min(ordering.key(other)).alias("k")).first()["k"]
    return last is not None and first is not None and last < first
