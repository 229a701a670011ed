"""Processing rules: statements of a condition, an update of the state and a constructor of new items.

Items are rows (v, dist[, level], n): the vertex, the value that its state may take, ordering attributes, and how many equal items
the row stands for. The state has a value for each vertex that was reached; no row means infinitely far.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import DataType, LongType, StructField, StructType


@dataclass(frozen=True)
class ItemSchema:
    """Columns of the items: a vertex, a state value and ordering attributes."""

    value: DataType
    attrs: tuple[str, ...] = ()

    def struct(self) -> StructType:
        return StructType([StructField("v", LongType()), StructField("dist", self.value), *[StructField(a, LongType()) for a in self.attrs], StructField("n", LongType())])


def lower(value, state) -> bool:
    """improves on Python values; None is infinitely far."""
    return state is None or value < state


@dataclass(frozen=True)
class Statement:
    """condition(value, state): whether an item may act. If `updates`, the update sets the state to the value (its only side
    effect, a minimum, so the order of arrival doesn't matter) and succeeds where that lowers the state; without it the state stays and
    the update always succeeds. Only where both hold does construct give the value of the item sent along each edge.

    A condition must be one that holds for every smaller value too, as rounds may look at the least value of a vertex alone.
    holds and local are condition and construct on Python values.
    """

    condition: Callable[[Column, Column], Column]
    construct: Callable[[Column, Column], Column]
    local: Callable[[object, object], object]
    levels: bool = False
    updates: bool = True
    holds: Callable[[object, object], bool] = lower

    def fires(self, value: Column, state: Column) -> Column:
        allowed = F.coalesce(self.condition(value, state), F.lit(False))
        return allowed & improves(value, state) if self.updates and self.condition is not improves else allowed

    def fires_local(self, value, state) -> bool:
        return self.holds(value, state) and (not self.updates or lower(value, state))


@dataclass(frozen=True)
class Rule:
    """Union of statements, each judged against the state that the item found. Most shipped rules have one: act if better than the state."""

    name: str
    statements: tuple[Statement, ...]

    @staticmethod
    def single(name: str, condition, construct, local, levels: bool = False) -> Rule:
        return Rule(name, (Statement(condition, construct, local, levels),))

    @property
    def attrs(self) -> tuple[str, ...]:
        return ("level",) if any(s.levels for s in self.statements) else ()

    def acts(self, value: Column, state: Column) -> Column:
        """Whether any statement fires."""
        return reduce(lambda a, b: a | b, (s.fires(value, state) for s in self.statements))

    def sets(self, value: Column, state: Column) -> Column:
        """Whether the state takes the value."""
        return reduce(lambda a, b: a | b, (s.fires(value, state) for s in self.statements if s.updates), F.lit(False))

    def emitted(self, value: Column, state: Column, level: Column, edge: Column) -> Column:
        """Array of structs (v, dist, level): what the statements that fire send along an edge (dst, w)."""
        made = [F.struct(edge["dst"].alias("v"), s.construct(value, edge["w"]).alias("dst_value"), ((level + 1) if s.levels else level).alias("level")) for s in self.statements]
        if len(made) == 1:  # the caller keeps items that fire
            return F.array(*made)
        return F.filter(F.array(*[F.when(s.fires(value, state), x) for s, x in zip(self.statements, made, strict=True)]), lambda x: x.isNotNull())


def improves(value: Column, state: Column) -> Column:
    """Strictly better than the state, or nothing known yet."""
    return state.isNull() | (value < state)


def sssp_rule() -> Rule:
    return Rule.single("sssp", improves, lambda d, w: d + w, lambda d, w: d + w)


def leveled_sssp_rule() -> Rule:
    """As sssp_rule, with the level of an item one above that of the item it comes from."""
    return Rule.single("leveled_sssp", improves, lambda d, w: d + w, lambda d, w: d + w, levels=True)


def bfs_rule() -> Rule:
    """Every edge counts one."""
    return Rule.single("bfs", improves, lambda d, w: d + F.lit(1).cast("long"), lambda d, w: d + 1)


def component_rule() -> Rule:
    """The smallest label wins; weights don't matter."""
    return Rule.single("components", improves, lambda d, w: d, lambda d, w: d)


__all__ = ["ItemSchema", "Rule", "Statement", "bfs_rule", "component_rule", "improves", "lower", "leveled_sssp_rule", "sssp_rule"]
