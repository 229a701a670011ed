"""Memory tiers: a tree of groups global > host > socket > task, each with an ordering or none.

Placement is arithmetic and nested by construction: the socket is a function of the task, the host of the socket.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F

from ordwork.core.ordering import Ordering, by_distance, chaotic, distance_bands, level_bands

TIERS = ("host", "socket", "task")


@dataclass(frozen=True)
class TierTree:
    """How many groups each tier has, and the ordering at each tier that has one."""

    hosts: int = 2
    sockets_per_host: int = 2
    tasks_per_socket: int = 2
    order: dict[str, Ordering] = field(default_factory=dict)

    @property
    def tasks(self) -> int:
        return self.hosts * self.sockets_per_host * self.tasks_per_socket

    def groups(self, tier: str) -> int:
        return {"host": self.hosts, "socket": self.hosts * self.sockets_per_host, "task": self.tasks}[tier]

    def task_of(self, v: Column) -> Column:
        spread = F.floor((F.pmod(v, F.lit(1 << 31).cast("long")) * 40503) / 16)
        return F.pmod(spread.cast("long"), F.lit(self.tasks).cast("long"))

    def group_of(self, v: Column, tier: str) -> Column:
        return F.floor(self.task_of(v) / (self.tasks // self.groups(tier))).cast("long")

    def local_group(self, v, tier: str):
        """group_of for numbers or numpy arrays."""
        return ((v % (1 << 31)) * 40503 // 16) % self.tasks // (self.tasks // self.groups(tier))


@dataclass(frozen=True)
class Tiered:
    """A root ordering with a tree of local orderings under it."""

    root: Ordering
    tree: TierTree
    tier: str | None

    def ordered(self) -> list[tuple[str, Ordering]]:
        """Tiers that have an ordering, outermost first."""
        return [(t, self.tree.order[t]) for t in TIERS if t in self.tree.order]

    def extends(self, base: Ordering) -> bool:
        """Whether the classes of the root are those of base."""
        return (self.root.name, self.root.parameter) == (base.name, base.parameter)

    @property
    def label(self) -> str:
        return self.tier or "fifo"


def tiered(root: Ordering, tier: str | None, tree: TierTree | None = None) -> Tiered:
    """root with the distance order at one tier, or none anywhere (first in, first out)."""
    tree = tree or TierTree()
    if tier not in (None, *TIERS):
        raise ValueError(f"tier is one of {TIERS}, or None")
    order = {tier: by_distance()} if tier else {}
    return Tiered(root, TierTree(tree.hosts, tree.sockets_per_host, tree.tasks_per_socket, order), tier)


def tiered_tree(root: Ordering, tree: TierTree) -> Tiered:
    """root with any orderings at any tiers of the tree; outer tiers decide first."""
    unknown = set(tree.order) - set(TIERS)
    if unknown:
        raise ValueError(f"no tiers: {sorted(unknown)}")
    return Tiered(root, tree, next((t for t in TIERS if t in tree.order), None))


def example_tree(delta=3) -> Tiered:
    """Distance bands at the root, distance order in each socket, nothing elsewhere."""
    return tiered(distance_bands(delta), "socket")


def all_variants(delta=3, k: int = 1, tree: TierTree | None = None) -> dict[str, Tiered]:
    """The twelve configurations: three roots, each without and with the distance order at a tier; and the distance order itself."""
    roots = {"delta": distance_bands(delta), "kla": level_bands(k), "chaotic": chaotic()}
    out = {f"{name}_{tier or 'fifo'}": tiered(root, tier, tree) for name, root in roots.items() for tier in (None, "task", "socket", "host")}
    return out | {"dijkstra": tiered(by_distance(), None, tree)}
