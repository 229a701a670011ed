"""Near-duplicates among embeddings with a forest of random-projection trees.

Each tree splits the unit vectors again and again by a random direction at the emptiest of a few random
thresholds; vectors close to a threshold go to both sides (spill). Vectors are compared, in double
precision, within the leaves of all trees, pairs with cosine >= the limit are links, and links are united to components.

The first levels are fitted on a sample of at most about SAMPLE distinct vectors, chosen by hash; every vector is indexed.
Trees are added until vectors planted at exactly the limit from those of the sample would miss each other in all of them with a chance of
at most MISS. A leaf that all data overfills is split further by a subtree fitted on a share of its own vectors, and so are the
leaves of that, each round a join of memberships with the subtrees: neither a task nor the driver holds more than samples. What no direction
separates is cut into blocks and each pair of blocks is a group of its own, so no group exceeds 2 * block vectors and no pair of the leaf is
lost. Equal vectors are one, with a count. A pair that meets in several leaves counts in the first of them: each row carries
the leaves of its vector. Leaves give counts for each vector and a spanning forest of their links, never all pairs.

Defined results: vectors that are null, zero, or hold null or non-finite components link with nothing and stay alone; vectors of
different lengths don't link, those of each length are compared with each other; equal vectors link with each other; rows that repeat an id are
vectors of their own that share their result; ids are integers; other columns don't matter, labels included.
"""

from __future__ import annotations

import pickle
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, FloatType

from ordwork.llm.common import Scratch, map_batches
from ordwork.llm.components import components

LIMIT = 0.9
#: Chance that a pair at the limit meets in no tree, on which the number of trees rests.
MISS = 0.02
LEAF = 500
#: Half the width of the spill, in typical distances of linked vectors along a direction.
SPILL = 0.35
DIRECTIONS = 4
THRESHOLDS = 8
SAMPLE = 20_000
#: Vectors on which the subtree of an overfull leaf is fitted (expected number), and about how many leaves it gets.
LEAF_SAMPLE, FAN = 2_000, 16
#: Vectors of the sample that a leaf of a fitted tree holds at least.
LEAST = 8.0
BLOCK = 2_000
SHARES = 1_000_003


@lru_cache(1 << 14)
def direction_of(seed: int, dims: int) -> np.ndarray:
    """The unit vector that a seed names, so that models hold seeds only."""
    direction = np.random.default_rng(seed).standard_normal(dims)
    return direction / np.linalg.norm(direction)


class Tree:
    """Nested tuples (seed of the direction, threshold, left, right) or numbers of leaves."""

    def __init__(self, rng, unit: np.ndarray, leaf: float, limit: float):
        self.margin = SPILL * np.sqrt(2 * max(1 - limit, 0) / unit.shape[1])
        self.leaves = 0
        self.root = self.split(rng, unit, leaf)

    def split(self, rng, x: np.ndarray, leaf: float):
        if len(x) > leaf:
            best = None
            for seed in rng.integers(1 << 62, size=DIRECTIONS).tolist():
                at = np.sort(x @ direction_of(seed, x.shape[1]))
                cuts = np.quantile(at, rng.uniform(0.25, 0.75, THRESHOLDS))
                mass = np.searchsorted(at, cuts + self.margin, "right") - np.searchsorted(at, cuts - self.margin)
                k = int(mass.argmin())
                if best is None or mass[k] < best[0]:
                    best = (mass[k], float(cuts[k]), seed)
            _, cut, seed = best
            at = x @ direction_of(seed, x.shape[1])
            left, right = x[at <= cut + self.margin], x[at >= cut - self.margin]
            if max(len(left), len(right)) < 0.95 * len(x):  # else nothing here separates them
                return seed, cut, self.split(rng, left, leaf), self.split(rng, right, leaf)
        self.leaves += 1
        return self.leaves - 1

    def place(self, unit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, leaf) of every membership."""
        rows, leaves, todo = [], [], [(self.root, np.arange(len(unit)))]
        while todo:
            node, at = todo.pop()
            if isinstance(node, int):
                rows.append(at)
                leaves.append(np.full(len(at), node))
            elif len(at):
                seed, cut, left, right = node
                p = unit[at] @ direction_of(seed, unit.shape[1])
                todo += [(left, at[p <= cut + self.margin]), (right, at[p >= cut - self.margin])]
        return np.concatenate(rows), np.concatenate(leaves)

    def meeting(self, unit: np.ndarray, rng, limit: float) -> float:
        """Share of vectors that share a leaf with one planted at the limit from them."""
        noise = rng.standard_normal(unit.shape)
        noise -= (noise * unit).sum(1)[:, None] * unit
        noise /= np.maximum(np.linalg.norm(noise, axis=1), 1e-300)[:, None]
        here, there = (r * self.leaves + y for r, y in (self.place(unit), self.place(limit * unit + np.sqrt(max(1 - limit**2, 0)) * noise)))
        return len(np.unique(here[np.isin(here, there)] // self.leaves)) / len(unit)


class Forest:
    """Trees for vectors of one length; ``total`` is about how many of them there are."""

    def __init__(self, unit: np.ndarray, total: float, leaf: int, limit: float, miss: float):
        self.trees, missed, dims = [], 1.0, unit.shape[1]
        wanted = max(leaf * len(unit) / max(total, 1), LEAST)
        # levels that all data have for each one fitted here
        deeper = max(1.0, np.log(max(total / leaf, 1.0)) / max(np.log(len(unit) / wanted), 1e-9)) if len(unit) > wanted else 1.0
        while missed > miss:
            rng = np.random.default_rng((dims, len(self.trees)))
            self.trees.append(Tree(rng, unit, wanted, limit))
            missed *= 1 - max(self.trees[-1].meeting(unit[:2000], rng, limit) ** deeper, 0.02)

    def place(self, unit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, leaf) of every membership, by row."""
        rows, leaves, base = [], [], unit.shape[1] << 32
        for tree in self.trees:
            r, y = tree.place(unit)
            rows.append(r)
            leaves.append(y + base)
            base += tree.leaves
        row, leaf = np.concatenate(rows), np.concatenate(leaves)
        order = np.lexsort((leaf, row))
        return row[order], leaf[order]


def matrix(column) -> np.ndarray:
    """Rows of an Arrow list column of one length as doubles of norm 1."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    x = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1)
    x = x / np.abs(x).max(1, initial=1e-300)[:, None]  # so that norms neither overflow nor vanish
    return x / np.linalg.norm(x, axis=1)[:, None]


def lengths(column) -> np.ndarray:
    return pc.list_value_length(column).to_numpy(zero_copy_only=False)


def finer(leaf: int, sub: np.ndarray) -> np.ndarray:
    """Numbers for the leaves of a leaf's subtree: 64 hash bits (leaves that share one by chance would be one, and still compared whole)."""
    h = (np.array([leaf]).view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) ^ (sub.astype(np.uint64) + np.uint64(1)) * np.uint64(0xD6E8FEB86659FD93)
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xBF58476D1CE4E5B9)
    return (h ^ (h >> np.uint64(29))).view(np.int64)


def single(vector: str, frame: DataFrame):
    """The column as an array of its own precision: float stays float, all else is double."""
    kind = frame.schema[vector].dataType
    return F.col(vector).cast("array<float>" if isinstance(kind, ArrayType) and isinstance(kind.elementType, FloatType) else "array<double>")


def usable(vectors: DataFrame, key: str, vector: str) -> DataFrame:
    """(vec, least, n): distinct finite vectors with the smallest id and number of their copies."""
    good = F.col("vec").isNotNull() & ~F.exists("vec", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists("vec", lambda x: x != 0)
    rows = vectors.where(F.col(key).isNotNull()).select(F.col(key).cast("long").alias("id"), single(vector, vectors).alias("vec")).where(good)
    return rows.groupBy("vec").agg(F.min("id").alias("least"), F.count("*").alias("n"))


def first_here(p: np.ndarray, q: np.ndarray, earlier: np.ndarray, other: np.ndarray) -> np.ndarray:
    """Which pairs of rows (p, q) share no earlier leaf; the rows of both tables are padded with numbers of their own."""
    keep = np.ones(len(p), bool)
    for lo in range(0, len(p), 100_000):
        a, b = earlier[p[lo : lo + 100_000]], other[q[lo : lo + 100_000]]
        for k in range(a.shape[1]):
            keep[lo : lo + 100_000] &= ~(a[:, k, None] == b).any(1)
    return keep


def leaf_links(table: pa.Table, limit: float) -> pa.Table:
    """Links of one group: (a, b, null) of a spanning forest, and (a, null, n) the number of vectors linked with a."""
    x, here = matrix(table["vec"]), table["leaf"][0].as_py()
    ids, n, part = (table[c].to_numpy() for c in ("least", "n", "part"))
    two = table["one"][0].as_py() != table["other"][0].as_py()
    left = np.flatnonzero(part != 1)
    right = np.flatnonzero(part != 0) if two else left
    # leaves before this one; pairs that share one were counted there
    column = table["leaves"].combine_chunks()
    of, y = np.repeat(np.arange(len(ids)), lengths(column)), column.flatten().to_numpy()
    of, y = of[y < here], y[y < here]
    at = np.arange(len(of)) - np.searchsorted(of, of)
    earlier = np.full((len(ids), int(at.max(initial=-1)) + 1), -1, np.int64)
    earlier[of, at] = np.unique(y, return_inverse=True)[1] if len(y) else y
    other = np.where(earlier < 0, -2, earlier)
    count, root, step = np.zeros(len(ids), np.int64), np.arange(len(ids)), 1000
    for i in range(0, len(left), step):
        for j in range(0 if two else i, len(right), step):
            a, b = left[i : i + step], right[j : j + step]
            p, q = np.nonzero(x[a] @ x[b].T >= limit)
            p, q = a[p], b[q]
            if not two:
                p, q = p[p < q], q[p < q]
            keep = first_here(p, q, earlier, other)
            p, q = p[keep], q[keep]
            count += np.bincount(p, n[q], len(ids)).astype(np.int64) + np.bincount(q, n[p], len(ids)).astype(np.int64)
            while True:  # hook the roots of linked rows onto the smaller, until all links lie within one
                u, v = root[p], root[q]
                if (u == v).all():
                    break
                np.minimum.at(root, np.maximum(u, v), np.minimum(u, v))
                while (root != root[root]).any():
                    root = root[root]
    linked, inner = np.flatnonzero(count), np.flatnonzero(root != np.arange(len(ids)))
    none = lambda k: [None] * len(k)
    return pa.table({
        "a": pa.array(np.concatenate([ids[linked], ids[inner]]), pa.int64()),
        "b": pa.array(none(linked) + ids[root[inner]].tolist(), pa.int64()),
        "n": pa.array(count[linked].tolist() + none(inner), pa.int64()),
    })


def refine(scratch: Scratch, placed: DataFrame, leaf: int, limit: float, block: int) -> DataFrame:
    """placed with the overfull leaves replaced by leaves of subtrees, as long as any can be split."""

    def fit(table: pa.Table) -> pa.Table:
        name, n, unit = table["leaf"][0].as_py(), table["size"][0].as_py(), matrix(table["vec"])
        tree = Tree(np.random.default_rng(name & (1 << 63) - 1), unit, max(leaf * len(unit) / n, len(unit) / FAN, LEAST), limit) if len(unit) > 1 else None
        split = tree is not None and tree.leaves > 1
        return pa.table({"leaf": pa.array([name] * split, pa.int64()), "tree": pa.array([pickle.dumps(tree)] * split, pa.binary())})

    def move(batch):
        names, vecs, least = batch.column(0).to_numpy(), batch.column(1), batch.column(2)
        for name in np.unique(names).tolist():
            at = np.flatnonzero(names == name)
            tree = pickle.loads(batch.column(3)[int(at[0])].as_py())
            row, sub = tree.place(matrix(vecs.take(pa.array(at))))
            yield {"least": least.to_numpy()[at[row]], "old": np.full(len(row), name), "leaf": finer(name, sub)}

    fresh = placed.select("least", F.explode("leaves").alias("leaf"))
    while True:
        over = scratch.save(fresh.groupBy("leaf").agg(F.count("*").alias("size")).where(F.col("size") > 2 * block), "over")
        if over.isEmpty():
            return placed
        inside = placed.select("vec", "least", F.explode("leaves").alias("leaf")).join(over, "leaf")
        share = F.pmod(F.xxhash64("least", "leaf"), F.lit(SHARES)) < F.lit(SHARES * LEAF_SAMPLE) / F.col("size")
        models = scratch.save(inside.where(share).groupBy("leaf").applyInArrow(fit, "leaf bigint, tree binary"), "models")
        if models.isEmpty():
            return placed
        split = inside.join(models, "leaf").select("leaf", "vec", "least", "tree")
        fresh = scratch.save(map_batches(split, move, "least bigint, old bigint, leaf bigint"), "moved")
        moves = fresh.groupBy("least").agg(F.collect_set("old").alias("old"), F.collect_set("leaf").alias("new"))  # the memberships of one vector
        leaves = F.when(F.col("new").isNull(), F.col("leaves")).otherwise(F.array_union(F.array_except("leaves", "old"), F.col("new")))
        placed = scratch.save(placed.join(moves, "least", "left").select("vec", "least", "n", leaves.alias("leaves")), "placed")


def near_vectors(vectors: DataFrame, vector: str = "embedding", key: str = "vec_id", limit: float = LIMIT, miss: float = MISS, leaf: int = LEAF, sample: int = SAMPLE, block: int = BLOCK) -> DataFrame:
    """key, n_links, component_id of every row."""
    spark, scratch = vectors.sparkSession, Scratch(vectors.sparkSession, "vectors")
    distinct = scratch.save(usable(vectors, key, vector), "distinct")
    total = distinct.count()
    # a share by hash, whose expected size is the bound; then fitted on the driver
    chosen = distinct.where(F.pmod(F.xxhash64("vec"), F.lit(SHARES)) < int(SHARES * min(1.0, sample / max(total, 1)) + 1)).orderBy("least").limit(2 * sample)
    drawn = chosen.select("vec").toArrow()["vec"].combine_chunks()
    dims = lengths(drawn)
    forests = {int(d): Forest(matrix(drawn.take(pa.array(np.flatnonzero(dims == d)))), total * (dims == d).mean(), leaf, limit, miss) for d in np.unique(dims)}
    shared = spark.sparkContext.broadcast(forests)  # bounded by the sample

    def put(batch):
        dims = lengths(batch.column(0))
        for d in np.unique(dims).tolist():
            part = batch.take(pa.array(np.flatnonzero(dims == d)))
            if d in shared.value:
                row, y = shared.value[d].place(matrix(part.column(0)))
            else:  # a length too rare for the sample is one leaf
                row, y = np.arange(len(part)), np.full(len(part), d << 32)
            starts = pa.array(np.searchsorted(row, np.arange(len(part) + 1)), pa.int32())
            yield {"vec": part.column(0), "least": part.column(1), "n": part.column(2), "leaves": pa.ListArray.from_arrays(starts, pa.array(y, pa.int64()))}

    kind = distinct.schema["vec"].dataType.simpleString()
    placed = scratch.save(map_batches(distinct.select("vec", "least", "n"), put, f"vec {kind}, least bigint, n bigint, leaves array<bigint>"), "placed")
    placed = refine(scratch, placed, leaf, limit, block)
    sizes = placed.select(F.explode("leaves").alias("leaf")).groupBy("leaf").count()
    blocks = scratch.save(sizes.where(F.col("count") > 2 * block).select("leaf", F.ceil(F.col("count") / block).alias("blocks")), "blocks")
    members = placed.select("*", F.explode("leaves").alias("leaf")).join(blocks, "leaf", "left").withColumn("blocks", F.coalesce("blocks", F.lit(1)))
    members = members.withColumn("own", F.pmod(F.xxhash64("least"), "blocks")).select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("j"))
    dealt = members.select(
        F.size("vec").alias("dims"), "leaf", F.least("own", "j").alias("one"), F.greatest("own", "j").alias("other"),
        F.when(F.col("own") < F.col("j"), 0).when(F.col("own") > F.col("j"), 1).otherwise(2).alias("part"), "least", "n", "vec", "leaves",
    )
    linked = dealt.groupBy("dims", "leaf", "one", "other").applyInArrow(lambda t: leaf_links(t, limit), "a bigint, b bigint, n bigint")
    linked = scratch.save(linked, "linked")
    roots = components(scratch, linked.where("b is not null").select(F.col("a").alias("u"), F.col("b").alias("v")))
    counts = linked.where("n is not null").groupBy("a").agg(F.sum("n").alias("others"))
    named = distinct.join(counts, distinct.least == counts.a, "left").join(roots, distinct.least == roots.node, "left")
    named = named.select("vec", "least", F.coalesce("root", "least").alias("root"), (F.coalesce("others", F.lit(0)) + F.col("n") - 1).alias("n_links"))
    lowest = named.groupBy("root").agg(F.min("least").alias("component_id"))
    of = scratch.save(named.join(lowest, "root").select("vec", "n_links", "component_id"), "of")
    rows = vectors.select(F.col(key), single(vector, vectors).alias("__vec"))
    out = rows.join(of, (F.col("__vec") == F.col("vec")) & F.col(key).isNotNull(), "left")
    return out.select(key, F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", F.col(key).cast("long")).alias("component_id"))
