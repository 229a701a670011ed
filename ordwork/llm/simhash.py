"""SimHash near-duplicates by the generalised pigeonhole principle.

A text's fingerprint has a bit set where more than half of the hashes of its word shingles have it. Two fingerprints link
if they differ in at most DISTANCE bits, and a document's component is the smallest id that links reach.

The 64 bits are cut into m parts, correlated bits together. If thresholds t_i >= -1 satisfy sum(t_i + 1) = DISTANCE + 1,
fingerprints within DISTANCE differ by at most t_i in some part i (else they'd differ in at least sum(t_i + 1) bits). So
each fingerprint is indexed by its bits in every part with t_i >= 0, probes all values within t_i of them, and
what meets is verified by the whole distance inside the join. m and the thresholds minimise probes plus candidates,
estimated from bit and collision counts over all fingerprints, by dynamic programming; with more data, fewer
and longer parts with larger thresholds win, which holds candidates near the size of the data.

Copies cost nothing: only distinct fingerprints are indexed, each with its smallest id. A pair is given in the
first part that finds it, so no pair comes twice.

Defined results: null texts and texts without words have the fingerprint zero and link as any other; a text of
fewer words than a shingle has its whole sequence as one shingle; repeated rows and ids link by distance 0; null ids
take part, but are never a component's smallest id unless all its ids are null; other columns pass through.
"""

from __future__ import annotations

from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordwork.llm.common import Scratch, map_batches
from ordwork.llm.components import components

BITS = 64
DISTANCE = 3
SEED = 42
#: Shingles are counted in portions of so many, to bound memory for very long texts.
PORTION = 50_000
#: Cost of a probe row, which is shuffled and sorted, against a candidate, which is only compared; low, as candidates
#: grow with the square of the data and real buckets are fuller than counts of random ones.
PROBE_COST = 3.0
MOST_PARTS = 8


def fingerprint(raw: bytes, width: int) -> int:
    """The fingerprint of UTF-8 text, unsigned; words are runs of bytes other than ASCII white space."""
    words = raw.lower().split()  # on bytes, lower() and split() know ASCII only
    if not words:
        return 0
    joined = b" ".join(words)
    size = np.fromiter(map(len, words), np.int64, len(words))
    first = np.concatenate(([0], np.cumsum(size + 1)[:-1]))
    last = first + size
    n = max(len(words) - width + 1, 1)
    starts, ends = first[:n].tolist(), last[min(width, len(words)) - 1 :].tolist()
    digest = xxhash.xxh64_intdigest
    ones = np.zeros(BITS, np.int64)
    for at in range(0, n, PORTION):
        hashes = np.array([digest(joined[a:b], SEED) for a, b in zip(starts[at : at + PORTION], ends[at : at + PORTION], strict=True)], np.uint64)
        ones += counted(hashes)
    return int(np.packbits(ones * 2 > n, bitorder="little").view(np.uint64)[0])


def counted(hashes: np.ndarray) -> np.ndarray:
    """How many of the hashes have each bit set."""
    bits = np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    out = np.zeros(BITS, np.int64)
    for at in range(0, len(bits), 255):  # sums of up to 255 fit a byte, which numpy adds fastest
        out += np.add.reduce(bits[at : at + 255], axis=0, dtype=np.uint8)
    return out


def fingerprints(docs: DataFrame, text: str = "text", key: str = "doc_id", width: int = 3) -> DataFrame:
    """key and fp (long) of every row; one pass, no shuffle."""
    kind = dict(docs.dtypes)[key]

    def each(batch):
        fps = [fingerprint((t.as_py() or "").encode(), width) for t in batch.column(1)]
        yield {"key": batch.column(0), "fp": np.array(fps, np.uint64).view(np.int64)}

    return map_batches(docs.select(F.col(key).alias("key"), F.col(text).alias("text")), each, f"key {kind}, fp bigint").withColumnRenamed("key", key)


def bit_statistics(distinct: DataFrame) -> tuple[int, np.ndarray]:
    """(number of fingerprints, 64 x 64 counts of both bits set): sums over all of them, of fixed size."""

    def each(batch):
        fps = batch.column(0).to_numpy()
        bits = np.unpackbits(fps.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(np.float64)
        both = (bits.T @ bits).astype(np.int64).ravel()
        yield {"cell": np.append(np.arange(BITS * BITS), -1), "n": np.append(both, len(fps))}

    sums = map_batches(distinct.select("fp"), each, "cell int, n bigint").groupBy("cell").agg(F.sum("n").alias("n")).toPandas()
    if not len(sums):
        return 0, np.zeros((BITS, BITS))
    sums = sums.set_index("cell")["n"].sort_index()
    return int(sums.loc[-1]), sums.drop(-1).to_numpy().reshape(BITS, BITS).astype(float)


def group_bits(n: int, both: np.ndarray, m: int) -> list[list[int]]:
    """Cut the bits into m parts of like size: each part grows by the bit that correlates most with it."""
    p = np.diag(both) / max(n, 1)
    spread = np.sqrt(np.maximum(p * (1 - p), 1e-12))
    related = np.abs((both / max(n, 1) - np.outer(p, p)) / np.outer(spread, spread))
    free, parts = set(range(BITS)), []
    for k in range(m):
        size = len(free) // (m - k)
        part = [min(free, key=lambda b: (abs(p[b] - 0.5), b))]  # starts from the most even bit
        free.remove(part[0])
        while len(part) < size:
            best = max(free, key=lambda b: (related[b, part].sum(), -b))
            part.append(best)
            free.remove(best)
        parts.append(sorted(part))
    return parts


def within(part: list[int], p: np.ndarray, most: int) -> np.ndarray:
    """Chance that two fingerprints differ in at most 0, 1, .. most bits of a part, were its bits independent."""
    out = np.zeros(most + 1)
    out[0] = 1.0
    for b in part:
        d = 2 * p[b] * (1 - p[b])
        out[1:] = out[1:] * (1 - d) + out[:-1] * d
        out[0] *= 1 - d
    return np.cumsum(out)


def allocate(costs: list[list[float]], total: int) -> tuple[float, list[int]]:
    """Thresholds t_i with sum(t_i + 1) = total at least cost; costs[i][t] for t >= 0, and t = -1 is free."""
    best = {0: (0.0, [])}
    for row in costs:
        after: dict[int, tuple[float, list[int]]] = {}
        for used, (cost, chosen) in best.items():
            for e in range(total - used + 1):
                if e > len(row):
                    break
                c = cost + (row[e - 1] if e else 0.0)
                if used + e not in after or c < after[used + e][0]:
                    after[used + e] = (c, [*chosen, e - 1])
        best = after
    return best[total]


def plan(distinct: DataFrame, distance: int) -> list[tuple[list[int], int]]:
    """(bits, threshold) of each part that is used."""
    n, both = bit_statistics(distinct)
    p = np.diag(both) / max(n, 1)
    choices = {m: group_bits(n, both, m) for m in range(2, min(distance + 1, MOST_PARTS) + 1)}
    masks = [(m, k, mask_of(part)) for m, parts in choices.items() for k, part in enumerate(parts)]
    values = distinct.select(F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.col("fp").bitwiseAND(F.lit(mask)).alias("v")) for i, (_, _, mask) in enumerate(masks)])).alias("x")).select("x.*")
    met = values.groupBy("i", "v").count().groupBy("i").agg(F.sum(F.col("count").cast("double") * (F.col("count") - 1) / 2).alias("pairs"))
    pairs = {r["i"]: r["pairs"] for r in met.collect()}  # one row a part
    found = []
    for m, parts in choices.items():
        costs = []
        for i, (mm, k, _) in enumerate(masks):
            if mm == m:
                chance = within(parts[k], p, distance)
                # collisions as counted, carried on to larger thresholds by the chances
                each = [max(pairs.get(i, 0.0) * chance[t] / max(chance[0], 1e-300), n * n / 2 * chance[t]) for t in range(distance + 1)]
                costs.append([PROBE_COST * n * sum(comb(len(parts[k]), r) for r in range(t + 1)) + each[t] for t in range(distance + 1)])
        cost, thresholds = allocate(costs, distance + 1)
        found.append((cost, m, list(zip(parts, thresholds, strict=True))))
    return [x for x in min(found)[2] if x[1] >= 0]


def mask_of(bits) -> int:
    return int(np.array([sum(1 << b for b in bits)], np.uint64).view(np.int64)[0])


def links(distinct: DataFrame, distance: int = DISTANCE, parts: list[tuple[list[int], int]] | None = None) -> DataFrame:
    """(a, b): pairs of different fingerprints within the distance, a < b, each once."""
    parts = plan(distinct, distance) if parts is None else parts
    keep = [mask_of(bits) for bits, _ in parts]
    indexed = F.array(*[F.struct(F.lit(i).alias("part"), F.col("fp").bitwiseAND(F.lit(k)).alias("v")) for i, k in enumerate(keep)])
    near = []
    for i, (bits, t) in enumerate(parts):
        flips = F.array(*[F.lit(mask_of(c)) for r in range(t + 1) for c in combinations(bits, r)])
        near.append(probe(flips, i, keep[i]))
    index = distinct.select(F.col("fp").alias("b"), F.explode(indexed).alias("x")).select("b", "x.part", "x.v")
    probes = distinct.select(F.col("fp").alias("a"), F.explode(F.concat(*near)).alias("x")).select("a", "x.part", "x.v")
    differ = F.col("a").bitwiseXOR(F.col("b"))
    earlier = F.lit(False)
    first = F.lit(True)
    for i, (k, (_, t)) in enumerate(zip(keep, parts, strict=True)):
        first = first & ((F.col("i.part") != i) | ~earlier)
        earlier = earlier | (F.bit_count(differ.bitwiseAND(F.lit(k))) <= t)
    on = (F.col("p.part") == F.col("i.part")) & (F.col("p.v") == F.col("i.v")) & (F.col("a") < F.col("b")) & (F.bit_count(differ) <= distance) & first
    return probes.alias("p").join(index.alias("i"), on).select("a", "b")


def probe(flips, part: int, keep: int):
    return F.transform(flips, lambda f: F.struct(F.lit(part).alias("part"), F.col("fp").bitwiseAND(F.lit(keep)).bitwiseXOR(f).alias("v")))


def jaccard(one: bytes, other: bytes, width: int) -> float:
    """Similarity of the sets of word shingles of two texts; two texts without words are equal."""
    sets = []
    for raw in (one, other):
        words = raw.lower().split()
        sets.append({b" ".join(words[k : k + width]) for k in range(max(len(words) - width + 1, 1))} if words else set())
    both = len(sets[0] & sets[1])
    return both / (len(sets[0]) + len(sets[1]) - both) if sets[0] or sets[1] else 1.0


def verified(found: DataFrame, distinct: DataFrame, docs: DataFrame, text: str, key: str, width: int, similarity: float) -> DataFrame:
    """The links that differ in at most DISTANCE bits, and of the others those whose texts are similar enough.

    Each fingerprint is represented by the text of its smallest id; only texts of linked fingerprints are shuffled.
    """
    sure = F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= DISTANCE
    unsure = found.where(~sure)
    ends = unsure.select(F.col("a").alias("fp")).union(unsure.select("b")).distinct()
    texts = docs.where(F.col(key).isNotNull()).select(F.col(key).alias("least"), F.col(text).alias("text"))
    used = distinct.join(ends, "fp", "left_semi").join(texts, "least").groupBy("fp").agg(F.min("text").alias("text"))
    both = unsure.join(used.select(F.col("fp").alias("a"), F.col("text").alias("one")), "a").join(used.select(F.col("fp").alias("b"), F.col("text").alias("other")), "b").select("a", "b", "one", "other")

    def each(batch):
        keep = [jaccard((x.as_py() or "").encode(), (y.as_py() or "").encode(), width) >= similarity for x, y in zip(batch.column(2), batch.column(3), strict=True)]
        if any(keep):
            kept = batch.filter(pa.array(keep))
            yield {"a": kept.column(0), "b": kept.column(1)}

    return found.where(sure).union(map_batches(both, each, "a bigint, b bigint"))


def near_duplicates(docs: DataFrame, text: str = "text", key: str = "doc_id", width: int = 3, distance: int = DISTANCE, verify: tuple[int, float] | None = None) -> DataFrame:
    """key, fp (long), component_id of every row.

    verify = (words, similarity): links of more than DISTANCE bits also need that Jaccard similarity of word shingles;
    closer ones are taken unseen, so what must be similar by text goes through near_dedup instead.
    """
    scratch = Scratch(docs.sparkSession, "simhash")
    marked = scratch.save(fingerprints(docs, text, key, width), "marked")
    distinct = scratch.save(marked.groupBy("fp").agg(F.min(key).alias("least")), "distinct")
    found = links(distinct, distance)
    if verify:
        found = verified(scratch.save(found, "links"), distinct, docs, text, key, *verify)
    roots = components(scratch, found.toDF("u", "v"))
    named = distinct.join(roots.select(F.col("node").alias("fp"), "root"), "fp", "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    least = named.groupBy("root").agg(F.min("least").alias("component_id"))
    of = scratch.save(named.join(least, "root").select("fp", "component_id"), "of")
    return marked.join(of, "fp").select(key, "fp", "component_id")


def keep_one(docs: DataFrame, text: str = "text", key: str = "doc_id", width: int = 3, distance: int = DISTANCE, verify: tuple[int, float] | None = None) -> DataFrame:
    """docs without those whose component holds a smaller id; rows with a null id stay, rows that repeat an id are one document."""
    found = near_duplicates(docs, text, key, width, distance, verify)
    later = found.where(F.col(key).isNotNull() & (F.col("component_id") < F.col(key))).select(F.col(key).alias("__key")).distinct()
    return docs.join(later, F.col(key) == F.col("__key"), "left_anti")
