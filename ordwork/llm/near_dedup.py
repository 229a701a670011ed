"""Near-duplicates by the Jaccard similarity of word shingles, exactly: no pair of similar texts is missed or assumed.

Texts of equal words (case and white space aside) are folded by 128 hash bits. SimHash comes first: texts whose fingerprints link as in
`simhash` are compared by their texts, and what is similar is one component from then on. It holds most near copies, not all, so
an exact search follows for pairs of texts that still lie in different components:

* Two sets of similarity t or more share at least t n shingles of each. A shingle that lies in one component only can't be shared across
  components, so a text of which less than t n shingles lie in several is settled. To see which do, 48 bits of each shingle travel in
  packed, sorted blocks, a group of blocks for each range of values; what is found is broadcast as a bit set of bounded size, which
  may let texts pass wrongly but never holds one back. Near copies that SimHash joined, and texts unlike others, end here.
* The shingles of the other texts are ordered, common ones last; of two similar sets the first n - ceil(t n) + 1 shingles of each share one, and where the
  first shared shingle stands bounds the overlap. So texts are indexed by these prefixes only. SKETCH words of parities of the set bound the
  difference from below in the join itself. Each pair that meets within the bounds is verified by both texts.

Only components are wanted, so groups of many similar texts need not be compared pair by pair: in the first rounds
the texts of a bucket are compared with a few of its texts, drawn by hash; after that all pairs that meet and still lie in different
components are compared. Every pair that is left out has both ends in one component already.

Defined results: null texts and texts without words are copies of each other; a text of fewer words than a shingle has its
whole sequence as one shingle; repeated rows are copies; null ids take part, but are never a component's smallest id
unless all its ids are null.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordwork.llm import bloom, simhash
from ordwork.llm.common import Scratch, map_batches
from ordwork.llm.components import components
from ordwork.llm.simhash import SEED, jaccard

#: Texts from which frequent shingles are counted, at most so many of which are told to the workers. It only orders shingles.
SAMPLE, MOST_COMMON, LEAST_COUNT = 20_000, 100_000, 3
#: Bits of a shingle that are looked at to tell which lie in several components, shingles packed at a time, shingles that a task holds of one range, least number of ranges.
KEY_BITS, PACKED, HELD, LEAST_RANGES = 48, 1 << 20, 4 << 20, 1024
#: 64-bit words of a set's parities.
SKETCH = 8
#: Rounds of comparison with drawn texts, and how many are drawn for each group of buckets with the same texts.
ROUNDS, DRAWN = 2, 8
#: Slack of bounds worked out in floating point; it only lets more candidates through.
SLACK = 1e-6


def shingles(raw: bytes, width: int) -> np.ndarray:
    """Hashes of the distinct word shingles, sorted; words as in simhash.fingerprint."""
    words = raw.lower().split()
    digest = xxhash.xxh64_intdigest
    found = {digest(b" ".join(words[k : k + width]), SEED) for k in range(max(len(words) - width + 1, 1))} if words else ()
    return np.sort(np.fromiter(found, np.uint64, len(found)).view(np.int64))


def marks(docs: DataFrame, text: str, key: str) -> DataFrame:
    """key, h (128 hash bits of the words), r (a number of the row), text."""
    kind = dict(docs.dtypes)[key]

    def each(batch):
        h = [xxhash.xxh3_128_digest(b" ".join((x.as_py() or "").encode().lower().split())) for x in batch.column(1)]
        yield {"key": batch.column(0), "h": h, "text": batch.column(1)}

    rows = map_batches(docs.select(F.col(key).alias("key"), F.col(text).alias("text")), each, f"key {kind}, h binary, text string")
    return rows.withColumn("r", F.monotonically_increasing_id())


def keys_of(own: np.ndarray) -> np.ndarray:
    return own.view(np.uint64) & np.uint64((1 << KEY_BITS) - 1)


def packed(keys: np.ndarray, of: np.ndarray, ranges: int):
    """Blocks (range, data) of keys with the hash of their component: sorted, differences and hashes of 32 bits where they fit."""
    order = np.argsort(keys, kind="stable")
    keys, of = keys[order], of[order]
    shift = np.uint64(KEY_BITS - (ranges.bit_length() - 1))
    which = (keys >> shift).astype(np.int64)
    cuts = np.flatnonzero(np.concatenate(([True], which[1:] != which[:-1])))
    out: dict[str, list] = {"range": which[cuts], "data": []}
    for a, b in zip(cuts, np.append(cuts[1:], len(keys)), strict=True):
        step = np.diff(keys[a:b], prepend=np.uint64(which[a]) << shift)
        kind = np.uint32 if int(step.max()) < 1 << 32 else np.uint64
        out["data"].append(bytes([np.dtype(kind).itemsize]) + step.astype(kind).tobytes() + of[a:b].tobytes())
    return out


def unpacked(start: int, data: bytes) -> tuple[np.ndarray, np.ndarray]:
    size = data[0]
    n = (len(data) - 1) // (size + 4)
    step = np.frombuffer(data, f"u{size}", n, 1).astype(np.uint64)
    return np.cumsum(step) + np.uint64(start), np.frombuffer(data, np.uint32, n, 1 + n * size)


def across_components(texts: DataFrame, width: int) -> DataFrame:
    """k: KEY_BITS of the shingles that lie in several components; texts (t, c, text)."""
    total = texts.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("n")).first()["n"] // 4
    ranges = max(LEAST_RANGES, 1 << int(total // HELD).bit_length())

    def pack(batches):
        schema = pa.schema([("range", pa.int64()), ("data", pa.binary())])
        keys, of, n = [], [], 0

        def made():
            got = packed(np.concatenate(keys), np.concatenate(of), ranges)
            return pa.RecordBatch.from_arrays([pa.array(got["range"], pa.int64()), pa.array(got["data"], pa.binary())], schema=schema)

        for batch in batches:
            for c, x in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                own = keys_of(shingles((x.as_py() or "").encode(), width))
                keys.append(own)
                of.append(np.full(len(own), xxhash.xxh32_intdigest(c.to_bytes(8, "little", signed=True), SEED), np.uint32))
                n += len(own)
                if n >= PACKED:
                    yield made()
                    keys, of, n = [], [], 0
        if n:
            yield made()

    def several(key, table):
        start = key[0].as_py() << (KEY_BITS - (ranges.bit_length() - 1))
        parts = [unpacked(start, x.as_py()) for x in table["data"]]
        keys, of = np.concatenate([k for k, _ in parts]), np.concatenate([c for _, c in parts])
        order = np.argsort(keys, kind="stable")
        keys, of = keys[order], of[order]
        first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
        found = keys[first][np.minimum.reduceat(of, first) != np.maximum.reduceat(of, first)]
        return pa.table({"k": pa.array(found.view(np.int64), pa.int64())})

    blocks = texts.select("c", "text").mapInArrow(pack, "range bigint, data binary")
    return blocks.groupBy("range").applyInArrow(several, "k bigint")


def unsettled(texts: DataFrame, shared, width: int, similarity: float) -> DataFrame:
    """The texts (t, c, text) that share enough shingles with other components to be similar to one there."""

    def each(batch):
        keep = []
        for x in batch.column(2):
            own = shingles((x.as_py() or "").encode(), width)
            keep.append(len(own) > 0 and int(bloom.test(shared.value, keys_of(own)).sum()) >= similarity * len(own) - SLACK)
        if any(keep):
            kept = batch.filter(pa.array(keep))
            yield {"t": kept.column(0), "c": kept.column(1), "text": kept.column(2)}

    return map_batches(texts.select("t", "c", "text"), each, "t bigint, c bigint, text string")


def frequent(texts: DataFrame, shared, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, counts) of the most frequent shingles of a sample, of bounded size."""
    share = min(SAMPLE / max(texts.count(), 1), 1.0)
    sampled = texts.where(F.pmod(F.xxhash64("t"), F.lit(1_000_003)) < share * 1_000_003)

    def each(batch):
        for x in batch.column(0):
            own = shingles((x.as_py() or "").encode(), width)
            yield {"s": own[bloom.test(shared.value, keys_of(own))]}

    counts = map_batches(sampled.select("text"), each, "s bigint").groupBy("s").agg(F.count("*").alias("k")).where(F.col("k") >= LEAST_COUNT)
    got = counts.orderBy(F.desc("k"), "s").limit(MOST_COMMON).toPandas().sort_values("s")
    return got["s"].to_numpy(np.int64), got["k"].to_numpy(np.int64)


def sketch(own: np.ndarray) -> np.ndarray:
    """Parities of how many shingles fall on each of SKETCH x 64 bits: two sets differ in at least as many shingles as their sketches in bits."""
    at = (own.view(np.uint64) >> np.uint64(KEY_BITS)).astype(np.int64) % (SKETCH * 64)
    return np.packbits(np.bincount(at, minlength=SKETCH * 64) & 1).view(np.int64)


def prefixes(texts: DataFrame, shared, width: int, similarity: float, common: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """s, t, n, rest, p0..: the shingles in the prefix of each text that other components may hold, how many the text has, how many follow with this one, its sketch."""
    names, counts = common
    words = [f"p{k}" for k in range(SKETCH)]

    def each(batch):
        out: dict[str, list] = {name: [] for name in ("s", "t", "n", "rest", *words)}
        for t, x in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            own = shingles((x.as_py() or "").encode(), width)
            n = len(own)
            hit = bloom.test(shared.value, keys_of(own))
            k = hit.astype(np.int64)
            if len(names):
                at = np.minimum(np.searchsorted(names, own), len(names) - 1)
                k += np.where(names[at] == own, counts[at], 0) * hit
            order = np.lexsort((own, k))[: n - math.ceil(similarity * n - SLACK) + 1]
            at = np.flatnonzero(hit[order])
            out["s"].append(own[order[at]])
            out["t"].append(np.full(len(at), t))
            out["n"].append(np.full(len(at), n, np.int32))
            out["rest"].append((n - at).astype(np.int32))
            for name, word in zip(words, sketch(own), strict=True):
                out[name].append(np.full(len(at), word))
        if out["s"]:
            yield {name: np.concatenate(x) for name, x in out.items()}

    return map_batches(texts.select("t", "text"), each, "s bigint, t bigint, n int, rest int, " + ", ".join(f"{w} bigint" for w in words))


def may_be(x: str, y: str, similarity: float):
    """Whether two texts can be similar if s is the first shingle that they share, by the overlap and by the difference."""
    both = F.col(f"{x}.n") + F.col(f"{y}.n")
    differ = sum((F.bit_count(F.col(f"{x}.p{k}").bitwiseXOR(F.col(f"{y}.p{k}"))) for k in range(SKETCH)), F.lit(0))
    enough = F.least(F.col(f"{x}.rest"), F.col(f"{y}.rest")) >= similarity / (1 + similarity) * both - SLACK
    return enough & (differ <= (1 - similarity) / (1 + similarity) * both + SLACK)


def ordered(x: str, y: str) -> list:
    return [F.least(f"{x}.t", f"{y}.t").alias("a"), F.greatest(f"{x}.t", f"{y}.t").alias("b")]


def with_drawn(index: DataFrame, turn: int, similarity: float) -> DataFrame:
    """(a, b): texts of a bucket and the one drawn for it, where they lie in different components."""
    words = [f"p{k}" for k in range(SKETCH)]
    draw = F.struct(F.xxhash64(F.lit(turn), F.pmod("s", F.lit(DRAWN)), F.col("t")).alias("draw"), "t", "c", "n", "rest", *words)
    drawn = index.groupBy("s").agg(F.min(draw).alias("x"), F.min("c").alias("low"), F.max("c").alias("high")).where("low <> high").select("s", "x.*")
    return index.alias("x").join(drawn.alias("y"), "s").where((F.col("x.c") != F.col("y.c")) & may_be("x", "y", similarity)).select(*ordered("x", "y")).distinct()


def across(index: DataFrame, similarity: float) -> DataFrame:
    """(a, b): all texts that share a bucket, lie in different components and may be similar; no other pair leaves the join."""
    on = (F.col("x.s") == F.col("y.s")) & (F.col("x.c") < F.col("y.c")) & may_be("x", "y", similarity)
    return index.alias("x").join(index.alias("y"), on).select(*ordered("x", "y")).distinct()


def near_fingerprints(scratch: Scratch, texts: DataFrame) -> DataFrame:
    """(a, b): texts whose fingerprints link, by one text of each fingerprint, and that text with the others of its fingerprint."""
    marked = scratch.save(simhash.fingerprints(texts, "text", "t"), "fingerprints")
    distinct = scratch.save(marked.groupBy("fp").agg(F.min("t").alias("least")), "distinct_fingerprints")
    linked = simhash.links(distinct).join(distinct.select(F.col("fp").alias("a"), F.col("least").alias("t1")), "a").join(distinct.select(F.col("fp").alias("b"), F.col("least").alias("t2")), "b")
    inside = marked.join(distinct, "fp").where("t <> least").select(F.col("least").alias("a"), F.col("t").alias("b"))
    return linked.select(F.least("t1", "t2").alias("a"), F.greatest("t1", "t2").alias("b")).union(inside)


def similar(pairs: DataFrame, texts: DataFrame, width: int, similarity: float) -> DataFrame:
    """The pairs whose texts are similar; only texts of pairs are shuffled."""
    ends = pairs.select(F.col("a").alias("t")).union(pairs.select("b")).distinct()
    used = texts.join(ends, "t", "left_semi")
    both = pairs.join(used.select(F.col("t").alias("a"), F.col("text").alias("one")), "a").join(used.select(F.col("t").alias("b"), F.col("text").alias("other")), "b").select("a", "b", "one", "other")

    def each(batch):
        keep = [jaccard((x.as_py() or "").encode(), (y.as_py() or "").encode(), width) >= similarity for x, y in zip(batch.column(2), batch.column(3), strict=True)]
        if any(keep):
            kept = batch.filter(pa.array(keep))
            yield {"a": kept.column(0), "b": kept.column(1)}

    return map_batches(both, each, "a bigint, b bigint")


def similar_components(scratch: Scratch, texts: DataFrame, width: int, similarity: float) -> DataFrame:
    """(node, root) of the texts (t, text) that are similar to another."""

    def named(frame: DataFrame, roots: DataFrame) -> DataFrame:
        return frame.join(roots, F.col("t") == F.col("node"), "left").withColumn("c", F.coalesce("root", "t")).drop("node", "root")

    compared = scratch.save(near_fingerprints(scratch, texts), "near")
    links = scratch.save(similar(compared, texts, width, similarity), "links")
    roots = components(scratch, links.toDF("u", "v"))
    labelled = named(texts, roots)
    keys = scratch.save(across_components(labelled, width), "across")
    shared = bloom.build(keys, keys.count())
    scratch.drop(keys)
    left = scratch.save(unsettled(labelled, shared, width, similarity), "left")
    entries = scratch.save(prefixes(left, shared, width, similarity, frequent(left, shared, width)), "prefixes")
    several = entries.groupBy("s").agg(F.count("*").alias("k")).where("k > 1").select("s")
    index = scratch.save(entries.join(several, "s"), "index")
    scratch.drop(entries)
    for turn in range(ROUNDS + 1):
        at = named(index, roots)
        pairs = with_drawn(at, turn, similarity) if turn < ROUNDS else across(at, similarity)
        pairs = scratch.save(pairs.join(compared, ["a", "b"], "left_anti"), f"pairs{turn}")
        links = links.union(scratch.save(similar(pairs, left, width, similarity), f"links{turn}"))
        compared = compared.union(pairs)
        roots = components(scratch, links.toDF("u", "v"))
    return roots


def near_duplicates(docs: DataFrame, text: str = "text", key: str = "doc_id", width: int = 5, similarity: float = 0.8) -> DataFrame:
    """key and component_id of every row: the smallest id that links of that similarity reach."""
    scratch = Scratch(docs.sparkSession, "near")
    rows = scratch.save(marks(docs, text, key), "rows")
    distinct = scratch.save(rows.groupBy("h").agg(F.min("key").alias("least"), F.min("r").alias("t")), "distinct")
    texts = scratch.save(rows.join(distinct.select(F.col("t").alias("r")), "r", "left_semi").select(F.col("r").alias("t"), "text"), "texts")
    marked = scratch.save(rows.select("key", "h"), "marked")
    scratch.drop(rows)
    roots = similar_components(scratch, texts, width, similarity)
    named = distinct.join(roots, F.col("t") == F.col("node"), "left").select("h", "least", F.coalesce("root", "t").alias("root"))
    least = named.groupBy("root").agg(F.min("least").alias("component_id"))
    of = scratch.save(named.join(least, "root").select("h", "component_id"), "of")
    return marked.join(of, "h").select(F.col("key").alias(key), "component_id")


def keep_one(docs: DataFrame, text: str = "text", key: str = "doc_id", width: int = 5, similarity: float = 0.8) -> DataFrame:
    """docs without those whose component holds a smaller id; rows with a null id stay, rows that repeat an id are one document."""
    found = near_duplicates(docs, text, key, width, similarity)
    later = found.where(F.col(key).isNotNull() & (F.col("component_id") < F.col(key))).select(F.col(key).alias("__key")).distinct()
    return docs.join(later, F.col(key) == F.col("__key"), "left_anti")
