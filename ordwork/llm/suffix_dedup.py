"""Removal of repeated substrings by bucket-pointer refinement.

Positions of the texts are put into buckets by a short q-gram, and buckets are refined by pairing the bucket of
a position with the bucket of a later offset: identifiers of 8 bytes give those of 16, these those of 32,
64 and, overlapping, LENGTH bytes, each level reusing all updates of the level below. A bucket identifier is a 64-bit
mix of the two that it is refined from, so it names the same string on every machine and no global ranks are
needed; buckets are brought together by sorting on identifiers. Where a decision rests on identifiers alone,
two that come from different levels are compared together (128 bits).

Sorting every position would move many times the corpus. Three facts keep that down, without changing the result:

* In a string of LENGTH bytes the leftmost smallest q-gram bucket (its pointer) depends on the string alone. Equal
  strings have equal pointers, so buckets that hold one pointer only are dropped at once.
* Consecutive positions that share a pointer are a run. If a whole run, with its bytes, stands earlier too, all of it is
  covered. So only the first of equal runs is refined down to single positions, and only if its
  pointer's bucket also holds a different run.
* A task settles equal runs of one batch itself. A string in a third of all texts therefore sends one row a batch to
  the sort, not one a text.

A pointer that more than HOT runs share (in a phrase of very many texts) would gather them in one task. Such runs are dealt by
their content instead and taken to differ from others, which sends a few more to the positions and changes no result. What shares content
is a row a portion. Only where more than HOT portions hold one pointer are rows ranked by partial aggregates that are
stored and joined back, as all of them would then go through several shuffles.

Defined results: null texts are empty; rows with a null id match nothing; rows that share an id but not the text are documents of their own,
in the order of a hash of the text; rows that share both count as one document (equal starts aren't earlier) and lose the same bytes; texts shorter than LENGTH bytes stay; texts of any length are handled in
overlapping pieces; ids are integers; columns of the input pass through, clashing result columns are replaced.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ordwork.llm import bloom
from ordwork.llm.common import Scratch, map_batches, portions, text_bytes

LENGTH = 100
GRAM = 48
#: Bytes of text that are refined together; a longer text is cut into overlapping pieces of so many starts.
PORTION = 750_000
#: Rows of one bucket that a window may rank in one task.
HOT = 500_000
#: Portions that may send such a row each.
HOT_PORTIONS = 500_000
U = np.uint64
PLACE = U(0xFFFFFF)


def pair(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Identifier of the bucket refined from two identifiers."""
    z = (x * U(0x9E3779B97F4A7C15)) ^ ((y + U(0x632BE59BD9B4E019)) * U(0xC2B2AE3D27D4EB4F))
    z ^= z >> U(29)
    z *= U(0xBF58476D1CE4E5B9)
    z ^= z >> U(32)
    return z


def refine(level: dict[int, np.ndarray], n: int) -> np.ndarray:
    """Identifiers of n bytes at every position, from those of the largest power of two below."""
    if n not in level:
        half = n // 2 if n & (n - 1) == 0 else 1 << (n.bit_length() - 1)
        low = refine(level, half)
        level[n] = pair(low[: len(low) - (n - half)], low[n - half :])
    return level[n]


def refine_at(level: dict[int, np.ndarray], n: int, at: np.ndarray) -> np.ndarray:
    """As refine, at some positions only."""
    if n in level:
        return level[n][at]
    half = n // 2 if n & (n - 1) == 0 else 1 << (n.bit_length() - 1)
    return pair(refine_at(level, half, at), refine_at(level, half, at + (n - half)))


def initial(data: np.ndarray) -> dict[int, np.ndarray]:
    """Buckets of 8 bytes: the bytes themselves."""
    if len(data) < 8:
        return {8: np.zeros(0, np.uint64)}
    return {8: np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(data, 8)).view(np.uint64).ravel()}


def smallest_ahead(x: np.ndarray, n: int) -> np.ndarray:
    """Minimum of x[p : p + n] for each p."""
    step, low = 1, x
    while step * 2 <= n:
        low = np.minimum(low[:-step], low[step:])
        step *= 2
    return np.minimum(low[: len(x) - n + 1], low[n - step :][: len(x) - n + 1]) if step < n else low


class Runs:
    """Runs of starts that share a pointer, over the texts of one portion."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, length: int, gram: int):
        n = len(data) - length + 1
        self.gram_id = self.first = self.size = self.text = self.start = np.zeros(0, np.int64)
        if n <= 0:
            return
        self.level, self.length = initial(data), length
        grams = refine(self.level, gram)
        ahead = length - gram + 1
        order = (grams[: n + ahead - 1] & ~PLACE) | np.arange(n + ahead - 1, dtype=np.uint64)
        pointer = (smallest_ahead(order, ahead) & PLACE).astype(np.int64)
        for end in offsets[1:].tolist():  # strings that would cross the end of their text
            pointer[max(end - length + 1, 0) : end] = -1
        first = np.flatnonzero(np.concatenate(([True], pointer[1:] != pointer[:-1])))
        size = np.diff(np.append(first, n))
        inside = pointer[first] >= 0
        self.first, self.size = first[inside], size[inside]
        self.pointer = pointer[self.first]
        self.gram_id = grams[self.pointer]
        self.text = np.searchsorted(offsets, self.first, side="right") - 1
        self.start = self.first - offsets[self.text]

    def whole(self, at: np.ndarray) -> np.ndarray:
        """Identifiers of the strings that start at `at`."""
        return refine_at(self.level, self.length, at)

    def content(self, k: np.ndarray) -> np.ndarray:
        """Identifier of the bytes of runs k and of where the pointer lies in them."""
        first, size = self.first[k], self.size[k]
        ends = pair(self.whole(first), self.whole(first + size - 1))
        return pair(ends, ((self.pointer[k] - first) << 16 | size).astype(np.uint64))

    def second(self, at: np.ndarray) -> np.ndarray:
        """A second identifier of the strings that start at `at`, put together from a lower level in another way."""
        step = 1 << (self.length.bit_length() - 2)
        out = refine_at(self.level, step, at)
        for k in range(step, self.length - step, step):
            out = pair(refine_at(self.level, step, at + k), out)
        return pair(refine_at(self.level, step, at + self.length - step), out)


def spots(ids: np.ndarray, starts: np.ndarray) -> np.ndarray:
    return pair(ids.view(np.uint64), starts.astype(np.uint64))


def settled(keys: tuple[np.ndarray, ...], ids: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """True for rows whose keys also occur in the same batch at a smaller (id, start)."""
    order = np.lexsort((starts, ids, *keys))
    same = np.ones(len(order), bool)
    if len(order):
        same[0] = False
    for k in keys:
        s = k[order]
        same[1:] &= s[1:] == s[:-1]
    heads = np.maximum.accumulate(np.where(same, 0, np.arange(len(order))))
    later = (ids[order] != ids[order][heads]) | (starts[order] != starts[order][heads])
    out = np.zeros(len(order), bool)
    out[order] = later
    return out


def each_runs(batch, length: int, gram: int):
    """(runs, ids, offset of each run's text piece) for every portion of a batch of (id, text)."""
    data, offsets = text_bytes(batch.column(1))
    ids = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
    for a, b in portions(offsets, PORTION):
        lo, hi = int(offsets[a]), int(offsets[b])
        step = PORTION if hi - lo > PORTION and b == a + 1 else hi - lo
        for at in range(lo, max(hi - length + 1, lo + 1), max(step, 1)):
            part = data[at : min(hi, at + step + length - 1)] if step < hi - lo else data[lo:hi]
            cuts = np.array([0, len(part)]) if step < hi - lo else offsets[a : b + 1] - lo
            runs = Runs(part, cuts, length, gram)
            if len(runs.first):
                yield runs, ids[a:b][runs.text], runs.start + (at - lo)


def spread(keys: np.ndarray, out: np.ndarray, ids: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """keys, but rows that are settled get a key of their own, so that they don't gather in the shuffle."""
    return np.where(out, spots(ids, starts), keys).view(np.int64)


def covered(docs: DataFrame, scratch: Scratch, text: str = "text", key: str = "doc_id", length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """(id, start, n): n consecutive starts of strings of `length` bytes that also stand earlier."""
    rows = docs.where(F.col(key).isNotNull() & F.col(text).isNotNull()).select(F.col(key).cast("long").alias("id"), F.col(text).alias("text"))

    def pointers(batch):
        for runs, _, _ in each_runs(batch, length, gram):
            grams, counts = np.unique(runs.gram_id, return_counts=True)
            yield {"g": grams.view(np.int64), "c": counts.astype(np.int32)}

    shared = map_batches(rows, pointers, "g bigint, c int").groupBy("g").agg(F.sum("c").alias("c"), F.count("*").alias("portions")).where("c > 1")
    shared = scratch.save(shared, "shared")
    n, most = shared.agg(F.count("*"), F.max("portions")).first()
    hot = (most or 0) > HOT_PORTIONS
    # at most one pointer for HOT runs, so far fewer than there are portions
    crowded = np.sort(shared.where(F.col("c") > HOT).select("g").toPandas()["g"].to_numpy(np.int64))
    repeated = bloom.build(shared.select("g"), n)
    scratch.drop(shared)

    def candidates(batch):
        for runs, ids, starts in each_runs(batch, length, gram):
            at = np.flatnonzero(bloom.test(repeated.value, runs.gram_id))
            g, k, ids, starts, n = runs.gram_id[at], runs.content(at), ids[at], starts[at], runs.size[at]
            late = settled((k, g), ids, starts)
            if len(g):
                many = np.isin(g.view(np.int64), crowded)
                g = np.where(many, pair(g, k), g)
                yield {"g": spread(g, late, ids, starts), "k": k.view(np.int64), "id": ids, "start": starts, "n": n.astype(np.int32), "late": late, "many": many}

    found = map_batches(rows, candidates, "g bigint, k bigint, id bigint, start bigint, n int, late boolean, many boolean")
    if hot:
        found = scratch.save(found, "found")
        firsts = scratch.save(found.groupBy("g", "k").agg(F.min(F.struct("id", "start")).alias("first")), "firsts")
        several = firsts.groupBy("g").agg((F.min("k") != F.max("k")).alias("mixed"))
        ranked = found.join(firsts.join(several, "g"), ["g", "k"]).withColumn("again", F.struct("id", "start") > F.col("first"))
    else:
        same, bucket = Window.partitionBy("g", "k").orderBy("id", "start"), Window.partitionBy("g")
        ranked = found.withColumn("mixed", F.min("k").over(bucket) != F.max("k").over(bucket)).withColumn("again", F.rank().over(same) > 1)
    kept = ranked.where("late or again or mixed or many").select("id", "start", "n", (F.col("late") | F.col("again")).alias("late"))
    runs_table = scratch.save(kept, "runs")
    open_runs = runs_table.where("not late").select("id", "start")

    def named(batch):
        yield {"h": spots(batch.column(0).to_numpy(), batch.column(1).to_numpy()).view(np.int64)}

    firsts = bloom.build(map_batches(open_runs, named, "h bigint"), open_runs.count())

    def singles(batch):
        for runs, ids, starts in each_runs(batch, length, gram):
            at = np.flatnonzero(bloom.test(firsts.value, spots(ids, starts)) & bloom.test(repeated.value, runs.gram_id))
            if not len(at):
                continue
            n = runs.size[at]
            inner = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            where = np.repeat(runs.first[at], n) + inner
            ids, starts = np.repeat(ids[at], n), np.repeat(starts[at], n) + inner
            a, b = runs.whole(where), runs.second(where)
            late = settled((b, a), ids, starts)
            yield {"a": spread(a, late, ids, starts), "b": b.view(np.int64), "id": ids, "start": starts, "late": late}

    # the position is covered unless it is the first of its bucket (a, b)
    one = map_batches(rows, singles, "a bigint, b bigint, id bigint, start bigint, late boolean")
    if hot:
        one = scratch.save(one, "one")
        one = one.join(one.groupBy("a", "b").agg(F.min(F.struct("id", "start")).alias("first")), ["a", "b"]).withColumn("again", F.struct("id", "start") > F.col("first"))
    else:
        one = one.withColumn("again", F.rank().over(Window.partitionBy("a", "b").orderBy("id", "start")) > 1)
    one = one.where("late or again")
    singles_table = scratch.save(one.select("id", "start", F.lit(1).alias("n")), "singles")
    return runs_table.where("late").select("id", "start", "n").unionByName(singles_table)


def merged(starts: np.ndarray, n: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Maximal byte spans under strings of `length` bytes at n starts from each of starts."""
    order = np.argsort(starts, kind="stable")
    low, high = starts[order], np.maximum.accumulate((starts + n + (length - 1))[order])
    new = np.concatenate(([True], low[1:] > high[:-1]))
    return low[new], high[np.append(np.flatnonzero(new)[1:] - 1, len(high) - 1)]


def placed(docs: DataFrame, scratch: Scratch, text: str, key: str) -> DataFrame:
    """docs with `__place`: a number in the order of ids, different for rows of one id with different texts; the id itself where there are none."""
    rows = docs.withColumn("__t", F.xxhash64(text))
    known = rows.where(F.col(key).isNotNull() & F.col(text).isNotNull()).select(F.col(key).alias("__id"), "__t")
    clashes = known.groupBy("__id").agg(F.min("__t").alias("a"), F.max("__t").alias("b")).where("a <> b")
    if not clashes.limit(1).count():
        return docs.withColumn("__place", F.col(key).cast("long"))
    # ids go up with the partitions of a global sort, and so does this number; stored, as it must not change
    places = scratch.save(known.distinct().orderBy("__id", "__t").withColumn("__place", F.monotonically_increasing_id()), "places").withColumnRenamed("__t", "__u")
    return rows.join(places, (F.col(key) == F.col("__id")) & (F.col("__t") == F.col("__u")), "left").select(*docs.columns, "__place")


def repeats(docs: DataFrame, scratch: Scratch, text: str = "text", key: str = "doc_id", length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """docs with `__cover`: array of (start, n) of the starts that also stand earlier, null if none."""
    docs = placed(docs, scratch, text, key)
    found = covered(docs, scratch, text, "__place", length, gram)
    per = found.groupBy("id").agg(F.collect_list(F.struct(F.col("start").cast("int").alias("start"), "n")).alias("__cover")).withColumnRenamed("id", "__id")
    return docs.join(per, F.col("__place") == F.col("__id"), "left").drop("__id", "__place")


def spans_of(cover, row: int, length: int) -> list[tuple[int, int]]:
    if not cover[row].is_valid:
        return []
    values = cover[row].values.flatten()
    low, high = merged(values[0].to_numpy().astype(np.int64), values[1].to_numpy().astype(np.int64), length)
    return list(zip(low.tolist(), high.tolist(), strict=True))


def cut(raw: bytes, spans: list[tuple[int, int]]) -> bytes:
    out, at = [], 0
    for a, b in spans:
        out.append(raw[at:a])
        at = b
    return b"".join([*out, raw[at:]])


def remove_repeats(docs: DataFrame, text: str = "text", key: str = "doc_id", length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """key, spans (start, end in bytes) that go, and `kept`: the bytes that stay, which may end inside a character."""
    rows = repeats(docs.select(key, text), Scratch(docs.sparkSession, "suffix"), text, key, length, gram)
    kind = dict(docs.dtypes)[key]

    def each(batch):
        texts, cover = batch.column(1).to_pylist(), batch.column(2)
        spans = [spans_of(cover, k, length) for k in range(len(texts))]
        kept = [cut((t or "").encode(), s) for t, s in zip(texts, spans, strict=True)]
        yield {"key": batch.column(0), "spans": [[{"start": a, "end": b} for a, b in s] for s in spans], "kept": kept}

    out = map_batches(rows.select(F.col(key).alias("key"), F.col(text).alias("text"), "__cover"), each, f"key {kind}, spans array<struct<start:bigint,end:bigint>>, kept binary")
    return out.withColumnRenamed("key", key)


def digest(docs: DataFrame, text: str = "text", key: str = "doc_id", length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """key, n_bytes, n_removed, n_spans and sha256 of the bytes that stay; made at once, as what it reads is dropped then."""
    scratch = Scratch(docs.sparkSession, "suffix")
    rows = repeats(docs.select(key, text), scratch, text, key, length, gram)
    kind = dict(docs.dtypes)[key]

    def each(batch):
        cover = batch.column(2)
        out = {"key": batch.column(0), "n_bytes": [], "n_removed": [], "n_spans": [], "kept_sha256": []}
        for k, t in enumerate(batch.column(1)):
            raw, spans = (t.as_py() or "").encode(), spans_of(cover, k, length)
            out["n_bytes"].append(len(raw))
            out["n_removed"].append(sum(b - a for a, b in spans))
            out["n_spans"].append(len(spans))
            out["kept_sha256"].append(hashlib.sha256(cut(raw, spans)).hexdigest())
        yield out

    out = map_batches(rows.select(F.col(key).alias("key"), F.col(text).alias("text"), "__cover"), each, f"key {kind}, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string")
    return scratch.save(out.withColumnRenamed("key", key), "digest")
