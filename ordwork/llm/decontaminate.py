"""Benchmark decontamination by a broadcast hash set of normalised n-grams.

Words are runs of 0-9, a-z (A-Z lower-cased) and characters beyond ASCII. The windows of an item are its runs
of ten consecutive words, or the whole item where it has fewer. A document word inside any occurrence of a window is hit.

The scan is one pass of built-in functions. A window of L words that starts anywhere contains an aligned block of b =
(L + 1) div 2 words, so each text is cut into such blocks and only their hashes are probed, by a
broadcast hash join with the blocks of all windows; around the few that are found, the exact windows are formed and
verified by their text. A sentinel block keeps one row for each document. The benchmark side is broadcast only after
its size has been summed and found under BROADCAST_BYTES; beyond, the same joins run as shuffles.

Defined results: null texts have no words; items without words have no windows; every row of the documents gives one
row, repeated ids and rows included; equal windows of several items count for each item; an empty benchmark
hits nothing. Removal works on (id, text), null ids included. Columns that are not used pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ordwork.llm.common import ascii_lower, let

WINDOW = 10
#: Bytes of benchmark text up to which its windows are broadcast.
BROADCAST_BYTES = 64 << 20
#: Fixed value: what separates words (A-Z count as letters, as they are lower-cased later).
SEPARATORS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
SENTINEL = 0


def words_of(text: Column) -> Column:
    return F.coalesce(F.array_remove(F.split(text, SEPARATORS, -1), ""), F.array().cast("array<string>"))


def joined(words: Column, start, n) -> Column:
    return F.array_join(F.slice(words, start + 1, n), " ")


def block_hash(words: Column, start, n) -> Column:
    """Hash of a block; lower() maps whatever differs in A-Z only to the same string, and what passes is verified."""
    return F.xxhash64(F.lower(joined(words, start, n)))


def item_windows(benchmark: DataFrame, text: str, key: str, width: int) -> DataFrame:
    """(size, window, items): each distinct window with the items that hold it."""

    def of(words):
        n = F.size(words)
        size = F.least(n, F.lit(width))
        return F.when(n > 0, F.transform(F.sequence(F.lit(0), n - size), lambda i: F.struct(size.alias("size"), joined(words, i, size).alias("window"))))

    lowered = F.transform(words_of(F.col(text)), ascii_lower)
    rows = benchmark.select(F.col(key).cast("string").alias("item"), F.explode(let(lowered, of)).alias("w"))
    return rows.groupBy("w.size", "w.window").agg(F.array_sort(F.collect_set("item")).alias("items"))


def report(docs: DataFrame, benchmark: DataFrame, text: str = "text", key: str = "doc_id", item_text: str = "text", item_key: str = "item_id", width: int = WINDOW) -> DataFrame:
    """One row a document: key, text_hash, n_words, n_hit, spans (start, end of merged hits), items (sorted as strings)."""
    windows = item_windows(benchmark, item_text, item_key, width)
    held = benchmark.agg(F.coalesce(F.sum(F.octet_length(item_text)), F.lit(0)).alias("b")).first()["b"]
    sizes = windows.agg(F.array_sort(F.collect_set("size")).alias("sizes")).first()["sizes"]  # at most `width` different ones
    small = (lambda x: F.broadcast(x)) if held <= BROADCAST_BYTES else (lambda x: x)
    half = F.expr("(size + 1) div 2").cast("int")
    parts = windows.select("size", F.explode(let(F.split("window", " "), lambda w: F.transform(F.sequence(F.lit(0), F.col("size") - half), lambda i: block_hash(w, i, half)))).alias("h")).distinct()
    parts = parts.union(docs.sparkSession.createDataFrame([(SENTINEL, SENTINEL)], "size int, h long"))

    def blocks_for(words, size):
        """The aligned blocks that windows of this size must hold one of, each with the words around it."""
        b = (size + 1) // 2

        def block(k):
            low = F.greatest(k * b - (size - b), F.lit(0))
            return let(low, lambda lo: F.struct(F.lit(size).alias("size"), block_hash(words, k * b, F.lit(b)).alias("h"), lo.alias("from"), F.slice(words, lo + 1, k * b + size - lo).alias("near")))

        every = F.transform(F.sequence(F.lit(0), F.floor(F.size(words) / b).cast("int") - 1), block)
        return F.when(F.size(words) >= size, every).otherwise(F.array().cast("array<struct<size:int,h:bigint,from:int,near:array<string>>>"))

    def blocks(words):
        sentinel = F.struct(F.lit(SENTINEL).alias("size"), F.lit(SENTINEL).cast("long").alias("h"), F.lit(0).alias("from"), F.array().cast("array<string>").alias("near"))
        return F.struct(F.size(words).cast("long").alias("n_words"), F.concat(F.array(sentinel), *[blocks_for(words, size) for size in sizes]).alias("blocks"))

    rows = docs.select(F.col(key).alias("key"), F.coalesce(F.xxhash64(text), F.lit(0)).alias("text_hash"), F.monotonically_increasing_id().alias("row"), let(words_of(F.col(text)), blocks).alias("d"))
    near = rows.select("key", "text_hash", "row", "d.n_words", F.explode("d.blocks").alias("b")).select("key", "text_hash", "row", "n_words", "b.*").join(small(parts), ["size", "h"])
    lowered = F.transform("near", ascii_lower)
    formed = let(lowered, lambda w: F.when(F.col("size") > 0, F.transform(F.sequence(F.lit(0), F.size(w) - F.col("size")), lambda i: F.struct((F.col("from") + i).alias("start"), joined(w, i, F.col("size")).alias("window")))))
    probes = near.select("key", "text_hash", "row", "n_words", "size", F.explode_outer(formed).alias("p")).select("key", "text_hash", "row", "n_words", "size", "p.start", "p.window")
    hits = probes.join(small(windows), ["size", "window"], "left").select("key", "text_hash", "row", "n_words", "items", F.when(F.col("items").isNotNull(), F.struct("start", (F.col("start") + F.col("size")).alias("end"))).alias("hit"))
    per = hits.groupBy("key", "text_hash", "row").agg(F.max("n_words").alias("n_words"), F.array_sort(F.collect_set("hit")).alias("hits"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"))
    none = F.array().cast("array<struct<start:int,end:int>>")
    grow = lambda a, x: F.when((F.size(a) > 0) & (F.try_element_at(a, F.lit(-1))["end"] >= x["start"]), F.concat(F.slice(a, 1, F.size(a) - 1), F.array(F.struct(F.try_element_at(a, F.lit(-1))["start"].alias("start"), F.greatest(F.try_element_at(a, F.lit(-1))["end"], x["end"]).alias("end"))))).otherwise(F.concat(a, F.array(x)))
    spans = F.aggregate("hits", none, grow)
    out = per.select(F.col("key").alias(key), "text_hash", "n_words", spans.alias("spans"), "items")
    return out.select(key, "text_hash", "n_words", F.aggregate("spans", F.lit(0).cast("long"), lambda a, x: a + x["end"] - x["start"]).alias("n_hit"), "spans", "items")


def remove_documents(docs: DataFrame, benchmark: DataFrame, text: str = "text", key: str = "doc_id", **settings) -> DataFrame:
    """docs without those that hold any window of the benchmark."""
    bad = report(docs, benchmark, text, key, **settings).where("n_hit > 0").select(F.col(key).alias("__key"), F.col("text_hash").alias("__hash")).distinct()
    return docs.join(bad, F.col(key).eqNullSafe(F.col("__key")) & (F.coalesce(F.xxhash64(text), F.lit(0)) == F.col("__hash")), "left_anti")


def remove_spans(docs: DataFrame, benchmark: DataFrame, text: str = "text", key: str = "doc_id", **settings) -> DataFrame:
    """docs with the hit words cut out; what separates words stays, so a cut leaves the separators on both its sides."""
    bad = report(docs, benchmark, text, key, **settings).where("n_hit > 0").select(F.col(key).alias("__key"), F.col("text_hash").alias("__hash"), F.col("spans").alias("__spans")).dropDuplicates(["__key", "__hash"])
    both = docs.join(bad, F.col(key).eqNullSafe(F.col("__key")) & (F.coalesce(F.xxhash64(text), F.lit(0)) == F.col("__hash")), "left")
    word = SEPARATORS.replace("[", "[^")
    marked = F.regexp_extract_all(text, F.lit(f"(?:{word})|(?:{SEPARATORS})"), F.lit(0))
    is_word = lambda x: ~x.rlike(f"^(?:{SEPARATORS})$")

    def cut(parts):
        numbered = F.aggregate(parts, F.struct(F.lit(0).alias("n"), F.array().cast("array<string>").alias("out")), lambda a, x: F.struct((a["n"] + is_word(x).cast("int")).alias("n"), F.concat(a["out"], F.when(is_word(x) & F.exists("__spans", lambda s: (s["start"] <= a["n"]) & (a["n"] < s["end"])), F.array().cast("array<string>")).otherwise(F.array(x))).alias("out")))
        return F.array_join(numbered["out"], "")

    new = F.when(F.col("__spans").isNotNull(), let(marked, cut)).otherwise(F.col(text))
    return both.select(*[new.alias(c) if c == text else F.col(f"`{c}`") for c in docs.columns])
