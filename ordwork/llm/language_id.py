"""Language identification by prediction by partial matching (PPM) over bytes.

For each language a variable-order context tree of up to three bytes is counted on a bounded sample of
labelled texts and then frozen. A symbol is coded in the longest context that the language has seen; if the
symbol never followed it, an escape is paid and the next shorter context tried, down to a uniform code. The
escape probability of a context is distinct / (total + distinct) of its followers. The language whose
tree gives the shortest code for the whole text wins.

As the statistics are frozen, the code length of a symbol after any three bytes is a constant. Each language keeps only
what it has seen: escapes of its contexts and costs of its grams, sorted, so its size follows its sample, whatever the
number of languages. A portion of text is reduced to its distinct four-byte grams first; these are looked up by
binary search, once a language, and their costs handed back to all places.

Defined results: null texts and texts without a letter are `und` with score 0; with no labelled text at all
every text is `und`; equal code lengths go to the language that sorts first; texts of any length are
scored whole; repeated rows are scored each; the sample doesn't depend on partitioning.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordwork.llm.common import kept_by_worker, map_batches, portions, text_bytes

ORDER = 3
#: Bound of the training sample: expected bytes of text for each language, taken in chunks by hash of id and place.
SAMPLE_BYTES = 2_000_000
#: Chunks in a full sample, more or less.
CHUNKS = 500
#: So many languages' sizes are handed to all tasks (a row each); more are joined by shuffle.
SENT_LANGUAGES = 100_000
SALTS = 256
UNDETERMINED = "und"
#: Texts are scored in portions of so many bytes.
PORTION = 1_000_000
LETTER = regex.compile(r"\p{L}")


def sample(labelled: DataFrame, text: str, lang: str, key: str, most: int) -> DataFrame:
    """(lang, text): of a language with at most `most` bytes all texts, of others chunks whose hash lies under the share that gives about so many.

    Chunks are short against `most`, so a few very long texts are sampled as evenly as many short ones.
    """
    rows = labelled.select(F.col(text).alias("text"), F.col(lang).alias("lang"), F.col(key).cast("string").alias("key")).where("text is not null and lang is not null")
    sized = beside_sizes(rows)
    share = F.lit(float(most)) / F.greatest("size", F.lit(1))
    chunk = max(most // CHUNKS, 1)
    hashed = lambda at: F.pmod(F.xxhash64("key", at), F.lit(1_000_003)) / 1_000_003.0
    starts = F.filter(F.sequence(F.lit(0), F.floor((F.greatest(F.char_length("text"), F.lit(1)) - 1) / chunk).cast("int")), lambda at: hashed(at) < share)
    parts = F.when(share >= 1, F.array("text")).otherwise(F.transform(starts, lambda at: F.substring("text", at * chunk + 1, F.lit(chunk))))
    return sized.select("lang", F.explode(parts).alias("text"))


def beside_sizes(rows: DataFrame) -> DataFrame:
    """rows with `size`, the bytes of their language; texts stay where they are unless there are more than SENT_LANGUAGES languages.

    Beyond that rows are joined by language and one of SALTS parts of it, so that no task holds a whole language.
    """
    sizes = rows.groupBy("lang").agg(F.sum(F.octet_length("text")).alias("size"))
    few = sizes.limit(SENT_LANGUAGES + 1).collect()
    if len(few) <= SENT_LANGUAGES:
        return rows.join(F.broadcast(rows.sparkSession.createDataFrame(few, sizes.schema)), "lang")
    parts = sizes.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))).alias("salt"))
    return rows.withColumn("salt", F.pmod(F.xxhash64("key", "text"), F.lit(SALTS))).join(parts, ["lang", "salt"]).drop("salt")


def gram_counts(rows: DataFrame) -> DataFrame:
    """(lang, n, gram, count) of all byte strings of 1 to ORDER + 1 bytes; a gram is packed big-endian into a long."""

    def each(batch):
        langs = np.array(batch.column(0).to_pylist(), object)
        data, offsets = text_bytes(batch.column(1))
        for lang in sorted(set(langs)):
            parts = [data[offsets[k] : offsets[k + 1]] for k in np.flatnonzero(langs == lang)]
            # texts are joined by the row's three starting zeros, as when scoring
            joined = np.concatenate([x for p in parts for x in (np.zeros(ORDER, np.uint8), p)]).astype(np.int64)
            start = np.concatenate([np.r_[np.ones(ORDER, bool), np.zeros(len(p), bool)] for p in parts])
            packed = np.zeros(len(joined), np.int64)
            for n in range(1, ORDER + 2):
                packed[n - 1 :] += joined[: len(joined) - n + 1] << (8 * (n - 1))
                grams, counts = np.unique(packed[n - 1 :][~start[n - 1 :]], return_counts=True)
                yield {"lang": [lang] * len(grams), "n": np.full(len(grams), n, np.int32), "gram": grams, "count": counts}

    local = map_batches(rows.select("lang", "text"), each, "lang string, n int, gram bigint, count bigint")
    return local.groupBy("lang", "n", "gram").agg(F.sum("count").alias("count"))


class Model:
    """Frozen statistics of all languages; the look-up tables are made where they are first used and don't travel."""

    def __init__(self, counts):
        """counts: rows of gram_counts as a pandas frame; their number is bounded by the sample of each language."""
        self.langs = sorted(counts["lang"].unique())
        self.grams = {(lang, int(n)): part.sort_values("gram")[["gram", "count"]].to_numpy(np.int64) for (lang, n), part in counts.groupby(["lang", "n"])}
        self.token = uuid.uuid4().hex

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("short", "long")}

    def prepare(self) -> None:
        """Work out, per language, the costs after at most one byte as a table and those after more as sorted arrays."""
        self.short, self.long = [], []
        for lang in self.langs:
            levels = [frozen(self.grams.get((lang, n + 1), np.zeros((0, 2), np.int64))) for n in range(ORDER + 1)]
            short = np.full((256, 256), 8.0, np.float32)
            for n, (contexts, escapes, known, costs) in enumerate(levels[:2]):
                rows = contexts if n else slice(None)
                short[rows] += escapes[:, None]
                short[(known >> 8, known & 255) if n else (slice(None), known)] = costs
            self.short.append(short.ravel())
            self.long.append(levels[2:])

    def costs(self, k: int, grams: np.ndarray) -> np.ndarray:
        """Bits of the last byte of each gram after the bytes before it, in language k."""
        out = self.short[k][grams & 0xFFFF]
        for n, (contexts, escapes, known, costs) in enumerate(self.long[k], 2):
            if len(known):
                tails = grams & np.uint32((1 << 8 * (n + 1)) - 1)
                at, met = places(contexts, tails >> 8)
                out = np.where(met, out + escapes[at], out)  # escape, then shorter
                at, met = places(known, tails)
                out = np.where(met, costs[at], out)
        return out

    def lengths(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """(texts, languages): bits of each text; a text beyond PORTION is summed portion by portion."""
        out = np.zeros((len(offsets) - 1, len(self.langs)))
        padded = np.concatenate([np.zeros(ORDER, np.uint8), data])
        for lo in range(0, len(data), PORTION):
            hi = min(lo + PORTION, len(data))
            cut = np.clip(offsets, lo, hi)
            sizes = np.diff(cut)
            filled = np.flatnonzero(sizes)
            depth = np.arange(lo, hi) - np.repeat(offsets[:-1], sizes)
            grams = data[lo:hi].astype(np.uint32)
            for back in range(1, ORDER + 1):  # each text starts after zeros, so that none sees the bytes of another
                before = np.where(depth >= back, padded[lo + ORDER - back : hi + ORDER - back], 0)
                grams |= before.astype(np.uint32) << np.uint32(8 * back)
            order = np.sort(grams)
            distinct = order[np.r_[True, order[1:] != order[:-1]]]
            inverse = np.searchsorted(distinct, grams)  # few distinct ones: faster than sorting places along
            for k in range(len(self.langs)):
                out[filled, k] += np.add.reduceat(self.costs(k, distinct)[inverse], cut[filled] - lo, dtype=np.float64)
        return out


def frozen(counted: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(contexts, their escapes in bits, grams, their costs in bits) of sorted (gram, count) rows of one length."""
    known, count = counted[:, 0], counted[:, 1].astype(np.float64)
    contexts, inverse = np.unique(known >> 8, return_inverse=True)
    total, distinct = np.bincount(inverse, count, len(contexts)), np.bincount(inverse, minlength=len(contexts))
    escapes, costs = np.log2((total + distinct) / distinct), np.log2((total + distinct)[inverse] / count)
    return contexts.astype(np.uint32), escapes.astype(np.float32), known.astype(np.uint32), costs.astype(np.float32)


def places(sorted_keys: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(place of each wanted key, whether it is there)."""
    at = np.minimum(np.searchsorted(sorted_keys, wanted), len(sorted_keys) - 1)
    return at, sorted_keys[at] == wanted


def fit(labelled: DataFrame, text: str = "text", lang: str = "lang", key: str = "doc_id", sample_bytes: int = SAMPLE_BYTES) -> Model:
    return Model(gram_counts(sample(labelled, text, lang, key, sample_bytes)).toPandas())


def prepared(model: Model) -> Model:
    if model.langs:
        model.prepare()
    return model


def judged(column: pa.Array, model: Model) -> list[tuple[str, float, float]]:
    """(language, score, bits per byte) of each text."""
    data, offsets = text_bytes(column)
    out: list[tuple[str, float, float]] = []
    for a, b in portions(offsets, PORTION):
        lo, hi = offsets[a], offsets[b]
        texts = column.slice(a, b - a).to_pylist()
        known = [bool(t) and bool(model.langs) and LETTER.search(t) is not None for t in texts]
        if not model.langs:
            out += [(UNDETERMINED, 0.0, 0.0)] * len(texts)
            continue
        bits = model.lengths(data[lo:hi], offsets[a : b + 1] - lo)
        best, least = bits.argmin(1), bits.min(1)
        score = 1 / np.exp2(np.maximum(least[:, None] - bits, -1000)).sum(1)
        sizes = np.maximum(np.diff(offsets[a : b + 1]), 1)
        out += [(model.langs[w], s, v) if k else (UNDETERMINED, 0.0, 0.0) for k, w, s, v in zip(known, best.tolist(), score.tolist(), (least / sizes).tolist(), strict=True)]
    return out


def predict(docs: DataFrame, model: Model, text: str = "text", key: str = "doc_id") -> DataFrame:
    """key, lang_pred, score (share of the winner, if code lengths are read as probabilities) and bits_per_byte."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # counts of the sample: a few MB a language at most
    kind = dict(docs.dtypes)[key]

    def each(batch):
        model = kept_by_worker(shared.value.token, lambda: prepared(shared.value))
        labels, scores, bits = zip(*judged(batch.column(1), model), strict=True)
        yield {"key": batch.column(0), "lang_pred": labels, "score": scores, "bits_per_byte": bits}

    out = map_batches(docs.select(F.col(key).alias("key"), F.col(text).alias("text")), each, f"key {kind}, lang_pred string, score double, bits_per_byte double")
    return out.withColumnRenamed("key", key)


def select_known(docs: DataFrame, model: Model, text: str = "text") -> DataFrame:
    """docs whose language can be told, all columns as they are; one pass, no shuffle."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names = docs.columns
    at = names.index(text)

    def each(batch):
        model = kept_by_worker(shared.value.token, lambda: prepared(shared.value))
        known = np.array([label != UNDETERMINED for label, _, _ in judged(batch.column(at), model)], bool)
        if known.any():
            kept = batch.filter(pa.array(known))
            yield {n: kept.column(k) for k, n in enumerate(names)}

    return map_batches(docs, each, docs.schema)


def held_out(key: str = "doc_id"):
    """True where crc32 of the id as text leaves remainder 2 by 4."""
    return F.coalesce(F.crc32(F.col(key).cast("string")) % 4 == 2, F.lit(False))
