"""BPE encoding and decoding of whole texts.

Each task collects the distinct pre-tokens of a group of texts, encodes the unseen ones together by
:meth:`Bpe.merge` and keeps their ids; texts are then put together from the ids of their pre-tokens. Decoding
concatenates the bytes of the ids and reads them as UTF-8.

Defined results: a null text encodes as no ids and decodes as the empty text; special strings in a text become
their one id; repeated rows are encoded each; columns of the input pass through, clashing ones are replaced.
"""

from __future__ import annotations

import hashlib
import uuid
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BooleanType, IntegerType, LongType, StructField, StructType

from ordwork.llm.bpe import PORTION, Bpe
from ordwork.llm.common import kept_by_worker, map_batches, portions, text_bytes, without

KEPT_WORDS = 250_000


class Codec:
    """Encodes texts; keeps the ids of the words it has met, up to KEPT_WORDS."""

    def __init__(self, bpe: Bpe):
        self.bpe = bpe
        self.known: dict[str, list[int]] = {}

    def learn(self, pieces: list[list[str]]) -> None:
        if len(self.known) > KEPT_WORDS:
            self.known = {}
        rest = list({w for p in pieces for w in p if w not in self.known and w not in self.bpe.special})
        ids, ends = self.bpe.merge(rest)
        flat, cut = ids.tolist(), ends.tolist()
        self.known.update({w: flat[a:b] for w, a, b in zip(rest, cut[:-1], cut[1:], strict=True)})
        self.known.update({s: [i] for s, i in self.bpe.special.items()})

    def encode(self, texts: list[str | None]) -> list[list[int]]:
        pieces = [self.bpe.pieces(t) if t else [] for t in texts]
        self.learn(pieces)
        return [[i for w in p for i in self.known[w]] for p in pieces]

    def decode(self, ids: list[int]) -> str:
        """Ids as text; bytes that are no UTF-8 become U+FFFD, as in the library's byte-level decoder."""
        return b"".join(map(self.bpe.token_bytes.__getitem__, ids)).decode("utf-8", "replace")


class Digests(Codec):
    """As Codec, but keeps for each word what the digests need: its ids as text, their bytes, their number."""

    def __init__(self, bpe: Bpe):
        super().__init__(bpe)
        self.names = list(map(str, range(bpe.size)))
        self.written: dict[str, str] = {}
        self.read: dict[str, bytes] = {}
        self.counts: dict[str, int] = {}

    def learn(self, pieces):
        if len(self.counts) > KEPT_WORDS:
            self.written, self.read, self.counts = {}, {}, {}
        rest = list({w for p in pieces for w in p if w not in self.counts and w not in self.bpe.special})
        ids, ends = self.bpe.merge(rest)
        flat, cut = ids.tolist(), ends.tolist()
        name, raw = list(map(self.names.__getitem__, flat)), list(map(self.bpe.token_bytes.__getitem__, flat))
        spans = list(zip(cut[:-1], cut[1:], strict=True))
        self.written.update(zip(rest, [",".join(name[a:b]) for a, b in spans], strict=True))
        self.read.update(zip(rest, [b"".join(raw[a:b]) for a, b in spans], strict=True))
        self.counts.update(zip(rest, np.diff(ends).tolist(), strict=True))
        for special, i in self.bpe.special.items():
            self.written[special], self.read[special], self.counts[special] = str(i), self.bpe.token_bytes[i], 1

    def __call__(self, texts: list[str | None]) -> list[tuple[int, str, str]]:
        pieces = [self.bpe.pieces(t) if t else [] for t in texts]
        self.learn(pieces)
        written, read, counts = self.written.__getitem__, self.read.__getitem__, self.counts.__getitem__
        out = []
        for p in pieces:
            decoded = b"".join(map(read, p)).decode("utf-8", "replace")
            out.append((sum(map(counts, p)), hashlib.sha256(",".join(map(written, p)).encode()).hexdigest(), hashlib.sha256(decoded.encode()).hexdigest()))
        return out


def encode(docs: DataFrame, tokenizer_path: str, text: str = "text") -> DataFrame:
    """Every row with `ids` array<int>, `n_tokens` and `exact`: whether decoding gives the text back; no shuffle.

    Columns of these names in the input are replaced.
    """
    bpe, token = Bpe(tokenizer_path), uuid.uuid4().hex
    kept = without(docs, "ids", "n_tokens", "exact")
    names = kept.columns

    def each(batch):
        codec = kept_by_worker(token, lambda: Codec(bpe))
        for a, b in portions(text_bytes(batch.column(names.index(text)))[1], PORTION):
            part = batch.slice(a, b - a)
            texts = part.column(names.index(text)).to_pylist()
            ids = codec.encode(texts)
            exact = [codec.decode(i) == (t or "") for i, t in zip(ids, texts, strict=True)]
            flat = pa.array(np.fromiter(chain.from_iterable(ids), np.int32))
            sizes = list(map(len, ids))
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(sizes))), pa.int32()), flat)
            yield {n: part.column(k) for k, n in enumerate(names)} | {"ids": lists, "n_tokens": sizes, "exact": exact}

    schema = StructType([*kept.schema.fields, StructField("ids", ArrayType(IntegerType())), StructField("n_tokens", LongType()), StructField("exact", BooleanType())])
    return map_batches(kept, each, schema)


def decode(rows: DataFrame, tokenizer_path: str, ids: str = "ids", into: str = "decoded") -> DataFrame:
    """Every row with its ids read back as text in column `into`; null ids give the empty text."""
    bpe = Bpe(tokenizer_path)

    @F.pandas_udf("string")
    def read(column):
        of = Codec(bpe)
        return column.map(lambda x: of.decode(list(x)) if x is not None else "")

    return rows.withColumn(into, read(F.col(ids)))


def digests(docs: DataFrame, tokenizer_path: str, text: str = "text", key: str = "doc_id") -> DataFrame:
    """key, n_tokens, sha256 of the comma-joined ids, sha256 of the decoded text; one pass, no shuffle."""
    bpe, kind = Bpe(tokenizer_path), dict(docs.dtypes)[key]
    token = uuid.uuid4().hex

    def each(batch):
        codec = kept_by_worker(token, lambda: Digests(bpe))
        for a, b in portions(text_bytes(batch.column(1))[1], PORTION):
            n, ids, decoded = zip(*codec(batch.column(1).slice(a, b - a).to_pylist()), strict=True)
            yield {"key": batch.column(0).slice(a, b - a), "n_tokens": n, "ids_sha256": ids, "decoded_sha256": decoded}

    out = map_batches(docs.select(F.col(key).alias("key"), F.col(text).alias("text")), each, f"key {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string")
    return out.withColumnRenamed("key", key)
