"""Token counts by the whole-token shortcut.

Offline, once on the driver, it is proved which vocabulary strings encode alone as one token
(:meth:`Bpe.whole_tokens`). A text's pre-tokens found in that set count one each, straight from a dictionary;
only the rest goes through the merges.

Defined results: null and empty texts count nothing; only the key and the counts are returned, so other columns, whatever their
names, neither matter nor clash; repeated rows are counted each.
"""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordwork.llm.bpe import PORTION, Bpe
from ordwork.llm.common import kept_by_worker, map_batches, portions, text_bytes

#: Words whose counts a task keeps besides the whole tokens; the table is emptied when it is full.
KEPT_WORDS = 300_000


class Counter:
    """Counts the tokens of texts; keeps what it has merged."""

    def __init__(self, bpe: Bpe, whole: dict[str, int]):
        self.bpe, self.base = bpe, dict.fromkeys([*whole, *bpe.special], 1)
        self.known = dict(self.base)

    def __call__(self, texts: list[str | None]) -> list[int]:
        pieces = [self.bpe.pieces(t) if t else [] for t in texts]
        if len(self.known) > len(self.base) + KEPT_WORDS:
            self.known = dict(self.base)
        rest = list({w for p in pieces for w in p if w not in self.known})
        _, ends = self.bpe.merge(rest)
        self.known.update(zip(rest, np.diff(ends).tolist(), strict=True))
        return [sum(map(self.known.__getitem__, p)) for p in pieces]


def count_tokens(docs: DataFrame, tokenizer_path: str, text: str = "text", key: str = "doc_id") -> DataFrame:
    """key, n_bytes (UTF-8) and n_tokens of every row; one pass, no shuffle."""
    bpe = Bpe(tokenizer_path)
    whole = bpe.whole_tokens()
    kind = dict(docs.dtypes)[key]
    token = uuid.uuid4().hex

    def each(batch):
        count = kept_by_worker(token, lambda: Counter(bpe, whole))
        texts, keys = batch.column(1), batch.column(0)
        for a, b in portions(text_bytes(texts)[1], PORTION):
            part = texts.slice(a, b - a).to_pylist()
            yield {"key": keys.slice(a, b - a), "n_tokens": count(part), "n_bytes": [len(t.encode()) if t else 0 for t in part]}

    out = map_batches(docs.select(F.col(key).alias("key"), F.col(text).alias("text")), each, f"key {kind}, n_tokens bigint, n_bytes bigint")
    return out.select(F.col("key").alias(key), "n_bytes", "n_tokens")
