"""Byte-level BPE from a public vocabulary file: pre-tokens, batched merge rounds in numpy, decoding.

The vocabulary is read on the driver from the path that is given and travels to the tasks inside the
function, so executors need no copy of the file. Merge rounds work on many words at once: their symbols lie
in one flat array, the rank of each adjacent pair is found by binary search over the sorted pair keys, and in
every round each word replaces all occurrences of its own lowest-ranked pair.
"""

from __future__ import annotations

import json
from functools import cached_property

import numpy as np

from ordwork.llm.common import portions

#: Bytes of text that are cut into pre-tokens at a time, unless one text is longer, and bytes of words that are merged at a time.
PORTION = 4_000_000
#: Fixed value: the pre-token pattern of this vocabulary.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: From this code point on the Unicode tables of Python's regex and of the tokenizers library may differ; texts
#: that reach it are split by the library's own pre-tokeniser.
SAME_CLASSES_BELOW = "՘"
NO_RANK = np.iinfo(np.int32).max


def printable_bytes() -> dict[str, int]:
    """Character by which byte-level vocabularies write each byte: itself where printable, else from U+0100 on."""
    keep = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    moved = iter(range(256, 512))
    return {chr(b if b in keep else next(moved)): b for b in range(256)}


class Bpe:
    """A vocabulary with its merges, as plain arrays that pickle well."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as file:
            self.source = file.read()
        spec = json.loads(self.source)
        of = printable_bytes()
        raw = lambda s: bytes(of[c] for c in s)
        vocab, merges = spec["model"]["vocab"], spec["model"]["merges"]
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        size = max([*vocab.values(), *self.special.values()]) + 1
        self.size = size
        self.token_bytes = [b""] * size
        for token, i in vocab.items():
            self.token_bytes[i] = raw(token)
        for token, i in self.special.items():
            self.token_bytes[i] = token.encode()
        self.byte_id = np.zeros(256, np.int32)
        for char, byte in of.items():
            self.byte_id[byte] = vocab.get(char, -1)
        pairs = [m if isinstance(m, list) else m.split(" ") for m in merges]
        left = np.array([vocab[a] for a, _ in pairs], np.int64)
        right = np.array([vocab[b] for _, b in pairs], np.int64)
        made = np.array([vocab[a + b] for a, b in pairs], np.int32)
        keys = left * size + right
        order = np.argsort(keys, kind="stable")
        self.keys, self.ranks, self.made = keys[order], order.astype(np.int32), made  # made is indexed by rank

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("find", "library", "byte_pair_ranks")}

    @cached_property
    def find(self):
        import regex

        return regex.compile(PATTERN).findall

    @cached_property
    def library(self):
        from tokenizers import Tokenizer

        return Tokenizer.from_str(self.source)

    def pretokens(self, text: str) -> list[str]:
        """Pre-tokens of a text that holds no special string."""
        if text.isascii() or max(text) < SAME_CLASSES_BELOW:
            return self.find(text)
        return [text[a:b] for _, (a, b) in self.library.pre_tokenizer.pre_tokenize_str(text)]

    def pieces(self, text: str) -> list[str]:
        """Pre-tokens, with special strings standing for themselves."""
        for special in self.special:
            if special in text:
                out = []
                for k, part in enumerate(text.split(special)):
                    if k:
                        out.append(special)
                    out += self.pieces(part) if part else []
                return out
        return self.pretokens(text) if text else []

    def ranks_of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of each pair, by binary search over the sorted pair keys."""
        key = left.astype(np.int64) * self.size + right
        at = np.searchsorted(self.keys, key)
        at[at == len(self.keys)] = 0
        return np.where(self.keys[at] == key, self.ranks[at], NO_RANK)

    @cached_property
    def byte_pair_ranks(self) -> np.ndarray:
        """Rank of every pair of single bytes, as most pairs of the first round repeat."""
        grid = np.arange(256)
        return self.ranks_of(np.repeat(self.byte_id, 256), np.tile(self.byte_id, 256)).reshape(len(grid), len(grid))

    def merge(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(all token ids one after the other, offsets of each word in them); long lists are merged in portions."""
        raw = [w.encode() for w in words]
        offsets = np.concatenate(([0], np.cumsum(np.fromiter(map(len, raw), np.int64, len(raw)))))
        done = [self.merge_rounds(raw[a:b]) for a, b in portions(offsets, PORTION)] or [self.merge_rounds([])]
        sizes = np.concatenate([np.diff(ends) for _, ends in done])
        return np.concatenate([ids for ids, _ in done]), np.concatenate(([0], np.cumsum(sizes)))

    def merge_rounds(self, raw: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        n = len(raw)
        length = np.fromiter(map(len, raw), np.int64, n)
        data = np.frombuffer(b"".join(raw), np.uint8)
        symbols = self.byte_id[data]
        word = np.repeat(np.arange(n, dtype=np.int64), length)
        rank = np.full(len(symbols), NO_RANK, np.int32)  # of the pair that starts at each symbol
        rank[:-1] = np.where(word[1:] == word[:-1], self.byte_pair_ranks[data[:-1], data[1:]], NO_RANK)
        done_ids, done_words = [], []
        while len(symbols):
            starts = np.flatnonzero(np.concatenate(([True], word[1:] != word[:-1])))
            sizes = np.diff(np.append(starts, len(word)))
            lowest = np.minimum.reduceat(rank, starts)
            going = lowest != NO_RANK
            if not going.all():  # finished words leave the flat array
                open_ = np.repeat(going, sizes)
                done_ids.append(symbols[~open_])
                done_words.append(word[~open_])
                symbols, word, rank = symbols[open_], word[open_], rank[open_]
                sizes, lowest = sizes[going], lowest[going]
                if not len(symbols):
                    break
            where = np.flatnonzero(rank == np.repeat(lowest, sizes))
            # "aaa": of overlapping occurrences every second one counts, from the left
            first = np.concatenate(([True], where[1:] != where[:-1] + 1))
            if not first.all():
                at = np.arange(len(where))
                where = where[(at - np.maximum.accumulate(np.where(first, at, 0))) % 2 == 0]
            symbols[where] = self.made[rank[where]]
            keep = np.ones(len(symbols), bool)
            keep[where + 1] = False
            symbols, word, rank = symbols[keep], word[keep], rank[keep]
            # only the pairs that touch a new symbol have a new rank
            new = where - np.arange(len(where))
            touched = np.concatenate((new, new[new > 0] - 1))
            inside = np.zeros(len(touched), bool)
            has_next = touched + 1 < len(word)
            inside[has_next] = word[touched[has_next]] == word[touched[has_next] + 1]
            rank[touched] = NO_RANK
            touched = touched[inside]
            rank[touched] = self.ranks_of(symbols[touched], symbols[touched + 1])
        ids, owner = (np.concatenate(done_ids), np.concatenate(done_words)) if done_ids else (np.zeros(0, np.int32), np.zeros(0, np.int64))
        order = np.argsort(owner, kind="stable")
        return ids[order], np.searchsorted(owner[order], np.arange(n + 1))

    def whole_tokens(self) -> dict[str, int]:
        """The vocabulary strings that are proved to encode alone as exactly themselves.

        A token qualifies if its bytes are valid UTF-8, the pre-token pattern leaves the string in one piece and the
        merges of that piece end in this one token. As the merges of a pre-token don't depend on its
        neighbours, any such pre-token of any text is one token.
        """
        out: dict[str, int] = {}
        for i, raw in enumerate(self.token_bytes):
            try:
                out.setdefault(raw.decode(), i)
            except UnicodeDecodeError:
                continue
        out.pop("", None)
        words = [w for w, i in out.items() if w not in self.special and self.pretokens(w) == [w]]
        ids, ends = self.merge(words)
        one = np.diff(ends) == 1
        return {w: out[w] for w, single, at in zip(words, one, ends, strict=False) if single and ids[at] == out[w]}
