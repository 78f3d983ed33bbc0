"""Byte-level BPE by an index of pair occurrences.

The distinct pre-tokens of a block of texts lie end to end in one array of symbols. An index maps each mergeable pair's rank to
all positions where the pair stands. Active ranks are taken in ascending order; one step merges a pair at all its valid
positions at once and adds the pairs that arise left and right of the merged symbols to the lists of their ranks. In these
vocabularies a merged symbol occurs only in later merges, so the ranks taken never go back.
"""

from __future__ import annotations

import hashlib
import heapq
import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import give_back, row_blocks, text_buffers, tidy

#: The pre-tokeniser's pattern, fixed by the vocabulary.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
CACHE_ENTRIES = 250_000
BLOCK = 1 << 20


def _byte_alphabet() -> dict[str, int]:
    """The printable stand-ins of byte-level vocabularies: printable Latin-1 stands for itself, others follow from U+0100."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(rest)}


class PairIndexTokenizer:
    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        alphabet, vocab = _byte_alphabet(), spec["model"]["vocab"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        size = max([*vocab.values(), *self.special.values()]) + 1
        self.bytes_of = [b""] * size
        for token, i in vocab.items():
            self.bytes_of[i] = bytes(alphabet[c] for c in token)
        for token, i in self.special.items():
            self.bytes_of[i] = token.encode()
        self.size, pairs, made = size, [], []
        for m in spec["model"]["merges"]:
            a, b = m if isinstance(m, list) else m.split(" ")
            pairs.append(vocab[a] * size + vocab[b])
            made.append(vocab[a + b])
        self.made = np.array(made, np.int64)
        self.pair_of = np.array(pairs, np.int64)
        self.order = np.argsort(self.pair_of)
        self.keys = self.pair_of[self.order]
        self.first = np.array([vocab[c] for c in sorted(alphabet, key=alphabet.get)], np.int64)
        self.words = regex.compile(PATTERN)
        self.split = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        self.cache = self._fresh()

    def _fresh(self) -> dict[str, bytes]:
        return {"": b""} | {s: int(i).to_bytes(4, "little") for s, i in self.special.items()}

    def _ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = left * self.size + right
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where((self.keys[at] == key) & (left >= 0) & (right >= 0), self.order[at], -1)

    def merge(self, words: list[bytes]) -> list[bytes]:
        """The ids of each word as little-endian unsigned 32-bit integers."""
        lengths = np.array([len(w) for w in words], np.int64)
        ends = np.cumsum(lengths + 1)
        sym = np.full(int(ends[-1]) + 1, -1, np.int64)  # -1 stands before each word and at the end
        body = np.ones(len(sym), bool)
        body[0] = body[ends] = False
        sym[body] = self.first[np.frombuffer(b"".join(words), np.uint8)]
        n = len(sym)
        nxt, prv = np.arange(1, n + 1), np.arange(-1, n - 1)
        nxt[-1], prv[0] = n - 1, 0
        lists: dict[int, list[np.ndarray]] = {}
        active: list[int] = []

        def add(ranks: np.ndarray, at: np.ndarray) -> None:
            keep = ranks >= 0
            ranks, at = ranks[keep], at[keep]
            if not len(ranks):
                return
            by = np.argsort(ranks, kind="stable")
            ranks, at = ranks[by], at[by]
            cuts = np.flatnonzero(ranks[1:] != ranks[:-1]) + 1
            for r, part in zip(ranks[np.r_[0, cuts]].tolist(), np.split(at, cuts), strict=True):
                if r in lists:
                    lists[r].append(part)
                else:
                    lists[r] = [part]
                    heapq.heappush(active, r)

        add(self._ranks(sym[:-1], sym[1:]), np.arange(n - 1))
        while active:
            rank = heapq.heappop(active)
            parts = lists.pop(rank)
            at = parts[0] if len(parts) == 1 else np.unique(np.concatenate(parts))
            a, b = divmod(int(self.pair_of[rank]), self.size)
            at = at[sym[at] == a]
            at = at[sym[nxt[at]] == b]
            if not len(at):
                continue
            if a == b and len(at) > 1:  # overlaps: every second one of a run, from its left end
                follows = np.r_[False, nxt[at[:-1]] == at[1:]]
                start = np.maximum.accumulate(np.where(follows, 0, np.arange(len(at))))
                at = at[(np.arange(len(at)) - start) % 2 == 0]
            gone = nxt[at]
            after = nxt[gone]
            sym[gone] = -2
            sym[at] = self.made[rank]
            nxt[at] = after
            prv[after] = at
            before = prv[at]
            add(np.r_[self._ranks(sym[before], sym[at]), self._ranks(sym[at], sym[after])], np.r_[before, at])
        left = sym >= 0
        ids = sym[left].astype("<u4").tobytes()
        stops = np.cumsum(left)[ends] * 4
        starts = np.r_[0, stops[:-1]]
        return [ids[i:j] for i, j in zip(starts.tolist(), stops.tolist(), strict=True)]

    def encode_block(self, texts: list[str]) -> list[bytes]:
        """The ids of each text; the distinct pre-tokens of the block that are not known yet are merged together."""
        cut: list[list[str]] = []
        for text in texts:
            if self.split is not None and any(s in text for s in self.special):
                parts = []
                for i, piece in enumerate(self.split.split(text)):
                    parts += [piece] if i % 2 else self.words.findall(piece)
                cut.append(parts)
            else:
                cut.append(self.words.findall(text))
        if len(self.cache) > CACHE_ENTRIES:
            self.cache = self._fresh()
        cache = self.cache
        new = list(set().union(*cut).difference(cache))
        if new:
            cache.update(zip(new, self.merge([w.encode() for w in new]), strict=True))
        return [b"".join(map(cache.__getitem__, parts)) for parts in cut]

    def decode(self, ids: bytes) -> str:
        table = self.bytes_of
        return b"".join([table[i] for i in np.frombuffer(ids, "<u4").tolist()]).decode("utf-8", "replace")


_LOADED: dict[str, PairIndexTokenizer] = {}


def tokenizer(path: str) -> PairIndexTokenizer:
    """One a worker process."""
    if path not in _LOADED:
        _LOADED[path] = PairIndexTokenizer(path)
        give_back()  # what parsing the file took
    return _LOADED[path]


def encode_documents(docs: DataFrame, path: str, with_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 (and ids, binary) of every row of docs(doc_id, text).

    A null text is empty: no ids. Null or repeated doc_ids are rows like others, extra columns are ignored, no rows give none. A
    special token's string in a text is that token, as in the tokenizers library. Map-only; memory is a block of texts and a
    bounded cache of pre-tokens (emptied when full and when a task ends), a single text being the least block.
    """
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids binary" * with_ids

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = tokenizer(path)
        for batch in batches:
            column = batch.column("text")
            for i, j in row_blocks(text_buffers(column)[1], BLOCK):
                coded = tok.encode_block(["" if t is None else t for t in column.slice(i, j - i).to_pylist()])
                out = [
                    batch.column("doc_id").slice(i, j - i), pa.array([len(x) // 4 for x in coded], pa.int64()), pa.array([hashlib.sha256(x).hexdigest() for x in coded], pa.string()),
                    pa.array([hashlib.sha256(tok.decode(x).encode()).hexdigest() for x in coded], pa.string()),
                ]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
                if with_ids:
                    out, names = [*out, pa.array(coded, pa.binary())], [*names, "ids"]
                yield pa.RecordBatch.from_arrays(out, names)
        tok.cache = tok._fresh()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("text")).mapInArrow(tidy(encode), schema)
