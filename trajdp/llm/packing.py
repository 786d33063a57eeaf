"""Best-fit decreasing packing of tokenised documents into windows of a fixed length.

A document longer than a window is first cut into full windows, each a sequence
of its own. What is left of each document is packed, longest first, into the
open window with the least room that still fits it; a segment tree over the
remaining capacities finds that window. Tasks pack blocks of what they read, so
nothing is shuffled and memory is bounded by a block.
"""

from __future__ import annotations

import json
import re
import zlib
from array import array
from collections.abc import Iterable, Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pandas as pd
import public_tokenizers
import regex
from pyspark import TaskContext
from pyspark.sql import DataFrame

from .storage import small_batches, written
from .text import documents
from .token_counts import byte_letters

#: Fixed value: the pattern that splits text before byte-level merges. The file names the splitter, which has it built in.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: The same for texts without unusual characters: letters there are word characters other than digits and "_".
FAST = r"'s|'t|'re|'ve|'m|'ll|'d| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+"
UNUSUAL = "[^\t\n\r -~\u00a1\u00ab\u00bb\u00bf-\u00d6\u00d8-\u00f6\u00f8-\u024f\u2013\u2014\u2018-\u201e\u20ac]"
END = np.array([1], "<u4").tobytes()
BLOCK = 1 << 16  # leftovers packed at once


class CapacityTree:
    """A segment tree over capacities 0..capacity: counts of open windows, and the tightest that fits."""

    def __init__(self, capacity: int):
        self.leaves = 1 << capacity.bit_length()
        self.count = [0] * (2 * self.leaves)
        self.open: list[list[int]] = [[] for _ in range(capacity + 1)]

    def _add(self, room: int, by: int) -> None:
        i = room + self.leaves
        while i:
            self.count[i] += by
            i >>= 1

    def push(self, room: int, window: int) -> None:
        self.open[room].append(window)
        self._add(room, 1)

    def tightest(self, length: int) -> tuple[int, int] | None:
        """Room and number of the open window with the least room >= length, taken out of the tree."""
        i, count = length + self.leaves, self.count
        if not count[i]:
            while i > 1 and not (i % 2 == 0 and count[i + 1]):  # up to the first right sibling that holds one
                i >>= 1
            if i <= 1:
                return None
            i += 1
            while i < self.leaves:  # down to its leftmost leaf
                i = 2 * i if count[2 * i] else 2 * i + 1
        room = i - self.leaves
        window = self.open[room].pop()
        self._add(room, -1)
        return room, window


def best_fit_decreasing(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray, int]:
    """Window and offset of each piece (1..capacity long), and the number of windows; ties by position."""
    tree = CapacityTree(capacity)
    window = np.zeros(len(lengths), np.int64)
    offset = np.zeros(len(lengths), np.int64)
    made = 0
    for i in np.argsort(-lengths, kind="stable").tolist():
        n = int(lengths[i])
        found = tree.tightest(n)
        if found is None:
            found = capacity, made
            made += 1
        room, window[i] = found
        offset[i] = capacity - room
        if room > n:
            tree.push(room - n, int(window[i]))
    return window, offset, made


class PieceEncoder:
    """Token ids of texts as bytes, from a bounded table of pre-tokens.

    The file's vocabulary is byte-level and numbered in the order of its merges,
    so ids serve as ranks for a merger of single pieces. Texts of the usual
    letters are split by the faster of two engines, which splits them alike.
    """

    def __init__(self, path: str, keep: int = 300_000):
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        splitter = spec["pre_tokenizer"]
        if splitter != {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": splitter.get("trim_offsets"), "use_regex": True} or spec["normalizer"]:
            raise ValueError(f"{path}: not a byte-level vocabulary with the usual splitter")
        byte = {c: b for b, c in byte_letters().items()}
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        ranks = {bytes(map(byte.__getitem__, t)): i for t, i in spec["model"]["vocab"].items() if t not in special}
        self.merge = tiktoken.Encoding("pieces", pat_str="(?s:.+)", mergeable_ranks=ranks, special_tokens={}).encode_ordinary  # a piece is one match
        self.special = {t: np.array([i], "<u4").tobytes() for t, i in special.items()}
        self.cut = re.compile("(" + "|".join(map(re.escape, special)) + ")") if special else None
        self.exact, self.fast, self.unusual = regex.compile(PATTERN), re.compile(FAST), re.compile(UNUSUAL)
        self.seen: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        self.keep = keep

    def encode(self, texts: list[str]) -> list[bytes]:
        split = [self.pieces(t) for t in texts]
        if len(self.seen) > self.keep:  # what was met since the last time stays once more
            self.older, self.seen = self.seen, {}
        older, seen = self.older, self.seen
        for piece in set().union(*split).difference(seen):
            found = older.get(piece) or self.special.get(piece)
            seen[piece] = array("I", self.merge(piece)).tobytes() if found is None else found
        get = seen.__getitem__
        return [b"".join(map(get, pieces)) for pieces in split]

    def split(self, text: str) -> list[str]:
        return (self.exact if self.unusual.search(text) else self.fast).findall(text)

    def pieces(self, text: str) -> list[str]:
        if self.cut is None or "<|" not in text:
            return self.split(text)
        parts = self.cut.split(text)
        return list(chain.from_iterable([p] if p in self.special else self.split(p) for p in parts))


@lru_cache(maxsize=2)
def encoder(path: str) -> PieceEncoder:
    return PieceEncoder(path)


def pieces_of(ids: bytes, capacity: int) -> list[tuple[int, int, int]]:
    """Start, length and CRC-32 of each window's worth of ids."""
    step = 4 * capacity
    return [(i // 4, len(part) // 4, zlib.crc32(part)) for i in range(0, len(ids), step) if (part := ids[i : i + step])]


def packed(docs: DataFrame, tokenizer: str = "byte_bpe_50k.json", capacity: int = 2048, slice_chars: int = 4_000_000) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    ``docs`` needs doc_id and text; other columns are ignored. Every document
    ends in id 1, so null and empty texts are one piece of length 1. Sequences
    are numbered apart in each task: the task's partition in the upper bits and
    its own count below, so a task that runs again gives the same numbers.
    Repeated rows are packed each. An empty table gives no rows.
    """

    def pack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        enc = encoder(public_tokenizers.path(tokenizer))
        context = TaskContext.get()
        number = (context.partitionId() if context else 0) << 40
        rest: list[tuple] = []

        def flush() -> pd.DataFrame:
            nonlocal number
            out = pd.DataFrame(rest, columns=["doc_id", "start", "length", "ids_crc32", "doc_tokens"])
            window, offset, made = best_fit_decreasing(out["length"].to_numpy(np.int64), capacity)
            out["sequence_id"], out["offset"] = window + number, offset
            number += made
            rest.clear()
            return out

        for batch in batches:
            for ids, texts in slices(batch, slice_chars):
                full: list[tuple] = []
                for doc_id, code in zip(ids, enc.encode(texts)):
                    code += END
                    for start, length, crc in pieces_of(code, capacity):
                        row = (doc_id, start, length, crc, len(code) // 4)
                        if length < capacity:
                            rest.append(row)
                        else:
                            full.append((*row, number, 0))
                            number += 1
                if full:
                    yield pd.DataFrame(full, columns=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])
                if len(rest) >= BLOCK:
                    yield flush()
        if rest:
            yield flush()

    kind = dict(docs.dtypes)["doc_id"]
    schema = f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
    with small_batches(docs.sparkSession):
        return written(docs.select("doc_id", "text").mapInPandas(pack, schema), "packed-pieces")


def slices(batch: pd.DataFrame, chars: int) -> Iterable[tuple[list, list[str]]]:
    """doc_ids and texts (null: empty) of a batch, in runs of about ``chars`` characters."""
    ids, texts, size = [], [], 0
    null = batch["doc_id"].isna().tolist()
    for doc_id, missing, text in zip(batch["doc_id"].tolist(), null, batch["text"].tolist()):
        ids.append(None if missing else doc_id)
        texts.append(text if isinstance(text, str) else "")
        size += len(texts[-1])
        if size >= chars:
            yield ids, texts
            ids, texts, size = [], [], 0
    if ids:
        yield ids, texts


def op6_packing(spark, sf_dir: str) -> DataFrame:
    return packed(documents(spark, sf_dir))
