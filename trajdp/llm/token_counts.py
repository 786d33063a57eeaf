"""Token counts by merging symbol arrays of many pre-tokens in step.

Texts are split into pre-tokens; those not met before are held as one flat array
of symbols with the sequence of each. In every round each sequence finds its
lowest-ranked adjacent pair and all its occurrences are merged at once, until no
sequence has a pair with a rank. The symbols that survive are the tokens.
"""

from __future__ import annotations

import json
import unicodedata
from collections.abc import Iterable, Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pandas as pd
import public_tokenizers
import regex
from pyspark.sql import DataFrame

from .storage import small_batches, written
from .text import documents

NONE = np.iinfo(np.int64).max


def byte_letters() -> dict[int, str]:
    """The letter that stands for each byte in byte-level vocabularies: itself if printable, else from 256 on."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    others = [b for b in range(256) if b not in set(plain)]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(others)}


class RankMerger:
    """Counts the tokens of texts for a byte-level BPE vocabulary with word ends."""

    def __init__(self, path: str, keep: int = 400_000):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab, suffix = spec["model"]["vocab"], spec["model"]["end_of_word_suffix"] or ""
        letters = byte_letters()
        self.inner = np.array([vocab[letters[b]] for b in range(256)], np.int64)
        self.last = np.array([vocab[letters[b] + suffix] for b in range(256)], np.int64)
        self.size = len(vocab)
        pairs = [x if isinstance(x, list) else x.split(" ") for x in spec["model"]["merges"]]
        key = np.array([vocab[a] * self.size + vocab[b] for a, b in pairs], np.int64)
        made = np.array([vocab[a + b] for a, b in pairs], np.int64)
        order = np.argsort(key, kind="stable")
        self.keys, self.ranks, self.made = key[order], order.astype(np.int64), made
        split = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.split = regex.compile(split["pattern"]["Regex"])
        self.special = regex.compile("|".join(regex.escape(t["content"]) for t in spec["added_tokens"]))
        self.seen: dict[str, int] = {}
        self.keep = keep

    def pre_tokens(self, text: str) -> tuple[list[str], int]:
        """Pre-tokens of a text, and the special tokens spelt out in it."""
        if "<|" not in text:
            return self.split.findall(normalised(text)), 0
        parts = self.special.split(text)
        return list(chain.from_iterable(self.split.findall(normalised(p)) for p in parts)), len(parts) - 1

    def counts(self, texts: Iterable[str]) -> list[int]:
        split = [self.pre_tokens(t) for t in texts]
        if len(self.seen) > self.keep:
            self.seen.clear()
        new = list(set().union(*(p for p, _ in split)).difference(self.seen)) if split else []
        if new:
            self.seen.update(zip(new, self.merged(new).tolist()))
        get = self.seen.__getitem__
        return [sum(map(get, pieces)) + special for pieces, special in split]

    def merged(self, words: list[str]) -> np.ndarray:
        """Symbols left in each word. Every round merges all occurrences of each word's lowest-ranked pair."""
        raw = [w.encode() for w in words]
        length = np.array([len(r) for r in raw], np.int64)
        left = length.copy()
        data = np.frombuffer(b"".join(raw), np.uint8)
        symbols = self.inner[data]
        ends = np.cumsum(length) - 1
        symbols[ends] = self.last[data[ends]]
        seq = np.repeat(np.arange(len(words)), length)
        while len(symbols) > 1:
            at, rank = self.lookup(symbols[:-1] * self.size + symbols[1:])
            rank[seq[:-1] != seq[1:]] = NONE
            rank = np.append(rank, NONE)
            starts = np.flatnonzero(np.r_[True, seq[1:] != seq[:-1]])
            lowest = np.minimum.reduceat(rank, starts)
            active = lowest < NONE
            if not active.any():
                break
            sizes = np.diff(np.r_[starts, len(seq)])
            hit = (rank == np.repeat(lowest, sizes)) & (rank < NONE)
            hit = first_of_runs(hit)
            where = np.flatnonzero(hit)
            symbols[where] = self.made[rank[where]]
            left -= np.bincount(seq[where], minlength=len(words))
            stay = np.repeat(active, sizes)  # words without a pair are done
            stay[where + 1] = False
            symbols, seq = symbols[stay], seq[stay]
        return left

    def lookup(self, pair: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = np.minimum(np.searchsorted(self.keys, pair), len(self.keys) - 1)
        return at, np.where(self.keys[at] == pair, self.ranks[at], NONE)


def first_of_runs(hit: np.ndarray) -> np.ndarray:
    """Of adjacent hits, which overlap, the first, third and so on."""
    if not (hit[1:] & hit[:-1]).any():
        return hit
    i = np.arange(len(hit))
    begin = np.maximum.accumulate(np.where(hit & ~np.r_[False, hit[:-1]], i, -1))
    return hit & ((i - begin) % 2 == 0)


def normalised(text: str) -> str:
    """NFC and lower case letter by letter: a final capital sigma has no form of its own."""
    return unicodedata.normalize("NFC", text).replace("Σ", "σ").lower()


@lru_cache(maxsize=2)
def merger(path: str) -> RankMerger:
    return RankMerger(path)


def token_counts(docs: DataFrame, tokenizer: str = "word_bpe_49k.json", limit: int = 2048, slice_chars: int = 4_000_000) -> DataFrame:
    """One row per document: doc_id, n_bytes, n_tokens, over_limit.

    ``docs`` needs doc_id and text; other columns are ignored. Null and empty
    texts have 0 bytes and 0 tokens. Whole texts are counted, special strings in
    them as single tokens; memory is bounded by an Arrow batch and a bounded
    table of pre-tokens. Repeated rows are counted each.
    """

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        m = merger(public_tokenizers.path(tokenizer))
        for batch in batches:
            texts = [t if isinstance(t, str) else "" for t in batch["text"]]
            n: list[int] = []
            i = 0
            while i < len(texts):
                j, size = i, 0
                while j < len(texts) and (j == i or size + len(texts[j]) <= slice_chars):
                    size += len(texts[j])
                    j += 1
                n += m.counts(texts[i:j])
                i = j
            yield pd.DataFrame({
                "doc_id": batch["doc_id"], "n_bytes": [len(t.encode()) for t in texts], "n_tokens": n,
                "over_limit": [k > limit for k in n],
            })

    kind = dict(docs.dtypes)["doc_id"]
    with small_batches(docs.sparkSession):
        return written(docs.select("doc_id", "text").mapInPandas(count, f"doc_id {kind}, n_bytes long, n_tokens long, over_limit boolean"), "token-counts")


def op2_token_counts(spark, sf_dir: str) -> DataFrame:
    return token_counts(documents(spark, sf_dir))
