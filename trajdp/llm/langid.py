"""Language identification: sparse multinomial logistic regression on TF-IDF of character n-grams.

Weights are learned by the follow-the-regularised-leader proximal method with
elastic-net penalties on a bounded sample of labelled rows; the document
frequencies of n-grams cover every training row; a temperature fitted on a part
of the sample that the weights have not seen calibrates the probabilities.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import small_batches, written
from .text import documents

SALTS = (0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D)


@dataclass(frozen=True)
class LanguageParams:
    """per_label: most labelled rows of each language that weights are learned from. buckets: hashed n-gram features."""

    per_label: int = 1500
    buckets: int = 1 << 14
    sizes: tuple[int, ...] = (1, 2, 3)
    epochs: int = 3
    alpha: float = 0.5
    beta: float = 1.0
    l1: float = 0.02
    l2: float = 0.5
    seed: int = 7


def n_grams(text: str, p: LanguageParams) -> np.ndarray:
    """How often each hashed character n-gram occurs in the lower-cased text."""
    code = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    total = np.zeros(p.buckets, np.int64)
    shift = np.uint32(32 - (p.buckets.bit_length() - 1))
    for n in p.sizes:
        if len(code) < n:
            break
        h = np.full(len(code) - n + 1, SALTS[n % 3], np.uint32)
        for j in range(n):
            h = (h ^ code[j : len(code) - n + 1 + j]) * np.uint32(0x01000193)
        h = (h ^ (h >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
        total += np.bincount((h >> shift).astype(np.int64), minlength=p.buckets)
    return total


def features(at: np.ndarray, counts: np.ndarray, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Unit vector of sublinear TF times IDF over the features ``at``."""
    v = (1 + np.log(counts)) * idf[at]
    norm = np.sqrt(v @ v)
    return at, v / norm if norm else v


class Ftrl:
    """Multinomial logistic regression, one row at a time; weights below the L1 penalty are exactly zero."""

    def __init__(self, size: int, labels: int, p: LanguageParams):
        self.z, self.n, self.p = np.zeros((size, labels)), np.zeros((size, labels)), p

    def weights(self, at) -> np.ndarray:
        z, n, p = self.z[at], self.n[at], self.p
        return np.where(np.abs(z) > p.l1, -(z - np.sign(z) * p.l1) / ((p.beta + np.sqrt(n)) / p.alpha + p.l2), 0.0)

    def learn(self, at: np.ndarray, v: np.ndarray, label: int) -> None:
        w = self.weights(at)
        prob = softmax(v @ w)
        prob[label] -= 1
        g = v[:, None] * prob
        self.z[at] += g - (np.sqrt(self.n[at] + g * g) - np.sqrt(self.n[at])) / self.p.alpha * w
        self.n[at] += g * g


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def fitted_temperature(logits: np.ndarray, labels: np.ndarray) -> float:
    """The temperature with the least negative log-likelihood, by golden-section search over its logarithm."""
    if not len(labels):
        return 1.0

    def loss(t: float) -> float:
        return -np.log(np.maximum(softmax(logits / np.exp(t))[np.arange(len(labels)), labels], 1e-12)).mean()

    lo, hi, r = np.log(0.05), np.log(20.0), (5**0.5 - 1) / 2
    for _ in range(40):
        a, b = hi - r * (hi - lo), lo + r * (hi - lo)
        lo, hi = (lo, b) if loss(a) <= loss(b) else (a, hi)
    return float(np.exp((lo + hi) / 2))


@dataclass(frozen=True)
class LanguageModel:
    labels: list[str]
    idf: np.ndarray
    weights: np.ndarray
    temperature: float
    params: LanguageParams

    def predict(self, text: str | None) -> tuple[str, float]:
        """``und`` with score 0 for null texts and texts without a letter."""
        if not isinstance(text, str) or not self.labels or not any(map(str.isalpha, text)):
            return "und", 0.0
        counts = n_grams(text, self.params)
        at = np.flatnonzero(counts)
        at, v = features(at, counts[at], self.idf)
        prob = softmax(v @ self.weights[at] / self.temperature)
        best = int(prob.argmax())
        return self.labels[best], float(min(1.0, prob[best]))


def document_frequencies(rows: DataFrame, p: LanguageParams) -> tuple[np.ndarray, int]:
    """In how many rows each feature occurs, over all rows: each task sends one row for each feature at most."""

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total, n = np.zeros(p.buckets, np.int64), 0
        for batch in batches:
            for text in batch["text"]:
                if isinstance(text, str):
                    total += n_grams(text, p) > 0
                    n += 1
        at = np.flatnonzero(total)
        yield pd.DataFrame({"feature": np.r_[-1, at], "df": np.r_[n, total[at]]})

    got = rows.select("text").mapInPandas(count, "feature int, df long").groupBy("feature").agg(F.sum("df").alias("df")).toPandas()
    df = np.zeros(p.buckets, np.int64)
    inside = got["feature"] >= 0
    df[got.loc[inside, "feature"].to_numpy(int)] = got.loc[inside, "df"]
    return df, int(got.loc[~inside, "df"].sum())


def labelled_sample(rows: DataFrame, label: str, per_label: int | dict) -> DataFrame:
    """About ``per_label`` rows of each label (or as many as it has for the label), the same ones in every run: those with the least hash of doc_id.

    A first pass over the thin columns counts the labels; joined to them, the
    counts give a threshold on the hash that thins the rows before any text
    moves. Labels that a dict leaves out, and null ones, have no rows. Adds the hash as ``h``.
    """
    whole = 1 << 30
    counts = rows.where(F.col(label).isNotNull()).groupBy(F.col(label).alias("_label")).agg(F.count(F.lit(1)).alias("_n"))
    most = F.lit(0 if isinstance(per_label, dict) else per_label)
    for k, v in (per_label if isinstance(per_label, dict) else {}).items():
        most = F.when(F.col("_label") == F.lit(k), F.lit(v)).otherwise(most)
    limits = counts.select("_label", F.least(F.lit(whole), F.floor(most * F.lit(float(whole)) / F.col("_n"))).alias("_limit"))
    limits = F.broadcast(limits) if limits.count() <= 100_000 else limits
    limits = F.broadcast(limits) if limits.count() <= 100_000 else limits
    thin = rows.withColumn("h", F.pmod(F.xxhash64("doc_id"), F.lit(whole)))
    return thin.join(limits, F.col(label) == F.col("_label")).where("h < _limit").drop("_label", "_limit")


def coded_rows(rows: DataFrame, p: LanguageParams) -> pd.DataFrame:
    """Sparse n-gram counts of the sampled rows, made where the texts are: the driver gets ``buckets`` numbers a row at most."""

    def code(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            counts = [n_grams(t, p) for t in batch["text"]]
            at = [np.flatnonzero(c) for c in counts]
            yield pd.DataFrame({
                "h": batch["h"], "doc_id": batch["doc_id"], "lang": batch["lang"],
                "at": [i.astype("<i4").tobytes() for i in at], "n": [c[i].astype("<i4").tobytes() for c, i in zip(counts, at)],
            })

    kind = dict(rows.dtypes)["doc_id"]
    got = rows.select("h", "doc_id", "lang", "text").mapInPandas(code, f"h long, doc_id {kind}, lang string, at binary, n binary").toPandas()
    return got.sort_values(["h", "doc_id"]).reset_index(drop=True)


def fit_languages(rows: DataFrame, p: LanguageParams = LanguageParams()) -> LanguageModel:
    """Learn from ``rows`` (doc_id, text, lang without null); weights from a bounded sample, frequencies from all."""
    df, n = document_frequencies(rows, p)
    idf = np.log((1 + n) / (1 + df)) + 1.0
    sample = coded_rows(labelled_sample(rows, "lang", p.per_label), p)
    labels = sorted(sample["lang"].unique())
    coded = [
        (*features(np.frombuffer(at, "<i4"), np.frombuffer(k, "<i4"), idf), labels.index(label))
        for at, k, label in zip(sample["at"], sample["n"], sample["lang"])
    ]
    held = [x for i, x in enumerate(coded) if i % 5 == 0]
    learned = [x for i, x in enumerate(coded) if i % 5] or held
    model, order = Ftrl(p.buckets, len(labels), p), np.random.default_rng(p.seed)
    for _ in range(p.epochs):
        for i in order.permutation(len(learned)):
            model.learn(*learned[i])
    w = model.weights(slice(None))
    logits = np.array([v @ w[at] for at, v, _ in held]).reshape(len(held), len(labels))
    return LanguageModel(labels, idf, w, fitted_temperature(logits, np.array([k for *_, k in held], int)), p)


def predicted_languages(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """doc_id, lang_pred, score of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # labels x features: bounded by the parameters

    def predict(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        m = shared.value
        for batch in batches:
            got = [m.predict(t) for t in batch["text"]]
            yield pd.DataFrame({"doc_id": batch["doc_id"], "held_out": batch["held_out"], "lang_pred": [x for x, _ in got], "score": [s for _, s in got]})

    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", "held_out", "text").mapInPandas(predict, f"doc_id {kind}, held_out boolean, lang_pred string, score double")


def identified(docs: DataFrame, params: LanguageParams = LanguageParams(), folds: int = 3, held: int = 1) -> DataFrame:
    """One row per document: doc_id, held_out, lang_pred, score.

    ``docs`` needs doc_id, text and lang; other columns are ignored. Rows whose
    crc32(doc_id) leaves the remainder ``held`` are never learned from, nor are
    null languages or texts. Null doc_ids are held out. Texts that are null or
    have no letter get ``und`` with score 0; so do all texts if nothing can be
    learned. Whole texts are scored. Repeated rows are scored each.
    """
    docs = docs.select("doc_id", "text", "lang", F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % folds == held, F.lit(True)).alias("held_out"))
    train = docs.where("not held_out and lang is not null and text is not null")
    with small_batches(docs.sparkSession):
        return written(predicted_languages(docs, fit_languages(train, params)), "languages")


def op8_language_id(spark, sf_dir: str) -> DataFrame:
    return identified(documents(spark, sf_dir))
