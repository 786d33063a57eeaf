"""Toxicity by fuzzy lexicon matches and the context that they stand in.

The lexicon is learned: beginnings of words that are common in toxic training
documents and rare in the others. Its trie is intersected with Levenshtein
automata of one edit; the states of the product are made as texts need them, so
most words leave it after a few letters. Each match is weighed by a window of
words around it, which tells quotation and report from direct abuse, and a
logistic regression over the sums gives the score.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .langid import labelled_sample
from .storage import discarded, free_name, release_memory, small_batches, written
from .text import documents

WORDS = regex.compile(r"[^\W\d_]+")
TOKENS = regex.compile(r"[^\W\d_]+|[\"“”„«»‹›‘’]")
QUOTES = frozenset("\"“”„«»‹›‘’")
#: Words that report what others say, and words that address someone.
REPORTING = frozenset("said says wrote writes quoted quote called reported sagte schrieb zitat dit écrit citation dijo escribió cita".split())
ADDRESSING = frozenset("you your you're u du dich dein ihr tu te ton toi vous tú ti usted".split())


@dataclass(frozen=True)
class ToxicityParams:
    """toxic_rows, clean_rows: about how many labelled rows of each label the fit uses."""

    toxic_rows: int = 1500
    clean_rows: int = 5000
    least_letters: int = 4
    fuzzy_letters: int = 5
    least_share: float = 0.01
    least_rows: int = 5
    least_lift: float = 40.0
    window: int = 6
    ridge: float = 1e-3


class FuzzyTrie:
    """The product of a trie of terms and Levenshtein automata, determinised lazily.

    A term matches a word that begins with it after at most ``edits`` edits of
    the term; terms shorter than ``fuzzy_letters`` match exactly.
    """

    def __init__(self, terms: list[str], fuzzy_letters: int, edits: int = 1):
        self.next: list[dict[str, int]] = [{}]
        self.ends = [False]
        self.may = [0]  # edits that the longest term through the node allows
        for term in terms:
            allowed, node = edits if len(term) >= fuzzy_letters else 0, 0
            for c in term:
                if c not in self.next[node]:
                    self.next[node][c] = len(self.next)
                    self.next.append({})
                    self.ends.append(False)
                    self.may.append(0)
                node = self.next[node][c]
                self.may[node] = max(self.may[node], allowed)
            self.ends[node] = True
        self.may[0] = max(self.may)
        self.length = {t: len(t) for t in terms}
        self.states: dict[frozenset, int] = {}
        self.sets: list[frozenset] = []
        self.accepts: list[int | None] = []
        self.moves: list[dict[str, int]] = []
        self.start = self._state({(0, 0)})

    def _state(self, pairs: set[tuple[int, int]]) -> int:
        todo = list(pairs)
        while todo:  # letters of the term that the word leaves out
            node, e = todo.pop()
            for child in self.next[node].values():
                if e < self.may[child] and (child, e + 1) not in pairs:
                    pairs.add((child, e + 1))
                    todo.append((child, e + 1))
        least: dict[int, int] = {}
        for node, e in pairs:
            least[node] = min(e, least.get(node, e))
        key = frozenset(least.items())
        if key not in self.states:
            self.states[key] = len(self.sets)
            self.sets.append(key)
            self.accepts.append(min((e for node, e in key if self.ends[node] and e <= self.may[node]), default=None))
            self.moves.append({})
        return self.states[key]

    def _move(self, state: int, c: str) -> int:
        out: set[tuple[int, int]] = set()
        for node, e in self.sets[state]:
            for letter, child in self.next[node].items():
                if letter == c:
                    out.add((child, e))
                elif e < self.may[child]:
                    out.add((child, e + 1))
            if e < self.may[node]:
                out.add((node, e + 1))
        return self._state(out) if out else -1

    def edits(self, word: str) -> int | None:
        """The least edits with which a term begins the word, or None."""
        state, best = self.start, None
        for c in word:
            move = self.moves[state].get(c)
            if move is None:
                move = self.moves[state][c] = self._move(state, c)
            if move < 0:
                break
            state = move
            found = self.accepts[state]
            if found is not None and (best is None or found < best):
                best = found
                if best == 0:
                    break
        return best


FEATURES = ("exact", "fuzzy", "quoted", "addressed", "distinct", "share")


@dataclass
class Scanner:
    """Finds lexicon matches in texts and sums up their contexts."""

    terms: list[str]
    params: ToxicityParams
    trie: FuzzyTrie = field(init=False)
    seen: dict[str, int | None] = field(init=False, default_factory=dict)

    def __post_init__(self):
        self.trie = FuzzyTrie(self.terms, self.params.fuzzy_letters)

    def matches(self, words: set[str]) -> dict[str, int]:
        if len(self.seen) > 200_000:
            self.seen.clear()
        for w in words.difference(self.seen):
            self.seen[w] = self.trie.edits(w)
        return {w: e for w in words if (e := self.seen[w]) is not None}

    def features(self, text: str | None) -> np.ndarray:
        """Zeros for null and empty texts and texts without a match."""
        out = np.zeros(len(FEATURES))
        if not isinstance(text, str) or not text or not self.terms:
            return out
        text = text.lower()
        words = WORDS.findall(text)
        hits = self.matches(set(words))
        if not hits:
            return out
        exact = fuzzy = quoted = addressed = 0.0
        tokens, k = TOKENS.findall(text), self.params.window
        opened, inside = 0, []
        for t in tokens:  # whether an odd number of quotation marks came before
            opened ^= t in QUOTES
            inside.append(opened)
        for i, t in enumerate(tokens):
            e = hits.get(t)
            if e is None:
                continue
            near = tokens[max(0, i - k) : i + k + 1]
            closed = inside[i] and any(x in QUOTES for x in tokens[i + 1 : i + 1 + 4 * k])
            if closed or any(x in REPORTING for x in near):
                quoted += 1
            elif e == 0:
                exact += 1
            else:
                fuzzy += 1
            addressed += any(x in ADDRESSING for x in near)
        out[:] = math.log1p(exact), math.log1p(fuzzy), math.log1p(quoted), math.log1p(addressed), math.log1p(len(hits)), min(1.0, 20 * (exact + fuzzy) / len(words))
        return out


@dataclass(frozen=True)
class ToxicityModel:
    terms: list[str]
    weights: np.ndarray
    params: ToxicityParams

    def score(self, x: np.ndarray) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.weights[0] + x @ self.weights[1:], -30, 30))))


def beginnings(text: str, least: int) -> set[str]:
    return {w[:i] for w in set(WORDS.findall(text.lower())) for i in range(least, len(w) + 1)}


def rows_with(rows: DataFrame, p: ToxicityParams) -> DataFrame:
    """term, n: in how many rows a word begins with the term."""

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total: Counter[str] = Counter()
        for batch in batches:
            for text in batch["text"]:
                total.update(beginnings(text, p.least_letters))
                if len(total) > 500_000:
                    yield pd.DataFrame({"term": list(total), "n": list(total.values())})
                    total.clear()
        if total:
            yield pd.DataFrame({"term": list(total), "n": list(total.values())})

    return rows.select("text").mapInPandas(count, "term string, n long").groupBy("term").agg(F.sum("n").alias("n"))


def learned_terms(toxic: DataFrame, clean: DataFrame, n_toxic: int, n_clean: int, p: ToxicityParams) -> list[str]:
    """Beginnings of words that toxic rows have ``least_lift`` times as often as clean ones; of nested ones the most general."""
    least = max(p.least_rows, p.least_share * n_toxic)
    against = rows_with(clean, p).withColumnRenamed("n", "against")
    lift = (F.col("n") / F.lit(max(n_toxic, 1))) / ((F.coalesce("against", F.lit(0)) + F.lit(0.5)) / F.lit(n_clean + 1))
    found = rows_with(toxic, p).where(F.col("n") >= least).join(against, "term", "left").where(lift >= p.least_lift)
    common = {r["term"]: r["n"] for r in found.select("term", "n").collect()}  # a longer term with as many toxic rows passes too
    longer = {(x[:-1], n) for x, n in common.items()}
    chosen: set[str] = set()
    for t in sorted(common, key=lambda t: (len(t), t)):
        if (t, common[t]) not in longer and not any(t[:i] in chosen for i in range(1, len(t))):
            chosen.add(t)
    return sorted(chosen, key=lambda t: (-common[t], t))


def logistic(x: np.ndarray, y: np.ndarray, ridge: float, steps: int = 50) -> np.ndarray:
    """Weights with the intercept first, by Newton's method. Rows count alike, so what says nothing is as likely as the share."""
    x = np.c_[np.ones(len(x)), x]
    w, penalty = np.zeros(x.shape[1]), ridge * len(y) * np.diag([1e-6] + [1.0] * (x.shape[1] - 1))
    for _ in range(steps):
        m = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (m * (1 - m))[:, None]).T @ x + penalty + 1e-9 * np.eye(len(w)), x.T @ (m - y) + penalty @ w)
        w -= np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-8:
            break
    return w


def fit_toxicity(docs: DataFrame, labels: DataFrame, p: ToxicityParams = ToxicityParams()) -> ToxicityModel:
    """Learn from a bounded sample of each label, outside the held-out fold."""
    with small_batches(docs.sparkSession):
        sample = training_sample(docs, labels, p)
        model = learned(sample, p)
        discarded(sample)
        return model


def learned(sample: DataFrame, p: ToxicityParams) -> ToxicityModel:
    """The lexicon and weights of a sample (doc_id, text, toxic)."""
    n = {r["toxic"]: r["n"] for r in sample.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not n.get(0) or not n.get(1):
        return ToxicityModel([], np.r_[-3.0, np.zeros(len(FEATURES))], p)
    terms = learned_terms(sample.where("toxic = 1"), sample.where("toxic = 0"), n[1], n[0], p)

    def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        scanner = Scanner(terms, p)
        for batch in batches:
            x = np.array([scanner.features(t) for t in batch["text"]]).reshape(len(batch), len(FEATURES))
            yield pd.DataFrame(x, columns=list(FEATURES)).assign(toxic=batch["toxic"].to_numpy(), doc_id=batch["doc_id"].to_numpy())

    kind = dict(sample.dtypes)["doc_id"]
    got = sample.mapInPandas(scan, ", ".join(f"{f} double" for f in FEATURES) + f", toxic int, doc_id {kind}").toPandas().sort_values("doc_id")
    return ToxicityModel(terms, logistic(got[list(FEATURES)].to_numpy(), got["toxic"].to_numpy(float), p.ridge), p)


def score_names(columns: list[str]) -> tuple[str, str]:
    """What the columns of score and prediction are called: tox_score and tox_predicted, with underscores before them where a column has that name."""
    return free_name(columns, "tox_score"), free_name(columns, "tox_predicted")


def toxicity_scores(docs: DataFrame, model: ToxicityModel, keep: list[str] | None = None) -> DataFrame:
    """The columns ``keep`` of every row, with tox_score (0 to 1) and tox_predicted (1 from a score of 0.5 on), see ``score_names``.

    ``docs`` needs text. The table is written, in small batches of texts.
    """
    keep = ["doc_id"] if keep is None else keep
    shared = docs.sparkSession.sparkContext.broadcast(model)  # terms that common enough toxic rows of the sample have
    names = score_names(keep)
    inputs = list(dict.fromkeys([*keep, "text"]))
    at = inputs.index("text")

    def score(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        model = shared.value
        scanner = Scanner(model.terms, model.params)
        for batch in batches:
            s = [model.score(scanner.features(t)) for t in batch.iloc[:, at]]
            out = batch if len(keep) == len(inputs) else batch.iloc[:, : len(keep)]
            yield out.assign(**{names[0]: s, names[1]: [int(x >= 0.5) for x in s]})
        scanner = batch = s = out = None
        release_memory()

    kinds = dict(docs.dtypes)
    schema = ", ".join([*(f"`{c}` {kinds[c]}" for c in keep), f"{names[0]} double", f"{names[1]} int"])
    with small_batches(docs.sparkSession):
        return written(docs.select(*inputs).mapInPandas(score, schema), "toxicity-scores")


def training_sample(docs: DataFrame, labels: DataFrame, p: ToxicityParams, folds: int = 5, held: int = 0) -> DataFrame:
    """doc_id, text, toxic of a bounded number of labelled rows of each label outside the held-out fold.

    Of several labels of a document the largest counts. The labels alone are
    sampled; they are then so few that the texts need not be shuffled.
    """
    marks = labels.where("toxic is not null and doc_id is not null").groupBy("doc_id").agg((F.max("toxic") > 0).cast("int").alias("toxic"))
    few = labelled_sample(marks.where(~held_out(folds, held)), "toxic", {0: p.clean_rows, 1: p.toxic_rows}).select("doc_id", "toxic")
    return written(docs.where(F.col("text").isNotNull()).select("doc_id", "text").join(F.broadcast(few), "doc_id"), "toxicity-sample")


def held_out(folds: int = 5, held: int = 0):
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % folds == held, F.lit(True))


def scored(docs: DataFrame, labels: DataFrame, params: ToxicityParams = ToxicityParams()) -> DataFrame:
    """One row per document: doc_id, held_out, score, predicted.

    ``docs`` needs doc_id and text, ``labels`` doc_id and toxic; other columns
    are ignored. Labels of documents whose crc32(doc_id) is divisible by 5 are
    never learned from, nor are null labels. Null and empty texts score as
    texts without a match; without labels of both kinds every text does.
    Whole texts are scored, repeated rows each. Null doc_ids are held out.
    """
    model = fit_toxicity(docs, labels, params)
    rows = docs.select("doc_id", held_out().alias("held_out"), "text")
    return toxicity_scores(rows, model, ["doc_id", "held_out"]).select(
        "doc_id", "held_out", F.col("tox_score").alias("score"), F.col("tox_predicted").alias("predicted")
    )


def op10_toxicity(spark, sf_dir: str) -> DataFrame:
    return scored(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))
