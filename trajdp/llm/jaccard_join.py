"""Jaccard metric-space join of documents' word shingles, exact, with the classes of linked documents.

Copies of a set are one point of the metric space. Points whose sets share none
of their rarest shingles are farther apart than the limit, which cuts the space
into first regions, one for each such shingle. In every region pivots are chosen.
A region of a few points has each of them as a pivot. In a larger one every point
is measured to all pivots: pairs with a pivot that may be within the limit are
compared, pivots that lie apart become the centres of Voronoi regions, and the
triangle inequality replicates a point into each region whose centre is nearer than
its own centre plus twice the limit. Regions that fall apart in this way are joined
again; large ones that don't are first cut by the next rare shingle that two linked
sets must share, and others get more pivots.

Distances to pivots come from a sketch of each set: its size and the parities of
its shingles in 1024 classes. With h, the larger of the number of parities that
differ and the difference of sizes, 2 h / (n + m + h) is a metric (h is one, and
sizes differ by no more than h) and never above the Jaccard distance, so that its
windows lose no pair. Pairs it can't tell apart are compared by their whole texts,
each point's nearest first, and the others only if no links join them by then. How
common shingles are is told by a sketch of bounded size; any order of them gives
exact results, a good one small regions.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .exact_dedup import block_pattern
from .storage import by_size, discarded, release_memory, small_batches, written
from .text import documents

U = np.uint64
ODD = U(0x9E3779B97F4A7C15)
SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
LETTER = np.random.default_rng(20).integers(1, 1 << 63, 256, dtype=np.uint64)


@dataclass(frozen=True)
class JoinParams:
    """Linked: percent * union <= 100 * intersection. few: points of a region that are all pivots. pivots: about how many
    a larger region has at first, eight times as many in each later round. chunk: points measured in one group, and the
    most pivots. cut: points of a region from which on it is cut by one more shingle, if Voronoi regions don't share them
    out. extra: how many more shingles than the first cut needs are kept for that."""

    span: int = 5
    percent: int = 80
    few: int = 16
    pivots: int = 64
    chunk: int = 4096
    cut: int = 65_536
    extra: int = 4
    sketch_bits: int = 18
    most_blocks: int = 1 << 20
    slice_bytes: int = 2_000_000


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


class Shingler:
    """Sets of 64-bit shingle hashes of whole texts, for many texts at once."""

    def __init__(self, span: int):
        self.span = span
        self.up = self.down = np.ones(1, np.uint64)

    def powers(self, n: int) -> None:
        if len(self.up) < n:
            self.up = np.cumprod(np.r_[U(1), np.full(n - 1, ODD)])
            self.down = np.cumprod(np.r_[U(1), np.full(n - 1, U(pow(int(ODD), -1, 1 << 64)))])

    def sets(self, texts: list[str | None]) -> list[np.ndarray]:
        """Sorted distinct hashes of each text's shingles; A-Z are lower-cased, null texts have none."""
        raw = [t.encode("utf-8", "surrogatepass").lower() if isinstance(t, str) else b"" for t in texts]
        data = np.frombuffer(b" " + b" ".join(raw) + b" ", np.uint8)
        ends = np.cumsum([1 + len(r) for r in raw])
        space = SPACE[data]
        begin = np.flatnonzero(space[:-1] & ~space[1:]) + 1
        stop = np.flatnonzero(~space[:-1] & space[1:]) + 1
        self.powers(len(data))
        total = np.r_[U(0), np.cumsum(LETTER[data] * self.up[: len(data)])]
        word = mixed((total[stop] - total[begin]) * self.down[begin])
        first = np.searchsorted(begin, np.r_[0, ends])
        out = []
        h = np.zeros(max(0, len(word) - self.span + 1), np.uint64)
        for k in range(self.span):
            h = mixed(h + word[k : k + len(h)] + U(k + 1))
        for i, j in zip(first[:-1].tolist(), first[1:].tolist()):
            if j - i >= self.span:
                out.append(np.unique(h[i : j - self.span + 1]))
            elif j > i:
                whole = np.full(1, 1000 + j - i, np.uint64)
                for x in word[i:j]:
                    whole = mixed(whole * ODD + x)
                out.append(whole)
            else:
                out.append(np.zeros(0, np.uint64))
        return out


def in_slices(batches: Iterator[pd.DataFrame], size: int, *columns: str) -> Iterator[pd.DataFrame]:
    """Parts of the batches with about ``size`` characters of text."""
    for batch in batches:
        long = sum(batch[c].str.len().fillna(0).to_numpy(float) for c in columns)
        part = (np.cumsum(long) // size).astype(int)
        for _, rows in batch.groupby(part, sort=False):
            yield rows


def shingle_sketch(docs: DataFrame, p: JoinParams) -> np.ndarray:
    """How many documents have a shingle in each of 2^sketch_bits buckets, over all documents."""

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingler, total = Shingler(p.span), np.zeros(1 << p.sketch_bits, np.int64)
        for rows in in_slices(batches, p.slice_bytes, "text"):
            sets = shingler.sets(rows["text"].tolist())
            total += np.bincount((np.concatenate(sets) >> U(64 - p.sketch_bits)).astype(np.int64), minlength=len(total))
        at = np.flatnonzero(total)
        if len(at):
            yield pd.DataFrame({"bucket": at.astype(np.int32), "n": total[at]})
        release_memory()

    got = docs.select("text").mapInPandas(count, "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n")).toPandas()
    sketch = np.zeros(1 << p.sketch_bits, np.int64)
    sketch[got["bucket"].to_numpy(int)] = got["n"].to_numpy(np.int64)
    return sketch


def points(docs: DataFrame, sketch: np.ndarray, p: JoinParams) -> DataFrame:
    """doc_id, text_hash, n, fp1, fp2, first, rare, odd: size and fingerprint of each set, its rarest shingles, the first of which
    two linked sets must share one, and the parities of its classes."""
    shared = docs.sparkSession.sparkContext.broadcast(sketch)
    names = ["n", "fp1", "fp2", "first", "rare", "odd"]

    def shingled(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingler, sketch = Shingler(p.span), shared.value
        for rows in in_slices(batches, p.slice_bytes, "text"):
            out = []
            for h in shingler.sets(rows["text"].tolist()):
                n = len(h)
                often = sketch[(h >> U(64 - p.sketch_bits)).astype(np.int64)]
                keep = n - (p.percent * n + 99) // 100 + 1 if n else 0
                at = np.lexsort((h, often))[: keep + p.extra]
                m = mixed(h + ODD)
                parity = np.packbits((np.bincount((m & U(1023)).astype(np.int64), minlength=1024) & 1).astype(np.uint8)).view(np.int64)
                out.append((n, int(m.sum().view(np.int64)) if n else 0, int(np.bitwise_xor.reduce(mixed(m)).view(np.int64)) if n else 0, keep, h[at].view(np.int64), parity))
            keys = {k: rows[k].to_numpy() for k in ("doc_id", "text_hash")}
            yield pd.DataFrame(out, columns=names).assign(**keys)[["doc_id", "text_hash", *names]]
        release_memory()

    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", "text", F.xxhash64("text").alias("text_hash")).mapInPandas(shingled, f"doc_id {kind}, text_hash long, n long, fp1 long, fp2 long, first int, rare array<long>, odd array<long>")


def measured_pairs(pairs: DataFrame, docs: DataFrame, p: JoinParams) -> DataFrame:
    """a, b, both, either: sizes of intersection and union of each pair's sets, from the whole texts.

    A Bloom filter of bounded size keeps most other documents out of the shuffle.
    """
    spark = docs.sparkSession
    ids = pairs.select(F.col("a").alias("id")).union(pairs.select(F.col("b").alias("id"))).distinct()
    blocks = 1 << 10
    while blocks < min(p.most_blocks, ids.count() // 4):
        blocks *= 2
    hashes = lambda c: block_pattern(F.xxhash64(F.lit(4), c), F.xxhash64(F.lit(5), c), blocks)
    block, pattern = hashes(F.col("id"))
    bloom = ids.select(block.alias("block"), pattern.alias("pattern")).groupBy("block").agg(F.bit_or("pattern").alias("filter"))
    block, pattern = hashes(F.col("id"))
    texts = docs.select(F.col("doc_id").alias("id"), "text").withColumn("block", block).withColumn("pattern", pattern)
    texts = texts.join(F.broadcast(bloom), "block").where(F.col("filter").bitwiseAND(F.col("pattern")) == F.col("pattern")).select("id", "text")
    one = pairs.join(texts.select(F.col("id").alias("b"), F.col("text").alias("text_b")), "b")
    two = one.join(texts.select(F.col("id").alias("a"), F.col("text").alias("text_a")), "a")

    def measure(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        shingler, key, left = Shingler(p.span), None, None
        for rows in in_slices(batches, p.slice_bytes, "text_b"):
            right, out = shingler.sets(rows["text_b"].tolist()), []
            for a, text, b, h in zip(rows["a"], rows["text_a"], rows["b"], right):
                if key is None or a != key:
                    key, left = a, shingler.sets([text])[0]
                at = np.searchsorted(left, h)
                at[at == len(left)] = 0
                both = int((left[at] == h).sum()) if len(left) else 0
                out.append((a, b, both, len(left) + len(h) - both))
            yield pd.DataFrame(out, columns=["a", "b", "both", "either"])
        release_memory()

    kind = dict(docs.dtypes)["doc_id"]
    with small_batches(spark, 200):
        return written(two.select("a", "b", "text_a", "text_b").mapInPandas(measure, f"a {kind}, b {kind}, both long, either long"), "join-pairs")


def differing(x: Column, n: Column, y: Column, m: Column) -> Column:
    """The sketch's part of two sets' symmetric difference, from parities and sizes."""
    parities = F.aggregate(F.zip_with(x, y, lambda u, v: F.bit_count(u.bitwiseXOR(v))), F.lit(0), lambda a, u: a + u)
    return F.greatest(parities.cast("long"), F.abs(n - m))


def distance(h: Column, total: Column) -> Column:
    """The sketch's distance of two sets with ``total`` elements."""
    return 2.0 * h / (total + h)


def within(h: Column, total: Column, p: JoinParams) -> Column:
    """Whether sets with ``total`` elements that differ by ``h`` of them are within the limit."""
    return h * (100 + p.percent) <= total * (100 - p.percent)


def chance(x: Column) -> Column:
    """A number from 0 on, below 2^62, told by the point alone: the same points are pivots wherever they meet."""
    return F.xxhash64(F.lit(6), x).bitwiseAND(F.lit((1 << 62) - 1))


def small_region_pairs(small: DataFrame, about: DataFrame, p: JoinParams) -> DataFrame:
    """a, b, rank, far: the sketch's distance of the pairs of regions in which every point is a pivot, where it is within the limit."""
    mine = small.join(about.select("id", "n"), "id").select("region", "id", "n")
    other = mine.select("region", F.col("id").alias("b"), F.col("n").alias("m"))
    near = F.least("n", "m") * 100 >= F.greatest("n", "m") * p.percent  # else the sizes alone keep them apart
    pairs = mine.join(other, "region").where((F.col("id") < F.col("b")) & near).select(F.col("id").alias("a"), "b").distinct()
    side = lambda k: about.select(F.col("id").alias(k), F.col("n").alias(f"{k}_n"), F.col("odd").alias(f"{k}_odd"))
    pairs = pairs.join(side("a"), "a").join(side("b"), "b")
    pairs = pairs.withColumn("h", differing(F.col("a_odd"), F.col("a_n"), F.col("b_odd"), F.col("b_n")))
    total = F.col("a_n") + F.col("b_n")
    return pairs.where(within(F.col("h"), total, p)).select("a", "b", F.lit(0).alias("rank"), distance(F.col("h"), total).alias("far"))


def measured_to_pivots(large: DataFrame, about: DataFrame, label: DataFrame | None, pivots: int, p: JoinParams) -> DataFrame:
    """region, id, at, level, is_pivot, over, near, cells, centres of each point of large regions.

    near: (rank, distance, pivot) of the pivots that may be within the limit and have another class so far; centres
    have rank 0 and are compared first, so that a dense place becomes one star and not one for each pivot. cells: the
    centres whose Voronoi region, widened by twice the limit, holds the point. over: the pivots were all points outside
    one class, so that the region is done. Regions of a single class are left out.
    """
    rows = large.join(about.select("id", "n", "odd"), "id").withColumn("chance", chance(F.col("id")))
    rows = rows.withColumn("class", F.col("id")) if label is None else rows.join(label, "id", "left").withColumn("class", F.coalesce("class", "id"))
    rows = written(rows, "join-large")
    stats = rows.groupBy("region").agg(
        F.count(F.lit(1)).alias("size"), F.min("chance").alias("low"), F.min_by("class", "chance").alias("lead"), F.min("class").alias("one"), F.max("class").alias("two")
    ).where("one <> two")
    marked = rows.join(stats.select("region", "size", "low", "lead"), "region")
    # where few points lie outside the class of the least one, these are the pivots: what is left has one class
    strangers = marked.groupBy("region").agg(F.sum((F.col("class") != F.col("lead")).cast("int")).alias("strangers"))
    marked = marked.join(strangers, "region")
    share = F.floor(F.lit(float(1 << 62)) * pivots / F.col("size")).cast("long")
    own = F.when(F.col("strangers") <= pivots, F.col("class") != F.col("lead")).otherwise(F.col("chance") <= F.greatest("low", share))
    marked = marked.withColumn("is_pivot", own).withColumn("over", F.col("strangers") <= pivots).withColumn("chunks", F.ceil(F.col("size") / p.chunk).cast("int"))
    marked = written(marked.drop("strangers", "lead", "low", "size"), "join-marked")
    columns = ["region", "chunk", "id", "at", "level", "is_pivot", "over", "class", "n", "odd", "chance"]
    dealt = marked.withColumn("chunk", F.pmod(F.xxhash64(F.lit(9), "id"), F.col("chunks")).cast("int")).select(F.lit(0).alias("role"), *columns)
    every = marked.where("is_pivot").withColumn("chunk", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1))).select(F.lit(1).alias("role"), *columns)
    kind = dict(about.dtypes)["id"]

    def measure(rows: pd.DataFrame) -> pd.DataFrame:
        """A part of a region's points against all of its pivots."""
        mine, far_ones = rows[rows["role"] == 0], rows[rows["role"] == 1].sort_values(["chance", "id"])
        ids, other = mine["id"].to_numpy(), far_ones["id"].to_numpy()
        odd, there = (np.stack(x["odd"].to_numpy()).view(np.uint64) if len(x) else np.zeros((0, 16), np.uint64) for x in (mine, far_ones))
        n, m = mine["n"].to_numpy(np.int64), far_ones["n"].to_numpy(np.int64)

        def compared(x: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            """Whether the sketch may be within the limit, and its distance, of rows to pivots."""
            h = np.maximum(np.bitwise_count(x[:, None] ^ there[None]).sum(axis=2, dtype=np.int64), np.abs(sizes[:, None] - m))
            total = sizes[:, None] + m
            return h * (100 + p.percent) <= total * (100 - p.percent), 2.0 * h / (total + h)

        central = np.ones(len(other), bool)
        for i in range(0, len(other), 64):
            part = np.arange(i, min(i + 64, len(other)))
            central[part] = ~(compared(there[part], m[part])[0] & (np.arange(len(other)) < part[:, None])).any(axis=1)
        limit, centre, out = 1 - p.percent / 100, np.flatnonzero(central), {"near": [], "rank": [], "far": [], "cells": []}
        mark, marks = mine["class"].to_numpy(), far_ones["class"].to_numpy()
        for i in range(0, len(ids), 64):
            part = slice(i, i + 64)
            near, far = compared(odd[part], n[part])
            near &= mark[part, None] != marks
            home = far[:, centre].min(axis=1, keepdims=True)
            inside = far[:, centre] <= home + 2 * limit + 1e-9
            for row, distances, cells in zip(near, far, inside):
                at = np.flatnonzero(row)
                out["near"].append(other[at])
                out["rank"].append((~central[at]).astype(np.int32))
                out["far"].append(distances[at])
                out["cells"].append(other[centre[cells]])
        apart = sum(map(len, out["cells"])) <= 2 * len(ids)
        if not apart:  # replicated over and over, the points are better cut another way
            out["cells"] = [other[:0]] * len(ids)
        return mine[["region", "id", "at", "level", "is_pivot", "over"]].assign(**out, centres=np.int32(len(centre) if apart else 0))

    schema = f"region long, id {kind}, at int, level int, is_pivot boolean, over boolean, near array<{kind}>, rank array<int>, far array<double>, cells array<{kind}>, centres int"
    out = written(dealt.unionByName(every).groupBy("region", "chunk").applyInPandas(measure, schema), "join-judged")
    discarded(rows, marked)
    return out


def next_regions(judged: DataFrame, about: DataFrame, label: DataFrame, pivots: int, p: JoinParams) -> DataFrame:
    """region, id, at, level of the points that are no pivots, of regions that links have not made one class: as they are
    where few points lie outside a class (the next pivots), in Voronoi regions where these share out the points, else
    cut by each later shingle of which linked sets share one more."""
    left = judged.where("not is_pivot and not over").select("region", "id", "at", "level", "cells", "centres")
    left = left.join(label, "id", "left").withColumn("class", F.coalesce("class", "id"))
    spread = left.groupBy("region").agg(
        (F.min("centres") > 1).alias("apart"), F.count(F.lit(1)).alias("left"), F.min("class").alias("one"), F.max("class").alias("two"), F.min_by("class", chance(F.col("id"))).alias("lead")
    ).where("one <> two")
    left = written(left.join(spread.drop("one", "two"), "region"), "join-left")
    strangers = left.groupBy("region").agg(F.sum((F.col("class") != F.col("lead")).cast("int")).alias("strangers"))
    left = left.join(strangers, "region").withColumn("few", F.col("strangers") <= pivots)
    apart = F.col("apart") & ~F.col("few")
    voronoi = left.where(apart).select("region", F.explode("cells").alias("cell"), "id", "at", "level")
    voronoi = voronoi.select(F.xxhash64(F.lit(7), "region", "cell").alias("region"), "id", "at", "level")
    rest = left.where(~apart)
    # few enough points, or no more shingles: fewer points and more pivots
    stay = F.col("few") | (F.col("level") > p.extra) | (F.col("left") <= p.cut)
    whole = rest.where(stay).select("region", "id", "at", "level")
    cut = rest.where(~stay).join(about.select("id", "first", "rare"), "id")
    later = F.slice("rare", F.col("at") + 1, F.greatest(F.col("first") + F.col("level") - F.col("at"), F.lit(0)))
    cut = cut.select("region", "id", "at", "level", F.posexplode(later).alias("more", "shingle"))
    cut = cut.select(F.xxhash64(F.lit(8), "region", "shingle").alias("region"), "id", (F.col("at") + F.col("more") + 1).alias("at"), (F.col("level") + 1).alias("level"))
    return written(voronoi.unionByName(whole).unionByName(cut), "join-regions")


def linked_points(about: DataFrame, docs: DataFrame, p: JoinParams, trace: list | None = None) -> DataFrame:
    """id, class: the smallest id that links lead to, of every point within the limit of another.

    about: id, n, first, rare, odd of each point. trace: gets the counts of each round.
    """
    regions = about.select("id", F.posexplode(F.slice("rare", F.lit(1), F.col("first"))).alias("at", "region"))
    regions = regions.select("region", "id", (F.col("at") + 1).alias("at"), F.lit(1).alias("level"))
    links, label, tested, pivots, made = None, None, None, p.pivots, None
    close = f"100 * both >= {p.percent} * either"
    while True:
        # most regions have one point: they go before anything but numbers is moved
        size = regions.groupBy("region").agg(F.count(F.lit(1)).alias("size")).where("size > 1")
        members = written(regions.join(size, "region"), "join-members")
        discarded(made)
        direct = written(small_region_pairs(members.where(F.col("size") <= p.few), about, p), "join-direct")
        large = members.where(F.col("size") > p.few).drop("size")
        judged = None if large.isEmpty() else measured_to_pivots(large, about, label, pivots, p)
        pairs = direct
        if judged is not None:
            near = judged.select("id", F.explode(F.arrays_zip("near", "rank", "far")).alias("x"))
            pairs = pairs.unionByName(near.select(F.least("id", "x.near").alias("a"), F.greatest("id", "x.near").alias("b"), "x.rank", "x.far"))
        if label is not None:
            named = lambda k: label.select(F.col("id").alias(k), F.col("class").alias(f"{k}_class"))
            pairs = pairs.join(tested, ["a", "b"], "left_anti").join(named("a"), "a", "left").join(named("b"), "b", "left")
            pairs = pairs.where("coalesce(a_class, a) <> coalesce(b_class, b)").select("a", "b", "rank", "far")
        pairs = written(pairs, "join-pairs-to-compare")
        # each point's nearest first; of the others only pairs that these links leave apart
        one = pairs.groupBy("a").agg(F.min(F.struct("rank", "far", "b")).alias("t")).select("a", "t.b")
        two = pairs.groupBy("b").agg(F.min(F.struct("rank", "far", "a")).alias("t")).select("t.a", "b")
        first = written(one.union(two).distinct(), "join-first")
        found = measured_pairs(first, docs, p).where(close).select("a", "b")
        before, links = links, written(found if links is None else links.union(found), "join-links")
        old, label = label, classes(links)
        discarded(before, old)
        named = lambda k: label.select(F.col("id").alias(k), F.col("class").alias(f"{k}_class"))
        rest = pairs.select("a", "b").distinct().join(first, ["a", "b"], "left_anti").join(named("a"), "a", "left").join(named("b"), "b", "left")
        rest = written(rest.where("coalesce(a_class, a) <> coalesce(b_class, b)").select("a", "b"), "join-rest")
        compared = 0
        if not rest.isEmpty():
            before, links = links, written(links.union(measured_pairs(rest, docs, p).where(close).select("a", "b")), "join-links")
            old, label = label, classes(links)
            discarded(before, old)
        if judged is not None:
            before, tested = tested, written(first.union(rest) if tested is None else tested.union(first).union(rest), "join-tested")
            discarded(before)
        if trace is not None:
            few = members.where(F.col("size") <= p.few)
            row = {"regions": members.select("region").distinct().count(), "pivots_of_small": few.count(), "compared": first.count() + rest.count(), "pairs": pairs.count()}
            if judged is not None:
                left = judged.where("not is_pivot").agg(F.count(F.lit(1)).alias("points"), F.sum(F.size("cells")).alias("placed")).first()
                row |= {"large": large.select("region").distinct().count(), "pivots": judged.where("is_pivot").count(), "points": left["points"], "placed": left["placed"] or 0}
            trace.append(row)
        discarded(direct, pairs, first, rest)
        if judged is None:
            discarded(members, links, tested)
            return label
        made = next_regions(judged, about, label, pivots, p)
        discarded(members, judged)
        regions, pivots = made, min(8 * pivots, p.chunk)


def classes(links: DataFrame) -> DataFrame:
    """id, class: the smallest id that links lead to. Each round merges every point into its smallest neighbour."""
    links = written(links.select("a", "b"), "join-links")
    label = written(links.select(F.col("a").alias("id")).union(links.select(F.col("b").alias("id"))).distinct().withColumn("class", F.col("id")), "join-labels")
    while not links.isEmpty():
        both = links.union(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        to = written(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("to")), "join-steps")
        old, label = label, written(label.join(to.withColumnRenamed("a", "class"), "class", "left").select("id", F.coalesce("to", "class").alias("class")), "join-labels")
        ends = links.join(to.select("a", F.col("to").alias("x")), "a").join(to.select(F.col("a").alias("b"), F.col("to").alias("y")), "b")
        gone, links = links, written(ends.where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), "join-links")
        discarded(old, gone, to)
    discarded(links)
    return label


def by_own_ids(docs: DataFrame, p: JoinParams, trace: list | None) -> DataFrame:
    """As ``near_duplicates`` where rows share a doc_id but no text: they get numbers of their own meanwhile."""
    rows = written(docs.withColumn("own", F.monotonically_increasing_id()), "join-own")
    found = near_duplicates(rows.select(F.col("own").alias("doc_id"), "text"), p, trace)
    found = written(rows.select("own", "doc_id").join(found.withColumnRenamed("doc_id", "own"), "own").drop("own"), "join-own-classes")
    least = found.where("n_shingles > 0").groupBy("component_id").agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("size"))
    full = by_size(found.where("n_shingles > 0"), least, ["component_id"], "size")
    discarded(rows)
    return full.select("doc_id", "n_shingles", F.col("least").alias("component_id"), "text_hash").unionByName(
        found.where("n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"), "text_hash"))


def near_duplicates(docs: DataFrame, p: JoinParams = JoinParams(), trace: list | None = None) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id, text_hash.

    ``docs`` needs doc_id and text; other columns are ignored. Texts are
    lower-cased in A-Z and cut at ASCII white space; a text with fewer words
    than ``span`` is one shingle. Null and empty texts have no shingle and are
    linked with nothing. Rows with a null doc_id count as copies of their text
    only: their component is that of equal texts, null if there are none.
    Repeated rows are listed each; rows that share a doc_id but no text have
    a different ``text_hash``. An empty table gives no rows. ``trace`` gets the counts
    of regions, pivots and comparisons of each round.
    """
    docs = docs.select("doc_id", "text")
    with small_batches(docs.sparkSession):
        table = written(points(docs, shingle_sketch(docs, p), p), "join-points")
    fp = ["n", "fp1", "fp2"]
    sets = written(
        table.where("n > 0").groupBy(*fp).agg(
            F.min("doc_id").alias("id"), F.count(F.lit(1)).alias("copies"), F.first("first").alias("first"), F.first("rare").alias("rare"), F.first("odd").alias("odd")
        ),
        "join-sets",
    )
    about = sets.where("id is not null").select("id", "n", "first", "rare", "odd")
    if not about.groupBy("id").agg(F.count(F.lit(1)).alias("sets")).where("sets > 1").isEmpty():
        return by_own_ids(docs, p, trace)
    label = linked_points(about, docs.where("doc_id is not null"), p, trace)
    named = sets.select(*fp, "id", "copies").join(label, "id", "left").withColumn("component_id", F.coalesce("class", "id"))
    named = written(named.select(*fp, "copies", "component_id"), "join-classes")
    discarded(sets, label)
    full = by_size(table.where("n > 0").select("doc_id", "text_hash", *fp), named, fp, "copies")
    empty = table.where("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"), "text_hash")
    return full.select("doc_id", F.col("n").alias("n_shingles"), "component_id", "text_hash").unionByName(empty)


def op7_jaccard_join(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(documents(spark, sf_dir), JoinParams(span=3, percent=90))
