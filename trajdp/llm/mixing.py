"""Mixing sources to target weights by iterative proportional fitting.

Token counts are summed by cell: source, language and topic. Raking finds one
factor for each source, language and topic, so that the cells, multiplied by
their three factors, have the wanted marginals. Documents are then sampled with
a probability in proportion to their cell's product, scaled so that the expected
tokens meet the rate where no probability passes 1. Raking goes on until the margins
are met or come no nearer. Up to ``most_cells`` cells (they are counted) it is a fold over
arrays in one row; beyond, factor tables are summed by key and written after each margin.
"""

from __future__ import annotations

import logging
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .storage import discarded, free_name, written
from .text import documents, words

MARGINS = ("source", "lang", "topic")
NONE = "(none)"
LOG = logging.getLogger(__name__)


@dataclass(frozen=True)
class MixParams:
    """tempers: exponents of each margin's own token shares that give its targets, if no targets are passed.

    rounds: rounds of raking between two tests of the margins; the SQL twin has these alone.
    tolerance: the largest error of a margin's share at which raking ends. Where cells
    are missing, so that no weights meet the targets, it ends when such rounds move no
    cell's share by more than a hundredth of it.
    """

    rate: float = 0.5
    rounds: int = 10
    tolerance: float = 1e-7
    scaling: int = 8
    tempers: tuple[float, float, float] = (0.5, 0.7, 0.8)
    topics: int = 4
    long_word: int = 7
    seed: int = 11
    most_cells: int = 20_000


def topic_of(w: str, p: MixParams) -> Column:
    """The class of initials that most long words of the array column ``w`` have; the first of equals.

    A stand-in for a topic column where a table has none.
    """
    initials = F.transform(F.filter(w, lambda x: F.length(x) >= p.long_word), lambda x: F.ascii(F.lower(x)) % p.topics)
    sizes = F.transform(F.array(initials), lambda xs: F.array(*[
        F.struct(F.size(F.filter(xs, equal_to(k))).alias("n"), F.lit(-k).alias("k")) for k in range(p.topics)
    ]))
    best = F.array_max(F.get(sizes, F.lit(0)))
    return F.when(best["n"] > 0, F.concat(F.lit("t"), (-best["k"]).cast("string"))).otherwise(NONE)


def equal_to(k: int):
    return lambda x: x == k


def uniform(seed: int, key: Column) -> Column:
    """A number in [0, 1) that depends on the seed and key alone."""
    digits = F.substring(F.md5(F.concat(F.lit(f"{seed}|"), F.coalesce(key.cast("string"), F.lit("")))), 1, 13)
    return F.conv(digits, 16, 10).cast("long") / F.lit(float(1 << 52))


def names(columns: list[str]) -> dict[str, str]:
    """What the columns that ``mixed`` adds are called: mix_ and their key, with underscores before it where a column has that name."""
    return {k: free_name(columns, f"mix_{k}") for k in (*MARGINS, "tokens", "probability", "kept")}


def celled(docs: DataFrame, p: MixParams) -> DataFrame:
    """``docs`` with the source, lang, topic and tokens columns of ``names``."""
    n, w = names(docs.columns), free_name(docs.columns, "mix_words")
    topic = F.coalesce(F.col("topic").cast("string"), F.lit(NONE)) if "topic" in docs.columns else topic_of(w, p)
    return (
        docs.withColumn(w, words(F.col("text")))
        .withColumns({
            n["topic"]: topic, n["tokens"]: F.size(w).cast("long"),
            n["source"]: F.coalesce(F.col("source"), F.lit(NONE)), n["lang"]: F.coalesce(F.col("lang"), F.lit(NONE)),
        })
        .drop(w)
    )


def tempered_targets(cells: DataFrame, p: MixParams) -> DataFrame:
    """margin, key, share: each margin's token shares to its power, summing to 1."""
    parts = []
    for margin, power in zip(MARGINS, p.tempers):
        raw = cells.groupBy(F.col(margin).alias("key")).agg(F.pow(F.sum("tokens").cast("double"), F.lit(power)).alias("v"))
        total = raw.agg(F.sum("v").alias("total"))
        parts.append(raw.join(F.broadcast(total)).select(F.lit(margin).alias("margin"), "key", F.try_divide("v", "total").alias("share")))
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def factor(table: DataFrame, margin: str, value: str, name: str) -> DataFrame:
    return table.where(F.col("margin") == margin).select(F.col("key").alias(margin), F.col(value).alias(name))


def raked(cells: DataFrame, targets: DataFrame, p: MixParams, few: bool = False) -> DataFrame:
    """source, lang, topic, tokens, ratio: the product of each cell's three factors; keys without target or tokens have factor 0.

    few: the cells were counted and found few, so that one row may hold them.
    """
    found, error = raked_arrays(cells, targets, p) if few else raked_tables(cells, targets, p)
    if error > p.tolerance:
        LOG.warning("raking ended with a largest margin error of %.3g", error)
    return found


def ended(error: float, moved: float, p: MixParams) -> bool:
    return not error > p.tolerance or not moved > p.tolerance / 100


def raked_arrays(cells: DataFrame, targets: DataFrame, p: MixParams, most_rounds: int = 200) -> tuple[DataFrame, float]:
    """The ratios and the largest error of a share. One row holds the cells three times, grouped by each margin, and a
    fold goes over the margins again and again: a group's factor is its target over the sum of tokens and other factors."""
    place = {m: free_name([*MARGINS, "tokens"], f"at_{m}") for m in MARGINS}
    keys = cells.agg(*[F.sort_array(F.collect_set(m)).alias(f"keys_{m}") for m in MARGINS])
    numbered = cells.join(F.broadcast(keys)).select("tokens", *[F.array_position(f"keys_{m}", F.col(m)).cast("int").alias(place[m]) for m in MARGINS], *MARGINS)
    numbered = written(numbered.coalesce(1), "mix-numbered")
    one = numbered.agg(F.sort_array(F.collect_list(F.struct(*place.values(), "tokens"))).alias("cells"))
    for m in MARGINS:
        own = factor(targets, m, "share", "t").join(numbered.select(m).distinct(), m, "left_semi")
        own = own.join(F.broadcast(own.agg(F.sum("t").alias("total")))).select(m, F.try_divide("t", "total").alias("t"))
        group = numbered.groupBy(m, place[m]).agg(F.sort_array(F.collect_list(F.struct(*place.values(), F.col("tokens").cast("double").alias("tokens")))).alias("cells"))
        group = group.join(F.broadcast(own), m, "left").select(place[m], F.coalesce("t", F.lit(0.0)).alias("t"), "cells")
        one = one.join(F.broadcast(group.agg(F.sort_array(F.collect_list(F.struct(place[m], "t", "cells"))).alias(f"by_{m}"))))
    names_ = ("s", "l", "t")
    ones = [F.transform(f"by_{m}", lambda g: F.lit(1.0)).alias(k) for m, k in zip(MARGINS, names_)]
    state = F.struct(*ones, F.transform("cells", lambda c: F.lit(0.0)).alias("share"), F.lit(1.0).alias("error"), F.lit(1.0).alias("moved"), F.lit(False).alias("done"))
    table = written(one.withColumn("state", state), "mix-raking")

    def times(c: Column, acc: Column, *but: int) -> Column:
        out = c["tokens"].cast("double")
        for i, (m, k) in enumerate(zip(MARGINS, names_)):
            if i not in but:
                out = out * F.get(acc[k], c[place[m]] - 1)
        return out

    def summed(cells_: Column, acc: Column, *but: int) -> Column:
        return F.aggregate(cells_, F.lit(0.0), lambda a, c: a + F.coalesce(times(c, acc, *but), F.lit(0.0)))

    def fields(acc: Column, **new: Column) -> Column:
        return F.struct(*[new.get(k, acc[k]).alias(k) for k in (*names_, "share", "error", "moved", "done")])

    def swept(acc: Column, i: int) -> Column:
        f = F.transform(f"by_{MARGINS[i]}", lambda g: F.coalesce(F.try_divide(g["t"], summed(g["cells"], acc, i)), F.lit(0.0)))
        return fields(acc, **{names_[i]: f})

    def tested(acc: Column) -> Column:
        def told(total: Column) -> Column:
            share = F.transform("cells", lambda c: F.coalesce(F.try_divide(times(c, acc), total), F.lit(0.0)))
            missed = [F.array_max(F.transform(f"by_{m}", lambda g: F.abs(F.try_divide(summed(g["cells"], acc), total) - g["t"]))) for m in MARGINS]
            moved = F.array_max(F.zip_with(share, acc["share"], lambda x, y: F.abs(x - y)))
            error = F.when(total > 0, F.greatest(*missed)).otherwise(0.0)
            return fields(acc, share=share, error=F.coalesce(error, F.lit(0.0)), moved=F.coalesce(moved, F.lit(0.0)))

        def judged(new: Column) -> Column:
            return fields(new, done=~(new["error"] > p.tolerance) | ~(new["moved"] > p.tolerance / 100))

        whole = F.transform(F.array(summed(F.col("cells"), acc)), told)  # arrays of one bind what is used more than once
        return F.get(F.transform(whole, judged), F.lit(0))

    length = 3 * p.rounds + 1
    step = lambda acc, i: (
        F.when(acc["done"], acc).when(i % length == length - 1, tested(acc)).when(i % length % 3 == 0, swept(acc, 0)).when(i % length % 3 == 1, swept(acc, 1)).otherwise(swept(acc, 2))
    )
    blocks = max(1, most_rounds // p.rounds)
    while True:
        turns = F.sequence(F.lit(0), F.lit(blocks * length - 1))
        before, table = table, written(table.withColumn("state", F.aggregate(turns, F.col("state"), step)), "mix-raking")
        discarded(before)
        got = table.select("state.error", "state.done").first()
        if got is None or got["done"]:
            break
    flat = table.select(F.explode("cells").alias("c"), "state").select("c.*", *[F.get(F.col("state")[k], F.col("c")[place[m]] - 1).alias(f"f_{m}") for m, k in zip(MARGINS, names_)])
    ratio = F.col(f"f_{MARGINS[0]}") * F.col(f"f_{MARGINS[1]}") * F.col(f"f_{MARGINS[2]}")
    ratios = numbered.join(F.broadcast(flat.drop("tokens")), list(place.values())).select(*MARGINS, "tokens", ratio.alias("ratio"))
    return ratios, float(got["error"] if got else 0.0)


def raked_tables(cells: DataFrame, targets: DataFrame, p: MixParams) -> tuple[DataFrame, float]:
    """As raked_arrays, with a factor table for each margin, whatever the number of cells."""
    now = {m: written(cells.select(m).distinct().withColumn("f", F.lit(1.0)), f"mix-{m}") for m in MARGINS}

    def multiplied() -> tuple[DataFrame, Column]:
        rows, product = cells, F.lit(1.0)
        for m in MARGINS:
            rows, product = rows.join(now[m].withColumnRenamed("f", f"f_{m}"), m), product * F.col(f"f_{m}")
        return rows, product

    error = moved = float("inf")
    was = None
    while not ended(error, moved, p):
        for _ in range(p.rounds):
            for m in MARGINS:
                others, product = cells, F.col("tokens").cast("double")
                for k in MARGINS:
                    if k != m:
                        others, product = others.join(now[k].withColumnRenamed("f", f"f_{k}"), k), product * F.col(f"f_{k}")
                sums = others.groupBy(m).agg(F.sum(product).alias("s"))
                found = sums.join(factor(targets, m, "share", "t"), m, "left").select(m, F.coalesce(F.try_divide("t", "s"), F.lit(0.0)).alias("f"))
                before, now[m] = now[m], written(found, f"mix-{m}")  # one margin at a time keeps each plan small
                discarded(before)
        weighed, product = multiplied()
        weighed = weighed.withColumn("weight", F.col("tokens") * product)
        total = weighed.agg(F.sum("weight").alias("total"))
        share = written(weighed.join(F.broadcast(total)).select(*MARGINS, F.try_divide("weight", "total").alias("share")), "mix-shares")
        error = float(shares_by_margin(share, targets, "share").agg(F.max(F.abs(F.col("share_share") - F.col("target")))).first()[0] or 0.0)
        if was is not None:
            moved = float(share.join(was.withColumnRenamed("share", "was"), list(MARGINS)).agg(F.max(F.abs(F.col("share") - F.col("was")))).first()[0] or 0.0)
        discarded(was)
        was = share
    discarded(was)
    rows, product = multiplied()
    return rows.select(*MARGINS, "tokens", product.alias("ratio")), error


def shares_by_margin(cells: DataFrame, targets: DataFrame, *values: str) -> DataFrame:
    """margin, key, target, and value_share of each value: shares of the keys of ``cells``, targets summing to 1 over them."""
    parts = []
    for m in MARGINS:
        own = cells.groupBy(F.col(m).alias("key")).agg(*[F.sum(v).cast("double").alias(v) for v in values])
        own = own.join(factor(targets, m, "share", "t").withColumnRenamed(m, "key"), "key", "left").withColumn("t", F.coalesce("t", F.lit(0.0)))
        total = own.agg(F.sum("t").alias("all_t"), *[F.sum(v).alias(f"all_{v}") for v in values])
        parts.append(own.join(F.broadcast(total)).select(
            F.lit(m).alias("margin"), "key", F.try_divide("t", "all_t").alias("target"), *[F.try_divide(v, f"all_{v}").alias(f"{v}_share") for v in values]
        ))
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def calibrated(cells: DataFrame, p: MixParams) -> DataFrame:
    """source, lang, topic, tokens, weight, probability of each cell with its ratio.

    The scale starts as if no probability were cut off at 1; each step gives the
    tokens that full cells can't take to the others.
    """
    weight = F.col("tokens") * F.col("ratio")
    total, all_weight = cells.agg(F.sum("tokens"), F.sum(weight)).first()
    scale = p.rate * total / all_weight if total and all_weight else 0.0
    for _ in range(p.scaling):
        full = F.col("ratio") * F.lit(scale) >= 1
        taken, rest = cells.agg(F.sum(F.when(full, F.col("tokens"))), F.sum(F.when(~full, weight))).first()
        if not rest or taken is None or p.rate * total - taken <= 0:
            break
        scale = (p.rate * total - taken) / rest
    return cells.select(
        *MARGINS, "tokens", weight.alias("weight"), F.least(F.lit(1.0), F.col("ratio") * F.lit(scale)).alias("probability")
    )


def cell_chances(docs: DataFrame, p: MixParams, targets: DataFrame | None) -> tuple[DataFrame, DataFrame, DataFrame, bool]:
    """Celled rows, targets, calibrated cells, and whether these are few."""
    rows, n = celled(docs, p), names(docs.columns)
    cells = rows.select(*[F.col(n[m]).alias(m) for m in MARGINS], F.col(n["tokens"]).alias("tokens"))
    cells = written(cells.groupBy(*MARGINS).agg(F.sum("tokens").alias("tokens")), "mix-cells")
    targets = written(tempered_targets(cells, p) if targets is None else targets, "mix-targets")
    few = cells.count() <= p.most_cells  # beyond it Spark chooses, and splits skewed cells
    ratios = written(raked(cells, targets, p, few), "mix-ratios")
    found = written(calibrated(ratios, p), "mix-probabilities")
    discarded(cells, ratios)
    return rows, targets, found, few


def margin_report(docs: DataFrame, p: MixParams = MixParams(), targets: DataFrame | None = None) -> DataFrame:
    """margin, key, target, tokens_share, weight_share, expected_share.

    The shares of the documents' tokens, of the raked weights, and of the tokens
    that are expected to stay; the last misses the target where probabilities end at 1.
    """
    _, targets, found, _ = cell_chances(docs, p, targets)
    found = found.withColumn("expected", F.col("tokens") * F.col("probability"))
    return shares_by_margin(found, targets, "tokens", "weight", "expected")


def mixed(docs: DataFrame, p: MixParams = MixParams(), targets: DataFrame | None = None) -> DataFrame:
    """``docs`` with mix_source, mix_lang, mix_topic, mix_tokens, mix_probability and mix_kept.

    ``docs`` needs doc_id, text, lang and source; a column topic is the topic, where
    there is one, else topic_of stands in. Other columns stay as they are; where one
    has the name of an added one, that gets underscores before it (``names`` tells).
    Null sources, languages and topics are a category of their own; null and empty
    texts have no tokens and no topic, and are sampled with their cell. ``targets``
    (margin, key, share) replaces the tempered shares; keys that it leaves out get
    probability 0. The same doc_id always draws the same number, so repeated rows
    stay or go together, and so do rows with a null doc_id. An empty table stays empty.
    """
    rows, _, found, few = cell_chances(docs, p, targets)
    n = names(docs.columns)
    found = found.select(*[F.col(m).alias(n[m]) for m in MARGINS], F.col("probability").alias(n["probability"]))
    out = rows.join(F.broadcast(found) if few else found, [n[m] for m in MARGINS], "left")
    out = out.withColumn(n["kept"], uniform(p.seed, F.col("doc_id")) < F.coalesce(n["probability"], F.lit(0.0)))
    return out.select(*docs.columns, *n.values())


def op5_mixing(spark, sf_dir: str) -> DataFrame:
    return mixed(documents(spark, sf_dir).select("doc_id", "text", "lang", "source")).select(
        "doc_id", F.col("mix_source").alias("source"), F.col("mix_lang").alias("lang"), F.col("mix_topic").alias("topic"),
        F.col("mix_tokens").alias("n_tokens"), F.round("mix_probability", 6).alias("probability"), F.col("mix_kept").alias("kept"),
    )


def oracle_ctes(p: MixParams = MixParams(), table: str = "documents") -> str:
    """CTEs up to ``mixed_rows`` for DuckDB, after WITH RECURSIVE. A recursion step is a round over all margins; as in
    ``raked``, every ``rounds`` of them it is tested whether the margins are met or the shares have ceased to move."""
    counts = ", ".join(f"len(list_filter(initials, lambda x: x = {k}))" for k in range(p.topics))
    out = [f"""mix_in AS (
  SELECT *, row_number() OVER () AS mix_rid, regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') AS w,
         coalesce(source, '{NONE}') AS mix_source, coalesce(lang, '{NONE}') AS mix_lang FROM {table}),
mix_ini AS (SELECT *, list_transform(list_filter(w, lambda x: length(x) >= {p.long_word}), lambda x: ascii(lower(x)) % {p.topics}) AS initials FROM mix_in),
mix_cnt AS (SELECT *, [{counts}] AS topic_n FROM mix_ini),
mix_rows AS MATERIALIZED (SELECT *, CASE WHEN list_max(topic_n) > 0 THEN 't' || (list_position(topic_n, list_max(topic_n)) - 1) ELSE '{NONE}' END AS mix_topic, len(w) AS mix_tokens FROM mix_cnt),
cells AS MATERIALIZED (SELECT mix_source AS source, mix_lang AS lang, mix_topic AS topic, sum(mix_tokens)::DOUBLE AS tokens FROM mix_rows GROUP BY ALL)"""]
    for m, power in zip(MARGINS, p.tempers):
        out.append(f"t_{m} AS MATERIALIZED (SELECT {m}, v / nullif(sum(v) OVER (), 0) AS t FROM (SELECT {m}, pow(sum(tokens), {power}) AS v FROM cells GROUP BY {m}))")
    share = "tokens * f_source * f_lang * f_topic"
    scaled = "coalesce(t_{m} / nullif(sum(tokens * f_{a} * f_{b}) OVER (PARTITION BY {m}), 0), 0) AS f_{m}"
    step = f"SELECT * FROM rake WHERE i % {p.rounds} <> 0 OR i = 0 OR (error > {p.tolerance!r} AND moved > {p.tolerance / 100!r})"
    for m in MARGINS:
        a, b = (k for k in MARGINS if k != m)
        step = f"SELECT * REPLACE ({scaled.format(m=m, a=a, b=b)}) FROM ({step})"
    step = f"SELECT * REPLACE (i + 1 AS i, {share} / nullif(sum({share}) OVER (), 0) AS share) FROM ({step})"
    missed = ", ".join(f"abs(sum(share) OVER (PARTITION BY {m}) - t_{m}) AS e_{m}" for m in MARGINS)
    step = f"SELECT *, {missed} FROM ({step})"
    end = f"i % {p.rounds} = 0"
    step = f"""SELECT i, source, lang, topic, tokens, t_source, t_lang, t_topic, f_source, f_lang, f_topic, share, CASE WHEN {end} THEN share ELSE was END AS was,
  CASE WHEN {end} THEN max(greatest(e_source, e_lang, e_topic)) OVER () ELSE error END AS error, CASE WHEN {end} THEN max(abs(share - was)) OVER () ELSE moved END AS moved FROM ({step})"""
    out.append(f"""rake AS (SELECT 0 AS i, source, lang, topic, tokens, s.t AS t_source, l.t AS t_lang, c.t AS t_topic, 1.0::DOUBLE AS f_source, 1.0::DOUBLE AS f_lang, 1.0::DOUBLE AS f_topic,
  0.0::DOUBLE AS share, 0.0::DOUBLE AS was, 1.0::DOUBLE AS error, 1.0::DOUBLE AS moved FROM cells JOIN t_source s USING (source) JOIN t_lang l USING (lang) JOIN t_topic c USING (topic)
  UNION ALL {step})""")
    out.append("ratios AS MATERIALIZED (SELECT source, lang, topic, tokens, f_source * f_lang * f_topic AS ratio FROM rake WHERE i = (SELECT max(i) FROM rake))")
    out.append(f"k0 AS MATERIALIZED (SELECT coalesce({p.rate} * sum(tokens) / nullif(sum(tokens * ratio), 0), 0) AS k FROM ratios)")
    for i in range(p.scaling):
        out.append(f"""k{i + 1} AS MATERIALIZED (SELECT CASE WHEN rest > 0 AND taken IS NOT NULL AND {p.rate} * total - taken > 0 THEN ({p.rate} * total - taken) / rest ELSE k END AS k FROM (
  SELECT any_value(k) AS k, sum(tokens) AS total, sum(CASE WHEN ratio * k >= 1 THEN tokens END) AS taken, sum(CASE WHEN ratio * k < 1 THEN tokens * ratio END) AS rest FROM ratios, k{i}))""")
    out.append(f"""mixed_rows AS MATERIALIZED (
  SELECT r.*, least(1.0, ratio * k) AS probability,
         ('0x' || substr(md5('{p.seed}|' || coalesce(doc_id::VARCHAR, '')), 1, 13))::BIGINT / {1 << 52}::DOUBLE < least(1.0, ratio * k) AS kept
  FROM mix_rows r LEFT JOIN ratios ON mix_source = ratios.source AND mix_lang = ratios.lang AND mix_topic = ratios.topic CROSS JOIN k{p.scaling})""")
    return ",\n".join(out)


def oracle(p: MixParams = MixParams()) -> str:
    return f"""WITH RECURSIVE {oracle_ctes(p)}
SELECT doc_id, mix_source AS source, mix_lang AS lang, mix_topic AS topic, mix_tokens AS n_tokens, round(probability, 6) AS probability, kept FROM mixed_rows"""
