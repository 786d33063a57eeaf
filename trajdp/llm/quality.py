"""Quality rules: histograms of a document against references of its language.

Each document gives two histograms: characters by class, and common words of its
language (with one bin for all other words). The references are the sums over
all documents of a language. A document fails if the Jensen-Shannon distance
(base 2, between 0 and 1) to a reference is above a limit, unless it is too
short for its histogram to say anything. All of it is SQL expressions; within a
document repeated windows are found by sorting, without a shuffle.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .storage import written
from .text import documents, words

#: Common words of the languages with a reference.
COMMON = {
    "en": "a an and are as at be by for from in is it of on or that the this to was with",
    "de": "als auch auf das dem den der des die ein eine für im in ist mit nicht sich und von zu",
    "fr": "au dans de des du en est et la le les par pas plus pour que qui sur un une",
    "es": "a al con de del el en la las lo los no para por que se su un una y",
}
#: Characters of each class, taken out of the text one after the other; what is left is the last class.
CLASSES = (("lower", "\\p{Ll}+"), ("space", "[\\x20\\x09-\\x0D]+"), ("upper", "\\p{Lu}+"), ("digit", "\\p{Nd}+"), ("stop", "[.,;:?'()\"-]+"))


@dataclass(frozen=True)
class QualityParams:
    class_limit: float = 0.28
    word_limit: float = 0.25
    least_chars: int = 200
    least_words: int = 150
    other: str = "other"


def repeated_window_words(w: str, span: int = 3) -> Column:
    """Words that lie in a window of ``span`` words found twice or more; ``w`` names an array column.

    Windows are compared by 64-bit hashes. Sorted, equal ones are neighbours;
    their positions, sorted again, cover min(span, gap to the next) words each.
    """
    count = F.greatest(F.size(w) - (span - 1), F.lit(0))
    hashed = F.transform(
        F.slice(w, F.lit(1), count),
        lambda x, i: F.struct(F.xxhash64(x, *[F.get(F.col(w), i + k) for k in range(1, span)]).alias("h"), i.alias("i")),
    )
    twice = lambda s: F.filter(
        F.transform(s, lambda x, k: F.when((x["h"] == F.get(s, k - 1)["h"]) | (x["h"] == F.get(s, k + 1)["h"]), x["i"])), lambda i: i.isNotNull()
    )
    covered = lambda p: F.transform(p, lambda i, k: F.least(F.lit(span), F.coalesce(F.get(p, k + 1) - i, F.lit(span))))
    # one-element arrays bind each sorted array once
    sizes = F.transform(F.array(F.sort_array(hashed)), lambda s: F.aggregate(
        F.flatten(F.transform(F.array(F.sort_array(twice(s))), covered)), F.lit(0).cast("long"), lambda a, x: a + x
    ))
    return F.get(sizes, F.lit(0))


def measured(docs: DataFrame, p: QualityParams) -> DataFrame:
    """Base measures and both histograms of each document."""
    text = F.coalesce(F.col("text"), F.lit(""))
    key = F.when(F.col("lang").isin(*COMMON), F.col("lang")).otherwise(p.other)
    df = docs.select("doc_id", key.alias("reference"), text.alias("text")).withColumn("w", words(F.col("text")))
    used = F.filter(F.split("text", "\n"), lambda x: x.rlike("[^\\x20\\x09-\\x0D]"))
    every = sorted({x for line in COMMON.values() for x in line.split()})
    df = df.select(
        "doc_id", "reference", "text", "w",
        F.transform(F.array(used), lambda x: F.size(x) - F.size(F.array_distinct(x))).alias("dup"),
        F.filter("w", lambda x: x.isin(*every)).alias("common"),
    )
    classes, rest = [], F.col("text")
    steps = []
    for name, pattern in CLASSES:
        steps.append((name, F.regexp_replace(rest, pattern, "")))
        rest = F.col(f"r_{name}")
    for name, column in steps:
        df = df.withColumn(f"r_{name}", column)
    before = F.length("text")
    for name, _ in CLASSES:
        after = F.length(f"r_{name}")
        classes.append(before - after)
        before = after
    classes.append(before)
    counted = F.lit(None).cast("array<long>")
    for lang, line in [*COMMON.items(), (p.other, " ".join(every))]:
        bins = F.transform(F.array(*map(F.lit, line.split())), lambda c: F.size(F.filter("common", lambda x: x == c)).cast("long"))
        counted = F.when(F.col("reference") == lang, bins).otherwise(counted)
    df = df.select(
        "doc_id", "reference",
        F.size("w").cast("long").alias("n_words"),
        F.length(F.array_join("w", "")).cast("long").alias("word_chars"),
        F.regexp_count("r_stop", F.lit("[#*$%&|<>]")).cast("long").alias("n_symbols"),
        F.get("dup", F.lit(0)).cast("long").alias("n_dup_lines"),
        repeated_window_words("w").alias("n_repeat_words"),
        F.array(*[c.cast("long") for c in classes]).alias("classes"),
        counted.alias("common"),
    )
    other = F.col("n_words") - F.aggregate("common", F.lit(0).cast("long"), lambda a, x: a + x)
    return df.withColumn("common", F.concat("common", F.array(other)))


def distance(counts: str, reference: str) -> Column:
    """Jensen-Shannon distance of two histograms of counts; null if one has no count."""
    total = lambda c: F.aggregate(c, F.lit(0.0), lambda a, x: a + x)
    shares = F.zip_with(counts, reference, lambda x, y: F.struct((x / total(F.col(counts))).alias("p"), (y / total(F.col(reference))).alias("q")))
    part = lambda a, m: F.when(a > 0, a * F.log2(a / m)).otherwise(0.0)
    terms = F.transform(shares, lambda s: (part(s["p"], (s["p"] + s["q"]) / 2) + part(s["q"], (s["p"] + s["q"]) / 2)) / 2)
    found = F.aggregate(terms, F.lit(0.0), lambda a, x: a + x)
    return F.when((total(F.col(counts)) > 0) & (total(F.col(reference)) > 0), F.sqrt(F.greatest(found, F.lit(0.0))))


def language_references(rows: DataFrame) -> DataFrame:
    """Summed histograms of each reference language: as many rows as languages listed, and one for the others."""
    longest = max(len(set(line.split())) for line in COMMON.values())
    every = len({x for line in COMMON.values() for x in line.split()})
    bins = max(longest, every) + 1
    sums = [F.sum(F.get("classes", F.lit(i))).alias(f"c{i}") for i in range(len(CLASSES) + 1)]
    sums += [F.sum(F.get("common", F.lit(i))).alias(f"w{i}") for i in range(bins)]
    got = rows.groupBy("reference").agg(*sums)
    gathered = lambda k, n: F.filter(F.array(*[F.col(f"{k}{i}") for i in range(n)]), lambda x: x.isNotNull())
    return got.select("reference", gathered("c", len(CLASSES) + 1).alias("ref_classes"), gathered("w", bins).alias("ref_common"))


def quality_rules(docs: DataFrame, p: QualityParams = QualityParams()) -> DataFrame:
    """One row per document with its measures, distances and verdict.

    ``docs`` needs doc_id, text and lang; other columns are ignored. Null and
    empty texts have no words: they fail the base rules. Null and unlisted
    languages share one reference over the words of all lists. Distances are
    null for histograms without counts and don't fail a document; nor do those
    of texts with fewer than ``least_chars`` characters or ``least_words`` words.
    Repeated rows are judged each.
    """
    rows = written(measured(docs, p), "quality-histograms")
    df = rows.join(F.broadcast(language_references(rows)), "reference")  # rows of COMMON and one: bounded
    df = df.withColumn("class_distance", F.round(distance("classes", "ref_classes"), 9)).withColumn(
        "word_distance", F.round(distance("common", "ref_common"), 9)
    )
    chars = F.aggregate("classes", F.lit(0).cast("long"), lambda a, x: a + x)
    odd = ((chars >= p.least_chars) & (F.col("class_distance") > p.class_limit)) | (
        (F.col("n_words") >= p.least_words) & (F.col("word_distance") > p.word_limit)
    )
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return df.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"),
        (~failed & ~F.coalesce(odd, F.lit(False))).alias("kept"),
        F.round("class_distance", 6).alias("class_distance"), F.round("word_distance", 6).alias("word_distance"),
    )


def op1_distribution_divergence(spark, sf_dir: str) -> DataFrame:
    return quality_rules(documents(spark, sf_dir))


def oracle(p: QualityParams = QualityParams()) -> str:
    every = " ".join(sorted({x for line in COMMON.values() for x in line.split()}))
    lists = ", ".join(f"('{k}', string_split('{line}', ' '))" for k, line in [*COMMON.items(), (p.other, every)])
    stripped = "".join(f", r{i} AS (SELECT *, regexp_replace(r{i}_in, '{pat.replace(chr(39), chr(39) * 2)}', '', 'g') AS r{i + 1}_in FROM {'base' if i == 0 else f'r{i - 1}'})" for i, (_, pat) in enumerate(CLASSES))
    n = len(CLASSES)
    classes = ", ".join([f"length(r{i}_in) - length(r{i + 1}_in)" for i in range(n)] + [f"length(r{n}_in)"])
    share = "(v / sum(v) OVER (PARTITION BY {k}))"
    js = """SELECT {k}, sqrt(greatest(sum(CASE WHEN p > 0 THEN p * log2(p / ((p + q) / 2)) ELSE 0 END + CASE WHEN q > 0 THEN q * log2(q / ((p + q) / 2)) ELSE 0 END) / 2, 0)) AS d FROM ({t}) GROUP BY {k}"""

    def distances(column: str) -> str:
        ref = f"SELECT reference, i, v / nullif(sum(v) OVER (PARTITION BY reference), 0) AS q FROM (SELECT reference, i, sum(v) AS v FROM (SELECT reference, unnest(range(len({column}))) AS i, unnest({column}) AS v FROM m) GROUP BY reference, i)"
        own = f"SELECT rid, reference, i, v / nullif(sum(v) OVER (PARTITION BY rid), 0) AS p FROM (SELECT rid, reference, unnest(range(len({column}))) AS i, unnest({column}) AS v FROM m)"
        return js.format(k="rid", t=f"SELECT rid, p, q FROM ({own}) JOIN ({ref}) USING (reference, i) WHERE p IS NOT NULL AND q IS NOT NULL")

    return f"""
WITH lists(reference, bins) AS (VALUES {lists}),
base AS (
  SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS r0_in,
         CASE WHEN lang IN ({", ".join(f"'{k}'" for k in COMMON)}) THEN lang ELSE '{p.other}' END AS reference,
         regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') AS w,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS lines
  FROM documents){stripped},
m AS (
  SELECT rid, doc_id, reference, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars,
         length(r{n}_in) - length(regexp_replace(r{n}_in, '[#*$%&|<>]', '', 'g')) AS n_symbols,
         len(lines) - len(list_distinct(lines)) AS n_dup_lines, [{classes}] AS classes,
         list_append(list_transform(bins, lambda b: len(list_filter(w, lambda x: x = b))),
                     len(w) - len(list_filter(w, lambda x: list_contains(bins, x)))) AS common
  FROM r{n - 1} JOIN lists USING (reference)),
pos AS (SELECT rid, unnest(range(len(w))) AS i, unnest(w) AS x FROM base),
tri AS (SELECT rid, i, x, lead(x) OVER o AS y, lead(x, 2) OVER o AS z FROM pos WINDOW o AS (PARTITION BY rid ORDER BY i)),
twice AS (SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, x, y, z) AS c FROM tri WHERE z IS NOT NULL) WHERE c > 1),
rep AS (SELECT rid, count(DISTINCT i + k) AS n FROM twice, (SELECT unnest([0, 1, 2]) AS k) GROUP BY rid),
dc AS ({distances('classes')}), dw AS ({distances('common')}),
j AS (SELECT m.*, coalesce(rep.n, 0) AS n_repeat_words, round(dc.d, 9) AS c, round(dw.d, 9) AS k,
             m.n_words < 50 OR 100 * coalesce(rep.n, 0) > 50 * m.n_words AS base_failed
      FROM m LEFT JOIN rep USING (rid) LEFT JOIN dc USING (rid) LEFT JOIN dw USING (rid))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND NOT coalesce((list_sum(classes) >= {p.least_chars} AND c > {p.class_limit}) OR (n_words >= {p.least_words} AND k > {p.word_limit}), false) AS kept,
       round(c, 6) AS class_distance, round(k, 6) AS word_distance
FROM j
"""
