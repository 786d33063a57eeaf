"""Lines that repeat an earlier line, or differ from it by one word.

Equal lines are found by a 128-bit hash of their words. For near ones each line
gives its deletion neighbourhood within one edit of words: all variants without
one word, as hashed keys that carry the place of the missing word. Lines with an
equal key are partners, and their words are compared; where a key has met two
lines that are no partners, its lines are met again by their variants' words.
Only lines that share a half with another line can have such a partner, so only
they give variants. The earliest line by (doc_id, text hash, line number) stays.
All of it is SQL expressions; groups are summed up before they are shuffled.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .exact_dedup import block_pattern
from .storage import by_size, discarded, free_name, written
from .text import documents, words


@dataclass(frozen=True)
class LineParams:
    """least_words: shorter lines always stay. near_words: shorter lines only match equal ones.

    key_bits: of a variant's key that are used; fewer make foreign lines meet (tests).
    """

    least_words: int = 5
    near_words: int = 10
    most_blocks: int = 1 << 20
    key_bits: int = 64


def position(prefix: str = "") -> Column:
    """Rows of one doc_id with different texts are different documents; rows with equal ones are one."""
    return F.struct(*[F.col(f"{prefix}{k}") for k in ("doc_id", "text_hash", "line_no")])


def lines_of(docs: DataFrame, p: LineParams) -> DataFrame:
    """doc_id, text_hash, line_no, line, n, h1, h2, halves of each line with enough words."""
    rows = docs.select("doc_id", F.xxhash64("text").alias("text_hash"), F.posexplode(F.split(F.coalesce("text", F.lit("")), "\n")).alias("line_no", "line"))
    rows = rows.withColumn("w", words(F.col("line"))).withColumn("n", F.size("w")).where(F.col("n") >= p.least_words)
    return rows.select(
        "doc_id", "text_hash", "line_no", "line", "n", F.xxhash64("w").alias("h1"), F.xxhash64(F.lit(1), "w").alias("h2"),
        F.when(F.col("n") >= p.near_words, halves("w", F.col("n"))).alias("halves"),
    )


def halves(w: str, n: Column) -> Column:
    """Keys of the first and last words, for partners no longer than the line and for those with one more word.

    Of two lines within one edit, the longer one m words long, the first or the
    last (m - 1) div 2 words are equal.
    """
    out = []
    for m in (n, n + 1):
        half = F.floor((m - 1) / 2).cast("int")
        out += [F.xxhash64(F.lit(0), m, F.slice(w, F.lit(1), half)), F.xxhash64(F.lit(1), m, F.slice(w, n - half + 1, half))]
    return F.array(*out)


def xor(x: Column) -> Column:
    return F.aggregate(x, F.lit(0).cast("long"), lambda a, b: a.bitwiseXOR(b))


def variants(w: str, n: Column) -> Column:
    """Keys of the line within one edit: (key, role); role 0: a word replaced, 1: the whole line, 2: a word left out.

    A line's hash is the XOR of hashes of (word, position), so that a variant
    is made of the sums before and behind a word; these are kept for blocks of
    about the square root of the length.
    """
    at = F.transform(w, lambda x, i: F.xxhash64(x, i))
    moved = F.transform(w, lambda x, i: F.xxhash64(x, i - 1))
    size = F.ceil(F.sqrt(n.cast("double"))).cast("int")

    def keyed(s: Column) -> Column:
        a, b, n_, size_ = s["a"], s["b"], s["n"], s["size"]
        blocks = lambda v: F.transform(F.sequence(F.lit(0), F.floor((n_ - 1) / size_).cast("int")), lambda k: xor(F.slice(v, k * size_ + 1, size_)))

        def sums(t: Column) -> Column:
            before = lambda v, bl, i: xor(F.slice(bl, F.lit(1), F.floor(i / size_).cast("int"))).bitwiseXOR(
                xor(F.slice(v, F.floor(i / size_).cast("int") * size_ + 1, i % size_)))
            whole, behind = xor(t["ba"]), xor(t["bb"])
            replaced = F.transform(a, lambda x, i: F.struct(F.xxhash64(F.lit("r"), n_, i, whole.bitwiseXOR(x)).alias("key"), F.lit(0).alias("role")))
            same = F.array(F.struct(F.xxhash64(F.lit("d"), n_, whole).alias("key"), F.lit(1).alias("role")))
            shorter = F.transform(b, lambda x, i: F.struct(
                F.xxhash64(F.lit("d"), n_ - 1, before(a, t["ba"], i).bitwiseXOR(behind).bitwiseXOR(before(b, t["bb"], i)).bitwiseXOR(x)).alias("key"),
                F.lit(2).alias("role"),
            ))
            return F.concat(replaced, same, shorter)

        return F.get(F.transform(F.array(F.struct(blocks(a).alias("ba"), blocks(b).alias("bb"))), sums), F.lit(0))

    return F.get(F.transform(F.array(F.struct(at.alias("a"), moved.alias("b"), n.alias("n"), size.alias("size"))), keyed), F.lit(0))


def within_one(w: Column, v: Column) -> Column:
    """Whether two arrays of words differ by one word replaced, left out or added."""
    n, m = F.size(w), F.size(v)
    same = F.zip_with(w, v, lambda x, y: x.eqNullSafe(y))  # the shorter one is filled up with nulls
    first = F.array_position(same, F.lit(False)).cast("int")  # from 1; 0: equal
    behind = lambda x, k, size: F.slice(x, k, F.greatest(size, F.lit(1)))
    return (first > 0) & (
        F.when(n == m, behind(w, first + 1, n) == behind(v, first + 1, m))
        .when(n == m + 1, behind(w, first + 1, n) == behind(v, first, m))
        .when(n + 1 == m, behind(w, first, n) == behind(v, first + 1, m))
        .otherwise(F.lit(False))
    )


def marked_rows(rows: DataFrame, at: Column, marks: DataFrame, p: LineParams) -> DataFrame:
    """The rows whose hash ``at`` is one of ``marks`` (at), and a few others: a Bloom filter of bounded size."""
    blocks = 1 << 10
    while blocks < min(p.most_blocks, marks.count() // 4):
        blocks *= 2
    block, pattern = block_pattern(F.col("at"), F.xxhash64(F.lit(3), "at"), blocks)
    bloom = marks.select(block.alias("block"), pattern.alias("pattern")).groupBy("block").agg(F.bit_or("pattern").alias("filter"))
    tested = rows.withColumn("at", at).withColumn("block", block).withColumn("pattern", pattern)
    tested = tested.join(F.broadcast(bloom), "block").where(F.col("filter").bitwiseAND(F.col("pattern")) == F.col("pattern"))
    return tested.drop("block", "pattern", "filter")


def earliest_partners(told: DataFrame, key: str) -> DataFrame:
    """key, own, partner: of lines that meet in a key, the earliest one before each that can be its partner."""
    role = lambda k: F.min(F.when(F.col("role") == k, F.col("own")))
    groups = told.groupBy(key).agg(*[role(k).alias(f"p{k}") for k in range(3)], F.min("own").alias("low"), F.max("own").alias("high"))
    groups = groups.where("low <> high").select(key, "p0", "p1", "p2")
    partner = F.when(F.col("role") == 0, F.col("p0")).when(F.col("role") == 1, F.col("p2")).otherwise(F.col("p1"))
    return told.join(groups, key).select(key, "own", partner.alias("partner")).where("partner < own")


def spelt_variants(w: str, n: Column) -> Column:
    """The variants of ``variants`` with their words in place of hashes: (key, role)."""
    without = lambda i: F.array_join(F.concat(F.slice(w, F.lit(1), i), F.slice(w, i + 2, n)), " ")
    spelt = lambda kind, size, i, text: F.concat_ws("|", F.lit(kind), size.cast("string"), i.cast("string"), text)
    each = F.sequence(F.lit(0), n - 1)
    none = F.lit(-1)
    return F.concat(
        F.transform(each, lambda i: F.struct(spelt("r", n, i, without(i)).alias("key"), F.lit(0).alias("role"))),
        F.array(F.struct(spelt("d", n, none, F.array_join(w, " ")).alias("key"), F.lit(1).alias("role"))),
        F.transform(each, lambda i: F.struct(spelt("d", n - 1, none, without(i)).alias("key"), F.lit(2).alias("role"))),
    )


def near_lines(base: DataFrame, first: DataFrame, p: LineParams) -> DataFrame:
    """own, partner: the first place of each line with an earlier line that differs by a word, and the earliest such."""
    place = lambda x: F.xxhash64(F.lit(2), x["doc_id"], x["text_hash"], x["line_no"])
    keys = first.where("halves is not null").select(F.explode("halves").alias("key"), place(F.col("first")).alias("at"))
    shared = keys.groupBy("key").agg(F.count(F.lit(1)).alias("lines")).where("lines > 1").select("key")  # a line's own halves have different keys
    close = written(keys.join(shared, "key", "left_semi").select("at").distinct(), "lines-close")

    lines = base.where(F.col("n") >= p.near_words).select(position().alias("own"), "line")
    chosen = marked_rows(lines, place(F.col("own")), close, p).withColumn("w", words(F.col("line")))
    told = chosen.select("own", F.explode(variants("w", F.size("w"))).alias("v")).select("own", "v.key", "v.role")
    if p.key_bits < 64:
        told = told.withColumn("key", F.col("key").bitwiseAND(F.lit((1 << p.key_bits) - 1)))
    pairs = written(earliest_partners(told, "key"), "lines-pairs")

    # equal keys are no proof: the words of each pair are compared
    ends = written(pairs.select(place(F.col("own")).alias("at")).union(pairs.select(place(F.col("partner")).alias("at"))).distinct(), "lines-ends")
    texts = marked_rows(lines, place(F.col("own")), ends, p).select("own", words(F.col("line")).alias("w"))
    both = pairs.join(texts, "own").join(texts.select(F.col("own").alias("partner"), F.col("w").alias("v")), "partner")
    both = written(both.select("key", "own", "partner", within_one(F.col("w"), F.col("v")).alias("near"), (F.col("w") == F.col("v")).alias("equal")), "lines-compared")
    near = both.where("near").select("own", "partner")
    # a later copy that the filter let through meets its own first place; its key holds no foreign line for that
    foreign = both.where("not near and not equal").select("key").distinct()
    if not foreign.isEmpty():
        again = written(told.join(foreign, "key", "left_semi").select(place(F.col("own")).alias("at")).distinct(), "lines-again")
        spelt = marked_rows(lines, place(F.col("own")), again, p).withColumn("w", words(F.col("line")))
        spelt = spelt.select("own", F.explode(spelt_variants("w", F.size("w"))).alias("v")).select("own", "v.key", "v.role")
        near = near.union(earliest_partners(spelt, "key").select("own", "partner"))
    found = written(near.groupBy("own").agg(F.min("partner").alias("partner")), "lines-near")
    discarded(close, pairs, ends, both)
    return found


def found_lines(docs: DataFrame, p: LineParams) -> DataFrame:
    """As ``repeated_lines``, with text_hash."""
    base = written(lines_of(docs, p), "lines")
    same = ["h1", "h2"]
    first = written(
        base.groupBy(*same).agg(F.min(position()).alias("first"), F.count(F.lit(1)).alias("copies"), F.first("halves").alias("halves")), "lines-distinct"
    )
    near = near_lines(base, first, p)

    # rows of lines that occur more than once, and of those with an earlier near line, by line
    found = first.drop("halves").join(near, F.col("first").eqNullSafe(F.col("own")), "left").where("copies > 1 or partner is not null")
    found = written(found.select(*same, "first", "copies", "partner"), "lines-found")
    later = by_size(base.select("doc_id", "text_hash", "line_no", *same), found, same, "copies")
    discarded(first, near)
    own = F.col("first") < position()
    partner = F.when(own, F.col("first")).otherwise(F.col("partner"))
    return later.where(own | (F.col("partner") < position())).select(
        "doc_id", "text_hash", "line_no", (~own).alias("near"), partner["doc_id"].alias("first_doc_id"), partner["line_no"].alias("first_line_no")
    )


def repeated_lines(docs: DataFrame, p: LineParams = LineParams()) -> DataFrame:
    """doc_id, line_no, near, first_doc_id, first_line_no of each line that an earlier line repeats.

    ``near`` is false if the earlier line has the same words; otherwise it
    differs by one word replaced, left out or added. The first_ columns name the
    earliest such line (of equal lines, if there are any). White space is not
    compared. The edit bound is one word. Lines with fewer than ``near_words``
    words are only listed for an equal line, those with fewer than ``least_words``
    never. Null doc_ids come first. Rows of one doc_id (or of none) with different
    texts are documents of their own; rows with equal ones are the same document,
    whose lines don't repeat each other. Null and empty texts have no lines.
    An empty table gives no rows.
    """
    return found_lines(docs.select("doc_id", "text"), p).drop("text_hash")


def without_repeated_lines(docs: DataFrame, p: LineParams = LineParams()) -> DataFrame:
    """``docs`` without their repeated lines; documents that lose all their words go.

    ``docs`` needs doc_id and text; other columns stay as they are, whatever their
    names. Null and empty texts have no lines to lose and stay as they are. A line
    goes from the rows with that doc_id and text alone, so rows that share a doc_id
    (or have none) lose only their own. An empty table stays empty.
    """
    names = {k: free_name(docs.columns, k) for k in ("gone_lines", "gone_id", "gone_hash", "kept_text")}
    lines, doc, text_hash, text = names.values()
    gone = found_lines(docs.select("doc_id", "text"), p)
    gone = gone.groupBy(F.col("doc_id").alias(doc), F.col("text_hash").alias(text_hash)).agg(F.collect_set("line_no").alias(lines))  # a document's own lines: as long as its text
    pair = docs.join(gone, docs["doc_id"].eqNullSafe(gone[doc]) & (F.xxhash64(docs["text"]) == gone[text_hash]), "left")
    kept = F.array_join(F.filter(F.split("text", "\n"), lambda x, i: ~F.array_contains(lines, i)), "\n")
    out = pair.withColumn(text, F.when(F.col(lines).isNull(), F.col("text")).otherwise(kept))
    out = out.where(F.col(lines).isNull() | F.col(text).rlike("[^\\x20\\x09-\\x0D]"))
    return out.select(*[F.col(text).alias(c) if c == "text" else F.col(c) for c in docs.columns])


def op9_line_dedup(spark, sf_dir: str) -> DataFrame:
    """Every line of whole texts; an edit bound of one word, from ten words on (from five on for equal lines)."""
    return repeated_lines(documents(spark, sf_dir))


def oracle(p: LineParams = LineParams()) -> str:
    """Pairs come from equal halves, compared word by word: another way to the same lines."""
    return f"""
WITH l AS (
  SELECT doc_id, i - 1 AS line_no, regexp_extract_all(x, '[^\\x20\\x09-\\x0D]+') AS w
  FROM (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS x, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS i FROM documents)),
k AS (SELECT * FROM l WHERE len(w) >= {p.least_words}),
d AS MATERIALIZED (SELECT w, len(w) AS n, min(row(doc_id, line_no)) AS f, row_number() OVER () AS id FROM k GROUP BY w),
h AS (SELECT id, m, (m - 1) // 2 AS half FROM d, (SELECT unnest([0, 1]) AS e) t, LATERAL (SELECT n + e AS m) WHERE n >= {p.near_words}),
keys AS (SELECT d.id, d.n, d.w, f, m, 0 AS side, w[1:half] AS part FROM h JOIN d USING (id) UNION ALL SELECT d.id, d.n, d.w, f, m, 1, w[d.n - half + 1:d.n] FROM h JOIN d USING (id)),
pairs AS (SELECT DISTINCT a.id, a.w, b.w AS v, a.n, b.n AS o, b.f AS g FROM keys a JOIN keys b USING (m, side, part) WHERE b.f < a.f AND abs(a.n - b.n) <= 1),
near AS (
  SELECT id, min(g) AS near_first FROM pairs
  WHERE (n = o AND len(list_filter(range(1, n + 1), lambda i: w[i] <> v[i])) = 1)
     OR (n = o + 1 AND len(list_filter(range(1, n + 1), lambda i: list_concat(w[1:i - 1], w[i + 1:n]) = v)) > 0)
     OR (n = o - 1 AND len(list_filter(range(1, o + 1), lambda i: list_concat(v[1:i - 1], v[i + 1:o]) = w)) > 0)
  GROUP BY id),
a AS (SELECT k.doc_id, k.line_no, d.f, near_first, d.f < row(k.doc_id, k.line_no) AS later FROM k JOIN d USING (w) LEFT JOIN near USING (id))
SELECT doc_id, line_no::INTEGER AS line_no, NOT later AS near,
       CASE WHEN later THEN f[1] ELSE near_first[1] END AS first_doc_id, (CASE WHEN later THEN f[2] ELSE near_first[2] END)::INTEGER AS first_line_no
FROM a WHERE later OR near_first < row(doc_id, line_no)
"""
