"""Operators against brute force, and hard cases: nulls, empty and long texts, ties, repeated rows, empty tables, extra columns."""

import itertools
import math
import random
import re
import string
import zlib

import duckdb
import numpy as np
import pandas as pd
import public_tokenizers as P
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from trajdp.llm import catalogue, chat, exact_dedup, jaccard_join, langid, line_dedup, mixing, packing, quality, token_counts, toxicity

WORDS = re.compile(r"[^\x20\x09-\x0d]+")
LONG = "alpha beta gamma delta epsilon zeta eta theta iota kappa " * 400
HARD = [
    (1, None, None, None), (2, "", "en", "a"), (3, "One two three", "en", "a"), (4, "one two THREE", None, "b"), (5, LONG, "en", "a"),
    (6, "one two three\none two three\n\n \t", "de", None), (7, "été ÉTÉ Σς ﬁ 日本語 😀", "fr", "b"), (8, "<|endoftext|> x <|startoftext|>", "en", "a"),
    (8, "<|endoftext|> x <|startoftext|>", "en", "a"), (9, "x" * 5000, "en", "a"), (None, "one two three", "en", "a"), (10, "... !!! 123", "es", "b"),
]


@pytest.fixture(scope="module")
def hard(spark):
    df = spark.createDataFrame(HARD, "doc_id long, text string, lang string, source string")
    return df.withColumns({k: F.lit("clash") for k in ("score", "n", "block", "pattern", "h1", "w", "key", "kept")})


def empty(df):
    return df.where("false")


def by_id(df):
    return sorted((tuple(r) for r in df.collect()), key=lambda r: (r[0] is None, r[0] or 0, repr(r)))


def oracle(sql, **tables):
    con = duckdb.connect()
    for name, frame in tables.items():
        con.register(name, frame)
    return con.sql(sql)


def same(df, want):
    cols = sorted(df.columns)
    assert cols == sorted(want.columns)
    at = [want.columns.index(c) for c in cols]
    norm = lambda v: None if isinstance(v, float) and math.isnan(v) else v
    assert sorted(repr(tuple(map(norm, r))) for r in df.select(*cols).collect()) == sorted(repr(tuple(norm(r[i]) for i in at)) for r in want.fetchall())


def base_measures(text):
    w = WORDS.findall(text or "")
    grams = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    twice = {g for g in grams if grams.count(g) > 1} if len(grams) < 5000 else {g for g in grams if grams[:200].count(g) > 1}
    covered = {i + k for i, g in enumerate(grams) if g in twice for k in range(3)}
    lines = [x for x in (text or "").split("\n") if WORDS.search(x)]
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(covered)


def test_quality_base_and_empty(hard):
    got = by_id(quality.quality_rules(hard).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed"))
    want = sorted(((i, *base_measures(t)) for i, t, *_ in HARD), key=lambda r: (r[0] is None, r[0] or 0, repr(r)))
    assert [r[:6] for r in got] == want
    assert all(r[6] == (r[1] < 50 or 100 * r[5] > 50 * r[1]) for r in got)
    assert quality.quality_rules(empty(hard)).count() == 0


def test_quality_tells_junk(spark):
    rng = random.Random(1)
    clean = [" ".join(rng.choice(quality.COMMON["en"].split() + ["house", "garden", "window", "morning"]) for _ in range(300)) for _ in range(30)]
    junk = [" ".join("%%" + "".join(rng.choices(string.ascii_uppercase, k=3)) + "**" for _ in range(300)) for _ in range(2)]
    df = spark.createDataFrame([(i, t, "en") for i, t in enumerate(clean + junk)], "doc_id long, text string, lang string")
    kept = {r["doc_id"]: r["kept"] for r in quality.quality_rules(df).collect()}
    assert all(kept[i] for i in range(30)) and not kept[30] and not kept[31]


@pytest.mark.parametrize("name", [k for k in catalogue.oracle_sql()])
def test_sql_twins(spark, data, name):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{data}/documents.parquet'")
    same(catalogue.queries()[name](spark, data), con.sql(catalogue.oracle_sql()[name]))


def test_exact_dedup_hard_cases(hard):
    frame = pd.DataFrame(HARD, columns=["doc_id", "text", "lang", "source"]).astype({"doc_id": "Int64"})
    got = by_id(exact_dedup.exact_duplicates(hard.where("doc_id is not null")))
    want = sorted(map(tuple, oracle(exact_dedup.ORACLE, documents=frame[frame["doc_id"].notna()]).fetchall()), key=lambda r: (r[0], repr(r)))
    assert got == want
    assert exact_dedup.exact_duplicates(empty(hard)).count() == 0
    assert exact_dedup.exact_duplicates(hard).count() == len(HARD)


def test_exact_dedup_small_filter_stays_exact(spark):
    rows = [(i, f"text {i % 3000}") for i in range(6000)]
    got = exact_dedup.exact_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), max_blocks=1 << 10)
    assert got.where("group_size <> 2").count() == 0 and got.where("kept").agg(F.min("doc_id")).first()[0] == 3000


def test_token_counts_equal_the_library(hard, spark, data):
    tok = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    docs = hard.select("doc_id", "text").union(spark.read.parquet(f"{data}/documents.parquet").select("doc_id", "text"))
    texts = [r["text"] or "" for r in docs.collect()]
    want = sorted(len(tok.encode(t, add_special_tokens=False).ids) for t in texts)
    got = token_counts.token_counts(docs, slice_chars=3000).collect()
    assert sorted(r["n_tokens"] for r in got) == want
    assert sorted(r["n_bytes"] for r in got) == sorted(len(t.encode()) for t in texts)
    assert all(r["over_limit"] == (r["n_tokens"] > 2048) for r in got)
    assert token_counts.token_counts(empty(hard)).count() == 0


def test_merging_overlaps():
    assert token_counts.first_of_runs(np.array([1, 1, 1, 0, 1, 1], bool)).tolist() == [True, False, True, False, True, False]


def test_chat_repair_is_cheapest(spark):
    rng, costs = random.Random(2), chat.RepairCosts()

    def brute(roles):
        best = chat.FAR
        for labels in itertools.product((1, 2, 3), repeat=len(roles)):
            state, cost = 0, 0
            for own, role in zip(roles, labels):
                cost += chat.link(state, role, costs)[0] + (0 if own == role else costs.unknown if own == 0 else costs.relabel)
                state = role
            best = min(best, cost + chat.tables(costs).closing[state])
        return best

    names = {0: None, 1: "System", 2: " human", 3: "gpt"}
    talks = {i: [rng.randrange(4) for _ in range(rng.randint(1, 6))] for i in range(30)}
    talks[99] = [rng.randrange(4) for _ in range(300)]
    rows = [(i, k, names[r], f"t{k}" if k % 3 else None, "x") for i, roles in talks.items() for k, r in enumerate(roles)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, cost string")
    seen = set()
    for parts in (2, 24):  # with many ranges, conversations cross their ends
        spark.conf.set("spark.sql.shuffle.partitions", parts)
        out = chat.formatted(df).toPandas().sort_values(["conv_id", "turn", "part"])
        spark.conf.set("spark.sql.shuffle.partitions", 4)
        cost = out.groupby("conv_id")["cost"].sum()
        assert all(cost[i] == brute(roles) for i, roles in talks.items() if i != 99)
        assert (out["action"] == "end").sum() == len(talks)
        for conv, part in out.groupby("conv_id"):
            text = "".join(part["rendered"])
            order = re.findall(r"<\|(system|user|assistant)\|>", text)
            assert order[-1] == "assistant" and all(a != b for a, b in itertools.pairwise(order)) and "system" not in order[1:]
        seen.add(tuple(out["rendered"]))
    assert len(seen) == 1
    assert chat.formatted(df.where("false")).count() == 0


def test_mixing_meets_targets_and_hard_cases(hard, spark):
    rng = random.Random(3)
    rows = [(i, " ".join(rng.choices(["windows", "gardens", "afternoon", "it", "of"], k=rng.randint(20, 60))), rng.choice(["en", "de"]), rng.choice(["a"] * 8 + ["b", "c"])) for i in range(1500)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    p = mixing.MixParams(rate=0.2, tempers=(0.0, 1.0, 1.0))
    out = mixing.mixed(df, p).toPandas()
    expected = (out["mix_tokens"] * out["mix_probability"]).groupby(out["mix_source"]).sum()
    assert expected.max() / expected.min() < 1.05  # equal shares of all sources
    assert (out["mix_tokens"] * out["mix_probability"]).sum() == pytest.approx(0.2 * out["mix_tokens"].sum(), rel=0.01)
    assert abs(out.loc[out["mix_kept"], "mix_tokens"].sum() / out["mix_tokens"].sum() - 0.2) < 0.04
    assert mixing.mixed(hard).count() == len(HARD) and mixing.mixed(empty(hard)).count() == 0


def test_packing_round_trip(hard, spark, data):
    tok = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    docs = hard.select("doc_id", "text").where("doc_id <> 8").union(spark.read.parquet(f"{data}/documents.parquet").select(F.col("doc_id") + 1000, "text"))
    out = packing.packed(docs, slice_chars=20_000).toPandas()
    ids = {r["doc_id"]: [*tok.encode(r["text"] or "", add_special_tokens=False).ids, 1] for r in docs.collect()}
    for doc, part in out.sort_values("start").groupby("doc_id"):
        assert part["length"].sum() == len(ids[doc]) == part["doc_tokens"].iloc[0]
        at = 0
        for r in part.itertuples():
            assert r.start == at and zlib.crc32(np.array(ids[doc][at : at + r.length], "<u4").tobytes()) == r.ids_crc32
            at += r.length
    assert set(out["doc_id"]) == set(ids)
    for _, part in out.sort_values("offset").groupby("sequence_id"):
        assert part["offset"].tolist() == [0, *part["length"].cumsum().tolist()[:-1]] and part["length"].sum() <= 2048
    assert packing.packed(empty(hard)).count() == 0


def test_best_fit_takes_the_tightest():
    rng = np.random.default_rng(4)
    lengths = rng.integers(1, 64, 300)
    window, offset, made = packing.best_fit_decreasing(lengths, 64)
    room, where = [], []
    for n in sorted(lengths, reverse=True):  # the same by looking at every window
        fits = [(r, -i) for i, r in enumerate(room) if r >= n]
        if fits:
            i = -min(fits)[1]
        else:
            i = len(room)
            room.append(64)
        room[i] -= n
        where.append(i)
    assert made == len(room)
    assert all(lengths[window == w].sum() <= 64 for w in range(made))
    assert (offset >= 0).all()


def near_brute(docs, span, percent):
    sets, parent = {}, {}
    for i, t in docs:
        w = WORDS.findall("".join(c.lower() if c in string.ascii_uppercase else c for c in t or ""))
        sets[i] = {tuple(w[k : k + span]) for k in range(max(1, len(w) - span + 1))} if w else set()
        parent[i] = i

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
            x, y = find(a), find(b)
            parent[max(x, y)] = min(x, y)
    return sorted((i, len(sets[i]), find(i)) for i in sets)


@pytest.mark.parametrize("span, percent, few, pivots", [(3, 90, 16, 64), (3, 90, 1, 4), (5, 80, 2, 2)])
def test_jaccard_join_equals_brute_force(spark, span, percent, few, pivots):
    rng, docs = random.Random(span * 16), []
    vocabulary = [f"w{i}" for i in range(400)]
    templates = [rng.choices(vocabulary, k=n) for n in (12, 60, 150, 150)]
    for i in range(260):  # copies of four templates with edits, so that regions are large and chained
        w = list(templates[i % 4] if i % 5 else rng.choices(vocabulary, k=40))
        for _ in range(rng.choice([0, 1, 1, 2, 3, 6])):
            w[rng.randrange(len(w))] = rng.choice(vocabulary).upper()
        docs.append((i, " ".join(w)))
    docs += [(900, None), (901, ""), (902, "just two"), (903, "JUST  two"), (904, "one")]
    df = spark.createDataFrame(docs, "doc_id long, text string").withColumn("n", F.lit("clash"))
    got = by_id(jaccard_join.near_duplicates(df, jaccard_join.JoinParams(span=span, percent=percent, few=few, pivots=pivots, chunk=32, cut=20)).drop("text_hash"))
    assert got == near_brute(docs, span, percent)


def test_jaccard_join_hard_cases(hard):
    got = jaccard_join.near_duplicates(hard, jaccard_join.JoinParams(span=3, percent=90))
    assert got.count() == len(HARD)
    assert {r["doc_id"]: r["component_id"] for r in got.collect()}[4] == 3
    assert jaccard_join.near_duplicates(empty(hard)).count() == 0


def test_language_id(spark, data, hard):
    docs = spark.read.parquet(f"{data}/documents.parquet")
    out = langid.identified(docs, langid.LanguageParams(per_label=30)).toPandas().merge(docs.select("doc_id", "lang").toPandas(), on="doc_id")
    held = out["doc_id"].map(lambda i: zlib.crc32(str(i).encode()) % 3 == 1)
    assert (out["held_out"] == held).all() and out["score"].between(0, 1).all()
    assert (out.loc[held, "lang"] == out.loc[held, "lang_pred"]).mean() >= 0.95
    got = langid.identified(hard, langid.LanguageParams(per_label=5)).collect()
    assert len(got) == len(HARD) and all(r["lang_pred"] == "und" for r in got if r["doc_id"] in (1, 2))
    assert langid.identified(empty(hard)).count() == 0


def test_temperature():
    z = np.array([[4.0, 0.0]] * 10)
    assert langid.fitted_temperature(z, np.array([0] * 7 + [1] * 3)) > 2


def repeated_brute(docs, p):
    lines = sorted((i, k, tuple(WORDS.findall(x))) for i, t in docs for k, x in enumerate((t or "").split("\n")))
    lines = [x for x in lines if len(x[2]) >= p.least_words]

    def near(a, b):
        if len(a) < p.near_words or len(b) < p.near_words or abs(len(a) - len(b)) > 1:
            return False
        if len(a) == len(b):
            return sum(x != y for x, y in zip(a, b)) == 1
        a, b = sorted((a, b), key=len)
        return any(b[:i] + b[i + 1 :] == a for i in range(len(b)))

    out = []
    for n, (i, k, w) in enumerate(lines):
        same = [x for x in lines[:n] if x[2] == w]
        close = [x for x in lines[:n] if near(x[2], w)]
        if same or close:
            first = (same or close)[0]
            out.append((i, k, not same, first[0], first[1]))
    return out


def test_line_dedup_equals_brute_force(spark):
    rng, p = random.Random(6), line_dedup.LineParams(least_words=3, near_words=5)
    base = [rng.choices(list("abcdefgh"), k=rng.randint(2, 14)) for _ in range(25)]
    docs = []
    for i in range(60):
        lines = []
        for _ in range(rng.randint(0, 5)):
            w = list(rng.choice(base))
            for _ in range(rng.choice([0, 0, 1, 1, 2])):
                k = rng.randrange(len(w))
                rng.choice([lambda w=w, k=k: w.__setitem__(k, "z"), lambda w=w, k=k: w.insert(k, "y"), lambda w=w, k=k: len(w) > 1 and w.pop(k)])()
            lines.append("  ".join(w))
        docs.append((i, "\n".join(lines)))
    docs.append((99, None))
    got = line_dedup.repeated_lines(spark.createDataFrame(docs, "doc_id long, text string"), p)
    assert sorted(map(tuple, got.collect())) == sorted(repeated_brute(docs, p))


def test_line_dedup_rewrites(hard, spark):
    same_line = "this line has more than five words"
    df = spark.createDataFrame([(1, f"{same_line}\nown words of the first document"), (2, f"short\n{same_line}"), (3, same_line), (4, None), (5, "")], "doc_id long, text string")
    out = {r["doc_id"]: r["text"] for r in line_dedup.without_repeated_lines(df).collect()}
    assert out == {1: f"{same_line}\nown words of the first document", 2: "short", 4: None, 5: ""}
    assert line_dedup.without_repeated_lines(hard).columns == hard.columns
    assert line_dedup.repeated_lines(empty(hard)).count() == 0


def levenshtein_prefix(term, word):
    """The least edits that turn the term into a beginning of the word."""
    row = list(range(len(word) + 1))
    best = [row]
    for i, c in enumerate(term, 1):
        row = [i] + [0] * len(word)
        for j, d in enumerate(word, 1):
            row[j] = min(best[-1][j] + 1, row[j - 1] + 1, best[-1][j - 1] + (c != d))
        best.append(row)
    return min(best[-1])


def test_fuzzy_trie_equals_edit_distance():
    rng = random.Random(7)
    terms = ["idiot", "scum", "moron", "trashy", "abcabc"]
    trie = toxicity.FuzzyTrie(terms, 5)
    words = ["idiots", "idoit", "1diot", "scums", "scam", "mron", "xmoron", "trahsy", "abab", ""] + ["".join(rng.choices("abcidotmrnsu", k=rng.randint(1, 9))) for _ in range(3000)]
    for w in words:
        fits = [e for t in terms if (e := levenshtein_prefix(t, w)) <= (1 if len(t) >= 5 else 0)]
        assert trie.edits(w) == (min(fits) if fits else None), w


def test_toxicity_learns_and_tells_quotes(spark, hard):
    rng = random.Random(8)
    filler = ["stone", "river", "cloud", "meadow", "paper", "lantern", "bridge", "orchard"]
    rows, labels = [], []
    for i in range(400):
        w = rng.choices(filler, k=60)
        toxic = i % 3 == 0
        if toxic:
            for k in range(4):
                w[10 * k + 5] = rng.choice(["blighter", "wretchly", "fouling"])
        rows.append((i, " ".join(w)))
        labels.append((i, int(toxic)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    marks = spark.createDataFrame(labels, "doc_id long, toxic int")
    out = toxicity.scored(docs, marks).toPandas().merge(pd.DataFrame(labels, columns=["doc_id", "toxic"]), on="doc_id")
    held = out[out["held_out"]]
    assert (held["predicted"] == held["toxic"]).mean() > 0.97
    assert (out["held_out"] == out["doc_id"].map(lambda i: zlib.crc32(str(i).encode()) % 5 == 0)).all()
    scanner = toxicity.Scanner(["blighter"], toxicity.ToxicityParams())
    x = dict(zip(toxicity.FEATURES, scanner.features('they wrote "blighter" in the paper')))
    assert x["quoted"] > 0 and x["exact"] == 0
    assert dict(zip(toxicity.FEATURES, scanner.features("what a blighter")))["exact"] > 0
    got = toxicity.scored(hard, marks.where("false")).collect()
    assert len(got) == len(HARD) and all(r["predicted"] == 0 for r in got)
    assert toxicity.scored(empty(hard), marks).count() == 0
