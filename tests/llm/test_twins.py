"""Plain-Python twins of the classifiers and of the pipeline's stages, and names, nulls and collisions that the operators meet."""

import itertools
import math
import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from trajdp.llm import chat, jaccard_join, langid, line_dedup, mixing, stages, toxicity

from .test_operators import levenshtein_prefix, near_brute, repeated_brute

CLASH = ("mix_source", "mix_lang", "MIX_kept", "mix_tokens", "mix_words", "tox_score", "tox_predicted", "gone_lines", "gone_id", "gone_hash", "kept_text", "text_hash", "line_no", "region", "n")


def test_n_grams_and_learning_equal_plain_python():
    p = langid.LanguageParams(buckets=64)

    def counted(text):
        out = Counter()
        code = [ord(c) for c in text.lower()]
        for n in p.sizes:
            for i in range(len(code) - n + 1):
                h = langid.SALTS[n % 3]
                for c in code[i : i + n]:
                    h = ((h ^ c) * 0x01000193) % 2**32
                out[((h ^ (h >> 15)) * 0x2C1B3C6D) % 2**32 >> 26] += 1
        return out

    rng = random.Random(1)
    texts = ["", "a", "été"] + ["".join(rng.choices("abcdeé zß", k=30)) for _ in range(30)]
    for t in texts:
        got = langid.n_grams(t, p)
        assert {i: n for i, n in enumerate(got.tolist()) if n} == counted(t)
    idf = {i: 1 + math.log((1 + len(texts)) / (1 + sum(i in counted(t) for t in texts))) for i in range(64)}
    z, sq = [[0.0] * 2 for _ in range(64)], [[0.0] * 2 for _ in range(64)]

    def vector(t):
        v = {i: (1 + math.log(n)) * idf[i] for i, n in counted(t).items()}
        norm = math.sqrt(sum(x * x for x in v.values()))
        return {i: x / norm for i, x in v.items()} if norm else v

    def weight(i, k):
        if abs(z[i][k]) <= p.l1:
            return 0.0
        return -(z[i][k] - math.copysign(p.l1, z[i][k])) / ((p.beta + math.sqrt(sq[i][k])) / p.alpha + p.l2)

    def chances(v):
        e = [math.exp(sum(x * weight(i, k) for i, x in v.items())) for k in (0, 1)]
        return [x / sum(e) for x in e]

    model = langid.Ftrl(64, 2, p)
    for j, t in enumerate(texts[3:]):
        v, label = vector(t), j % 2
        g = chances(v)
        g[label] -= 1
        for i, x in v.items():
            for k in (0, 1):
                w, step = weight(i, k), x * g[k]
                z[i][k] += step - (math.sqrt(sq[i][k] + step * step) - math.sqrt(sq[i][k])) / p.alpha * w
                sq[i][k] += step * step
        counts = langid.n_grams(t, p)
        at = np.flatnonzero(counts)
        model.learn(*langid.features(at, counts[at], np.array([idf[i] for i in range(64)])), label)
    fitted = langid.LanguageModel(["x", "y"], np.array([idf[i] for i in range(64)]), model.weights(slice(None)), 1.0, p)
    for t in texts:
        if any(map(str.isalpha, t)):
            want = chances(vector(t))
            label, score = fitted.predict(t)
            assert score == pytest.approx(max(want), abs=1e-9) and (label == "xy"[want.index(max(want))] or abs(want[0] - want[1]) < 1e-9)


def plain_features(text, terms, p):
    text = (text or "").lower()
    words = toxicity.WORDS.findall(text)
    edits = {}
    for w in set(words):
        fits = [e for t in terms if (e := levenshtein_prefix(t, w)) <= (1 if len(t) >= p.fuzzy_letters else 0)]
        if fits:
            edits[w] = min(fits)
    if not edits:
        return np.zeros(6)
    tokens = toxicity.TOKENS.findall(text)
    exact = fuzzy = quoted = addressed = 0
    for i, t in enumerate(tokens):
        if t in edits:
            near = tokens[max(0, i - p.window) : i + p.window + 1]
            inside = sum(x in toxicity.QUOTES for x in tokens[:i]) % 2 == 1 and any(x in toxicity.QUOTES for x in tokens[i + 1 : i + 1 + 4 * p.window])
            if inside or any(x in toxicity.REPORTING for x in near):
                quoted += 1
            elif edits[t] == 0:
                exact += 1
            else:
                fuzzy += 1
            addressed += any(x in toxicity.ADDRESSING for x in near)
    return np.array([math.log1p(exact), math.log1p(fuzzy), math.log1p(quoted), math.log1p(addressed), math.log1p(len(edits)), min(1.0, 20 * (exact + fuzzy) / len(words))])


def test_toxic_features_and_weights_equal_plain_python():
    rng, p = random.Random(2), toxicity.ToxicityParams()
    terms = ["idiot", "scum", "moron"]
    scanner = toxicity.Scanner(terms, p)
    pool = ["idiots", "idoit", "scums", "scam", "mron", "stone", "river", "you", "said", '"', "“", "cloud", "moronic", "xidiot"]
    x = []
    for _ in range(400):
        text = " ".join(rng.choices(pool, k=rng.randint(0, 40)))
        assert np.allclose(scanner.features(text), plain_features(text, terms, p)), text
        x.append(scanner.features(text))
    x, y = np.array(x), np.array([rng.random() < 0.2 + 0.5 * (v[0] > 0) for v in x], float)
    w = toxicity.logistic(x, y, p.ridge)
    m = 1 / (1 + np.exp(-(w[0] + x @ w[1:])))
    slope = np.r_[(m - y).sum(), x.T @ (m - y) + p.ridge * len(y) * w[1:]]
    assert np.abs(slope).max() < 1e-3  # the penalised likelihood is at its top


def documents(spark):
    rng = random.Random(4)
    words = "stone river cloud meadow paper lantern bridge orchard window garden".split()
    rows = []
    for i in range(160):
        lines = [" ".join(rng.choices(words, k=rng.randint(6, 14))) for _ in range(rng.randint(1, 5))]
        if i % 4 == 0:
            lines.append("this boilerplate line is found in every fourth document of them all")
        if i % 10 == 3:
            lines.append(" ".join(["blighter"] * 4 + rng.choices(words, k=8)))
        rows.append((i, "\n".join(lines), rng.choice(["en", "de", None]), rng.choice(["a", "a", "b"]), 0))
    for i in range(160, 200):  # near copies
        w = rows[i - 160][1].split(" ")
        w[rng.randrange(len(w))] = "changed"
        rows.append((i, " ".join(w), "en", "a", 0))
    short = [" ".join(rng.choices(words, k=3)) for _ in range(60)]  # lines too short to be looked at
    for i in range(200, 206):
        lines = list(short)
        lines[rng.randrange(60)] = "another short line"
        rows.append((i, "\n".join(lines), "en", "a", 0))
    rows += [(300, None, "en", "a", None), (301, "", None, None, 0), (302, "?! 12", "en", "b", 0), (None, rows[0][1], "en", "a", 0), (303, "one two " * 300_000, "en", "b", 0)]
    return rows, spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars int").withColumns({c: F.lit("own") for c in CLASH})


def test_stages_equal_plain_python(spark, tmp_path):
    rows, docs = documents(spark)
    labels = [(i, int("blighter" in t)) for i, t, *_ in rows if i is not None and t]
    spark.createDataFrame(labels, "doc_id long, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    texts = {i: t for i, t, *_ in rows}
    written = lambda df, k: (df.write.parquet(f"{tmp_path}/{k}"), spark.read.parquet(f"{tmp_path}/{k}"))[1]
    columns = docs.columns
    docs = written(docs, "in")

    model = toxicity.fit_toxicity(docs, spark.read.parquet(f"{tmp_path}/labels.parquet"))
    out = written(stages.toxicity_stage(spark, docs, str(tmp_path)), "toxicity")
    assert out.columns == columns and out.where("mix_source <> 'own' or tox_score <> 'own'").count() == 0
    want = {i for i, t in texts.items() if model.score(plain_features(t, model.terms, model.params)) < 0.5}
    assert {r["doc_id"] for r in out.select("doc_id").collect()} == want and 0 < len(want) < len(texts)

    before = {r["doc_id"]: r["text"] for r in out.collect()}
    out = written(stages.line_stage(spark, out, str(tmp_path)), "lines")
    gone = {(i, k) for i, k, *_ in repeated_brute([(-1 if i is None else i, t) for i, t in before.items()], line_dedup.LineParams())}
    want = {}
    for i, t in before.items():
        lines = None if t is None else [x for k, x in enumerate(t.split("\n")) if ((-1 if i is None else i), k) not in gone]
        if t is None or len(lines) == len(t.split("\n")) or "".join(lines).strip():
            want[i] = None if t is None else "\n".join(lines)
    assert {r["doc_id"]: r["text"] for r in out.collect()} == want and len(gone) > 20

    ids = {i: t for i, t in want.items() if i is not None}
    out = written(stages.near_duplicate_stage(spark, out, str(tmp_path)), "near")
    keep = {i for i, n, c in near_brute(list(ids.items()), 5, 80) if i == c}
    assert {r["doc_id"] for r in out.collect()} - {None} == keep and len(keep) < len(ids) and out.columns == columns

    mixed = mixing.mixed(out, stages.MIX).collect()
    n = mixing.names(out.columns)
    want = {r["doc_id"] for r in mixed if r[n["kept"]]}
    got = stages.mixing_stage(spark, out, str(tmp_path))
    assert got.columns == columns and {r["doc_id"] for r in got.collect()} == want
    assert all(0 <= r[n["probability"]] <= 1 for r in mixed) and stages.packing_stage(spark, out, str(tmp_path)).select("doc_id").distinct().count() == out.count()
    assert [k for k, _ in corpus_pipeline.STAGES] == ["toxicity", "line_dedup", "near_duplicates", "mixing", "packing"]


def test_foreign_lines_that_meet_in_a_key_are_told_apart(spark):
    rng, p = random.Random(6), line_dedup.LineParams(least_words=2, near_words=4, key_bits=5)
    base = [rng.choices(list("abcdef"), k=rng.randint(4, 8)) for _ in range(12)]
    docs = []
    for i in range(40):
        w = list(rng.choice(base))
        w[rng.randrange(len(w))] = rng.choice("xyz")
        docs.append((i, " ".join(w)))
    got = line_dedup.repeated_lines(spark.createDataFrame(docs, "doc_id long, text string"), p)
    assert sorted(map(tuple, got.collect())) == sorted(repeated_brute(docs, p))


def test_rows_without_ids_lose_only_their_own_lines(spark):
    same, other = "this line stands in both of the texts", "only the second text has this one"
    df = spark.createDataFrame([(None, f"short\n{same}"), (None, f"{other}\n{same}\nown words that stand here alone"), (7, same)], "doc_id long, text string")
    out = sorted(r["text"] for r in line_dedup.without_repeated_lines(df).collect())
    kept = "\n".join(out)
    assert kept.count(same) == 1 and kept.count(other) == 1 and "short" in kept and "own words that stand here alone" in kept


def test_rows_that_share_an_id_are_points_of_their_own(spark):
    texts = [" ".join(f"w{i}{k}" for k in range(30)) for i in range(3)]
    df = spark.createDataFrame([(5, texts[0]), (5, texts[1]), (6, texts[1] + " more"), (7, texts[2]), (None, texts[2])], "doc_id long, text string")
    got = sorted((r["doc_id"] is None, r["doc_id"] or 0, r["component_id"]) for r in jaccard_join.near_duplicates(df, jaccard_join.JoinParams(span=3, percent=80)).collect())
    assert got == [(False, 5, 5), (False, 5, 5), (False, 6, 5), (False, 7, 7), (True, 0, 7)]


def test_conversations_with_nulls_and_repeated_rows(spark):
    rows = [(1, 0, "user", "a"), (1, 0, "user", "a"), (1, None, None, None), (None, 1, "assistant", "x"), (None, None, "user", None), (2, 3, "tool", "t"), (2, 3, "tool", "t")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("part", F.lit("clash"))
    out = chat.formatted(df).toPandas()
    costs = chat.RepairCosts()
    order = {1: [0, 2, 2], None: [2, 3], 2: [0, 0]}  # roles in the order of turns, null ones first
    for conv, roles in order.items():
        part = out[out["conv_id"].isna()] if conv is None else out[out["conv_id"] == conv]
        best = min(
            sum(chat.link(a, b, costs)[0] + (0 if own == b else costs.unknown if own == 0 else costs.relabel) for a, b, own in zip((0, *labels), labels, roles)) + chat.tables(costs).closing[labels[-1]]
            for labels in itertools.product((1, 2, 3), repeat=len(roles)))
        assert part["cost"].sum() == best and (part["action"] == "end").sum() == 1
