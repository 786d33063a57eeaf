"""Raking to the end: margins that depend on each other, targets out of reach, and the shares that are reported."""

import random

import duckdb
import numpy as np
import pytest

from trajdp.llm import mixing

WORDS = {"t0": "windows", "t1": "afternoon", "t3": "gardens"}  # long words by the class of their initials


@pytest.fixture(scope="module")
def correlated(spark):
    """Source, language and topic mostly agree, so that one round for a margin undoes another."""
    rng = random.Random(5)
    rows = []
    for i in range(900):
        k = rng.choices([0, 1, 2], [6, 3, 1])[0]
        lang, topic = (k if rng.random() < 0.85 else rng.randrange(3) for _ in range(2))
        word = list(WORDS.values())[topic]
        rows.append((i, " ".join([word] * rng.randint(20, 60)), ["en", "de", "fr"][lang], "abc"[k]))
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")


def shares(frame, column, weight):
    return frame.groupby(column)[weight].sum() / frame[weight].sum()


@pytest.mark.parametrize("most_cells", [200_000, 0])
def test_correlated_margins_meet_their_targets(spark, correlated, most_cells):
    p = mixing.MixParams(rate=0.002, tempers=(0.0, 0.3, 0.0), most_cells=most_cells, tolerance=1e-7 if most_cells else 1e-3)
    out = mixing.mixed(correlated, p).toPandas()
    assert out["mix_probability"].max() < 1
    out["expected"] = out["mix_tokens"] * out["mix_probability"]
    for margin, power in zip(mixing.MARGINS, p.tempers):
        target = out.groupby(f"mix_{margin}")["mix_tokens"].sum() ** power
        assert np.abs(shares(out, f"mix_{margin}", "expected") - target / target.sum()).max() < 2 * p.tolerance


def test_targets_out_of_reach_end_and_are_reported(spark, caplog):
    docs = spark.createDataFrame([(1, "windows " * 9, "en", "a"), (2, "gardens " * 3, "de", "b")], "doc_id long, text string, lang string, source string")
    targets = spark.createDataFrame([("source", "a", 0.5), ("source", "b", 0.5), ("lang", "en", 0.9), ("lang", "de", 0.1), ("topic", "t3", 1.0), ("topic", "t0", 0.0)], "margin string, key string, share double")
    assert mixing.mixed(docs, targets=targets).count() == 2
    assert "largest margin error" in caplog.text


@pytest.mark.parametrize("tolerance", [1.0, 1e-7])  # after ten rounds, and at the end
def test_rounds_are_those_of_the_sql_twin(spark, data, tolerance):
    docs = spark.read.parquet(f"{data}/documents.parquet").select("doc_id", "text", "lang", "source")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{data}/documents.parquet'")
    p = mixing.MixParams(tolerance=tolerance)
    want = con.sql(mixing.oracle(p)).df().set_index("doc_id")["probability"]
    found = mixing.mixed(docs, p).toPandas().set_index("doc_id")["mix_probability"]
    assert np.abs(found - want.loc[found.index]).max() < 1e-6


def test_report_has_target_and_expected_shares(correlated):
    for rate in (0.002, 0.9):
        p = mixing.MixParams(rate=rate, tempers=(0.0, 0.3, 0.0))
        report = mixing.margin_report(correlated, p).toPandas()
        out = mixing.mixed(correlated, p).toPandas()
        out["expected"] = out["mix_tokens"] * out["mix_probability"]
        for margin, part in report.groupby("margin"):
            part = part.set_index("key")
            assert np.abs(part["tokens_share"] - shares(out, f"mix_{margin}", "mix_tokens")).max() < 1e-9
            assert np.abs(part["expected_share"] - shares(out, f"mix_{margin}", "expected")).max() < 1e-9
            assert np.abs(part["weight_share"] - part["target"]).max() < 2e-7
        missed = np.abs(report["expected_share"] - report["target"]).max()
        assert missed < 2e-7 if rate == 0.002 else missed > 0.05


def test_topic_column_is_used(spark):
    docs = spark.createDataFrame([(1, "windows", "en", "a", "sport"), (2, "windows", "en", "a", None)], "doc_id long, text string, lang string, source string, topic string")
    assert {r["doc_id"]: r["mix_topic"] for r in mixing.celled(docs, mixing.MixParams()).collect()} == {1: "sport", 2: mixing.NONE}
    assert {r["mix_topic"] for r in mixing.celled(docs.drop("topic"), mixing.MixParams()).collect()} == {"t3"}
