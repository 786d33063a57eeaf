"""Later copies of a line that the bounded filter lets through."""

from trajdp.llm import line_dedup


def test_copies_are_not_foreign_lines(spark, monkeypatch):
    """Many marks in few blocks let copies through; their keys need no variants by words."""
    near = [(i, f"a{i} b{i} c d e f g h i j k{i} l" + "\n" + f"a{i} b{i} c d e f x h i j k{i} l") for i in range(4000)]
    docs = spark.createDataFrame(near + [(10_000 + i, t) for i, t in near[:3000]], "doc_id long, text string")

    def never(*_):
        raise AssertionError("variants by words")

    monkeypatch.setattr(line_dedup, "spelt_variants", never)
    found = line_dedup.repeated_lines(docs, line_dedup.LineParams(most_blocks=1024)).collect()
    first = {(r["doc_id"], r["line_no"], r["near"], r["first_doc_id"], r["first_line_no"]) for r in found}
    want = {(i, 1, True, i, 0) for i in range(4000)} | {(10_000 + i, k, False, i, k) for i in range(3000) for k in (0, 1)}
    assert first == want
