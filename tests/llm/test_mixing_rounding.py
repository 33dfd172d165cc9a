"""A pass count that rounds below a whole number costs no row."""

from collections import Counter

from parsieve.llm import mixing


def test_least_passes_are_one_where_the_quotient_rounds_below(spark):
    rows = [(i, "abcd", "a") for i in range(98)] + [(1000 + i, "abcd", "b") for i in range(15)]  # a token each
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    used = Counter(r["doc_id"] for r in mixing.mixture(docs).collect())
    assert used == {d: 1 if s == "a" else 2 for d, _, s in rows}
    assert mixing.mix_stage(spark, docs).distinct().count() == len(rows)


def test_plans_lose_no_row():
    for a in range(1, 400, 7):
        for b in range(1, 400, 3):
            assert min(mixing.plan({"a": a, "b": b, None: 5}).passes.values()) >= 1
