"""Line dedup runs DataFrame operations only, and links as sets of shingles do."""

import random

from pyspark.sql import DataFrame

from parsieve.llm import lines


def test_no_python_on_the_executors(spark, monkeypatch):
    def refused(*_, **__):
        raise AssertionError("Python on the executors")

    rng = random.Random(4)
    base = [" ".join(f"w{rng.randrange(5000)}" for _ in range(40)) for _ in range(5)]
    ruled = ["=-" * 400, "-=" * 390, "abcdefghijk" * 60, "defghijkabc" * 61]
    found = [*base, *(f"{b} and \U0001d11e" for b in base), *(f"{b[20:]}" for b in base), *ruled, "a", "ab", "a", "\U0001d11e"]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(found)] + [(99, None), (100, "")], "doc_id long, text string")
    for kind in {DataFrame, type(docs)}:
        monkeypatch.setattr(kind, "mapInArrow", refused)
    got = {r["doc_id"]: (r["n_lines"], r["n_dropped"]) for r in lines.deduped(spark, docs).collect()}
    sets = lines._sets(found)
    near = lambda a, b: 100 * len(set(sets[a]) & set(sets[b])) >= 80 * len(set(sets[a]) | set(sets[b]))
    gone = {i for i in range(len(found)) if any(near(i, j) for j in range(i))}
    assert got == {i: (1, int(i in gone)) for i in range(len(found))} | {99: (0, 0), 100: (0, 0)}
    assert {16, 18, 21} <= gone and len(gone) == 13
