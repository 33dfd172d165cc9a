"""Rounds of joins over few edges need no exchange, and give what larger ones give."""

import random

from parsieve.llm import linking
from parsieve.llm.common import Cuts


def test_small_rounds_write_one_table_each(spark, monkeypatch):
    names, cut = [], Cuts.cut
    monkeypatch.setattr(Cuts, "cut", lambda self, df, name="t": (names.append((name, df._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning"))), cut(self, df, name))[1])
    ids = random.Random(8).sample(range(10_000), 40)
    edges = spark.createDataFrame([*zip(ids[:30], ids[1:30]), (ids[30], ids[31])], "a long, b long")
    cuts = Cuts(spark)
    given = cuts.cut(edges, "given")
    want = {x: min(part) for part in (ids[:30], ids[30:32]) for x in part}
    found = linking.components(cuts, given, 0)
    assert {r["id"]: r["component"] for r in found.collect()} == want
    assert {n for n in names if n[0] != "given"} == {("edges", 0)}
    monkeypatch.setattr(linking, "ONE_PLACE", 0)
    assert {r["id"]: r["component"] for r in linking.components(cuts, given, 0).collect()} == want
