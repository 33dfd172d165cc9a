"""A pair that shares several small buckets is made once, and its bitmaps are compared as columns."""

import random

from pyspark.sql import functions as F

from parsieve.llm import lines, linking
from parsieve.llm.common import Cuts


def test_a_pair_is_made_in_one_of_its_buckets(spark, monkeypatch):
    rng = random.Random(6)
    base = [f"word{rng.randrange(900)}" for _ in range(40)]
    near = [" ".join([*base[:at], f"new{at}", *base[at + 1 :]]) for at in range(0, 40, 2)]
    far = [" ".join(f"far{i}x{j}" for j in range(40)) for i in range(200)]
    rows = lines.lines_of(spark.createDataFrame(list(enumerate(near + far)), "doc_id long, text string"))
    key = {r["doc_id"]: r["key"] for r in rows.select("doc_id", "key").collect()}
    # The smallest item of all buckets is far from the others, which are linked with one another.
    hub, copies = min(key.values()), {key[i] for i in range(len(near))}
    assert hub not in copies
    mark = F.struct(F.lit(0).cast("long").alias("sketch0"), F.lit(0).cast("long").alias("sketch1"))
    cuts, paired, made = Cuts(spark), linking._paired, []
    keys = cuts.cut(rows.where(F.col("key").isin(hub, *copies)).select(F.col("key").alias("id"), mark.alias("mark"), F.explode(F.array(*(F.lit(i).cast("long") for i in range(3)))).alias("bucket")))
    monkeypatch.setattr(Cuts, "drop", lambda self, *frames: None)
    monkeypatch.setattr(linking, "_paired", lambda *x: (made.append(paired(*x)), made[-1])[1])
    got = {r["id"]: r["component"] for r in linking.link(cuts, keys, lines._Lines(spark, rows), 80).collect()}
    assert got == dict.fromkeys(copies, min(copies))
    n = len(copies) * (len(copies) - 1) // 2
    assert made[0].count() == made[0].distinct().count() == n
    joins = [x for x in made[0]._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Join Inner" in x]
    assert joins and not any("parity" in x for x in joins)
