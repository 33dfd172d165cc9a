"""Line signatures and verification by hashes of shingles, and components in one task."""

import random

import numpy as np
import pyarrow as pa
import pytest

from parsieve.llm import lines, linking
from parsieve.llm.common import Cuts


def shingles(line):
    u = line.encode("utf-16-le")
    return {u[2 * k : 2 * (k + lines.Q)] for k in range(max(0, len(u) // 2 - lines.Q) + 1)}


def test_shingle_hashes_are_the_shingles():
    some = ["a", "ab", "abcdefg", "abcdefgh", "=-" * 30, "\U0001d11e clef \U0001d11e clef", "tab\tand\rreturn", "abcdefgh abcdefgh"]
    got = lines._sets(some)
    known = {}
    for line, hashes in zip(some, got, strict=True):
        assert len(hashes) == len(shingles(line))
        known |= dict.fromkeys(hashes.tolist())
    assert len(known) == len(set().union(*map(shingles, some)))


def test_verification_matches_sets():
    rng = random.Random(5)
    words = [f"w{i}" for i in range(40)]
    some = [" ".join(rng.choices(words, k=rng.choice((1, 5, 40)))) for _ in range(20)]
    some += [x[: rng.randrange(len(x) + 1)] + "!" + x[rng.randrange(len(x)) :] for x in some]
    rows = [(i, j, some[i], some[j]) for i in range(len(some)) for j in range(i)]
    batch = pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows)], names=["a", "b", "line_a", "line_b"])
    got = {p for out in lines._verified([batch], 80) for p in zip(out.column(0).to_pylist(), out.column(1).to_pylist())}
    s = [shingles(x) for x in some]
    assert got == {(i, j) for i, j, *_ in rows if 100 * len(s[i] & s[j]) >= 80 * len(s[i] | s[j])} and got


@pytest.mark.parametrize("one_task", [0, 1000])
def test_components_of_paths_and_rings(spark, one_task):
    ids = random.Random(3).sample(range(10_000), 60)
    edges = [*zip(ids[:20], ids[1:20]), *zip(ids[20:40], ids[21:40]), (ids[39], ids[20]), (ids[50], ids[50])]
    cuts = Cuts(spark)
    got = {r["id"]: r["component"] for r in linking.components(cuts, cuts.cut(spark.createDataFrame(edges, "a long, b long")), one_task).collect()}
    assert got == {x: min(part) for part in (ids[:20], ids[20:40]) for x in part}


@pytest.mark.parametrize("few", [2, 1000])
def test_buckets_of_several_components(spark, few, monkeypatch):
    """Pairs of one bucket, in full or by hubs and prefixes, give the components of all links."""
    monkeypatch.setattr(linking, "FEW", few)
    rng = random.Random(9)
    base = [" ".join(f"word{rng.randrange(900)}" for _ in range(30)) for _ in range(4)]
    texts = [t for b in base for t in (b, b + " one", b + " two", b[5:])]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    cuts = Cuts(spark)
    rows = lines.lines_of(docs)
    signed = cuts.cut(lines.signed_lines(rows))
    from pyspark.sql import functions as F

    # One bucket for all, with one mark, so that no pair ends before it is verified.
    keys = cuts.cut(signed.select(F.col("key").alias("id"), F.struct(F.lit(0).cast("long").alias("sketch0"), F.lit(0).cast("long").alias("sketch1")).alias("mark"), F.lit(1).cast("long").alias("bucket")))
    got = {r["id"]: r["component"] for r in linking.link(cuts, keys, lines._Lines(spark, rows), 80).collect()}
    of = {r["line"]: r["key"] for r in rows.collect()}
    groups = [[of[t.strip(" ")] for t in texts[4 * i : 4 * i + 4]] for i in range(4)]
    assert got == {k: min(g) for g in groups for k in g}


def test_kept_text_splits_once(spark):
    text = "\n".join(f"line {i}" for i in range(50))
    from pyspark.sql import functions as F

    df = spark.createDataFrame([(text, [0, 7, 49]), (text, None)], "text string, gone array<int>")
    plan = df.select(lines._kept_text(F.col("text"), F.col("gone")).alias("t"))
    assert [r["t"] for r in plan.collect()] == ["\n".join(f"line {i}" for i in range(50) if i not in (0, 7, 49)), text]
    assert plan._jdf.queryExecution().optimizedPlan().toString().count("split(") == 1
