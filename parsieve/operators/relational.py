"""Counting with joins and aggregations only, for tables too large to broadcast.

A batch of sets is broadcast (its length is checked), each compressed row gives a cell
number per set by mixed radix, and two aggregations give the sums of c * log2 c. The
same plan scores listed pairs; the search over (target, set) rows passes optima from
predecessors to children instead of looking lists up.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parsieve.functions import bitset
from parsieve.functions.scores import Score
from parsieve.operators import kernel
from parsieve.operators.search import SearchResult
from parsieve.plans.encode import Encoded
from parsieve.plans.staging import Stage

BATCH = 4096


def count_log_sums(spark: SparkSession, enc: Encoded, sets: list[int]) -> dict[int, float]:
    """C(S) of each set of columns (bits), exact for any number of rows."""
    out: dict[int, float] = {}
    for i in range(0, len(sets), BATCH):
        out |= {r["u"]: r["logs"] for r in _sums(spark, enc, sets[i : i + BATCH]).collect()}
    return out


def _sums(spark: SparkSession, enc: Encoded, sets: list[int]) -> DataFrame:
    codes = F.array(*(F.col(c).cast("long") for c in enc.order)) if enc.order else F.array().cast("array<bigint>")
    radix = F.array(*(F.lit(a).cast("long") for a in enc.arity))
    rows = [(u, bitset.members(u)) for u in sets]
    batch = F.broadcast(spark.createDataFrame(rows, "u long, at array<int>"))  # BATCH rows at most
    # A product of arities beyond a long needs the codes themselves as the key.
    wide = max((kernel_product(enc, u) for u in sets), default=1) >= 2**62
    if wide:
        cell = F.transform("at", lambda i: F.element_at(codes, i + 1))
    else:
        cell = F.aggregate("at", F.lit(0).cast("long"), lambda acc, i: acc * F.element_at(radix, i + 1) + F.element_at(codes, i + 1))
    counts = enc.rows.crossJoin(batch).select("u", cell.alias("cell"), "w").groupBy("u", "cell").agg(F.sum("w").alias("c"))
    return counts.groupBy("u").agg(F.sum(F.col("c") * F.log2("c")).alias("logs"))


def kernel_product(enc: Encoded, u: int) -> float:
    q = 1.0
    for i in bitset.members(u):
        q *= enc.arity[i]
    return q


def conditional_entropy(spark: SparkSession, enc: Encoded, target: str, parents: list[str]) -> float:
    """H(target | parents) in bits."""
    u, t = bitset.from_names(parents, enc.order), enc.order.index(target)
    sums = count_log_sums(spark, enc, [u, u | 1 << t])
    return (sums[u] - sums[u | 1 << t]) / enc.m


def score_pairs(spark: SparkSession, enc: Encoded, scorer: Score, pairs: list[tuple[int, int]]) -> dict[tuple[int, int], float]:
    """Scores of (target, set) pairs from counts of the set and of the set with the target."""
    sums = count_log_sums(spark, enc, sorted({u for _, u in pairs} | {u | 1 << t for t, u in pairs}))
    return {(t, u): sums[u] - sums[u | 1 << t] + scorer.penalty(kernel_product(enc, u), enc.arity[t], enc.m) for t, u in pairs}


def search_relational(spark: SparkSession, enc: Encoded, scorer: Score, prune=("c1", "c2"), ties="strict", max_parents: int | None = None, targets: list[int] | None = None) -> SearchResult:
    """Breadth-first over unfolded rows (t, u, d): counts by aggregation, conditions as
    column expressions, optima by passing d to children and taking the least of all
    predecessors that arrive. A child whose other predecessors were pruned gets too
    large a d only for targets that Condition 2 ends there anyway, so a find is checked
    against the finished lists as in the depth-first mode."""
    if not scorer.monotone:
        raise ValueError("the relational search needs a score with a monotone penalty")
    if enc.n > bitset.WORD:
        raise ValueError(f"the relational search takes up to {bitset.WORD} columns: the packed one takes any number")
    begun, stage = time.time(), Stage(spark)
    chosen = range(enc.n) if targets is None else targets
    p = kernel.Problem(None, None, enc.arity, enc.m, [e + scorer.penalty(1, a, enc.m) for e, a in zip(enc.entropy, enc.arity, strict=True)], enc.floor, scorer, frozenset(prune), [], ties == "strict", max_parents)
    p.eps = [max(1e-6, 1e-12 * abs(s)) for s in p.empty]
    facts = F.broadcast(spark.createDataFrame([(t, enc.arity[t], p.empty[t], p.floor[t], p.eps[t]) for t in range(p.n)], "t int, r int, empty double, floor double, eps double"))
    frontier = spark.createDataFrame([(t, 0, float("inf")) for t in chosen], "t int, u long, d double")
    entries: list[tuple[int, int, float]] = []
    layers, depth = [], 0
    while True:
        size = frontier.count()
        if not size:
            break
        frontier = stage.cut(frontier)
        wanted = frontier.select("u").union(frontier.select(F.col("u").bitwiseOR(bitset.bit(0, F.col("t"), p.n)))).distinct()
        sums = None
        ids = [r["u"] for r in wanted.collect()]
        for i in range(0, len(ids), BATCH):
            part = _sums(spark, enc, ids[i : i + BATCH])
            sums = part if sums is None else sums.union(part)
        sums = stage.cut(sums)
        q = F.aggregate(F.sequence(F.lit(0), F.lit(p.n - 1)), F.lit(1.0), lambda acc, i: acc * F.when(F.col("u").bitwiseAND(bitset.bit(0, i, p.n)) != 0, F.element_at(F.array(*map(F.lit, map(float, enc.arity))), i + 1)).otherwise(1.0))
        joint = sums.select(F.col("u").alias("ju"), F.col("logs").alias("jl"))
        rows = frontier.join(sums, "u").withColumn("ju", F.col("u").bitwiseOR(bitset.bit(0, F.col("t"), p.n))).join(joint, "ju").join(facts, "t")
        rows = rows.withColumn("fine", scorer.penalty_column(q, F.col("r"), enc.m)).withColumn("s", F.col("logs") - F.col("jl") + F.col("fine"))
        better = F.col("s") < F.col("d") - F.col("eps") if p.strict else F.col("s") <= F.col("d") + F.col("eps")
        stop = F.lit(False)
        if "c1" in prune:
            stop = stop | (F.col("fine") >= F.col("empty") - F.col("eps"))
        if "c2" in prune:
            stop = stop | (F.least("s", "d") <= F.col("floor") + F.col("fine") + F.col("eps"))
        rows = stage.cut(rows.select("t", "u", "s", better.alias("hit"), F.least("s", "d").alias("d"), stop.alias("stop")))
        hits = rows.where("hit").select("t", "u", "s").collect()
        entries += [(h["t"], h["u"], h["s"]) for h in hits]
        layers.append({"layer": depth, "nodes": frontier.select("u").distinct().count(), "pairs": size, "scored": size, "c1": 0, "c2": rows.where("stop").count(), "hits": len(hits), "mode": "relational"})
        if max_parents is not None and depth >= max_parents:
            break
        # Every column that is not in u makes a child; it lives if its chosen predecessor does.
        grown = rows.where("not stop").select("t", "u", "d", F.explode(F.sequence(F.lit(0), F.lit(p.n - 1))).alias("new"))
        inside = F.col("u").bitwiseAND(bitset.bit(0, F.col("new"), p.n)) != 0
        grown = grown.where((F.col("new") != F.col("t")) & ~inside).withColumn("v", F.col("u").bitwiseOR(bitset.bit(0, F.col("new"), p.n)))
        led = F.max(F.col("u") < bitset.bit(0, F.col("new"), p.n))
        frontier = grown.groupBy("t", "v").agg(F.min("d").alias("d"), led.alias("led")).where("led").select("t", F.col("v").alias("u"), "d")
        depth += 1
    entries = sorted(e for e in entries if not any(t == e[0] and v != e[1] and not v & ~e[1] and s <= e[2] + p.eps[t] for t, v, s in entries)) if p.strict else sorted(entries)
    totals = {"nodes": sum(x["nodes"] for x in layers[1:]), "pairs": sum(x["pairs"] for x in layers), "seconds": time.time() - begun, "mode": "relational", "l_max": len(layers) - 1, "l_z": max((u.bit_count() for _, u, _ in entries), default=0), "z": len(entries), "flagged": 0, "rejected": 0, "left_at_switch": 0}
    return SearchResult(spark, enc.order, enc.arity, entries, layers, totals, max_parents is None, p)
