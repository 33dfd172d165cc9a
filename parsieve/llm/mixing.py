"""Mixing sources to target weights.

A source's weight is its token share to a power between 0 and 1, normalised. The power is
found by bisection, for a target entropy of the weights or for a limit on how often a
source is repeated. Weights and a token budget are realised by passes: each source is
hashed into blocks of about BLOCK rows; a pass is a keyed permutation of its blocks and
of the rows in each; a source gets as many whole passes as its budget holds and of the
next one the part that fits. Sums over rows are sums over blocks first, so only the
block table is ever ordered, and of the rows only the one block that a budget cuts.
"""

from __future__ import annotations

import math
from typing import NamedTuple

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

BLOCK = 4096
NEAR = 1e-9
MOST_SOURCES = 100_000


class Plan(NamedTuple):
    power: float
    budget: float
    weights: dict[str | None, float]
    passes: dict[str | None, float]


def tokens_of(text: Column) -> Column:
    """A token measure: a token for each 4 bytes begun, at least one."""
    return F.greatest(F.ceil(F.octet_length(F.coalesce(text, F.lit(""))) / 4), F.lit(1)).cast("long")


def tempered(sizes: dict, power: float) -> dict:
    total = sum(sizes.values())
    raw = {s: (n / total) ** power for s, n in sizes.items()}
    norm = sum(raw.values())
    return {s: w / norm for s, w in raw.items()}


def entropy(weights: dict) -> float:
    return -sum(w * math.log2(w) for w in weights.values() if w > 0)


def bisect(holds, steps: int = 60) -> float:
    """The smallest power in [0, 1] for which `holds`, if it holds from there on up to 1."""
    if holds(0.0):
        return 0.0
    low, high = 0.0, 1.0
    for _ in range(steps):
        mid = (low + high) / 2
        low, high = (low, mid) if holds(mid) else (mid, high)
    return high


def snapped(passes: float) -> float:
    """A number of passes within NEAR of a whole one is that: rounding must cost no row."""
    return float(round(passes)) if abs(passes - round(passes)) <= NEAR else passes


def plan(sizes: dict, repetitions: float | None = 2.0, target_entropy: float | None = None, budget: float | None = None) -> Plan:
    """Weights for token counts by source. Without a budget the source that is cut most
    gets exactly one pass, so that no row is lost; with one, each gets its share of it.

    With a target entropy (bits) the power is the largest that reaches it (0 if none
    does); else the smallest by which no source is passed more than `repetitions` times.
    """
    sizes = {s: n for s, n in sizes.items() if n > 0}
    if not sizes:
        return Plan(1.0, 0.0, {}, {})

    def spent(power: float) -> tuple[float, dict, dict]:
        w = tempered(sizes, power)
        total = budget if budget is not None else max(n / w[s] for s, n in sizes.items())
        return total, w, {s: snapped(total * w[s] / n) for s, n in sizes.items()}

    if target_entropy is not None:
        power = 1 - bisect(lambda x: entropy(tempered(sizes, 1 - x)) >= target_entropy)
    else:
        power = bisect(lambda a: max(spent(a)[2].values()) <= repetitions * (1 + 1e-12))
    total, w, passes = spent(power)
    return Plan(power, total, w, passes)


def source_tokens(docs: DataFrame, tokens: Column) -> dict:
    """Token sums by source; null is a source of its own. The number of sources is checked."""
    rows = docs.select("source", tokens.alias("tokens")).groupBy("source").agg(F.sum("tokens").alias("tokens")).limit(MOST_SOURCES + 1).collect()
    if len(rows) > MOST_SOURCES:
        raise ValueError("more sources than a weight table may have")
    return {r["source"]: r["tokens"] for r in rows}


def mixed(docs: DataFrame, chosen: Plan, seed: int = 17, tokens: Column | None = None, content: Column | None = None) -> DataFrame:
    """docs with mix_pass (0..), mix_block and mix_slot: a row for each time that a row is
    used; in the order of (mix_pass, mix_block, mix_slot) a source's passes are
    permutations of it. Repeated rows count each; ties in a hash go by doc_id.

    The part of a last pass takes whole blocks in their order, then of the next block the
    rows whose running sum stays within the budget. Rows are dealt by doc_id and `content`
    (default: the text), so rows without an id do not gather in one block. Columns of docs may have any
    names: they travel as one value.
    """
    tokens = tokens if tokens is not None else tokens_of(F.col("text"))
    content = content if content is not None else F.col("text")
    schema = "source string, passes double"
    # A row per source, whose number is checked: a broadcast of bounded size.
    table = docs.sparkSession.createDataFrame([(s, float(p)) for s, p in chosen.passes.items()], schema)
    table = F.broadcast(table.withColumnRenamed("source", "of"))
    key = F.xxhash64(F.lit(seed), F.col("doc_id"), F.col("source"), content)
    sized = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("doc"), F.col("source").alias("from"), F.col("doc_id").alias("id"), tokens.alias("tokens"), key.alias("key"))
    sums = sized.groupBy("from").agg(F.count(F.lit(1)).alias("rows"), F.sum("tokens").alias("all_tokens"))
    facts = table.join(sums, table["of"].eqNullSafe(sums["from"])).select("of", "passes", "rows", "all_tokens")
    facts = F.broadcast(facts.select("of", F.floor("passes").alias("whole"), F.ceil(F.col("rows") / BLOCK).alias("blocks"), ((F.col("passes") - F.floor("passes")) * F.col("all_tokens")).alias("part")))
    rows = sized.join(facts, F.col("from").eqNullSafe(F.col("of"))).withColumn("block", F.pmod("key", "blocks"))
    order = F.xxhash64(F.lit(seed), F.col("whole"), F.col("block"))
    blocks = rows.groupBy("of", "whole", "part", "block").agg(F.sum("tokens").alias("block_tokens"))
    run = Window.partitionBy("of").orderBy(order, "block").rowsBetween(Window.unboundedPreceding, -1)
    blocks = blocks.withColumn("before", F.coalesce(F.sum("block_tokens").over(run), F.lit(0)))
    left = F.col("part") - F.col("before")
    taken = blocks.where(left > 0).select(F.col("of").alias("taken_from"), F.col("block").alias("taken_block"), left.alias("left"), (F.col("block_tokens") <= left).alias("all_of_it"))
    joined = rows.join(taken, F.col("of").eqNullSafe(F.col("taken_from")) & (F.col("block") == F.col("taken_block")), "left")
    # A running sum only in the block that is cut: one of each source.
    inside = Window.partitionBy("of", "block").orderBy("key", "id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    cut = joined.where("not all_of_it").withColumn("extra", (F.sum("tokens").over(inside) <= F.col("left")).cast("int"))
    rest = joined.where("all_of_it is null or all_of_it").withColumn("extra", F.coalesce("all_of_it", F.lit(False)).cast("int"))
    both = rest.unionByName(cut).withColumn("copies", (F.col("whole") + F.col("extra")).cast("int")).where("copies > 0")
    each = both.withColumn("pass", F.explode(F.sequence(F.lit(0), F.col("copies") - 1)))
    own = [F.col(f"doc.`{c}`").alias(c) for c in docs.columns]
    return each.select(*own, F.col("pass").alias("mix_pass"), F.xxhash64(F.lit(seed), F.col("pass").cast("long"), F.col("block")).alias("mix_block"), F.xxhash64("pass", "key").alias("mix_slot"))


def mixture(docs: DataFrame, repetitions: float = 2.0) -> DataFrame:
    """doc_id, source, n_tokens, mix_pass, mix_block, mix_slot for the whole table; an empty
    one gives no row, a null source is a source of its own."""
    slim = docs.select("doc_id", "source", tokens_of(F.col("text")).alias("n_tokens"), F.xxhash64("text").alias("content"))
    chosen = plan(source_tokens(slim, F.col("n_tokens")), repetitions)
    return mixed(slim, chosen, tokens=F.col("n_tokens"), content=F.col("content")).drop("content")


def mix_stage(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """Pipeline stage: every row at least once, rows of rare sources up to twice."""
    chosen = plan(source_tokens(docs, tokens_of(F.col("text"))))
    used = mixed(docs, chosen)
    return used.select(docs.columns)
