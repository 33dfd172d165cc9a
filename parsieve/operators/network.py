"""Optimal networks over the lists, and what follows from their edges."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parsieve.functions import bitset
from parsieve.operators.search import SearchResult
from parsieve.plans.staging import Stage


def optimal_network(spark: SparkSession, result: SearchResult) -> tuple[float, DataFrame, int]:
    """Score, edges(parent, child) and number of optimum queries of the best network.

    Subsets of columns layer by layer: the best network on V ends in some sink t, with
    the best parents of t within V and the best network on the rest.
    """
    n = len(result.order)
    stage = Stage(spark)
    lists = F.broadcast(spark.createDataFrame([(t, u, s) for t, u, s in result.entries], "t int, pu long, s double"))  # the lists, z rows
    layer = spark.createDataFrame([(0, 0.0, -1, 0)], "v long, score double, sink int, parents long")
    kept = [layer]
    queries = 0
    for _ in range(n):
        grown = layer.select("v", "score", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("t"))
        grown = grown.where(F.col("v").bitwiseAND(bitset.bit(0, F.col("t"), n)) == 0)
        cost = grown.join(lists, "t").where(bitset.contains(F.col("v"), F.col("pu")))
        best = cost.groupBy("v", "t", "score").agg(F.min(F.struct("s", "pu")).alias("b"))
        ends = best.select(F.col("v").bitwiseOR(bitset.bit(0, F.col("t"), n)).alias("v"), (F.col("score") + F.col("b.s")).alias("score"), "t", F.col("b.pu").alias("parents"))
        layer = stage.cut(ends.groupBy("v").agg(F.min(F.struct("score", "t", "parents")).alias("b")).select("v", "b.score", F.col("b.t").alias("sink"), "b.parents"))
        kept.append(layer)
    queries = n * 2 ** (n - 1)
    v, edges, total = (1 << n) - 1, [], 0.0
    for k in range(n, 0, -1):
        row = kept[k].where(F.col("v") == v).first()
        total = row["score"] if k == n else total
        edges += [(result.order[i], result.order[row["sink"]]) for i in bitset.members(row["parents"])]
        v &= ~(1 << row["sink"])
    return total, spark.createDataFrame(edges, "parent string, child string"), queries


def markov_blanket(edges: DataFrame, target: str) -> DataFrame:
    """Parents, children and the children's other parents."""
    parents = edges.where(F.col("child") == target).select(F.col("parent").alias("name"))
    children = edges.where(F.col("parent") == target).select(F.col("child").alias("name"))
    mates = edges.join(children, edges["child"] == children["name"], "left_semi").select(F.col("parent").alias("name"))
    return parents.union(children).union(mates).where(F.col("name") != target).distinct()
