"""Questions to the lists: the best parents within a pool, the best sets, list exports."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def best_score(mps: DataFrame, queries: DataFrame) -> DataFrame:
    """For queries(query_id, target, pool array): the least score over the stored sets
    inside the pool and that set. Equal on target, contained in the pool."""
    inside = F.size(F.array_except("parents", "pool")) == 0
    joined = queries.join(mps, "target").where(inside)
    best = F.min(F.struct("score", "size", F.array_join("parents", "+").alias("names"))).alias("b")
    return joined.groupBy("query_id", "target").agg(best).select("query_id", "target", F.col("b.score").alias("score"), F.col("b.names").alias("parents"))


def optimal(mps: DataFrame, target: str, pool: list[str] | None = None) -> DataFrame:
    """The optimal parent set of one target within a pool (default: all columns)."""
    rows = mps.where(F.col("target") == target)
    if pool is not None:
        rows = rows.where(F.size(F.array_except("parents", F.array(*map(F.lit, pool)).cast("array<string>"))) == 0)
    return rows.orderBy("score", "size").limit(1)


def top_sets(mps: DataFrame, k: int) -> DataFrame:
    """The k best sets of each target."""
    w = Window.partitionBy("target").orderBy("score", "size", F.array_join("parents", "+"))
    return mps.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)


def front(mps: DataFrame) -> DataFrame:
    """Per target and size: best score, and the best of all sizes up to it."""
    sizes = mps.groupBy("target", "size").agg(F.min("score").alias("score"))
    w = Window.partitionBy("target").orderBy("size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return sizes.withColumn("best_so_far", F.min("score").over(w)).withColumn("gain", F.lag("score").over(Window.partitionBy("target").orderBy("size")) - F.col("score"))


def flat(mps: DataFrame) -> DataFrame:
    """Rows as the SQL checks have them: names joined, scores rounded."""
    return mps.select("target", F.array_join("parents", "+").alias("parents"), "size", F.round("score", 3).alias("score"))


def summary(mps: DataFrame) -> DataFrame:
    """z, and the shortest and longest list."""
    lists = mps.groupBy("target").agg(F.count(F.lit(1)).alias("n"))
    return lists.agg(F.sum("n").alias("z"), F.min("n").alias("list_min"), F.max("n").alias("list_max"))
