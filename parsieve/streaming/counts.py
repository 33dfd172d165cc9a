"""Streams: counts are additive, so only they are stateful; the search is a batch job."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parsieve.plans.staging import shared_folder


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def run_now(df: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over what is there now; the result as a written table."""
    spark = df.sparkSession
    root = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"

    def put(batch: DataFrame, number: int) -> None:
        if mode in ("append", "update"):
            batch.write.mode("overwrite").parquet(f"{root}/out/batch={number}")
        else:
            batch.write.mode("overwrite").parquet(f"{root}/out")

    schema = df.schema
    query = df.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    out = spark.read.parquet(f"{root}/out") if mode == "update" else spark.read.schema(schema).parquet(f"{root}/out")
    if mode == "update":  # the latest row of each value of the first column
        latest = out.groupBy(schema.names[0]).agg(F.max_by(F.struct(*schema.names), "batch").alias("r"))
        return latest.select("r.*")
    return out.select(*schema.names)


def contingency(stream: DataFrame, columns: list[str]) -> DataFrame:
    """Counts of every combination of states, kept current."""
    return stream.groupBy(*columns).agg(F.count(F.lit(1)).alias("w"))


def tumbling(stream: DataFrame, span: str = "1 day", late: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", span).alias("win"), "event_type").agg(F.count(F.lit(1)).alias("c")).select(F.col("win.start").alias("begins"), "event_type", "c")


def sliding(stream: DataFrame, span: str = "2 days", step: str = "1 day", late: str = "1 day") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", span, step).alias("win"), "event_type").agg(F.count(F.lit(1)).alias("c")).select(F.col("win.start").alias("begins"), "event_type", "c")


def sessions(stream: DataFrame, gap: str = "6 hours", late: str = "1 day") -> DataFrame:
    timed = stream.withWatermark("ts", late)
    return timed.groupBy(F.session_window("ts", gap).alias("win"), "user_id").agg(F.count(F.lit(1)).alias("c")).select("user_id", F.col("win.start").alias("begins"), "c")


def once(stream: DataFrame, late: str = "3650 days") -> DataFrame:
    """Each event_id once within the watermark."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def running_entropy(stream: DataFrame, group: str, state: str) -> DataFrame:
    """group, total, entropy (bits) of the states seen so far: a custom stateful operator
    that keeps one number for each state of a group and a row for each update."""
    import numpy as np
    import pandas as pd

    def update(key, batches, held):
        seen = dict(zip(*held.get, strict=True)) if held.exists else {}
        for b in batches:
            for s, n in b[state].value_counts().items():
                seen[str(s)] = seen.get(str(s), 0) + int(n)
        held.update((list(seen), list(seen.values())))
        c = np.array(list(seen.values()), float)
        yield pd.DataFrame({group: [key[0]], "total": [int(c.sum())], "entropy": [float(np.log2(c.sum()) - (c * np.log2(c)).sum() / c.sum())]})

    slim = stream.select(group, F.col(state).cast("string").alias(state))
    return slim.groupBy(group).applyInPandasWithState(update, f"{group} string, total long, entropy double", "states array<string>, counts array<long>", "update", "NoTimeout")


def with_static(stream: DataFrame, static: DataFrame, key: str, columns: list[str]) -> DataFrame:
    """Counts by columns of a static table that each event is joined to."""
    return contingency(stream.join(static, key), columns)
