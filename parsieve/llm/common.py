"""Shared plumbing: table access, lineage cuts in the shared folder, bounded batches."""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Text bytes handled at once by a Python kernel; a longer document is a batch of its own.
SLICE_BYTES = 2_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors see. Only a local session may fall back on its own."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder.rstrip("/")
    set_before = spark.sparkContext._jsc.sc().getCheckpointDir()
    if set_before.isDefined():
        return set_before.get().rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    global _own
    if _own is None:
        _own = tempfile.mkdtemp(prefix="parsieve-")
        atexit.register(shutil.rmtree, _own, ignore_errors=True)
    return f"file://{_own}"


_own: str | None = None


class Cuts:
    """Written tables that end a lineage; superseded ones can be dropped early."""

    def __init__(self, spark: SparkSession):
        self.spark, self.root = spark, f"{shared_folder(spark)}/cut-{uuid.uuid4().hex}"
        self.n = 0

    def cut(self, df: DataFrame, name: str = "t") -> DataFrame:
        self.n += 1
        path = f"{self.root}/{self.n}-{name}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._cut_path = path
        gc.collect()  # shuffle files go when the driver's last reference to them does
        self.spark._jvm.System.gc()
        return out

    def drop(self, *frames: DataFrame | None) -> None:
        for df in frames:
            path = getattr(df, "_cut_path", None)
            if path:
                jvm = self.spark._jvm
                p = jvm.org.apache.hadoop.fs.Path(path)
                p.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(p, True)


class Sieve:
    """A set of keys as a bit table: a row for each word of 64 bits, at most MOST_WORDS
    rows however many keys there are, so it can be broadcast at any size of the data. It
    passes every key that it holds, and some others: 1 in 16 or fewer up to 2^22 keys, more beyond.
    """

    MOST_WORDS = 1 << 20

    def __init__(self, keys: DataFrame, column: str):
        n = keys.count()
        self.words = min(self.MOST_WORDS, 1 << max(0, (n * 16 // 64).bit_length()))
        word, bit = self._place(F.col(column))
        marks = keys.where(F.col(column).isNotNull()).select(word.alias("sieve_word"), F.call_function("shiftleft", F.lit(1).cast("long"), bit).alias("bit"))
        self.table = marks.groupBy("sieve_word").agg(F.bit_or("bit").alias("sieve_bits"))

    def _place(self, key: Column) -> tuple[Column, Column]:
        h = F.xxhash64(key, F.lit(7))
        return F.shiftrightunsigned(h, 6).bitwiseAND(F.lit(self.words - 1)), h.bitwiseAND(F.lit(63)).cast("int")

    def marked(self, rows: DataFrame, column: str, flag: str) -> DataFrame:
        """rows with a boolean `flag`: false only where the key is surely not in the set."""
        word, bit = self._place(F.col(column))
        joined = rows.join(F.broadcast(self.table), word == F.col("sieve_word"), "left")
        inside = F.call_function("shiftrightunsigned", F.col("sieve_bits"), bit).bitwiseAND(F.lit(1).cast("long")) == 1
        return joined.withColumn(flag, F.coalesce(inside, F.lit(False)) & F.col(column).isNotNull()).drop("sieve_word", "sieve_bits")

    def passed(self, rows: DataFrame, column: str) -> DataFrame:
        """The rows whose key may be in the set."""
        word, bit = self._place(F.col(column))
        joined = rows.join(F.broadcast(self.table), word == F.col("sieve_word"))
        return joined.where(F.call_function("shiftrightunsigned", F.col("sieve_bits"), bit).bitwiseAND(F.lit(1).cast("long")) == 1).drop("sieve_word", "sieve_bits")


def partitions(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def slices(batches: Iterator[pa.RecordBatch], column: str = "text", limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cuts Arrow batches so that each holds about `limit` text bytes, or one row."""
    for batch in batches:
        sizes = pa.compute.fill_null(pa.compute.binary_length(batch.column(column)), 0).to_pylist()
        start = total = 0
        for i, n in enumerate(sizes):
            if i > start and total + n > limit:
                yield batch.slice(start, i - start)
                start, total = i, 0
            total += n
        if start < len(sizes):
            yield batch.slice(start)
