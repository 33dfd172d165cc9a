"""Fuzzy line dedup.

A line (trimmed, not empty) is its set of character shingles of length Q, taken over
UTF-16 units so that any of them is a constant-time slice; a shorter line is one shingle.
Signatures come from one hash of each shingle. Slot i of SLOTS holds the hash that is
nearest to i in its upper bits (least exclusive or), which is a min-wise value: two lines
agree in a slot with about their similarity. Of a long line only hashes close to one of the
slots can be nearest, about NEAR for each, and only those reach the aggregation. BUCKETS
sets of four slots are the buckets: a pair at the threshold of 0.8 shares none with
probability 0.009, at 0.85 with 0.002, at 0.9 with 0.0002. Pairs that agree in fewer than AGREE
slots go (0.0007 of those at 0.8); links are confirmed on full shingle sets,
components found by star contraction, and one line of each component stays: the first
position in the document with the smallest doc_id that has a line of it.

Lines are told apart by a 64-bit hash of the trimmed text; a second one shows where two
different lines share the first. Such lines (one in ten million at 10^12 lines) are left as
they are, so no line goes for another's sake.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from parsieve.llm.common import Cuts, Sieve, partitions, slices
from parsieve.llm.linking import Items, link, may_link, parity, spread

Q = 7
SLOTS, BUCKETS = 16, 16
STEPS = (0, 7, 11, 13)  # bucket j has the slots j + step; of all such choices the one that misses least
NEAR = 3
AGREE = 8
PERCENT = 80
WORDS = 16  # longs of a line's bitmap
_FREE = 60  # bits of a hash below the slot number


def lines_of(docs: DataFrame) -> DataFrame:
    """doc_id, pos (0-based line number), line (trimmed), key; lines without text left out."""
    cut = docs.select("doc_id", F.posexplode(F.split("text", "\n", -1)).alias("pos", "line"))
    return cut.select("doc_id", "pos", F.trim("line").alias("line")).where("line <> ''").withColumn("key", F.xxhash64("line"))


def _units(line: Column) -> Column:
    return F.encode(line, "UTF-16BE")


def _places(units: Column) -> Column:
    """1-based byte positions of the shingles; 1 alone for a line of at most Q units."""
    return F.sequence(F.lit(1), F.greatest(F.octet_length(units) - 2 * Q + 1, F.lit(1)), F.lit(2))


def _shingle(units: Column, at: Column) -> Column:
    return F.xxhash64(F.substring(units, at, F.lit(2 * Q)))


_MULTIPLY = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)]


def shingle_hashes(lines: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes by position, the first position of each line, and its number of shingles.
    Positions between two lines belong to none.

    Line feeds, which no line holds, stand between lines, so a line of fewer than Q units is
    one shingle that no other line has."""
    gap = "\n" * Q
    u = np.frombuffer((gap.join(lines) + gap).encode("utf-16-le", "surrogatepass"), np.uint16)
    feed = u == 10
    ends = np.flatnonzero(feed[1:] & ~feed[:-1]) + 1
    starts = np.concatenate([[0], ends[:-1] + Q])
    pair = u[:-1].astype(np.uint32) | u[1:].astype(np.uint32) << np.uint32(16)
    four = pair[:-2].astype(np.uint64) | pair[2:].astype(np.uint64) << np.uint64(32)
    h = four[: 4 - Q] * _MULTIPLY[0]
    h ^= h >> np.uint64(32)
    h += four[Q - 4 :]
    for multiply, shift in ((_MULTIPLY[1], 29), (_MULTIPLY[2], 32)):
        h *= multiply
        h ^= h >> np.uint64(shift)
    return h, starts, np.maximum(ends - starts - Q + 1, 1)


def _signed(h: Column, slot: int) -> Column:
    """The hash nearest to a slot, as a distance."""
    place = slot << _FREE
    return F.min(h.bitwiseXOR(F.lit(place - (1 << 64) if place >> 63 else place)))


def signed_lines(lines: DataFrame) -> DataFrame:
    """key, first_doc, n (occurrences), mark struct of SLOTS // 8 longs, buckets array: a row
    for each different line. Shingles are hashed in the task that splits the text, and
    those too far from all slots end there, so neither text nor shingles are shuffled."""
    # How often the line's first shingle comes again tells a ruled or periodic line, of which
    # few shingles differ, from a line of prose.
    start = F.substring("line", 1, Q)
    again = (F.octet_length("line") - F.octet_length(F.replace("line", start, F.lit("")))) / F.octet_length(start)
    each = lines.select("key", F.xxhash64(F.lit(1), "line").alias("other"), F.col("doc_id").cast("long").alias("doc_id"), _units(F.col("line")).alias("units"), again.alias("again"))
    units = F.col("units")
    places = F.greatest(F.octet_length(units) / 2 - Q + 1, F.lit(1))
    # A hash is close enough if its free bits are below this: NEAR a slot on average, all of a short line.
    reach = F.least(F.col("again") * (NEAR * SLOTS) / places, F.lit(1.0)) * float(1 << _FREE)
    at = each.select("key", "other", "doc_id", "units", reach.alias("reach"), F.explode(_places(units)).alias("at"))
    hashed = at.select("key", "other", "doc_id", "reach", "at", _shingle(units, F.col("at")).alias("h"))
    close = hashed.where((F.col("at") == 1) | (F.col("h").bitwiseAND(F.lit((1 << _FREE) - 1)) < F.col("reach")))  # one at least
    # A line has the same signature everywhere; two that share a key end here.
    slots = [_signed(F.col("h"), i).alias(f"slot{i}") for i in range(SLOTS)]
    same = close.groupBy("key").agg(F.min("other").alias("low"), F.max("other").alias("high"), F.min("doc_id").alias("first_doc"), F.sum((F.col("at") == 1).cast("long")).alias("n"), *slots).where("low = high")
    byte = lambda i: F.shiftleft(F.col(f"slot{i}").bitwiseAND(F.lit(255)), i % 8 * 8)
    mark = F.struct(*(reduce(Column.bitwiseOR, map(byte, range(8 * w, 8 * w + 8))).alias(f"sketch{w}") for w in range(SLOTS // 8)))
    buckets = F.array(*(F.xxhash64(F.lit(j), *(f"slot{(j + step) % SLOTS}" for step in STEPS)) for j in range(BUCKETS)))
    return same.select("key", "first_doc", "n", mark.alias("mark"), buckets.alias("buckets"))


def _differing(a: Column, b: Column) -> Column:
    """The number of different bytes of two longs."""
    x = a.bitwiseXOR(b)
    for k in (4, 2, 1):
        x = x.bitwiseOR(F.shiftrightunsigned(x, k))
    return F.bit_count(x.bitwiseAND(F.lit(0x0101010101010101)))


def _shingles(line: Column) -> Column:
    """Hashes of the shingles by position; the line is encoded once."""
    return F.transform(F.array(_units(line)), lambda units: F.transform(_places(units), lambda at: _shingle(units, at)))[0]


def _sets(lines: list[str]) -> list[np.ndarray]:
    h, starts, places = shingle_hashes(lines)
    return [np.unique(h[s : s + n]) for s, n in zip(starts.tolist(), places.tolist())]


def _verified(batches: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    """The rows (a, b) of (a, b, line_a, line_b) that are linked on all their shingles: the
    rule of `_Lines.linked` in numpy, which no query runs."""
    for batch in slices(slices(batches, "line_a"), "line_b"):
        a, b = (batch.column(x).to_numpy() for x in ("a", "b"))
        texts: dict[int, str] = {}
        for x, ids in (("line_a", a), ("line_b", b)):
            at = np.unique(ids, return_index=True)[1]
            texts.update(zip(ids[at].tolist(), batch.column(x).take(pa.array(at)).to_pylist()))
        sets = dict(zip(texts, _sets(list(texts.values()))))
        keep = np.zeros(len(a), bool)
        for i, (x, y) in enumerate(zip(a.tolist(), b.tolist())):
            merged = np.concatenate([sets[x], sets[y]])
            merged.sort()
            both = int(np.count_nonzero(merged[1:] == merged[:-1]))
            keep[i] = 100 * both >= percent * (len(merged) - both)
        if keep.any():
            yield pa.RecordBatch.from_arrays([pa.array(a[keep]), pa.array(b[keep])], names=["a", "b"])


class _Lines(Items):
    words = WORDS
    one_task = 0  # no Python on the executors

    def __init__(self, spark: SparkSession, lines: DataFrame):
        self.spark, self.lines = spark, lines

    def near(self, a: Column, b: Column, percent: int) -> Column:
        return sum(_differing(a[f"sketch{w}"], b[f"sketch{w}"]) for w in range(SLOTS // 8)) <= SLOTS - AGREE

    def content_of(self, cuts: Cuts, ids: DataFrame) -> tuple[DataFrame, DataFrame]:
        wanted = Sieve(ids, "id").passed(self.lines, "key").groupBy("key").agg(F.min("line").alias("content"))
        content = cuts.cut(wanted.join(ids.hint("merge"), wanted["key"] == ids["id"]).select("id", "content"), "content")
        each = content.select("id", F.explode(F.array_distinct(_shingles(F.col("content")))).alias("e"))
        return content, cuts.cut(each.groupBy("id").agg(F.count(F.lit(1)).alias("n"), parity(WORDS).alias("parity")), "sizes")

    def linked(self, cuts: Cuts, pairs: DataFrame, content: DataFrame, sizes: DataFrame, percent: int) -> DataFrame:
        """Sizes and bitmaps end most far pairs, and none that is linked, before lines move."""
        size = lambda x: sizes.select(F.col("id").alias(x), F.col("n").alias(f"n{x}"), *spread("parity", WORDS, f"p{x}")).hint("merge")
        both = pairs.join(size("b"), "b").join(size("a"), "a")
        close = cuts.cut(both.where(may_link(WORDS, percent)).select("a", "b", "na", "nb"), "close")
        text = lambda x: content.select(F.col("id").alias(x), F.col("content").alias(f"line_{x}")).hint("merge")
        met = close.join(text("b"), "b").join(text("a"), "a")
        shared = F.size(F.array_intersect(_shingles(F.col("line_a")), _shingles(F.col("line_b"))))
        return met.where((100 + percent) * shared >= percent * (F.col("na") + F.col("nb"))).select("a", "b")

    def elements(self, rows: DataFrame) -> DataFrame:
        units = rows.select("id", "component", _units(F.col("content")).alias("units")).repartition(4 * partitions(self.spark), "id")
        each = units.select("id", "component", "units", F.explode(_places(F.col("units"))).alias("at"))
        return each.select("id", "component", _shingle(F.col("units"), F.col("at")).alias("e")).dropDuplicates(["id", "component", "e"])


def repeated_lines(spark: SparkSession, docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """doc_id, pos, component: the line occurrences that are to go.

    Rows that share a doc_id count as one document. Lines of rows without doc_id, and
    documents with null or empty text, have none.
    """
    cuts = Cuts(spark)
    lines = lines_of(docs.select("doc_id", "text").where("doc_id is not null"))
    signed = cuts.cut(signed_lines(lines), "signed")
    found = link(cuts, signed.select(F.col("key").alias("id"), "mark", F.explode("buckets").alias("bucket")), _Lines(spark, lines), percent)
    counted = signed.select("key", "n", "first_doc").join(found.withColumnRenamed("id", "key").hint("merge"), "key", "left")
    several = cuts.cut(counted.where("n > 1 or component is not null").select("key", "first_doc", F.coalesce("component", "key").alias("component")), "several")
    cuts.drop(signed)
    homes = several.groupBy("component").agg(F.min("first_doc").alias("home"))
    homes = cuts.cut(several.select("key", "component").join(homes.hint("merge"), "component"), "homes")
    cuts.drop(several)
    found_again = Sieve(homes, "key").passed(lines.select("doc_id", "pos", "key"), "key")
    at = cuts.cut(found_again.join(homes.hint("merge"), "key").drop("key"), "at")
    cuts.drop(homes)
    kept = at.where("doc_id = home").groupBy("component").agg(F.min("pos").alias("kept_pos"))
    kept = cuts.cut(kept, "kept")
    return at.join(kept.hint("merge"), "component").where("doc_id <> home or pos <> kept_pos").select("doc_id", "pos", "component")


def _rebuilt(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """docs with `line_dedup_gone`, the set of their line positions to leave out (null: none).
    Only rows that may have one are shuffled."""
    cuts = Cuts(spark)
    by_doc = repeated_lines(spark, docs).groupBy(F.col("doc_id").alias("line_dedup_doc")).agg(F.collect_set("pos").alias("line_dedup_gone"))
    by_doc = cuts.cut(by_doc, "by-doc")
    marked = Sieve(by_doc, "line_dedup_doc").marked(docs, "doc_id", "line_dedup_hit")
    hit = marked.where("line_dedup_hit").drop("line_dedup_hit")
    hit = hit.join(by_doc.hint("merge"), hit["doc_id"] == by_doc["line_dedup_doc"], "left").drop("line_dedup_doc")
    rest = marked.where("not line_dedup_hit").drop("line_dedup_hit").withColumn("line_dedup_gone", F.lit(None).cast("array<int>"))
    return hit.unionByName(rest)


def _kept_text(text: Column, gone: Column) -> Column:
    """Kept lines as they stood, in order; the text is split once."""
    stay = F.filter(F.split(text, "\n", -1), lambda line, i: ~F.array_contains(gone, i))
    return F.when(gone.isNull(), text).otherwise(F.array_join(stay, "\n"))


def deduped(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """doc_id, n_lines, n_dropped, text without the dropped lines; a row per input row."""
    joined = _rebuilt(spark, docs.select("doc_id", "text"))
    gone = F.col("line_dedup_gone")
    n = F.when(F.length("text") > 0, F.size(F.split("text", "\n", -1))).otherwise(0)
    return joined.select("doc_id", n.cast("long").alias("n_lines"), F.when(gone.isNull(), 0).otherwise(F.size(gone)).cast("long").alias("n_dropped"), _kept_text(F.col("text"), gone).alias("text"))


def line_dedup(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """Pipeline stage: texts without repeated lines. A document that keeps no line with text
    goes, one without text stays as it is; n_chars follows the text. Columns named
    line_dedup_* are this stage's own; all other names are the user's."""
    joined = _rebuilt(spark, docs)
    joined = joined.withColumn("text", _kept_text(F.col("text"), F.col("line_dedup_gone")))
    joined = joined.where(F.col("line_dedup_gone").isNull() | F.col("text").rlike(r"\S"))
    if "n_chars" in docs.columns:
        joined = joined.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return joined.select(docs.columns)
