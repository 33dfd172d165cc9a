"""Near-duplicate documents by min-max hashing.

A document is its set of 5-word shingles. Each of PERMUTATIONS hash orders gives two
signature values, the least and the greatest shingle, so a signature needs half as many
evaluations as its length and its estimate varies less than with minima alone. BANDS
groups of ROWS values are the buckets: at the threshold of 0.85 a pair shares no bucket
with probability (1 - 0.85^5)^24 < 1e-6. Buckets only propose; links are confirmed
on full sets (see `linking`).

Words are hashed to 64 bits and shingles mixed from their words' hashes; two of the
at most n shingles of a pair of documents collide with probability n^2 / 2^65.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from parsieve.llm.common import Cuts, Sieve, slices
from parsieve.llm.linking import Items, bitmaps, link

SHINGLE = 5
BANDS, ROWS = 24, 5
PERMUTATIONS = BANDS * ROWS // 2
PERCENT = 85
WORDS = 16  # longs of a document's bitmap
STAGE_PERCENT = 80  # of the pipeline stage, which takes more than op1's contract asks for

_rng = np.random.Generator(np.random.PCG64(20240601))
_MULTIPLY = _rng.integers(1, 2**63, PERMUTATIONS, np.uint64) * np.uint64(2) + np.uint64(1)
_ADD = _rng.integers(0, 2**63, PERMUTATIONS, np.uint64)
_STEP = _rng.integers(1, 2**63, SHINGLE, np.uint64) * np.uint64(2) + np.uint64(1)
_BAND = _rng.integers(1, 2**63, (BANDS, ROWS + 1), np.uint64) * np.uint64(2) + np.uint64(1)


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


class Shingler:
    """Distinct shingle hashes of texts; the word dictionary is emptied when it is full."""

    def __init__(self, entries: int = 500_000):
        self.entries, self.known = entries, {}

    def sets(self, texts: list[str | None]) -> list[np.ndarray]:
        if len(self.known) > self.entries:
            self.known.clear()
        known = self.known
        words = [(t or "").encode("utf-8", "surrogatepass").lower().split() for t in texts]
        for w in set().union(*words) - known.keys():
            known[w] = xxhash.xxh3_64_intdigest(w)
        out = []
        with np.errstate(over="ignore"):
            for ws in words:
                h = np.fromiter(map(known.__getitem__, ws), np.uint64, len(ws))
                k = min(SHINGLE, len(h))
                if not k:
                    out.append(h)
                    continue
                mixed = np.full(len(h) - k + 1, k, np.uint64)
                for j in range(k):
                    mixed = mixed * _STEP[j] + h[j : len(h) - k + 1 + j]
                out.append(np.unique(_mix(mixed)))
        return out


def signature(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Band keys (documents x BANDS) and 128-bit keys of the whole sets, non-empty sets only."""
    joined = np.concatenate(sets)
    begin = np.cumsum([0, *map(len, sets)])[:-1]
    values = np.empty((len(sets), BANDS * ROWS), np.uint64)
    with np.errstate(over="ignore"):
        for p in range(PERMUTATIONS):
            y = joined * _MULTIPLY[p] + _ADD[p]
            y ^= y >> np.uint64(32)
            values[:, 2 * p] = np.minimum.reduceat(y, begin)
            values[:, 2 * p + 1] = np.maximum.reduceat(y, begin)
        # A band takes its values far apart, so that it seldom holds both ends of one order.
        rows = values.reshape(len(sets), ROWS, BANDS).swapaxes(1, 2)
        keys = np.broadcast_to(_BAND[:, ROWS], (len(sets), BANDS)).copy()
        for r in range(ROWS):
            keys = _mix(keys * _BAND[:, r] + rows[:, :, r])
        whole = np.stack([np.add.reduceat(_mix(joined), begin), np.bitwise_xor.reduceat(_mix(joined + np.uint64(1)), begin)], axis=1)
    return keys, whole


def signatures(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, set_key struct<hi, lo> (null for an empty set), buckets array."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler()
        for b in slices(batches):
            sets = shingler.sets(b.column("text").to_pylist())
            sizes = np.array([len(s) for s in sets], np.int64)
            full = sizes > 0
            keys = np.zeros((len(sets), BANDS), np.uint64)
            whole = np.zeros((len(sets), 2), np.uint64)
            if full.any():
                keys[full], whole[full] = signature([s for s in sets if len(s)])
            offsets = np.concatenate([[0], np.cumsum(np.where(full, BANDS, 0))]).astype(np.int32)
            buckets = pa.ListArray.from_arrays(offsets, keys[full].view(np.int64).ravel())
            hi, lo = (pa.array(whole[:, i].view(np.int64), mask=~full) for i in (0, 1))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(sizes), hi, lo, buckets], names=["doc_id", "n_shingles", "hi", "lo", "buckets"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_shingles long, hi long, lo long, buckets array<long>")


def shingle_sets(docs: DataFrame) -> DataFrame:
    """id, n, content (the elements), parity (WORDS longs) of each row's full shingle set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler()
        for b in slices(batches):
            sets = shingler.sets(b.column("text").to_pylist())
            offsets = np.cumsum([0, *map(len, sets)]).astype(np.int32)
            elems = pa.ListArray.from_arrays(offsets, np.concatenate([np.zeros(0, np.uint64), *sets]).view(np.int64))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(np.diff(offsets).astype(np.int64)), elems, bitmaps(sets, WORDS)], names=["id", "n", "content", "parity"])

    return docs.select("doc_id", "text").mapInArrow(run, "id long, n long, content array<long>, parity array<long>")


class _Documents(Items):
    """Documents by their shingle sets, which move only for pairs whose sizes allow a
    link: a union has the larger set's size at least."""

    words = WORDS

    def __init__(self, docs: DataFrame):
        self.text = docs.select("doc_id", "text")

    def near(self, a: Column, b: Column, percent: int) -> Column:
        return 100 * F.least(a, b) >= percent * F.greatest(a, b)

    def content_of(self, cuts: Cuts, ids: DataFrame) -> tuple[DataFrame, DataFrame]:
        near = Sieve(ids, "id").passed(self.text, "doc_id")
        sets = shingle_sets(near.join(ids.hint("merge"), near["doc_id"] == ids["id"], "left_semi")).dropDuplicates(["id"])
        content = cuts.cut(sets, "content")
        return content, content.select("id", "n", "parity")

    def linked(self, cuts: Cuts, pairs: DataFrame, content: DataFrame, sizes: DataFrame, percent: int) -> DataFrame:
        sets = lambda x: content.select(F.col("id").alias(x), F.col("n").alias(f"n{x}"), F.col("content").alias(f"e{x}")).hint("merge")
        met = pairs.join(sets("a"), "a").join(sets("b"), "b")
        met = met.select("a", "b", "na", "nb", F.size(F.array_intersect("ea", "eb")).cast("long").alias("both"))
        return met.where(100 * F.col("both") >= percent * (F.col("na") + F.col("nb") - F.col("both"))).select("a", "b")

    def elements(self, rows: DataFrame) -> DataFrame:
        return rows.select("id", "component", F.explode("content").alias("e"))


def near_duplicates(spark: SparkSession, docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id, kept; a row per input row.

    component_id is the smallest doc_id that can be reached over links (itself if there
    is none), kept marks that document. Null texts and texts without a word have the empty
    set and no links. doc_id identifies a document: rows that repeat one are together.
    Documents with equal sets are one item from the start, however many they are.
    """
    cuts = Cuts(spark)
    signed = cuts.cut(signatures(docs), "signed")
    same = signed.where("hi is not null and doc_id is not null")
    classes = cuts.cut(same.groupBy("hi", "lo", "n_shingles").agg(F.min("doc_id").alias("id")), "classes")
    # The buckets of a class are those of any member: of its first document.
    first = Sieve(classes, "id").passed(signed, "doc_id")
    items = first.join(classes.select("id", "hi", "lo").hint("merge"), [F.col("doc_id") == classes["id"], first["hi"] == classes["hi"], first["lo"] == classes["lo"]])
    items = cuts.cut(items.select("id", F.col("n_shingles").alias("mark"), "buckets").dropDuplicates(["id"]), "items")
    found = link(cuts, items.select("id", "mark", F.explode("buckets").alias("bucket")), _Documents(docs), percent)
    linked = classes.join(found.hint("merge"), "id", "left").select("hi", "lo", "n_shingles", F.coalesce("component", "id").alias("component_id"))
    linked = cuts.cut(linked, "linked")
    cuts.drop(items, classes)
    out = signed.select("doc_id", "n_shingles", "hi", "lo").join(linked.hint("merge"), ["hi", "lo", "n_shingles"], "left")
    component = F.coalesce("component_id", "doc_id")
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def keep_one(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """Pipeline stage: of each group of near duplicates, the row with the smallest doc_id.
    A pair at 0.8 shares no bucket with probability (1 - 0.8^5)^24 < 1e-4."""
    gone = near_duplicates(spark, docs, STAGE_PERCENT).where("not kept").select(F.col("doc_id").alias("near_dedup_gone")).distinct()
    gone = Cuts(spark).cut(gone, "gone")
    marked = Sieve(gone, "near_dedup_gone").marked(docs, "doc_id", "near_dedup_hit")
    hit = marked.where("near_dedup_hit")
    left = hit.join(gone.hint("merge"), hit["doc_id"] == gone["near_dedup_gone"], "left_anti")
    return left.unionByName(marked.where("not near_dedup_hit")).select(docs.columns)
