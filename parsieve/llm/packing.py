"""Best-fit packing into bins of several permitted lengths.

Documents longer than the largest length are cut into pieces of it. Pieces are dealt by a
hash into groups of about GROUP pieces, and each group is packed by itself in one task, so
memory is bounded and a lost group can be packed again with the same result. Within a
group, pieces go by falling length into the open bin that they leave least room in; where
none has room a bin is opened, of the length that costs least for each token that it can
still be filled with from the pieces that remain. All permitted lengths are weighed against
each other at every opening. Every bin is at last downsized to the least length that holds
its contents. Openings by one preferred length (larger ones only for pieces that need
them) are tried beside, and the result of least total cost stays.
"""

from __future__ import annotations

from bisect import bisect_left, insort
from collections.abc import Callable
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

LENGTHS = (512, 1024, 2048, 4096)
OVERHEAD = 16
GROUP = 4096


def bin_cost(length: int) -> float:
    """Default cost of a bin: its length, and what any sequence costs besides."""
    return length + OVERHEAD


def _cheapest(sizes: list[int], left: list[int], i: int, lengths: tuple[int, ...], cost: Callable[[int], float]) -> int:
    """The length to open for piece i: least cost a token if smaller pieces fill its room.
    left[j] is the sum of sizes[j:]; sizes fall, so the pieces that fit are a tail."""
    n = sizes[i]

    def rate(c: int) -> float:
        tail = bisect_left(sizes, n - c, lo=i + 1, key=lambda s: -s)
        return cost(c) / (n + min(c - n, left[tail]))

    return min((c for c in lengths if c >= n), key=rate)


def best_fit(sizes: list[int], lengths: tuple[int, ...], preferred: int | None, cost: Callable[[int], float] = bin_cost) -> tuple[list[int], list[int]]:
    """For sizes in falling order: the bin of each piece, and each bin's contents. Without a
    preferred length every opening takes the cheapest."""
    room: list[tuple[int, int]] = []  # open bins by (room left, bin)
    used: list[int] = []
    place = []
    left_over = [*accumulate(reversed(sizes))][::-1] + [0]
    for i, n in enumerate(sizes):
        at = bisect_left(room, (n, -1))
        if at < len(room):
            left, b = room.pop(at)
        else:
            b = len(used)
            left = _cheapest(sizes, left_over, i, lengths, cost) if preferred is None else next(c for c in lengths if c >= n and (c >= preferred or c == lengths[-1]))
            used.append(0)
        used[b] += n
        if left > n:
            insort(room, (left - n, b))
        place.append(b)
    return place, used


def pack(sizes: list[int], lengths: tuple[int, ...] = LENGTHS, cost: Callable[[int], float] = bin_cost) -> tuple[list[int], list[int]]:
    """The bin of each piece and the final length of each bin, at least cost over the ways to
    open bins (ties: the first). Sizes: falling, from 1 to lengths[-1]."""
    best = None
    for preferred in (None, *lengths):
        place, used = best_fit(sizes, lengths, preferred, cost)
        final = [next(c for c in lengths if c >= u) for u in used]
        total = sum(map(cost, final))
        if best is None or total < best[0]:
            best = (total, place, final)
    return best[1], best[2]


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"\S+")), F.lit(0)).cast("long")


def packed(docs: DataFrame, size: Column | None = None, lengths: tuple[int, ...] = LENGTHS) -> DataFrame:
    """doc_id, piece, start, length, bin_id, bin_length, bin_offset: a row for each piece.

    `size` measures a row (words by default). Rows of size 0, null or empty texts, have
    no piece. Repeated rows are packed each. Ties in length go by doc_id and piece.
    """
    lengths = tuple(sorted(lengths))
    longest = lengths[-1]
    size = size if size is not None else word_count(F.col("text"))
    # Rows are dealt by doc_id and content, so that rows without an id do not gather in one group.
    content = F.xxhash64("text") if "text" in docs.columns else F.lit(0).cast("long")
    sized = docs.select("doc_id", size.alias("size"), content.alias("content")).where("size > 0")
    pieces = sized.select("doc_id", "size", "content", F.posexplode(F.sequence(F.lit(0).cast("long"), F.col("size") - 1, F.lit(longest).cast("long"))).alias("piece", "start"))
    pieces = pieces.select("doc_id", "content", "piece", "start", F.least(F.lit(longest).cast("long"), F.col("size") - F.col("start")).alias("length"))
    n = sized.agg(F.sum(F.ceil(F.col("size") / longest))).first()[0] or 0
    groups = max(1, -(-n // GROUP))
    dealt = pieces.withColumn("grp", F.pmod(F.xxhash64("doc_id", "content", "piece"), F.lit(groups))).drop("content")

    def run(key: tuple, group: pa.Table) -> pa.Table:
        order = group.sort_by([("length", "descending"), ("doc_id", "ascending"), ("piece", "ascending")])
        sizes = order.column("length").to_pylist()
        place, final = pack(sizes, lengths)
        offset, filled = np.zeros(len(place), np.int64), np.zeros(len(final), np.int64)
        for i, b in enumerate(place):
            offset[i] = filled[b]
            filled[b] += sizes[i]
        g = key[0].as_py()
        return pa.table(
            {
                "doc_id": order.column("doc_id"),
                "piece": order.column("piece"),
                "start": order.column("start"),
                "length": order.column("length"),
                "bin_id": pa.array([(g << 20) + b for b in place], pa.int64()),
                "bin_length": pa.array([final[b] for b in place], pa.int64()),
                "bin_offset": pa.array(offset),
            }
        )

    return dealt.groupBy("grp").applyInArrow(run, "doc_id long, piece int, start long, length long, bin_id long, bin_length long, bin_offset long")


def pack_stage(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """Pipeline stage: what remains, packed."""
    return packed(docs)
