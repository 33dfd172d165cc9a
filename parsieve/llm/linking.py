"""From banding keys to verified components.

Items share buckets; two items of a bucket are a candidate pair; a pair is linked if the
Jaccard similarity of their full element sets reaches a threshold; the result is the
components of the links. Pairs inside one component need no look, so not all of a bucket
is paired up: each bucket's smallest item (its hub) is compared with the others, and the
links found give components. Of buckets that still hold several components, those of up to
FEW items are paired up across components, all but those that lie in the component of the
bucket's smallest with all others; sizes and bitmaps end far pairs in that join, and a pair is
made in one of its shared buckets only, so that it gives little more than links. In larger ones the next smallest is the hub for TURNS further
turns, and what is left then meets by prefixes: with all elements in one order, rarest first, a pair can only be
linked if it shares one of the first few of either set, and the places of the first
shared one bound the intersection. What is left out can change no component: all linked
candidate pairs count, and so do linked pairs that meet by prefixes without a bucket.

Each item carries a small mark in its bucket rows (a size, a sketch), by which most far pairs end
where they are made.

Joins on a key that may be hot read a written side, so that adaptive execution can
split the hot partition, and every aggregation is combined before its shuffle. Joins that
move sets or texts are sort-merge joins at every size, so they spill and never fill memory.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from parsieve.llm.common import Cuts, Sieve


def _stars(e: DataFrame) -> bool:
    """Whether e(u, v), v < u, is a set of disjoint stars: each u once, no v is a u."""
    end = lambda x, up: F.struct(F.col(x).alias("x"), F.lit(up).alias("up"), F.lit(1 - up).alias("down"))
    ends = e.select(F.explode(F.array(end("u", 1), end("v", 0))).alias("end")).select("end.*")
    met = ends.groupBy("x").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
    return met.where("up + down > 1 and up > 0").isEmpty()


def _least_reachable(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The different end points of the edges a[i], b[i], and the smallest each can reach."""
    ids, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    low = np.arange(len(ids))
    u, v = ends[: len(a)], ends[len(a) :]
    while len(u):
        # Roots hook on to the smallest root next to them, then all paths are cut short.
        np.minimum.at(low, np.maximum(u, v), np.minimum(u, v))
        while (low[low] != low).any():
            low = low[low]
        u, v = low[u], low[v]
        apart = u != v
        u, v = u[apart], v[apart]
    return ids, ids[low]


def _in_one_task(edges: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches if b.num_rows]
        if found:
            ids, low = _least_reachable(*map(np.concatenate, zip(*found)))
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(low)], names=["id", "component"])

    return edges.coalesce(1).mapInArrow(run, "id long, component long")


#: Edges that one task may join up (64 MB of them); more go through rounds of joins.
ONE_TASK = 1 << 22
#: Edges whose rounds of joins may go through one task, which then shuffles and waits for nothing.
ONE_PLACE = 1 << 20


def components(cuts: Cuts, edges: DataFrame, one_task: int = ONE_TASK) -> DataFrame:
    """(id, component) of all end points of edges(a, b), a view of written tables; component
    is the smallest id.

    Up to `one_task` edges are joined up by one task (0: none). More go through rounds of large-star and
    small-star steps on the edge table until it consists of stars; each is written, and the
    previous one removed. Rounds of up to ONE_PLACE edges are one job of one partition each.
    """
    edges = edges.where("a <> b")
    count = edges.count()
    if one_task and count <= one_task:
        return _in_one_task(edges.select(F.col("a").cast("long"), F.col("b").cast("long")))
    alone = count <= ONE_PLACE
    place = lambda df: df.coalesce(1) if alone else df
    step = (lambda df, _: df) if alone else cuts.cut
    written = cuts.cut(place(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))).distinct(), "edges")
    while not _stars(place(written)):
        e = place(written)
        both = place(e.union(e.select("v", "u")))
        low = step(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "low")
        large = step(both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct(), "large")
        least = step(large.groupBy("u").agg(F.min("v").alias("m")), "low")
        small = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        after = cuts.cut(place(small.union(least.select("u", F.col("m").alias("v")))).distinct(), "edges")
        cuts.drop(written, low, large, least)
        written = after
    return written.select(F.col("u").alias("id"), F.col("v").alias("component")).union(written.select("v", "v").distinct())


class Items:
    """What `link` must know of the items. Items are linked if 100 * |A and B| >= percent * |A or B|."""

    words: int
    one_task = ONE_TASK  # as `components` takes it

    def near(self, a: Column, b: Column, percent: int) -> Column:
        """Whether items with the marks a and b may be linked."""
        raise NotImplementedError

    def content_of(self, cuts: Cuts, ids: DataFrame) -> tuple[DataFrame, DataFrame]:
        """(id, content) and (id, n, parity) of the items in ids(id), written: n elements, and a
        bitmap of `words` longs, of which a bit tells whether an odd number of elements falls on it."""
        raise NotImplementedError

    def linked(self, cuts: Cuts, pairs: DataFrame, content: DataFrame, sizes: DataFrame, percent: int) -> DataFrame:
        """Those of pairs(a, b) that reach the threshold on their full sets."""
        raise NotImplementedError

    def elements(self, rows: DataFrame) -> DataFrame:
        """(id, component, e) for each different element of rows(id, component, content),
        those of an item in one task."""
        raise NotImplementedError


def _enough(common: Column, percent: int) -> Column:
    """Whether sets of na and nb elements, `common` of them shared, are linked."""
    return (100 + percent) * common >= percent * (F.col("na") + F.col("nb"))


def spread(bitmap: str, words: int, name: str) -> list[Column]:
    """The words of a bitmap as columns name0, name1 and so on. Comparisons of arrays make the code
    of a join so long that the JVM interprets it, at ten times the cost."""
    return [F.col(bitmap)[w].alias(f"{name}{w}") for w in range(words)]


def may_link(words: int, percent: int) -> Column:
    """False only for far pairs: sets of na and nb elements with the bitmaps pa0, pa1, .. and pb0,
    pb1, .. differ in at least as many elements as their bitmaps do in bits."""
    apart = sum(F.bit_count(F.col(f"pa{w}").bitwiseXOR(F.col(f"pb{w}"))) for w in range(words))
    return _enough(F.least("na", "nb"), percent) & _enough(F.shiftright(F.col("na") + F.col("nb") - apart, 1), percent)


def bitmaps(sets: list[np.ndarray], words: int) -> pa.ListArray:
    """The bitmap of each set of hashes."""
    size = 64 * words
    bits = np.array([np.bincount((x % np.uint64(size)).astype(np.intp), minlength=size) & 1 for x in sets], bool).reshape(len(sets), size)
    flat = np.packbits(bits, axis=1).view(np.int64).ravel()
    return pa.ListArray.from_arrays(np.arange(0, len(flat) + 1, words, dtype=np.int32), flat)


#: Items of a bucket that are paired up in full: FEW / 2 pairs or fewer for each.
FEW = 1000
#: Further turns of hubs in larger ones. They only move work between turns and prefixes: what they leave
#: meets by prefixes in full.
TURNS = 2
#: Longs of a bitmap of 64 bits each. More end more far pairs of large sets.
PARITY = 4
#: Elements of a prefix that go with the next one.
WINDOW = 8


def parity(words: int) -> Column:
    """The bitmap of a group's elements e, an array of longs."""
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftrightunsigned("e", 8).bitwiseAND(F.lit(63)).cast("int"))
    return F.array(*(F.coalesce(F.bit_xor(F.when(F.col("e").bitwiseAND(F.lit(words - 1)) == w, bit)), F.lit(0).cast("long")) for w in range(words)))


def _across(each: DataFrame) -> DataFrame:
    """(e, c, who): elements of several components, the number of their items, and a hash of
    the set of their items."""
    found = each.groupBy("e").agg(F.count(F.lit(1)).alias("c"), F.bit_xor(F.xxhash64("id")).alias("who"), F.min("component").alias("low"), F.max("component").alias("high"))
    return found.where("low < high").select("e", "c", "who")


def _prefix_pairs(cuts: Cuts, items: Items, rows: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) of different components that may be linked, a superset of those that
    are, from rows(id, component, content).

    Elements found in one component only are in no intersection that counts; in the order
    they come first. A set of n elements shares at least ceil(percent * n / 100) with a
    partner, so one of its first n + 1 less that many is shared. From the first shared
    one on, the intersection is no larger than what follows in either set.

    Each item also has a bitmap: bit k tells whether an odd number of its elements falls on
    k. Sets differ in at least as many elements as their bitmaps do in bits, so far pairs end
    in the join itself, and none that is linked does.

    Elements of the same items, as the shingles of a shared passage are, stand together in
    the order. All that such items can meet by is the first of them, so the others go. Nor
    does a pair meet by an element if both prefixes have one element among the WINDOW before
    it: it has met by that one. (32-bit hashes stand for those; for one pair in 10^7 or fewer
    they are equal by chance where the pair first meets.)
    """
    across = cuts.cut(_across(items.elements(rows)), "across")
    met = items.elements(rows).join(across.hint("merge"), "e", "left").groupBy("id")
    useful = met.agg(parity(PARITY).alias("parity"), F.first("component").alias("component"), F.count(F.lit(1)).alias("n"), F.sort_array(F.collect_list(F.when(F.col("c").isNotNull(), F.struct("c", "who", "e")))).alias("useful"))
    n, size = F.col("n"), F.size("useful")
    length = n + 1 - F.ceil(n * percent / 100) - (n - size)
    prefix = F.slice("useful", F.lit(1), F.greatest(length, F.lit(0)).cast("int"))
    placed = useful.select("id", "component", "n", "parity", size.alias("size"), prefix.alias("prefix"))
    before = lambda i: F.get("prefix", i - 1)
    numbered = F.transform("prefix", lambda x, i: F.struct(x["e"].alias("e"), (F.col("size") - i).alias("after"), ((i > 0) & (before(i)["c"] == x["c"]) & (before(i)["who"] == x["who"])).alias("again")))
    first = F.filter(numbered, lambda x: ~F.coalesce(x["again"], F.lit(False)))
    met_by = F.transform(first, lambda x: F.struct(x["e"].alias("e"), x["after"].alias("after")))
    cut = cuts.cut(placed.select("id", "component", "n", "parity", met_by.alias("met_by")), "prefixes")
    marked = cut.select("*", F.transform("met_by", lambda x: F.hash(x["e"])).alias("marks"))
    each = marked.select("id", "component", "n", "parity", "marks", F.posexplode("met_by").alias("i", "x"))
    earlier = F.slice("marks", F.greatest(F.col("i") - (WINDOW - 1), F.lit(1)), F.least("i", F.lit(WINDOW)))
    each = each.select("id", "component", "n", "parity", "x.e", "x.after", earlier.alias("earlier"))
    side = lambda x: [F.col("id").alias(x), *(F.col(c).alias(f"{c}_{x}") for c in ("component", "after", "earlier")), F.col("n").alias(f"n{x}"), *spread("parity", PARITY, f"p{x}")]
    x, y = each.select("e", *side("a")), each.select("e", *side("b"))
    near = _enough(F.least("after_a", "after_b"), percent) & may_link(PARITY, percent)
    pairs = x.join(y.hint("merge"), "e").where((F.col("component_a") != F.col("component_b")) & (F.col("a") < F.col("b")) & near & ~F.arrays_overlap("earlier_a", "earlier_b"))
    pairs = cuts.cut(pairs.select("a", "b").distinct(), "pairs")
    cuts.drop(cut, across)
    return pairs


def _left(cuts: Cuts, members: DataFrame, found: DataFrame) -> DataFrame:
    """(bucket, id, mark, component, size, hub struct<id, component, mark>) for members(bucket,
    id, mark) of buckets that hold several components; size is the bucket's, the hub its smallest item."""
    placed = members.join(found.hint("merge"), "id", "left").select("bucket", "id", "mark", F.coalesce("component", "id").alias("component"))
    placed = cuts.cut(placed, "placed")
    mixed = placed.groupBy("bucket").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.count(F.lit(1)).alias("size"), F.min(F.struct("id", "component", "mark")).alias("hub")).where("low < high")
    mixed = cuts.cut(mixed.select("bucket", "size", "hub"), "mixed")
    left = cuts.cut(placed.join(mixed.hint("merge"), "bucket"), "left")
    cuts.drop(placed, mixed)
    return left


def _paired(few: DataFrame, items: Items, percent: int) -> DataFrame:
    """The pairs (a, b) of different components that share a bucket and may be linked, from few(bucket, id,
    mark, component, inner, n, parity, own): inner tells whether the component is that of the bucket's
    smallest, own are all buckets of the item. A pair is made in the smallest bucket that it shares."""
    kind = few.schema["mark"].dataType
    fields = kind.names if isinstance(kind, StructType) else []
    marks = lambda x: [F.col(f"mark.{c}").alias(f"{x}_mark_{c}") for c in fields] or [F.col("mark").alias(f"{x}_mark")]
    mark = lambda x: F.struct(*(F.col(f"{x}_mark_{c}").alias(c) for c in fields)) if fields else F.col(f"{x}_mark")
    side = lambda x: [*(F.col(c).alias(f"{x}_{c}") for c in ("id", "component", "inner", "own")), *marks(x), F.col("n").alias(f"n{x}"), *spread("parity", items.words, f"p{x}")]
    both = few.where("not inner").select("bucket", *side("a")).join(few.select("bucket", *side("b")).hint("merge"), "bucket")
    both = both.where("a_component <> b_component and (b_inner or a_id < b_id)").where(items.near(mark("a"), mark("b"), percent)).where(may_link(items.words, percent))
    both = both.where(F.array_min(F.array_intersect("a_own", "b_own")) == F.col("bucket"))
    return both.select(F.least("a_id", "b_id").alias("a"), F.greatest("a_id", "b_id").alias("b"))


def _merged(cuts: Cuts, items: Items, found: DataFrame, more: DataFrame) -> DataFrame:
    """The components of found(id, component) and the links more(a, b)."""
    if more.isEmpty():
        return found
    merged = components(cuts, found.select(F.col("id").alias("a"), F.col("component").alias("b")).union(more), items.one_task)
    return cuts.cut(merged, "found")


def link(cuts: Cuts, keys: DataFrame, items: Items, percent: int) -> DataFrame:
    """(id, component) of every item with a link, from keys(id, mark, bucket), a view of a
    written table."""
    shared = keys.groupBy("bucket").agg(F.min("id").alias("hub"), F.max("id").alias("last")).where("hub < last")
    shared = cuts.cut(shared.select("bucket", "hub"), "shared")
    # Rows of buckets with one member end here, before they are shuffled.
    every = Sieve(shared, "bucket").passed(keys, "bucket").join(shared.hint("merge"), "bucket")
    every = cuts.cut(every.select("bucket", "id", "mark", "hub"), "every")
    cuts.drop(shared)
    hubs = every.where("id = hub").select("bucket", F.struct("id", "mark").alias("hub"))
    members = every.where("id <> hub").drop("hub").join(hubs.hint("merge"), "bucket")
    members = cuts.cut(members.select("bucket", "id", "mark", "hub"), "members")
    cuts.drop(every)

    def near(rows: DataFrame, a: str, b: str) -> DataFrame:
        return rows.where(items.near(F.col(f"{a}mark"), F.col(f"{b}mark"), percent)).select(F.col(f"{a}id").alias("a"), F.col(f"{b}id").alias("b"))

    star = cuts.cut(near(members, "", "hub.").distinct(), "spokes")
    # The hub itself meets everyone now; buckets with three items or more may go on without it.
    ids = members.select("bucket", "id").groupBy("bucket").agg(F.min("id").alias("low"), F.max("id").alias("high")).where("low < high").select("bucket")
    ids = Sieve(cuts.cut(ids, "several"), "bucket").passed(members, "bucket").select("id")
    ids = cuts.cut(ids.union(star.select("a")).union(star.select("b")).distinct(), "ids")
    content, sizes = items.content_of(cuts, ids)
    cuts.drop(ids)
    met = cuts.cut(items.linked(cuts, star, content, sizes, percent), "star")
    found = cuts.cut(components(cuts, met, items.one_task), "found")
    cuts.drop(star, met)
    # What is left: buckets that still hold several components.
    left = _left(cuts, members.select("bucket", "id", "mark"), found)
    cuts.drop(members)
    small = left.where(F.col("size") <= FEW).drop("size")
    own = small.groupBy("id").agg(F.collect_set("bucket").alias("own"))
    sized = small.join(sizes.hint("merge"), "id").join(own.hint("merge"), "id")
    few = cuts.cut(sized.withColumn("inner", F.col("component") == F.col("hub.component")).drop("hub"), "sized")
    pairs = cuts.cut(_paired(few, items, percent).distinct(), "few")
    cuts.drop(few)
    more = cuts.cut(items.linked(cuts, pairs, content, sizes, percent), "more")
    found = _merged(cuts, items, found, more)
    cuts.drop(pairs, more)
    large = left.where(F.col("size") > FEW).select("bucket", "id", "mark")
    if large.isEmpty():
        return found
    met, left = left, _left(cuts, large, found)
    cuts.drop(met)
    for _ in range(TURNS):
        if left.isEmpty():
            return found
        # The smallest item left in each is its hub now.
        spokes = cuts.cut(near(left.where("component <> hub.component"), "", "hub.").distinct(), "spokes")
        more = cuts.cut(items.linked(cuts, spokes, content, sizes, percent), "more")
        found = _merged(cuts, items, found, more)
        met = left
        left = _left(cuts, met.where("id <> hub.id").select("bucket", "id", "mark"), found)
        cuts.drop(met, more, spokes)
    rest = left.groupBy("id").agg(F.min("component").alias("component"), F.min("mark").alias("mark"))
    rest = cuts.cut(rest.join(content.hint("merge"), "id"), "rest")
    cuts.drop(left, content)
    pairs = _prefix_pairs(cuts, items, rest.drop("mark"), percent)
    side = lambda x: rest.select(F.col("id").alias(f"{x}_id"), F.col("mark").alias(f"{x}_mark")).hint("merge")
    marked = pairs.select(F.col("a").alias("a_id"), F.col("b").alias("b_id")).join(side("a"), "a_id").join(side("b"), "b_id")
    close = cuts.cut(near(marked, "a_", "b_"), "close")
    more = cuts.cut(items.linked(cuts, close, rest.drop("component", "mark"), sizes, percent), "more")
    cuts.drop(rest, pairs, close)
    return _merged(cuts, items, found, more)
