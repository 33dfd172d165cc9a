"""SimHash fingerprints with DataFrame operations only.

Every occurrence of a term votes on each of 64 bits with its weight, for the bit if it is
set in the term's hash and against it otherwise. Words of LONG characters and more weigh
more: short ones are mostly those that all texts share. The votes of two bits travel in
one long (32 bits each), so a word costs 32 additions in whole-stage code.

`near_fingerprints` finds all pairs within a Hamming radius by permuted block tables: of
`blocks` bit blocks, radius differing bits leave blocks - radius untouched, so each
choice of that many blocks is a table keyed by their bits.
"""

from __future__ import annotations

from functools import reduce
from itertools import combinations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from parsieve.llm.common import Cuts, partitions
from parsieve.llm.linking import components

LONG, WEIGHT = 6, 8
_NO_ID = -(1 << 63)


def _votes() -> list[Column]:
    pair = F.lit((1 << 32) + 1)
    return [F.sum(F.shiftrightunsigned("h", j).bitwiseAND(pair) * F.col("weight")).alias(f"votes{j}") for j in range(32)]


def _fingerprint() -> Column:
    """From the votes: a bit is set if the weight for it is more than half of all."""
    half = F.col("weights")
    bits = []
    for j in range(32):
        low, high = F.col(f"votes{j}").bitwiseAND(F.lit((1 << 32) - 1)), F.shiftrightunsigned(f"votes{j}", 32)
        bits += [F.when(2 * v > half, F.shiftleft(F.lit(1).cast("long"), j + k)).otherwise(F.lit(0).cast("long")) for v, k in ((low, 0), (high, 32))]
    return reduce(Column.bitwiseOR, bits)


def simhash(rows: DataFrame, keys: list[str], words: str) -> DataFrame:
    """keys, fp bigint, from an array column of words; an empty array or word votes nothing."""
    each = rows.select(*keys, F.explode_outer(words).alias("word"))
    weight = F.when(F.length("word") >= LONG, WEIGHT).when(F.length("word") > 0, 1).otherwise(0).cast("long")
    hashed = each.select(*keys, F.xxhash64("word").alias("h"), weight.alias("weight"))
    return hashed.groupBy(*keys).agg(F.sum("weight").alias("weights"), *_votes()).select(*keys, _fingerprint().alias("fp"))


def words_of(text: Column) -> Column:
    return F.split(F.lower(text), r"[\x20\x09-\x0D]+")


def hexed(fp: Column) -> Column:
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def likeness(a: Column, b: Column) -> Column:
    """Share of equal bits."""
    return 1 - F.bit_count(a.bitwiseXOR(b)) / F.lit(64.0)


def _bucketed(spark: SparkSession, rows: DataFrame) -> DataFrame:
    """A bucket by ranges of `rank_id`, of about equal size, in the order of the ids: the
    ranges come from quantiles of the ids, searched in two steps."""
    n = max(4 * partitions(spark), rows.count() // 50_000)
    cuts = rows.approxQuantile("rank_id", [i / n for i in range(1, n)], 0.25 / n) if n > 1 else []
    cuts = sorted({int(c) for c in cuts})
    if not cuts:
        return rows.withColumn("bucket", F.lit(0))
    wide = max(1, int(len(cuts) ** 0.5))
    parts = [cuts[i : i + wide] for i in range(0, len(cuts), wide)]

    def passed(points: Column) -> Column:
        return F.size(F.filter(points, lambda c: c <= F.col("rank_id")))

    longs = lambda xs: F.array(*(F.lit(x).cast("long") for x in xs))
    coarse = passed(longs([p[0] for p in parts]))
    fine = F.element_at(F.array(*map(longs, parts)), F.col("coarse"))
    rows = rows.withColumn("coarse", coarse)
    inside = F.when(F.col("coarse") > 0, (F.col("coarse") - 1) * wide + passed(fine)).otherwise(0)
    return rows.withColumn("bucket", inside.cast("int")).drop("coarse")


def with_next(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """bucket, row, rank_id, text, next_text, guest: each row and its successor by
    ascending doc_id (after the last the first; nulls first, repeated ids by text).

    The first row of a bucket also comes as a guest at the end of the bucket before, so
    that a window over buckets sees every successor. No bucket is more than its range.
    """
    rows = docs.select(F.coalesce("doc_id", F.lit(_NO_ID)).alias("rank_id"), F.coalesce("text", F.lit("")).alias("text"))
    rows = _bucketed(spark, rows)
    firsts = rows.groupBy("bucket").agg(F.min("rank_id").alias("first_id"))  # a row per bucket
    order = Window.orderBy("bucket")
    last = firsts.agg(F.max("bucket").alias("last_bucket"))
    hosts = firsts.crossJoin(F.broadcast(last)).select("first_id", F.coalesce(F.lag("bucket").over(order), "last_bucket").alias("host"))
    guests = rows.join(F.broadcast(hosts), rows["rank_id"] == hosts["first_id"]).groupBy("host", "rank_id").agg(F.min("text").alias("text"))
    both = rows.select("bucket", "rank_id", "text", F.lit(0).alias("guest")).union(guests.select("host", "rank_id", "text", F.lit(1)))
    w = Window.partitionBy("bucket").orderBy("guest", "rank_id", "text")
    return both.select("bucket", F.row_number().over(w).alias("row"), "rank_id", "text", F.lead("text").over(w).alias("next_text"), "guest")


def edited(text: Column, following: Column) -> Column:
    """The last half of the code points replaced by the first as many of another text."""
    half = F.floor(F.length(text) / 2).cast("int")
    return F.concat(F.left(text, F.length(text) - half), F.left(following, half))


def document_fingerprints(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited,
    near_next; a row per input row. A null text counts as empty. The text is shuffled once, by ranges of doc_id; all else follows in place."""
    base = with_next(spark, docs)
    text, change = F.col("text"), edited(F.col("text"), F.coalesce("next_text", F.lit("")))
    sides = F.array(F.struct(F.lit(0).alias("side"), words_of(text).alias("words")), F.struct(F.lit(1).alias("side"), words_of(change).alias("words")))
    spread = base.select("bucket", "row", F.explode(sides).alias("s")).select("bucket", "row", "s.side", "s.words")
    fps = simhash(spread, ["bucket", "row", "side"], "words")
    pair = fps.groupBy("bucket", "row").agg(F.max(F.when(F.col("side") == 0, F.col("fp"))).alias("fp"), F.max(F.when(F.col("side") == 1, F.col("fp"))).alias("edited_fp"))
    facts = base.select("bucket", "row", "rank_id", "guest", F.length("text").cast("long").alias("n_chars"), F.sha2(change, 256).alias("edited_sha256"))
    w = Window.partitionBy("bucket").orderBy("row")
    out = facts.join(pair, ["bucket", "row"]).withColumn("next_fp", F.lead("fp").over(w)).where("guest = 0")
    return out.select(
        F.when(F.col("rank_id") != _NO_ID, F.col("rank_id")).alias("doc_id"),
        "n_chars",
        "edited_sha256",
        hexed(F.col("fp")).alias("fingerprint"),
        hexed(F.col("edited_fp")).alias("edited_fingerprint"),
        likeness(F.col("fp"), F.col("edited_fp")).alias("near_edited"),
        likeness(F.col("fp"), F.col("next_fp")).alias("near_next"),
    )


def near_fingerprints(fps: DataFrame, radius: int = 3, blocks: int = 6, cuts: Cuts | None = None) -> DataFrame:
    """a, b, distance: all pairs a < b of different fingerprints within the radius.

    From a bigint column `fp`; equal fingerprints are one item, so copies cost nothing.
    With `cuts` the block tables are written, without the keys of one item, so that
    adaptive execution can split a hot key.
    """
    if not 0 <= radius < blocks <= 64:
        raise ValueError("more blocks than the radius are needed, 64 at most")
    edges = [64 * i // blocks for i in range(blocks + 1)]
    masks = [((1 << edges[i + 1]) - (1 << edges[i])) for i in range(blocks)]
    signed = lambda m: m - (1 << 64) if m >> 63 else m
    tables = [signed(sum(masks[i] for i in kept)) for kept in combinations(range(blocks), blocks - radius)]
    items = fps.select("fp").where("fp is not null").distinct()
    keyed = items.select("fp", F.posexplode(F.array(*(F.col("fp").bitwiseAND(F.lit(m).cast("long")) for m in tables))).alias("t", "k"))
    if cuts:
        # A key's items from its least and greatest: one of a single item has no partner.
        several = cuts.cut(keyed.groupBy("t", "k").agg(F.min("fp").alias("low"), F.max("fp").alias("high")).where("low < high").select("t", "k"), "several")
        keyed = cuts.cut(keyed.join(several, ["t", "k"]), "keyed")
    x, y = keyed.withColumnRenamed("fp", "a"), keyed.withColumnRenamed("fp", "b")
    far = F.bit_count(F.col("a").bitwiseXOR(F.col("b")))
    return x.join(y, ["t", "k"]).where(F.col("a") < F.col("b")).select("a", "b", far.alias("distance")).where(F.col("distance") <= radius).distinct()


def with_links(spark: SparkSession, prints: DataFrame, radius: int = 3) -> DataFrame:
    """prints(doc_id, fingerprint, ..) with near_links, the number of different other
    fingerprints within the radius, and near_class, the smallest (as a signed number) that can
    be reached over such links (its own without any)."""
    cuts = Cuts(spark)
    prints = cuts.cut(prints.withColumn("fp", F.conv("fingerprint", 16, -10).cast("long")), "prints")
    links = cuts.cut(near_fingerprints(prints, radius, cuts=cuts), "links")
    counted = links.select(F.explode(F.array("a", "b")).alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("near_links"))
    reached = components(cuts, links, one_task=0)  # by rounds of joins at any size, so that no Python runs on the executors
    linked = cuts.cut(counted.join(reached, "id"), "linked")
    out = prints.join(linked, F.col("fp") == F.col("id"), "left")
    return out.withColumns({"near_links": F.coalesce("near_links", F.lit(0)), "near_class": hexed(F.coalesce("component", "fp"))}).drop("fp", "id", "component")
