"""The search on Spark: breadth-first layers, depth-first subtrees, and the switch.

A layer is a table of nodes: words of the set u and of the mask x of targets that still
want it. One Arrow stage scores a layer. A small layer comes from the driver and its
result goes back there; that of a larger one is written with the finds and the surviving
masks, so a repeated task counts nothing twice, and its children are column expressions.
Lists of finds are broadcast to the next layer; they are far smaller than the lattice.
"""

from __future__ import annotations

import json
import time
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from parsieve.functions import bitset
from parsieve.functions.scores import Mdl, Score
from parsieve.operators import kernel
from parsieve.operators.kernel import Cells, Lists, Problem
from parsieve.plans.encode import Encoded, encode
from parsieve.plans.staging import Stage

NODE_BYTES = 32
LOCAL_NODES = 20_000  # of a layer that the driver may hold
COUNTED_ROWS = 1 << 14  # different rows from which on a layer's sets are counted once for all targets
COUNTED_NODES = 8  # times LOCAL_NODES may be held then: counting rules the time


@dataclass
class SearchResult:
    """`mps` rows (target, parents, size, score), one dict per layer, and the totals.
    `complete` is False where a cap or pruning under weak ties may have left sets out."""

    spark: SparkSession
    order: list[str]
    arity: list[int]
    entries: list[tuple[int, int, float]]
    layers: list[dict]
    totals: dict
    complete: bool
    problem: Problem = field(repr=False, default=None)

    @property
    def mps(self) -> DataFrame:
        rows = [(self.order[t], bitset.names(u, self.order), u.bit_count(), float(s)) for t, u, s in self.entries]
        return self.spark.createDataFrame(rows, "target string, parents array<string>, size int, score double")

    @property
    def layer_table(self) -> DataFrame:
        kind = "layer int, nodes long, pairs long, scored long, new_mps long, pruned_c1 long, pruned_c2 long, mode string"
        rows = [(x["layer"], x["nodes"], x["pairs"], x["scored"], x["hits"], x["c1"], x["c2"], x["mode"]) for x in self.layers]
        return self.spark.createDataFrame(rows, kind)

    @property
    def variables(self) -> DataFrame:
        p = self.problem
        rows = [(c, i, a, float(f), float(e)) for i, (c, a, f, e) in enumerate(zip(self.order, self.arity, p.floor, p.empty, strict=True))]
        return self.spark.createDataFrame(rows, "name string, pos int, arity int, floor_bits double, s_empty double")


def partitions(spark: SparkSession, nodes: int, factor: int = 4, most: int = 100_000) -> int:
    """A small multiple of the cores, fewer for small layers, more for very large ones."""
    cores = spark.sparkContext.defaultParallelism
    return max(1, min(factor * cores, -(-nodes // 64)), -(-nodes // most))


def _names(n_words: int, letter: str) -> list[str]:
    return [f"{letter}{i}" for i in range(n_words)]


def _node_schema(n_words: int) -> str:
    return ", ".join(f"{c} long" for c in _names(n_words, "u") + _names(n_words, "x"))


def scored(nodes: DataFrame, shared, lists_shared, n_words: int) -> DataFrame:
    """u*, y* (targets that go on), hits and counters of every node."""
    columns = _names(n_words, "u") + _names(n_words, "x")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p, lists = shared.value, lists_shared.value
        cells = Cells(p)
        for b in batches:
            cols = [b.column(c).to_pylist() for c in columns]
            out: list[list] = [[] for _ in range(2 * n_words + 6)]
            for row in zip(*cols, strict=True):
                u, x = bitset.join(row[:n_words]), bitset.join(row[n_words:])
                hits, go_on, seen = kernel.evaluate(p, cells, lists, u, x)
                for c, v in zip(out, [*row[:n_words], *bitset.split(go_on, n_words), [{"t": t, "s": s} for t, s in hits], u.bit_length() - 1, seen["pairs"], seen["scored"], seen["c1"], seen["c2"]], strict=True):
                    c.append(v)
            kinds = [pa.int64()] * (2 * n_words) + [pa.list_(pa.struct([("t", pa.int32()), ("s", pa.float64())])), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64()]
            names = _names(n_words, "u") + _names(n_words, "y") + ["hits", "top", "pairs", "scored", "c1", "c2"]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds, strict=True)], names=names)

    schema = ", ".join(f"{c} long" for c in _names(n_words, "u") + _names(n_words, "y"))
    return nodes.mapInArrow(run, f"{schema}, hits array<struct<t int, s double>>, top int, pairs long, scored long, c1 long, c2 long")


def expand(layer: DataFrame, p_n: int, n_words: int) -> DataFrame:
    """Children by the chosen predecessor, with column expressions only."""
    new = F.explode(F.when(F.col("top") < p_n - 1, F.sequence(F.col("top") + 1, F.lit(p_n - 1))).otherwise(F.array().cast("array<int>")))
    grown = layer.select("*", new.alias("new"))
    u = [F.col(f"u{w}").bitwiseOR(bitset.bit(w, F.col("new"), p_n)).alias(f"u{w}") for w in range(n_words)]
    x = [F.col(f"y{w}").bitwiseAND(F.bitwise_not(bitset.bit(w, F.col("new"), p_n))).alias(f"x{w}") for w in range(n_words)]
    return grown.select(*u, *x).where(bitset.any_set([F.col(f"x{w}") for w in range(n_words)]))


def fold(nodes: DataFrame, n_words: int) -> DataFrame:
    """Rows of equal u become one whose mask has all their targets."""
    return nodes.groupBy(*_names(n_words, "u")).agg(*(F.bit_or(c).alias(c) for c in _names(n_words, "x")))


def _early(children: DataFrame, p: Problem, n_words: int) -> DataFrame:
    """Early Condition 1: drop targets whose penalty at the child already ends them."""
    if "early_c1" not in p.rules:
        return children
    inside = lambda i: F.col(f"u{i // bitset.WORD}").bitwiseAND(F.lit(1 << i % bitset.WORD)) != 0
    q = reduce(Column.__mul__, (F.when(inside(i), float(a)).otherwise(1.0) for i, a in enumerate(p.arity)))
    sized = children.withColumn("q", q)

    def alive(word: int) -> Column:
        """One bit of each target that may go on."""
        of_word = range(word * bitset.WORD, min(p.n, (word + 1) * bitset.WORD))
        fine = lambda t: p.score.penalty_column(F.col("q"), F.lit(p.arity[t]), p.m) < p.empty[t] - p.eps[t]
        return reduce(Column.bitwiseOR, (F.when(fine(t), F.lit(1 << t % bitset.WORD).cast("long")).otherwise(F.lit(0).cast("long")) for t in of_word))

    out = sized.withColumns({f"x{w}": F.col(f"x{w}").bitwiseAND(alive(w)) for w in range(n_words)}).drop("q")
    return out.where(bitset.any_set([F.col(f"x{w}") for w in range(n_words)]))


def _ahead(p_n: int, n_words: int) -> tuple[Column, Column]:
    """Of a scored node: the number of its children, and a bound on that of their children.
    Each column above the node's own makes a child, but a lone target is no parent of itself."""
    above = F.lit(p_n - 1) - F.col("top")
    y = [F.col(f"y{w}") for w in range(n_words)]
    alive = bitset.any_set(y)
    own = reduce(Column.bitwiseOR, (F.when(F.col(f"u{w}") >= 0, F.col(f"y{w}").bitwiseAND(_above(w, p_n))) for w in range(n_words)))
    lone = (bitset.size(y) == 1) & (own != 0)
    return F.when(alive, above - lone.cast("int")).otherwise(0), F.when(alive, above * (above - 1) / 2).otherwise(0)


def _above(word: int, n: int) -> Column:
    """The mask of the columns above `top` in word number `word`."""
    values = [sum(1 << p % bitset.WORD for p in range(top + 1, n) if p // bitset.WORD == word) for top in range(-1, n)]
    return F.element_at(F.array(*(F.lit(v).cast("long") for v in values)), F.col("top") + 2)


def default_budget(spark: SparkSession) -> int:
    """Bytes that the widest layer may take: half of what the executors have."""
    conf = spark.sparkContext._jsc.sc().conf()
    local = spark.sparkContext.master.startswith("local") and "cluster" not in spark.sparkContext.master
    kind = "spark.driver.memory" if local else "spark.executor.memory"
    one = spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(conf.get(kind, "1g"))
    return one // 2 if local else one // 2 * max(1, spark.sparkContext._jsc.sc().getExecutorMemoryStatus().size() - 1)


def _frame(spark: SparkSession, rows: list[tuple[int, int]], n_words: int, parts: int) -> DataFrame:
    """A small layer, neighbours in one task."""
    flat = zip(*((*bitset.split(u, n_words), *bitset.split(x, n_words)) for u, x in sorted(rows)), strict=True)
    table = pa.table([pa.array(c, pa.int64()) for c in flat], names=_names(n_words, "u") + _names(n_words, "x"))
    return spark.createDataFrame(table).coalesce(parts)


def _evaluated(done: pa.Table, n_words: int) -> Iterator[tuple]:
    """What `kernel.evaluate` gives, with u before it, for each row of a small scored layer."""
    cols = {c: done.column(c).to_pylist() for c in done.column_names}
    for i in range(done.num_rows):
        u, y = (bitset.join(cols[f"{letter}{w}"][i] for w in range(n_words)) for letter in "uy")
        yield u, [(h["t"], h["s"]) for h in cols["hits"][i]], y, {k: cols[k][i] for k in ("pairs", "scored", "c1", "c2")}


def _local_layer(p: Problem, done: Iterable[tuple], lists: Lists) -> tuple[dict, list[tuple[int, int]], int]:
    """Counters of a small layer, its children, and a bound on theirs; finds go to `lists`."""
    sums = dict.fromkeys(("pairs", "scored", "c1", "c2", "nodes", "hits"), 0)
    following, ahead = [], 0
    for u, hits, y, seen in done:
        for k, v in seen.items():
            sums[k] += v
        sums["nodes"] += 1
        sums["hits"] += len(hits)
        for t, s in hits:
            lists.add(t, u, s)
        if y:
            above = p.n - u.bit_length()
            ahead += above * (above - 1) // 2
            following += kernel.children(p, u, y)
    return sums, following, ahead


def _log_sums(spark: SparkSession, shared, p: Problem, sets: set[int], n_words: int, factor: int) -> dict[int, float]:
    """The log sum of each set. A row for a task is a run of neighbouring sets, their words one
    after the other; the task finds those that it can count together."""
    if not sets:
        return {}
    ordered = kernel.in_order(p, sets)
    parts = factor * spark.sparkContext.defaultParallelism
    step = max(64, -(-len(ordered) // parts))
    flat = [[w for u in ordered[i : i + step] for w in bitset.split(u, n_words)] for i in range(0, len(ordered), step)]
    table = pa.table([pa.array(flat, pa.list_(pa.int64()))], names=["words"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = Cells(shared.value)
        for b in batches:
            for words in b.column("words").to_pylist():
                own = [bitset.join(words[i : i + n_words]) for i in range(0, len(words), n_words)]
                found = [x for g in kernel.neighbours(cells.p, own) for x in kernel.log_sums(cells, g)]
                split = [bitset.split(u, n_words) for u, _ in found]
                columns = [pa.array([x[w] for x in split], pa.int64()) for w in range(n_words)]
                yield pa.RecordBatch.from_arrays([*columns, pa.array([v for _, v in found], pa.float64())], names=[*_names(n_words, "u"), "logs"])

    kind = ", ".join(f"{c} long" for c in _names(n_words, "u")) + ", logs double"
    done = spark.createDataFrame(table).repartition(len(flat)).mapInArrow(run, kind).toArrow()
    columns = [c.to_pylist() for c in done.columns]
    return {bitset.join(row[:-1]): row[-1] for row in zip(*columns, strict=True)}


def _counted_layer(spark: SparkSession, shared, p: Problem, nodes: list[tuple[int, int]], before: dict[int, float], n_words: int, factor: int) -> kernel.Known:
    """Log sums for a layer of nodes; `before` has those of the layer before."""
    sets = kernel.sets_to_count(p, nodes)
    known = {u: before[u] for u in sets if u in before}
    return kernel.Known(known | _log_sums(spark, shared, p, sets - known.keys(), n_words, factor))


def _folded(rows: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: dict[int, int] = {}
    for u, x in rows:
        out[u] = out.get(u, 0) | x
    return list(out.items())


def _collected(nodes: DataFrame, n_words: int) -> list[tuple[int, int]]:
    return [(bitset.join(r[:n_words]), bitset.join(r[n_words:])) for r in nodes.collect()]


def search(
    spark: SparkSession, enc: Encoded, p: Problem, mode: str = "auto", root_layer: int | None = None, memory_budget: int | None = None, fold_from: int = 0,
    targets: list[int] | None = None, factor: int = 4, local_nodes: int = LOCAL_NODES, checkpoint: str | None = None,
) -> SearchResult:
    """mode 'bfs': layers to the end; 'dfs': roots at `root_layer` (default: the first layer with
    `factor` nodes a core); 'auto': depth-first from the first layer whose grandchildren
    may exceed `memory_budget` bytes (default: half of the executors' memory).

    A layer of up to `local_nodes` nodes goes to the tasks from the driver and back; a larger
    one is a written table, of which only the last is kept. Of a table of many different rows
    the tasks count the sets of such a layer instead (up to COUNTED_NODES times as many nodes),
    each once for all pairs of a node and a target, and the driver takes the scores from them. `checkpoint` names a folder for the
    finds and the frontier after each layer; a search that finds it goes on from there."""
    if mode not in ("auto", "bfs", "dfs"):
        raise ValueError(f"no mode {mode}")
    n_words = bitset.words(p.n)
    names_u = _names(n_words, "u")
    budget = memory_budget if memory_budget is not None else default_budget(spark)
    shared = spark.sparkContext.broadcast(p)
    stage, lists, layers, begun = Stage(spark), Lists(), [], time.time()
    everything = sum(1 << t for t in (targets if targets is not None else range(p.n)))
    unfolded = fold_from > 0
    frontier: list | DataFrame = [(0, 1 << t) for t in bitset.members(everything)] if unfolded else [(0, everything)]
    depth, mode_now, flagged, rejected, left_at_switch, over, behind = 0, "bfs", 0, 0, 0, False, None
    saved = _resumed(spark, checkpoint, n_words) if checkpoint else None
    if saved:
        depth, unfolded, frontier, layers, rows = saved
        for t, u, s in rows:
            lists.add(t, u, s)
    size = len(frontier) if everything and p.n else 0
    counted, known = p.score.monotone and p.codes.shape[1] >= COUNTED_ROWS, kernel.Known({})
    if counted:
        local_nodes *= COUNTED_NODES
    while size:
        enough = depth == root_layer if root_layer is not None else size >= factor * spark.sparkContext.defaultParallelism
        if (mode == "dfs" and enough) or (mode == "auto" and over):
            mode_now = "dfs"
        local = isinstance(frontier, list)
        parts = partitions(spark, size, factor)
        here = local and counted and mode_now == "bfs"
        nodes = frontier if here or not local else _frame(spark, frontier, n_words, parts)
        lists_shared = spark.sparkContext.broadcast(lists)
        if mode_now == "dfs":
            left_at_switch = size
            roots = nodes.repartition(max(parts, min(size, factor * spark.sparkContext.defaultParallelism)), F.xxhash64(*names_u)).sortWithinPartitions(*names_u)
            found, rejected, row = _depth_first(spark, stage, roots, shared, lists_shared, n_words, lists)
            flagged = sum(u.bit_count() > depth for _, u, _ in found) + rejected
            for t, u, s in found:
                lists.add(t, u, s)
            layers.append(row | {"layer": depth, "mode": "dfs"})
            break
        if local:
            if here:
                known = _counted_layer(spark, shared, p, nodes, known.logs, n_words, factor)
                done = [(u, *kernel.evaluate(p, known, lists, u, x)) for u, x in nodes]
            else:
                done = _evaluated(scored(nodes, shared, lists_shared, n_words).toArrow(), n_words)
            sums, frontier, ahead = _local_layer(p, done, lists)
            if unfolded and depth + 1 >= fold_from:
                frontier, unfolded = _folded(frontier), False
            size = len(frontier)
            if size > local_nodes:
                frontier = _frame(spark, frontier, n_words, partitions(spark, size, factor))
        else:
            done = stage.cut(scored(nodes.repartitionByRange(parts, *names_u).sortWithinPartitions(*names_u), shared, lists_shared, n_words))
            stage.drop(behind)
            behind = done
            born, grand = _ahead(p.n, n_words)
            sums = done.agg(F.count(F.lit(1)).alias("nodes"), *(F.sum(c).alias(c) for c in ("pairs", "scored", "c1", "c2")), F.sum(F.size("hits")).alias("hits"), F.sum(born).alias("born"), F.sum(grand).alias("grand")).first().asDict()
            size, ahead = sums.pop("born") or 0, sums.pop("grand") or 0
            if sums["hits"]:  # maximal parent sets of this layer only; a repeated task repeats rows of another file, never of this one
                for row in done.where(F.size("hits") > 0).select(*names_u, F.explode("hits").alias("h")).select(*names_u, "h.t", "h.s").collect():
                    lists.add(row["t"], bitset.join(row[c] for c in names_u), row["s"])
            frontier = _early(expand(done, p.n, n_words), p, n_words)
            if unfolded and depth + 1 >= fold_from:
                frontier, unfolded = fold(frontier, n_words), False
            if size <= local_nodes:
                frontier = _collected(frontier, n_words)
                size = len(frontier)
        lists_shared.unpersist()
        if sums["nodes"]:
            layers.append({k: v or 0 for k, v in sums.items()} | {"layer": depth, "mode": "bfs"})
        over, depth = ahead * NODE_BYTES > budget, depth + 1
        if checkpoint:
            _save(spark, checkpoint, depth, unfolded, frontier, layers, lists, n_words)
    stage.close()
    entries = lists.rows()
    counted = [x for x in layers if x["layer"] > 0]
    totals = {
        "nodes": sum(x["nodes"] for x in counted), "pairs": sum(x["pairs"] for x in layers), "seconds": time.time() - begun, "mode": mode_now,
        "l_max": max((max(x["layer"], x.get("deepest", 0)) for x in layers), default=0), "l_z": max((u.bit_count() for _, u, _ in entries), default=0), "z": len(entries),
        "flagged": flagged, "rejected": rejected, "left_at_switch": left_at_switch,
    }
    complete = p.most_parents is None and (p.strict or not p.rules)
    return SearchResult(spark, enc.order, enc.arity, entries, layers, totals, complete, p)


def _save(spark: SparkSession, folder: str, depth: int, unfolded: bool, frontier: list | DataFrame, layers: list[dict], lists: Lists, n_words: int) -> None:
    """One table a layer; the marker file that Spark writes last makes it count."""
    names = _names(n_words, "u")
    nodes = _frame(spark, frontier, n_words, 1) if isinstance(frontier, list) and frontier else frontier
    blank = [F.lit(None).cast(k).alias(c) for c, k in (("t", "int"), ("s", "double"))]
    kind = ", ".join(f"{c} long" for c in names + _names(n_words, "x")) + ", t int, s double, note string"
    finds = [(*bitset.split(u, n_words), *[None] * n_words, t, s, None) for t, u, s in lists.rows()]
    note = json.dumps({"depth": depth, "unfolded": unfolded, "layers": layers}, default=float)
    out = spark.createDataFrame([*finds, (*[None] * (2 * n_words), None, None, note)], kind)
    if not isinstance(nodes, list):
        out = out.unionByName(nodes.select("*", *blank, F.lit(None).cast("string").alias("note")))
    out.write.mode("overwrite").parquet(f"{folder}/layer={depth}")


def _resumed(spark: SparkSession, folder: str, n_words: int):
    """What `_save` wrote for the last whole layer, if anything."""
    root = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = root.getFileSystem(spark._jsc.hadoopConfiguration())
    if not fs.exists(root):
        return None
    whole = [x.getPath().getName() for x in fs.listStatus(root) if fs.exists(spark._jvm.org.apache.hadoop.fs.Path(x.getPath(), "_SUCCESS"))]
    if not whole:
        return None
    table = spark.read.parquet(f"{folder}/{max(whole, key=lambda x: int(x.split('=')[1]))}")
    note = json.loads(table.where("note is not null").first()["note"])
    names = _names(n_words, "u")
    finds = [(r["t"], bitset.join(r[c] for c in names), r["s"]) for r in table.where("t is not null").collect()]
    frontier = _collected(table.where(F.col("x0").isNotNull()).select(*names, *_names(n_words, "x")), n_words)
    return note["depth"], note["unfolded"], frontier, note["layers"], finds


def _depth_first(spark, stage: Stage, roots: DataFrame, shared, lists_shared, n_words: int, lists: Lists):
    """Scores the subtrees of all roots; cross-checks the merged finds."""
    counters = ("nodes", "pairs", "scored", "c1", "c2", "deepest")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p, known = shared.value, lists_shared.value
        cells = Cells(p)
        for b in batches:
            cols = [b.column(c).to_pylist() for c in _names(n_words, "u") + _names(n_words, "x")]
            rows = [(bitset.join(row[:n_words]), bitset.join(row[n_words:])) for row in zip(*cols, strict=True)]
            found, seen = kernel.subtree(p, known, rows, cells)
            # The last row has the counters of the batch and no find.
            sets = [bitset.split(u, n_words) for _, u, _ in found] + [[0] * n_words]
            data = [pa.array([s[w] for s in sets], pa.int64()) for w in range(n_words)]
            data += [pa.array([*(t for t, _, _ in found), -1], pa.int32()), pa.array([*(s for *_, s in found), 0.0], pa.float64())]
            data += [pa.array([0] * len(found) + [seen[k]], pa.int64()) for k in counters]
            yield pa.RecordBatch.from_arrays(data, names=[*_names(n_words, "u"), "t", "s", *counters])

    schema = ", ".join(f"{c} long" for c in _names(n_words, "u")) + ", t int, s double, " + ", ".join(f"{c} long" for c in counters)
    out = stage.cut(roots.mapInArrow(run, schema))
    sums = out.agg(*(F.sum(c).alias(c) for c in counters[:-1]), F.max("deepest").alias("deepest"), F.sum((F.col("t") >= 0).cast("long")).alias("found")).first()
    finds = out.where("t >= 0").select(*_names(n_words, "u"), "t", "s")
    known = [(*bitset.split(u, n_words), t, s) for t, u, s in lists.rows()]
    old = spark.createDataFrame(known, ", ".join(f"{c} long" for c in _names(n_words, "u")) + ", t int, s double")
    eps = max(shared.value.eps)
    good = recheck(finds, finds.union(old), n_words, eps)
    kept = [(r["t"], bitset.join(r[f"u{w}"] for w in range(n_words)), r["s"]) for r in good.collect()]
    return kept, (sums["found"] or 0) - len(kept), {k: sums[k] or 0 for k in counters[:-1]} | {"hits": len(kept), "deepest": sums["deepest"] or 0}


def recheck(finds: DataFrame, lists: DataFrame, n_words: int, eps: float) -> DataFrame:
    """Finds that no entry of the same target inside them beats or equals."""
    other = lists.select(*(F.col(f"u{w}").alias(f"v{w}") for w in range(n_words)), F.col("t").alias("vt"), F.col("s").alias("vs"))
    inside = reduce(Column.__and__, (bitset.contains(F.col(f"u{w}"), F.col(f"v{w}")) for w in range(n_words)))
    proper = reduce(Column.__or__, (F.col(f"u{w}") != F.col(f"v{w}") for w in range(n_words)))
    return finds.join(other, (F.col("t") == F.col("vt")) & inside & proper & (F.col("vs") <= F.col("s") + eps), "left_anti")


def find_parent_sets(
    df: DataFrame | None, variables: list[str] | None = None, *, targets: list[str] | None = None, scorer: Score | None = None, prune: tuple[str, ...] = ("c1", "c2"),
    prune_extra: tuple[str, ...] = (), order: str = "arity", ties: str = "strict", mode: str = "auto", dfs_root_layer: int | None = None, memory_budget: int | None = None,
    max_parents: int | None = None, fold_from: int = 0, null_policy: str = "state", backend: str = "auto", encoded: Encoded | None = None,
    checkpoint: str | None = None, weight: str | None = None,
) -> SearchResult:
    """All maximal parent sets of the targets (default: of every column) of a table.

    backend: 'packed' broadcasts the compressed table, 'relational' counts with joins and
    aggregations only, 'auto' takes the first unless the table is too large for it; what the
    second cannot do is then an error, not another answer. `weight` names a column of row counts.
    """
    scorer = scorer or Mdl()
    enc = encoded or encode(df, variables, null_policy, order, weight)
    spark = enc.rows.sparkSession
    chosen = [enc.order.index(t) for t in targets] if targets else None
    if backend == "auto":
        try:
            packed = enc.packed()
        except MemoryError:
            backend = "relational"
    elif backend == "packed":
        packed = enc.packed()
    if backend == "relational":
        from parsieve.operators.relational import search_relational

        asked = {"prune_extra": prune_extra, "dfs_root_layer": dfs_root_layer, "memory_budget": memory_budget, "fold_from": fold_from, "checkpoint": checkpoint, "mode": mode if mode == "dfs" else None}
        if unknown := [k for k, v in asked.items() if v]:
            raise ValueError(f"the relational search has no {', '.join(unknown)}")
        return search_relational(spark, enc, scorer, prune, ties, max_parents, chosen)
    p = kernel.problem(enc, scorer, (*prune, *prune_extra), ties, max_parents, packed)
    return search(spark, enc, p, mode, dfs_root_layer, memory_budget, fold_from, chosen, checkpoint=checkpoint)
