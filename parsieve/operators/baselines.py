"""What the search is compared with: other ways to the same lists, and lesser answers."""

from __future__ import annotations

import time
from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from parsieve.functions import bitset
from parsieve.functions.scores import Mdl, Score
from parsieve.operators import kernel
from parsieve.operators.kernel import Cells, Lists, Problem
from parsieve.operators.search import SearchResult, partitions, scored, search
from parsieve.plans.encode import Encoded
from parsieve.plans.staging import Stage


def sequential(p: Problem) -> tuple[Lists, dict]:
    """One process, layer by layer, with the kernel and rules of the distributed search."""
    begun, cells, lists = time.time(), Cells(p), Lists()
    layer, seen = [(0, (1 << p.n) - 1)], {"nodes": 0, "pairs": 0}
    while layer:
        finds, following = [], []
        for u, x in layer:
            hits, go_on, part = kernel.evaluate(p, cells, lists, u, x)
            finds += [(t, u, s) for t, s in hits]
            following += kernel.children(p, u, go_on)
            seen["nodes"] += u > 0
            seen["pairs"] += part["pairs"]
        for t, u, s in finds:
            lists.add(t, u, s)
        layer = sorted(following)
    return lists, seen | {"seconds": time.time() - begun}


def synchronised(p: Problem) -> tuple[Lists, dict]:
    """A child is kept for a target only if every predecessor survives for it: no extra
    nodes, at the price of a grouping of all predecessors' children each layer."""
    cells, lists, nodes = Cells(p), Lists(), 0
    layer = {0: (1 << p.n) - 1}
    while layer:
        finds, survive = [], {}
        for u, x in sorted(layer.items()):
            hits, go_on, _ = kernel.evaluate(p, cells, lists, u, x)
            finds += [(t, u, s) for t, s in hits]
            survive[u] = go_on
            nodes += u > 0
        for t, u, s in finds:
            lists.add(t, u, s)
        layer = {}
        for u, go_on in survive.items():
            for i in range(u.bit_length(), p.n):
                child = u | 1 << i
                mask = go_on & ~child
                for j in bitset.members(u):
                    mask &= survive.get(child & ~(1 << j), 0)
                if mask:
                    layer[child] = mask
    return lists, {"nodes": nodes}


def synchronised_table(layer: DataFrame, p_n: int) -> DataFrame:
    """The same rule as a DataFrame: children from every predecessor of a scored layer
    (u0, y0), kept where all size(u) of them came, with the masks' intersection."""
    new = F.explode(F.sequence(F.lit(0), F.lit(p_n - 1))).alias("new")
    one = bitset.bit(0, F.col("new"), p_n)
    grown = layer.select("u0", "y0", new).where(F.col("u0").bitwiseAND(one) == 0)
    grown = grown.select(F.col("u0").bitwiseOR(one).alias("v"), F.col("y0").bitwiseAND(F.bitwise_not(one)).alias("y"))
    both = grown.groupBy("v").agg(F.bit_and("y").alias("x0"), F.count(F.lit(1)).alias("c"))
    return both.where((F.col("c") == F.bit_count("v")) & (F.col("x0") != 0)).select(F.col("v").alias("u0"), "x0")


def synchronised_nodes(spark: SparkSession, p: Problem, factor: int = 4) -> int:
    """Nodes of the synchronised search, run as tables of up to 63 columns: each layer is scored by the
    search's own Arrow stage and grouped over all predecessors before the next."""
    if p.n > bitset.WORD:
        raise ValueError(f"up to {bitset.WORD} columns")
    shared, stage, lists, total = spark.sparkContext.broadcast(p), Stage(spark), Lists(), 0
    layer, depth, behind = spark.createDataFrame([(0, (1 << p.n) - 1)], "u0 long, x0 long"), 0, None
    while True:
        known = spark.sparkContext.broadcast(lists)
        done = stage.cut(scored(layer, shared, known, 1))
        stage.drop(behind)
        behind = done
        hits = done.select("u0", F.explode("hits").alias("h")).select("u0", "h.t", "h.s").collect()  # parent sets of one layer
        for h in hits:
            lists.add(h["t"], h["u0"], h["s"])
        count, alive = done.agg(F.count(F.lit(1)), F.sum((F.col("y0") != 0).cast("long"))).first()
        total += count if depth else 0
        known.unpersist()
        if not alive:
            stage.close()
            return total
        layer = synchronised_table(done.where("y0 <> 0"), p.n)
        layer = layer.repartitionByRange(partitions(spark, alive, factor), "u0").sortWithinPartitions("u0")
        depth += 1


def unfolded(spark: SparkSession, enc: Encoded, p: Problem) -> SearchResult:
    """A lattice per target: rows are never folded."""
    return search(spark, enc, p, "bfs", fold_from=10**9)


def all_optimal(p: Problem) -> dict[tuple[int, int], float]:
    """The optimum of every (target, set), by recursion over ever larger sets."""
    cells, d = Cells(p), {}
    for u in sorted(range(1 << p.n), key=lambda v: (v.bit_count(), v)):
        q = kernel.product(p, u)
        for t in range(p.n):
            if not u >> t & 1:
                own = cells.score(t, u, q) if u else p.empty[t]
                d[t, u] = min([own, *(d[t, u & ~(1 << i)] for i in bitset.members(u))])
    return d


def depth_first_memo(p: Problem) -> dict[tuple[int, int], float]:
    """Depth-first over sets, holding the optima of sets whose supersets are not done."""
    cells, d = Cells(p), {}

    def visit(t: int, u: int) -> float:
        if (t, u) not in d:
            own = cells.score(t, u, kernel.product(p, u)) if u else p.empty[t]
            d[t, u] = min([own, *(visit(t, u & ~(1 << i)) for i in bitset.members(u))])
        return d[t, u]

    full = (1 << p.n) - 1
    for t in range(p.n):
        visit(t, full & ~(1 << t))
    return d


def brute_force(p: Problem) -> list[tuple[int, int, float]]:
    """Maximal parent sets straight from their definition over the power set."""
    cells, out = Cells(p), []
    for t in range(p.n):
        scores = {}
        others = [i for i in range(p.n) if i != t]
        for k in range(len(others) + 1):
            for c in combinations(others, k):
                u = sum(1 << i for i in c)
                scores[u] = cells.score(t, u, kernel.product(p, u)) if u else p.empty[t]
        best: dict[int, float] = {}
        for u in scores:  # by rising size: all smaller sets are there
            below = min((best[u & ~(1 << i)] for i in bitset.members(u)), default=float("inf"))
            better = scores[u] < below - p.eps[t] if p.strict else scores[u] <= below + p.eps[t]
            if better:
                out.append((t, u, scores[u]))
            best[u] = min(below, scores[u])
    return sorted(out)


def greedy(p: Problem, t: int) -> tuple[int, float]:
    """Forward selection: no guarantee, misses parents that help only together."""
    cells, u, s = Cells(p), 0, p.empty[t]
    while True:
        tries = [(cells.score(t, v, kernel.product(p, v)), v) for i in range(p.n) if i != t and not u >> i & 1 for v in [u | 1 << i]]
        if not tries or min(tries)[0] >= s - p.eps[t]:
            return u, s
        s, u = min(tries)


def greedy_table(spark: SparkSession, enc: Encoded, result: SearchResult, score: Score | None = None) -> DataFrame:
    """target, greedy and exact best score, and how much is lost."""
    p = kernel.problem(enc, score or Mdl())
    rows = []
    for t, name in enumerate(enc.order):
        u, s = greedy(p, t)
        exact = min(x for k, _, x in result.entries if k == t)
        rows.append((name, "+".join(bitset.names(u, enc.order)), float(s), float(exact), float(s - exact)))
    return spark.createDataFrame(rows, "target string, greedy_parents string, greedy_score double, exact_score double, lost double")
