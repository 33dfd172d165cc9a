"""Cost measures: search-space shares, extra work, speed-up, memory bounds, balance."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from parsieve.operators.search import NODE_BYTES, SearchResult


def unpruned_nodes(n: int, deepest: int) -> int:
    """Sets of 1 to `deepest` of n columns; the full set has no target."""
    return sum(math.comb(n, k) for k in range(1, min(deepest, n - 1) + 1))


def extra_work(nodes: int, synchronised: int) -> float:
    """Per cent of nodes beyond the synchronised run."""
    return 100 * (nodes - synchronised) / synchronised if synchronised else 0.0


def removed_share(nodes: int, synchronised: int, unpruned: int) -> float:
    """Per cent of all prunable nodes that were not visited."""
    return 100 * (unpruned - nodes) / (unpruned - synchronised) if unpruned > synchronised else 100.0


def speedup(times: dict[int, float]) -> list[tuple[int, float, float, float]]:
    """(workers, seconds, speed-up over the fewest workers, efficiency)."""
    base = min(times)
    return [(p, t, times[base] / t, times[base] / t * base / p) for p, t in sorted(times.items())]


def fold_bounds(view: DataFrame) -> DataFrame:
    """Per layer of the lattice over the columns of the view that take several values: rows with
    one lattice per target and with folding, and the ratio of their bytes (a row of the former
    needs one word, of the latter two)."""
    spread = view.agg(*((F.min(c) < F.max(c)).cast("int").alias(c) for c in view.columns)).first()
    n = sum(x or 0 for x in spread)
    rows = [(k, n * math.comb(n - 1, k), math.comb(n, k), n * math.comb(n - 1, k) / (2 * math.comb(n, k))) for k in range(n)]
    return view.sparkSession.createDataFrame(rows, "layer int, unfolded_rows long, folded_rows long, ratio double")


def shared_gain(scored: int, nodes: int) -> float:
    """How many times fewer countings there are if the targets of a node share that of the
    node's set: one and one a target, in place of two a target."""
    return 2 * scored / (scored + nodes) if scored + nodes else 1.0


def layer_bytes(result: SearchResult) -> list[int]:
    return [x["nodes"] * NODE_BYTES for x in result.layers]


def report(result: SearchResult, synchronised: int | None = None) -> dict:
    t = result.totals
    n = len(result.order)
    full = unpruned_nodes(n, t["l_max"])
    out = dict(t) | {"unpruned": full, "share_percent": 100 * t["nodes"] / full if full else 0.0, "nodes_per_second": t["nodes"] / max(t["seconds"], 1e-9)}
    out["shared_gain"] = shared_gain(sum(x["scored"] for x in result.layers), t["nodes"])
    out["peak_bytes"] = max(layer_bytes(result), default=0)
    lists: dict[int, int] = {}
    for k, *_ in result.entries:
        lists[k] = lists.get(k, 0) + 1
    out |= {"list_min": min(lists.values(), default=0), "list_max": max(lists.values(), default=0)}
    if synchronised is not None:
        out |= {"sync_nodes": synchronised, "extra_percent": extra_work(t["nodes"], synchronised), "removed_percent": removed_share(t["nodes"], synchronised, full)}
    return out
