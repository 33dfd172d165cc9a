"""Scoring of lattice nodes against a packed table: one node, all targets of its mask."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from functools import cache, reduce
from itertools import combinations
from math import comb

import numpy as np

from parsieve.functions.bitset import members
from parsieve.functions.scores import Score
from parsieve.plans.encode import Encoded

DENSE = 1 << 22
TABLED = 1 << 20  # counts below this have their c * log2 c in a table
BLOCK = 1 << 18  # cells and rows that one pass over several targets may take
TOGETHER = 4  # sets whose union has at most so many cells a row are summed out of one table of them
TRIED = 512  # subsets of a union that may be looked up for one more column
SPARSE = 6  # a set of more cells a row than this is counted by sorting


@dataclass
class Problem:
    """What every task needs: packed codes, weights, facts and rules. Sent by broadcast."""

    codes: np.ndarray
    weights: np.ndarray
    arity: list[int]
    m: int
    empty: list[float]  # score of the empty set by target
    floor: list[float]
    score: Score
    rules: frozenset[str]
    eps: list[float]
    strict: bool = True
    most_parents: int | None = None

    @property
    def n(self) -> int:
        return len(self.arity)


def problem(enc: Encoded, score: Score, rules: tuple[str, ...] = ("c1", "c2"), ties: str = "strict", most_parents: int | None = None, packed=None) -> Problem:
    if not score.monotone:  # Condition 2 needs a fit that can be told from the penalty
        rules = tuple(r for r in rules if score.bounded and r in ("c1", "early_c1"))
    codes, weights = packed if packed is not None else enc.packed()
    p = Problem(codes, weights, enc.arity, enc.m, [], enc.floor, score, frozenset(rules), [], ties == "strict", most_parents)
    p.empty = [Cells(p).score(t, 0, 1.0) if not score.monotone else enc.entropy[t] + score.penalty(1, enc.arity[t], enc.m) for t in range(p.n)]
    p.eps = [max(1e-6, 1e-12 * abs(s)) for s in p.empty]
    return p


@cache
def _log_table(m: int) -> np.ndarray:
    """c * log2 c of the counts that m rows can have, up to TABLED."""
    c = np.arange(min(m, TABLED) + 1, dtype=float)
    return c * np.log2(np.maximum(c, 1))


class Cells:
    """Cell numbers of the rows under a set of columns, kept for every prefix of the last
    set asked for, so that neighbours in sorted order share the work."""

    def __init__(self, p: Problem):
        self.p = p
        self.path: list[tuple[int, np.ndarray, int, float | None]] = []
        self.bare: list[tuple[int, np.ndarray, int]] = []  # as `path`, of `numbered`
        self.first, self.codes, self.heavy = None, p.codes, p.weights.astype(float)  # rows by their code in column `first`
        self.table = _log_table(p.m)
        self.even = bool((p.weights == 1).all())  # no row occurs twice: weights can stay out

    def of(self, u: int) -> tuple[np.ndarray, int]:
        wanted = members(u)
        keep = 0
        while keep < len(self.path) and keep < len(wanted) and self.path[keep][0] == wanted[keep]:
            keep += 1
        del self.path[keep:]
        for position in wanted[keep:]:
            cell, size = (self.path[-1][1], self.path[-1][2]) if self.path else (np.zeros(self.p.codes.shape[1], np.int32), 1)
            r = self.p.arity[position]
            size *= r
            cell = np.multiply(cell, r, dtype=np.int32 if size < 1 << 31 else np.int64)
            cell += self.p.codes[position]
            if size > max(1024, 2 * len(cell)):
                found, cell = np.unique(cell, return_inverse=True)
                size, cell = len(found), cell.astype(np.int32)
            self.path.append((position, cell, size, None))
        return (self.path[-1][1], self.path[-1][2]) if self.path else (np.zeros(self.p.codes.shape[1], np.int64), 1)

    def _sort(self, first: int) -> None:
        """Sorts the rows by column `first` and those behind it, as far as a short sorting key goes."""
        key, size = np.zeros(self.p.codes.shape[1], np.uint16), 1
        for i in range(first, self.p.n):
            if size * self.p.arity[i] >= 1 << 16:
                break
            key, size = key * np.uint16(self.p.arity[i]) + self.p.codes[i].astype(np.uint16), size * self.p.arity[i]
        place = np.argsort(key, kind="stable")
        self.first, self.codes, self.heavy, self.bare = first, np.take(self.p.codes, place, axis=1), self.p.weights[place].astype(float), []

    def numbered(self, u: int) -> tuple[np.ndarray, int, list[int]]:
        """Cell numbers as `of`, but all possible cells have one, and the columns, the fastest first.
        The slowest are the two that the rows are sorted by, so that counting stays in one place."""
        wanted = members(u)
        if wanted[0] != self.first:
            self._sort(wanted[0])
        wanted = wanted[2:] + wanted[1::-1]
        keep = 0
        while keep < len(self.bare) and keep < len(wanted) and self.bare[keep][0] == wanted[keep]:
            keep += 1
        del self.bare[keep:]
        cell, size = self.bare[-1][1:] if self.bare else (0, 1)
        for i in wanted[keep:]:
            r = self.p.arity[i]
            if size * r >= 1 << 62:
                found, cell = np.unique(cell, return_inverse=True)
                size = len(found)
            more = self.codes[i].astype(np.int32 if size * r < 1 << 31 else np.int64)
            more *= size
            more += cell
            cell, size = more, size * r
            self.bare.append((i, cell, size))
        return cell, size, wanted

    def log_sum(self, u: int) -> float:
        """Sum of c * log2 c over the cells of u, which gives m * H(t | u) for all targets t in turn."""
        cell, size, _ = self.numbered(u)
        counts = self._tally(cell, size, self.heavy) if size <= max(1024, SPARSE * len(cell)) else self._runs(cell, size)
        return float(self._logs(counts).sum())

    def _runs(self, cell: np.ndarray, size: int) -> np.ndarray:
        """The counts of the cells that occur, by sorting."""
        bits = 0 if self.even else int(self.p.weights.max()).bit_length()
        if size << bits < 1 << 62:  # a weight goes with its cell in one number
            key = np.sort(cell if self.even else (cell.astype(np.int64) << bits) | self.heavy.astype(np.int64))
            weights, key = key & (1 << bits) - 1, key >> bits
        else:
            place = np.argsort(cell)
            weights, key = self.heavy[place], cell[place]
        first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        return np.diff(first, append=len(key)) if self.even else np.add.reduceat(weights, first)

    def summed(self, union: int, sets: set[int]) -> Iterator[tuple[int, float]]:
        """(set, log sum) of subsets of a union, from one table of the union's cells."""
        cell, size, columns = self.numbered(union)
        table = self._tally(cell, size, self.heavy)
        yield from self._summed(table.astype(np.int32 if self.p.m < 1 << 31 else np.int64), columns, sets)

    def _summed(self, table: np.ndarray, columns: list[int], sets: set[int]) -> Iterator[tuple[int, float]]:
        whole = sum(1 << i for i in columns)
        if whole in sets:
            yield whole, float(self._logs(table).sum())
        rest, below = sets - {whole}, 1
        for place, i in enumerate(columns):
            r = self.p.arity[i]
            if lacking := {u for u in rest if not u >> i & 1}:
                rest = rest - lacking
                split = table.reshape(-1, r, below)
                if below >= 64:
                    fewer = split.sum(axis=1, dtype=table.dtype)
                else:  # short runs of numbers are added faster a state at a time
                    fewer = split[:, 0].copy()
                    for state in range(1, r):
                        fewer += split[:, state]
                yield from self._summed(fewer.ravel(), columns[:place] + columns[place + 1 :], lacking)
            below *= r

    def counts(self, u: int) -> np.ndarray:
        cell, size = self.of(u)
        return np.bincount(cell, weights=self.p.weights, minlength=size)

    def joint(self, u: int, t: int) -> np.ndarray:
        cell, size = self.of(u)
        r = self.p.arity[t]
        key = cell.astype(np.int64) * r + self.p.codes[t]
        if size * r <= DENSE:
            return np.bincount(key, weights=self.p.weights, minlength=size * r)
        return np.bincount(np.unique(key, return_inverse=True)[1], weights=self.p.weights)

    def _tally(self, key: np.ndarray, size: int, weights: np.ndarray | None = None) -> np.ndarray:
        if self.even:
            return np.bincount(key, minlength=size)
        return np.bincount(key, weights=self.p.weights if weights is None else weights, minlength=size)

    def _logs(self, counts: np.ndarray) -> np.ndarray:
        """c * log2 c of each count."""
        counts, last = counts.astype(np.intp, copy=False), len(self.table) - 1
        if self.p.m <= last:
            return self.table[counts]
        out = self.table[np.minimum(counts, last)]
        large = np.flatnonzero(counts > last)
        out[large] = counts[large] * np.log2(counts[large])
        return out

    def fits(self, u: int, targets: list[int]) -> list[float]:
        """m * H(t | u) of all targets: as many as fit into a block take one pass."""
        cell, size = self.of(u)
        own = float(self._logs(self._tally(cell, size)).sum())
        out, arity = [], self.p.arity
        while targets:
            taken = room = 0
            for t in targets:
                room += max(size * arity[t], len(cell))
                if taken and room > BLOCK:
                    break
                taken += 1
            part, targets = targets[:taken], targets[taken:]
            if taken == 1:
                out.append(own - float(self._logs(self.joint(u, part[0])).sum()))
                continue
            r = np.array([arity[t] for t in part], np.int64)
            first = np.concatenate([[0], np.cumsum(size * r)])
            key = cell[None, :] * r[:, None] + self.p.codes[part] + first[:-1, None]
            logs = self._logs(self._tally(key.ravel(), int(first[-1]), np.tile(self.p.weights, taken)))
            out += (own - np.add.reduceat(logs, first[:-1])).tolist()
        return out

    def score(self, t: int, u: int, q: float, parent: tuple[np.ndarray, float] | None = None) -> float:
        p = self.p
        counts, logs = parent or (self.counts(u), None)
        if p.score.monotone:
            return self.fits(u, [t])[0] + p.score.penalty(q, p.arity[t], p.m)
        joint = self.joint(u, t)
        return p.score.cells(counts[counts > 0], joint[joint > 0], q, p.arity[t])


@dataclass
class Lists:
    """Maximal parent sets by target, ascending by score: first contained entry is best."""

    sets: dict[int, list[int]] = field(default_factory=dict)
    scores: dict[int, list[float]] = field(default_factory=dict)
    compared: int = 0

    def add(self, t: int, u: int, s: float) -> None:
        import bisect

        scores = self.scores.setdefault(t, [])
        at = bisect.bisect_right(scores, s)
        scores.insert(at, s)
        self.sets.setdefault(t, []).insert(at, u)

    def best(self, t: int, u: int) -> float:
        """Least score over the stored proper subsets of u."""
        outside = ~u
        for i, v in enumerate(self.sets.get(t, ())):
            if not v & outside and v != u:
                self.compared += i + 1
                return self.scores[t][i]
        return float("inf")

    def rows(self) -> list[tuple[int, int, float]]:
        return sorted((t, u, s) for t, v in self.sets.items() for u, s in zip(v, self.scores[t], strict=True))


@dataclass
class Overlay(Lists):
    """Lists of one subtree on top of those that all subtrees share."""

    below: Lists = field(default_factory=Lists)

    def best(self, t: int, u: int) -> float:
        return min(super().best(t, u), self.below.best(t, u))


@dataclass
class Known:
    """Log sums by set, from which fits follow: m * H(t | u) is that of u less that of u and t."""

    logs: dict[int, float]

    def fits(self, u: int, targets: list[int]) -> list[float]:
        own = self.logs[u]
        return [own - self.logs[u | 1 << t] for t in targets]


def product(p: Problem, u: int) -> float:
    q = 1.0
    for i in members(u):
        q *= p.arity[i]
    return q


def _to_score(p: Problem, u: int, targets: list[int]) -> tuple[float, dict[int, float], set[int], list[int]]:
    """The number of parent states, the penalties, the targets that Condition 1 ends, and those to score."""
    q = product(p, u)
    fine = {t: p.score.penalty(q, p.arity[t], p.m) if p.score.bounded else 0.0 for t in targets}
    ended = {t for t in targets if "c1" in p.rules and fine[t] >= p.empty[t] - p.eps[t]}
    return q, fine, ended, [t for t in targets if not u or t not in ended]


def sets_to_count(p: Problem, nodes: list[tuple[int, int]]) -> set[int]:
    """The sets whose log sums `evaluate` needs for nodes (u, x). A set of k + 1 columns serves
    up to k + 1 pairs of a node and a target."""
    out = set()
    for u, x in nodes:
        if u and (wanted := _to_score(p, u, members(x))[3]):
            out.add(u)
            out.update(u | 1 << t for t in wanted)
    return out


def in_order(p: Problem, sets: Iterable[int]) -> list[int]:
    """Sets with the same first columns next to each other."""
    return sorted(sets, key=lambda u: f"{u:0{p.n}b}"[::-1], reverse=True)


def neighbours(p: Problem, sets: Iterable[int]) -> list[list[int]]:
    """The sets in groups whose unions have few cells. A group starts from a set and takes, while
    the union stays small, the column that brings in the most sets for its number of states."""
    most = max(256, TOGETHER * p.codes.shape[1])
    ordered, out = in_order(p, sets), []
    left = set(ordered)
    for u in ordered:
        if u not in left:
            continue
        size, union, group = product(p, u), u, {u}
        while comb(union.bit_count(), union.bit_count() + 1 - u.bit_count()) <= TRIED:
            best, gain = None, 0.0
            for i in range(p.n):
                if union >> i & 1 or size * p.arity[i] > most:
                    continue
                more = _inside(union, i, union.bit_count() + 1 - u.bit_count(), left)
                if len(more) > gain * p.arity[i]:
                    best, gain = (i, more), len(more) / p.arity[i]
            if best is None:
                break
            union, size = union | 1 << best[0], size * p.arity[best[0]]
            group.update(best[1])
        left -= group
        out.append(in_order(p, group))
    return sorted(out, key=lambda g: members(reduce(int.__or__, g)))


def _inside(union: int, new: int, fewer: int, left: set[int]) -> list[int]:
    """Of the sets left those of column `new` and all but `fewer` columns of the union."""
    whole = union | 1 << new
    found = (whole & ~sum(1 << i for i in out) for out in combinations(members(union), fewer))
    return [u for u in found if u in left]


def log_sums(cells: Cells, group: list[int]) -> Iterator[tuple[int, float]]:
    """(set, log sum) of one group of `neighbours`."""
    if len(group) == 1:
        yield group[0], cells.log_sum(group[0])
    else:
        yield from cells.summed(reduce(int.__or__, group), set(group))


def evaluate(p: Problem, cells: Cells | Known, lists: Lists, u: int, x: int) -> tuple[list[tuple[int, float]], int, dict[str, int]]:
    """New entries (target, score) of node (x, u), the targets that go on above u, and
    counters. Targets that Condition 1 ends are not scored: the penalty alone is no
    better than the empty set."""
    hits, go_on = [], 0
    seen = {"pairs": 0, "scored": 0, "c1": 0, "c2": 0}
    smallest = min((p.arity[i] for i in range(p.n) if not u >> i & 1), default=1) if "tight_c2" in p.rules else 1
    targets = members(x)
    q, fine, ended, wanted = _to_score(p, u, targets)
    seen["pairs"] = len(targets)
    if not u:
        scores = {t: p.empty[t] for t in wanted}
    elif p.score.monotone:
        scores = {t: fit + fine[t] for t, fit in zip(wanted, cells.fits(u, wanted), strict=True)} if wanted else {}
    else:
        parent = (cells.counts(u), None) if wanted else None
        scores = {t: cells.score(t, u, q, parent) for t in wanted}
    if u:
        seen["c1"], seen["scored"] = len(targets) - len(wanted), len(wanted)
    for t in wanted:
        s, d = scores[t], lists.best(t, u) if u else float("inf")
        if (s < d - p.eps[t]) if p.strict else (s <= d + p.eps[t]):
            hits.append((t, s))
        d = min(d, s)
        if t in ended:
            seen["c1"] += 1
        elif "c2" in p.rules and d <= p.floor[t] + fine[t] * max(1, smallest) + p.eps[t]:
            seen["c2"] += 1
        else:
            go_on |= 1 << t
    if p.most_parents is not None and len(members(u)) >= p.most_parents:
        go_on = 0
    return hits, go_on, seen


def children(p: Problem, u: int, go_on: int) -> list[tuple[int, int]]:
    """Nodes whose chosen predecessor is u, by ascending new column; targets that early
    Condition 1 would end at once are left out if that rule is on."""
    out = []
    for i in range(u.bit_length(), p.n):
        x = go_on & ~(1 << i)
        if "early_c1" in p.rules:
            q = product(p, u) * p.arity[i]
            for t in members(x):
                if p.score.penalty(q, p.arity[t], p.m) >= p.empty[t] - p.eps[t]:
                    x &= ~(1 << t)
        if x:
            out.append((u | 1 << i, x))
    return out


def subtree(p: Problem, lists: Lists, roots: list[tuple[int, int]], cells: Cells | None = None) -> tuple[list[tuple[int, int, float]], dict[str, int]]:
    """Depth-first search below each root with finds of its own on top of `lists`. Siblings
    go by falling column, so a subset that the same root visits always comes before its
    supersets. Cells are shared by all roots."""
    cells, found = cells or Cells(p), []
    seen = {"nodes": 0, "pairs": 0, "scored": 0, "c1": 0, "c2": 0, "deepest": 0}
    for root in roots:
        own, stack = Overlay(below=lists), [root]
        while stack:
            u, x = stack.pop()
            hits, go_on, part = evaluate(p, cells, own, u, x)
            seen["nodes"] += 1
            seen["deepest"] = max(seen["deepest"], u.bit_count())
            for k, v in part.items():
                seen[k] += v
            for t, s in hits:
                own.add(t, u, s)
                found.append((t, u, s))
            stack += children(p, u, go_on)
    return found, seen
