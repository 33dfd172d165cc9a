"""Scores of a parent set from counts: bits to describe the target, lower is better.

`fit` bits come from count-log sums C(S) = sum of c * log2 c over the cells of S:
m * H(t | U) = C(U) - C(U + t). A score with a penalty that grows with the number q of
parent states and needs no counts allows exact pruning; one without does not.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass
from functools import cache

import numpy as np
from pyspark import cloudpickle
from pyspark.sql import Column
from pyspark.sql import functions as F


class Score:
    monotone = True  # the score is a fit and a penalty that is free of counts and grows with q
    bounded = True  # `penalty` is a lower bound of the score that grows with q

    def penalty(self, q: float, r: int, m: float) -> float:
        raise NotImplementedError

    def penalty_column(self, q: Column, r: Column, m: float) -> Column:
        raise NotImplementedError


@dataclass(frozen=True)
class Mdl(Score):
    """Half of log2 m for each free parameter."""

    def penalty(self, q: float, r: int, m: float) -> float:
        return 0.5 * math.log2(m) * q * (r - 1) if m > 0 else 0.0

    def penalty_column(self, q: Column, r: Column, m: float) -> Column:
        return F.lit(0.5 * math.log2(m) if m > 0 else 0.0) * q * (r - 1)


Bic = Mdl


@dataclass(frozen=True)
class Aic(Score):
    """One nat for each free parameter, in bits."""

    def penalty(self, q: float, r: int, m: float) -> float:
        return q * (r - 1) * math.log2(math.e)

    def penalty_column(self, q: Column, r: Column, m: float) -> Column:
        return q * (r - 1) * F.lit(math.log2(math.e))


@dataclass(frozen=True)
class Bdeu(Score):
    """-log2 of the Bayesian Dirichlet marginal likelihood with equal prior shares."""

    ess: float = 1.0
    monotone = bounded = False

    def cells(self, parent: np.ndarray, joint: np.ndarray, q: float, r: int) -> float:
        """From the counts of parent cells and of (parent, target) cells, zeros left out."""
        a, b = self.ess / q, self.ess / (q * r)
        lg = np.vectorize(math.lgamma, otypes=[float])
        nats = (lg(a + parent) - math.lgamma(a)).sum() - (lg(b + joint) - math.lgamma(b)).sum()
        return float(nats / math.log(2))


@cache
def _regret(n: int, r: int) -> float:
    """log2 of the sum of all maximum likelihoods of n draws from r states."""
    if r <= 1 or n == 0:
        return 0.0
    if n <= 1000:
        h = np.arange(n + 1)
        logs = np.array([math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1) for k in h])
        part = lambda k: k * np.log(np.maximum(k, 1) / n)
        two = float(np.exp(logs + part(h) + part(n - h)).sum())
    else:  # asymptotic in n, below a 10^-4 off from here on
        two = math.sqrt(math.pi * n / 2) + 2 / 3 + math.sqrt(2 * math.pi) / (24 * math.sqrt(n))
    below, now = 1.0, two
    for k in range(1, r - 1):
        below, now = now, now + n / k * below
    return math.log2(now)


@dataclass(frozen=True)
class Fnml(Score):
    """Factorised normalised maximum likelihood: the regret of every parent cell instead of
    a penalty by the number of parameters."""

    monotone = bounded = False

    def cells(self, parent: np.ndarray, joint: np.ndarray, q: float, r: int) -> float:
        fit = float((parent * np.log2(parent)).sum() - (joint * np.log2(joint)).sum())
        sizes, times = np.unique(parent.astype(np.int64), return_counts=True)
        return fit + sum(k * _regret(int(n), r) for n, k in zip(sizes, times, strict=True))


@dataclass(frozen=True)
class Custom(Score):
    """A function of (parent counts, joint counts, q, r). With `bound` (q, r, m), a lower bound of
    the score that grows with q, Condition 1 prunes exactly; without, nothing is pruned."""

    fn: Callable[[np.ndarray, np.ndarray, float, int], float]
    bound: Callable[[float, int, float], float] | None = None
    monotone = False

    @property
    def bounded(self) -> bool:
        return self.bound is not None

    def __reduce__(self):
        return _unpacked, (cloudpickle.dumps((self.fn, self.bound)),)  # functions of any kind travel to the tasks

    def penalty(self, q: float, r: int, m: float) -> float:
        return self.bound(q, r, m)

    def cells(self, parent: np.ndarray, joint: np.ndarray, q: float, r: int) -> float:
        return self.fn(parent, joint, q, r)


def _unpacked(data: bytes) -> Custom:
    return Custom(*cloudpickle.loads(data))


def entropy_bits(counts: np.ndarray) -> float:
    """Entropy of a table of counts, times its total."""
    c = counts[counts > 0].astype(float)
    return float(c.sum() * np.log2(c.sum()) - (c * np.log2(c)).sum()) if len(c) else 0.0
