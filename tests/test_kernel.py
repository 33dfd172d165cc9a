"""Kernel, rules and baselines on small tables, without Spark."""

import math

import numpy as np
import pytest

from parsieve.functions import bitset
from parsieve.functions.scores import Aic, Bdeu, Mdl
from parsieve.operators import baselines, kernel, metrics
from parsieve.plans.encode import Encoded, count_log


def encoded(columns: list[list[int]]) -> tuple[Encoded, tuple]:
    rows, w = np.unique(np.array(columns).T, axis=0, return_counts=True)
    arity = [int(max(c)) + 1 for c in columns]
    n, m = len(columns), len(columns[0])

    def logs(chosen):
        return count_log(np.unique(np.array([columns[i] for i in chosen]).T, axis=0, return_counts=True)[1]) if chosen else m * math.log2(m)

    every = list(range(n))
    ent = [logs([]) - logs([i]) for i in every]
    floor = [max(0.0, logs([j for j in every if j != i]) - logs(every)) for i in every]
    return Encoded(None, [f"c{i}" for i in every], arity, {}, m, ent, floor), (rows.T.astype(np.uint8), w.astype(np.int64))


def make(columns, score=None, rules=("c1", "c2"), **kw):
    e, packed = encoded(columns)
    return kernel.problem(e, score or Mdl(), rules, packed=packed, **kw)


@pytest.fixture(scope="module")
def noisy():
    r = np.random.default_rng(5)
    a, b, c = (r.integers(0, k, 600) for k in (3, 2, 2))
    d = (a + b + (r.random(600) < 0.1)) % 3
    e = (b + c + (r.random(600) < 0.05)) % 2
    return [x.tolist() for x in (a, d, b, c, e)]


XOR = [[0, 0, 1, 1] * 100, [0, 1, 0, 1] * 100, [0, 1, 1, 0] * 100]


def test_scores_by_hand():
    p = make([[0, 0, 0, 1, 1, 1], [0, 0, 1, 1, 1, 0]])
    h = 6 * 1.0  # both columns are half and half
    assert p.empty[0] == pytest.approx(h + 0.5 * math.log2(6))
    given = 2 * (3 * math.log2(3) - 2 * math.log2(2))  # two cells of 3 rows: 2 and 1
    assert kernel.Cells(p).score(1, 1, 2.0) == pytest.approx(given + 0.5 * math.log2(6) * 2)
    q = make([[0, 0, 0, 1, 1, 1], [0, 0, 1, 1, 1, 0]], Aic())
    assert q.empty[0] == pytest.approx(h + math.log2(math.e))


def test_bdeu_is_a_probability():
    p = make([[0, 1]], Bdeu())
    # One row of each of two states, prior 1/2 each: 1/2 * (1/2) / 2.
    assert p.empty[0] == pytest.approx(-math.log2(0.125))


@pytest.mark.parametrize("rules", [(), ("c1",), ("c2",), ("c1", "c2"), ("c1", "c2", "early_c1"), ("c1", "c2", "tight_c2")])
def test_rules_lose_nothing(noisy, rules):
    truth = baselines.brute_force(make(noisy))
    got = baselines.sequential(make(noisy, rules=rules))[0].rows()
    assert [(t, u) for t, u, _ in got] == [(t, u) for t, u, _ in truth]
    assert [s for *_, s in got] == pytest.approx([s for *_, s in truth])


def test_condition_one_implies_two(noisy):
    count = lambda rules: baselines.sequential(make(noisy, rules=rules))[1]["nodes"]
    assert count(("c2",)) == count(("c1", "c2"))


def test_no_extra_nodes_under_condition_one_alone(noisy):
    p = make(noisy, rules=("c1",))
    assert baselines.sequential(p)[1]["nodes"] == baselines.synchronised(p)[1]["nodes"]


def test_depth_first_needs_only_the_check_across_roots(noisy):
    p = make(noisy)
    truth = {(t, u) for t, u, _ in baselines.brute_force(p)}
    whole, _ = kernel.subtree(p, kernel.Lists(), [(0, (1 << p.n) - 1)])
    assert {(t, u) for t, u, _ in whole} == truth  # one root: every subset comes first


def test_lists_answer_all_optima(noisy):
    p = make(noisy)
    lists = baselines.sequential(p)[0]
    d = baselines.all_optimal(p)
    assert d == pytest.approx(baselines.depth_first_memo(p))
    for (t, u), best in d.items():
        stored = min(s for v, s in zip(lists.sets[t], lists.scores[t], strict=True) if not v & ~u)
        assert stored == pytest.approx(best)


def test_greedy_misses_parity():
    p = make(XOR)
    u, s = baselines.greedy(p, 2)
    assert u == 0 and s > min(x for t, _, x in baselines.brute_force(p) if t == 2)


def test_constant_and_copied_columns():
    p = make([[0, 1] * 50, [0, 1] * 50, [0] * 100])
    rows = baselines.brute_force(p)
    assert [(t, u) for t, u, _ in baselines.sequential(p)[0].rows()] == [(t, u) for t, u, _ in rows]
    assert [u for t, u, _ in rows if t == 2] == [0]  # nothing explains a constant better


def test_bits():
    assert bitset.members(0b10110) == [1, 2, 4]
    assert bitset.join(bitset.split(1 << 64 | 5, 2)) == 1 << 64 | 5
    assert bitset.names(0b101, ["z", "y", "x"]) == ["x", "z"]


def test_closed_forms():
    assert metrics.unpruned_nodes(56, 8) == 1_689_096_333
    assert metrics.unpruned_nodes(4, 4) == 4 + 6 + 4
    assert metrics.speedup({2: 10.0, 4: 5.0})[1][2:] == (2.0, 1.0)
