"""Layers whose sets are counted once for all targets, against nodes scored one by one."""

import math
import random

import numpy as np
import pytest

from parsieve.functions.scores import Mdl
from parsieve.operators import kernel, search
from parsieve.operators.search import find_parent_sets
from parsieve.plans.encode import encode


@pytest.fixture(scope="module")
def table(spark):
    rng = random.Random(11)
    rows = []
    for _ in range(3000):
        a, b, c = rng.randrange(7), rng.randrange(4), rng.randrange(3)
        rows.append((a, b, c, (a + b) % 5 if rng.random() < 0.9 else rng.randrange(5), (b ^ c) if rng.random() < 0.8 else rng.randrange(4), rng.randrange(2)))
    return spark.createDataFrame(rows, "a int, b int, c int, d int, e int, f int")


def test_sets_are_counted_once(table, monkeypatch):
    plain = find_parent_sets(table)
    asked = []
    whole = search._log_sums
    monkeypatch.setattr(search, "_log_sums", lambda s, b, p, sets, *a: asked.extend(sets) or whole(s, b, p, sets, *a))
    monkeypatch.setattr(search, "COUNTED_ROWS", 1)
    got = find_parent_sets(table)
    assert [(t, u) for t, u, _ in got.entries] == [(t, u) for t, u, _ in plain.entries] and got.totals["l_z"] >= 2
    assert [s for *_, s in got.entries] == pytest.approx([s for *_, s in plain.entries])
    counters = lambda r: [(x["layer"], x["nodes"], x["pairs"], x["scored"], x["c1"], x["c2"], x["hits"]) for x in r.layers]
    assert counters(got) == counters(plain)
    assert len(asked) == len(set(asked)) < sum(x["scored"] for x in got.layers)


def test_log_sums_of_neighbours(table):
    p = kernel.problem(encode(table), Mdl())
    sets = list(range(1, 1 << p.n))
    groups = kernel.neighbours(p, sets)
    assert sorted(u for g in groups for u in g) == sets and len(groups) < len(sets)
    rows = p.codes.T.astype(int)
    cells = kernel.Cells(p)
    for g in groups:
        for u, got in kernel.log_sums(cells, g):
            chosen = [i for i in range(p.n) if u >> i & 1]
            place = np.unique(rows[:, chosen], axis=0, return_inverse=True)[1].ravel()
            c = np.bincount(place, weights=p.weights)
            assert got == pytest.approx((c * np.log2(c)).sum())


def test_facts_of_a_larger_table_from_its_codes(table, monkeypatch):
    from parsieve.plans import encode as module

    few = encode(table)
    monkeypatch.setattr(module, "LOCAL_ROWS", 10)
    many = encode(table)
    monkeypatch.setattr(module, "_spark_facts", None)
    assert many.local is not None and encode(table).floor == pytest.approx(few.floor)
    assert (many.order, many.arity, many.m) == (few.order, few.arity, few.m) and many.entropy == pytest.approx(few.entropy)


def test_many_sets_from_one_count_of_the_rows(table, monkeypatch):
    p = kernel.problem(encode(table), Mdl())
    sets = [u for u in range(1, 1 << p.n) if u.bit_count() == 3]
    tallied = []
    plain = kernel.Cells._tally
    monkeypatch.setattr(kernel.Cells, "_tally", lambda self, key, *a: tallied.append(len(key) == p.codes.shape[1]) or plain(self, key, *a))
    groups = kernel.neighbours(p, sets)
    cells = kernel.Cells(p)
    got = dict(x for g in groups for x in kernel.log_sums(cells, g))
    assert sorted(got) == sorted(sets) and sum(tallied) <= len(sets) // 4  # before: 10 counts for the 20 sets


@pytest.mark.parametrize("weight", [1, 3])
def test_sparse_sets_are_counted_by_sorting(table, monkeypatch, weight):
    monkeypatch.setattr(kernel, "SPARSE", 0)
    p = kernel.problem(encode(table), Mdl())
    p.weights = np.full(p.codes.shape[1], 1, np.int64) if weight == 1 else np.arange(p.codes.shape[1], dtype=np.int64) % 7 + 1
    u = (1 << p.n) - 1
    monkeypatch.setattr(kernel, "TABLED", 3)
    kernel._log_table.cache_clear()
    c = p.weights[p.weights > 0].astype(float)
    assert kernel.Cells(p).log_sum(u) == pytest.approx((c * np.log2(c)).sum())
    kernel._log_table.cache_clear()


def test_a_larger_table_is_coded_by_tasks(spark, monkeypatch):
    from parsieve.plans import encode as module

    rows = [(i % 5 if i % 7 else None, f"k{i % 3}", i % 2 == 0, -0.0 if i % 4 else 0.5) for i in range(400)]
    df = spark.createDataFrame(rows, "a int, b string, c boolean, d double")
    few = encode(df)
    monkeypatch.setattr(module, "LOCAL_ROWS", 10)
    monkeypatch.setattr(module, "_listed_states", None)  # before: sketches of the numbers of states
    many = encode(df)
    assert (many.order, many.arity, many.labels, many.m) == (few.order, few.arity, few.labels, few.m)
    assert sorted(map(tuple, many.rows.collect())) == sorted(map(tuple, few.rows.collect()))
    monkeypatch.setattr(module, "MOST_STATES", 4)
    with pytest.raises(ValueError, match="more than 4 states"):
        encode(df)
    with pytest.raises(ValueError, match="nulls"):
        encode(df, null_policy="error")


def test_groups_of_a_wide_table_are_found_soon(monkeypatch):
    p = kernel.Problem(np.zeros((40, 1 << 19), np.uint8), np.ones(1 << 19, np.int64), [2] * 40, 1 << 19, [], [], Mdl(), frozenset(), [])
    rng = random.Random(3)
    sets = {sum(1 << i for i in rng.sample(range(40), 10)) for _ in range(100)}
    asked = []
    plain = kernel._inside
    monkeypatch.setattr(kernel, "_inside", lambda union, new, fewer, left: asked.append(math.comb(union.bit_count(), fewer)) or plain(union, new, fewer, left))
    groups = kernel.neighbours(p, sets)
    assert sorted(u for g in groups for u in g) == sorted(sets) and max(asked) <= 512
