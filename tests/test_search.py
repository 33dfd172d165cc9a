"""The search on Spark against brute force, and DataFrame forms of the baselines."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from parsieve.functions.scores import Custom, Mdl
from parsieve.operators import baselines, kernel, lookup, network
from parsieve.operators.search import expand, find_parent_sets, scored, search
from parsieve.plans.encode import encode
from parsieve.sources import io
from parsieve.sources.views import load

SF = "/root/testdata/sf0.001"


def entries(result):
    return [(t, u) for t, u, _ in result.entries]


@pytest.fixture(scope="module")
def geo(spark):
    df = load(spark, SF, "geo5")
    enc = encode(df)
    return df, enc, [(t, u) for t, u, _ in baselines.brute_force(kernel.problem(enc, Mdl()))]


@pytest.mark.parametrize("options", [{}, {"mode": "dfs", "dfs_root_layer": 1}, {"mode": "dfs"}, {"fold_from": 2}, {"memory_budget": 64}, {"prune_extra": ("early_c1",)}, {"backend": "relational"}], ids=str)
def test_ways_agree(geo, options):
    df, enc, truth = geo
    assert entries(find_parent_sets(df, encoded=enc, **options)) == truth


def test_tables_and_network(spark, geo, tmp_path):
    df, enc, truth = geo
    r = find_parent_sets(df, encoded=enc)
    assert r.complete and r.mps.count() == len(truth)
    score, edges, _ = network.optimal_network(spark, r)
    free = sum(min(s for t, _, s in r.entries if t == k) for k in range(enc.n))
    empty = sum(r.problem.empty)
    assert free - 1e-6 <= score <= empty
    assert set(network.markov_blanket(edges, "a").toPandas().name) >= set(edges.where("child = 'a'").toPandas().parent)
    io.write_mps(r.mps, str(tmp_path / "mps"))
    assert io.resume(spark, str(tmp_path / "mps")).count() == len(truth)
    assert lookup.optimal(r.mps, "b", []).first()["size"] == 0


def test_edges_of_the_domain(spark):
    none = spark.createDataFrame([], "a int, b string")
    assert find_parent_sets(none).totals["z"] >= 0
    one = spark.createDataFrame([(1, "x")], "a int, b string")
    assert entries(find_parent_sets(one)) == [(0, 0), (1, 0)]
    nulls = spark.createDataFrame([(None, "x"), (1, None), (1, "x"), (None, None)] * 5, "a int, b string")
    assert encode(nulls).arity == [2, 2]
    with pytest.raises(ValueError):
        encode(nulls, null_policy="error")


def test_expansion_stays_out_of_python(spark):
    layer = spark.createDataFrame([(1, 14, 0)], "u0 long, y0 long, top int")
    out = expand(layer, 4, 1)
    assert sorted(map(tuple, out.collect())) == [(3, 12), (5, 10), (9, 6)]
    plan = out._jdf.queryExecution().toString()
    assert "Python" not in plan and "Exchange" not in plan


def test_synchronised_rule_as_a_table(spark):
    layer = spark.createDataFrame([(1, 0b110), (2, 0b101), (4, 0b011)], "u0 long, y0 long")
    out = {r["u0"]: r["x0"] for r in baselines.synchronised_table(layer, 3).collect()}
    assert out == {3: 4, 5: 2, 6: 1}


@pytest.mark.parametrize("options", [{}, {"fold_from": 2}, {"prune": ()}, {"prune": ("c1", "c2", "early_c1")}], ids=str)
def test_written_layers_give_what_local_ones_do(spark, geo, options):
    df, enc, truth = geo
    rules = options.get("prune", ("c1", "c2"))
    p = kernel.problem(enc, Mdl(), rules)
    runs = [search(spark, enc, p, fold_from=options.get("fold_from", 0), local_nodes=n) for n in (0, 20_000)]
    assert entries(runs[0]) == entries(runs[1]) == truth
    assert runs[0].layers == runs[1].layers


def test_targets(geo):
    df, enc, truth = geo
    b = enc.order.index("b")
    for backend in ("packed", "relational"):
        assert entries(find_parent_sets(df, encoded=enc, targets=["b"], backend=backend)) == [e for e in truth if e[0] == b]
    with pytest.raises(ValueError, match="memory_budget"):
        find_parent_sets(df, encoded=enc, backend="relational", memory_budget=1)
    with pytest.raises(ValueError, match="no mode"):
        find_parent_sets(df, encoded=enc, mode="deep")


def test_wide_tables(spark):
    """66 columns: two words; single parents against a direct count."""
    rows = [tuple((i * (k + 3) // (k % 5 + 1) + (i >> k % 4)) % 2 for k in range(66)) for i in range(40)]
    df = spark.createDataFrame(rows, ", ".join(f"c{k} int" for k in range(66)))
    enc = encode(df)
    got = find_parent_sets(df, encoded=enc, max_parents=1)
    p, want = got.problem, set()
    cells = kernel.Cells(p)
    for t in range(p.n):
        want.add((t, 0))
        want |= {(t, 1 << i) for i in range(p.n) if i != t and cells.score(t, 1 << i, float(p.arity[i])) < p.empty[t] - p.eps[t]}
    assert set(entries(got)) == want
    written = search(spark, enc, p, local_nodes=0)
    assert entries(written) == entries(got)
    with pytest.raises(ValueError, match="63 columns"):
        find_parent_sets(df, encoded=enc, max_parents=1, backend="relational")


def test_a_search_goes_on_from_its_checkpoint(spark, geo, tmp_path, monkeypatch):
    df, enc, truth = geo
    p, folder = kernel.problem(enc, Mdl(), ()), str(tmp_path / "run")
    whole = search(spark, enc, p)
    real, calls = kernel.children, []

    def stops(*a):
        calls.append(a)
        if len(calls) > 9:  # in the third layer
            raise KeyboardInterrupt
        return real(*a)

    monkeypatch.setattr(kernel, "children", stops)
    with pytest.raises(KeyboardInterrupt):
        search(spark, enc, p, checkpoint=folder)
    monkeypatch.setattr(kernel, "children", real)
    again = search(spark, enc, p, checkpoint=folder)
    assert entries(again) == entries(whole) == truth
    assert [x["nodes"] for x in again.layers] == [x["nodes"] for x in whole.layers]


def test_large_layer_has_one_exchange(spark, geo):
    df, enc, _ = geo
    p = kernel.problem(enc, Mdl())
    layer = spark.createDataFrame([(1, 14, 0), (2, 13, 1)], "u0 long, y0 long, top int")
    shared, lists = (spark.sparkContext.broadcast(x) for x in (p, kernel.Lists()))
    plan = scored(expand(layer, p.n, 1).repartitionByRange(2, "u0").sortWithinPartitions("u0"), shared, lists, 1)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1


def test_weights_stand_for_rows(spark, geo):
    df, enc, truth = geo
    counted = df.groupBy(*df.columns).agg(F.count(F.lit(1)).alias("times"))
    found = find_parent_sets(counted, weight="times")
    assert entries(found) == truth and found.order == enc.order


def test_too_many_states(spark):
    with pytest.raises(ValueError, match="bin it first"):
        encode(spark.range(6000).select("id", (F.col("id") % 2).alias("b")))


def test_own_scores(geo):
    """A bound that is the score's own penalty prunes and changes nothing."""
    df, enc, truth = geo
    half = math.log2(enc.m) / 2

    def bits(parent, joint, q, r):
        return float((parent * np.log2(parent)).sum() - (joint * np.log2(joint)).sum() + half * q * (r - 1))

    free = find_parent_sets(df, encoded=enc, scorer=Custom(bits))
    bound = find_parent_sets(df, encoded=enc, scorer=Custom(bits, lambda q, r, m: half * q * (r - 1)))
    assert entries(free) == entries(bound) == truth
    assert bound.totals["pairs"] < free.totals["pairs"]


def test_normalised_likelihood():
    from parsieve.functions.scores import Fnml, _regret

    # One draw of r states has r outcomes of likelihood one; two draws of two have 1, 1/2, 1/2... in pairs.
    assert _regret(1, 3) == pytest.approx(math.log2(3)) and _regret(2, 2) == pytest.approx(math.log2(2.5))
    assert _regret(1000, 2) == pytest.approx(_regret(1001, 2), abs=2e-3)
    got = Fnml().cells(np.array([2.0, 1.0]), np.array([1.0, 1.0, 1.0]), 2.0, 2)
    assert got == pytest.approx(2 + math.log2(2.5) + 1)


def test_synchronised_nodes_as_tables(spark, geo):
    df, enc, _ = geo
    p = kernel.problem(enc, Mdl())
    assert baselines.synchronised_nodes(spark, p) == baselines.synchronised(p)[1]["nodes"]


def test_sql_functions(spark):
    from parsieve.functions import sql

    sql.register(spark)
    row = spark.sql("select ps_contains(array('a','b'), array('b')) as i, ps_contains(array('a'), array('b')) as o, ps_names(6, array('z','y','x')) as n, ps_entropy(array(1L,1L,2L)) as h, ps_entropy(array()) as e").first()
    assert (row.i, row.o, row.n, row.h, row.e) == (True, False, ["x", "y"], 1.5, 0.0)
    assert sorted(map(tuple, spark.sql("select * from ps_children(2, 13, 4)").collect())) == [(2, 6, 9), (3, 10, 5)]
