"""All queries of the engine by name, and the SQL for those that SQL can express."""

from __future__ import annotations

import math
from collections.abc import Callable
from itertools import combinations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from parsieve.functions.scores import Aic, Bdeu, Custom, Fnml, Mdl
from parsieve.functions import sql
from parsieve.functions.bitset import from_names, names
from parsieve.operators import baselines, kernel, lookup, metrics, network, relational
from parsieve.operators.search import find_parent_sets
from parsieve.plans import surround
from parsieve.plans.encode import encode
from parsieve.sources import oracle
from parsieve.sources.io import table
from parsieve.sources.views import duck_sql, load
from parsieve.streaming import counts

COLUMNS = {"ord4": "a b c d", "geo5": "a b c d e", "evt7": "a b c d e f g", "doc10": "a b c d e f g h i j", "plant12": "a b c d e f g h i j k v"}
COLUMNS = {k: v.split() for k, v in COLUMNS.items()}
EVT3 = ["event_type", "quarter", "part"]
Query = Callable[[SparkSession, str], DataFrame]


def _mps(view: str, **options) -> Query:
    return lambda spark, sf: lookup.flat(find_parent_sets(load(spark, sf, view), **options).mps)


def _facts(view: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        e = encode(load(spark, sf, view))
        rows = [(c, e.arity[i], round(e.entropy[i] / e.m, 6), round(e.floor[i] / e.m, 6), round(e.entropy[i] + Mdl().penalty(1, e.arity[i], e.m), 3)) for i, c in enumerate(e.order)]
        return spark.createDataFrame(rows, "name string, arity int, entropy double, entropy_floor double, s_empty double")

    return run


def _facts_sql(view: str) -> str:
    cols = COLUMNS[view]
    n, full = len(cols), (1 << len(cols)) - 1
    one = " union all ".join(
        f"select '{c}' as name, (select count(distinct {c}) from d)::int as arity, round((select log2(sum(x)) - sum(x*log2(x))/sum(x) from (select sum(w)::double as x from d group by {c})), 6) + 0.0 as entropy, "
        f"round(greatest(0, (select sum(x*log2(x)) from (select sum(w)::double as x from d group by {', '.join(k for k in cols if k != c)})) - (select sum(w*log2(w)) from d)) / (select sum(w) from d), 6) as entropy_floor, "
        f"round((select sum(x)*log2(sum(x)) - sum(x*log2(x)) from (select sum(w)::double as x from d group by {c})) + 0.5*log2((select sum(w) from d))*((select count(distinct {c}) from d)-1), 3) as s_empty"
        for c in cols
    )
    return f"with v as ({duck_sql(view)}), d as (select {', '.join(cols)}, count(*)::double as w from v group by all) {one}"


def _compressed(view: str) -> Query:
    return lambda spark, sf: load(spark, sf, view).groupBy(*COLUMNS[view]).agg(F.count(F.lit(1)).alias("w"))


def _compressed_sql(view: str) -> str:
    return f"with v as ({duck_sql(view)}) select {', '.join(COLUMNS[view])}, count(*) as w from v group by all"


def _brute(view: str) -> Query:
    """The definition in DataFrame operations: counts of all sets by CUBE, scores by
    joins of sets, then an anti-join with better subsets."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        e = encode(load(spark, sf, view), order="input")
        n = len(e.order)
        full = (1 << n) - 1
        cube = e.rows.cube(*e.order).agg(F.sum("w").alias("cnt__"), F.grouping_id().alias("gid__"))
        # grouping_id has the first column as its highest bit; ours is the lowest.
        own = sum((F.when(F.col("gid__").bitwiseAND(F.lit(1 << (n - 1 - i))) == 0, F.lit(1 << i)).otherwise(F.lit(0)) for i in range(n)), F.lit(0)).cast("long")
        logs = cube.select(own.alias("u"), "cnt__").groupBy("u").agg(F.sum(F.col("cnt__") * F.log2("cnt__")).alias("l"))
        q = F.lit(1.0)
        for i, a in enumerate(e.arity):
            q = q * F.when(F.col("u").bitwiseAND(F.lit(1 << i)) != 0, float(a)).otherwise(1.0)
        facts = F.broadcast(spark.createDataFrame([(c, i, 1 << i, e.arity[i]) for i, c in enumerate(e.order)], "target string, t int, tb long, r int"))
        joined = logs.join(facts, F.col("u").bitwiseAND(F.col("tb")) == 0).withColumn("ju", F.col("u").bitwiseOR(F.col("tb")))
        joined = joined.join(logs.select(F.col("u").alias("ju"), F.col("l").alias("jl")), "ju")
        scored = joined.select("target", "u", (F.col("l") - F.col("jl") + Mdl().penalty_column(q, F.col("r"), e.m)).alias("s"))
        other = scored.select(F.col("target").alias("ot"), F.col("u").alias("ou"), F.col("s").alias("os"))
        inside = (F.col("target") == F.col("ot")) & (F.col("u").bitwiseAND(F.col("ou")) == F.col("ou")) & (F.col("u") != F.col("ou")) & (F.col("os") <= F.col("s") + 1e-6)
        best = scored.join(other, inside, "left_anti")
        labels = F.array_sort(F.filter(F.array(*(F.when(F.col("u").bitwiseAND(F.lit(1 << i)) != 0, F.lit(c)) for i, c in enumerate(e.order))), lambda x: x.isNotNull()))
        return best.select("target", F.array_join(labels, "+").alias("parents"), F.bit_count("u").cast("int").alias("size"), F.round("s", 3).alias("score"))

    return run


PAIRS = {"ord4": [("a", ["b"]), ("a", ["b", "c"]), ("d", ["a", "c"])], "plant12": [("h", ["a", "e"]), ("v", ["a", "d", "e", "g"]), ("k", ["b", "i"]), ("j", ["d"])]}


def _pairs(view: str, scorer, name: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        e = encode(load(spark, sf, view))
        pairs = {(e.order.index(t), from_names(u, e.order)): (t, u) for t, u in PAIRS[view]}
        if name == "entropy":
            rows = [(t, "+".join(sorted(u)), round(relational.conditional_entropy(spark, e, t, u), 6)) for t, u in PAIRS[view]]
        else:
            got = relational.score_pairs(spark, e, scorer, list(pairs))
            rows = [(t, "+".join(sorted(u)), round(got[k], 3)) for k, (t, u) in pairs.items()]
        return spark.createDataFrame(rows, "target string, parents string, value double")

    return run


def _pairs_sql(view: str, name: str) -> str:
    def logs(cols: list[str]) -> str:
        return f"(select sum(x*log2(x)) from (select sum(w)::double as x from d group by {', '.join(cols)}))"

    parts = []
    for t, u in PAIRS[view]:
        fit = f"({logs(u)} - {logs([*u, t])})"
        free = " * ".join(f"(select count(distinct {c}) from d)" for c in u) + f" * ((select count(distinct {t}) from d) - 1)"
        m = "(select sum(w) from d)"
        value = {"entropy": f"round({fit} / {m}, 6)", "mdl": f"round({fit} + 0.5*log2({m})*{free}, 3)", "aic": f"round({fit} + {free}/ln(2.0), 3)"}[name]
        parts.append(f"select '{t}' as target, '{'+'.join(sorted(u))}' as parents, {value} as value")
    return f"with v as ({duck_sql(view)}), d as (select {', '.join(COLUMNS[view])}, count(*)::double as w from v group by all) " + " union all ".join(parts)


def _lookup(view: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        r = find_parent_sets(load(spark, sf, view))
        cols = COLUMNS[view]
        rows = [(f"{t}|{'+'.join(pool)}", t, list(pool)) for t in cols for k in range(len(cols)) for pool in combinations([c for c in cols if c != t], k)]
        q = spark.createDataFrame(rows, "query_id string, target string, pool array<string>")
        return lookup.best_score(r.mps, q).select("query_id", "target", F.round("score", 3).alias("score"))

    return run


def _lookup_sql(view: str) -> str:
    cols = COLUMNS[view]
    label = oracle.names_sql(cols, "a.ub")
    return oracle.scores_sql(view, cols) + f" select a.target || '|' || {label} as query_id, a.target, round(min(b.s), 3) as score from scored a join scored b on a.target = b.target and (a.ub & b.ub) = b.ub group by a.target, a.ub, {label}"


def _functions_sql() -> str:
    cols = COLUMNS["geo5"]
    pool = sum(1 << (len(cols) - 1 - cols.index(c)) for c in ("a", "c"))
    h = "(select round(log2(sum(x)) - sum(x*log2(x))/sum(x), 6) from (select count(*)::double as x from v group by b))"
    return oracle.scores_sql("geo5", cols) + f" select target, round(min(s), 3) as score, true as inside, 'a+c' as names, {h} as entropy_b, 4::bigint as children from scored where (ub & {31 - pool}) = 0 group by target"


def _summary(view: str) -> Query:
    return lambda spark, sf: lookup.summary(find_parent_sets(load(spark, sf, view)).mps)


def _summary_sql(view: str) -> str:
    tail = "select sum(n)::bigint as z, min(n) as list_min, max(n) as list_max from (select target, count(*) as n from mps group by target)"
    return oracle.mps_sql(view, COLUMNS[view], tail)


def _topk(view: str) -> Query:
    return lambda spark, sf: lookup.top_sets(find_parent_sets(load(spark, sf, view)).mps, 3).select("target", "place", F.array_join("parents", "+").alias("parents"), F.round("score", 3).alias("score"))


def _topk_sql(view: str) -> str:
    return oracle.mps_sql(view, COLUMNS[view], f"select target, place::int as place, {oracle.names_sql(COLUMNS[view], 'ub')} as parents, round(s, 3) as score from (select *, row_number() over (partition by target order by s) as place from mps) where place <= 3")


def _layers(view: str, **options) -> Query:
    return lambda spark, sf: find_parent_sets(load(spark, sf, view), **options).layer_table.select("layer", "nodes", "pairs", "new_mps")


def _layers_sql(view: str) -> str:
    tail = " select v.size::int as layer, count(distinct v.ub) as nodes, count(*) as pairs, (select count(*) from mps where mps.size = v.size) as new_mps from visited v group by v.size"
    return oracle.visited_sql(view, COLUMNS[view]) + tail


def _order(view: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        return spark.createDataFrame(list(enumerate(encode(load(spark, sf, view)).order)), "pos int, name string")

    return run


def _order_sql(view: str) -> str:
    return oracle.visited_sql(view, COLUMNS[view]) + " select (place - 1)::int as pos, name from pos"


def _front(view: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        f = lookup.front(find_parent_sets(load(spark, sf, view)).mps)
        return f.select("target", "size", *(F.round(c, 3).alias(c) for c in ("score", "best_so_far", "gain")))

    return run


def _front_sql(view: str) -> str:
    by_size = "sizes as (select target, size, min(s) as score from mps group by all)"
    gain = "lag(score) over (partition by target order by size) - score"
    best = "min(score) over (partition by target order by size rows between unbounded preceding and current row)"
    return oracle.mps_sql(view, COLUMNS[view], f", {by_size} select target, size, round(score, 3) as score, round({best}, 3) as best_so_far, round({gain}, 3) as gain from sizes")


POOL = ["a", "d", "e", "g", "h", "j"]


def q_optimal(spark: SparkSession, sf: str) -> DataFrame:
    """The best parents of v within a pool, and of k within all columns."""
    mps = find_parent_sets(load(spark, sf, "plant12")).mps
    return lookup.flat(lookup.optimal(mps, "v", POOL).union(lookup.optimal(mps, "k")))


def _optimal_sql() -> str:
    cols = COLUMNS["plant12"]
    pool = sum(1 << (len(cols) - 1 - cols.index(c)) for c in POOL)
    one = lambda where: f"(select target, {oracle.names_sql(cols, 'ub')} as parents, size, round(s, 3) as score from mps where {where} order by s limit 1)"
    every = (1 << len(cols)) - 1
    return oracle.mps_sql("plant12", cols, f"{one(f'target = {chr(39)}v{chr(39)} and (ub & {every - pool}) = 0')} union all {one(f'target = {chr(39)}k{chr(39)}')}")


def _custom(view: str) -> Query:
    """MDL given as a score of one's own: with its penalty as the bound it prunes."""
    def run(spark: SparkSession, sf: str) -> DataFrame:
        e = encode(load(spark, sf, view))
        half = math.log2(e.m) / 2

        def bits(parent, joint, q, r):
            import numpy as np

            return float((parent * np.log2(parent)).sum() - (joint * np.log2(joint)).sum() + half * q * (r - 1))

        return lookup.flat(find_parent_sets(None, scorer=Custom(bits, lambda q, r, m: half * q * (r - 1)), encoded=e).mps)

    return run


def _unpruned_sql(view: str) -> str:
    n = len(COLUMNS[view])
    return f"select k::int as layer, (range_count)::bigint as nodes from (select bit_count(s)::int as k, count(*) as range_count from range(0, {(1 << n) - 1}) t(s) group by 1)"


def _network(view: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        score, _, queries = network.optimal_network(spark, find_parent_sets(load(spark, sf, view)))
        return spark.createDataFrame([(round(score, 3), queries)], "score double, queries long")

    return run


def _network_sql(view: str) -> str:
    cols = COLUMNS[view]
    n = len(cols)
    head = "with recursive " + oracle.scores_sql(view, cols)[5:]
    best = ", best as (select a.target, a.tb, a.ub, min(b.s) as d from scored a join scored b on a.target = b.target and (a.ub & b.ub) = b.ub group by 1, 2, 3)"
    walk = f", walk as (select 0::bigint as vb, 0::double as cost, 0 as k union all select vb | tb, cost + d, k + 1 from walk join best on ub = vb where k < {n})"
    return f"{head}{best}{walk} select round(min(cost), 3) as score, {n * 2 ** (n - 1)}::bigint as queries from walk where k = {n}"


def _blanket(view: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        _, edges, _ = network.optimal_network(spark, find_parent_sets(load(spark, sf, view)))
        return network.markov_blanket(edges, COLUMNS[view][1])

    return run


WORK = ["nodes", "pairs", "sync_nodes", "extra_percent", "removed_percent", "unpruned", "share_percent", "l_max", "l_z", "z", "list_min", "list_max"]


def _work(view: str) -> Query:
    """Search-space table of a view: nodes, synchronised nodes, extra and removed shares."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        r = find_parent_sets(load(spark, sf, view))
        m = metrics.report(r, baselines.synchronised_nodes(spark, r.problem))
        return spark.createDataFrame([tuple(round(float(m[k]), 6) for k in WORK)], ", ".join(f"{k} double" for k in WORK))

    return run


def _work_sql(view: str) -> str:
    n = len(COLUMNS[view])
    return f"""{oracle.visited_sql(view, COLUMNS[view])},
    lists as (select count(*) as k from mps group by target),
    f as (select (select count(distinct ub) from visited where ub > 0)::double as nodes, (select count(*) from visited)::double as pairs, (select count(*) from synced)::double as sync_nodes,
      (select max(size) from visited)::double as l_max, (select max(size) from mps)::double as l_z, (select count(*) from mps)::double as z,
      (select min(k) from lists)::double as list_min, (select max(k) from lists)::double as list_max),
    g as (select *, (select count(*) from range(1, {(1 << n) - 1}) t(s) where bit_count(s) <= l_max)::double as unpruned from f)
    select *, case when sync_nodes > 0 then round(100 * (nodes - sync_nodes) / sync_nodes, 6) else 0.0 end as extra_percent,
      case when unpruned > sync_nodes then round(100 * (unpruned - nodes) / (unpruned - sync_nodes), 6) else 100.0 end as removed_percent,
      case when unpruned > 0 then round(100 * nodes / unpruned, 6) else 0.0 end as share_percent from g"""


def _single_machine(view: str, which: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        e = encode(load(spark, sf, view))
        p = kernel.problem(e, Mdl())
        if which == "sequential":
            rows = baselines.sequential(p)[0].rows()
        elif which == "synchronised":
            rows = baselines.synchronised(p)[0].rows()
        else:
            rows = baselines.brute_force(p)
        flat = [(e.order[t], "+".join(names(u, e.order)), u.bit_count(), round(s, 3)) for t, u, s in rows]
        return spark.createDataFrame(flat, "target string, parents string, size int, score double")

    return run


def _all_optimal(view: str, memo: bool) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        e = encode(load(spark, sf, view))
        p = kernel.problem(e, Mdl())
        d = (baselines.depth_first_memo if memo else baselines.all_optimal)(p)
        rows = [(f"{e.order[t]}|{'+'.join(names(u, e.order))}", e.order[t], round(s, 3)) for (t, u), s in d.items()]
        return spark.createDataFrame(rows, "query_id string, target string, score double")

    return run


def _greedy(spark: SparkSession, sf: str) -> DataFrame:
    df = load(spark, sf, "plant12")
    e = encode(df)
    return baselines.greedy_table(spark, e, find_parent_sets(df, encoded=e))


def _unfolded(spark: SparkSession, sf: str) -> DataFrame:
    e = encode(load(spark, sf, "evt7"))
    return lookup.flat(baselines.unfolded(spark, e, kernel.problem(e, Mdl())).mps)


def _emb64(most: int) -> Query:
    """All 65 columns in two bitmap words, sets of up to `most` of them."""
    return lambda spark, sf: lookup.flat(find_parent_sets(load(spark, sf, "emb64"), max_parents=most).mps)


# --- operators around the search -------------------------------------------------------


def q_cube(spark: SparkSession, sf: str) -> DataFrame:
    g = load(spark, sf, "geo5").cube("b", "c", "e").agg(F.count(F.lit(1)).alias("c_rows"), F.grouping_id().alias("gid"))
    return g.select("b", F.col("c").alias("segment"), "e", "c_rows", "gid")


def q_rollup(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "ord4").rollup("a", "b", "c").agg(F.count(F.lit(1)).alias("n"))


def q_left_labels(spark: SparkSession, sf: str) -> DataFrame:
    d, x = table(spark, sf, "documents"), table(spark, sf, "labels")
    return d.join(x, "doc_id", "left").groupBy("lang", "quality").agg(F.count(F.lit(1)).alias("n"))


def q_unlabelled(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "documents").join(table(spark, sf, "labels"), "doc_id", "left_anti").groupBy("source").agg(F.count(F.lit(1)).alias("n"))


def q_range_bins(spark: SparkSession, sf: str) -> DataFrame:
    bins = F.broadcast(spark.createDataFrame([(i, 1000.0 * (i * i), 1000.0 * (i + 1) ** 2 if i < 25 else math.inf) for i in range(26)], "bin int, lo double, hi double"))
    o = table(spark, sf, "orders").select(F.col("o_totalprice").cast("double").alias("p"))
    return o.join(bins, (F.col("p") >= F.col("lo")) & (F.col("p") < F.col("hi"))).groupBy("bin").agg(F.count(F.lit(1)).alias("n"))


def q_running(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(spark, sf, "events").withColumn("before", F.lag("event_type").over(w))
    return e.where("before is not null").groupBy("before", "event_type").agg(F.count(F.lit(1)).alias("n"))


def q_pivot(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).select("l_returnflag", F.coalesce("F", F.lit(0)).alias("n_f"), F.coalesce("O", F.lit(0)).alias("n_o"))


def q_sets(spark: SparkSession, sf: str) -> DataFrame:
    """Nations with customers, with suppliers: union, both, only the first."""
    c = table(spark, sf, "customer").select(F.col("c_nationkey").alias("k")).distinct()
    s = table(spark, sf, "supplier").select(F.col("s_nationkey").alias("k")).distinct()
    tag = lambda d, name: d.withColumn("kind", F.lit(name))
    return tag(c.union(s).distinct(), "union").union(tag(c.intersect(s), "both")).union(tag(c.exceptAll(s), "first"))


def q_turns(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("conv_id").orderBy("turn")
    t = table(spark, sf, "conversations").withColumn("before", F.coalesce(F.lag("role").over(w), F.lit("-")))
    return t.groupBy("before", "role").agg(F.count(F.lit(1)).alias("n"))


def q_stream(which: str) -> Query:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        s = counts.events_stream(spark, sf)
        if which == "contingency":
            return counts.run_now(counts.contingency(s.select("event_type", F.hour("ts").alias("h")), ["event_type", "h"]))
        if which == "dedup":
            out = counts.run_now(counts.once(s.select("event_id", "ts", "event_type")), "append")
            return out.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))
        out = counts.run_now({"sessions": counts.sessions, "tumbling": counts.tumbling, "sliding": counts.sliding}[which](s), "complete")
        return out.withColumn("begins", F.date_format("begins", "yyyy-MM-dd HH:mm:ss"))

    return run


def stream_entropy(spark: SparkSession, sf: str) -> DataFrame:
    """Entropy of the hour given the type of event, kept by a stateful operator."""
    s = counts.events_stream(spark, sf).select("event_type", F.hour("ts").alias("h"))
    out = counts.run_now(counts.running_entropy(s, "event_type", "h"), "update")
    return out.select("event_type", "total", F.round("entropy", 6).alias("entropy"))


def stream_segments(spark: SparkSession, sf: str) -> DataFrame:
    """Events by market segment: a stream joined to a static table."""
    static = table(spark, sf, "customer").select(F.col("c_custkey").alias("user_id"), F.col("c_mktsegment").alias("segment"))
    return counts.run_now(counts.with_static(counts.events_stream(spark, sf), static, "user_id", ["event_type", "segment"]))


def sql_functions(spark: SparkSession, sf: str) -> DataFrame:
    """Each target's best score within a pool, its names and the entropy of its column, by SQL functions."""
    sql.register(spark)
    r = find_parent_sets(load(spark, sf, "geo5"))
    r.mps.createOrReplaceTempView("ps_lists")
    load(spark, sf, "geo5").createOrReplaceTempView("ps_rows")
    return spark.sql("""
      with lists as (select target, collect_list(struct(parents, score)) as l from ps_lists group by target),
      h as (select ps_entropy(collect_list(n)) as h from (select b, count(*) as n from ps_rows group by b))
      select target, round(ps_best_score(l, array('a', 'c')), 3) as score, ps_contains(array('a', 'b'), array('b')) as inside,
        array_join(ps_names(5L, array('a', 'b', 'c')), '+') as names, round(h, 6) as entropy_b,
        (select count(*) from ps_children(1L, 30L, 5)) as children from lists cross join h""")


def stream_mps(spark: SparkSession, sf: str) -> DataFrame:
    """Parent sets from the counts that a stream keeps: equal to those of the rows."""
    s = counts.events_stream(spark, sf).select("event_type", F.floor(F.hour("ts") / 6).alias("quarter"), (F.col("user_id") % 5).alias("part"))
    kept = counts.run_now(counts.contingency(s, ["event_type", "quarter", "part"]))
    return lookup.flat(find_parent_sets(kept, EVT3, weight="w").mps)


def udaf_entropy(spark: SparkSession, sf: str) -> DataFrame:
    """Entropy as a grouped aggregate over Arrow batches, next to the expression's."""
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("double")
    def ps_entropy(c: pd.Series) -> float:
        import numpy as np

        p = c.to_numpy(float)
        return float(np.log2(p.sum()) - (p * np.log2(p)).sum() / p.sum())

    g = load(spark, sf, "ord4").groupBy("a", "b").agg(F.count(F.lit(1)).alias("w"))
    return g.groupBy("a").agg(ps_entropy("w").alias("h")).select("a", F.round("h", 6).alias("h"))


def queries() -> dict[str, Query]:
    small = ("ord4", "geo5", "evt7")
    out: dict[str, Query] = {f"facts_{v}": _facts(v) for v in (*small, "doc10", "plant12")}
    out |= {f"compress_{v}": _compressed(v) for v in ("geo5", "evt7", "plant12")}
    out |= {f"brute_mps_{v}": _brute(v) for v in small}
    out |= {f"mps_{v}": _mps(v) for v in (*small, "doc10", "plant12")}
    out |= {f"mps_{v}": _mps(v) for v in ("brand12",)}
    out |= {
        "mps_plant12_c1": _mps("plant12", prune=("c1",)), "mps_evt7_c2": _mps("evt7", prune=("c2",)), "mps_evt7_none": _mps("evt7", prune=()),
        "mps_plant12_early": _mps("plant12", prune_extra=("early_c1",)), "mps_plant12_tight": _mps("plant12", prune_extra=("tight_c2",)),
        "mps_plant12_reverse": _mps("plant12", order="reverse"), "mps_plant12_input": _mps("plant12", order="input"),
        "mps_plant12_dfs1": _mps("plant12", mode="dfs", dfs_root_layer=1), "mps_plant12_dfs3": _mps("plant12", mode="dfs", dfs_root_layer=3),
        "mps_plant12_budget": _mps("plant12", memory_budget=4096), "mps_evt7_unfolded": _unfolded, "mps_evt7_late_fold": _mps("evt7", fold_from=2),
        "mps_geo5_relational": _mps("geo5", backend="relational"), "mps_ord4_relational": _mps("ord4", backend="relational"),
        "mps_plant12_sequential": _single_machine("plant12", "sequential"), "mps_plant12_synchronised": _single_machine("plant12", "synchronised"), "mps_evt7_power_set": _single_machine("evt7", "brute"),
        "mps_geo5_aic": _mps("geo5", scorer=Aic()), "mps_ord4_bdeu": _mps("ord4", scorer=Bdeu()), "mps_emb64_capped": _emb64(3), "mps_emb16": _mps("emb16"), "mps_star20": _mps("star20"),
        "summary_plant12": _summary("plant12"), "summary_doc10": _summary("doc10"), "topk_plant12": _topk("plant12"),
        "lookup_best_geo5": _lookup("geo5"), "lookup_best_evt7": _lookup("evt7"), "all_optimal_geo5": _all_optimal("geo5", False), "depth_first_memo_geo5": _all_optimal("geo5", True),
        "layers_plant12": _layers("plant12"), "layers_doc10": _layers("doc10"),
        "mps_geo5_target": _mps("geo5", targets=["b"]), "mps_geo5_relational_target": _mps("geo5", targets=["b"], backend="relational"), "mps_evt7_dfs_default": _mps("evt7", mode="dfs"),
        "mps_ord4_fnml": _mps("ord4", scorer=Fnml()), "mps_evt7_custom": _custom("evt7"), "order_plant12": _order("plant12"), "order_evt7": _order("evt7"), "front_plant12": _front("plant12"), "optimal_plant12": q_optimal,
        "layers_evt7_unpruned": lambda spark, sf: _layers("evt7", prune=())(spark, sf).select("layer", "nodes"),
        "network_geo5": _network("geo5"), "network_ord4": _network("ord4"), "blanket_geo5": _blanket("geo5"), "greedy_vs_exact_plant12": _greedy,
        "entropy_pairs_ord4": _pairs("ord4", Mdl(), "entropy"), "mdl_pairs_plant12": _pairs("plant12", Mdl(), "mdl"), "aic_pairs_plant12": _pairs("plant12", Aic(), "aic"),
        "fold_memory_bounds": lambda spark, sf: metrics.fold_bounds(load(spark, sf, "plant12")),
        "cube_counts_geo5": q_cube, "rollup_chain_ord4": q_rollup, "left_labels": q_left_labels, "anti_unlabelled": q_unlabelled, "range_bins": q_range_bins,
        "win_transitions": q_running, "pivot_flags": q_pivot, "setops_nations": q_sets, "win_turns": q_turns, "udaf_entropy": udaf_entropy,
        "stream_contingency": q_stream("contingency"), "stream_tumbling": q_stream("tumbling"), "stream_sliding": q_stream("sliding"), "stream_sessions": q_stream("sessions"), "stream_dedup": q_stream("dedup"), "stream_mps": stream_mps,
        "stream_entropy": stream_entropy, "stream_segments": stream_segments, "sql_functions_geo5": sql_functions,
    }
    out |= {f"work_{v}": _work(v) for v in COLUMNS}
    return out | surround.QUERIES


def oracle_sql() -> dict[str, str]:
    out = {f"facts_{v}": _facts_sql(v) for v in ("ord4", "geo5", "evt7", "doc10", "plant12")}
    out |= {f"compress_{v}": _compressed_sql(v) for v in ("geo5", "evt7", "plant12")}
    full = {v: oracle.mps_sql(v, COLUMNS[v]) for v in COLUMNS}
    for name in queries():
        kind, _, rest = name.partition("_")
        view = rest.removeprefix("mps_").split("_")[0]
        if (kind == "mps" or name.startswith("brute_mps")) and view in full and not name.endswith(("aic", "bdeu", "fnml", "target")):
            out[name] = full[view]
    for v in ("plant12", "doc10"):
        out[f"summary_{v}"] = _summary_sql(v)
    out |= {f"work_{v}": _work_sql(v) for v in COLUMNS} | {f"order_{v}": _order_sql(v) for v in ("plant12", "evt7")} | {f"layers_{v}": _layers_sql(v) for v in ("plant12", "doc10")}
    one = f"select target, {oracle.names_sql(COLUMNS['geo5'], 'ub')} as parents, size, round(s, 3) as score from mps where target = 'b'"
    out |= {f"mps_geo5_{k}": oracle.mps_sql("geo5", COLUMNS["geo5"], one) for k in ("target", "relational_target")}
    day = "strftime(date_trunc('day', ts::timestamp){}, '%Y-%m-%d %H:%M:%S') as begins"
    spans = " union all ".join(f"select {day.format(back)}, event_type from events" for back in ("", " - interval 1 day"))
    out |= {
        "mps_geo5_aic": oracle.mps_sql("geo5", COLUMNS["geo5"], score="aic"), "mps_ord4_bdeu": oracle.mps_sql("ord4", COLUMNS["ord4"], score="bdeu"),
        "stream_entropy": "with c as (select event_type, hour(ts) as h, count(*)::double as c from events group by all) select event_type, sum(c)::bigint as total, round(log2(sum(c)) - sum(c*log2(c))/sum(c), 6) as entropy from c group by event_type",
        "stream_segments": "select event_type, c_mktsegment as segment, count(*) as w from events join customer on user_id = c_custkey group by all",
        "sql_functions_geo5": _functions_sql(),
        "stream_mps": oracle.mps_sql("evt3", EVT3), "front_plant12": _front_sql("plant12"), "optimal_plant12": _optimal_sql(),
        "stream_tumbling": f"select {day.format('')}, event_type, count(*) as c from events group by all", "stream_sliding": f"select begins, event_type, count(*) as c from ({spans}) group by all",
        "stream_sessions": """with e as (select user_id, ts::timestamp as ts, case when ts::timestamp - lag(ts::timestamp) over w < interval 6 hours then 0 else 1 end as fresh from events window w as (partition by user_id order by ts)),
          s as (select *, sum(fresh) over (partition by user_id order by ts rows between unbounded preceding and current row) as k from e)
          select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') as begins, count(*) as c from s group by user_id, k""",
    }
    out |= {
        "topk_plant12": _topk_sql("plant12"), "lookup_best_geo5": _lookup_sql("geo5"), "lookup_best_evt7": _lookup_sql("evt7"), "all_optimal_geo5": _lookup_sql("geo5"), "depth_first_memo_geo5": _lookup_sql("geo5"),
        "layers_evt7_unpruned": _unpruned_sql("evt7"), "network_geo5": _network_sql("geo5"), "network_ord4": _network_sql("ord4"),
        "entropy_pairs_ord4": _pairs_sql("ord4", "entropy"), "mdl_pairs_plant12": _pairs_sql("plant12", "mdl"), "aic_pairs_plant12": _pairs_sql("plant12", "aic"),
        "cube_counts_geo5": f"with v as ({duck_sql('geo5')}) select b, c as segment, e, count(*) as c_rows, grouping_id(b, c, e)::bigint as gid from v group by cube(b, c, e)",
        "rollup_chain_ord4": f"with v as ({duck_sql('ord4')}) select a, b, c, count(*) as n from v group by rollup(a, b, c)",
        "left_labels": "select lang, quality, count(*) as n from documents left join labels using (doc_id) group by all",
        "anti_unlabelled": "select source, count(*) as n from documents d where not exists (select 1 from labels l where l.doc_id = d.doc_id) group by all",
        "range_bins": "select least(floor(sqrt(o_totalprice / 1000)), 25)::int as bin, count(*) as n from orders where o_totalprice >= 0 group by all",
        "win_transitions": "select before, event_type, count(*) as n from (select event_type, lag(event_type) over (partition by user_id order by ts, event_id) as before from events) where before is not null group by all",
        "pivot_flags": "select l_returnflag, count(*) filter (l_linestatus = 'F') as n_f, count(*) filter (l_linestatus = 'O') as n_o from lineitem group by all",
        "setops_nations": "with c as (select distinct c_nationkey as k from customer), s as (select distinct s_nationkey as k from supplier) select k, 'union' as kind from (select k from c union select k from s) union all select k, 'both' from (select k from c intersect select k from s) union all select k, 'first' from (select k from c except select k from s)",
        "win_turns": "select before, role, count(*) as n from (select role, coalesce(lag(role) over (partition by conv_id order by turn), '-') as before from conversations) group by all",
        "udaf_entropy": f"with v as ({duck_sql('ord4')}), g as (select a, b, count(*)::double as w from v group by all) select a, round(log2(sum(w)) - sum(w*log2(w))/sum(w), 6) as h from g group by a",
        "stream_contingency": "select event_type, hour(ts)::int as h, count(*) as w from events group by all",
        "stream_dedup": "select event_type, count(distinct event_id) as n from events group by all",
        "fold_memory_bounds": f"with x as ({duck_sql('plant12')}), w as (select {' + '.join(f'(min({c}) < max({c}))::int' for c in COLUMNS['plant12'])} as n from x), k as (select unnest(range(0, n))::int as layer, n from w) select layer, n * (factorial(n - 1) / (factorial(layer) * factorial(n - 1 - layer)))::bigint as unfolded_rows, (factorial(n) / (factorial(layer) * factorial(n - layer)))::bigint as folded_rows, (n - layer) / 2.0 as ratio from k",
    }
    return out | surround.SQL
