"""SQL by which another engine finds the same lists: brute force over CUBE counts."""

from __future__ import annotations

from parsieve.sources.views import duck_sql


def scores_sql(view: str, columns: list[str], score: str = "mdl") -> str:
    """CTEs up to scored(target, tb, ub, size, pen, s): all pairs of a view."""
    n = len(columns)
    full = (1 << n) - 1
    cols = ", ".join(columns)
    bits = {c: 1 << (n - 1 - i) for i, c in enumerate(columns)}
    arity = " union all ".join(f"select '{c}' as name, {b}::bigint as b, count(distinct {c})::bigint as r from d" for c, b in bits.items())
    weigh = {"mdl": "0.5 * log2(total.m) * q.q * (ar.r - 1)", "aic": "q.q * (ar.r - 1) / ln(2.0)", "bdeu": "0.0"}[score]
    cell = "cnt__ * log2(cnt__)" if score != "bdeu" else "(lgamma(1 / q.q + cnt__) - lgamma(1 / q.q)) / ln(2.0)"
    return f"""with v as ({duck_sql(view)}), d as (select {cols}, count(*) as w from v group by {cols}),
    total as (select sum(w)::double as m from d),
    cube_counts as (select {full} - grouping_id({cols})::bigint as sb, {cols}, sum(w)::double as cnt__ from d group by cube({cols})),
    ar as ({arity}),
    q as (select sb, coalesce(product(case when (sb & ar.b) <> 0 then ar.r else 1 end), 1)::double as q, bit_count(sb)::int as size from range(0, {full + 1}) x(sb) cross join ar group by sb),
    logs as (select sb, sum({cell}) as l from cube_counts join q using (sb) group by sb),
    scored as (select ar.name as target, ar.b as tb, lu.sb as ub, q.size, {weigh} as pen, lu.l - lt.l + {weigh} as s
      from ar join logs lu on (lu.sb & ar.b) = 0 join logs lt on lt.sb = (lu.sb | ar.b) join q on q.sb = lu.sb cross join total)"""


def best_sql(columns: list[str]) -> str:
    """CTE mps(target, ub, size, s): strictly better than every proper subset."""
    return """, mps as (select * from scored a where not exists (select 1 from scored b where b.target = a.target
      and (b.ub & a.ub) = b.ub and b.ub <> a.ub and b.s <= a.s + 1e-6))"""


def names_sql(columns: list[str], bits: str) -> str:
    n = len(columns)
    parts = ", ".join(f"case when ({bits} & {1 << (n - 1 - i)}) <> 0 then '{c}' end" for i, c in sorted(enumerate(columns), key=lambda x: x[1]))
    return f"concat_ws('+', {parts})"


def mps_sql(view: str, columns: list[str], tail: str | None = None, score: str = "mdl") -> str:
    head = scores_sql(view, columns, score) + best_sql(columns)
    return f"{head} {tail or f'select target, {names_sql(columns, 'ub')} as parents, size, round(s, 3) as score from mps'}"


def visited_sql(view: str, columns: list[str]) -> str:
    """CTEs visited(target, ub, size) and synced(ub): the pairs that the search comes to, and
    the sets that it would come to if it waited for every predecessor.

    A pair is ended if a condition holds at it with the optimum over its subsets. The search
    comes to a set for a target if no set is ended that has only the first columns of it in
    search order; the synchronised one if no proper subset is ended."""
    n = len(columns)
    full = (1 << n) - 1
    floors = " union all ".join(
        f"select '{c}' as name, greatest(0, (select l from logs where sb = {full - (1 << (n - 1 - i))}) - (select l from logs where sb = {full})) as floor" for i, c in enumerate(columns)
    )
    return f"""{scores_sql(view, columns)}{best_sql(columns)},
    floors as ({floors}),
    pos as (select ar.name, ar.b, row_number() over (order by ar.r desc, round(f.floor / total.m, 6), ar.name) as place from ar join floors f on f.name = ar.name cross join total),
    span as (select sb, max(place) as last, min(place) as head from q join pos on (sb & pos.b) <> 0 group by sb),
    blank as (select target, s as empty from scored where ub = 0),
    ended as (select a.target, a.ub from scored a join scored b on a.target = b.target and (a.ub & b.ub) = b.ub
        join blank on blank.target = a.target join floors f on f.name = a.target
      group by a.target, a.ub, a.pen, f.floor, blank.empty
      having a.pen >= blank.empty - greatest(1e-6, 1e-12 * blank.empty) or min(b.s) <= f.floor + a.pen + greatest(1e-6, 1e-12 * blank.empty)),
    visited as (select a.target, a.ub, a.size from scored a where not exists (select 1 from ended e left join span on span.sb = e.ub join span rest on rest.sb = a.ub - e.ub
        where e.target = a.target and (a.ub & e.ub) = e.ub and e.ub <> a.ub and coalesce(span.last, 0) < rest.head)),
    synced as (select distinct a.ub from scored a where a.ub > 0 and not exists (select 1 from ended e where e.target = a.target and (a.ub & e.ub) = e.ub and e.ub <> a.ub))"""
