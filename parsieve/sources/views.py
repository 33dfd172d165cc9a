"""Categorical views over the given tables, as SQL that Spark and DuckDB both run.

Table names stand in braces; `{json}` and `{dow}` are the two spots where the dialects
differ. Every column is an integer or string label with few states.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

_NOISE = "(7*l_orderkey + 13*l_partkey + 5*l_suppkey + l_linenumber) % 20"
_INT = "cast(floor({}) as int)".format


def _plant() -> str:
    base = f"""select (l_linenumber-1) % 4 as a, quarter(l_shipdate)-1 as b,
      case l_returnflag when 'A' then 0 when 'N' then 1 else 2 end as c, case l_linestatus when 'F' then 0 else 1 end as d,
      {_INT("(l_quantity-1)/25")} as e, l_partkey % 3 as f, l_suppkey % 2 as g, {_NOISE} as noise from {{lineitem}}"""
    hit = lambda lo, hi: f"case when noise between {lo} and {hi} then 1 else 0 end"
    more = f"""select *, (a+e+{hit(0, 1)}) % 2 as h, (c+f+{hit(2, 3)}) % 3 as i, (d+e+g+{hit(4, 6)}) % 2 as j,
      (a+e+d+g+{hit(10, 11)}) % 2 as v from ({base}) p0"""
    return f"select a,b,c,d,e,f,g,h,i,j,(i+b+{hit(7, 9)}) % 4 as k,v from ({more}) p1"


_STAR = f"""select l_linenumber as ln, {_INT("(l_quantity-1)/10")} as qty, {_INT("l_extendedprice/20000")} as price,
  cast(round(100*l_discount) as int) as disc, cast(round(100*l_tax) as int) as tax, l_returnflag as rf, l_linestatus as ls,
  year(l_shipdate) as sy, quarter(l_shipdate) as sq, o_orderstatus as os, o_orderpriority as op, year(o_orderdate) as oy,
  least({_INT("o_totalprice/100000")}, 4) as tp, p_type as pt, {_INT("(p_size-1)/10")} as ps,
  least({_INT("p_retailprice/500")}, 9) as pr, c_mktsegment as seg, cn.n_regionkey as cr, sn.n_regionkey as sr, s_nationkey as sk
  from {{lineitem}} l join {{orders}} o on l_orderkey = o_orderkey join {{part}} p on l_partkey = p_partkey
  join {{customer}} c on o_custkey = c_custkey join {{nation}} cn on c_nationkey = cn.n_nationkey
  join {{supplier}} s on l_suppkey = s_suppkey join {{nation}} sn on s_nationkey = sn.n_nationkey"""

_TEXT_BANDS = "case when n_chars < 500 then 0 when n_chars < 1000 then 1 when n_chars < 2000 then 2 when n_chars < 4000 then 3 else 4 end"
_FLAG = "case when {} then 1 else 0 end".format

VIEWS: dict[str, str] = {
    "ord4": f"select o_orderstatus as a, o_orderpriority as b, year(o_orderdate) as c, least({_INT('o_totalprice/100000')}, 4) as d from {{orders}}",
    "geo5": f"select c_nationkey as a, n_regionkey as b, c_mktsegment as c, {_INT('(c_acctbal+1000)/2500')} as d, c_nationkey % 2 as e from {{customer}} c join {{nation}} n on c_nationkey = n_nationkey",
    "evt7": f"select event_type as a, {_INT('hour(ts)/6')} as b, {{dow}} as c, least({_INT('value/50')}, 5) as d, {_INT('cast({json} as int)/25')} as e, user_id % 5 as f, {_INT('minute(ts)/15')} as g from {{events}}",
    "doc10": f"""select lang as a, source as b, {_TEXT_BANDS} as c, coalesce(cast(quality as varchar(9)), '?') as d, coalesce(cast(toxic as varchar(9)), '?') as e,
      {_FLAG("length(text) - length(replace(text, chr(10), '')) > 3")} as f, {_FLAG("text <> translate(text, '0123456789', '')")} as g, {_FLAG("text like '%@%'")} as h,
      {_FLAG("lower(text) like '%http%'")} as i, {_FLAG("lower(text) like '%licen%'")} as j from {{documents}} x left join {{labels}} y on x.doc_id = y.doc_id""",
    "brand12": f"""select p_brand as a, p_type as b, {_INT("(p_size-1)/10")} as c, split_part(p_name, ' ', 1) as d, split_part(p_name, ' ', 2) as e, l_linenumber as f,
      {_INT("(l_quantity-1)/10")} as g, {_INT("l_extendedprice/20000")} as h, cast(round(100*l_discount) as int) as i, l_returnflag as j, l_linestatus as k, year(l_shipdate) as l
      from {{lineitem}} x join {{part}} y on l_partkey = p_partkey""",
    "evt3": f"select event_type, {_INT('hour(ts)/6')} as quarter, user_id % 5 as part from {{events}}",
    "plant12": _plant(),
    "star20": _STAR,
}


def emb_view(dims: int, first: str) -> str:
    return "select " + ", ".join(f"case when {first.format(k)} > 0 then 1 else 0 end as d{k}" for k in range(dims)) + ", label from {embeddings}"


def sql_for(view: str, engine: str) -> str:
    """The view's SQL with table names left in braces."""
    if view.startswith("emb"):
        sql = emb_view(int(view[3:]), "embedding[{}]" if engine == "spark" else "list_extract(embedding, {}+1)")
    else:
        sql = VIEWS[view]
    spark = engine == "spark"
    return sql.replace("{json}", "get_json_object(props, '$.k')" if spark else "json_extract_string(props, '$.k')").replace("{dow}", "dayofweek(ts)" if spark else "dayofweek(ts) + 1")


def duck_sql(view: str) -> str:
    return re.sub(r"\{(\w+)\}", r"\1", sql_for(view, "duckdb"))


def load(spark: SparkSession, sf_dir: str, view: str) -> DataFrame:
    return spark.sql(re.sub(r"\{(\w+)\}", lambda m: f"parquet.`{sf_dir}/{m[1]}.parquet`", sql_for(view, "spark")))
