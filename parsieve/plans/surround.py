"""Operators around the search on the given tables: joins, windows, groupings, features."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from parsieve.sources.io import table
from parsieve.sources.views import duck_sql, load

_HTML_LANG = '<html[^>]*lang="([A-Za-z-]+)"'


def _rows() -> Column:
    """A fresh row count: columns need a session."""
    return F.count(F.lit(1))


def star_join(spark: SparkSession, sf: str) -> DataFrame:
    """Line items by the regions of customer and supplier, over six joined tables."""
    return load(spark, sf, "star20").groupBy("cr", "sr").agg(_rows().alias("n"), F.sum("qty").cast("long").alias("bins"))


def text_flags(spark: SparkSession, sf: str) -> DataFrame:
    flags = [F.sum(c).cast("long").alias(f"n_{c}") for c in "fghj"]
    return load(spark, sf, "doc10").groupBy(F.col("a").alias("lang")).agg(*flags)


def json_props_bins(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "evt7").groupBy(F.col("e").alias("bin")).agg(_rows().alias("n"))


def embedding_bits(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "emb16").groupBy("label").agg(*(F.sum(f"d{k}").cast("long").alias(f"d{k}") for k in range(16)))


def grouping_sets(spark: SparkSession, sf: str) -> DataFrame:
    """Counts of three sets of columns in one pass."""
    return load(spark, sf, "evt7").groupingSets([["a", "b"], ["b", "d"], []], "a", "b", "d").agg(_rows().alias("n"))


def asof_events(spark: SparkSession, sf: str) -> DataFrame:
    """For each event the latest one before it of the same user with a value above 100."""
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    found = F.last(F.when(F.col("value") > 100, F.col("event_id")), ignorenulls=True).over(before)
    e = table(spark, sf, "events").select("user_id", "event_id", found.alias("found"))
    return e.groupBy("user_id").agg(F.count("found").alias("n"), F.sum(F.col("event_id") - F.col("found")).alias("gap"))


def interval_orders(spark: SparkSession, sf: str) -> DataFrame:
    """Orders of the same customer in the 30 days up to an order, without pairing them up."""
    day = F.datediff("o_orderdate", F.lit("1970-01-01"))
    span = Window.partitionBy("o_custkey").orderBy(day).rangeBetween(-30, 0)
    o = table(spark, sf, "orders").select("o_orderpriority", _rows().over(span).alias("near"))
    return o.groupBy("o_orderpriority").agg(F.sum("near").alias("near"), F.max("near").alias("most"))


def win_rank_parts(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return table(spark, sf, "part").select("p_brand", "p_partkey", F.row_number().over(w).alias("place")).where("place <= 3")


def page_languages(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "pages").groupBy(F.regexp_extract("html", _HTML_LANG, 1).alias("lang")).agg(_rows().alias("n"))


QUERIES = {
    "star_join": star_join, "text_flags": text_flags, "json_props_bins": json_props_bins, "embedding_bits": embedding_bits, "grouping_sets_evt7": grouping_sets,
    "asof_events": asof_events, "interval_orders": interval_orders, "win_rank_parts": win_rank_parts, "page_languages": page_languages,
}

SQL = {
    "star_join": f"with v as ({duck_sql('star20')}) select cr, sr, count(*) as n, sum(qty)::bigint as bins from v group by all",
    "text_flags": f"with v as ({duck_sql('doc10')}) select a as lang, " + ", ".join(f"sum({c})::bigint as n_{c}" for c in "fghj") + " from v group by all",
    "json_props_bins": f"with v as ({duck_sql('evt7')}) select e as bin, count(*) as n from v group by all",
    "embedding_bits": f"with v as ({duck_sql('emb16')}) select label, " + ", ".join(f"sum(d{k})::bigint as d{k}" for k in range(16)) + " from v group by all",
    "grouping_sets_evt7": f"with v as ({duck_sql('evt7')}) select a, b, d, count(*) as n from v group by grouping sets ((a, b), (b, d), ())",
    "asof_events": """with e as (select user_id, event_id, last_value(case when value > 100 then event_id end ignore nulls) over
      (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as found from events)
      select user_id, count(found) as n, sum(event_id - found)::bigint as gap from e group by all""",
    "interval_orders": """with o as (select o_orderpriority, count(*) over (partition by o_custkey order by date_diff('day', date '1970-01-01', o_orderdate::date)
      range between 30 preceding and current row) as near from orders)
      select o_orderpriority, sum(near)::bigint as near, max(near) as most from o group by all""",
    "win_rank_parts": "select * from (select p_brand, p_partkey, row_number() over (partition by p_brand order by p_retailprice desc, p_partkey)::int as place from part) where place <= 3",
    "page_languages": f"select regexp_extract(html, '{_HTML_LANG}', 1) as lang, count(*) as n from pages group by all",
}
