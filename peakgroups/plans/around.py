"""Relational operations around a clustering, as queries with SQL: what users of covers and
link tables ask next to it. All declarative; the optimizer picks joins and aggregations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _read(spark, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def semi_anti(spark, sf_dir):
    """Customers with and without an order, counted by nation."""
    c, o = _read(spark, sf_dir, "customer"), _read(spark, sf_dir, "orders")
    buyers = c.join(o, c.c_custkey == o.o_custkey, "left_semi").select("c_nationkey", F.lit("ordered").alias("kind"))
    others = c.join(o, c.c_custkey == o.o_custkey, "left_anti").select("c_nationkey", F.lit("none").alias("kind"))
    return buyers.union(others).groupBy("c_nationkey", "kind").agg(F.count(F.lit(1)).alias("n"))


def rollup_metrics(spark, sf_dir):
    """Documents by language and source with subtotals."""
    d = _read(spark, sf_dir, "documents")
    out = d.rollup("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"), F.grouping_id().cast("long").alias("grouped"))
    return out.select("lang", "source", "n", "chars", "grouped")


def cube_flags(spark, sf_dir):
    """Labelled documents by each combination of their flags."""
    return _read(spark, sf_dir, "labels").cube("quality", "toxic").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("grouped"))


def topk_links(spark, sf_dir, k: int = 3):
    """The ``k`` heaviest links of each customer to suppliers; ties by supplier."""
    o, li = _read(spark, sf_dir, "orders"), _read(spark, sf_dir, "lineitem")
    links = o.join(li, o.o_orderkey == li.l_orderkey).groupBy("o_custkey", "l_suppkey").agg(F.count(F.lit(1)).alias("weight"))
    rank = F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("weight"), "l_suppkey"))
    return links.withColumn("place", rank.cast("long")).where(F.col("place") <= k)


def setops_snapshots(spark, sf_dir):
    """Links between users and event types of even and odd events: lost, new and common."""
    e = _read(spark, sf_dir, "events").select("user_id", "event_type", "event_id")
    old, new = (e.where(F.col("event_id") % 2 == r).select("user_id", "event_type") for r in (0, 1))
    parts = [("lost", old.subtract(new)), ("new", new.subtract(old)), ("common", old.intersect(new))]
    a, b, c = (x.withColumn("change", F.lit(name)) for name, x in parts)
    return a.union(b).union(c)


def array_cosine(spark, sf_dir):
    """Each vector's cosine with the mean of all vectors; the mean is one bounded row."""
    v = _read(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    mean = v.select(F.posexplode("e").alias("i", "x")).groupBy("i").agg(F.avg("x").alias("m"))
    mean = mean.agg(F.expr("transform(array_sort(collect_list(struct(i, m))), p -> p.m)").alias("m"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    cos = dot("e", "m") / F.sqrt(dot("e", "e") * dot("m", "m"))
    return v.join(F.broadcast(mean)).select("vec_id", F.round(cos, 6).alias("cosine"))


def purity(spark, sf_dir):
    """Languages as clusters of documents: size, largest source and its share."""
    d = _read(spark, sf_dir, "documents").where("lang is not null and source is not null")
    n = d.groupBy("lang", "source").agg(F.count(F.lit(1)).alias("n"))
    best = n.groupBy("lang").agg(F.sum("n").alias("size"), F.max("n").alias("largest"))
    return best.withColumn("share", F.round(F.col("largest") / F.col("size"), 9))


QUERIES = {
    "semi_anti": semi_anti,
    "rollup_metrics": rollup_metrics,
    "cube_flags": cube_flags,
    "topk_links": topk_links,
    "setops_snapshots": setops_snapshots,
    "array_cosine": array_cosine,
    "cluster_purity": purity,
}

SQL = {
    "semi_anti": """select c_nationkey, case when exists (select 1 from orders where o_custkey = c_custkey) then 'ordered' else 'none' end as kind, count(*) as n
      from customer group by 1, 2""",
    "rollup_metrics": "select lang, source, count(*) as n, cast(sum(n_chars) as bigint) as chars, grouping_id(lang, source) as grouped from documents group by rollup (lang, source)",
    "cube_flags": "select quality, toxic, count(*) as n, grouping_id(quality, toxic) as grouped from labels group by cube (quality, toxic)",
    "topk_links": """select * from (select *, row_number() over (partition by o_custkey order by weight desc, l_suppkey) as place from
      (select o_custkey, l_suppkey, count(*) as weight from orders join lineitem on l_orderkey = o_orderkey group by 1, 2)) where place <= 3""",
    "setops_snapshots": """with a as (select distinct user_id, event_type from events where event_id % 2 = 0), b as (select distinct user_id, event_type from events where event_id % 2 = 1)
      select *, 'lost' as change from (select * from a except select * from b) union all
      select *, 'new' from (select * from b except select * from a) union all
      select *, 'common' from (select * from a intersect select * from b)""",
    "array_cosine": """with x as (select vec_id, unnest(embedding)::double as x, unnest(range(len(embedding))) as i from embeddings),
      m as (select i, avg(x) as m from x group by i)
      select vec_id, round(sum(x * m) / sqrt(sum(x * x) * sum(m * m)), 6) as cosine from x join m using (i) group by vec_id""",
    "cluster_purity": """select lang, cast(sum(n) as bigint) as size, max(n) as largest, round(max(n)::double / sum(n), 9) as share
      from (select lang, source, count(*) as n from documents where lang is not null and source is not null group by 1, 2) group by lang""",
}
