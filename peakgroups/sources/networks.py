"""Intake of networks (M1) and the networks built from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from peakgroups.functions.storage import collect_garbage, materialize, release
from peakgroups.operators.meeting import meeting_links
from peakgroups.schema import WEIGHT, Network


def load_network(df: DataFrame, src: str = "src", dst: str = "dst", weight: str | None = "weight", form: str = "undirected", node_weights: DataFrame | None = None, scale: int = 1) -> Network:
    """Fold direction, parallel links and node weights into canonical links.

    ``form``: ``undirected`` and ``arcs`` add up what runs between two nodes;
    ``both_arcs`` says that each link is given in both directions, and halves.
    ``scale`` multiplies weights before they are made integers; with a scale of 1 a weight
    that is no whole number raises an error, as rounding would change or lose links. Rows
    with a null end or weight, and zero weights, are left out; negative weights and NaN
    raise an error.
    A link of a node to itself is the node's own weight. ``node_weights(node,
    self_weight)`` adds to it and may name nodes without links.
    """
    if form not in ("undirected", "arcs", "both_arcs"):
        raise ValueError(f"unknown form {form!r}")
    value = F.col(weight) * F.lit(scale) if weight else F.lit(scale)
    bad = F.isnan(value.cast("double")) | (value < 0)
    part = (value != F.round(value)) if scale == 1 else F.lit(False)
    exact = F.when(bad, F.raise_error(F.lit("weights are neither negative nor NaN"))).when(part, F.raise_error(F.lit("weights are not whole; choose a scale"))).otherwise(F.round(value)).cast(WEIGHT)
    rows = df.select(F.col(src).cast("long").alias("a"), F.col(dst).cast("long").alias("b"), exact.alias("w")).where("a is not null and b is not null and w is not null and w <> 0")
    folded = rows.groupBy(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).agg(F.sum("w").cast(WEIGHT).alias("weight"))
    if form == "both_arcs":
        folded = folded.withColumn("weight", F.when(F.col("src") == F.col("dst"), F.col("weight")).otherwise((F.col("weight") / 2).cast(WEIGHT)))
    own = folded.where("src = dst").select(F.col("src").alias("node"), F.col("weight").alias("self_weight"))
    ends = folded.select(F.explode(F.array("src", "dst")).alias("node"), F.lit(0).cast(WEIGHT).alias("self_weight"))
    nodes = own.union(ends)
    if node_weights is not None:
        nodes = nodes.union(node_weights.select(F.col("node").cast("long"), F.coalesce(F.round(F.col("self_weight") * scale), F.lit(0)).cast(WEIGHT)))
    nodes = nodes.groupBy("node").agg(F.sum("self_weight").cast(WEIGHT).alias("self_weight"))
    return Network(folded.where("src < dst"), nodes)


def encode(df: DataFrame, src: str, dst: str, weight: str | None = None) -> tuple[DataFrame, DataFrame]:
    """Links between strings as ``(links(src, dst[, weight]), id_map(node, label))``.

    Ids are content hashes, equal in every run; two labels on one id raise an error.
    """
    labels = df.select(F.explode(F.array(src, dst)).alias("label")).where("label is not null").distinct()
    ids = labels.select(F.xxhash64("label").alias("node"), "label")
    clash = ids.groupBy("node").count().where("count > 1").limit(1).count()
    if clash:
        raise ValueError("two labels share an id")
    keep = [F.col(weight).alias("weight")] if weight else []
    return df.select(F.xxhash64(src).alias("src"), F.xxhash64(dst).alias("dst"), *keep), ids


def read_edge_list(spark: SparkSession, path: str, sep: str = " ") -> DataFrame:
    """Text lines ``src dst [weight]``, ``#`` comments; missing weights are 1."""
    rows = spark.read.option("sep", sep).option("comment", "#").schema("src long, dst long, weight double").csv(path)
    return rows.withColumn("weight", F.coalesce("weight", F.lit(1.0)))


#: The networks as SQL over the tables, in words that Spark and DuckDB both know.
NET_SQL = {
    "trade": "select c_nationkey as src, s_nationkey as dst, count(*) as weight from customer join orders on o_custkey = c_custkey join lineitem on l_orderkey = o_orderkey join supplier on s_suppkey = l_suppkey group by c_nationkey, s_nationkey",
    "part_supplier": "select l_partkey as src, 1000000000 + l_suppkey as dst, count(*) as weight from lineitem group by l_partkey, l_suppkey",
    "copurchase": "select a.l_partkey as src, b.l_partkey as dst, count(*) as weight from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and a.l_partkey < b.l_partkey group by a.l_partkey, b.l_partkey",
    "customer_part": "select o_custkey as src, 1000000000 + l_partkey as dst, count(*) as weight from orders join lineitem on l_orderkey = o_orderkey group by o_custkey, l_partkey",
    "user_handoff": "select user_id as src, later as dst, count(*) as weight from (select user_id, lead(user_id) over (order by ts, event_id) as later from events) where later is not null group by user_id, later",
    "user_window": "select a.user_id as src, b.user_id as dst, count(*) as weight from (select distinct user_id, cast(floor({epoch_ts} / 600) as bigint) as slot from events) a join (select distinct user_id, cast(floor({epoch_ts} / 600) as bigint) as slot from events) b on a.slot = b.slot and a.user_id < b.user_id group by a.user_id, b.user_id",
    "region_tree": "select 1000000 + n_nationkey as src, 2000000 + n_regionkey as dst, 1 as weight from nation union all select c_custkey as src, 1000000 + c_nationkey as dst, 1 as weight from customer",
    "high_quantity": "select distinct o_custkey as src, 1000000000 + l_suppkey as dst, 1 as weight from orders join lineitem on l_orderkey = o_orderkey where l_quantity >= 49",
}
_TOKENS = {"spark": "split(trim(lower(text)), '\\\\s+')", "duckdb": "string_split_regex(trim(lower(text)), '\\s+')"}
_EPOCH = {"spark": "unix_timestamp(cast(ts as timestamp))", "duckdb": "epoch(ts)"}


#: How many shingles two documents share at least.
DOC_LEAST = {"doc_shingles": 1, "doc_copies": 20}


def doc_network_sql(least: int, dialect: str) -> str:
    """Documents that share word 3-shingles found in 2 to 20 documents, with the number
    shared where it is at least ``least`` (N8, N9)."""
    if dialect == "spark":
        shingles = f"select distinct doc_id, concat(w[i], ' ', w[i + 1], ' ', w[i + 2]) as s from (select doc_id, w, explode(sequence(0, size(w) - 3)) as i from (select doc_id, {_TOKENS[dialect]} as w from documents) where size(w) >= 3)"
    else:
        shingles = f"select distinct doc_id, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] as s from (select doc_id, w, unnest(range(1, len(w) - 1)) as i from (select doc_id, {_TOKENS[dialect]} as w from documents) where len(w) >= 3)"
    return f"select a.doc_id as src, b.doc_id as dst, count(*) as weight from (select s, doc_id from shared) a join (select s, doc_id from shared) b on a.s = b.s and a.doc_id < b.doc_id group by a.doc_id, b.doc_id having count(*) >= {least}", shingles


#: The hand-offs in hours of their own, and over the borders between hours that have events:
#: no task sorts more than an hour's, and the window over hours has one row for each.
_HANDOFF_STEPS = [
    "timed as (select user_id, ts, event_id, cast(floor(unix_timestamp(cast(ts as timestamp)) / 3600) as bigint) as hour from events)",
    "followed as (select user_id, hour, lead(user_id) over (partition by hour order by ts, event_id) as later, lead(event_id) over (partition by hour order by ts, event_id) as next_id from timed)",
    "firsts as (select hour, min_by(user_id, struct(ts, event_id)) as opener from timed group by hour)",
    "openers as (select hour, lead(opener) over (order by hour) as opener from firsts)",
]
_HANDOFF = "select src, dst, count(*) as weight from (select user_id as src, case when next_id is null then opener else later end as dst from followed join openers on followed.hour <=> openers.hour) where dst is not null group by src, dst"


#: How many times texts are read for the links between them. A slice of the shingles takes some
#: 4 x input / SLICES of disk; beyond that, splitting the texts anew is what a slice costs.
SLICES = 4


def _slice_pairs(docs: DataFrame, part: int, slices: int) -> DataFrame:
    """``src, dst`` for every shingle of one slice and every two of its 2 to 20 documents.

    One shuffle by shingle, each as two hashes (96 bits) of its words in place of its text;
    words have no spaces, so equal words are equal shingles. In its order, rows of their own
    go first, then each shingle's last row names the documents before it, so that no frequent
    shingle is gathered.
    """
    # The id keeps the filter above the words, which would be split twice below.
    words = docs.selectExpr("doc_id", f"if(monotonically_increasing_id() >= 0, {_TOKENS['spark']}, null) as w").where("size(w) >= 3")
    at = words.selectExpr("doc_id", "w", "explode(sequence(0, size(w) - 3)) as i")
    three = "w[i], w[i + 1], w[i + 2]"
    rows = at.where(f"pmod(xxhash64({three}), {slices}) = {part}").selectExpr("doc_id", f"xxhash64({three}) as h", f"hash({three}) as g")
    w = Window.partitionBy("h", "g").orderBy("doc_id")
    near = rows.select("*", F.lag(F.lit(1)).over(w).alias("old"), F.lag("doc_id").over(w).alias("before"), F.lead(F.lit(1)).over(w).alias("new"))
    several = near.where("(old is not null or new is not null) and not (old is not null and before <=> doc_id)").select("h", "g", "doc_id")
    last = several.select("doc_id", F.row_number().over(w).alias("df"), F.lead(F.lit(1)).over(w).alias("new"), F.collect_list("doc_id").over(w.rowsBetween(-19, -1)).alias("d"))
    met = last.where("new is null and df between 2 and 20").selectExpr("concat(d, array(doc_id)) as d")
    return met.selectExpr("inline(flatten(transform(d, (x, i) -> transform(slice(d, i + 2, 20), y -> struct(x as src, y as dst)))))")


def doc_links(docs: DataFrame, least: int, slices: int = SLICES) -> DataFrame:
    """The links of :func:`doc_network_sql`, written. Shingles are taken a slice of their
    hashes at a time, which reads the texts again each time but keeps only a slice of them
    on disk; what a slice's documents share is written as pairs and counted at the end."""
    pairs = []
    for part in range(slices):
        pairs.append(materialize(_slice_pairs(docs, part, slices), "pairs"))
        collect_garbage(docs.sparkSession)
    every = pairs[0]
    for x in pairs[1:]:
        every = every.union(x)
    links = materialize(every.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("weight")).where(F.col("weight") >= least), "doc-links")
    for x in pairs:
        release(x)
    return links


def turn_term_sql(dialect: str) -> str:
    """Words of more than two letters, in 2 to 20 turns, that share turns (N12), as strings."""
    words = "explode(split(lower(text), '[^a-z]+'))" if dialect == "spark" else "unnest(string_split_regex(lower(text), '[^a-z]+'))"
    return f"select distinct conv_id, turn, w from (select conv_id, turn, {words} as w from conversations) where length(w) > 2"


def network_sql(name: str, dialect: str) -> tuple[str, list[str]]:
    """``(query, ctes)`` for a network's raw links."""
    if name in DOC_LEAST:
        query, shingles = doc_network_sql(DOC_LEAST[name], dialect)
        return query, [f"shingles as ({shingles})", "shared as (select shingles.s, doc_id from shingles join (select s, count(*) as df from shingles group by s having count(*) between 2 and 20) few on shingles.s = few.s)"]
    if name == "turn_terms":
        few = "terms as (select conv_id, turn, words.w from words join (select w, count(*) as df from words group by w having count(*) between 2 and 20) few on words.w = few.w)"
        return "select a.w as src, b.w as dst, count(*) as weight from terms a join terms b on a.conv_id = b.conv_id and a.turn = b.turn and a.w < b.w group by a.w, b.w", [f"words as ({turn_term_sql(dialect)})", few]
    if name == "page_hosts":
        href = "explode(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1))" if dialect == "spark" else "unnest(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1))"
        return "select host as src, target as dst, count(*) as weight from hrefs where host <> '' group by host, target", [f"hrefs as (select regexp_extract(url, '://([^/?#]*)', 1) as host, {href} as target from pages)"]
    if name == "user_handoff" and dialect == "spark":
        return _HANDOFF, _HANDOFF_STEPS
    return NET_SQL[name].replace("{epoch_ts}", _EPOCH[dialect]), []


NAMES = (*NET_SQL, "doc_shingles", "doc_copies", "page_hosts", "turn_terms")
_TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def raw_links(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Links of a network as its SQL gives them. Tables are read under private view names."""
    import re

    if name == "knn":
        return knn_links(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
    if name in DOC_LEAST:
        return doc_links(spark.read.parquet(f"{sf_dir}/documents.parquet"), DOC_LEAST[name])
    query, ctes = network_sql(name, "spark")
    text = (f"with {', '.join(ctes)} " if ctes else "") + query
    for t in _TABLES:
        if re.search(rf"\b{t}\b", text):
            view = f"pg_{t}_{abs(hash(sf_dir)) % 10**8}"
            spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(view)
            text = re.sub(rf"\b(from|join) {t}\b", rf"\1 {view} {t}", text)
            text = text.replace(f"{view} {t} a ", f"{view} a ").replace(f"{view} {t} b ", f"{view} b ")
    return spark.sql(text)


def knn_links(vectors: DataFrame, k: int = 8, planes: int = 0, seed: int = 11) -> DataFrame:
    """Vectors with their ``k`` nearest by cosine, weight ``round(1000 cos)``.

    Exact: every vector meets every other, in blocks of a hash of the one side, so that no
    task holds more than its block. ``planes`` > 0 compares only vectors on the same side
    of that many random hyperplanes, for tables beyond all-pairs reach; it may miss some.
    """
    v = vectors.select(F.col("vec_id"), F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    v = v.withColumn("norm", F.sqrt(F.aggregate("e", F.lit(0.0), lambda a, x: a + x * x))).where("norm > 0")
    v = v.withColumn("e", F.expr("transform(e, x -> x / norm)")).drop("norm")
    side = [F.signum(F.expr(f"aggregate(transform(e, (x, i) -> x * (xxhash64({seed}, {p}, i) % 1000)), 0.0D, (a, x) -> a + x)")) for p in range(planes)]
    v = v.withColumn("bucket", F.xxhash64(F.lit(0), *side) if planes else F.lit(0))
    blocks = 8
    a = v.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    b = v.select(F.col("vec_id").alias("other"), F.col("e").alias("f"), F.col("bucket").alias("bucket_b"), F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int").alias("block_b"))
    pairs = a.join(b, (F.col("block") == F.col("block_b")) & (F.col("bucket") == F.col("bucket_b")) & (F.col("vec_id") != F.col("other")))
    cos = F.aggregate(F.zip_with("e", "f", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    scored = pairs.select("vec_id", "other", F.round(cos * 1000).cast("long").alias("weight"))
    rank = F.row_number().over(Window.partitionBy("vec_id").orderBy(F.desc("weight"), "other"))
    near = scored.withColumn("r", rank).where(F.col("r") <= k).where("weight > 0")
    return near.select(F.least("vec_id", "other").alias("src"), F.greatest("vec_id", "other").alias("dst"), "weight").distinct()


def network(spark: SparkSession, sf_dir: str, name: str) -> Network:
    """A network by name, ready for clustering."""
    if name == "user_window":
        return window_network(spark.read.parquet(f"{sf_dir}/events.parquet"))
    raw = raw_links(spark, sf_dir, name)
    if name in ("page_hosts", "turn_terms"):
        raw, _ = encode(raw, "src", "dst", "weight")
    return canonical_network(raw) if name in CANONICAL else load_network(raw)


def window_network(events: DataFrame) -> Network:
    """Users active in the same ten minutes (N6), a link for nearly any two of them in large
    tables. Strengths and the total follow from how many users each slot has."""
    rows = events.selectExpr("user_id as user", f"cast(floor({_EPOCH['spark']} / 600) as bigint) as slot").where("user is not null and slot is not null").distinct()
    rows = materialize(rows, "slots")
    n = materialize(rows.groupBy("slot").agg(F.count(F.lit(1)).cast(WEIGHT).alias("n")), "slot-sizes")
    total = n.agg(F.sum((F.col("n") * (F.col("n") - 1)).cast(WEIGHT))).first()[0] or 0
    k = materialize(rows.join(F.broadcast(n), "slot").groupBy(F.col("user").cast("long").alias("node")).agg(F.sum(F.col("n") - 1).cast(WEIGHT).alias("k")).where("k > 0"), "strengths")
    links, both = (meeting_links(rows, both=x).select("src", "dst", F.col("weight").cast(WEIGHT).alias("weight")) for x in (False, True))
    slots = rows.join(F.broadcast(n), "slot").select("slot", F.col("user").cast("long").alias("user"), F.col("n").cast("long").alias("n")).where("n > 1")
    return Network(links, k.select("node", F.lit(0).cast(WEIGHT).alias("self_weight")), k, int(total) // 2, both, slots)


#: Networks whose SQL gives each link once, with src < dst and a weight of 1 or more.
CANONICAL = ("copurchase", *DOC_LEAST)


def canonical_network(links: DataFrame) -> Network:
    """A network of links that need no folding: :func:`load_network` without its shuffle."""
    links = links.select(F.col("src").cast("long"), F.col("dst").cast("long"), F.col("weight").cast(WEIGHT).alias("weight"))
    nodes = links.select(F.explode(F.array("src", "dst")).alias("node")).distinct()
    return Network(links, nodes.select("node", F.lit(0).cast(WEIGHT).alias("self_weight")))


def from_rows(spark: SparkSession, links, self_weights=()) -> Network:
    """A small network from Python rows ``(src, dst, weight)`` and ``(node, weight)``."""
    df = spark.createDataFrame([(int(a), int(b), int(w)) for a, b, w in links], "src long, dst long, weight long")
    own = spark.createDataFrame([(int(n), int(w)) for n, w in self_weights], "node long, self_weight long")
    return load_network(df, node_weights=own)
