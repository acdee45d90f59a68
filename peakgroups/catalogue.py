"""All registered queries of the clustering engine with their DuckDB SQL."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from peakgroups.baselines import labels, moves, structural
from peakgroups.functions.storage import materialize
from peakgroups.operators import consensus, formation, gains
from peakgroups.operators.contraction import contract
from peakgroups.plans import around, measures, perturb, workloads
from peakgroups.plans.hierarchy import MutualPeakClusterer
from peakgroups.schema import Network, Params
from peakgroups.sources import networks
from peakgroups.streaming import feeds

#: Hand networks: links (src, dst, weight) and own weights. Fixed values.
_ONE = {
    "f02": [(0, 1), (0, 2), (1, 2), (0, 3), (0, 4), (3, 4)],
    "f03": [(0, 1), (1, 2), (2, 3), (3, 4)],
    "f04": [(0, 1), (1, 2)],
    "f05": [(0, 1), (1, 2), (2, 3)],
    "f06": [(0, 1), (1, 2), (2, 3), (0, 3)],
    "f07": [(i, (i + 1) % 6) for i in range(6)],
    "f08": [(0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3), (4, 5), (4, 6), (4, 7), (5, 6), (5, 7), (6, 7), (3, 4)],
    "f09": [(i, j) for i in range(3) for j in range(3, 6)],
    "f10": [(0, i) for i in range(1, 7)],
}
FIXTURES = {name: ([(a, b, 1) for a, b in links], []) for name, links in _ONE.items()}
FIXTURES["f01"] = [(0, 2, 12), (1, 2, 12), (2, 3, 12)], [(0, 10), (1, 10), (2, 9), (3, 10)]
FIXTURES["f11"] = [(0, i, 12) for i in range(1, 7)], [(i, 10) for i in range(7)]
FIXTURES["f12"] = [(0, 1, 2), (1, 2, 1), (2, 3, 2)], []

#: Hand networks that their hierarchy query lays over the customers.
LAID = tuple(f"f{i:02}" for i in range(1, 11))

#: Networks of the per-step queries, small enough for SQL closures.
STEP_NETS = ("trade", "doc_copies", "customer_part", "region_tree", "high_quantity")


def _values(name: str) -> str:
    links, own = FIXTURES[name]
    rows = [*links, *((n, n, w) for n, w in own)]
    return "select * from (values " + ", ".join(str(r) for r in rows) + ") t(src, dst, weight)"


def _net_sql(name: str) -> str:
    """CTEs ``links(src, dst, weight)`` and ``own(node, s)`` of a network in DuckDB SQL."""
    query, ctes = (_values(name), []) if name in FIXTURES else networks.network_sql(name, "duckdb")
    return ", ".join([
        *ctes,
        f"raw as ({query})",
        "folded as (select least(src, dst) as src, greatest(src, dst) as dst, cast(sum(weight) as hugeint) as weight from raw where src is not null and dst is not null group by 1, 2)",
        "links as (select * from folded where src <> dst)",
        "own as (select node, cast(sum(s) as hugeint) as s from (select src as node, weight as s from folded where src = dst union all select unnest([src, dst]), 0 from folded) group by node)",
    ])


_STEPS = """
arcs as (select src, dst, weight from links union all select dst, src, weight from links),
strength as (select node, cast(sum(x) as hugeint) as k from (select node, 2 * s as x from own union all select src, weight from arcs) group by node),
total as (select cast((select coalesce(sum(s), 0) from own) + (select coalesce(sum(weight), 0) from links) as hugeint) as w),
scored as (select l.src, l.dst, l.weight, 2 * w * l.weight - a.k * b.k as gkey from links l join strength a on a.node = l.src join strength b on b.node = l.dst, total),
good as (select src as node, dst as cand, gkey from scored where gkey >= 0 union all select dst, src, gkey from scored where gkey >= 0),
peak as (select node, max(gkey) as peak from good group by node),
pre as (select node, cand, gkey from good join peak using (node) where gkey = peak),
cands as (select a.node, a.cand, a.gkey from pre a join pre b on a.node = b.cand and a.cand = b.node),
several as (select node, count(*) as k, max(gkey) as g from cands group by node having count(*) > 1),
tied as (select c.node, c.cand, k, g from cands c join several using (node)),
inner_links as (select a.node, sum(l.weight) as l from links l join tied a on a.cand = l.src join tied b on b.cand = l.dst and b.node = a.node group by a.node),
gall as (
  select node, k, g, k * g + 2 * w * coalesce(l, 0) - (s1 * s1 - s2) // 2 as gain_all
  from (select t.node, any_value(t.k) as k, any_value(g) as g, cast(sum(s.k) as hugeint) as s1, cast(sum(s.k * s.k) as hugeint) as s2 from tied t join strength s on s.node = t.cand group by t.node) left join inner_links using (node), total
), degree as (select src as node, count(*) as d from arcs group by src),
splits as (select node, k, gain_all, (k, d) in ((2, 2), (2, 3), (3, 3)) and g > gain_all as split from gall join degree using (node)),
tied_shared as (
  select t.node, t.cand, t.k, count(m.cand) as n from tied t join splits s on s.node = t.node and not split
  left join cands c on c.node = t.cand left join cands m on m.node = t.node and m.cand = c.cand group by t.node, t.cand, t.k
), narrow as (select node, cand from (select *, max(n) over (partition by node) as most from tied_shared) where n = most and n > 0 and 2 * most >= k),
actions as (
  select node, 'single' as action, 1 as k from cands group by node having count(*) = 1 union all
  select node, case when split then 'split' when node in (select node from narrow) then 'narrow' when gain_all >= 0 then 'merge_all' else 'carried' end, k from splits
), choices as (
  select c.node, c.cand from cands c join actions using (node) where action in ('single', 'split', 'merge_all') union all select node, cand from narrow
), pairs as (
  select distinct least(c.node, c.cand) as x, greatest(c.node, c.cand) as y from choices c
  join actions a on a.node = c.node join actions b on b.node = c.cand where a.action <> 'carried' and b.action <> 'carried'
), vpairs as (
  select case when a.action = 'split' then x || ':' || y else x::varchar end as a, case when b.action = 'split' then y || ':' || x else y::varchar end as b
  from pairs join actions a on a.node = x join actions b on b.node = y
), varcs as (select a, b from vpairs union select b, a from vpairs),
reach(v, r) as (select a, a from varcs union select reach.v, varcs.b from reach join varcs on varcs.a = reach.r),
vgroups as (select v, min(r) as label from reach group by v),
parts as (select label, cast(split_part(v, ':', 1) as bigint) as node from vgroups),
members as (select label, node, count(*) as num, any_value(den) as den from parts join (select node, count(*) as den from parts group by node) using (node) group by label, node),
every as (select label, node, num, den from members union all select 'n' || node, node, 1, 1 from own where node not in (select node from members)),
next_all as (
  select least(ca, cb) as src, greatest(ca, cb) as dst, cast(sum(w) as hugeint) as weight from (
    select a.label as ca, b.label as cb, l.weight * 36 * a.num * b.num // (a.den * b.den) as w from links l join every a on a.node = l.src join every b on b.node = l.dst
    union all
    select a.label, b.label, o.s * 36 * a.num * b.num // (a.den * b.den) * case when a.label = b.label then 1 else 2 end from own o join every a on a.node = o.node join every b on b.node = o.node and a.label <= b.label
  ) group by 1, 2
)
"""


def _sql(name: str, final: str) -> str:
    return f"with recursive {_net_sql(name)}, {_STEPS} {final}"


def _net(spark: SparkSession, sf_dir: str, name: str) -> Network:
    net = networks.from_rows(spark, *FIXTURES[name]) if name in FIXTURES else networks.network(spark, sf_dir, name)
    if net.by_node is not None:
        return net
    return Network(materialize(net.links, "links"), materialize(net.nodes, "nodes"))


def _long(*columns: str):
    return [F.col(c).cast("long").alias(c) for c in columns]


def _level_one(net: Network):
    w = gains.total_weight(net)
    cands = materialize(MutualPeakClusterer().candidates(net, w), "cands")
    actions, members = formation.form_clusters(net, cands, w, 1)
    return w, cands, actions, members


#: Bytes of a cluster's name from which its rows have a task of their own, of the shorter names in a task,
#: and of all names that executors hold whole.
_LONG_NAME, _NAMES_A_TASK, _SENT_NAMES = 65_536, 131_072, 67_108_864


def _signed(members: DataFrame) -> DataFrame:
    """Members with their cluster named by its sorted members, so each name stands in as many rows as it lists.

    A name joins its rows where they are written, and no task has many long names: a writer
    of Parquet keeps each name once then, where it would hold thousands of rows with
    their names in memory as soon as the names of a file outgrow its dictionary (1 MB).
    """
    rows = F.sort_array(F.collect_list(F.struct("node", *_long("num", "den")))).alias("rows")
    whole = materialize(members.groupBy("cluster").agg(rows, F.sum(F.length(F.col("node").cast("string")) + 1).alias("bytes")), "clusters")
    is_long = F.col("bytes") > _LONG_NAME
    long, short, size = whole.agg(F.count_if(is_long), F.sum(F.when(is_long, 0).otherwise(F.col("bytes"))), F.coalesce(F.sum("bytes"), F.lit(0))).first()
    parts = 1 + (short or 0) // _NAMES_A_TASK
    numbers = Window.orderBy("cluster")
    tasks = whole.where(is_long).select("cluster", (F.row_number().over(numbers) - 1 + parts).cast("int").alias("task"))
    dealt = whole.join(F.broadcast(tasks), "cluster", "left").select("cluster", F.coalesce("task", F.pmod(F.hash("cluster"), F.lit(parts))).alias("task"), F.inline("rows"))
    names = whole.select("cluster", F.array_join(F.expr("transform(rows, x -> cast(x.node as string))"), ",").alias("members"))
    named = dealt.repartitionById(parts + long, "task").join(F.broadcast(names) if size <= _SENT_NAMES else names, "cluster")
    return named.select("members", "node", "num", "den")


def _contracted(net: Network, members: DataFrame) -> DataFrame:
    alone = net.nodes.select("node").join(members.select("node"), "node", "left_anti").selectExpr("node as cluster", "node", "1 as num", "1 as den")
    nxt, unit = contract(net, members.unionByName(alone), True)
    loops = nxt.nodes.where("self_weight <> 0").selectExpr("node as src", "node as dst", "self_weight as weight")
    every = nxt.links.select("src", "dst", "weight").union(loops)
    return every.groupBy((F.col("src") == F.col("dst")).alias("own"), "weight").agg(F.count(F.lit(1)).alias("n")).select("own", *_long("weight"), "n")


#: step -> (Spark query on a network, final SQL select)
STEPS = {
    "net": (lambda n: n.links.select("src", "dst", *_long("weight")), "select src, dst, cast(weight as bigint) as weight from links"),
    "strengths": (lambda n: gains.node_strengths(n).select("node", *_long("k")), "select node, cast(k as bigint) as k from strength"),
    "degrees": (lambda n: gains.degrees(n).select("node", *_long("d")), "select node, d from degree"),
    "total_weight": (lambda n: n.links.sparkSession.createDataFrame([(gains.total_weight(n),)], "w long"), "select cast(w as bigint) as w from total"),
    "gain_keys": (lambda n: gains.modularity_gain(n).select("src", "dst", *_long("gkey")), "select src, dst, cast(gkey as bigint) as gkey from scored"),
    "peak_gains": (lambda n: consensus.peak_gains(gains.modularity_gain(n)).select("node", *_long("peak")), "select node, cast(peak as bigint) as peak from peak"),
    "preselected": (lambda n: consensus.preselect(gains.modularity_gain(n)).select("node", "cand"), "select node, cand from pre"),
    "mutual_candidates": (lambda n: MutualPeakClusterer().candidates(n, gains.total_weight(n)).select("node", "cand", *_long("gkey")), "select node, cand, cast(gkey as bigint) as gkey from cands"),
    "carried": (lambda n: consensus.carried_nodes(n.nodes, MutualPeakClusterer().candidates(n, gains.total_weight(n))), "select node from own where node not in (select node from cands)"),
    "gain_each": (lambda n: formation.gain_each(MutualPeakClusterer().candidates(n, gains.total_weight(n))).select("node", *_long("gain_each")), "select node, cast(g as bigint) as gain_each from several"),
    "gain_all": (lambda n: formation.gain_all(n, MutualPeakClusterer().candidates(n, gains.total_weight(n)), gains.total_weight(n)).select("node", *_long("k", "gain_all")), "select node, k, cast(gain_all as bigint) as gain_all from gall"),
    "actions": (lambda n: _level_one(n)[2].select("node", "action", *_long("k")), "select node, action, k from actions"),
    "level1_membership": (lambda n: _signed(_level_one(n)[3]), "select members, node, num, den from members join (select label, string_agg(cast(node as varchar), ',' order by node) as members from members group by label) using (label)"),
    "contracted_links": (lambda n: _contracted(n, _level_one(n)[3]), "select src = dst as own, cast(weight as bigint) as weight, count(*) as n from next_all where weight <> 0 group by 1, 2"),
    "modularity": (lambda n: n.links.sparkSession.createDataFrame([(round(gains.modularity(n), 9),)], "q double"), "select round(cast(4 * w * (select coalesce(sum(s), 0) from own) - (select sum(k * k) from strength) as double) / cast(4 * w * w as double), 9) as q from total"),
}
#: Steps of networks that are too large for the closure in SQL, or have cluster names too long.
_LIGHT = ("net", "strengths", "total_weight", "gain_keys", "mutual_candidates")
_LIGHT_NETS = ("part_supplier", "copurchase", "user_handoff", "user_window", "doc_shingles")
#: The growth guard has no SQL here, and only f09 needs it.
_GUARDED = ("actions", "level1_membership", "contracted_links")


def _similarity(net: Network) -> DataFrame:
    return structural.structural_similarity(net).select("src", "dst", *_long("common", "du", "dv"))


_SIMILARITY_SQL = """select l.src, l.dst, 2 + count(b.dst) as common, any_value(du.d) + 1 as du, any_value(dv.d) + 1 as dv
from links l join degree du on du.node = l.src join degree dv on dv.node = l.dst
join arcs a on a.src = l.src left join arcs b on b.src = l.dst and b.dst = a.dst group by l.src, l.dst"""
_TRIANGLES_SQL = "select x.src as a, x.dst as b, y.dst as c from links x join links y on y.src = x.dst join links z on z.src = x.src and z.dst = y.dst"
_STRUCTURAL_SQL = f"""select distinct members from (
  with sim as ({_SIMILARITY_SQL}), ok as (select src, dst from sim where 4 * common * common >= du * dv),
  both_ways as (select src, dst from ok union all select dst, src from ok),
  core as (select src as node from both_ways group by src having count(*) + 1 >= 3),
  ca as (select src as a, dst as b from both_ways where src in (select node from core) and dst in (select node from core) union select node, node from core),
  label as (with recursive r(v, x) as (select a, a from ca union select r.v, ca.b from r join ca on ca.a = r.x) select v as node, min(x) as c from r group by v),
  cover as (select c, node from label union select c, dst from both_ways join label on label.node = src where dst not in (select node from core))
  select c, string_agg(cast(node as varchar), ',' order by node) as members from cover group by c)"""


def _cover_names(cover: DataFrame) -> DataFrame:
    c = cover.select("cluster", "node").distinct()
    return c.groupBy("cluster").agg(F.array_join(F.sort_array(F.collect_list("node")).cast("array<string>"), ",").alias("members")).select("members").distinct()


_F1_SQL = """with d as (select distinct lang, source, doc_id from documents where doc_id is not null),
a as (select distinct lang as c, doc_id as n from d where lang is not null), b as (select distinct source as c, doc_id as n from d where source is not null),
na as (select c, count(*) as n from a group by c), nb as (select c, count(*) as n from b group by c),
f as (select ca, cb, 2.0::double * k / (na.n + nb.n) as f1 from (select a.c as ca, b.c as cb, count(*) as k from a join b using (n) group by a.c, b.c) m join na on na.c = ca join nb on nb.c = cb),
d2 as (select (select sum(m) from (select max(f1) as m from f group by ca)) / (select count(*) from na) as x, (select sum(m) from (select max(f1) as m from f group by cb)) / (select count(*) from nb) as y)
select round(coalesce((x + y) / 2, 0), 9) as f1a, round(coalesce(2 * x * y / (x + y), 0), 9) as f1h from d2"""


def _f1_fixture(spark, sf_dir):
    """How well the documents' languages and sources match as covers (A2, A3)."""
    d = spark.read.parquet(f"{sf_dir}/documents.parquet").where("doc_id is not null")
    a, b = (d.where(f"{x} is not null").selectExpr(f"{x} as cluster", "doc_id as node") for x in ("lang", "source"))
    return spark.createDataFrame([(round(measures.f1_average(a, b), 9), round(measures.f1_harmonic(a, b), 9))], "f1a double, f1h double")


def _pair_counts(spark, sf_dir):
    """Language groups against sources: what any two of them have in common (A1)."""
    d = spark.read.parquet(f"{sf_dir}/documents.parquet")
    a, b = d.selectExpr("lang as cluster", "doc_id as node"), d.selectExpr("source as cluster", "doc_id as node")
    return measures.pair_f1(a, b).selectExpr("ca as lang", "cb as source", "common", "round(f1, 9) as f1")


_PAIR_SQL = """select lang, source, count(*) as common, round(2.0::double * count(*) / (any_value(nl) + any_value(ns)), 9) as f1 from
(select lang, source, count(*) over (partition by lang) as nl, count(*) over (partition by source) as ns from documents) group by lang, source"""


_PASSAGES_SQL = """with d as (select doc_id, string_split_regex(trim(lower(text)), '\\s+') as w from documents),
b as (select item_id, string_split_regex(trim(lower(text)), '\\s+') as w from benchmark),
dr as (select doc_id, array_to_string(list_slice(w, i, i + 7), ' ') as run from (select doc_id, w, unnest(range(1, len(w) - 6)) as i from d where len(w) >= 8)),
br as (select item_id, array_to_string(list_slice(w, i, i + 7), ' ') as run from (select item_id, w, unnest(range(1, len(w) - 6)) as i from b where len(w) >= 8))
select distinct item_id as cluster, doc_id as node from dr join br using (run)"""


def _events(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/events.parquet")


def _register_feeds(q: dict, sql: dict) -> None:
    """What the feeds of streaming/ give for all events at once (S1-S3) and the as-of join."""
    q["window_activity"] = lambda spark, sf_dir: feeds.window_activity(_events(spark, sf_dir)).select(F.unix_timestamp("start").alias("start"), "user_id", "n")
    sql["window_activity"] = "select cast(floor(epoch(ts) / 600) as bigint) * 600 as start, user_id, count(*) as n from events group by 1, 2"
    q["sliding_activity"] = lambda spark, sf_dir: feeds.window_activity(_events(spark, sf_dir), "10 minutes", "5 minutes").select(F.unix_timestamp("start").alias("start"), "user_id", "n")
    sql["sliding_activity"] = "select (slot - k) * 300 as start, user_id, count(*) as n from (select user_id, cast(floor(epoch(ts) / 300) as bigint) as slot from events), (values (0), (1)) t(k) group by 1, 2"
    q["session_activity"] = lambda spark, sf_dir: feeds.session_activity(_events(spark, sf_dir)).select(F.unix_micros("start").alias("start"), F.unix_micros("stop").alias("stop"), "user_id", "n")
    sql["session_activity"] = """with e as (select user_id, ts, case when ts < lag(ts) over (partition by user_id order by ts) + interval 10 minutes then 0 else 1 end as opens from events),
      s as (select user_id, ts, sum(opens) over (partition by user_id order by ts rows unbounded preceding) as no from e)
      select epoch_us(min(ts)) as start, epoch_us(max(ts)) + 600000000 as stop, user_id, count(*) as n from s group by user_id, no"""
    q["activity_links"] = lambda spark, sf_dir: feeds.activity_links(feeds.window_activity(_events(spark, sf_dir)))
    sql["activity_links"] = "with a as (select distinct cast(floor(epoch(ts) / 600) as bigint) as slot, user_id from events) select x.user_id as src, y.user_id as dst, count(*) as weight from a x join a y on x.slot = y.slot and x.user_id < y.user_id group by 1, 2"
    q["session_links"] = lambda spark, sf_dir: feeds.session_links(feeds.session_activity(_events(spark, sf_dir)))
    # Every fifth event's id stands for a membership that holds from then on.
    q["membership_asof"] = lambda spark, sf_dir: feeds.membership_asof(_events(spark, sf_dir), _events(spark, sf_dir).where("event_id % 5 = 0").selectExpr("user_id", "ts as at", "event_id as cluster"))
    sql["membership_asof"] = "select event_id, (select max_by(s.event_id, s.ts) from events s where s.event_id % 5 = 0 and s.user_id = e.user_id and s.ts <= e.ts) as cluster from events e"


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every level of the document copy network with input documents and shares."""
    h = MutualPeakClusterer().fit(networks.network(spark, sf_dir, "doc_copies"))
    return h.flatten_levels(list(range(1, h.levels + 1)))


def _hierarchy(name: str, **overrides):
    def query(spark, sf_dir):
        h = MutualPeakClusterer(Params(**overrides)).fit(_net(spark, sf_dir, name))
        return h.flatten_levels(list(range(1, h.levels + 1))) if h.levels else h.rows.selectExpr("level", "cluster", "member as node", "1.0D as share").where("false")

    return query


def laid_on_customers(spark: SparkSession, sf_dir: str, name: str) -> Network:
    """A hand network laid over the customers in order of their keys: each run of as many
    customers as it has nodes is linked as it is, customer ``i`` of a run as node ``i``.
    What is left over at the end of the table has the links that its customers have."""
    links, own = FIXTURES[name]
    size = 1 + max(x for a, b, _ in links for x in (a, b))
    keys = spark.read.parquet(f"{sf_dir}/customer.parquet").selectExpr("c_custkey as key").where("key is not null").distinct()
    # Gaps between keys leave runs with fewer customers, as at the end.
    at = keys.selectExpr("key", f"cast(floor(key / {size}) as bigint) as run", f"cast(pmod(key, {size}) as int) as i")
    ends = F.expr("inline(array(" + ", ".join(f"struct({a} as i, {b} as j, {w} as weight)" for a, b, w in links) + "))")
    shape = spark.range(1).select(ends)
    out = at.join(F.broadcast(shape), "i").selectExpr("key as src", "run", "j", "weight")
    met = out.join(at.selectExpr("run", "i as j", "key as dst"), ["run", "j"]).select("src", "dst", "weight")
    if own:
        selves = spark.range(1).select(F.expr("inline(array(" + ", ".join(f"struct({n} as i, {w} as weight)" for n, w in own) + "))"))
        met = met.union(at.join(F.broadcast(selves), "i").selectExpr("key as src", "key as dst", "weight"))
    net = networks.load_network(met)
    return Network(materialize(net.links, "links"), materialize(net.nodes, "nodes"))


def _laid(name: str):
    def query(spark, sf_dir):
        h = MutualPeakClusterer().fit(laid_on_customers(spark, sf_dir, name))
        return h.flatten_levels(list(range(1, h.levels + 1)))

    return query


def _report(name: str):
    return lambda spark, sf_dir: MutualPeakClusterer().fit(_net(spark, sf_dir, name)).report_frame(spark)


def _perturbed(spark, sf_dir):
    """Links left at each step, and the nodes that still have one (invariants)."""
    net = _net(spark, sf_dir, "doc_copies")
    rows = []
    for f in workloads.FRACTIONS:
        cut = perturb.perturb_links(net, f)
        rows.append((f, cut.links.count(), cut.arcs.select("src").distinct().count()))
    return spark.createDataFrame(rows, "fraction double, links long, nodes_with_links long")


_PERTURBED_SQL = f"""with recursive {_net_sql("doc_copies")}, fr as (select unnest([{", ".join(str(f) for f in workloads.FRACTIONS)}])::double as fraction)
select fraction, (select count(*) from links) - cast(round(fraction * (select count(*) from links)) as bigint) as links,
       (select count(distinct n) from (select unnest([src, dst]) as n from links)) as nodes_with_links from fr"""


def _register() -> tuple[dict, dict]:
    q: dict = {}
    sql: dict = {}
    for step, (run, final) in STEPS.items():
        nets = [*STEP_NETS, *FIXTURES] + (list(_LIGHT_NETS) if step in _LIGHT else [])
        for name in nets:
            if name in FIXTURES and step not in ("gain_all", "actions", "level1_membership", "contracted_links", "modularity"):
                continue
            key = f"{step}_{name}"
            q[key] = lambda spark, sf_dir, run=run, name=name: run(_net(spark, sf_dir, name))
            if not (name == "f09" and step in _GUARDED):
                sql[key] = _sql(name, final)
    for name in FIXTURES:
        q[f"fixture_{name}"] = _laid(name) if name in LAID else _hierarchy(name)
    for name in (*STEP_NETS, "doc_shingles"):
        q[f"hierarchy_{name}"] = _hierarchy(name)
        q[f"level_report_{name}"] = _report(name)
    q["hierarchy_without_split_f02"] = _hierarchy("f02", use_split=False)
    q["hierarchy_without_split_high_quantity"] = _hierarchy("high_quantity", use_split=False)
    q["hierarchy_without_narrowing_doc_copies"] = _hierarchy("doc_copies", use_narrowing=False)
    q["hierarchy_leaf_pull_f11"] = _hierarchy("f11", hub_policy="leaf_pull")
    for name in ("net_knn", "net_page_hosts", "net_turn_terms"):
        q[name] = lambda spark, sf_dir, name=name[4:]: networks.network(spark, sf_dir, name).links.select("src", "dst", *_long("weight"))
    for name in ("trade", "doc_copies", "f08"):
        q[f"structural_similarity_{name}"] = lambda spark, sf_dir, name=name: _similarity(_net(spark, sf_dir, name))
        sql[f"structural_similarity_{name}"] = _sql(name, _SIMILARITY_SQL)
        q[f"triangles_{name}"] = lambda spark, sf_dir, name=name: structural.triangles(_net(spark, sf_dir, name)).select(F.array_sort(F.array("a", "b", "c")).alias("t")).selectExpr("t[0] as a", "t[1] as b", "t[2] as c")
        sql[f"triangles_{name}"] = _sql(name, _TRIANGLES_SQL)
        q[f"structural_clusters_{name}"] = lambda spark, sf_dir, name=name: _cover_names(structural.structural_clusters(_net(spark, sf_dir, name), Fraction(1, 2), 3))
        sql[f"structural_clusters_{name}"] = _sql(name, _STRUCTURAL_SQL)
    flat = {
        "clique_percolation_k3_doc_copies": lambda n: structural.clique_percolation(n, 3),
        "triangle_communities_doc_copies": structural.triangle_communities,
        "louvain_doc_copies": lambda n: moves.louvain(n)[-1],
        "randomized_greedy_doc_copies": moves.randomized_greedy,
        "core_groups_doc_copies": lambda n: moves.core_groups(n, runs=2),
        "core_groups_iterated_doc_copies": lambda n: moves.core_groups(n, runs=2, iterated=True, rounds=2),
        "fast_consensus_f08": lambda n: moves.fast_consensus(n, 2, rounds=1),
        "speaker_listener_doc_copies": labels.speaker_listener,
        "significance_doc_copies": labels.significance_communities,
    }
    for key, run in flat.items():
        q[key] = lambda spark, sf_dir, run=run, name=next(x for x in ("doc_copies", "f08") if key.endswith(x)): run(_net(spark, sf_dir, name)).select("cluster", "node")
    q["random_doc_copies"] = lambda spark, sf_dir: labels.random_communities(_net(spark, sf_dir, "doc_copies"), workloads.document_truths(spark, sf_dir)["copies"])
    q["fixture_cover_f14"], sql["fixture_cover_f14"] = _f1_fixture, _F1_SQL
    q["pair_f1_language_source"], sql["pair_f1_language_source"] = _pair_counts, _PAIR_SQL
    q["perturbed_links_doc_copies"], sql["perturbed_links_doc_copies"] = _perturbed, _PERTURBED_SQL
    q["split_admission_grid"] = lambda spark, sf_dir: spark.range(1, 40).selectExpr("id as k").crossJoin(spark.range(1, 40).selectExpr("id as d")).where(formation.split_allowed(F.col("k"), F.col("d")))
    sql["split_admission_grid"] = "select k, d from range(2, 40) a(k), range(2, 40) b(d) where k <= d and k * (d - k) + k * (k - 1) // 2 <= d"
    q["accuracy_planted"] = lambda spark, sf_dir: workloads.run_accuracy({"planted": perturb.planted_network(spark, 500, 12, 40)}, ("mutual_peak", "structural"))
    q["determinism_high_quantity"] = lambda spark, sf_dir: workloads.run_determinism(_net(spark, sf_dir, "high_quantity"), "mutual_peak").select("run", "value")
    q["truth_passages"] = lambda spark, sf_dir: workloads.document_truths(spark, sf_dir)["passages"]
    sql["truth_passages"] = _PASSAGES_SQL
    _register_feeds(q, sql)
    q.update(around.QUERIES)
    sql.update(around.SQL)
    return q, sql


_QUERIES, _SQL = _register()


def queries() -> dict:
    return dict(_QUERIES)


def oracle_sql() -> dict:
    return dict(_SQL)
