"""Mixing sources to target weights (operator 10, DataFrame functions only).

A source's weight is its token share to the power of an exponent, normalised. The exponent
is bisected until the mixture meets a target entropy or a limit on how often a source
repeats. A source's budget of tokens is then filled by whole passes over it and one part
of a pass; each pass goes through the source's blocks, and through a block's documents,
in an order of its own.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from peakgroups.functions.storage import materialize, release
from peakgroups.llm.text import space_words

#: Sources up to which the plan (a few short columns each) is broadcast.
BROADCAST_SOURCES = 100_000
#: Bisection steps in one job, and jobs: 2 ** -30 of exactness.
STEPS, PASSES = 5, 6
#: Digits of the permutation key by which the last pass is cut: the block's, then the document's.
DIGITS = (4, 3, 3)
_END = "~"  # beyond every key


def count_tokens(docs: DataFrame, doc_id: str = "doc_id", source: str = "source", text: str = "text") -> DataFrame:
    """``doc_id, source, n_tokens`` with the number of words; null text has none."""
    return docs.select(F.col(doc_id).alias("doc_id"), F.col(source).alias("source"), F.size(space_words(F.col(text))).cast("long").alias("n_tokens"))


def bisect_exponent(shares: DataFrame, ratio: float, max_repeats: float | None = None, target_entropy: float | None = None) -> float:
    """The exponent for ``shares(share)``, from 0 (uniform) to 1 (as it is).

    ``max_repeats``: the least exponent with which no source is passed through more often,
    where ``ratio`` is the budget over all tokens. ``target_entropy`` (in nats): the
    largest that still reaches it. Where no exponent meets the target, the nearest.
    """
    if (max_repeats is None) == (target_entropy is None):
        raise ValueError("give either max_repeats or target_entropy")
    low, high = 0.0, 1.0
    n = 2**STEPS
    for _ in range(PASSES):
        grid = F.explode(F.array(*[F.lit(low + (high - low) * i / n) for i in range(n + 1)]))
        at = shares.withColumn("a", grid).withColumn("m", F.pow("share", "a")).groupBy("a")
        z = at.agg(F.sum("m").alias("z"), F.sum(F.col("m") * F.log("m")).alias("ml"), F.max(F.col("m") / F.col("share")).alias("r"))
        if max_repeats is not None:
            z = z.select("a", (F.lit(ratio) * F.col("r") / F.col("z") > max_repeats).alias("low"))
        else:
            z = z.select("a", (F.log("z") - F.col("ml") / F.col("z") >= target_entropy).alias("low"))
        found = [r.low for r in sorted(z.collect(), key=lambda r: r.a)]  # n + 1 rows
        step = (high - low) / n
        k = found.index(False) if False in found else n + 1
        if k == 0:
            return low
        if k == n + 1:
            return high
        low, high = low + step * (k - 1), low + step * k
    return high if max_repeats is not None else low


def _block(doc_id: Column) -> Column:
    return F.substring(F.md5(F.coalesce(doc_id.cast("string"), F.lit(""))), 1, 2)


def permutation_key(doc_id: Column, epoch: Column) -> Column:
    """Place in a pass: the block's digits, then the document's. Equal ids share a place."""
    e = epoch.cast("string")
    blocks = F.substring(F.md5(F.concat_ws(":", e, _block(doc_id))), 1, DIGITS[0])
    return F.concat(blocks, F.md5(F.concat_ws(":", e, F.coalesce(doc_id.cast("string"), F.lit("")))))


def mixing_plan(counted: DataFrame, budget: int | None = None, max_repeats: float | None = None, target_entropy: float | None = None) -> DataFrame:
    """``source, weight, passes, cut``: whole passes, and the key up to which the next goes.

    ``budget`` is all tokens by default. Weights have six decimals. The cut is found by
    sums over the leading digits of the permutation key, each time within the one group of
    the last digits in which the budget runs out; no task sorts a source. A source without
    tokens has weight 0 and is left out.
    """
    totals = materialize(counted.groupBy("source").agg(F.sum("n_tokens").alias("tokens")).where("tokens > 0"), "totals")
    everything = totals.agg(F.sum("tokens")).first()[0] or 0
    budget = everything if budget is None else budget
    shares = totals.select("source", "tokens", (F.col("tokens") / F.lit(float(max(1, everything)))).alias("share"))
    exponent = bisect_exponent(shares, budget / max(1, everything), max_repeats, target_entropy)
    norm = shares.agg(F.sum(F.pow("share", F.lit(exponent)))).first()[0] or 1.0
    ppm = F.round(F.pow("share", F.lit(exponent)) / F.lit(norm) * 1_000_000).cast("decimal(20,0)")
    quota = (F.floor(ppm * F.lit(budget).cast("decimal(20,0)") / 1_000_000)).cast("long")
    plan = shares.select("source", "tokens", (ppm / 1_000_000).cast("double").alias("weight"), quota.alias("quota"))
    plan = plan.withColumn("passes", F.expr("quota div tokens")).withColumn("rest", F.expr("quota % tokens"))
    plan = materialize(plan.withColumn("cut", F.lit("")).withColumn("open", F.lit(True)), "plan")
    for digits in (*DIGITS, 64):
        p = plan.select(F.col("source").alias("s"), "passes", "cut", "rest").where("open")
        p = F.broadcast(p) if plan.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES else p
        d = counted.where("n_tokens > 0").join(p, F.col("source").eqNullSafe(F.col("s"))).withColumn("key", permutation_key(F.col("doc_id"), F.col("passes") + 1))
        d = d.where("startswith(key, cut)").groupBy("source", "cut", "rest", F.expr(f"substring(key, length(cut) + 1, {digits})").alias("digit"))
        w = Window.partitionBy("source").orderBy("digit")  # 16 ** 4 rows of a source at most
        sums = d.agg(F.sum("n_tokens").alias("n")).withColumn("upto", F.sum("n").over(w))
        # The first group that does not fit; what fits before it is spent.
        over = sums.where("upto > rest").groupBy("source").agg(F.min("digit").alias("digit"), F.min_by(F.col("upto") - F.col("n"), "digit").alias("spent"))
        over = over.select(F.col("source").alias("s"), "digit", "spent")
        joined = plan.join(over, F.col("source").eqNullSafe(F.col("s")) & F.col("open"), "left")
        later = joined.select(
            "source", "tokens", "weight", "quota", "passes",
            (F.col("rest") - F.coalesce("spent", F.lit(0))).alias("rest"),
            F.when(F.col("digit").isNotNull(), F.concat("cut", "digit")).when(F.col("open"), F.lit(_END)).otherwise(F.col("cut")).alias("cut"),
            F.col("digit").isNotNull().alias("open"),
        )
        before, plan = plan, materialize(later, "plan")
        release(before)
    return plan.select("source", "weight", "passes", "cut")


def deal(docs: DataFrame, plan: DataFrame, doc_id: str = "doc_id", source: str = "source") -> DataFrame:
    """``docs`` by ``plan``, with ``mix_epoch`` (from 1), ``mix_block`` and ``mix_key``.

    A document comes once in each whole pass of its source, and once more if its key in the
    next pass lies before the cut. Sort by epoch and key to train; columns of these three
    names are replaced.
    """
    docs = docs.drop("mix_epoch", "mix_block", "mix_key")
    p = plan.select(F.col("source").alias("_mix_source"), F.col("passes").alias("_mix_passes"), F.col("cut").alias("_mix_cut"), F.col("weight").alias("mix_weight"))
    p = F.broadcast(p) if plan.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES else p
    d = docs.drop("mix_weight").join(p, F.col(source).eqNullSafe(F.col("_mix_source")))
    more = permutation_key(F.col(doc_id), F.col("_mix_passes") + 1) < F.col("_mix_cut")
    last = F.col("_mix_passes") + more.cast("int")
    d = d.withColumn("mix_epoch", F.explode(F.when(last > 0, F.sequence(F.lit(1), last.cast("int"))).otherwise(F.array().cast("array<int>"))))
    d = d.withColumn("mix_block", _block(F.col(doc_id))).withColumn("mix_key", permutation_key(F.col(doc_id), F.col("mix_epoch")))
    return d.drop("_mix_source", "_mix_passes", "_mix_cut")


def mix(docs: DataFrame, budget=None, max_repeats=None, target_entropy=None, doc_id: str = "doc_id", source: str = "source", text: str = "text") -> DataFrame:
    """:func:`deal` by the plan for the documents themselves.

    A null source is a source of its own. No documents, or none with words, give no rows.
    """
    counted = materialize(count_tokens(docs, doc_id, source, text), "counted")
    return deal(docs, mixing_plan(counted, budget, max_repeats, target_entropy), doc_id, source)


#: The most passes through a source in production, for a budget of as many tokens as there are.
MAX_REPEATS = 1.25


def op10_mix_sources(spark, sf_dir):
    counted = materialize(count_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet")), "counted")
    return deal(counted, mixing_plan(counted, max_repeats=MAX_REPEATS))


OP10_SQL = rf"""
with recursive d as (
  select doc_id, source, len(list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '')) as n_tokens,
         substr(md5(cast(doc_id as varchar)), 1, 2) as block
  from documents
), t as (select source, cast(sum(n_tokens) as bigint) as tokens from d group by source having sum(n_tokens) > 0),
total as (select cast(sum(tokens) as bigint) as b from t),
s as (select source, tokens, tokens / b::double as share from t, total),
ends as (select max(pow(share, -1)) / count(*) as r0 from s),
bis(i, low, high) as (
  select 0, 0.0::double, 1.0::double
  union all
  select i + 1, case when over then mid else low end, case when over then high else mid end
  from (select i, low, high, mid, (select max(pow(share, mid - 1)) / sum(pow(share, mid)) > {MAX_REPEATS} from s) as over
        from (select *, (low + high) / 2 as mid from bis where i < 45))
), a as (select case when r0 <= {MAX_REPEATS} then 0.0 else (select high from bis where i = 45) end as a from ends),
w as (select source, tokens, cast(round(pow(share, a) / (select sum(pow(share, a)) from s, a) * 1000000) as bigint) as ppm from s, a),
q as (select source, tokens, ppm, cast(ppm::hugeint * b // 1000000 as bigint) as quota from w, total),
p as (select source, ppm / 1000000.0::double as mix_weight, quota // tokens as passes, quota % tokens as rest from q),
k as (
  select d.*, p.mix_weight, p.passes, p.rest,
         substr(md5((passes + 1) || ':' || block), 1, 4) || md5((passes + 1) || ':' || doc_id) as next_key
  from d join p using (source)
), c as (select *, sum(n_tokens) over (partition by source order by next_key) <= rest as more from k),
e as (select *, unnest(range(1, cast(passes + 1 + more::int as bigint))) as mix_epoch from c)
select doc_id, source, n_tokens, cast(mix_epoch as int) as mix_epoch, block as mix_block,
       substr(md5(mix_epoch || ':' || block), 1, 4) || md5(mix_epoch || ':' || doc_id) as mix_key, mix_weight
from e
"""
