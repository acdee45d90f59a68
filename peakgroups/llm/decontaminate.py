"""Benchmark decontamination (operator 1, DataFrame functions only).

The benchmark's word windows become a broadcast hash table. One scan of the documents
turns each word place into the hash of the window that starts there, probes the table,
compares the words of a hit with the window's, and ships only hits.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peakgroups.functions.storage import materialize
from peakgroups.llm.text import alnum_words, window_keys

#: Distinct benchmark windows up to which their table is broadcast (some 200 bytes each);
#: beyond, Spark joins by shuffle.
BROADCAST_WINDOWS = 2_000_000
#: The key under which every document reports itself.
_SELF = -1


def benchmark_windows(benchmark: DataFrame, n: int, item_id: str = "item_id", text: str = "text") -> DataFrame:
    """``key, len, window, items``: distinct windows of ``n`` words with their items.

    An item of fewer words than ``n``, but not none, is one window. Null texts and items
    without words give none; items with a null id are left out.
    """
    b = benchmark.select(F.col(item_id).cast("string").alias("item"), alnum_words(F.col(text)).alias("words")).where("item is not null and size(words) > 0")
    starts = f"sequence(1, greatest(1, size(words) - {n - 1}))"
    w = b.select("item", F.explode(F.expr(f"transform({starts}, i -> slice(words, i, {n}))")).alias("window"))
    return w.groupBy("window").agg(F.sort_array(F.collect_set("item")).alias("items")).withColumn("len", F.size("window"))


def _keyed(windows: DataFrame, lengths: list[int]) -> DataFrame:
    key = F.lit(None).cast("long")
    for k in lengths:
        key = F.when(F.col("len") == k, F.xxhash64(*[F.get("window", F.lit(j)) for j in range(k)])).otherwise(key)
    return windows.withColumn("key", key)


def find_hits(docs: DataFrame, benchmark: DataFrame, n: int = 10, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each document: ``doc_id, text_key, copies, n_words, spans, items``.

    ``text_key`` is the XXH64 of the text: rows with equal id and text are one row with
    ``copies`` of them. ``spans`` are merged runs of hit words ``(first, last)``, from 0;
    ``items`` the sorted ids with occurring windows. A null text has no words and no hits.
    """
    spark = docs.sparkSession
    windows = materialize(benchmark_windows(benchmark, n), "windows")
    lengths = sorted((r.len for r in windows.select("len").distinct().collect()), reverse=True)  # at most n rows
    table = _keyed(windows, lengths)
    itself = spark.createDataFrame([(None, [], 0, _SELF)], table.select("window", "items", "len", "key").schema)
    table = table.select("window", "items", "len", "key").union(itself)
    if windows.count() <= BROADCAST_WINDOWS:
        table = F.broadcast(table)
    d = docs.select(F.col(doc_id).alias("doc_id"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("text_key"), alnum_words(F.col(text)).alias("words"))
    # Windows of each length, one length after the other, behind the document's own key.
    parts = ", ".join(window_keys("words", k) for k in lengths)
    probes = d.withColumn("keys", F.expr(f"concat(array(cast({_SELF} as bigint)){', ' if parts else ''}{parts})"))
    # Outer, as each array has an element anyway: of an inner one Spark would infer a filter
    # on its size and evaluate the arrays' whole expressions for it, below this projection.
    rows = probes.select("doc_id", "text_key", "words", F.posexplode_outer("keys").alias("at", "key"))
    offset, before = F.lit(0), F.lit(1)
    for k in lengths:
        offset = F.when(F.col("len") == k, before).otherwise(offset)
        before = before + F.greatest(F.lit(0), F.size("words") - (k - 1))
    hit = rows.join(table, "key").withColumn("first", F.col("at") - offset)
    real = (F.col("len") == 0) & (F.col("at") == 0) | (F.col("len") > 0) & (F.col("at") > 0) & (F.slice("words", F.col("first") + 1, F.col("len")) == F.col("window"))
    hit = hit.where(real).select(
        "doc_id", "text_key",
        F.when(F.col("len") == 0, F.size("words")).alias("n_words"),
        F.when(F.col("len") > 0, F.struct("first", (F.col("first") + F.col("len") - 1).alias("last"))).alias("span"),
        F.when(F.col("len") > 0, F.col("items")).alias("items"),
    )
    merged = """
      aggregate(array_sort(spans), cast(array() as array<struct<first: int, last: int>>), (a, s) ->
        if(size(a) > 0 and s.first <= element_at(a, -1).last + 1,
           concat(slice(a, 1, size(a) - 1), array(struct(element_at(a, -1).first as first, greatest(element_at(a, -1).last, s.last) as last))),
           concat(a, array(s))))
    """
    return (
        hit.groupBy("doc_id", "text_key")
        .agg(F.count("n_words").alias("copies"), F.max("n_words").cast("long").alias("n_words"), F.collect_set("span").alias("spans"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"))
        .withColumn("spans", F.expr(merged))
    )


def contamination(hits: DataFrame) -> DataFrame:
    """Digest of :func:`find_hits`, a row for each row of the documents."""
    n_hit = F.expr("aggregate(spans, 0L, (n, s) -> n + s.last - s.first + 1)")
    return hits.select(
        F.explode(F.array_repeat(F.lit(1), F.col("copies").cast("int"))).alias("copy"),
        "doc_id", "n_words", n_hit.alias("n_hit"),
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        (n_hit > 0).alias("contaminated"),
    ).drop("copy")


def decontaminate(docs: DataFrame, benchmark: DataFrame, n: int = 10, action: str = "spans", doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` without the hit documents (``action="documents"``) or the hit words.

    ``"spans"`` keeps all rows and cuts, in the text of hit documents, each run of hit
    words with what stands between them. All columns stay as they are.
    """
    hits = find_hits(docs, benchmark, n, doc_id, text).where("size(spans) > 0").select("doc_id", "text_key", "spans")
    hits = materialize(hits, "hits").select(F.col("doc_id").alias("_hit_id"), F.col("text_key").alias("_hit_key"), F.col("spans").alias("_hit_spans"))
    on = docs[doc_id].eqNullSafe(F.col("_hit_id")) & (F.xxhash64(F.coalesce(docs[text], F.lit(""))) == F.col("_hit_key"))
    if action == "documents":
        return docs.join(hits, on, "left_anti")
    if action != "spans":
        raise ValueError(f"action is 'spans' or 'documents', not {action!r}")
    # A word with the separators before it, so that word k is piece k and the rest is the tail.
    pieces = f"regexp_extract_all(`{text}`, '[\\\\x00-\\\\x2F\\\\x3A-\\\\x40\\\\x5B-\\\\x60\\\\x7B-\\\\x7F]*[^\\\\x00-\\\\x2F\\\\x3A-\\\\x40\\\\x5B-\\\\x60\\\\x7B-\\\\x7F]+', 0)"
    tail = f"regexp_extract(`{text}`, '[\\\\x00-\\\\x2F\\\\x3A-\\\\x40\\\\x5B-\\\\x60\\\\x7B-\\\\x7F]*$', 0)"
    kept = f"concat(array_join(filter({pieces}, (p, i) -> not exists(_hit_spans, s -> i between s.first and s.last)), ''), {tail})"
    out = docs.join(hits, on, "left")
    return out.select(*[F.when(F.col("_hit_spans").isNull(), F.col(text)).otherwise(F.expr(kept)).alias(text) if c == text else docs[c] for c in docs.columns])


def op1_decontaminate(spark, sf_dir):
    docs, items = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "benchmark"))
    return contamination(find_hits(docs, items))


OP1_SQL = r"""
with w as (
  select doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') as words from documents
), b as (
  select item_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') as words from benchmark
), bw as (
  select distinct item_id, least(len(words), 10) as n, array_to_string(list_slice(words, i, i + 9), ' ') as k
  from (select item_id, words, unnest(range(1, greatest(2, len(words) - 8))) as i from b where len(words) > 0)
), lens as (select distinct n from bw), dw as (
  select doc_id, n, i, array_to_string(list_slice(words, i, i + n - 1), ' ') as k
  from (select doc_id, words, n, unnest(range(1, len(words) - n + 2)) as i from w, lens where len(words) >= n)
), hits as (select doc_id, i, dw.n, item_id from dw join bw on dw.k = bw.k and dw.n = bw.n),
covered as (select doc_id, count(distinct p) as n_hit from (select doc_id, unnest(range(i, i + n)) as p from hits) group by doc_id),
items as (
  select doc_id, count(*) as n_items, string_agg(item, ',' order by item) as ids
  from (select distinct doc_id, cast(item_id as varchar) as item from hits) group by doc_id
)
select w.doc_id, len(words) as n_words, coalesce(n_hit, 0) as n_hit, coalesce(n_items, 0) as n_items,
       sha256(coalesce(ids, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from w left join covered using (doc_id) left join items using (doc_id)
"""
