"""Line deduplication by an exact set-similarity join (operator 3, DataFrame functions only).

A line is the set of its words. Words are ordered by rarity, so that the first few of a
line, its prefix, are its rarest; two sets as similar as asked share a word of the larger
one's prefix and of an even shorter prefix of the smaller one. What shares one has to pass
the length filter, the positional filter and a bound from parity bits before the whole
sets are compared. A line goes if an earlier line of the corpus, kept or not, has a Jaccard
similarity of at least ``SIMILAR``; order is document id, then line.

Rarity comes from counts of all words in hash buckets, a table of bounded size; words are
then compared within a bucket's rank by hash, which is the same order everywhere.
"""

from __future__ import annotations


from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from peakgroups.functions.storage import collect_garbage, materialize, release
from peakgroups.llm.text import SPACES, ascii_lower

#: Jaccard similarity as a fraction.
SIMILAR = (4, 5)
#: Words from which a set can be as similar to a larger one; smaller ones only match equals.
SMALLEST = -(-SIMILAR[0] // (SIMILAR[1] - SIMILAR[0]))
#: Bytes of input for each bucket of the word counts, a power of two between the bounds; a
#: bucket's rank is the first byte of its words' codes.
BUCKET_BYTES, BUCKETS = 4096, (1 << 16, 1 << 20)
#: Rank from which a word stands in 1,024 places or more. Of these words, the last ``LEAD`` of a
#: line's prefix are compared with the first lines of each: ``LEADERS`` classes of hashes have
#: one. Of rarer words a line meets fewer than 1,024 others anyway.
HOT, LEAD, LEADERS, LIGHT = 40, 4, 8, 16
#: Numbers of sets up to which a table of them is broadcast; a larger one is joined and written.
BROADCAST_SETS = 200_000
#: What a line with a word matches.
WORDED = r"[^\x20\x09-\x0D]"
#: All characters beyond ASCII that lower() may change, and some more.
OTHER_CAPITALS = r"[\x{80}-\x{10FFFF}&&[\p{Lu}\p{Lt}\p{Nl}\p{So}]]"
#: Words beyond which a line has 128 parity bits.
WIDE = 80
#: Words of 64 bits of the filter over documents and lines, at least; half as many as buckets.
FILTER_WORDS = 1 << 15


def _spaced(text: Column) -> Column:
    """The text with other white space as spaces, so that a split at single spaces, which
    takes no regular expression, gives words and, where white space meets, empty strings."""
    other = F.lit(False)
    for c in "\t\x0b\x0c\r":
        other = other | F.contains(text, F.lit(c))
    return F.when(other, F.regexp_replace(text, r"[\t\x0B\x0C\r]", " ")).otherwise(text)


def _worded(line: Column) -> Column:
    """Whether a line has a word; what starts above the space does, without a search."""
    return (line >= "!") | line.rlike(WORDED)


def _small_letters(line: Column) -> Column:
    """:func:`ascii_lower` for lines: all but those with capitals beyond ASCII, which have to
    stay, take the faster lower()."""
    return F.when((F.octet_length(line) == F.char_length(line)) | ~line.rlike(OTHER_CAPITALS), F.lower(line)).otherwise(ascii_lower(line))


def _dense(table: DataFrame, size: int) -> DataFrame:
    """``table(at, v)`` with places below ``size`` as one row with one array, 0 where none is."""
    every = table.union(table.sparkSession.range(size).select(F.col("id").alias("at"), F.lit(0).cast("long"))).groupBy("at").agg(F.bit_or("v").alias("v"))
    return every.agg(F.array_sort(F.collect_list(F.struct("at", "v"))).alias("x")).select(F.col("x.v").alias("a"))


def bucket_count(docs: DataFrame) -> int:
    """Buckets for an input as large as Spark takes it to be. More tell more words apart,
    which saves time; results are the same with any number."""
    size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    fit = 1 << max(1, size // BUCKET_BYTES - 1).bit_length()
    return BUCKETS[0] if size >= 1 << 60 else min(max(fit, BUCKETS[0]), BUCKETS[1])  # unknown sizes are huge


def word_ranks(docs: DataFrame, buckets: int, text: str = "text") -> DataFrame:
    """One row: an array with the rank of each bucket, quarter powers of two of its number of
    words in all texts, in the place that a code has it.

    Capitals that are not ASCII count with their small letters here, which is faster; an
    order of words is an order whatever they are counted with.
    """
    words = docs.select(F.explode(F.split(F.replace(F.lower(_spaced(F.coalesce(F.col(text), F.lit("")))), F.lit("\n"), F.lit(" ")), " ")).alias("w"))
    counts = words.groupBy(F.xxhash64("w").bitwiseAND(F.lit(buckets - 1)).alias("at")).count()
    rank = F.least(F.lit(127), F.round(4 * F.log2(F.col("count") + 1))).cast("long")
    return materialize(_dense(counts.select("at", F.shiftleft(rank, 56).alias("v")), buckets), "ranks")


def coded_lines(docs: DataFrame, ranks: DataFrame, buckets: int, doc_id: str = "doc_id", text: str = "text", worded: bool = True) -> DataFrame:
    """``doc_id, text_key, line, codes``: a line's words as codes, rarest first. Lines without
    a word are left out if ``worded``. A null text is one empty line."""
    t = F.coalesce(F.col(text), F.lit(""))
    d = docs.select(F.col(doc_id).alias("doc_id"), F.xxhash64(t).alias("text_key"), F.posexplode(F.split(_spaced(t), "\n")).alias("line", "l"))
    d = d.where(_worded(F.col("l"))) if worded else d
    hashes = F.transform(F.split(_small_letters(F.col("l")), " "), lambda w: F.xxhash64(w))
    hashes = F.array_distinct(F.array_remove(hashes, F.xxhash64(F.lit(""))))
    # The table comes as a subquery, which plans show by name; "ranks" is used once, so that
    # it is put in place and not copied from row to row.
    d = d.withColumn("ranks", ranks.scalar())
    # Not null in Spark's eyes, so that sorting works on plain numbers.
    code = lambda h: F.coalesce(F.col("ranks")[h.bitwiseAND(F.lit(buckets - 1))], F.lit(0).cast("long")).bitwiseOR(F.shiftrightunsigned(h, 8))
    return d.select("doc_id", "text_key", "line", F.sort_array(F.transform(hashes, code)).alias("codes"))


def _prefix(n: str) -> str:
    """Words of a set of ``n`` by which it looks for sets of as many or fewer."""
    p, q = SIMILAR
    return f"({n} - ({p} * {n} + {q - 1}) div {q} + 1)"


def _short_prefix(n: str) -> str:
    """Words of a set of ``n`` by which sets of as many or more find it."""
    p, q = SIMILAR
    return f"({n} - ({2 * p} * {n} + {p + q - 1}) div {p + q} + 1)"


def _may_match(x: str, y: str) -> str:
    """SQL on two postings with the same code: the filters that need no more of the sets.
    A place ``i`` may be given as ``-1 - i``.

    The sizes bound the words that they must share, and that how many they may differ in;
    where they differ, parity bits can."""
    p, q = SIMILAR
    m, n = f"{x}.n", f"{y}.n"
    i, j = (f"greatest({side}.i, -1 - {side}.i)" for side in (x, y))
    common = f"(({p} * ({m} + {n}) + {p + q - 1}) div {p + q})"
    return f"""
      {q} * least({m}, {n}) >= {p} * greatest({m}, {n})
      and least({i}, {j}) + 1 + least({m} - 1 - {i}, {n} - 1 - {j}) >= {common}
      and if(least({m}, {n}) > {WIDE}, bit_count({x}.more ^ {y}.more) + bit_count({x}.bits ^ {y}.bits ^ {x}.more ^ {y}.more), bit_count({x}.bits ^ {y}.bits)) <= {m} + {n} - 2 * {common}
    """


def _filter_mask(key: Column) -> Column:
    """Three bits of the filter's word that belongs to a key."""
    bits = [F.call_function("shiftleft", F.lit(1).cast("long"), F.shiftrightunsigned(key, k).bitwiseAND(F.lit(63)).cast("int")) for k in (15, 21, 27)]
    return bits[0].bitwiseOR(bits[1]).bitwiseOR(bits[2])


def _few(sets: DataFrame) -> DataFrame:
    """A written table of sets, sent to all executors if it is small."""
    return F.broadcast(sets) if sets.count() <= BROADCAST_SETS else sets


def _later(pairs: DataFrame, sets: DataFrame, docs: DataFrame, ranks: DataFrame, buckets: int, repeated: bool, doc_id: str, text: str) -> DataFrame:
    """``set`` of the later set of each pair ``(a, b)`` that is as similar as asked.

    The whole sets come from a second look at the documents that hold them; a filter over
    documents and lines, a bit array with some bits for each, keeps other lines from moving.
    """
    used = pairs.select(F.col("a").alias("set")).union(pairs.select(F.col("b").alias("set"))).distinct()
    used = materialize(used, "used")
    wanted = materialize(sets.select("set", "doc_id", "text_key", "line").join(_few(used), "set", "left_semi"), "wanted")
    words = max(FILTER_WORDS, buckets // 2)
    at = lambda k: k.bitwiseAND(F.lit(words - 1))
    doc_key, line_key = F.xxhash64("doc_id", "text_key"), F.xxhash64("doc_id", "text_key", "line")
    filled = wanted.select(F.explode(F.array(doc_key, line_key)).alias("k"))
    table = materialize(_dense(filled.groupBy(at(F.col("k")).alias("at")).agg(F.bit_or(_filter_mask(F.col("k"))).alias("v")), words), "filter")
    held = lambda k: F.get(table.scalar(), at(k).cast("int")).bitwiseAND(_filter_mask(k)) == _filter_mask(k)
    t = F.coalesce(F.col(text), F.lit(""))
    some = docs.select(F.col(doc_id).alias("doc_id"), t.alias("_text"), F.xxhash64(t).alias("text_key")).where(held(doc_key))
    lines = some.select("doc_id", "text_key", F.posexplode(F.split("_text", "\n")).alias("line", "_text")).where(held(line_key))
    same = lines["doc_id"].eqNullSafe(wanted["doc_id"]) & (lines["text_key"] == wanted["text_key"]) & (lines["line"] == wanted["line"])
    chosen = lines.join(wanted, same).select(F.struct("set", F.struct(wanted["doc_id"], wanted["text_key"], wanted["line"]).alias("place")).alias("owner"), "_text")
    codes = coded_lines(chosen, ranks, buckets, "owner", "_text", worded=False).select("doc_id.set", "doc_id.place", "codes")
    # Rows that repeat id and text hold the same lines.
    codes = codes.groupBy("set").agg(F.first("place").alias("place"), F.first("codes").alias("codes")) if repeated else codes
    codes = materialize(codes, "codes")
    a = codes.select(F.col("set").alias("a"), F.col("codes").alias("ca"), F.col("place").alias("pa"))
    b = codes.select(F.col("set").alias("b"), F.col("codes").alias("cb"), F.col("place").alias("pb"))
    p, q = SIMILAR
    same = F.expr(f"{p + q} * size(array_intersect(ca, cb)) >= {p} * (size(ca) + size(cb))")
    found = pairs.join(a, "a").join(b, "b").where(same).select(F.when(F.col("pa") < F.col("pb"), F.col("b")).otherwise(F.col("a")).alias("set"))
    found = materialize(found.distinct(), "later")
    for t in (used, wanted, table, codes):
        release(t)
    return found


def _sets(docs: DataFrame, ranks: DataFrame, buckets: int, doc_id: str, text: str) -> DataFrame:
    """Distinct sets of words with their first place: ``set, doc_id, text_key, line, n, bits,
    more, prefix``; the last three only of sets that can match others than equals.

    For each of 64 bits the parity of the words that fall on it: sets differ in at least as
    many words as bits. Of longer lines also of half of the words, which makes 128 bits.
    """
    one = [1 << k if k < 63 else -(1 << 63) for k in range(64)]
    parity, half = (f"aggregate(codes, 0L, (a, c) -> a ^ array({', '.join(f'{x + 1}L - 1L' if x < 0 else f'{x}L' for x in t)})[c & {len(t) - 1}])" for t in (one, [0] * 64 + one))
    coded = coded_lines(docs, ranks, buckets, doc_id, text).withColumn("n", F.size("codes"))
    own = [F.expr(f"if(n {over}, {x}, null)").alias(c) for c, over, x in (("bits", f">= {SMALLEST}", parity), ("more", f"> {WIDE}", half), ("prefix", f">= {SMALLEST}", f"slice(codes, 1, {_prefix('n')})"))]
    coded = coded.select("doc_id", "text_key", "line", "n", F.xxhash64("codes").alias("sig"), *own)
    first = F.min(F.struct("doc_id", "text_key", "line", "n", "bits", "more", "prefix")).alias("x")
    # Numbers instead of hashes, as near ones take less room when they move.
    return materialize(coded.groupBy("sig").agg(first).select(F.monotonically_increasing_id().alias("set"), "x.*"), "sets")


def _lead_pairs(sets: DataFrame) -> DataFrame | None:
    """Each set with a fixed number of first ones of some of its frequent words: linear, and
    settles most that can go of a large group of near copies. None if comparing all sets that
    share a frequent word takes no more than ``LIGHT`` comparisons a set. Of a prefix the last words are
    the ones that near copies share; the first are those by which they differ."""
    frequent = sets.where(f"n >= {SMALLEST}").select(F.explode("prefix").alias("code")).where(F.col("code") >= F.lit(HOT << 56))
    work = frequent.groupBy("code").count().agg(F.sum(F.col("count").cast("double") * F.col("count"))).first()[0] or 0
    if work <= LIGHT * sets.count():
        return None
    codes = F.posexplode(F.expr(f"slice(prefix, greatest(size(prefix) - {LEAD - 1}, 1), {LEAD})")).alias("i", "code")
    lead = sets.where(f"n >= {SMALLEST}").select("set", "n", "bits", "more", "doc_id", codes).where(F.col("code") >= F.lit(HOT << 56))
    lead = materialize(lead.withColumn("i", F.expr(f"i + greatest({_prefix('n')} - {LEAD}, 0)")), "lead")
    first = F.min(F.struct("doc_id", "set", "n", "i", "bits", "more")).alias("x")
    leaders = lead.groupBy("code", F.expr(f"pmod(set, {LEADERS})").alias("class")).agg(first, F.count(F.lit(1)).alias("c"))
    leaders = leaders.groupBy("code").agg(F.collect_list("x").alias("xs"), F.sum("c").alias("c")).where("c > 1").select("code", F.inline("xs"))
    near = lead.alias("x").join(leaders.alias("y"), F.expr(f"x.code = y.code and x.set <> y.set and {_may_match('x', 'y')}"))
    pairs = materialize(near.select(F.expr("least(x.set, y.set)").alias("a"), F.expr("greatest(x.set, y.set)").alias("b")).distinct(), "lead-pairs")
    release(lead)
    return pairs


def _pairs(sets: DataFrame) -> DataFrame:
    """``(a, b)``: all pairs of sets that pass the filters, but those that are both gone.

    A set looks by its prefix for those of as many words or fewer, which it finds by a shorter
    one. Both sides are the same postings, shuffled once: that the smaller set's word is in the
    shorter prefix is asked of a pair, since Spark would ask it of one side before the shuffle.
    ``set`` is given as ``-1 - set`` if it is gone, ``i`` so beyond the shorter prefix.
    """
    p, q = SIMILAR
    some = sets.where(f"n >= {SMALLEST}").select(F.expr("if(gone, -1 - set, set)").alias("set"), "n", "bits", "more", "prefix")
    posted = some.select("set", "n", "bits", "more", F.posexplode("prefix").alias("i", "code"))
    # Of a code 32 bits move: two words on one key only cost time.
    key = F.col("code").bitwiseAND(F.lit((1 << 32) - 1)).alias("key")
    # Bytes that vary stand together, which compresses better.
    posted = posted.select("more", F.expr(f"if(i < {_short_prefix('n')}, i, -1 - i)").alias("i"), "n", "set", key, "bits")
    a, b = (f"if({t}.set < 0, -1 - {t}.set, {t}.set)" for t in ("x", "y"))
    # Of sets of one size the one looks for the other once. What is cheap and seldom true comes first.
    once = f"if(y.i < 0, {(1 << 31) - 1}, y.n) <= x.n and {q} * y.n >= {p} * x.n and (y.n < x.n or {b} < {a}) and (x.set >= 0 or y.set >= 0)"
    near = posted.alias("x").join(posted.alias("y"), F.expr(f"x.key = y.key and {once} and {_may_match('x', 'y')}"))
    return near.select(F.expr(f"least({a}, {b})").alias("a"), F.expr(f"greatest({a}, {b})").alias("b")).distinct()


def kept_lines(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, text_key, copies, n_lines, n_eligible, kept``: rows with equal id and text
    are one with ``copies``; ``kept`` are the eligible lines (from 0) that stay. Eligible are
    all lines that have a word. Of fewer than ``SMALLEST`` words a line matches only equal
    sets, which grouping finds.

    Equal lines of rows that repeat id and text stand at the same place, so all stay or go
    together. Null ids come first in order; a null text is one line without words. Extra
    columns are not returned.
    """
    lines = F.split(F.coalesce(F.col(text), F.lit("")), "\n")
    each = docs.select(F.col(doc_id).alias("doc_id"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("text_key"), lines.alias("lines"))
    each = each.select("doc_id", "text_key", F.size("lines").cast("long").alias("n_lines"), F.size(F.filter("lines", _worded)).cast("long").alias("n_eligible"))
    per_doc = materialize(each.groupBy("doc_id", "text_key").agg(F.count(F.lit(1)).alias("copies"), F.max("n_lines").alias("n_lines"), F.max("n_eligible").alias("n_eligible")), "per-doc")
    repeated = per_doc.where("copies > 1").limit(1).count() > 0
    buckets = bucket_count(docs)
    ranks = word_ranks(docs, buckets, text)
    sets = _sets(docs, ranks, buckets, doc_id, text)
    pairs = _lead_pairs(sets)
    some = pairs is not None and pairs.limit(1).count() > 0
    flagged, small = sets.withColumn("gone", F.lit(False)), True
    if some:
        gone = _later(pairs, sets, docs, ranks, buckets, repeated, doc_id, text).withColumn("gone", F.lit(True))
        small = gone.count() <= BROADCAST_SETS
        flagged = sets.join(F.broadcast(gone) if small else gone, "set", "left").withColumn("gone", F.coalesce("gone", F.lit(False)))
    if not small:
        flagged = materialize(flagged, "flagged")
        release(sets)
    collect_garbage(docs.sparkSession)
    rest = _pairs(flagged)
    rest = materialize(rest.join(pairs, ["a", "b"], "left_anti") if some else rest, "pairs")
    collect_garbage(docs.sparkSession)
    more = _later(rest, flagged, docs, ranks, buckets, repeated, doc_id, text)
    stay = flagged.where("not gone").join(_few(more), "set", "left_anti").groupBy("doc_id", "text_key").agg(F.sort_array(F.collect_list("line")).alias("kept"))
    stay = materialize(stay.select(F.col("doc_id").alias("_id"), F.col("text_key").alias("_key"), "kept"), "stay")
    for t in (ranks, *([pairs] if pairs else []), rest, more, *([gone] if some else []), sets if small else flagged):
        release(t)
    out = per_doc.join(stay, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("text_key") == F.col("_key")), "left")
    return out.select("doc_id", "text_key", "copies", "n_lines", "n_eligible", F.coalesce("kept", F.expr("cast(array() as array<int>)")).alias("kept"))


def dedup_lines(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` without the lines that match an earlier one; all rows and columns stay.

    Lines without a word stay; a null text stays null."""
    changed = kept_lines(docs, doc_id, text).where("size(kept) < n_eligible")
    changed = materialize(changed.select(F.col("doc_id").alias("_id"), F.col("text_key").alias("_key"), F.col("kept").alias("_kept")), "changed")
    on = docs[doc_id].eqNullSafe(F.col("_id")) & (F.xxhash64(F.coalesce(docs[text], F.lit(""))) == F.col("_key"))
    joined = docs.join(changed, on, "left")
    cut = F.array_join(F.filter(F.split(text, "\n"), lambda line, i: F.array_contains("_kept", i) | ~_worded(line)), "\n")
    return joined.select(*[F.when(F.col("_kept").isNull(), F.col(text)).otherwise(cut).alias(text) if c == text else docs[c] for c in docs.columns])


def op3_line_dedup(spark, sf_dir):
    """Per document: its lines, those that have a word, those removed, and which stay."""
    found = kept_lines(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select(
        F.explode(F.array_repeat(F.lit(1), F.col("copies").cast("int"))).alias("copy"),
        "doc_id", "n_lines", "n_eligible", (F.col("n_eligible") - F.size("kept")).alias("n_removed"),
        F.array_join(F.col("kept").cast("array<string>"), ",").alias("kept_lines"),
    ).drop("copy")


_P, _Q = SIMILAR
OP3_SQL = rf"""
with lines as (
  select doc_id, cast(i - 1 as int) as line, list_sort(list_distinct(list_filter(string_split_regex(ls[i], '{SPACES}'), lambda x: x <> ''))) as ws
  from (select doc_id, ls, unnest(range(1, len(ls) + 1)) as i
        from (select doc_id, string_split(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), chr(10)) as ls from documents))
), e as (select *, array_to_string(ws, ' ') as k from lines where len(ws) >= 1),
sets as (select k, min((doc_id, line)) as place, any_value(ws) as ws from e group by k),
words as (select k, len(ws) as n, unnest(ws) as w from sets),
df as (select w, count(*) as c from words group by w),
ranked as (select k, n, w, row_number() over (partition by k order by c, w) as r from words join df using (w)),
pre as (select k, n, w from ranked where r <= n - ({_P} * n + {_Q - 1}) // {_Q} + 1),
pairs as (select distinct a.k as x, b.k as y from pre a join pre b on a.w = b.w and a.k <> b.k and {_Q} * least(a.n, b.n) >= {_P} * greatest(a.n, b.n)),
gone as (
  select distinct y as k from pairs join sets a on a.k = x join sets b on b.k = y
  where a.place < b.place and {_P + _Q} * len(list_intersect(a.ws, b.ws)) >= {_P} * (len(a.ws) + len(b.ws))
), stay as (select e.doc_id, e.line from e join sets using (k) where place = (doc_id, line) and k not in (select k from gone))
select doc_id, count(*) as n_lines, count(*) filter (where len(ws) >= 1) as n_eligible,
       count(*) filter (where len(ws) >= 1) - count(stay.line) as n_removed,
       coalesce(string_agg(cast(stay.line as varchar), ',' order by stay.line), '') as kept_lines
from lines left join stay using (doc_id, line) group by doc_id
"""
