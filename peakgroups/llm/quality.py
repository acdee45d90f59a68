"""Quality rules as a short-circuit cascade (operator 6, DataFrame functions only).

Each rule is an SQL predicate that is true for a bad text. Their cost and the share of
texts they reject are measured on a random sample; the cascade then asks first the rule
with the most rejections per second, and a text that fails one rule is asked no other.
Where only the verdict is wanted (:func:`keep_good`), the base is two rules among the others
and what a rule counts is counted when the cascade comes to it, so a rejected text never
meets the rules behind. :func:`judge` returns the counts of every text, so its cascade
orders what is left to ask of them. The order never changes a verdict, only the time.
"""

from __future__ import annotations

import re
import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peakgroups.functions.storage import materialize, release
from peakgroups.llm.text import guarded, space_words, window_keys


@dataclass(frozen=True)
class QualityRule:
    name: str
    bad: str  # SQL over text, n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words


#: Production rules beyond the base. Ratios are to the words or characters of the text.
RULES = (
    QualityRule("symbols", "10 * n_symbols > n_words"),
    QualityRule("repeated_lines", "n_dup_lines > 3 and 10 * n_dup_lines > 3 * n_lines"),
    QualityRule("word_length", "word_chars < 2 * n_words or word_chars > 16 * n_words"),
    QualityRule("exclamation", "5 * (char_length(text) - char_length(replace(text, '!', ''))) > n_words"),
    QualityRule("capitals", "2 * char_length(regexp_replace(text, '[^A-Z]+', '')) > word_chars"),
    QualityRule("stutter", r"5 * regexp_count(text, '(?<![^ ])([^ ]+) (?=\\1(?![^ ]))') > n_words"),
    QualityRule("digits", "2 * char_length(regexp_replace(text, '[^0-9]+', '')) > word_chars"),
)
BASE_FAILED = "n_words < 20 or 100 * n_repeat_words > 30 * n_words"
#: The base, as rules of the cascade where only the verdict is wanted.
BASE = (QualityRule("few_words", "n_words < 20"), QualityRule("repeated_words", "100 * n_repeat_words > 30 * n_words"))
#: Expected rows of the sample on which cost and selectivity are estimated, and how often
#: a rule is asked about each, so that its time stands out from that of starting a job.
SAMPLE_ROWS, TIMES = 256, 3

# Starts of the windows that occur twice or more: in order of key and place, those whose
# neighbour has the same key.
_STARTS = """
  sort_array(transform(
    filter(
      transform(ordered, (x, i) -> struct(x.at as at,
        coalesce(x.key = get(ordered, i - 1).key, false) or coalesce(x.key = get(ordered, i + 1).key, false) as twice)),
      x -> x.twice),
    x -> x.at))
"""
# Words under the windows at the sorted starts.
_COVERED = """
  aggregate(starts, struct(0 as upto, 0 as n),
            (a, s) -> struct(s + 8 as upto, a.n + s + 8 - greatest(a.upto, s) as n), a -> cast(a.n as bigint))
"""
_ORDERED = """
  if(size(array_distinct(keys)) = size(keys), cast(null as array<struct<key: bigint, at: int>>),
     sort_array(transform(keys, (k, i) -> struct(k as key, i as at))))
"""


#: What is counted, as SQL over ``text``, ``words`` and what stands before it here.
COUNTS = {
    "lines": r"filter(split(text, '\n'), x -> x rlike r'[^\x20\x09-\x0D]')",
    "keys": window_keys("words", 8),
    "ordered": _ORDERED,
    "starts": f"if(ordered is null, cast(null as array<int>), {_STARTS})",
    "n_words": "cast(size(words) as bigint)",
    "word_chars": "cast(char_length(concat_ws('', words)) as bigint)",
    "n_symbols": "cast(char_length(text) - char_length(regexp_replace(text, '[#*$%&|<>]+', '')) as bigint)",
    "n_lines": "cast(size(lines) as bigint)",
    "n_dup_lines": "cast(size(lines) - size(array_distinct(lines)) as bigint)",
    "n_repeat_words": f"if(starts is null, 0L, {_COVERED})",
}


def _worded(docs: DataFrame, doc_id: str, text: str, whole_row: bool = False) -> DataFrame:
    row = [F.struct("*").alias("row")] if whole_row else []
    d = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"), *row)
    return d.withColumn("words", space_words(F.col("text")))


def measures(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, text, n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words``.

    A null text counts as empty. A word is in ``n_repeat_words`` if it lies in a window
    of eight words that occurs twice or more in its text. Only texts in which some window
    key occurs twice sort their keys; all others stop at a hash set.
    """
    d = _worded(docs, doc_id, text)
    for name in ("lines", "keys", "ordered", "starts"):
        d = d.withColumn(name, F.expr(COUNTS[name]))
    free = ("word_chars", "n_symbols", "n_lines")  # what a filter may ask anew at no great cost
    counts = (name for name in COUNTS if name.startswith("n_") or name == "word_chars")
    return d.select("doc_id", "text", *((F.expr(COUNTS[c]) if c in free else guarded(F.expr(COUNTS[c]))).alias(c) for c in counts))


def on_demand(bad: str) -> str:
    """The predicate ``bad`` as one over ``text`` and ``words``, which makes the counts it names
    itself, each once: a name is bound as the one element of an array."""
    for name in reversed(COUNTS):
        if re.search(rf"\b{name}\b", bad):
            bad = f"transform(array({COUNTS[name]}), {name} -> {bad})[0]"
    return bad


def ordered_rules(
    docs: DataFrame, ready: Callable[[DataFrame], DataFrame], said: Callable[[str], str] = str, rules=RULES, sample_rows: int = SAMPLE_ROWS
) -> list[tuple[QualityRule, float, float]]:
    """``(rule, seconds, share rejected)``, most rejections per second first; ties as given.

    Measured on a random sample of some ``sample_rows`` rows of ``docs`` made ``ready``.
    ``said`` turns a rule's predicate into one that the sample's columns answer. The seconds
    are the lesser of two runs, less those of a run that asks nothing.
    """
    n = docs.count()
    sample = materialize(ready(docs.sample(min(1.0, sample_rows / max(n, 1)), seed=6)).coalesce(1), "rule-sample")
    asked = sample.withColumn("again", F.explode(F.sequence(F.lit(1), F.lit(TIMES))))

    def run(bad: str):
        count = asked.agg(F.count_if(F.expr(bad)).alias("bad"), F.count(F.lit(1)).alias("n"))
        best = float("inf")
        for _ in range(2):
            began = time.perf_counter()
            bad_rows, rows = count.first()
            best = min(best, time.perf_counter() - began)
        return best, bad_rows / rows if rows else 0.0

    nothing = run("char_length(text) < again - 10")[0]
    found = []
    for rule in rules:
        seconds, share = run(said(rule.bad))
        found.append((rule, max(seconds - nothing, 1e-4), share))
    release(sample)
    return sorted(found, key=lambda x: -x[2] / x[1])


def judge(docs: DataFrame, rules=RULES, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """:func:`measures` with ``base_failed`` and ``kept``; one row for each row of ``docs``.

    A text is kept if neither the base nor any rule finds it bad; a rule that comes out
    null does not reject. Extra columns of ``docs`` are not returned.
    """
    verdict = F.when(F.col("base_failed"), F.lit(False))
    for rule, _, _ in ordered_rules(docs, lambda d: measures(d, doc_id, text), rules=rules):
        verdict = verdict.when(F.expr(rule.bad), F.lit(False))
    return measures(docs, doc_id, text).withColumn("base_failed", F.expr(BASE_FAILED)).withColumn("kept", verdict.otherwise(F.lit(True)))


def keep_good(docs: DataFrame, rules=RULES, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of ``docs`` that :func:`judge` keeps, columns as they came.

    Nulls, ties, repeated rows and empty tables: as there, each row by itself.
    """
    verdict = F
    for rule, _, _ in ordered_rules(docs, lambda d: _worded(d, doc_id, text), on_demand, (*BASE, *rules)):
        verdict = verdict.when(F.expr(on_demand(rule.bad)), F.lit(False))
    d = _worded(docs, doc_id, text, whole_row=True).withColumn("kept", guarded(verdict.otherwise(F.lit(True))))
    return d.where("kept").select("row.*")


def op6_quality_rules(spark, sf_dir):
    out = judge(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


OP6_SQL = r"""
with w as (
  select doc_id, coalesce(text, '') as text, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') as words,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) as lines
  from documents
), g as (
  select doc_id, i, array_to_string(list_slice(words, i, i + 7), ' ') as k from (select doc_id, words, unnest(range(1, len(words) - 6)) as i from w)
), twice as (
  select doc_id, i from (select doc_id, i, count(*) over (partition by doc_id, k) as n from g) where n > 1
), rep as (
  select doc_id, count(distinct p) as n from (select doc_id, unnest(range(i, i + 8)) as p from twice) group by doc_id
), m as (
  select w.doc_id, text, len(words) as n_words, length(array_to_string(words, '')) as word_chars,
         length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) as n_symbols,
         len(lines) as n_lines, len(lines) - len(list_distinct(lines)) as n_dup_lines, coalesce(rep.n, 0) as n_repeat_words
  from w left join rep on w.doc_id = rep.doc_id
), b as (select *, n_words < 20 or 100 * n_repeat_words > 30 * n_words as base_failed from m)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       not (base_failed or 10 * n_symbols > n_words or (n_dup_lines > 3 and 10 * n_dup_lines > 3 * n_lines) or word_chars < 2 * n_words or word_chars > 16 * n_words
            or 5 * (length(text) - length(replace(text, '!', ''))) > n_words
            or 2 * length(regexp_replace(text, '[^A-Z]+', '', 'g')) > word_chars
            or 5 * len(list_filter(range(2, len(sp) + 1), lambda i: sp[i] = sp[i - 1] and sp[i] <> '')) > n_words
            or 2 * length(regexp_replace(text, '[^0-9]+', '', 'g')) > word_chars) as kept
from (select *, string_split(text, ' ') as sp from b)
"""
