"""URL rules through a cascade of Bloom filters (operator 9, DataFrame functions only).

Level 1 holds the listed keys, level 2 the keys of the corpus that level 1 takes for
listed by mistake, level 3 the listed keys that level 2 would throw out, and so on until
no mistake is left. As the levels are built against every key that occurs in the corpus,
the answer for each of these keys is exact, and judging a row takes a few bit tests and
no join.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from peakgroups.functions.storage import materialize
from peakgroups.llm.text import LOWER, UPPER

#: Bits that all levels of a cascade may hold together: 8 MB in each task.
MAX_BITS = 1 << 26


@dataclass(frozen=True)
class Level:
    seed: int
    hashes: int
    bits: int
    words: tuple[int, ...]

    def _place(self, key: Column, j: int) -> Column:
        return F.pmod(F.xxhash64(key, F.lit(self.seed), F.lit(j)), F.lit(self.bits))

    def holds(self, key: Column) -> Column:
        """True for every key that was put in, and for a few others."""
        table = F.split(F.lit(",".join(map(str, self.words))), ",").cast("array<bigint>")
        out = F.lit(True)
        for j in range(self.hashes):
            p = self._place(key, j)
            word = F.get(table, F.floor(p / 64).cast("int"))
            out = out & (F.call_function("getbit", word, (p % 64).cast("int")) == 1)
        return out


@dataclass(frozen=True)
class Cascade:
    levels: tuple[Level, ...]

    def contains(self, key: Column) -> Column:
        """Exact for every key of the universe that the cascade was built over."""
        out = F.lit(len(self.levels) % 2 == 1)
        for at in range(len(self.levels) - 1, -1, -1):
            out = F.when(self.levels[at].holds(key), out).otherwise(F.lit(at % 2 == 1))
        return out


def _level(keys: DataFrame, count: int, rate: float, seed: int) -> Level:
    hashes = max(1, min(24, math.ceil(-math.log2(rate))))
    bits = 64 * max(1, math.ceil(count * hashes / math.log(2) / 64))
    empty = Level(seed, hashes, bits, ())
    places = keys.select(F.explode(F.array(*[empty._place(F.col("key"), j) for j in range(hashes)])).alias("p"))
    set_words = (
        places.groupBy(F.floor(F.col("p") / 64).cast("int").alias("w"))
        .agg(F.expr("bit_or(shiftleft(1L, cast(p % 64 as int)))").alias("v"))
        .collect()
    )  # at most bits / 64 rows
    words = [0] * (bits // 64)
    for r in set_words:
        words[r.w] = r.v
    return Level(seed, hashes, bits, tuple(words))


def build_cascade(listed: DataFrame, universe: DataFrame, max_bits: int = MAX_BITS) -> Cascade:
    """A cascade that holds ``listed(key)``, exact on ``listed`` and ``universe(key)``.

    Null keys belong to neither. An empty list gives a cascade that holds nothing.
    Raises ValueError beyond ``max_bits``; split the list by a hash of the key then.
    """
    listed = materialize(listed.select("key").where("key is not null").distinct(), "listed")
    others = materialize(universe.select("key").where("key is not null").distinct().join(listed, "key", "left_anti"), "others")
    held, held_n, against, against_n = listed, listed.count(), others, others.count()
    levels: list[Level] = []
    while held_n:
        rate = min(0.5, held_n * math.sqrt(0.5) / against_n) if against_n and not levels else 0.5
        level = _level(held, held_n, rate, len(levels))
        levels.append(level)
        if sum(x.bits for x in levels) > max_bits:
            raise ValueError(f"a cascade over {held_n} keys needs more than {max_bits} bits")
        mistaken = materialize(against.where(level.holds(F.col("key"))), "mistaken")
        held, held_n, against, against_n = mistaken, mistaken.count(), held, held_n
    return Cascade(tuple(levels))


@dataclass(frozen=True)
class Rule:
    host: str
    path: str
    verdict: str

    @property
    def key(self) -> str:
        return self.host + self.path


def url_parts(url: Column) -> tuple[Column, Column]:
    """Host and path. Without ``://``, and for null, both are empty."""
    at = F.locate("://", url)
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    host = F.translate(F.regexp_extract(rest, "^[^/?#]*", 0), UPPER, LOWER)
    return host, F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1)


def _candidates(rules: list[Rule]) -> Column:
    """Keys of a row, longest first: the host's last labels with the path's first
    characters, in each shape that some rule has. Null where the row is too short."""
    shapes = {(r.host.count(".") + 1, len(r.path), len(r.host)) for r in rules}
    keys = []
    for labels, chars in sorted({s[:2] for s in shapes}):
        host = F.substring_index("host", ".", -labels)
        enough = (F.length("path") >= chars) & (F.length("host") - F.length(F.replace(F.col("host"), F.lit("."), F.lit(""))) >= labels - 1)
        keys.append(F.when(enough, F.concat(host, F.substring("path", 1, chars))))
    return F.array_compact(F.array(*keys))


def judge_urls(pages: DataFrame, rules: list[Rule], default: str = "allow", page_id: str = "page_id", url: str = "url") -> DataFrame:
    """``page_id, host, path, rule, verdict`` for each row, repeated rows included.

    A rule fits its host and all subdomains where the path starts with the rule's path;
    the rule with the longest host and path wins (of two as long, the longer host). Where
    none fits, ``rule`` is null and the verdict is ``default``. A null URL, or one without
    ``://``, has empty host and path and fits no rule. Other columns are not returned.
    """
    host, path = url_parts(F.col(url))
    rows = pages.select(F.col(page_id).alias("page_id"), host.alias("host"), path.alias("path"))
    spark = pages.sparkSession
    keyed = rows.withColumn("keys", _candidates(rules))
    universe = keyed.select(F.explode("keys").alias("key"))
    every = spark.createDataFrame([(r.key,) for r in rules], "key string")
    blocked = spark.createDataFrame([(r.key,) for r in rules if r.verdict == "block"], "key string")
    listed, blocks = build_cascade(every, universe), build_cascade(blocked, every)
    fit = F.filter("keys", listed.contains)
    longest = F.array_max(F.transform(fit, lambda k: F.struct(F.length(k).alias("n"), F.instr(k, "/").alias("h"), k.alias("k")))).getField("k")
    return keyed.select("page_id", "host", "path", longest.alias("rule")).select(
        "page_id", "host", "path", "rule",
        F.when(F.col("rule").isNull(), F.lit(default)).when(blocks.contains(F.col("rule")), F.lit("block")).otherwise(F.lit("allow")).alias("verdict"),
    )


#: Rules of the registered query: fixed values.
RULES = [
    Rule("org", "/", "allow"),
    Rule("example.org", "/es/", "block"),
    Rule("example.org", "/en/1", "block"),
    Rule("com", "/fr/", "allow"),
    Rule("com", "/de/", "block"),
]


def op9_url_filter(spark, sf_dir):
    return judge_urls(spark.read.parquet(f"{sf_dir}/pages.parquet"), RULES)


_FITS = " ".join(
    f"when (host = '{r.host}' or ends_with(host, '.{r.host}')) and starts_with(path, '{r.path}') then '{r.key}'"
    for r in sorted(RULES, key=lambda r: -len(r.key))
)
_BLOCKED = ", ".join(f"'{r.key}'" for r in RULES if r.verdict == "block")
OP9_SQL = f"""
with rest as (
  select page_id, case when strpos(url, '://') > 0 then substr(url, strpos(url, '://') + 3) else '' end as rest from pages
), parts as (
  select page_id, translate(regexp_extract(rest, '^[^/?#]*'), '{UPPER}', '{LOWER}') as host,
         regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) as path from rest
), ruled as (select page_id, host, path, case {_FITS} end as rule from parts)
select page_id, host, path, rule, case when rule in ({_BLOCKED}) then 'block' else 'allow' end as verdict from ruled
"""
