"""License detection by ordered signature rules (operator 4, DataFrame functions only).

Signatures are regular expressions over a text's words, which stand in lower case with a
space before and after each. A signature is tried only where one of its keywords occurs,
of which each text that it matches has one. Of two
detections, one that lies within another of the same or a higher rank is dropped.
"""

from __future__ import annotations

import json
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peakgroups.llm.text import alnum_words, guarded

#: Base phrases and their labels: fixed values.
PHRASES = {"gnu general public license": "gpl", "apache license": "apache", "cc by": "cc-by", "mit license": "mit"}

#: label, keywords of which every name has one, how the license is named, its identifier as
#: words. Written by hand.
FAMILIES = (
    ("gpl", "gnu", r"gnu (?:general public licen[sc]e|gpl)(?: (?:version|v) ?[123])?", r"gpl [123](?: 0)?(?: only| or later)?"),
    ("gpl", "gpl gplv1 gplv2 gplv3 gpl1 gpl2 gpl3", r"gpl(?: ?v?[123])?(?: or later)?", r"gpl v?[123]"),
    ("lgpl", "lesser", r"(?:gnu )?lesser general public licen[sc]e", r"lgpl [23](?: [01])?(?: only| or later)?"),
    ("lgpl", "lgpl lgplv2 lgplv3 lgpl2 lgpl3", r"(?:gnu )?lgpl(?: ?v?[23])?", r"lgpl v?[23]"),
    ("agpl", "affero", r"(?:gnu )?affero general public licen[sc]e", r"agpl 3(?: 0)?(?: only| or later)?"),
    ("agpl", "agpl agplv3 agpl3", r"(?:gnu )?agpl(?: ?v?3)?", r"agpl v?3"),
    ("apache", "apache", r"apache(?: software)? licen[sc]e(?: version [12](?: [01])?)?", r"apache [12](?: [01])?"),
    ("mit", "mit", r"mit(?: expat)? licen[sc]e", r"mit"),
    ("mit", "expat", r"expat licen[sc]e", r"expat"),
    ("bsd", "bsd", r"(?:[234] clause )?(?:new |modified |simplified |revised )?bsd(?: style)? licen[sc]e", r"bsd [0234] clause"),
    ("mpl", "mozilla", r"mozilla public licen[sc]e(?: version [12](?: [01])?)?", r"mpl [12](?: [01])?"),
    ("epl", "eclipse", r"eclipse public licen[sc]e(?: v?[12](?: 0)?)?", r"epl [12](?: 0)?"),
    ("cc-by", "attribution", r"creative commons attribution(?: [1234](?: 0)?)?(?: international)?(?: licen[sc]e)?", r"cc by [1234](?: 0)?"),
    ("cc-by-sa", "attribution", r"(?:creative commons )?attribution share ?alike(?: [1234](?: 0)?)?", r"cc by sa(?: [1234](?: 0)?)?"),
    ("cc-by-nc", "attribution", r"(?:creative commons )?attribution non ?commercial(?: [1234](?: 0)?)?", r"cc by nc(?: [1234](?: 0)?)?"),
    ("cc0", "cc0", r"cc0(?: 1 0)?(?: universal)?", r"cc0 1(?: 0)?"),
    ("public-domain", "domain", r"public domain", r"pddl 1(?: 0)?"),
    ("unlicense", "unlicense", r"unlicense", r"unlicense"),
    ("isc", "isc", r"isc licen[sc]e", r"isc"),
    ("zlib", "zlib", r"zlib(?: libpng)? licen[sc]e", r"zlib"),
    ("boost", "boost", r"boost software licen[sc]e(?: version 1 0)?", r"bsl 1 0"),
    ("artistic", "artistic", r"artistic licen[sc]e(?: [12](?: 0)?)?", r"artistic [12](?: 0)?"),
    ("wtfpl", "wtfpl", r"wtfpl", r"wtfpl"),
    ("cddl", "cddl", r"cddl(?: 1 [01])?", r"cddl 1 [01]"),
    ("eupl", "eupl", r"eupl(?: 1 [012])?", r"eupl 1 [012]"),
    ("ofl", "ofl font", r"(?:sil )?(?:open font licen[sc]e|ofl)(?: 1 1)?", r"ofl 1 [01]"),
    ("postgresql", "postgresql", r"postgresql licen[sc]e", r"postgresql"),
    ("psf", "python", r"python software foundation licen[sc]e", r"psf 2(?: 0)?"),
    ("php", "php", r"php licen[sc]e(?: version 3(?: 0\d?)?)?", r"php 3(?: 0\d?)?"),
    ("gfdl", "documentation", r"(?:gnu )?free documentation licen[sc]e", r"gfdl 1 [123]"),
)
#: name, rank (1 the highest), confidence, pattern around NAME or ID, ordered.
SHAPES = (
    ("identifier", 1, 1.0, r"spdx licen[sc]e identifier ID"),
    ("licensed", 2, 0.95, r"(?:dual )?licen[sc]ed (?:to you )?under (?:the )?(?:terms of (?:the )?)?NAME"),
    ("released", 2, 0.95, r"released under (?:the )?(?:terms of (?:the )?)?NAME"),
    ("distributed", 2, 0.95, r"(?:re)?distributed under (?:the )?(?:terms of (?:the )?)?NAME"),
    ("available", 2, 0.9, r"(?:made )?available under (?:the )?(?:terms of (?:the )?)?NAME"),
    ("terms", 2, 0.9, r"under the terms (?:and conditions )?of (?:the )?NAME"),
    ("covered", 2, 0.85, r"(?:covered|governed|protected) by (?:the )?NAME"),
    ("subject", 2, 0.85, r"subject to (?:the )?(?:terms of (?:the )?)?NAME"),
    ("copy", 2, 0.8, r"(?:a )?copy of (?:the )?NAME"),
    ("mention", 3, 0.6, r"NAME"),
)
#: label, keywords, a sentence of the license's own text. Written by hand.
BODIES = (
    ("mit", "hereby", r"permission is hereby granted free of charge to any person obtaining a copy of this software"),
    ("boost", "hereby", r"permission is hereby granted free of charge to any person or organization obtaining a copy of the software"),
    ("isc", "hereby", r"permission to use copy modify and (?:or )?distribute this software for any purpose with or without fee is hereby granted"),
    ("bsd", "redistribution", r"redistribution and use in source and binary forms with or without modification are permitted"),
    ("zlib", "liable", r"this software is provided as is without any express or implied warranty in no event will the authors be held liable"),
    ("unlicense", "unencumbered", r"this is free and unencumbered software released into the public domain"),
)


@dataclass(frozen=True)
class Signature:
    label: str
    keywords: list[str]
    rank: int
    confidence: float
    pattern: str


def signatures() -> list[Signature]:
    """Every shape for every family, 300 rules, and the bodies, by rank and then as listed."""
    made = [
        Signature(label, ["spdx"] if "ID" in shape else keywords.split(), rank, sure, shape.replace("NAME", f"(?:{name})").replace("ID", f"(?:{ident})"))
        for _, rank, sure, shape in SHAPES
        for label, keywords, name, ident in FAMILIES
    ]
    made += [Signature(label, keywords.split(), 2, 0.9, text) for label, keywords, text in BODIES]
    return sorted(made, key=lambda s: s.rank)


def _base_places() -> str:
    whens = " ".join(
        "when " + " and ".join(f"{'w' if k == 0 else f'get(words, i + {k})'} = '{word}'" for k, word in enumerate(phrase.split())) + f" then struct(i as at, '{label}' as label)"
        for phrase, label in PHRASES.items()
    )
    return f"filter(transform(words, (w, i) -> case {whens} end), x -> x is not null)"


#: Each signature has a word that says it is about a license, or one used for little else.
WORDED = " (?:licen[sc]e[sd]?|spdx|unlicense|wtfpl|cc0|[al]?gpl(?:v?[123])?|cddl|eupl|ofl|gnu|domain|attribution|released|distributed|bsd|hereby|redistribution|liable|unencumbered) "

# Words that a signature covers are marked at both ends; as words hold no control
# characters, the marks give the places of the first and the last word.
_DETECTIONS = r"""
  flatten(transform(filter(rules, r -> exists(r.keywords, k -> contains(joined, concat(' ', k, ' ')))), r ->
    transform(
      filter(array(split(regexp_replace(joined, concat('(?<= )(?:', r.pattern, ')(?= )'), concat(unhex('01'), '$0', unhex('02'))), ' ')), m -> size(m) > 0),
      m -> struct(r.rank as rank, r.label as label, r.confidence as confidence,
             filter(transform(m, (w, i) -> if(startswith(w, string(unhex('01'))), i - 1, null)), i -> i is not null) as firsts,
             filter(transform(m, (w, i) -> if(endswith(w, string(unhex('02'))), i - 1, null)), i -> i is not null) as lasts))))
"""


# In order of first word, longest first, a span lies within an earlier one of its rank or a
# higher one exactly if the furthest end so far in those ranks is not before its own.
_UNSUPPRESSED = """
  aggregate(spans,
    struct(-1 as e1, -1 as e2, -1 as e3,
           cast(array() as array<struct<first: int, last: int, rank: int, label: string, confidence: double>>) as kept),
    (a, s) -> struct(
      if(s.rank = 1, greatest(a.e1, -s.back), a.e1) as e1,
      if(s.rank <= 2, greatest(a.e2, -s.back), a.e2) as e2,
      greatest(a.e3, -s.back) as e3,
      if(-s.back > case s.rank when 1 then a.e1 when 2 then a.e2 else a.e3 end,
         array_append(a.kept, struct(s.first as first, -s.back as last, s.rank as rank, s.label as label, s.confidence as confidence)),
         a.kept) as kept),
    a -> a.kept)
"""


def scan(docs: DataFrame, rules: list[Signature] | None = None, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each row of ``docs``.

    ``n_words``; of the base phrases ``n_base``, ``first_word``, ``last_word`` and
    ``base_labels``; ``detections``, an array of ``(first, last, rank, label,
    confidence)`` in word places with the suppressed ones left out; ``labels`` with the
    base ones; and ``score``, the highest confidence (0.7 for a base phrase, 0 for
    none). A null text counts as empty: no words, no labels, null places.
    """
    table = json.dumps([s.__dict__ for s in rules or signatures()])
    shape = "array<struct<label: string, keywords: array<string>, rank: int, confidence: double, pattern: string>>"
    d = docs.select(F.col(doc_id).alias("doc_id"), alnum_words(F.col(text)).alias("words"))
    d = d.withColumn("joined", F.concat(F.lit(" "), F.array_join("words", " "), F.lit(" ")))
    gate = " or ".join(f"contains(joined, ' {p} ')" for p in PHRASES)
    d = d.withColumn("places", F.expr(f"if({gate}, {_base_places()}, cast(array() as array<struct<at: int, label: string>>))"))
    worded = f"joined rlike '{WORDED}'"
    d = d.withColumn("rules", F.from_json(F.lit(table), shape))
    found = f"if({worded}, {_DETECTIONS}, null)"
    d = d.withColumn("found", F.expr(found)).drop("rules")
    spans = """
      array_sort(flatten(transform(coalesce(found, array()), r -> transform(arrays_zip(r.firsts, r.lasts), p ->
        struct(p.firsts as first, -p.lasts as back, r.rank as rank, r.label as label, r.confidence as confidence)))))
    """
    d = d.withColumn("spans", F.expr(spans))
    d = d.withColumn("detections", F.expr(_UNSUPPRESSED))
    base = F.array_sort(F.array_distinct(F.col("places.label")))
    return d.select(
        "doc_id",
        guarded(F.size("words").cast("long")).alias("n_words"),
        guarded(F.size("places").cast("long")).alias("n_base"),
        F.array_min("places.at").cast("long").alias("first_word"),
        F.array_max("places.at").cast("long").alias("last_word"),
        guarded(F.array_join(base, ",")).alias("base_labels"),
        guarded(F.array_join(F.array_sort(F.array_union(base, F.col("detections.label"))), ",")).alias("labels"),
        F.greatest(F.when(F.size("places") > 0, 0.7).otherwise(0.0), F.coalesce(F.array_max("detections.confidence"), F.lit(0.0))).alias("score"),
        guarded(F.col("detections")).alias("detections"),
    )


def op4_license_scan(spark, sf_dir):
    return scan(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop("detections")
