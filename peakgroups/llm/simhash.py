"""SimHash near-duplicates with covering locality-sensitive hashing (operator 2).

Each of the 64 bits gets a random non-zero label of ``radius + 1`` bits. Table v, for each
non-zero v, looks at the bits whose label has an odd inner product with v. Two
fingerprints that differ in at most ``radius`` bits agree on all of some table: their
labels leave a non-zero v that is orthogonal to all of them. So no pair can be missed.

Within a bucket nothing is compared pair by pair. With a radius of two, fingerprints lie
within it exactly if some 64-bit value lies within one bit of both; each member names the
values within one bit of it that the bucket allows, and a value is shared by at most 65
fingerprints. Work and rows stay in proportion to the members of a bucket.
"""

from __future__ import annotations

import random
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peakgroups.functions.storage import materialize
from peakgroups.llm.text import ascii_lower, space_words
from peakgroups.operators.components import connected_groups

RADIUS, SEED = 2, 7
#: Hashes whose bits are counted at a time.
CHUNK = 1 << 16


def covering_masks(radius: int = RADIUS, seed: int = SEED) -> list[int]:
    """The ``2 ** (radius + 1) - 1`` masks, as signed 64-bit numbers."""
    width = radius + 1
    labels = [1 + i % (2**width - 1) for i in range(64)]  # every label as often, none zero
    random.Random(seed).shuffle(labels)
    masks = [sum(1 << i for i, a in enumerate(labels) if bin(a & v).count("1") % 2) for v in range(1, 2**width)]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


def _majority(hashes: np.ndarray) -> int:
    """Bits set in over half the hashes, as a signed 64-bit number."""
    ones = np.zeros(64, np.int64)
    for i in range(0, len(hashes), CHUNK):
        block = np.ascontiguousarray(hashes[i : i + CHUNK])
        ones += np.unpackbits(block.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.int64)[0]) if len(hashes) else 0


def fingerprints(docs: DataFrame, shingle: int = 3, keep: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """Columns ``keep`` with ``fp``, a signed 64-bit SimHash.

    Words are runs of non-space, A to Z in lower case; shingles are hashed with XXH64
    (UTF-8, seed 42), repeats included. Of fewer words than ``shingle`` the whole sequence
    is one; a text without words, or null, has fingerprint 0.
    """
    d = docs.select(*keep, space_words(ascii_lower(F.coalesce(F.col(text), F.lit("")))).alias("_words"))
    part = ", ".join(f"_words[i{f' + {k}' if k else ''}]" for k in range(shingle))
    hashes = f"""
      case when size(_words) >= {shingle} then transform(sequence(0, size(_words) - {shingle}), i -> xxhash64(concat_ws(' ', {part})))
           when size(_words) > 0 then array(xxhash64(array_join(_words, ' '))) else cast(array() as array<bigint>) end
    """
    d = d.select(*keep, F.expr(hashes).alias("_hashes"))

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists = b.column(b.num_columns - 1)
            at, flat = lists.offsets.to_numpy(), lists.values.to_numpy(zero_copy_only=False)
            fps = np.fromiter((_majority(flat[i:j]) for i, j in zip(at[:-1], at[1:])), np.int64, len(lists))
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(fps)], [*b.schema.names[:-1], "fp"])

    shape = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in d.schema.fields[:-1])
    return d.mapInArrow(counted, f"{shape}, fp long")


def links(values: DataFrame, masks: list[int] | None = None) -> DataFrame:
    """``values(fp)``, distinct -> ``(a, b)`` whose groups are those of all pairs within two bits.

    Of the values that share a neighbour, each is linked to the least.
    """
    masks = covering_masks() if masks is None else masks
    table = F.array(*[F.struct(F.lit(t).alias("t"), F.lit(m).alias("mask"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for t, m in enumerate(masks)])
    rows = materialize(values.select("fp", F.explode(table).alias("e")).select("fp", "e.*"), "tables")
    several = rows.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    members = rows.join(several, ["t", "key"])
    # Itself and each value with one of the bits flipped that the table does not look at.
    near = F.expr("""
      concat(array(fp), transform(filter(sequence(0, 63), i -> getbit(mask, i) = 0), i -> fp ^ shiftleft(1L, i)))
    """)
    hubs = members.select("fp", F.explode(near).alias("hub")).groupBy("hub").agg(F.collect_set("fp").alias("fps")).where("size(fps) > 1")
    return hubs.select(F.array_min("fps").alias("a"), F.explode("fps").alias("b")).where("a <> b").distinct()


def near_duplicates(docs: DataFrame, shingle: int = 3, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, fp, component_id`` for each row: the least id that links of two bits or
    fewer reach, itself included. Null ids take part but name no component unless it holds
    nothing else; repeated rows repeat.
    """
    prints = materialize(fingerprints(docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")), shingle), "prints")
    values = materialize(prints.groupBy("fp").agg(F.min("doc_id").alias("least")), "values")
    groups = connected_groups(links(values.select("fp")))
    named = values.join(groups, values.fp == groups.node, "left").select("fp", "least", F.coalesce("label", "fp").alias("label"))
    named = materialize(named, "named")
    lowest = materialize(named.groupBy("label").agg(F.min("least").alias("component_id")), "lowest")
    component = materialize(named.join(lowest, "label").select("fp", "component_id"), "component")
    return prints.join(component, "fp").select("doc_id", "fp", "component_id")


def drop_near_duplicates(docs: DataFrame, shingle: int = 3, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``docs`` with one row of each group, that of its least id. Columns stay as they are.

    Of rows that repeat an id, one stays. Rows with a null id all stay.
    """
    found = materialize(near_duplicates(docs, shingle, doc_id, text), "found")
    gone = materialize(found.where("doc_id <> component_id").select(F.col("doc_id").alias("_gone")).distinct(), "gone")
    kept = docs.join(gone, docs[doc_id] == F.col("_gone"), "left_anti")
    again = materialize(found.where("doc_id is not null").groupBy(F.col("doc_id").alias("_again")).count().where("count > 1").select("_again"), "again")
    if again.limit(1).count() == 0:
        return kept
    once = kept.join(again, kept[doc_id] == F.col("_again"), "left_semi").dropDuplicates([doc_id])
    return kept.join(again, kept[doc_id] == F.col("_again"), "left_anti").unionByName(once)


def op2_simhash(spark, sf_dir):
    out = near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
