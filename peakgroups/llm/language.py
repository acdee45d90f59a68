"""Language identification with hyperdimensional profiles (operator 8).

Every letter has a random vector of +1 and -1. A run of three letters is bound into one
vector by permuting the first letter's twice, the second's once, and multiplying; a text
is the sum of its runs' vectors, a language the sum over its training texts. The language
with the highest cosine wins.
"""

from __future__ import annotations

import functools
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Length of the vectors, letters that have one of their own (a to z, the other letters
#: share the rest, the gap between words is 0), and the seed of the letters' vectors.
DIMENSIONS, SYMBOLS, SEED = 1024, 48, 20240117
UNKNOWN = "und"
#: Characters that one step works on.
CHUNK = 1 << 19


@functools.cache
def _symbols() -> np.ndarray:
    table = np.zeros(0x110000, np.uint8)
    letters = np.fromiter((unicodedata.category(chr(c))[0] == "L" for c in range(0x110000)), bool, 0x110000)
    points = np.flatnonzero(letters)
    table[points] = 27 + points % (SYMBOLS - 27)
    table[ord("a") : ord("z") + 1] = np.arange(1, 27)
    return table


@functools.cache
def run_vectors() -> np.ndarray:
    """The bound vector of every run of three symbols, int8."""
    letters = np.random.default_rng(SEED).choice(np.array([-1, 1], np.int8), (SYMBOLS, DIMENSIONS))
    first, second = np.roll(letters, 2, 1), np.roll(letters, 1, 1)
    pairs = (first[:, None, :] * second[None, :, :]).reshape(-1, 1, DIMENSIONS)
    return (pairs * letters[None, :, :]).reshape(-1, DIMENSIONS)


def _symbols_of(text: str) -> np.ndarray:
    return _symbols()[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)].astype(np.int32)


def _squeezed(s: np.ndarray) -> np.ndarray:
    """Symbols with one gap where several stand."""
    return s[np.concatenate([[True], (s[1:] != 0) | (s[:-1] != 0)])]


def _codes(s: np.ndarray) -> np.ndarray:
    return (s[:-2] * SYMBOLS + s[1:-1]) * SYMBOLS + s[2:]


def run_codes(text: str) -> np.ndarray:
    """Codes of a text's runs: letters in lower case, anything between words one gap."""
    return _codes(_squeezed(np.concatenate([[0], _symbols_of(text.lower()), [0]]).astype(np.int32)))


def run_counts(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Distinct codes and counts of a text, chunk by chunk if it is long."""
    if len(text) <= 4000:
        return np.unique(run_codes(text), return_counts=True)
    total, text = np.zeros(SYMBOLS**3, np.int64), text.lower()
    before = np.zeros(1, np.int32)  # the last two symbols of what came before, so that no run is lost
    for i in range(0, len(text), CHUNK):
        s = _squeezed(np.concatenate([before, _symbols_of(text[i : i + CHUNK])]))
        total += np.bincount(_codes(s), minlength=SYMBOLS**3)
        before = s[-2:]
    total += np.bincount(_codes(_squeezed(np.concatenate([before, [0]]))), minlength=SYMBOLS**3)
    codes = np.flatnonzero(total)
    return codes, total[codes]


def learn(docs: DataFrame, text: str = "text", lang: str = "lang") -> dict[str, np.ndarray]:
    """Unit prototype of each language. Rows with null text or language teach nothing.

    Counts of runs are summed by the cluster; what reaches the driver is one vector for
    each language.
    """

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        for b in batches:
            for name, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                codes, n = run_counts(t)
                if name not in sums:
                    sums[name] = np.zeros(SYMBOLS**3, np.int64)
                sums[name][codes] += n
        for name, total in sums.items():
            codes = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(codes)), pa.array(codes, pa.int64()), pa.array(total[codes], pa.int64())], ["lang", "code", "n"])

    def bundled(pdf):
        import pandas as pd

        v = np.zeros(DIMENSIONS)
        codes, n = pdf["code"].to_numpy(), pdf["n"].to_numpy(np.float64)
        for i in range(0, len(codes), 4096):
            v += n[i : i + 4096] @ run_vectors()[codes[i : i + 4096]].astype(np.float64)
        return pd.DataFrame({"lang": [pdf["lang"].iloc[0]], "v": [(v / max(np.linalg.norm(v), 1e-12)).tolist()]})

    rows = docs.select(F.col(lang).cast("string").alias("lang"), F.col(text).alias("text")).where("lang is not null and text is not null")
    counts = rows.mapInArrow(counted, "lang string, code long, n long").groupBy("lang", "code").agg(F.sum("n").alias("n"))
    return {r.lang: np.array(r.v) for r in counts.groupBy("lang").applyInPandas(bundled, "lang string, v array<double>").collect()}


def predict(docs: DataFrame, prototypes: dict[str, np.ndarray], keep: list[str], text: str = "text") -> DataFrame:
    """Columns ``keep`` of ``docs`` with ``lang_pred`` and ``score``, the cosine from 0 to 1.

    ``und`` with score 0 where the text is null or has no letter, or nothing was learnt.
    Of equal cosines, the language first by name.
    """
    names = sorted(prototypes)
    matrix = np.array([prototypes[n] for n in names], np.float32).reshape(-1, DIMENSIONS).T

    def judged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            pred, score = [], []
            for t in b.column(b.num_columns - 1).to_pylist():
                codes, n = run_counts(t) if t and names else (np.zeros(0, int), np.zeros(0, int))
                if not codes.any():
                    pred.append(UNKNOWN)
                    score.append(0.0)
                    continue
                v = np.zeros(DIMENSIONS, np.float32)
                for i in range(0, len(codes), 4096):
                    v += n[i : i + 4096].astype(np.float32) @ run_vectors()[codes[i : i + 4096]].astype(np.float32)
                cos = v @ matrix / max(float(np.linalg.norm(v)), 1e-12)
                best = int(np.argmax(cos))
                pred.append(names[best])
                score.append(min(1.0, max(0.0, float(cos[best]))))
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(pred, pa.string()), pa.array(score, pa.float64())], [*b.schema.names[:-1], "lang_pred", "score"])

    d = docs.select(*keep, F.col(text).alias("_text"))
    shape = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in d.schema.fields[:-1])
    return d.mapInArrow(judged, f"{shape}{', ' if keep else ''}lang_pred string, score double")


def op8_language_id(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False))
    docs = docs.select("doc_id", "text", "lang", held.alias("held_out"))
    return predict(docs, learn(docs.where("not held_out")), ["doc_id", "held_out"])
