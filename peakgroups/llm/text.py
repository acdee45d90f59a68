"""Word splitting that the operators share. All JVM expressions; null text has no words."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: What separates words: white space, or all ASCII but digits and letters a to z.
SPACES, NON_WORD = r"[\x20\x09-\x0D]+", r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def ascii_lower(text: Column) -> Column:
    """Lower-case A to Z only. Pure ASCII text takes the byte-wise path of lower()."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def space_words(text: Column) -> Column:
    """Runs of anything but white space."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SPACES), "")


def alnum_words(text: Column) -> Column:
    """Runs of digits, letters and non-ASCII characters, A to Z lower-cased."""
    return F.array_remove(F.split(ascii_lower(F.coalesce(text, F.lit(""))), NON_WORD), "")


def window_keys(words: str, n: int) -> str:
    """SQL: an array with the XXH64 of each run of ``n`` words of the array ``words``."""
    part = ", ".join(f"{words}[i{f' + {k}' if k else ''}]" for k in range(n))
    return f"if(size({words}) >= {n}, transform(sequence(0, size({words}) - {n}), i -> xxhash64({part})), cast(array() as array<bigint>))"


def guarded(value: Column) -> Column:
    """``value``, in a form that keeps filters on it above the projection that makes it.

    Spark moves a filter below projections by putting their expressions in its place; one
    on words or windows would then be computed anew for each element of an array.
    """
    return F.when(F.monotonically_increasing_id() >= 0, value)
