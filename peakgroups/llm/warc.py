"""WARC archives: writing, and reading with verified record chains (operator 5).

A record says how long it is, so the records of an archive form a chain from its first
byte. Tasks look for the magic everywhere and report each candidate with the offset of
its successor; a payload that quotes a record makes candidates too. Pointer jumping over
block borders finds the offset at which the chain enters each block of a file, and only
candidates on the chain from there are records.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from peakgroups.functions.storage import materialize, shared_path

#: Bytes of a block: candidates of one are put in order together.
BLOCK = 1 << 22
#: Records of one written file; a task reads a file at once.
FILE_RECORDS = 4000
#: The date that records carry unless one is given.
DATE = "1970-01-01T00:00:00Z"
#: A record is the first of its file or comes after the two line ends of another, so the
#: headers of candidates do not overlap and need no limit of their own.
_MAGIC = re.compile(rb"(?:\A|(?<=\r\n\r\n))WARC/1\.[01]\r\n")
_HTTP = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n"
#: Base 32 digits of numbers in Java and of RFC 4648: fixed values.
_JAVA32, _RFC32 = "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"


def base32_sha1(payload: Column) -> Column:
    """Bare upper-case base32 SHA-1: forty bits, ten hex digits, make eight of its digits."""
    digest = F.sha1(payload)
    parts = [F.lpad(F.conv(F.substring(digest, 1 + 10 * i, 10), 16, 32), 8, "0") for i in range(4)]
    return F.translate(F.concat(*parts), _JAVA32, _RFC32)


def deduplicated(pages: DataFrame, page_id: str = "page_id", url: str = "url", html: str = "html", min_bytes: int = 0) -> DataFrame:
    """``page_id, url, payload, digest, refers_to``: the last is null for a response.

    Of rows with equal payloads of ``min_bytes`` or more, that with the largest id is the
    response (all rows with that id, should it repeat). A null payload counts as empty; a
    null id is a response only if its payload has no other.
    """
    payload = F.coalesce(F.col(html), F.lit(""))
    p = pages.select(F.col(page_id).alias("page_id"), F.col(url).alias("url"), payload.alias("payload"), base32_sha1(payload).alias("digest"))
    slim = p.where(F.octet_length("payload") >= min_bytes).select("page_id", "digest")
    last = slim.groupBy("digest").agg(F.max("page_id").alias("last"), F.count(F.lit(1)).alias("n")).where("n > 1")
    last = materialize(last.select(F.col("digest").alias("d"), "last"), "responses")
    joined = p.join(last, F.col("digest") == F.col("d"), "left")
    revisit = (F.octet_length("payload") >= min_bytes) & F.col("last").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("last"))
    return joined.select("page_id", "url", "payload", "digest", F.when(revisit, F.col("last")).alias("refers_to"))


def write_archives(records: DataFrame, path: str, date: str = DATE, file_records: int = FILE_RECORDS) -> None:
    """Write :func:`deduplicated` rows as WARC 1.1 files; the JVM writes them anywhere.

    A record ends in two line ends, which is the separator of the text writer.
    """
    revisit = F.col("refers_to").isNotNull()
    name = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(c.cast("string"), F.lit("none")), F.lit(">"))
    size = F.octet_length("payload")
    http = F.concat(F.lit(_HTTP), F.lit("Content-Length: "), size.cast("string"), F.lit("\r\n\r\n"))
    block = F.when(revisit, http).otherwise(F.concat(http, "payload"))
    fields = [
        F.concat(F.lit("WARC/1.1\r\nWARC-Type: "), F.when(revisit, F.lit("revisit")).otherwise(F.lit("response"))),
        F.concat(F.lit("WARC-Record-ID: "), name(F.col("page_id"))),
        F.when(F.col("url").isNotNull(), F.concat(F.lit("WARC-Target-URI: "), F.replace(F.replace("url", F.lit("\r"), F.lit("%0D")), F.lit("\n"), F.lit("%0A")))),
        F.lit(f"WARC-Date: {date}"),
        F.concat(F.lit("WARC-Payload-Digest: sha1:"), F.col("digest")),
        F.when(revisit, F.concat(F.lit("WARC-Refers-To: "), name(F.col("refers_to")), F.lit("\r\nWARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"))),
        F.when(revisit, F.lit("Content-Type: application/http; msgtype=response")).otherwise(F.lit("Content-Type: application/http;msgtype=response")),
        F.concat(F.lit("Content-Length: "), F.octet_length(block).cast("string")),
    ]
    value = F.concat(F.concat_ws("\r\n", *fields), F.lit("\r\n\r\n"), block)
    records.select(value.alias("value")).write.option("lineSep", "\r\n\r\n").option("maxRecordsPerFile", file_records).text(path)


def _head(data: memoryview | bytes, at: int) -> tuple[dict[str, str], int] | None:
    end = data.find(b"\r\n\r\n", at)
    if end < 0:
        return None
    lines = data[at:end].decode("utf-8", "replace").split("\r\n")[1:]
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines)}, end + 4


def candidates_of(data: bytes, block: int = BLOCK) -> list[dict]:
    """Every place of a file that reads like a record, with its successor's offset and the
    offset at which the chain through it leaves its block."""
    found = []
    for m in _MAGIC.finditer(data):
        head = _head(data, m.start())
        if head is None or not head[0].get("content-length", "").isdigit():
            continue
        fields, body = head
        end = body + int(fields["content-length"])
        if data[end : end + 4] != b"\r\n\r\n":
            continue
        found.append({"offset": m.start(), "successor": end + 4, "body": body, "end": end, "fields": fields})
    leaves: dict[int, int] = {}
    for c in reversed(found):
        on = c["successor"]
        same = on // block == c["offset"] // block and on in leaves
        c["leaves"] = leaves[c["offset"]] = leaves[on] if same else on
    return found


def candidate_records(spark: SparkSession, path: str, block: int = BLOCK, payloads: bool = False) -> DataFrame:
    """Candidates of all files under ``path`` with what their headers and payloads say."""

    def number(name: str | None) -> int | None:
        tail = (name or "").rpartition(":")[2].rstrip(">")
        return int(tail) if tail.lstrip("-").isdigit() else None

    def parsed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                data, rows = b.column(1)[i].as_py(), []
                for c in candidates_of(data, block):
                    fields, kind = c["fields"], c["fields"].get("warc-type")
                    http = data.find(b"\r\n\r\n", c["body"], c["end"])
                    payload = data[(http + 4 if http >= 0 else c["body"]) : c["end"]]
                    length, digest = len(payload), base64.b32encode(hashlib.sha1(payload).digest()).decode()
                    if kind == "revisit":
                        said = re.search(rb"\r\nContent-Length: *(\d+)", data[c["body"] : c["end"]])
                        length, digest = int(said[1]) if said else None, fields.get("warc-payload-digest", "").rpartition(":")[2]
                    rows.append({
                        "file": b.column(0)[i].as_py(), "block": c["offset"] // block, "offset": c["offset"], "successor": c["successor"], "leaves": c["leaves"],
                        "page_id": number(fields.get("warc-record-id")), "payload_bytes": length, "payload_digest": digest, "record_type": kind,
                        "refers_to": number(fields.get("warc-refers-to")), "url": fields.get("warc-target-uri"), "payload": payload if payloads and kind != "revisit" else None,
                    })
                yield pa.RecordBatch.from_pylist(rows, schema)

    long, text = pa.int64(), pa.string()
    schema = pa.schema([("file", text), ("block", long), ("offset", long), ("successor", long), ("leaves", long), ("page_id", long), ("payload_bytes", long), ("payload_digest", text), ("record_type", text), ("refers_to", long), ("url", text), ("payload", pa.binary())])
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("path", "content")
    shape = "file string, block long, offset long, successor long, leaves long, page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url string, payload binary"
    return files.mapInArrow(parsed, shape)


def chain_entries(candidates: DataFrame) -> DataFrame:
    """``file, offset``: where the chain from a file's first byte enters its blocks.

    Jump pointers double their reach in each round, so a file takes as many rounds as the
    logarithm of its blocks.
    """
    goals = candidates.select("file", F.col("leaves").alias("offset")).distinct()
    entries = candidates.select("file", "offset", "leaves").join(goals, ["file", "offset"], "left_semi")
    first = candidates.where("offset = 0").select("file", "offset", "leaves")
    jumps = materialize(entries.union(first).distinct().select("file", "offset", F.col("leaves").alias("to")), "jumps")
    reached = materialize(first.select("file", "offset"), "reached")
    count = reached.count()
    while count:
        ahead = reached.join(jumps, ["file", "offset"]).select("file", F.col("to").alias("offset"))
        known = jumps.select("file", "offset")
        reached = materialize(reached.union(ahead.join(known, ["file", "offset"], "left_semi")).distinct(), "reached")
        before, count = count, reached.count()
        if count == before:
            break
        on = jumps.select("file", F.col("offset").alias("to"), F.col("to").alias("further"))
        jumps = materialize(jumps.join(on, ["file", "to"], "left").select("file", "offset", F.coalesce("further", "to").alias("to")), "jumps")
    return reached


def read_archives(spark: SparkSession, path: str, block: int = BLOCK, payloads: bool = False, whole: bool = False) -> DataFrame:
    """Records of all files under ``path``; quoted and cut-off ones are rejected.

    ``page_id, payload_bytes, payload_digest, record_type, refers_to, url, payload``; the
    digest and size of a response are those of the bytes read. A file that does not begin
    with a record has none. With ``whole`` a file whose records stop before its end is an error.
    """
    found = materialize(candidate_records(spark, path, block, payloads), "candidates")
    entries = chain_entries(found).select("file", F.floor(F.col("offset") / block).alias("block"), F.col("offset").alias("entry"))
    # Candidates of a block in order; those at the offset that the chain expects are records.
    on_chain = """
      aggregate(array_sort(hops), struct(entry as next, cast(array() as array<bigint>) as seen),
        (a, h) -> if(h.offset = a.next, struct(h.successor as next, array_append(a.seen, h.offset) as seen), a), a -> a.seen)
    """
    blocks = found.groupBy("file", "block").agg(F.collect_list(F.struct("offset", "successor")).alias("hops"))
    good = blocks.join(entries, ["file", "block"]).select("file", F.explode(F.expr(on_chain)).alias("offset"))
    if whole:
        good = materialize(good, "good")
        ends = found.join(good, ["file", "offset"]).groupBy("file").agg(F.max("successor").alias("end"))
        sizes = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select(F.col("path").alias("file"), "length")
        short = sizes.join(ends, "file", "left").where("length <> coalesce(end, 0)").first()
        if short:
            raise ValueError(f"records of {short['file']} stop at byte {short['end'] or 0} of {short['length']}")
    return found.join(good, ["file", "offset"]).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url", "payload")


def op5_warc(spark, sf_dir):
    path = shared_path(spark, "warc")
    write_archives(deduplicated(spark.read.parquet(f"{sf_dir}/pages.parquet")), path)
    return read_archives(spark, path, whole=True).drop("url", "payload")


_FORTY = "list_transform(range(0, 4), lambda k: cast('0x' || substr(sha1(coalesce(html, '')), cast(1 + 10 * k as int), 10) as bigint))"
OP5_SQL = f"""
with d as (
  select page_id, coalesce(html, '') as payload, strlen(coalesce(html, '')) as payload_bytes,
         array_to_string(list_transform({_FORTY}, lambda v: array_to_string(list_transform(range(0, 8),
           lambda j: substr('{_RFC32}', cast(1 + ((v >> (35 - 5 * j)) & 31) as int), 1)), '')), '') as payload_digest
  from pages
), m as (select *, max(page_id) over (partition by payload) as last from d)
select page_id, payload_bytes, payload_digest, case when page_id = last then 'response' else 'revisit' end as record_type,
       case when page_id <> last then last end as refers_to
from m
"""
