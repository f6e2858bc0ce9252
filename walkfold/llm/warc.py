r"""WARC archives: a writer and a salvage reader.

Writing is plain DataFrame code: each record is one string, and the text sink puts the
two line ends after it, so the files are ordinary uncompressed WARC on any file system
that Spark writes. Records with equal payloads: the one with the largest page_id is a
response; others are revisits whose HTTP head still states the full payload's length and digest.

Reading takes whole files (the writer bounds their bytes: pages of one size class share a file) and checks every record:
version line, header, length, closing line ends, block digest. After a failed check it searches for
the next gzip member or version line that yields a valid record, and logs the bytes between as a gap. Of a damaged gzip
member, what unpacks before the damage is salvaged too; gaps inside a member are logged with the member's offset, no
length of their own in the file, and their place in the unpacked bytes.

Defined cases: null html is an empty payload; a null url is written as an empty URI;
a null page_id comes below all others; rows that repeat the largest page_id of a
payload are all responses; payloads under ``min_bytes`` are all responses; an empty table gives
no file and an empty result; extra columns are not archived.
"""

from __future__ import annotations

import base64
import hashlib
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from walkfold.llm.common import cut, scratch

#: The RFC 4648 alphabet, the archive's line ends and the revisit profile.
BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
CRLF = "\r\n"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
#: A hot payload's rows are dealt over so many parts.
SALTS = 32
#: Most bytes of a file, so that a file fits a task. A record of over a class's bytes belongs to a later class, and a class
#: puts as many records in a file as fit; a record of over the last class's bytes has a file of its own.
FILE_BYTES = 256 << 20
CLASSES = (64 << 10, 1 << 20, 16 << 20, FILE_BYTES)
HEAD_BYTES = 1 << 10


def base32_of_hex(hexed: Column) -> Column:
    """Base32 of a 40-digit hex string: each five digits are four letters."""
    letters = []
    for i in range(8):
        five = F.conv(F.substring(hexed, 5 * i + 1, 5), 16, 10).cast("int")
        letters += [F.substr(F.lit(BASE32), F.shiftright(five, 15 - 5 * j).bitwiseAND(31) + 1, F.lit(1)) for j in range(4)]
    return F.concat(*letters)


def plan_records(pages: DataFrame, min_bytes: int = 0) -> DataFrame:
    """page_id, url, payload, payload_bytes, payload_digest, refers_to (null: a response)."""
    payload = F.coalesce(F.col("html"), F.lit(""))
    rows = pages.select("page_id", "url", payload.alias("payload"), F.octet_length(payload).cast("long").alias("payload_bytes"), F.sha1(payload.cast("binary")).alias("_sha"))
    repeated = rows.where(F.col("payload_bytes") >= min_bytes).groupBy("_sha").agg(F.max("page_id").alias("_first"), F.count(F.lit(1)).alias("_n")).where("_n > 1").drop("_n")
    salted = cut(repeated, "warc-repeats").withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    rows = rows.withColumn("_salt", F.pmod(F.xxhash64("page_id"), F.lit(SALTS)).cast("int"))
    refers = F.when(F.col("_first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("_first")), F.col("_first"))
    return rows.join(salted, ["_sha", "_salt"], "left").select("page_id", "url", "payload", "payload_bytes", base32_of_hex(F.col("_sha")).alias("payload_digest"), refers.alias("refers_to"))


def _urn(page_id: Column) -> Column:
    return F.concat(F.lit("<urn:walkfold:page:"), F.coalesce(page_id.cast("string"), F.lit("null")), F.lit(">"))


def write_archive(plan: DataFrame, path: str, date: str = "2024-01-01T00:00:00Z", compression: str = "none") -> None:
    """One WARC record for each row of ``plan_records``."""
    revisit = F.col("refers_to").isNotNull()
    head = F.concat(F.lit(f"HTTP/1.1 200 OK{CRLF}Content-Type: text/html; charset=utf-8{CRLF}Content-Length: "), F.col("payload_bytes").cast("string"), F.lit(CRLF * 2))
    block = F.concat(head, F.when(revisit, F.lit("")).otherwise(F.col("payload")))
    rows = plan.withColumn("_block", block)
    line = lambda name, value: F.concat(F.lit(f"{name}: "), value, F.lit(CRLF))
    record = F.concat(
        F.lit(f"WARC/1.1{CRLF}"),
        line("WARC-Type", F.when(revisit, F.lit("revisit")).otherwise(F.lit("response"))),
        line("WARC-Record-ID", _urn(F.col("page_id"))),
        line("WARC-Date", F.lit(date)),
        line("WARC-Target-URI", F.regexp_replace(F.coalesce(F.col("url"), F.lit("")), r"[\r\n]", " ")),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("payload_digest"))),
        line("WARC-Block-Digest", F.concat(F.lit("sha1:"), base32_of_hex(F.sha1(F.col("_block").cast("binary"))))),
        F.when(revisit, F.concat(line("WARC-Refers-To", _urn(F.col("refers_to"))), line("WARC-Profile", F.lit(PROFILE)))).otherwise(F.lit("")),
        F.lit(f"Content-Type: application/http;msgtype=response{CRLF}"),
        line("Content-Length", F.octet_length("_block").cast("string")),
        F.lit(CRLF),
        F.col("_block"),
    )
    size = F.col("payload_bytes") + F.octet_length(F.coalesce("url", F.lit(""))) + HEAD_BYTES
    least = F.lit(len(CLASSES))
    for k, most in reversed(list(enumerate(CLASSES))):
        least = F.when(size <= most, F.lit(k)).otherwise(least)
    present = sorted(r[0] for r in plan.select(least.alias("k")).distinct().collect())  # five numbers at most
    for k in present or [0]:  # an empty table writes an empty folder
        records = max(1, FILE_BYTES // CLASSES[k]) if k < len(CLASSES) else 1
        out = rows.where(least == k).select(record.alias("value"))
        out.write.option("lineSep", CRLF * 2).option("compression", compression).option("maxRecordsPerFile", records).text(f"{path}/class={k}")


#: Bytes of a gzip member that are unpacked at a time.
FED = 64 << 10
_START = re.compile(rb"WARC/1\.[01]\r\n|\x1f\x8b\x08")
_LENGTH = re.compile(rb"content-length:\s*(\d+)", re.I)


def _digest(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def _record_at(data: bytes, at: int) -> tuple[dict | None, int, str]:
    """(record, position after it, reason if there is none) of the plain record that starts at ``at``."""
    if not data.startswith(b"WARC/", at):
        return None, at, "no version line"
    end = data.find(b"\r\n\r\n", at)
    if end < 0:
        return None, at, "header without end"
    names = {}
    for part in data[at:end].split(b"\r\n")[1:]:
        name, colon, value = part.partition(b":")
        if not colon:
            return None, at, "bad header line"
        names[name.strip().lower().decode("latin-1")] = value.strip().decode("utf-8", "replace")
    if not names.get("content-length", "").isdigit():
        return None, at, "no length"
    start, size = end + 4, int(names["content-length"])
    if len(data) < start + size + 4:
        return None, at, "truncated"
    if data[start + size : start + size + 4] != b"\r\n\r\n":
        return None, at, "wrong length"
    block = data[start : start + size]
    said = names.get("warc-block-digest", "")
    if said.startswith("sha1:") and said[5:] != _digest(block):
        return None, at, "wrong digest"
    return {"names": names, "block": block}, start + size + 4, ""


def _member_at(data: bytes, at: int) -> tuple[list[dict], int, str]:
    """(records and inner gaps, position after, reason) of the gzip member at ``at``; a damaged one ends where it began."""
    worker, view, parts, fed = zlib.decompressobj(31), memoryview(data), [], at
    reason = "truncated"
    try:
        while fed < len(data) and not worker.eof:  # piece by piece: what is left of the file is never copied
            parts.append(worker.decompress(view[fed : fed + FED]))
            fed += min(FED, len(data) - fed)
    except zlib.error:
        reason = "damaged member"
    found = list(salvage(b"".join(parts)))
    whole = worker.eof
    records = [x for x in found if "names" in x]
    inner = [{"reason": x["reason"], "inner_offset": x["offset"], "inner_length": x["length"]} for x in found if "reason" in x]
    if whole:
        return (records + inner if records else []), fed - len(worker.unused_data), "" if records else "member without record"
    return records, at, reason


def salvage(data: bytes) -> Iterator[dict]:
    """Records ({names, block, offset, length}) and gaps ({reason, offset, length}) of an archive's bytes, in order."""
    at, gap, why = 0, None, ""
    while at < len(data):
        packed = data.startswith(b"\x1f\x8b", at)
        if packed:
            records, after, reason = _member_at(data, at)
        else:
            record, after, reason = _record_at(data, at)
            records = [record] if record else []
        if records and after > at:
            if gap is not None:
                yield {"reason": why, "offset": gap, "length": at - gap}
                gap = None
            for record in records:
                yield record | {"offset": at, "length": after - at if "names" in record else 0}
            at = after
            continue
        for record in records:  # of a damaged member: its bytes are a gap all the same
            yield record | {"offset": at, "length": 0}
        if gap is None:
            gap, why = at, reason
        following = _START.search(data, at + 1)
        at = following.start() if following else len(data)
    if gap is not None:
        yield {"reason": why, "offset": gap, "length": len(data) - gap}


_SCHEMA = "file string, start long, length long, gap_reason string, record_type string, record_id string, refers_to string, uri string, payload_digest string, payload_bytes long, payload binary"


def _row(path: str, found: dict, with_payload: bool) -> tuple:
    if "reason" in found:
        return (path, found["offset"], found["length"], found["reason"], *[None] * 7)
    names, block = found["names"], found["block"]
    head, _, payload = block.partition(b"\r\n\r\n")
    kind = names.get("warc-type")
    said = _LENGTH.search(head)
    size = int(said[1]) if kind == "revisit" and said else len(payload)
    digest = names.get("warc-payload-digest", "").removeprefix("sha1:") if kind == "revisit" else _digest(payload)
    return (path, found["offset"], found["length"], None, kind, names.get("warc-record-id"), names.get("warc-refers-to"), names.get("warc-target-uri"), digest, size, payload if with_payload else None)


def read_archive(spark: SparkSession, path: str, with_payload: bool = True) -> DataFrame:
    """Every record and every quarantined gap (gap_reason is set) of the archives under ``path``."""
    names = [x.split()[0] for x in _SCHEMA.split(", ")]
    kinds = [{"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}[x.split()[1]] for x in _SCHEMA.split(", ")]

    def parse(batches):
        for batch in batches:
            for file, content in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                rows, held = [], 0
                for found in salvage(content.as_py() or b""):
                    rows.append(_row(file, found, with_payload))
                    held += len(rows[-1][-1] or b"")
                    if len(rows) >= 2000 or held > 8 << 20:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)
                        rows, held = [], 0
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).where("length > 0").select("path", "content")
    return files.mapInArrow(parse, _SCHEMA)


def archive_round_trip(pages: DataFrame, min_bytes: int = 0) -> DataFrame:
    """Archive ``pages``, read the archives back and report each page's record."""
    spark, path = pages.sparkSession, scratch(pages.sparkSession, "warc")
    write_archive(plan_records(pages, min_bytes), path)
    page = lambda name: F.try_element_at(F.split(F.regexp_extract(F.col(name), r"page:(-?\d+)>", 1), ","), F.lit(1))
    number = lambda name: F.when(page(name) != "", page(name)).cast("long")
    records = read_archive(spark, path, with_payload=False).where("gap_reason IS NULL")
    return records.select(number("record_id").alias("page_id"), "payload_bytes", "payload_digest", "record_type", number("refers_to").alias("refers_to"))


_FIVE = ", ".join(f"('0x' || substr(h, {5 * i + 1}, 5))::INT" for i in range(8))
SQL = f"""
WITH p AS (SELECT page_id, coalesce(html, '') AS body, sha1(coalesce(html, '')) AS h FROM pages),
g AS (SELECT h, max(page_id) AS top FROM p GROUP BY h)
SELECT page_id, octet_length(encode(body))::BIGINT AS payload_bytes,
  list_aggregate(list_transform(flatten(list_transform([{_FIVE}], lambda v: [(v >> 15) & 31, (v >> 10) & 31, (v >> 5) & 31, v & 31])), lambda x: substr('{BASE32}', x + 1, 1)), 'string_agg', '') AS payload_digest,
  CASE WHEN page_id = top THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> top THEN top END AS refers_to
FROM p JOIN g USING (h)
"""
