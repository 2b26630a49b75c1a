"""WARC revisit resolution: headers are grouped by payload digest, the record of least id with a digest is the response and the others revisit it;
archives are written with fresh headers, without the repeated payloads, and read back.

Only headers (id, url, digest, size) are shuffled. A revisit record has no payload, so it is made from headers alone; a response is made where its page is
read. Which pages these are is told by Bloom filters of fixed size: one of all revisits, and one of the few pages that the first takes for revisits wrongly.

An archive is a text file whose lines end in the CRLF CRLF that ends a WARC record, so Spark's own writer commits it to any store. It is read the same way,
piece by piece, so no task holds more than its largest record and a batch of pieces.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Bloom, cut, pick, scratch_path, spread_join

#: Production values: least payload that is deduplicated, and records in one archive at most.
MIN_BYTES, RECORDS_PER_FILE = 0, 1_000
#: The profile of revisits, and the date of records whose crawl time is not known.
PROFILE, DATE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", "2000-01-01T00:00:00Z"
_END = "\r\n\r\n"
_DIGITS, _LETTERS = "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"


def base32_sha1(payload: Column) -> Column:
    """Bare upper-case base32 of the SHA-1: five hex digits make four base32 digits."""
    h = F.sha1(payload)
    groups = [F.lpad(F.conv(F.substring(h, 5 * k + 1, 5), 16, 32), 4, "0") for k in range(8)]
    return F.translate(F.upper(F.concat(*groups)), _DIGITS, _LETTERS)


def record_urn(page_id: Column) -> Column:
    """A record id that holds the page id: reruns make the same archives."""
    h = F.lpad(F.hex(F.coalesce(page_id, F.lit(0))), 16, "0")
    kind = F.when(page_id.isNull(), "0").otherwise("1")
    return F.lower(F.concat(F.lit("urn:uuid:0000000"), kind, F.lit("-0000-8000-"), F.substring(h, 1, 4), F.lit("-"), F.substring(h, 5, 12)))


def page_of(urn: str) -> int | None:
    """The page id in a record id of ours."""
    parts = urn.strip("<>").removeprefix("urn:uuid:").split("-")
    return None if parts[0][-1] == "0" else int.from_bytes(bytes.fromhex(parts[3] + parts[4]), "big", signed=True)


def _key() -> Column:
    return F.xxhash64("page_id", "digest")


def page_rows(pages: DataFrame) -> DataFrame:
    """page_id, url, html (null as empty), digest, size."""
    rows = pick(pages, "page_id", "url", "html").select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    return rows.withColumn("digest", base32_sha1(F.col("html"))).withColumn("size", F.octet_length("html").cast("long"))


def resolve(headers: DataFrame, min_bytes: int = MIN_BYTES) -> DataFrame:
    """The headers (page_id, url, digest, size) that revisit another page, with first and first_url of the response.

    Of rows with equal payloads of min_bytes or more, those with the least page_id are responses (all of them, where rows repeat); a null page_id is
    larger than any other, and a payload that only such rows have is a response each time. A digest that many rows have is split."""
    rows = headers.where(F.col("size") >= min_bytes)
    groups = rows.groupBy("digest").agg(F.min(F.struct(F.col("page_id").isNull().alias("none"), "page_id", "url")).alias("least"), F.count("*").alias("n")).where("n > 1")
    groups = cut(groups.select("digest", F.col("least.page_id").alias("first"), F.col("least.url").alias("first_url"), "n").where("first IS NOT NULL"))
    return spread_join(rows, groups, "digest", "page_id").where(~F.col("page_id").eqNullSafe(F.col("first"))).select("page_id", "url", "digest", "size", "first", "first_url")


def _may_hold(rows: DataFrame, bloom: Bloom, wanted: bool) -> DataFrame:
    """The rows whose __key the filter may hold, or those that it doesn't."""

    def run(batches):
        held = None
        for b in batches:
            held = held or bloom.test()
            found = held.may_hold(b.column(b.schema.names.index("__key")))
            yield b.filter(pa.array(found if wanted else ~found))

    return rows.mapInArrow(run, rows.schema)


def responses(rows: DataFrame, headers: DataFrame, revisits: DataFrame) -> DataFrame:
    """The rows (of page_rows) that are no revisits. Bodies of rows that a filter is sure of are not shuffled."""
    told = Bloom.of(revisits.select(_key().alias("__key")))
    keyed = headers.withColumn("__key", _key())
    # pages that the filter can't clear though they are responses
    same = F.col("page_id").eqNullSafe(F.col("__id")) & (F.col("digest") == F.col("__d"))
    wrong = cut(_may_hold(keyed, told, True).join(revisits.select(F.col("page_id").alias("__id"), F.col("digest").alias("__d")), same, "left_anti").select("page_id", "digest", "__key").distinct())
    again = Bloom.of(wrong.select("__key"))
    bodies = rows.withColumn("__key", _key())
    doubtful = _may_hold(_may_hold(bodies, told, True), again, True)
    cleared = doubtful.join(wrong.select(F.col("page_id").alias("__id"), F.col("digest").alias("__d")), same, "left_semi")
    return _may_hold(bodies, told, False).unionByName(cleared).drop("__key")


def records(rows: DataFrame, revisits: bool, date: str = DATE) -> DataFrame:
    """value: the text of one record without the CRLF CRLF that ends it."""
    crlf, line = "\r\n", lambda name, value: F.concat(F.lit(f"{name}: "), value, F.lit("\r\n"))
    clean = lambda c: F.regexp_replace(F.coalesce(F.col(c), F.lit("")), "[\r\n]", " ")
    urn = lambda c: F.concat(F.lit("<"), record_urn(F.col(c)), F.lit(">"))
    head = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), F.col("size").cast("string"), F.lit(_END))
    extra = [line("WARC-Profile", F.lit(PROFILE)), line("WARC-Refers-To", urn("first")), line("WARC-Refers-To-Target-URI", clean("first_url")), line("WARC-Refers-To-Date", F.lit(date))] if revisits else []
    length = F.octet_length(head) if revisits else F.octet_length(head) + F.col("size")
    value = F.concat(
        F.lit("WARC/1.1" + crlf), line("WARC-Type", F.lit("revisit" if revisits else "response")), line("WARC-Record-ID", urn("page_id")),
        line("WARC-Date", F.lit(date)), line("WARC-Target-URI", clean("url")), line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("digest"))), *extra,
        line("Content-Type", F.lit("application/http; msgtype=response")), line("Content-Length", length.cast("string")), F.lit(crlf), head, *([] if revisits else [F.col("html")]),
    )
    return rows.select(value.alias("value"))


def write_archives(pages: DataFrame, path: str, min_bytes: int = MIN_BYTES, records_per_file: int = RECORDS_PER_FILE, compression: str = "gzip") -> str:
    """Writes deduplicated archives under path and returns it. Compressed archives are one gzip member each."""
    rows = page_rows(pages)
    headers = cut(rows.drop("html"))
    revisits = cut(resolve(headers, min_bytes))
    text = records(responses(rows, headers, revisits), False).unionByName(records(revisits, True))
    text.write.option("lineSep", _END).option("maxRecordsPerFile", records_per_file).option("compression", compression).text(path)
    return path


def parse_records(pieces: Iterable[bytes]) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers and block of each record of archives that come as what lies between their CRLF CRLF, in order. A payload that ends in CRLF makes the last piece of
    a file lack its CRLF CRLF, so line ends before a record don't count."""
    held, size = [], 0

    def parsed(data: bytes):
        end = data.index(b"\r\n\r\n")
        lines = data[:end].decode().split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"no WARC record: {lines[0][:40]!r}")
        head = dict(x.split(": ", 1) for x in lines[1:])
        return head, end + 4, end + 4 + int(head["Content-Length"])

    need = None
    for piece in pieces:
        held.append((piece if size else piece.lstrip(b"\r\n")) + b"\r\n\r\n")
        size += len(held[-1])
        if held[0] == b"\r\n\r\n":
            held, size = [], 0
        # the record's own end is four bytes
        while size and (need is None or size >= need + 4):
            data = b"".join(held)
            held, size = [data], len(data)
            head, begin, need = parsed(data)
            if size < need + 4:
                break
            yield head, data[begin:need]
            rest = data[need + 4 :].lstrip(b"\r\n")
            held, size, need = ([rest], len(rest), None) if rest else ([], 0, None)
    if size:
        raise ValueError("an archive ends within a record")


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to, intact (a response's payload has its digest) of all records under path."""
    pieces = spark.read.option("lineSep", _END).text(path)

    def run(batches):
        rows: list[tuple] = []
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.bool_())

        def made():
            cols = list(zip(*rows, strict=True)) or [[]] * 6
            rows.clear()
            return pa.record_batch([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "intact"])

        for head, block in parse_records(x.as_py() for b in batches for x in b.column(0).cast(pa.binary())):
            http, _, payload = block.partition(b"\r\n\r\n")
            kind, digest = head["WARC-Type"], head["WARC-Payload-Digest"].removeprefix("sha1:")
            size = int(http.rpartition(b"Content-Length: ")[2])
            intact = kind == "revisit" or (size == len(payload) and base64.b32encode(hashlib.sha1(payload).digest()).decode() == digest)
            rows.append((page_of(head["WARC-Record-ID"]), size, digest, kind, page_of(head["WARC-Refers-To"]) if kind == "revisit" else None, intact))
            if len(rows) == 10_000:
                yield made()
        yield made()

    return pieces.mapInArrow(run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, intact boolean")


def round_trip(pages: DataFrame, **options) -> DataFrame:
    """Archives of pages in the shared folder, read back. A row for every row of pages; null html is the empty payload; line breaks in urls become spaces;
    an empty table gives no rows; other columns are ignored."""
    spark = pages.sparkSession
    return read_archives(spark, write_archives(pages, scratch_path(spark), **options))
