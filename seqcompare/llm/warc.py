"""A content-addressed WARC archive: payloads stored once by digest, exact record headers apart, records by joins.

The digest that addresses a payload is the base32 SHA-1 of WARC's digest fields, verified by a SHA-256 and the length:
payloads are taken for equal only where all three are. Archives are two tables in a shared folder, payloads compressed.
``records`` makes whole WARC records of them by joins, ``read_back`` parses these again, and ``write_files`` and
``read_files`` turn them into WARC files and back.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import batch, stage_path, tidy, written

VERSION = "WARC/1.1"
END = "\r\n\r\n"
#: Columns that address a payload, in headers and payloads alike.
ADDRESS = ["digest", "check", "size"]
DATE = "2024-01-01T00:00:00Z"
_BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
_CONV = "0123456789ABCDEFGHIJKLMNOPQRSTUV"


def base32_sha1(text: Column) -> Column:
    """SHA-1 of the UTF-8 text in upper-case base32: five hex digits make four of base 32."""
    digest = F.sha1(text)
    parts = [F.lpad(F.conv(F.substring(digest, 5 * k + 1, 5), 16, 32), 4, "0") for k in range(8)]
    return F.translate(F.concat(*parts), _CONV, _BASE32)


@dataclass
class Archive:
    headers: DataFrame
    payloads: DataFrame


def header(kind: Column, page: Column, url: Column, digest: Column, size: Column, refers: Column) -> Column:
    """The record's header lines, without the blank line after them. Line breaks in a url are escaped."""
    clean = F.replace(F.replace(url, F.lit("\r"), F.lit("%0D")), F.lit("\n"), F.lit("%0A"))
    lines = [
        F.lit(VERSION),
        F.concat(F.lit("WARC-Type: "), kind),
        F.concat(F.lit("WARC-Record-ID: <urn:page:"), F.coalesce(page.cast("string"), F.lit("none")), F.lit(">")),
        F.lit(f"WARC-Date: {DATE}"),
        F.concat(F.lit("WARC-Target-URI: "), clean),
        F.concat(F.lit("WARC-Payload-Digest: sha1:"), digest),
        F.when(kind == "revisit", F.concat(F.lit("WARC-Refers-To: <urn:page:"), refers.cast("string"), F.lit(">"))),
        F.when(kind == "revisit", F.lit("WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")),
        F.lit("Content-Type: text/html; charset=utf-8"),
        F.concat(F.lit("Content-Length: "), F.when(kind == "revisit", F.lit("0")).otherwise(size.cast("string"))),
    ]
    return F.concat_ws("\r\n", *lines)


def stored(pages: DataFrame, least_bytes: int = 0) -> Archive:
    """The archive of pages (page_id, url, html).

    Of equal payloads of at least ``least_bytes`` that of the largest page_id is the response; others revisit it. A null
    html is an empty payload. A row that repeats the response's page_id is a response too, its payload stored once. Rows
    without a page_id revisit an equal payload that has one, and are responses otherwise. Other columns are not kept.
    """
    html = F.coalesce("html", F.lit(""))
    marks = [base32_sha1(html).alias("digest"), F.sha2(html, 256).alias("check"), F.octet_length(html).cast("bigint").alias("size")]
    slim = written(pages.select("page_id", "url", *marks), "warc-index")
    # one row of each group keeps the payload: that of the largest page_id, or one without an id where none has one
    keepers = written(slim.groupBy(*ADDRESS).agg(F.max("page_id").alias("first")), "warc-groups")
    revisit = (F.col("size") >= least_bytes) & F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first"))
    kinds = slim.join(keepers, ADDRESS).withColumn("kind", F.when(revisit, "revisit").otherwise("response"))
    lines = header(F.col("kind"), F.col("page_id"), F.col("url"), F.col("digest"), F.col("size"), F.col("first"))
    headers = written(kinds.select("page_id", "kind", lines.alias("header"), *ADDRESS), "warc-headers")
    own = keepers.select(F.col("first").alias("page_id"), *ADDRESS)
    held = pressed(pages)
    named = held.where(F.col("page_id").isNotNull()).join(own.where(F.col("page_id").isNotNull()), ["page_id", *ADDRESS])
    unnamed = held.where(F.col("page_id").isNull()).join(own.where(F.col("page_id").isNull()).select(*ADDRESS), ADDRESS)
    if _repeats(slim.where(F.col("page_id").isNotNull())):
        named = named.dropDuplicates(ADDRESS)
    whole = named.select(*ADDRESS, "z").unionByName(unnamed.dropDuplicates(ADDRESS).select(*ADDRESS, "z"))
    return Archive(headers, written(whole, "warc-payloads"))


def pressed(pages: DataFrame) -> DataFrame:
    """page_id, digest, check, size and the payload's bytes compressed, of pages: what a payload is addressed by is taken from its bytes."""

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdCompressor(level=3)
        for b in batches:
            data = [(t or "").encode() for t in b.column("html").to_pylist()]
            yield batch(
                page_id=b.column("page_id"), digest=pa.array(map(_sha1, data), pa.string()), check=pa.array([hashlib.sha256(x).hexdigest() for x in data], pa.string()),
                size=pa.array(map(len, data), pa.int64()), z=pa.array(map(press.compress, data), pa.binary()),
            )

    return pages.select(F.col("page_id").cast("bigint").alias("page_id"), "html").mapInArrow(tidy(step), "page_id bigint, digest string, check string, size bigint, z binary")


def _sha1(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def _repeats(slim: DataFrame) -> bool:
    """Whether a page_id is repeated, so that payloads need a pass of their own to be stored once."""
    return slim.groupBy("page_id").agg(F.count("*").alias("n")).where("n > 1").limit(1).count() > 0


def records(archive: Archive) -> DataFrame:
    """(page_id, record, size, digest): whole records, without the blank lines that end them, and what is stored for each.

    A response's payload is joined by its address and goes into its record; a revisit has an empty block, and only the size
    and digest of what it refers to are joined. A record whose payload isn't in the archive is an error.
    """

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdDecompressor()
        for b in batches:
            blocks = [press.decompress(z) for z in _all(b, "z")]
            out = [h.encode() + END.encode() + x for h, x in zip(b.column("header").to_pylist(), blocks, strict=True)]
            yield batch(page_id=b.column("page_id"), record=pa.array(out, pa.binary()), size=pa.array(map(len, blocks), pa.int64()), digest=pa.array(map(_sha1, blocks), pa.string()))

    heads = archive.headers
    responses = heads.where("kind = 'response'").join(archive.payloads, ADDRESS, "left").select("page_id", "header", "z")
    revisits = heads.where("kind = 'revisit'").join(measured(archive), ADDRESS, "left")
    empty = F.concat(F.encode("header", "UTF-8"), F.lit(END.encode()))
    again = revisits.select("page_id", empty.alias("record"), _there("found_size").alias("size"), _there("found_digest").alias("digest"))
    return responses.mapInArrow(tidy(step), "page_id bigint, record binary, size bigint, digest string").unionByName(again)


def _there(column: str) -> Column:
    return F.when(F.col(column).isNull(), F.raise_error(F.lit("a record's payload is not in the archive"))).otherwise(F.col(column))


def _all(b: pa.RecordBatch, column: str) -> list:
    if b.column(column).null_count:
        raise ValueError("a record's payload is not in the archive")
    return b.column(column).to_pylist()


def measured(archive: Archive) -> DataFrame:
    """The address of every payload, with size and digest of its bytes as stored."""

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdDecompressor()
        for b in batches:
            data = [press.decompress(z) for z in b.column("z").to_pylist()]
            yield batch(**{c: b.column(c) for c in ADDRESS}, found_size=pa.array(map(len, data), pa.int64()), found_digest=pa.array(map(_sha1, data), pa.string()))

    return archive.payloads.mapInArrow(tidy(step), "digest string, check string, size bigint, found_size bigint, found_digest string")


def parsed(data: bytes, at: int = 0) -> tuple[dict[str, str], bytes, int]:
    """Header fields and block of the record that starts at a place, and where the block ends: it is as long as Content-Length says."""
    stop = data.index(END.encode(), at)
    lines = data[at:stop].decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError(f"not a WARC record: {lines[0][:40]!r}")
    fields = dict(line.split(": ", 1) for line in lines[1:])
    at = stop + len(END)
    end = at + int(fields["Content-Length"])
    if end > len(data):
        raise ValueError("a record's block ends early")
    return fields, data[at:end], end


def read_back(archive: Archive) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to of every record, parsed from the records' bytes.

    A response's size and digest are those of its block; a revisit's are those of the stored payload that it refers to.
    A record's digest field must say the same as its payload.
    """

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            kinds, refers, sizes, digests = [], [], [], []
            for record, size, digest in zip(*(b.column(c).to_pylist() for c in ("record", "size", "digest")), strict=True):
                fields, block, end = parsed(record)
                kinds.append(fields["WARC-Type"])
                if kinds[-1] == "response":
                    size, digest = len(block), _sha1(block)
                if end != len(record) or fields["WARC-Payload-Digest"] != "sha1:" + digest:
                    raise ValueError("a record's payload is not what its header says")
                refer = fields.get("WARC-Refers-To")
                refers.append(int(refer[len("<urn:page:") : -1]) if refer else None)
                sizes.append(size)
                digests.append(digest)
            yield batch(page_id=b.column("page_id"), payload_bytes=pa.array(sizes, pa.int64()), payload_digest=pa.array(digests, pa.string()), record_type=pa.array(kinds, pa.string()), refers_to=pa.array(refers, pa.int64()))

    kinds = "page_id bigint, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint"
    return records(archive).mapInArrow(tidy(step), kinds)


def originals(archive: Archive) -> DataFrame:
    """(page_id, header, payload): every record with its full payload, revisits included."""

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdDecompressor()
        for b in batches:
            yield batch(page_id=b.column("page_id"), header=b.column("header"), payload=pa.array([press.decompress(z).decode() for z in _all(b, "z")], pa.string()))

    return archive.headers.join(archive.payloads, ADDRESS, "left").select("page_id", "header", "z").mapInArrow(tidy(step), "page_id bigint, header string, payload string")


def write_files(archive: Archive, path: str | None = None, rows_a_file: int = 10_000) -> str:
    """WARC files of all records: Spark's text writer ends each with the two line breaks of the format."""
    spark = archive.headers.sparkSession
    path = path or stage_path(spark, "warc-files")
    records(archive).select(F.decode("record", "UTF-8").alias("record")).write.option("lineSep", END).option("maxRecordsPerFile", rows_a_file).text(path)
    return path


def read_files(spark: SparkSession, path: str) -> DataFrame:
    """(header, block) of each record in WARC files, cut by its Content-Length."""

    def step(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for data in b.column("content").to_pylist():
                at, found = 0, []
                while at < len(data):
                    _, block, end = parsed(data, at)
                    found.append((data[at : data.index(END.encode(), at)].decode(), block.decode()))
                    at = end + len(END)
                yield batch(header=pa.array([h for h, _ in found], pa.string()), block=pa.array([x for _, x in found], pa.string()))

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(step, "header string, block string")
