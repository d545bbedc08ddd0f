"""A content-addressed WARC archive: payloads once, headers apart, records by a join.

``payloads`` holds each distinct payload once under its SHA-256, verified by a second strong digest
(SHA-1, which the records carry as well); ``headers`` holds the exact WARC and HTTP header bytes of every record
and the address of its payload. A record is its header followed by the payload, or the header alone
where the record is a revisit.
"""

from __future__ import annotations

import gzip
import zlib
from collections.abc import Iterator
from typing import NamedTuple

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamat.llm import common
from deltamat.sources.scratch import materialize

# Fixed values of the formats.
BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
CRLF = "\r\n"
NO_DATE = "1970-01-01T00:00:00Z"


class Archive(NamedTuple):
    headers: DataFrame
    payloads: DataFrame


def base32(hexed: Column) -> Column:
    """Base32 of 40 hexadecimal digits: five digits make four characters."""
    groups = [F.conv(F.substring(hexed, 5 * g + 1, 5), 16, 10).cast("int") for g in range(8)]
    letter = lambda n: F.substring(F.lit(BASE32), n + 1, F.lit(1))
    return F.concat(*[letter(F.shiftright(n, 15 - 5 * k).bitwiseAND(F.lit(31))) for n in groups for k in range(4)])


def line(name: str, value: Column | str) -> Column:
    value = F.lit(value) if isinstance(value, str) else value
    return F.coalesce(F.concat(F.lit(f"{name}: "), value, F.lit(CRLF)), F.lit(""))


def write(pages: DataFrame, min_bytes: int = 0, date: str = NO_DATE) -> Archive:
    """Archive one record for every row of pages(page_id, url, html); null html is empty.

    Of records with equal payloads of at least ``min_bytes`` bytes those with the largest page_id
    are responses and the others revisit them; shorter payloads are all responses. Repeated rows
    with one page_id are records of their own; a null page_id counts as smaller than any other, and
    a null url leaves its header out. Line breaks in urls are percent-encoded.
    """
    html = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    rec = pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), html.alias("payload"))
    rec = rec.withColumns({"address": F.sha2("payload", 256), "bytes": F.octet_length("payload").cast("long")})
    second = F.sha1("payload")
    store = rec.groupBy("address").agg(F.first("payload").alias("payload"), F.max("page_id").alias("owner"), F.min(second).alias("lo"), F.max(second).alias("hi"))
    clash = F.raise_error(F.concat(F.lit("different payloads under one digest "), F.col("address")))
    store = store.select(F.when(F.col("lo") == F.col("hi"), F.col("address")).otherwise(clash.cast("string")).alias("address"), "owner", base32(F.col("lo")).alias("digest"), "payload")
    payloads = materialize(store, "payloads")

    thin = payloads.select("address", "owner", "digest")
    r = rec.select("page_id", "url", "bytes", "address").join(thin, "address")
    first = (F.col("bytes") < min_bytes) | F.col("page_id").eqNullSafe(F.col("owner"))
    name = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(F.col(c).cast("string"), F.lit("")), F.lit(">"))
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{CRLF}"), line("Content-Type", "text/html; charset=utf-8"), line("Content-Length", F.col("bytes").cast("string")), F.lit(CRLF))
    url = F.replace(F.replace(F.col("url"), F.lit("\r"), F.lit("%0D")), F.lit("\n"), F.lit("%0A"))
    length = F.octet_length(http) + F.when(first, F.col("bytes")).otherwise(0)
    head = F.concat(
        F.lit(f"WARC/1.1{CRLF}"),
        line("WARC-Type", F.when(first, "response").otherwise("revisit")),
        line("WARC-Record-ID", name("page_id")),
        line("WARC-Target-URI", url),
        line("WARC-Date", date),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("digest"))),
        F.when(first, F.lit("")).otherwise(F.concat(line("WARC-Refers-To", name("owner")), line("WARC-Profile", PROFILE))),
        line("Content-Type", "application/http; msgtype=response"),
        line("Content-Length", length.cast("string")),
        F.lit(CRLF),
        http,
    )
    headers = materialize(r.select("address", head.cast("binary").alias("header")), "headers")
    return Archive(headers, payloads.select("address", "payload"))


def field(name: str) -> Column:
    head = F.col("header").cast("string")
    return F.when(F.contains(head, F.lit(f"\n{name}: ")), F.regexp_extract(head, rf"\n{name}: ([^\r\n]*)", 1))


def page(c: Column) -> Column:
    return F.try_to_number(F.nullif(F.regexp_extract(c, r"<urn:page:(-?\d*)>", 1), F.lit("")), F.lit("S9999999999999999999")).cast("long")


def index(archive: Archive) -> DataFrame:
    """(page_id, record_type, refers_to, address, payload_digest, header) as the stored headers say."""
    kind = field("WARC-Type")
    return archive.headers.select(
        page(field("WARC-Record-ID")).alias("page_id"),
        kind.alias("record_type"),
        F.when(kind == "revisit", page(field("WARC-Refers-To"))).alias("refers_to"),
        "address",
        F.regexp_replace(field("WARC-Payload-Digest"), "^sha1:", "").alias("payload_digest"),
        "header",
    )


def rebuilt(archive: Archive) -> DataFrame:
    """index() with the header's bytes and the whole payload of every original record, revisits too.

    Each record is put together by a join on the payload's address and checked: a payload that does
    not hash to its address or to the header's digest, or a block whose length is not the header's
    Content-Length, fails the query. A payload that many records share is a hot key of a merge join.
    """
    said = index(archive).select("page_id", "record_type", "refers_to", "address", "payload_digest", "header")
    both = said.join(archive.payloads.hint("merge"), "address")
    head = F.col("header").cast("string")
    http = F.octet_length("header") - F.octet_length(F.substring_index(head, CRLF + CRLF, 1)) - 4
    block = http + F.when(F.col("record_type") == "response", F.octet_length("payload")).otherwise(0)
    sound = (F.sha2("payload", 256) == F.col("address")) & (base32(F.sha1("payload")) == F.col("payload_digest")) & (block == field("Content-Length").cast("long"))
    bad = F.raise_error(F.concat(F.lit("a record does not fit its payload "), F.col("address"))).cast("string")
    return both.select("page_id", "record_type", "refers_to", F.when(sound, F.col("payload_digest")).otherwise(bad).alias("payload_digest"), "header", "payload")


def records(archive: Archive) -> DataFrame:
    """(page_id, record): every record as a WARC file holds it, header and block and closing blank lines."""
    body = F.when(F.col("record_type") == "response", F.col("payload")).otherwise(F.lit(b""))
    return rebuilt(archive).where("payload_digest is not null").select("page_id", F.concat("header", body, F.lit(b"\r\n\r\n")).alias("record"))


def warc_files(archive: Archive, target_bytes: int = 64 << 20) -> DataFrame:
    """(part, data): the records as gzip members, joined into files of about target_bytes."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        part, members, size = 0, [], 0
        for f in frames:
            for record in f["record"]:
                members.append(gzip.compress(record, 6, mtime=0))
                size += len(members[-1])
                if size >= target_bytes:
                    yield pd.DataFrame({"part": [part], "data": [b"".join(members)]})
                    part, members, size = part + 1, [], 0
        if members:
            yield pd.DataFrame({"part": [part], "data": [b"".join(members)]})

    return records(archive).mapInPandas(run, "part int, data binary")


def parse(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Header fields and block of every record of a WARC file, plain or gzipped by record."""
    plain = bytearray()
    while data[:2] == b"\x1f\x8b":
        d = zlib.decompressobj(31)
        plain += d.decompress(data)
        data = d.unused_data
    data = bytes(plain) or data
    at = 0
    while (at := data.find(b"WARC/", at)) >= 0:
        end = data.index(b"\r\n\r\n", at)
        fields = dict(x.split(": ", 1) for x in data[at:end].decode("utf-8").split("\r\n")[1:])
        start = end + 4
        at = start + int(fields["Content-Length"])
        yield fields, data[start:at]
        at += 4


def read_warc(files: DataFrame) -> DataFrame:
    """(record_id, record_type, url, refers_to, payload) of files(data), payload without HTTP header."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            for data in f["data"]:
                rows = [(h.get("WARC-Record-ID"), h.get("WARC-Type"), h.get("WARC-Target-URI"), h.get("WARC-Refers-To"), b.partition(b"\r\n\r\n")[2]) for h, b in parse(data)]
                yield pd.DataFrame(rows, columns=["record_id", "record_type", "url", "refers_to", "payload"])

    return files.select("data").mapInPandas(run, "record_id string, record_type string, url string, refers_to string, payload binary")


def op10_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every page's record, archived, rebuilt from header and payload, and read back."""
    back = rebuilt(write(common.table(spark, sf_dir, "pages")))
    return back.select("page_id", F.octet_length("payload").cast("long").alias("payload_bytes"), "payload_digest", "record_type", "refers_to")


def oracle() -> str:
    letter = " || ".join(f"substr('{BASE32}', ((('0x' || substr(h, {5 * g + 1}, 5))::BIGINT >> {15 - 5 * k}) & 31)::INT + 1, 1)" for g in range(8) for k in range(4))
    return f"""
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
o AS (SELECT *, sha1(html) AS h, octet_length(encode(html))::BIGINT AS n, max(page_id) OVER (PARTITION BY html) AS owner FROM p)
SELECT page_id, n AS payload_bytes, {letter} AS payload_digest,
  CASE WHEN page_id IS NOT DISTINCT FROM owner THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id IS NOT DISTINCT FROM owner THEN NULL ELSE owner END AS refers_to FROM o"""
