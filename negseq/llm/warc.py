"""Legacy archive converter: ARC records to WARC, archives as files, and reading them back.

An ARC record is a line of fields and a body of the declared length. Version 1 has
``url ip date type length``; version 2 has ``url ip date type code checksum location
offset file length``. The version is that of the file's first record (``filedesc:``),
whose body states it. The converter parses the line from the right, so a URL with blanks does
no harm, takes the body by its length and never by its content, and synthesises what WARC asks
for: a record id (a name-based UUID of URL, date and place in the archive), an ISO
timestamp, the record type and SHA-1 digests in base32.

Equal payloads are found by SHA-256 over all pages: the least page id is the response, others
are revisits that name it. Archives are compressed files of whole records in the shared
folder, about ``ARCHIVE_BYTES`` each before compression; reading goes by declared lengths only.

Defined results: a null html is an empty payload, and empty payloads equal each other;
a null url is written as ``about:blank``; white space and control characters in a URL are
percent-encoded; repeated rows of one page id each get a record, the page id refers to
itself only through another id; a null page id is written as -1.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import re
import uuid
from collections.abc import Iterator
from urllib.parse import quote

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import shared_dir

#: Size of an archive, but for one larger record; a task holds one archive at a time.
ARCHIVE_BYTES = 16 << 20
VERSION_LINES = {1: "URL IP-address Archive-date Content-type Archive-length", 2: "URL IP-address Archive-date Content-type Result-code Checksum Location Offset Filename Archive-length"}
EPOCH = "20200101000000"


def arc_header(version: int, name: str, date: str = EPOCH) -> bytes:
    body = f"{version} 0 converter\n{VERSION_LINES[version]}\n".encode()
    fields = [f"filedesc://{name}", "0.0.0.0", date, "text/plain"] + (["200", "-", "-", "0", name] if version == 2 else [])
    return " ".join([*fields, str(len(body))]).encode() + b"\n" + body + b"\n"


def arc_record(version: int, url: str, body: bytes, date: str = EPOCH, kind: str = "text/html", offset: int = 0, name: str = "-", ip: str = "0.0.0.0") -> bytes:
    fields = [url, ip, date, kind] + (["200", "-", "-", str(offset), name] if version == 2 else [])
    return " ".join([*fields, str(len(body))]).encode() + b"\n" + body + b"\n"


def parse_arc(data: bytes) -> Iterator[dict]:
    """Records of an ARC file; the first, filedesc, sets the version of the others."""
    at, version = 0, None
    while at < len(data):
        if data[at : at + 1] in (b"\n", b"\r"):
            at += 1
            continue
        stop = data.find(b"\n", at)
        if stop < 0:
            raise ValueError(f"an ARC header line at {at} does not end")
        line = data[at:stop].decode("utf-8", "surrogateescape").rstrip("\r")
        length = int(line.rsplit(" ", 1)[1])
        body = data[stop + 1 : stop + 1 + length]
        if len(body) < length:
            raise ValueError(f"the ARC record at {at} declares {length} bytes and has {len(body)}")
        if version is None:
            if not line.startswith("filedesc:"):
                raise ValueError("an ARC file begins with a filedesc record")
            version = int(body.split(b" ", 1)[0])
            if version not in VERSION_LINES:
                raise ValueError(f"ARC version {version}")
        else:
            fields = line.rsplit(" ", len(VERSION_LINES[version].split(" ")) - 1)
            named = dict(zip(VERSION_LINES[version].split(" "), fields, strict=True))
            yield {"url": named["URL"], "ip": named["IP-address"], "date": named["Archive-date"], "type": named["Content-type"], "offset": at, "body": body}
        at = stop + 1 + length


def base32_sha1(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def timestamp(date: str) -> str:
    """ISO form of an ARC date of 12 or 14 digits."""
    d = (date + "00000000000000")[:14] if re.fullmatch(r"\d{8,14}", date) else EPOCH
    return f"{d[:4]}-{d[4:6]}-{d[6:8]}T{d[8:10]}:{d[10:12]}:{d[12:14]}Z"


def record_id(record: dict, key: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, '|'.join((record['url'], record['date'], key)))}>"


def warc_record(record: dict, key: str, refers_to: tuple[str, str] | None = None) -> bytes:
    """An ARC record as a WARC one. refers_to: key and URL of the record with the same payload; the body then stays out."""
    body = record["body"]
    digest = base32_sha1(body)
    head = [
        ("WARC-Type", "revisit" if refers_to is not None else "response"),
        ("WARC-Record-ID", record_id(record, key)),
        ("WARC-Date", timestamp(record["date"])),
        ("WARC-Target-URI", record["url"]),
        ("WARC-IP-Address", record["ip"]),
        ("WARC-Payload-Digest", f"sha1:{digest}"),
        ("X-Payload-Length", str(len(body))),
        ("X-Source-Key", key),
    ]
    if refers_to is not None:
        to, url = refers_to
        head += [("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"), ("WARC-Refers-To", record_id({"url": url, "date": record["date"]}, to)), ("WARC-Refers-To-Target-URI", url), ("WARC-Refers-To-Date", timestamp(record["date"])), ("X-Refers-To-Key", to)]
    block = b"" if refers_to is not None else body
    head += [("WARC-Block-Digest", f"sha1:{base32_sha1(block)}"), ("Content-Type", record["type"]), ("Content-Length", str(len(block)))]
    return b"WARC/1.1\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head).encode() + b"\r\n" + block + b"\r\n\r\n"


def parse_warc(data: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    at = 0
    while at < len(data):
        stop = data.index(b"\r\n\r\n", at)
        first, *lines = data[at:stop].decode().split("\r\n")
        if not first.startswith("WARC/"):
            raise ValueError(f"no WARC record begins at {at}")
        head = dict(line.split(": ", 1) for line in lines)
        size = int(head["Content-Length"])
        yield head, data[stop + 4 : stop + 4 + size]
        at = stop + 4 + size + 4


def convert(arc: bytes, refers_to: list[tuple[str, str] | None], keys: list[str]) -> list[bytes]:
    """The WARC records of an ARC file; keys and referred keys in the order of its records."""
    return [warc_record(r, k, to) for r, k, to in zip(parse_arc(arc), keys, refers_to, strict=True)]


def _url(url: str | None) -> str:
    return quote(url, safe="".join(map(chr, range(0x21, 0x7F)))) if url else "about:blank"


def pack(archive_bytes: int):
    """Pages to archives: the pages of each slice become one ARC file, in the old and the new version in turn, which is converted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        arc, keys, refers, size, version = [], [], [], 0, 1

        def archive() -> pa.RecordBatch:
            records = convert(arc_header(version, "pages.arc") + b"".join(arc), refers, keys)
            # the writer ends each line, so the last line break stays out
            return pa.RecordBatch.from_arrays([pa.array([b"".join(records)[:-1].decode()], pa.string())], ["value"])

        for batch in batches:
            for row in zip(*batch.columns, strict=True):
                key, url, html, to, to_url = (x.as_py() for x in row)
                arc.append(arc_record(version, _url(url), (html or "").encode()))
                keys.append(str(key))
                refers.append(None if to is None else (str(to), _url(to_url)))
                size += len(arc[-1])
                if size >= archive_bytes:
                    yield archive()
                    arc, keys, refers, size, version = [], [], [], 0, 3 - version
        if arc:
            yield archive()

    return run


def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for data in batch.column(0):
            rows = []
            own: dict[str, str] = {}
            for head, block in parse_warc(gzip.decompress(data.as_py())):
                revisit = head["WARC-Type"] == "revisit"
                digest = head["WARC-Payload-Digest"].split(":", 1)[1] if revisit else base32_sha1(block)
                if not revisit and head["WARC-Payload-Digest"] != f"sha1:{digest}":
                    raise ValueError(f"payload of {head['WARC-Record-ID']} does not match its digest")
                length = int(head["X-Payload-Length"]) if revisit else len(block)
                to = head.get("X-Refers-To-Key")
                rows.append((int(head["X-Source-Key"]), length, digest, head["WARC-Type"], None if to is None else int(to), head["WARC-Target-URI"], head["WARC-Record-ID"], head["WARC-Date"]))
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.string()]
            names = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url", "record_id", "date"]
            columns = list(zip(*rows, strict=True)) or [()] * len(kinds)
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names)


def with_first(pages: DataFrame, id_col: str, url_col: str, html_col: str, least_bytes: int = 0) -> DataFrame:
    """id, url, html, refers_to and refers_url: the least id of an equal payload and its URL, null for that id itself."""
    body = F.coalesce(F.col(html_col), F.lit(""))
    rows = pages.select(F.coalesce(F.col(id_col).cast("long"), F.lit(-1)).alias("id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    digests = pages.select(F.coalesce(F.col(id_col).cast("long"), F.lit(-1)).alias("id"), F.col(url_col).alias("url"), F.sha2(body, 256).alias("digest"), F.octet_length(body).alias("bytes"))
    digests = digests.where(F.col("bytes") >= least_bytes).select("id", "url", "digest")
    first = digests.groupBy("digest").agg(F.min(F.struct("id", "url")).alias("least"), F.count("*").alias("n")).where("n > 1").select("digest", F.col("least.id").alias("first"), F.col("least.url").alias("first_url"))
    # with repeated ids the payload of the row decides, so the join also holds the digest
    to = digests.select("id", "digest").distinct().join(first, "digest").where("id <> first").select(F.col("id").alias("_id"), F.col("digest").alias("_digest"), F.col("first").alias("refers_to"), F.col("first_url").alias("refers_url"))
    return rows.withColumn("digest", F.sha2(F.coalesce("html", F.lit("")), 256)).join(to, (F.col("id") == F.col("_id")) & (F.col("digest") == F.col("_digest")), "left").select("id", "url", "html", "refers_to", "refers_url")


def write_archives(pages: DataFrame, path: str, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", archive_bytes: int = ARCHIVE_BYTES, least_bytes: int = 0) -> str:
    """Write one WARC record per page; equal payloads of at least least_bytes are stored once."""
    rows = with_first(pages, id_col, url_col, html_col, least_bytes)
    rows.mapInArrow(pack(archive_bytes), "value string").write.option("lineSep", "\n").option("maxRecordsPerFile", 1).option("compression", "gzip").text(path)
    return path


def read_archives(spark, path: str) -> DataFrame:
    files = spark.read.format("binaryFile").load(path).select("content")
    return files.mapInArrow(unpack, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url string, record_id string, date string")


def round_trip(pages: DataFrame) -> DataFrame:
    spark = pages.sparkSession
    return read_archives(spark, write_archives(pages, f"{shared_dir(spark)}/warc-{uuid.uuid4().hex}"))
