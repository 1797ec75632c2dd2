"""Web archives with an index first: write records, index them, read chosen records by coalesced ranges.

Each task writes one gzip-per-record archive into the shared folder and returns an index row for
each record: file, offset, length, URL, digest. Files carry the attempt's number and only the index
of the attempt that Spark commits is kept, so a lost executor leaves at most an unreferenced file.
Readers take index rows in (file, offset) order, join ranges that lie close together into one read,
and check each payload against its digest.

Of records with equal payloads of at least ``least`` bytes the one with the largest id is the
response and the others revisit it (digests are summed before the join, which AQE can split, and only
rows that a bitmap of repeated digests lets through take part in it).

Defined results: a null html is an empty payload; a null URL is written as an empty one; a row with
a null page_id revisits when others have its payload and an id, else it is a response; rows that
repeat the largest id are all responses; empty input gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import zlib

import pandas as pd
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import map_rows, map_texts, pick, scratch, split_among, written

LEAST, GAP, READ = 1000, 64 << 10, 8 << 20
FILE_BYTES, BIN_BYTES = 256 << 20, 4 << 20
INDEX = "file string, offset long, length long, url string, digest string, page_id long, record_type string"
_REVISIT = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def opened(path: str) -> tuple[fs.FileSystem, str]:
    """File system and path of a URI or plain path, on the driver or an executor."""
    if path.startswith("file:"):
        path = "/" + path.removeprefix("file:").lstrip("/")
    return (fs.LocalFileSystem(), path) if path.startswith("/") else fs.FileSystem.from_uri(path)


def record(page_id: int | None, url: str | None, payload: bytes, digest: str, refers_to: int | None) -> bytes:
    """One WARC record: response, or revisit of the record ``refers_to``."""
    name = "none" if page_id is None else str(page_id)
    coded = base64.b32encode(bytes.fromhex(digest)).decode()
    revisit = refers_to is not None
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
    block = http if revisit else http + payload
    head = [
        "WARC/1.1",
        f"WARC-Type: {'revisit' if revisit else 'response'}",
        f"WARC-Record-ID: <urn:page:{name}>",
        f"WARC-Target-URI: {(url or '').encode('unicode_escape').decode()}",
        "WARC-Date: 1970-01-01T00:00:00Z",
        f"WARC-Payload-Digest: sha1:{coded}",
        f"X-Payload-Length: {len(payload)}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    if revisit:
        head[3:3] = [f"WARC-Profile: {_REVISIT}", f"WARC-Refers-To: <urn:page:{refers_to}>"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def parsed(raw: bytes) -> dict:
    """Fields of a record, its payload checked against its digest (revisits carry none)."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    version, *lines = head.decode().split("\r\n")
    if version != "WARC/1.1":
        raise ValueError(f"not a record: {version[:40]!r}")
    fields = dict(line.split(": ", 1) for line in lines if ": " in line)
    block = rest[: int(fields["Content-Length"])]
    digest = base64.b32decode(fields["WARC-Payload-Digest"].removeprefix("sha1:")).hex()
    payload = None
    if fields["WARC-Type"] == "response":
        payload = block.partition(b"\r\n\r\n")[2]
        if hashlib.sha1(payload).hexdigest() != digest or len(payload) != int(fields["X-Payload-Length"]):
            raise ValueError(f"payload of {fields['WARC-Record-ID']} does not match its digest")

    def number(field: str) -> int | None:
        name = fields.get(field, "<urn:page:none>")[10:-1]
        return None if name == "none" else int(name)

    return {
        "page_id": number("WARC-Record-ID"), "payload_bytes": int(fields["X-Payload-Length"]), "payload_digest": digest,
        "record_type": fields["WARC-Type"], "refers_to": number("WARC-Refers-To"), "payload": payload,
        "url": fields.get("WARC-Target-URI", "").encode().decode("unicode_escape"),
    }


def _writer(folder: str):
    def run(batches):
        where, path = opened(folder)
        where.create_dir(path, recursive=True)
        task, n, out, at = TaskContext.get(), 0, None, 0
        for pdf in batches:
            rows = []
            for page_id, url, html, digest, first in zip(pdf["page_id"], pdf["url"], pdf["html"], pdf["digest"], pdf["first"]):
                page_id, first = (None if pd.isna(x) else int(x) for x in (page_id, first))
                if out is None or at >= FILE_BYTES:
                    if out is not None:
                        out.close()
                    name, n, at = f"part-{task.partitionId():06d}-{task.taskAttemptId()}-{n:04d}.warc.gz", n + 1, 0
                    out = where.open_output_stream(f"{path}/{name}", compression=None)
                refers_to = first if first is not None and first != page_id else None
                packer = zlib.compressobj(6, zlib.DEFLATED, 31)
                raw = packer.compress(record(page_id, url, (html or "").encode("utf-8", "surrogatepass"), digest, refers_to)) + packer.flush()
                out.write(raw)
                rows.append((name, at, len(raw), url, digest, page_id, "response" if refers_to is None else "revisit"))
                at += len(raw)
            yield pd.DataFrame(rows, columns=["file", "offset", "length", "url", "digest", "page_id", "record_type"]).astype({"page_id": "Int64"})
        if out is not None:
            out.close()

    return run


def write(pages: DataFrame, folder: str, least: int = LEAST) -> DataFrame:
    """Writes a record per row of pages (page_id, url, html) into folder; returns the index, itself written."""
    own = pick(pages, page_id="page_id", url="url", html="html").withColumn("digest", F.sha1(F.coalesce("html", F.lit("")).cast("binary")))
    large = F.coalesce(F.octet_length("html"), F.lit(0)) >= least
    keyed = own.withColumn("large", F.when(large, F.col("digest")))
    many = keyed.where("large is not null").groupBy("large").agg(F.max("page_id").alias("first"), F.count("*").alias("n")).where("n > 1 and first is not null")
    many = written(many.select(F.col("large").alias("_k"), "first"), "repeated")
    # a bitmap of fixed size tells which rows may have a repeated payload; only those are shuffled with their text
    alone, shared = split_among(keyed, "large", many, "_k", 20)
    columns = ["page_id", "url", "html", "digest"]
    alone = alone.select(*columns, F.lit(None).cast("long").alias("first"))
    shared = shared.join(many, F.concat("large", F.lit("")) == F.concat("_k", F.lit("")), "left").select(*columns, "first")
    return written(map_texts(alone, _writer(folder), INDEX).unionByName(map_texts(shared, _writer(folder), INDEX)), "warc-index")


def _reader(folder: str, with_payload: bool):
    columns = ["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url", *["payload"] * with_payload]

    def ranges(batches):
        """Runs of index rows of one file that one read covers."""
        run: list[tuple[str, int, int]] = []
        for pdf in batches:
            for row in zip(pdf["file"], pdf["offset"].tolist(), pdf["length"].tolist()):
                if run and (row[0] != run[0][0] or row[1] > run[-1][1] + run[-1][2] + GAP or row[1] + row[2] - run[0][1] > READ):
                    yield run
                    run = []
                run.append(row)
        if run:
            yield run

    def read(batches):
        where, path = opened(folder)
        source, name = None, None
        for run in ranges(batches):
            if name != run[0][0]:
                if source is not None:
                    source.close()
                name = run[0][0]
                source = where.open_input_file(f"{path}/{name}")
            start = run[0][1]
            data = memoryview(source.read_at(run[-1][1] + run[-1][2] - start, start))
            rows = [parsed(zlib.decompress(data[o - start : o - start + n], 31)) for _, o, n in run]
            yield pd.DataFrame(rows, columns=columns).astype({"page_id": "Int64", "refers_to": "Int64"})
        if source is not None:
            source.close()

    return read


def read(index: DataFrame, folder: str, with_payload: bool = False) -> DataFrame:
    """The records that the index rows name; filter the index first to read some of them.

    Rows of a file that lie in one bin of ``BIN_BYTES`` go to one task, so tasks follow the bytes they read."""
    schema = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, url string" + ", payload binary" * with_payload
    total = index.agg(F.sum("length")).first()[0] or 0
    at = F.expr(f"offset div {BIN_BYTES}")
    parts = max(1, -(-total // BIN_BYTES))
    ordered = index.select("file", "offset", "length").repartition(parts, "file", at).sortWithinPartitions("file", "offset")
    return map_rows(ordered, _reader(folder, with_payload), schema)


def round_trip(pages: DataFrame) -> DataFrame:
    """Writes all pages to a new folder and reads every record back."""
    folder = scratch(pages.sparkSession, "warc")
    return read(write(pages, folder), folder)


ORACLE = """
with own as (select page_id, coalesce(html, '') as body from pages),
d as (select page_id, strlen(body) as payload_bytes, sha1(body) as payload_digest from own),
m as (select payload_digest, max(page_id) as first from d where payload_bytes >= 1000 group by 1 having count(*) > 1)
select d.page_id, d.payload_bytes, d.payload_digest,
  case when m.first is not null and m.first is distinct from d.page_id then 'revisit' else 'response' end as record_type,
  case when m.first is distinct from d.page_id then m.first end as refers_to
from d left join m on d.payload_digest = m.payload_digest and d.payload_bytes >= 1000"""
