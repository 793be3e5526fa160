"""WARC archives written index first, and read back by coalesced byte ranges.

Each task writes one archive of gzip members, one per record, and returns the
index: archive, offset, length, URL and digest. Only the index that Spark
commits names archives, so what a lost or repeated task left behind is never
read. Reading sorts the selected index rows by archive and offset and joins
neighbouring ranges into one read.
"""

from __future__ import annotations

import gzip
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator
from urllib.parse import quote, unquote

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .workers import tidy
from .workspace import Workspace

#: Payloads below it are never revisits. Ranges nearer than GAP are read in one go, up to READ bytes.
REVISIT_BYTES, GAP, READ = 100, 64 << 10, 8 << 20
INDEX = "page_id {kind}, archive string, offset long, length long, url string, payload_digest string, record_type string"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def _record_id(page, url: str) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'{page} {url}')}>"


def _store(folder: str) -> tuple[pafs.FileSystem, str]:
    """Arrow's file system for a folder as Hadoop names it."""
    return pafs.FileSystem.from_uri(re.sub("^s3[an]:", "s3:", folder))


def _record(page, url: str, payload: bytes, digest: str, refers_to, refers_url: str | None) -> bytes:
    """One record; a revisit carries headers alone and the length of the payload it stands for. Ids stand escaped, a null id not at all."""
    revisit = refers_to is not None
    block = b"" if revisit else b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload) + payload
    head = [
        "WARC/1.1",
        f"WARC-Type: {'revisit' if revisit else 'response'}",
        f"WARC-Record-ID: {_record_id(page, url)}",
        f"WARC-Target-URI: {url}",
        "WARC-Date: 1970-01-01T00:00:00Z",
        f"WARC-Payload-Digest: sha256:{digest}",
        *([f"X-Page-ID: {quote(str(page), safe='')}"] if page is not None else []),
        f"X-Payload-Length: {len(payload)}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    if revisit:
        head += [f"WARC-Profile: {REVISIT_PROFILE}", f"WARC-Refers-To: {_record_id(refers_to, refers_url)}", f"WARC-Refers-To-Target-URI: {refers_url}", f"X-Refers-To-Page-ID: {quote(str(refers_to), safe='')}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def plan_records(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``page_id, url, payload, payload_digest, refers_to, refers_url``: which page each one revisits, if any.

    Digests are counted before anything wide moves; only digests that occur
    more than once are joined back. Of repeated rows of the smallest page all
    are responses; null ids never are the smallest, and if a payload has null
    ids alone all its records are responses. A null page is an empty payload,
    a null URL an empty one; white space and controls in URLs are escaped, as
    a header ends at the line.
    """
    html = F.coalesce(F.col(html_col).cast("string"), F.lit("")).cast("binary")
    rows = pages.select(
        F.col(id_col).alias("page_id"),
        F.regexp_replace(F.coalesce(F.col(url_col).cast("string"), F.lit("")), r"[\x00-\x20\x7F-\x9F\u2028\u2029]", "%20").alias("url"),
        html.alias("payload"),
        F.sha2(html, 256).alias("payload_digest"),
    )
    long_enough = F.octet_length("payload") >= REVISIT_BYTES
    # short payloads, of which thousands may be empty, look up no digest: each has a key of its own
    rows = rows.withColumn("sought", F.when(long_enough, F.col("payload_digest")).otherwise(F.concat(F.lit("-"), F.coalesce(F.col("page_id").cast("string"), F.lit("")))))
    narrow = rows.where(long_enough).select("page_id", "url", F.col("payload_digest").alias("sought"))
    first = F.min(F.when(F.col("page_id").isNotNull(), F.struct("page_id", "url"))).alias("first")
    shared = narrow.groupBy("sought").agg(first, F.count("*").alias("n")).where("n > 1").select("sought", F.col("first.page_id").alias("first_id"), F.col("first.url").alias("first_url"))
    revisits = F.col("first_id").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first_id"))
    return rows.join(shared, "sought", "left").select(
        "page_id", "url", "payload", "payload_digest", F.when(revisits, F.col("first_id")).alias("refers_to"), F.when(revisits, F.col("first_url")).alias("refers_url")
    )


def write_archives(records: DataFrame, folder: str) -> DataFrame:
    """Index rows of the records, whose archives lie in ``folder``; evaluate it once, by writing it."""
    kind = records.schema["page_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, base = _store(folder)
        store.create_dir(base, recursive=True)
        name, at, out = f"{uuid.uuid4().hex}.warc.gz", 0, None
        try:
            for batch in batches:
                rows = []
                pages, urls, digests, refers, refers_urls = (batch.column(k).to_pylist() for k in (0, 1, 3, 4, 5))
                for k, page in enumerate(pages):
                    out = out or store.open_output_stream(f"{base}/{name}", compression=None)
                    member = gzip.compress(_record(page, urls[k], batch.column(2)[k].as_py(), digests[k], refers[k], refers_urls[k]), 6, mtime=0)
                    out.write(member)
                    rows.append((page, name, at, len(member), urls[k], digests[k], "revisit" if refers[k] is not None else "response"))
                    at += len(member)
                types = [batch.column(0).type, pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string()]
                columns = zip(*rows, strict=True) if rows else [[]] * 7
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], ["page_id", "archive", "offset", "length", "url", "payload_digest", "record_type"])
        finally:
            if out:
                out.close()

    return records.mapInArrow(tidy(run), INDEX.format(kind=kind))


def coalesce_ranges(ranges: list[tuple[int, int]], gap: int = GAP, most: int = READ) -> Iterator[tuple[int, int, int, int]]:
    """``(first, last, start, stop)``: rows [first, last) of the sorted ranges that one read of [start, stop) serves."""
    first = 0
    while first < len(ranges):
        start, stop = ranges[first][0], sum(ranges[first])
        last = first + 1
        while last < len(ranges) and ranges[last][0] - stop <= gap and sum(ranges[last]) - start <= most:
            stop = max(stop, sum(ranges[last]))
            last += 1
        yield first, last, start, stop
        first = last


def parse_record(member: bytes) -> dict:
    """Headers and payload of one gzip member; raises ValueError if it is not whole."""
    inflate = zlib.decompressobj(31)
    raw = inflate.decompress(member) + inflate.flush()
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode("utf-8").split("\r\n")
    fields = dict(x.partition(": ")[::2] for x in lines[1:])
    n = int(fields["Content-Length"])
    if lines[0] != "WARC/1.1" or not inflate.eof or rest[n:] != b"\r\n\r\n":
        raise ValueError("broken WARC record")
    payload = rest[:n].partition(b"\r\n\r\n")[2] if n else b""
    return fields | {"payload": payload}


def read_records(index: DataFrame, folder: str) -> DataFrame:
    """The selected records, parsed from their byte ranges and checked against their digests.

    ``page_id, url, payload, payload_bytes, payload_digest, record_type,
    refers_to``; the payload of a revisit is null. ``index`` may be any
    selection of index rows. Rows are dealt by archive and sorted by offset.
    """
    kind = index.schema["page_id"].dataType.simpleString()
    schema = f"page_id {kind}, url string, payload binary, payload_bytes long, payload_digest string, record_type string, refers_to {kind}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, base = _store(folder)
        handle, opened = None, None
        for batch in batches:
            pages, names, offsets, lengths = (batch.column(k).to_pylist() for k in range(4))
            ranges = list(zip(offsets, lengths, strict=True))
            k = 0
            while k < len(pages):
                stop_row = k
                while stop_row < len(pages) and names[stop_row] == names[k]:
                    stop_row += 1
                if opened != names[k]:
                    handle, opened = store.open_input_file(f"{base}/{names[k]}"), names[k]
                for first, last, start, stop in coalesce_ranges(ranges[k:stop_row]):
                    held, rows = handle.read_at(stop - start, start), []
                    for j in range(k + first, k + last):
                        r = parse_record(held[offsets[j] - start : offsets[j] - start + lengths[j]])
                        revisit, digest = r["WARC-Type"] == "revisit", r["WARC-Payload-Digest"].removeprefix("sha256:")
                        if not revisit and (hashlib.sha256(r["payload"]).hexdigest() != digest or len(r["payload"]) != int(r["X-Payload-Length"])):
                            raise ValueError(f"payload of page {pages[j]} differs from its digest")
                        rows.append((r.get("X-Page-ID"), r["WARC-Target-URI"], None if revisit else r["payload"], int(r["X-Payload-Length"]), digest, r["WARC-Type"], r.get("X-Refers-To-Page-ID")))
                    columns = list(zip(*rows, strict=True))
                    ids = [pa.array([x if x is None else unquote(x) for x in columns[c]], pa.string()).cast(batch.column(0).type) for c in (0, 6)]
                    middle = [pa.array(c, t) for c, t in zip(columns[1:6], (pa.string(), pa.binary(), pa.int64(), pa.string(), pa.string()), strict=True)]
                    yield pa.RecordBatch.from_arrays([ids[0], *middle, ids[1]], ["page_id", "url", "payload", "payload_bytes", "payload_digest", "record_type", "refers_to"])
                k = stop_row

    archives = index.agg(F.countDistinct("archive")).first()[0]  # a stated number keeps small index rows from meeting in one task
    return index.select("page_id", "archive", "offset", "length").repartition(max(1, archives), "archive").sortWithinPartitions("archive", "offset").mapInArrow(tidy(run), schema)


def archive_pages(pages: DataFrame, **columns: str) -> tuple[DataFrame, str]:
    """Writes archives and their index; returns the index table and the folder of the archives."""
    work = Workspace(pages.sparkSession, "warc")
    folder = work.path("archives")
    return work.save(write_archives(plan_records(pages, **columns), folder), "index"), folder


def op3_warc(spark, sf_dir: str) -> DataFrame:
    """Every page archived and read back: its payload's length and digest, and what it revisits."""
    index, folder = archive_pages(spark.read.parquet(f"{sf_dir}/pages.parquet"))
    return read_records(index, folder).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url")


ORACLE = """
WITH p AS (SELECT page_id, coalesce(html, '') AS h, octet_length(encode(coalesce(html, ''))) AS n, sha256(coalesce(html, '')) AS d,
                  regexp_replace(coalesce(url, ''), '[\\x00-\\x20\\x7F-\\x{9F}\\x{2028}\\x{2029}]', '%20', 'g') AS url FROM pages),
     f AS (SELECT d, min(page_id) AS first_id FROM p WHERE n >= 100 GROUP BY d)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes, p.d AS payload_digest,
       CASE WHEN n >= 100 AND page_id <> first_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN n >= 100 AND page_id <> first_id THEN first_id END AS refers_to, url
FROM p LEFT JOIN f ON p.d = f.d
"""
