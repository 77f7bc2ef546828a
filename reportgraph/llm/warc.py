"""WARC archives: writing with revisits, reading back, and merging of the capture index.

Each record is a gzip member of its own, so an index entry's offset and length are those of the file, and ``read_record``
reads one record without the others. Each archive read gives a run of index
entries sorted by URL key and time; entries are dealt by ranges of that key, and each range merges its
runs with a loser tree, so the whole index is in order, each URL's captures following each other.
"""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from collections.abc import Iterator
from urllib.parse import urlsplit

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reportgraph.operators.hot import join_hot
from reportgraph.sources.io import checkpointed, shared_dir

#: The alphabet of base32 digests, and the profile of revisits by equal payload.
BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
SAME_PAYLOAD = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
CRLF = "\r\n"
MIN_BYTES = 0
#: A file ends with the record that brings it to so many bytes or records.
FILE_BYTES, FILE_RECORDS = 64 << 20, 100_000
#: Index entries that a task merges, about.
RANGE_ROWS = 200_000
GZIP = 31
INDEX = "run string, urlkey string, ts string, page_id long, url string, record_type string, payload_digest string, payload_bytes long, refers_to long, offset long, length long"


def base32_sha1(text: Column) -> Column:
    """Upper-case base32 SHA-1 of a text's UTF-8 bytes, 20 bits at a time."""
    digits = F.sha1(F.encode(text, "UTF-8"))
    letters = F.array(*[F.lit(c) for c in BASE32])

    def four(k: int) -> Column:
        v = F.conv(F.substring(digits, 5 * k + 1, 5), 16, 10).cast("int")
        return F.concat(*[F.element_at(letters, F.shiftright(v, s).bitwiseAND(F.lit(31)) + 1) for s in (15, 10, 5, 0)])

    return F.concat(*[four(k) for k in range(8)])


def url_key(url: str | None) -> str:
    """Host with its labels reversed, then path and query, in lower case; what is no URL is its own key."""
    try:
        parts = urlsplit((url or "").strip())
        host = (parts.hostname or "").removeprefix("www.")
    except ValueError:
        return (url or "").lower()
    if not host:
        return (url or "").lower()
    port = ""
    try:
        port = f":{parts.port}" if parts.port and parts.port not in (80, 443) else ""
    except ValueError:
        pass
    return f"{','.join(reversed(host.split('.')))}{port}){parts.path or '/'}{'?' + parts.query if parts.query else ''}".lower()


def write_archives(pages: DataFrame, path: str, min_bytes: int = MIN_BYTES, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", file_bytes: int = FILE_BYTES, file_records: int = FILE_RECORDS) -> None:
    """Writes one record for each page under ``path``.

    Of pages with equal payloads of ``min_bytes`` or more, that with the largest id is the response and the
    others refer to it; null ids come before all others, and rows equal to the response in id are responses too.
    The largest id for each digest is combined before its shuffle; a hot digest is joined in many tasks. Names and sizes of the
    files written are in ``path/manifest``, which is complete when this returns.
    """
    html = F.coalesce(F.col(html_col), F.lit(""))
    rows = pages.select(
        F.col(id_col).cast("bigint").alias("page_id"), F.regexp_replace(F.coalesce(F.col(url_col), F.lit("")), r"[\r\n]", " ").alias("url"),
        html.alias("html"), base32_sha1(html).alias("digest"), F.octet_length(html).cast("bigint").alias("bytes"),
    )
    kept = rows.where(F.col("bytes") >= min_bytes).groupBy("digest").agg(F.max("page_id").alias("kept"), F.max_by("url", "page_id").alias("kept_url"), F.count("*").alias("n")).where("n > 1")
    rows = join_hot(rows, checkpointed(kept), "digest", ["page_id", "url"]).drop("n")
    again = F.coalesce(F.col("kept").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("kept")), F.lit(False))
    ident = F.coalesce(F.col("page_id").cast("string"), F.lit("none"))
    when = F.date_format(F.timestamp_seconds(F.pmod(F.coalesce("page_id", F.lit(0)), F.lit(1 << 31))), "yyyy-MM-dd'T'HH:mm:ss'Z'")
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{CRLF}Content-Type: text/html; charset=utf-8{CRLF}Content-Length: "), F.col("bytes").cast("string"), F.lit(CRLF + CRLF))
    block = F.when(again, http).otherwise(F.concat(http, F.col("html")))
    line = lambda name, value: F.concat(F.lit(f"{name}: "), value, F.lit(CRLF))
    head = F.concat(
        F.lit(f"WARC/1.1{CRLF}"), line("WARC-Type", F.when(again, "revisit").otherwise("response")), line("WARC-Record-ID", F.concat(F.lit("<urn:page:"), ident, F.lit(">"))),
        line("WARC-Target-URI", F.col("url")), line("WARC-Date", when), line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("digest"))),
        F.when(again, F.concat(line("WARC-Profile", F.lit(SAME_PAYLOAD)), line("WARC-Refers-To", F.concat(F.lit("<urn:page:"), F.col("kept").cast("string"), F.lit(">"))), line("WARC-Refers-To-Target-URI", F.coalesce("kept_url", F.lit(""))))).otherwise(""),
        line("Content-Type", F.lit("application/http; msgtype=response")), line("Content-Length", (F.octet_length(block)).cast("string")), F.lit(CRLF),
    )
    written = rows.select(F.concat(head, block, F.lit(CRLF + CRLF)).alias("record")).mapInArrow(lambda batches: _write(batches, path, file_bytes, file_records), "file string, records long, bytes long")
    written.write.parquet(f"{path}/manifest")


def place(path: str) -> tuple[fs.FileSystem, str]:
    """File system and path of a folder or file, given as a path or with a scheme."""
    if path.startswith("file:"):
        path = "/" + path.removeprefix("file:").lstrip("/")
    return fs.FileSystem.from_uri(path)


def _write(batches: Iterator[pa.RecordBatch], path: str, file_bytes: int, file_records: int) -> Iterator[pa.RecordBatch]:
    """Writes records as gzip members and gives the names of the files.

    A task tried twice writes files of two names; only those that the manifest lists are read.
    """
    system, folder = place(path)
    system.create_dir(folder, recursive=True)
    out, name, records, size = None, "", 0, 0
    for b in batches:
        for record in b.column(0):
            if out is None:
                name, records, size = f"{uuid.uuid4().hex}.warc.gz", 0, 0
                out = system.open_output_stream(f"{folder}/{name}", compression=None)
            member = zlib.compressobj(6, zlib.DEFLATED, GZIP)
            data = member.compress(record.as_buffer()) + member.flush()
            out.write(data)
            records, size = records + 1, size + len(data)
            if size >= file_bytes or records >= file_records:
                out.close()
                out = None
                yield _listed(name, records, size)
    if out is not None:
        out.close()
        yield _listed(name, records, size)


def _listed(name: str, records: int, size: int) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([records]), pa.array([size])], names=["file", "records", "bytes"])


def members(stream, step: int = 1 << 20) -> Iterator[tuple[int, int, bytes]]:
    """``(offset, length, content)`` of each gzip member of a stream; only one is held."""
    offset, member, parts, length, data = 0, zlib.decompressobj(GZIP), [], 0, b""
    while data or (data := stream.read(step)):
        parts.append(member.decompress(data))
        length += len(data) - len(member.unused_data)
        data = member.unused_data
        if member.eof:
            yield offset, length, b"".join(parts)
            offset, member, parts, length = offset + length, zlib.decompressobj(GZIP), [], 0
    if length:
        raise ValueError(f"record at {offset} is cut short")


def parsed(data: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and block of one record."""
    end = data.index(b"\r\n\r\n")
    lines = data[:end].decode("utf-8").split(CRLF)
    if not lines[0].startswith("WARC/"):
        raise ValueError("no record")
    headers = {k.lower(): v.strip() for k, v in (x.split(":", 1) for x in lines[1:])}
    block = data[end + 4 : end + 4 + int(headers["content-length"])]
    if len(data) != end + 8 + int(headers["content-length"]) or not data.endswith(b"\r\n\r\n"):
        raise ValueError("a record's length does not fit")
    return headers, block


def read_record(path: str, offset: int, length: int) -> tuple[dict[str, str], bytes]:
    """Headers and block of the record that an index entry names; nothing else of its file is read."""
    system, name = place(path)
    with system.open_input_file(name) as f:
        return parsed(zlib.decompress(f.read_at(length, offset), GZIP))


def _page(urn: str) -> int | None:
    ident = urn.removeprefix("<urn:page:").removesuffix(">")
    return None if ident == "none" else int(ident)


def read_index(spark, path: str) -> DataFrame:
    """Index entries of all archives that the manifest under ``path`` lists; payloads are read and their digests checked.

    A task reads one file after another, record by record; the entries of a file are a sorted run.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, folder = place(path)
        for b in batches:
            for name, count in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                rows = []
                with system.open_input_stream(f"{folder}/{name}", compression=None) as stream:
                    for offset, length, data in members(stream):
                        h, block = parsed(data)
                        head, _, payload = block.partition(b"\r\n\r\n")
                        http = dict(x.lower().split(b": ", 1) for x in head.split(b"\r\n")[1:])
                        digest = h["warc-payload-digest"].removeprefix("sha1:")
                        if h["warc-type"] == "response" and base64.b32encode(hashlib.sha1(payload).digest()).decode() != digest:
                            raise ValueError(f"{name}: payload at {offset} does not fit its digest")
                        rows.append((name, url_key(h["warc-target-uri"]), h["warc-date"], _page(h["warc-record-id"]), h["warc-target-uri"], h["warc-type"], digest, int(http[b"content-length"]), _page(h["warc-refers-to"]) if "warc-refers-to" in h else None, offset, length))
                if len(rows) != count:
                    raise ValueError(f"{name}: {len(rows)} records of {count}")
                rows.sort(key=entry_key)
                yield from (_batch(rows[k : k + 8192]) for k in range(0, len(rows), 8192))

    files = spark.read.parquet(f"{path}/manifest").select("file", "records")
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return files.repartition(n, "file").mapInArrow(run, INDEX)


_NAMES = [x.split()[0] for x in INDEX.split(", ")]
_TYPES = [pa.string() if x.endswith("string") else pa.int64() for x in INDEX.split(", ")]


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), _TYPES)], names=_NAMES)


class LoserTree:
    """Merges sorted runs; each inner node holds the loser of the match below it, so a step costs one path of comparisons."""

    def __init__(self, runs: list[Iterator], key):
        self.runs, self.key = [iter(r) for r in runs], key
        self.k = max(1, len(self.runs))
        self.heads = [self._pull(i) for i in range(len(self.runs))] + [None] * (self.k - len(self.runs))
        self.losers = [-1] * self.k
        for i in range(self.k):
            self._play(i)

    def _pull(self, i: int):
        row = next(self.runs[i], None)
        return None if row is None else (self.key(row), i, row)

    def _beats(self, a: int, b: int) -> bool:
        x, y = self.heads[a], self.heads[b]
        return x is not None and (y is None or x[:2] < y[:2])

    def _play(self, i: int) -> None:
        node = (i + self.k) // 2
        while node > 0:
            if self.losers[node] < 0:
                self.losers[node] = i
                return
            if self._beats(self.losers[node], i):
                i, self.losers[node] = self.losers[node], i
            node //= 2
        self.losers[0] = i

    def __iter__(self):
        while (head := self.heads[self.losers[0]]) is not None:
            yield head[2]
            i = self.losers[0]
            self.heads[i] = self._pull(i)
            node = (i + self.k) // 2
            while node > 0:
                if self._beats(self.losers[node], i):
                    i, self.losers[node] = self.losers[node], i
                node //= 2
            self.losers[0] = i


def entry_key(row: tuple) -> tuple:
    return row[1], row[2], row[3] is not None, row[3] or 0


def _rows_of(table: pa.Table, step: int = 256) -> Iterator[tuple]:
    """Rows of a run, a few at a time."""
    for k in range(0, table.num_rows, step):
        yield from zip(*(c.to_pylist() for c in table.slice(k, step).columns))


def merged_index(index: DataFrame, total: int | None = None, range_rows: int = RANGE_ROWS) -> DataFrame:
    """The entries in global order of URL key, time and page, with ``range``, ``place`` and ``capture``.

    Entries are dealt to ranges of about ``range_rows``, each of which merges its runs; the order is that of range and place in it.
    ``capture`` counts the entries of a URL key from 1, over ranges where its history goes on. Entries of null pages come
    first among equals. What a task holds are the entries of one range, of which only the heads of the runs are unpacked.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = [b for b in batches if b.num_rows]
        if not kept:
            return
        table = pa.Table.from_batches(kept)  # sorted by run, then key
        names = table.column("run").combine_chunks().dictionary_encode()
        names = (names.combine_chunks() if isinstance(names, pa.ChunkedArray) else names).indices.to_numpy()
        bounds = [0, *(np.flatnonzero(np.diff(names)) + 1).tolist(), len(names)]
        out, n, at, capture = [], 0, None, 0
        for row in LoserTree([_rows_of(table.slice(a, z - a)) for a, z in zip(bounds, bounds[1:])], entry_key):
            capture = capture + 1 if row[1] == at else 1
            at, n = row[1], n + 1
            out.append((*row, n, capture))
            if len(out) == 8192:
                yield batch(out)
                out = []
        if out:
            yield batch(out)

    def batch(rows: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), [*_TYPES, pa.int64(), pa.int64()])], names=[*_NAMES, "place", "capture"])

    total = index.count() if total is None else total
    n = max(1, min(int(index.sparkSession.conf.get("spark.sql.shuffle.partitions")), total), -(-total // range_rows))
    dealt = index.repartitionByRange(n, "urlkey", "ts", F.col("page_id").asc_nulls_first(), "run", "offset").sortWithinPartitions("run", "urlkey", "ts", F.col("page_id").asc_nulls_first(), "offset")
    # The ranges are numbered as they are written, and read again with those numbers.
    merged = checkpointed(dealt.mapInArrow(run, INDEX + ", place long, capture long").withColumn("range", F.spark_partition_id()))
    ends = merged.groupBy("range").agg(F.max_by(F.struct("urlkey", "capture"), "place").alias("last"), F.min_by("urlkey", "place").alias("first"))
    before = Window.partitionBy("key").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    # A key that ends one range and begins the next goes on there: what came before is the sum of its ends so far.
    lasts = ends.select(F.col("last.urlkey").alias("key"), "range", F.col("last.capture").alias("c"))
    firsts = ends.select(F.col("first").alias("key"), "range", F.lit(0).cast("bigint").alias("c"))
    begun = lasts.unionByName(firsts).groupBy("key", "range").agg(F.sum("c").alias("c")).withColumn("more", F.coalesce(F.sum("c").over(before), F.lit(0)))
    begun = begun.where("more > 0").select(F.col("key").alias("urlkey"), "range", "more")
    return merged.join(begun, ["urlkey", "range"], "left").withColumn("capture", F.col("capture") + F.coalesce("more", F.lit(0))).select(*_NAMES, "range", "place", "capture")


def archive_pages(pages: DataFrame, path: str | None = None, range_rows: int = RANGE_ROWS, **options) -> DataFrame:
    """Writes the pages' archives (in the shared folder if no path is given) and returns their merged index as read back.

    Null payloads count as empty, null URLs as empty, and a record without id refers to none. An empty table writes no record and gives no rows.
    """
    spark = pages.sparkSession
    path = path or f"{shared_dir(spark).rstrip('/')}/warc-{uuid.uuid4().hex}"
    write_archives(pages, path, **options)
    total = spark.read.parquet(f"{path}/manifest").agg(F.sum("records")).first()[0] or 0
    return merged_index(read_index(spark, path), total, range_rows)
