"""WARC archives with a two-level capture index.

Archives are files of gzip members, one record each, in the shared folder.  The index is the list of captures sorted by
reversed-host URL key: its lines are cut into gzip blocks, a sparse directory keeps each block's first key, and a
lookup binary-searches the directory, reads one block, and then reads one record by its byte range.
"""

from __future__ import annotations

import base64
import bisect
import gzip
import hashlib
import json
import uuid
import zlib
from collections.abc import Iterable, Iterator
from urllib.parse import urlsplit

import pandas as pd
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import clean_columns, fresh_path, stage

#: Index lines in a block at least, and blocks at most: beyond that many blocks grow, so that the directory stays bounded.
BLOCK_LINES, MAX_BLOCKS = 256, 1 << 18
#: Characters of a key that the directory keeps.
FIRST_CHARS = 200
#: Pages that one task looks up on average.
LOOKUPS = 4000
# Fixed values of the format.
RESPONSE, REVISIT = "response", "revisit"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
_EPOCH = "2024-01-01T00:00:00Z"


def open_store(path: str) -> tuple[pafs.FileSystem, str]:
    """File system and path of a folder: local for ``file:``, else what pyarrow knows by the scheme."""
    if path.startswith("file:"):
        return pafs.LocalFileSystem(), "/" + path[5:].lstrip("/")
    if "://" not in path:
        return pafs.LocalFileSystem(), path
    return pafs.FileSystem.from_uri(path)


def url_key(url: str | None) -> str:
    """Reversed host and path of an address, lower case: ``http://Www.a.org/x`` gives ``org,a)/x`` (null: empty)."""
    if not url:
        return ""
    try:
        parts = urlsplit(url if "//" in url else "//" + url)
        host, port = (parts.hostname or "").lower(), parts.port
    except ValueError:
        return "invalid)/" + url.lower()
    host = host.removeprefix("www.")
    tail = (parts.path or "/") + (f"?{parts.query}" if parts.query else "")
    return ",".join(reversed(host.split("."))) + (f":{port}" if port and port not in (80, 443) else "") + ")" + tail.lower()


def block_digest(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def _target(url: str | None) -> str:
    return " ".join((url or "about:blank").split())


def make_record(page_id, url: str | None, payload: bytes, digest: str, refers_to) -> bytes:
    """One record: a response with its payload, or (``refers_to`` given) a revisit with the HTTP head alone."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    head = ["WARC/1.1", f"WARC-Type: {RESPONSE if refers_to is None else REVISIT}", f"WARC-Record-ID: <urn:page:{page_id}>", f"WARC-Date: {_EPOCH}", f"WARC-Target-URI: {_target(url)}", f"WARC-Payload-Digest: sha1:{digest}", "Content-Type: application/http; msgtype=response"]
    body = http + payload
    if refers_to is not None:
        head += [f"WARC-Refers-To: <urn:page:{refers_to}>", f"WARC-Profile: {PROFILE}"]
        body = http
    head.append(f"Content-Length: {len(body)}")
    return "\r\n".join(head).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"


def read_record(data: bytes) -> dict:
    """Fields of a record: headers by lower-case name, ``http`` head likewise, ``payload``."""
    head, _, rest = data.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    out = {k.lower(): v for k, _, v in (line.partition(": ") for line in lines[1:])}
    body = rest[: int(out["content-length"])]
    http, _, payload = body.partition(b"\r\n\r\n")
    out["http"] = {k.lower(): v for k, _, v in (line.partition(": ") for line in http.decode().split("\r\n")[1:])}
    out["payload"] = payload
    return out


def _id(urn: str | None):
    return None if urn is None or urn == "<urn:page:None>" else int(urn[len("<urn:page:") : -1])


def owners(pages: DataFrame, least: int = 0) -> DataFrame:
    """page_id, url, html with ``first_id``: the smallest page_id whose payload is equal (own id if under ``least`` bytes)."""
    raw = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    keyed = pages.withColumns({"digest_": F.sha1(raw), "size_": F.octet_length(raw)})
    first = stage(keyed.filter(F.col("size_") >= least).groupBy("digest_").agg(F.min("page_id").alias("first_id"), F.count("*").alias("n_")).filter("n_ > 1").drop("n_"), "warc-owners")
    joined = keyed.join(first, "digest_", "left")
    return joined.select("page_id", "url", "html", F.coalesce(F.when(F.col("size_") >= least, F.col("first_id")), F.col("page_id")).alias("first_id"))


_CAPTURE = pa.schema([("key", pa.string()), ("page_id", pa.int64()), ("file", pa.string()), ("start", pa.int64()), ("length", pa.int64())])
_CAPTURE_DDL = "key string, page_id long, file string, start long, length long"


def write_archives(pages: DataFrame, least: int = 0) -> tuple[DataFrame, str]:
    """Writes a record per page; returns the captures (key of the index, page_id, file, start, length) and the folder.

    Null html is an empty payload, a null url becomes about:blank, a null page_id is a record of its own.  Of equal
    payloads of ``least`` bytes or more that with the smallest page_id is the response (all rows that repeat that id),
    the others revisit it.  A task's file has a fresh name, and only files of tasks that ended are in the captures, so
    a task that is lost and run again leaves nothing that is read.
    """
    folder = fresh_path(pages.sparkSession, "warc")
    rows = clean_columns(pages, "page_id", "url", "html")
    rows = owners(rows.withColumn("page_id", rows["page_id"].cast("long")), least)

    def run(batches: Iterator[pa.RecordBatch]):
        fs, top = open_store(folder)
        name, sink, at = f"{uuid.uuid4().hex}.warc.gz", None, 0
        for batch in batches:
            made = []
            for page_id, url, html, first in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                if sink is None:
                    fs.create_dir(top, recursive=True)
                    sink = fs.open_output_stream(f"{top}/{name}", compression=None)
                payload = (html or "").encode()
                record = gzip.compress(make_record(page_id, url, payload, block_digest(payload), None if first == page_id else first), 6, mtime=0)
                sink.write(record)
                made.append((sort_key(url_key(url), page_id), page_id, name, at, len(record)))
                at += len(record)
            if made:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*made, strict=True), _CAPTURE, strict=True)], schema=_CAPTURE)
        if sink is not None:
            sink.close()

    return stage(rows.mapInArrow(run, _CAPTURE_DDL), "warc-captures"), folder


_BLOCK = pa.schema([("first_key", pa.string()), ("last_key", pa.string()), ("part", pa.string()), ("start", pa.int64()), ("length", pa.int64())])


def sort_key(key: str, page_id) -> str:
    """Order of index lines: URL key, then page id as a fixed-width number (null first)."""
    return f"{key} {'' if page_id is None else format(page_id + (1 << 63), '020d')}"


def build_index(captures: DataFrame, folder: str, block_lines: int | None = None) -> DataFrame:
    """Writes the sorted lines as gzip blocks and returns the sparse directory: one row per block, in order of its keys.

    Lines are range-partitioned by key and page id, so an address with very many captures spreads over parts.  Keys of
    the directory are cut to ``FIRST_CHARS`` characters, which keeps their order; with ``MAX_BLOCKS`` that bounds it.
    """
    block_lines = block_lines or max(BLOCK_LINES, -(-captures.count() // MAX_BLOCKS))
    order = ["key", "file", "start"]
    lines = captures.repartitionByRange(*order).sortWithinPartitions(*order).select("key", "page_id", "file", "start", "length")

    def run(batches: Iterator[pa.RecordBatch]):
        fs, top = open_store(folder)
        name, sink, at, held = f"{uuid.uuid4().hex}.cdx.gz", None, 0, []
        done: list[tuple] = []

        def flush():
            nonlocal sink, at, held
            if sink is None:
                sink = fs.open_output_stream(f"{top}/{name}", compression=None)
            block = gzip.compress("".join(x[1] for x in held).encode(), 6, mtime=0)
            sink.write(block)
            done.append((held[0][0][:FIRST_CHARS], held[-1][0][:FIRST_CHARS], name, at, len(block)))
            at += len(block)
            held = []

        for batch in batches:
            for key, page_id, file, start, length in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
                held.append((key, json.dumps([key, page_id, file, start, length], ensure_ascii=False) + "\n"))
                if len(held) >= block_lines:
                    flush()
        if held:
            flush()
        if sink is not None:
            sink.close()
        if done:
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*done, strict=True), _BLOCK, strict=True)], schema=_BLOCK)

    return stage(lines.mapInArrow(run, "first_key string, last_key string, part string, start long, length long"), "warc-directory")


class IndexReader:
    """Lookups in the parts of an index: binary search in the directory, then one range read per block."""

    def __init__(self, folder: str, directory: list[tuple]):
        self.fs, self.top = open_store(folder)
        self.directory = sorted(directory)
        self.firsts = [d[0] for d in self.directory]
        self.files: dict[str, object] = {}
        self.block: tuple[int, list] = (-1, [])

    def _read(self, file: str, start: int, length: int) -> bytes:
        if file not in self.files:
            if len(self.files) > 64:
                self.files.pop(next(iter(self.files))).close()
            self.files[file] = self.fs.open_input_file(f"{self.top}/{file}")
        data = self.files[file].read_at(length, start)
        return zlib.decompress(data, wbits=31)

    def lines(self, i: int) -> list:
        if self.block[0] != i:
            _, _, part, start, length = self.directory[i]
            self.block = (i, [json.loads(x) for x in self._read(part, start, length).decode().split("\n") if x])
        return self.block[1]

    def find(self, low: str, high: str) -> Iterator[list]:
        """Index lines with low <= key <= high: the last block that begins before ``low``, and those that go on from it."""
        i = max(0, bisect.bisect_left(self.firsts, low[:FIRST_CHARS]) - 1)
        while i < len(self.directory) and self.firsts[i] <= high[:FIRST_CHARS]:
            lines = self.lines(i)
            k = bisect.bisect_left(lines, low, key=lambda x: x[0])
            while k < len(lines) and lines[k][0] <= high:
                yield lines[k]
                k += 1
            i += 1

    def record(self, line: list) -> dict:
        return read_record(self._read(line[2], line[3], line[4]))


def lookup(directory: DataFrame, folder: str, url: str) -> Iterator[dict]:
    """Records of one address.  The directory is searched where it lies; the driver gets the blocks that can match."""
    key = url_key(url)
    low, high = key + " ", key + " ~"
    blocks = directory.filter((F.col("first_key") <= high[:FIRST_CHARS]) & (F.col("last_key") >= low[:FIRST_CHARS])).collect()
    reader = IndexReader(folder, [tuple(b) for b in blocks])
    for line in reader.find(low, high):
        yield reader.record(line)


_FOUND = pa.schema([("page_id", pa.int64()), ("payload_bytes", pa.int64()), ("payload_digest", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64())])


def read_archives(pages: DataFrame, directory: DataFrame, folder: str) -> DataFrame:
    """Every page looked up in the index and read back: page_id, payload_bytes, payload_digest, record_type, refers_to.

    ``pages`` has (page_id, url).  Each distinct address and id is searched for, first in the directory, then in a block,
    and the records found are read by their byte ranges; lookups go in order of their keys, so a task reads few blocks.
    A response's digest and size are taken from its bytes and must agree with its heads.  A revisit has no bytes: the
    record that it refers to is joined to it, and its digest must be the one that was computed there.  A page that the
    index doesn't give is an error.
    """
    spark = pages.sparkSession
    # at most MAX_BLOCKS rows of bounded size and one more for each part
    given = spark.sparkContext.broadcast([tuple(b) for b in directory.collect()])

    @F.pandas_udf("string")
    def key_of(url: pd.Series, page_id: pd.Series) -> pd.Series:
        return pd.Series([sort_key(url_key(u), None if n is None else int(n)) for u, n in zip(url, page_id, strict=True)])

    wanted = pages.groupBy("page_id", "url").agg(F.count("*").alias("n"))
    wanted = stage(wanted.withColumn("key", key_of("url", F.col("page_id").cast("string"))).groupBy("key").agg(F.sum("n").alias("n")), "warc-wanted")
    parts = max(1, -(-(wanted.agg(F.sum("n")).first()[0] or 0) // LOOKUPS))
    wanted = wanted.repartitionByRange(parts, "key").sortWithinPartitions("key").select("key", "n")

    def run(batches: Iterable[pa.RecordBatch]):
        reader = IndexReader(folder, given.value)
        for batch in batches:
            made = []
            for key, n in zip(*(batch.column(k).to_pylist() for k in range(2)), strict=True):
                before = n
                for line in reader.find(key, key):
                    r = reader.record(line)
                    digest, size = r["warc-payload-digest"].removeprefix("sha1:"), int(r["http"]["content-length"])
                    if r["warc-type"] == RESPONSE and (block_digest(r["payload"]) != digest or len(r["payload"]) != size):
                        raise ValueError(f"record {r['warc-record-id']} is damaged")
                    made.append((_id(r["warc-record-id"]), size, digest, r["warc-type"], _id(r.get("warc-refers-to"))))
                    n -= 1
                    if len(made) >= 5000:
                        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*made, strict=True), _FOUND, strict=True)], schema=_FOUND)
                        made = []
                if n:
                    raise ValueError(f"{before} captures of {key} were written, {before - n} are found")
            if made:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*made, strict=True), _FOUND, strict=True)], schema=_FOUND)

    found = stage(wanted.mapInArrow(run, "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"), "warc-found")
    given.unpersist()
    responses, revisits = found.filter(F.col("record_type") == RESPONSE), found.filter(F.col("record_type") == REVISIT)
    named = responses.filter("page_id is not null").groupBy(F.col("page_id").alias("refers_to")).agg(F.min("payload_digest").alias("own_digest"), F.min("payload_bytes").alias("own_bytes"))
    joined = revisits.join(stage(named, "warc-responses"), "refers_to", "left")
    agrees = F.col("own_digest").eqNullSafe(F.col("payload_digest")) & F.col("own_bytes").eqNullSafe(F.col("payload_bytes"))
    checked = F.when(agrees, F.col("own_digest")).otherwise(F.raise_error(F.concat(F.lit("a revisit without its response: page "), F.coalesce(F.col("page_id").cast("string"), F.lit("null")))))
    resolved = joined.select("page_id", F.col("own_bytes").alias("payload_bytes"), checked.alias("payload_digest"), "record_type", "refers_to")
    return responses.unionByName(resolved)


def archive_pages(pages: DataFrame, least: int = 0) -> DataFrame:
    """Writes all pages as records, indexes them, and looks each page up in the index."""
    captures, folder = write_archives(pages, least)
    rows = clean_columns(pages, "page_id", "url")
    return read_archives(rows.select(rows["page_id"].cast("long").alias("page_id"), "url"), build_index(captures, folder), folder)
