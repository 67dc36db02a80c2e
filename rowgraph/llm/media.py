"""Media columns: interleaved sequences of text and media references, resolved by digest.

A page's HTML becomes an ordered array of structs (pos, kind, text, ref, caption).  Media live in files of a store, one
stored form after the other, with a table of where each digest's form lies; a join on the digest resolves references to
places, and the payload is read from its place.  Positions and captions stay with the reference, so they can't shift, and
no payload is shuffled.
"""

from __future__ import annotations

import hashlib
import struct
import uuid
import zlib
from collections.abc import Iterator
from html import escape
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import clean_columns, discard, fresh_path, stage
from .warc import open_store

WIDTH = 64
#: Bytes of a text in one picture; longer texts are several.
TILE = 1 << 20
#: Scheme of references to the store.
SCHEME = "media:sha256/"
_MAGIC = b"\x89PNG\r\n\x1a\n"
SEQUENCE = "array<struct<pos:int,kind:string,text:string,ref:string,caption:string>>"


def pad(data: bytes) -> bytes:
    """The bytes with zeros up to a positive multiple of ``WIDTH``."""
    return data + b"\0" * (-len(data) % WIDTH if data else WIDTH)


def _chunk(kind: bytes, body: bytes) -> bytes:
    return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(kind + body))


def to_png(payload: bytes, n_bytes: int | None = None) -> bytes:
    """A greyscale picture of 8-bit samples, 64 to a row, without loss; ``n_bytes`` is kept in a text chunk."""
    rows = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH)
    lines = np.zeros((len(rows), WIDTH + 1), np.uint8)
    lines[:, 1:] = rows
    head = struct.pack(">IIBBBBB", WIDTH, len(rows), 8, 0, 0, 0, 0)
    note = b"" if n_bytes is None else _chunk(b"tEXt", b"Bytes\0%d" % n_bytes)
    return _MAGIC + _chunk(b"IHDR", head) + note + _chunk(b"IDAT", zlib.compress(lines, 1)) + _chunk(b"IEND", b"")


def from_png(media: bytes) -> tuple[bytes, int | None]:
    """The samples of such a picture and the size that it notes; raises ValueError where it is damaged."""
    if media[:8] != _MAGIC:
        raise ValueError("not a picture")
    at, body, height, noted = 8, b"", -1, None
    while at < len(media):
        (n,) = struct.unpack_from(">I", media, at)
        kind, part = media[at + 4 : at + 8], media[at + 8 : at + 8 + n]
        if zlib.crc32(kind + part) != struct.unpack_from(">I", media, at + 8 + n)[0]:
            raise ValueError("a damaged chunk")
        if kind == b"IHDR":
            height = struct.unpack_from(">I", part, 4)[0]
        elif kind == b"IDAT":
            body += part
        elif kind == b"tEXt" and part.startswith(b"Bytes\0"):
            noted = int(part[6:])
        at += 12 + n
    lines = np.frombuffer(zlib.decompress(body), np.uint8).reshape(height, WIDTH + 1)
    if lines[:, 0].any():
        raise ValueError("filtered rows")
    return lines[:, 1:].tobytes(), noted


class Features:
    """Rows, mean, spread, share of empty samples and mean step between neighbours of samples that come in pieces."""

    def __init__(self):
        self.n = self.total = self.squares = self.zeros = self.steps = 0
        self.last: int | None = None

    def add(self, samples: bytes) -> None:
        x = np.frombuffer(samples, np.uint8)
        self.n += len(x)
        self.total += int(x.sum(dtype=np.int64))
        self.squares += int((x.astype(np.uint16) ** 2).sum(dtype=np.int64))
        self.zeros += int((x == 0).sum())
        self.steps += int(np.abs(np.diff(x.astype(np.int16))).sum(dtype=np.int64))
        if len(x):
            self.steps += 0 if self.last is None else abs(int(x[0]) - self.last)
            self.last = int(x[-1])

    def __str__(self) -> str:
        n = max(1, self.n)
        spread = max(0.0, self.squares / n - (self.total / n) ** 2) ** 0.5
        return f"rows={self.n // WIDTH};mean={self.total / n:.4f};std={spread:.4f};zeros={self.zeros / n:.4f};step={self.steps / max(1, n - 1):.4f}"


# ------------------------------------------------------------------------------------------------ sequences

_BLOCKS = frozenset("address article aside blockquote body br dd div dl dt figure footer form h1 h2 h3 h4 h5 h6 header hr html li main nav ol p pre section table td th tr ul title".split())
_HIDDEN = frozenset(("script", "style", "template", "noscript"))
_MEDIA = frozenset(("img", "video", "audio", "source", "embed"))


class _Interleaver(HTMLParser):
    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.out: list[dict] = []
        self.words: list[str] = []
        self.hidden = 0
        self.figures: list[list[int]] = []
        self.caption: list[str] | None = None

    def flush(self) -> None:
        text = " ".join("".join(self.words).split())
        self.words = []
        if text:
            self.out.append({"pos": len(self.out), "kind": "text", "text": text, "ref": None, "caption": None})

    def handle_starttag(self, tag, attrs):
        if tag in _HIDDEN:
            self.hidden += 1
        elif tag in _MEDIA:
            at = dict(attrs)
            if at.get("src"):
                self.flush()
                if self.figures:
                    self.figures[-1].append(len(self.out))
                self.out.append({"pos": len(self.out), "kind": "media", "text": None, "ref": at["src"], "caption": at.get("alt") or at.get("title")})
        elif tag == "figcaption":
            self.flush()
            self.caption = []
        elif tag in _BLOCKS:
            self.flush()
            if tag == "figure":
                self.figures.append([])

    def handle_endtag(self, tag):
        if tag in _HIDDEN:
            self.hidden = max(0, self.hidden - 1)
        elif tag == "figcaption" and self.caption is not None:
            said, self.caption = " ".join("".join(self.caption).split()), None
            for i in self.figures[-1] if self.figures else []:
                self.out[i]["caption"] = said or self.out[i]["caption"]
        elif tag in _BLOCKS:
            self.flush()
            if tag == "figure" and self.figures:
                self.figures.pop()

    def handle_data(self, data):
        if not self.hidden:
            (self.words if self.caption is None else self.caption).append(data)


def interleave(html: str | None) -> list[dict]:
    """Ordered text and media structs of a page (null or empty: none).  A figure's caption goes to its media."""
    parser = _Interleaver()
    parser.feed(html or "")
    parser.close()
    parser.flush()
    return parser.out


def sequences(pages: DataFrame, html: str = "html", out: str = "sequence") -> DataFrame:
    """``pages`` with the parsed sequence in a new last column; all other columns are kept, one of that name is replaced.

    Null and empty HTML give an empty array; a page without tags is one text.  Repeated rows give equal rows, an empty
    table an empty result.
    """
    if out in pages.columns and out != html:
        pages = pages.drop(out)
    where = pages.columns.index(html)
    kind = pa.list_(pa.struct([("pos", pa.int32()), ("kind", pa.string()), ("text", pa.string()), ("ref", pa.string()), ("caption", pa.string())]))

    def run(batches):
        for batch in batches:
            made = pa.array([interleave(x) for x in batch.column(where).to_pylist()], kind)
            yield pa.RecordBatch.from_arrays([*(c for k, c in enumerate(batch.columns) if kept[k]), made], names=[*(n for k, n in enumerate(batch.schema.names) if kept[k]), out])

    from pyspark.sql import types as T

    kept = [c != out for c in pages.columns]
    field = T.StructField(out, T.ArrayType(T.StructType([T.StructField("pos", T.IntegerType()), *(T.StructField(n, T.StringType()) for n in ("kind", "text", "ref", "caption"))])))
    return pages.mapInArrow(run, T.StructType([*(f for f in pages.schema.fields if f.name != out), field]))


def resolve(seqs: DataFrame, store: DataFrame, keys: list[str], out: str = "sequence") -> DataFrame:
    """One row per media reference: ``keys``, pos, ref, caption and the columns of ``store`` (left join on digest).

    References that the store lacks, or that name no digest, keep null columns.  Only references travel, not the texts
    between them.  A page that refers twice to one payload has two rows, a null or empty sequence none.
    """
    items = seqs.select(*keys, F.explode(out).alias("item_")).filter(F.col("item_.kind") == "media")
    refs = items.select(*keys, F.col("item_.pos").alias("pos"), F.col("item_.ref").alias("ref"), F.col("item_.caption").alias("caption"))
    refs = refs.withColumn("digest_", F.when(F.col("ref").startswith(SCHEME), F.substring(F.col("ref"), len(SCHEME) + 1, 64)))
    return refs.join(store.withColumnRenamed("digest", "digest_"), "digest_", "left").drop("digest_")


# ------------------------------------------------------------------------------------------------ the store

_STORED = pa.schema([("row", pa.int64()), ("doc_id", pa.int64()), ("html", pa.string()), ("digests", pa.list_(pa.string())), ("starts", pa.list_(pa.int64())), ("lengths", pa.list_(pa.int64())), ("file", pa.string())])
#: Digests that a task remembers, so that it doesn't store the same payload twice.
REMEMBERED = 100_000


def tiles(raw: bytes, tile: int = TILE) -> list[bytes]:
    """A text's bytes in pieces of ``tile``, a multiple of ``WIDTH``; an empty text is one empty piece."""
    return [raw[k : k + tile] for k in range(0, len(raw), tile)] or [b""]


def page_of(doc_id, parts: list[tuple[str, bytes]]) -> str:
    """A page of (digest, bytes): a title, and by turns the words that a piece begins with and its picture with caption."""
    out = [f"<article><h1>Document {doc_id}</h1>"]
    for k, (digest, piece) in enumerate(parts, 1):
        begins = escape(" ".join(piece[:48].decode(errors="ignore").split()), quote=False)
        out.append(f'<p>Part {k}: {begins}</p><figure><img src="{SCHEME}{digest}" alt="text"><figcaption>part {k} of {len(parts)}</figcaption></figure>')
    return "".join(out) + "<p>End.</p></article>"


def store_texts(docs: DataFrame, tile: int = TILE) -> tuple[DataFrame, str]:
    """Each text as a page with its pictures, in a stored table (row, doc_id, html, digests, starts, lengths, file), and the
    folder of the store's files.

    Pages refer to pictures by the digest of their unpadded bytes.  A task writes one file with a fresh name, and only
    files of tasks that ended are in the table, so a task that is lost and run again leaves nothing that is read.  A
    digest that the task has just stored has no place of its own (start null).
    """
    folder = fresh_path(docs.sparkSession, "media")
    rows = clean_columns(docs, "doc_id", "text")
    rows = rows.select(rows["doc_id"].cast("long").alias("doc_id"), "text")

    def batch_of(made: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*made, strict=True), _STORED, strict=True)], schema=_STORED)

    def run(batches):
        fs, top = open_store(folder)
        name, sink, at, row = f"{uuid.uuid4().hex}.media", None, 0, TaskContext.get().partitionId() << 40
        seen: set[str] = set()
        for batch in batches:
            made = []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                parts, starts, lengths = [], [], []
                for piece in tiles((text.as_py() or "").encode(), tile):
                    digest = hashlib.sha256(piece).hexdigest()
                    parts.append((digest, piece))
                    media = None if digest in seen else to_png(pad(piece), len(piece))
                    starts.append(None if media is None else at)
                    lengths.append(None if media is None else len(media))
                    if media is not None:
                        if sink is None:
                            fs.create_dir(top, recursive=True)
                            sink = fs.open_output_stream(f"{top}/{name}", compression=None)
                        sink.write(media)
                        at += len(media)
                    if len(seen) >= REMEMBERED:
                        seen.clear()
                    seen.add(digest)
                made.append((row, doc_id, page_of(doc_id, parts), [d for d, _ in parts], starts, lengths, name))
                row += 1
                if len(made) >= 500:
                    yield batch_of(made)
                    made = []
            if made:
                yield batch_of(made)
        if sink is not None:
            sink.close()

    ddl = "row long, doc_id long, html string, digests array<string>, starts array<long>, lengths array<long>, file string"
    return stage(rows.mapInArrow(run, ddl), "media-pages"), folder


def places(stored: DataFrame) -> DataFrame:
    """(digest, place): one place (file, start, length) of each digest."""
    one = stored.select("file", F.explode(F.arrays_zip("digests", "starts", "lengths")).alias("x")).filter("x.starts is not null")
    return one.groupBy(F.col("x.digests").alias("digest")).agg(F.min(F.struct("file", F.col("x.starts").alias("start"), F.col("x.lengths").alias("length"))).alias("place"))


_READ = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string())])
_READ_DDL = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def read_media(refs: DataFrame, folder: str) -> DataFrame:
    """Each document's pictures read from their places, in order of their positions: sizes, checksums and features.

    ``refs`` has (row, doc_id, pos, caption, place) with all references of a row together and in order.  A reference
    without a place, a damaged picture, and captions that don't number the pictures in their order are errors.
    """

    def run(batches: Iterator[pa.RecordBatch]):
        fs, top = open_store(folder)
        files: dict[str, object] = {}
        row, parts, doc, last, made = None, [], None, (None, None), []

        def read(place: dict) -> bytes:
            name = place["file"]
            if name not in files:
                if len(files) > 64:
                    files.pop(next(iter(files))).close()
                files[name] = fs.open_input_file(f"{top}/{name}")
            return files[name].read_at(place["length"], place["start"])

        def figures(doc_id, parts: list[tuple]) -> tuple:
            payload_hash, media_hash, features, tail = hashlib.sha256(), hashlib.sha256(), Features(), b""
            n_bytes = payload_bytes = media_bytes = 0
            for k, (caption, place) in enumerate(parts, 1):
                if place is None or caption != f"part {k} of {len(parts)}":
                    raise ValueError(f"document {doc_id}: picture {k} of {len(parts)} is {caption} at {place}")
                media = read(place)
                payload, noted = from_png(media)
                payload_hash.update(payload)
                media_hash.update(media)
                features.add(payload)
                n_bytes, payload_bytes, media_bytes, tail = n_bytes + noted, payload_bytes + len(payload), media_bytes + len(media), payload[-WIDTH:]
            return n_bytes, payload_bytes, payload_hash.hexdigest(), zlib.crc32(tail), media_bytes, media_hash.hexdigest(), str(features)

        def done() -> None:
            nonlocal last
            # rows with the same pictures lie side by side and are read once
            key = str(parts)
            if last[0] != key:
                last = (key, figures(doc, parts))
            made.append((doc, *last[1]))

        def batch_of() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*made, strict=True), _READ, strict=True)], schema=_READ)

        for batch in batches:
            for own, doc_id, caption, place in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                if own != row and row is not None:
                    done()
                    parts = []
                    if len(made) >= 2000:
                        yield batch_of()
                        made = []
                row, doc = own, doc_id
                parts.append((caption, place))
        if row is not None:
            done()
        if made:
            yield batch_of()

    return refs.select("row", "doc_id", "caption", "place").mapInArrow(run, _READ_DDL)


#: Rows that a task reads back on average.
READ_ROWS = 8000


def text_media(docs: DataFrame, tile: int = TILE) -> DataFrame:
    """doc_id, n_bytes and the stored form's figures for every whole text (null: empty).

    Texts longer than ``tile`` bytes are several pictures; media_bytes and media_sha256 are those of their stored forms
    one after the other.  Repeated rows give equal rows.  What is shuffled are references and places, not payloads; both
    sides of the digest join are stored tables, so a digest that a third of all rows share can be split.
    """
    stored, folder = store_texts(docs, tile)
    store = stage(places(stored), "media-places")
    # the sequences themselves are not kept here, so only their references are
    seqs = sequences(stored.select("row", "doc_id", "html")).select("row", "doc_id", "sequence")
    refs = stage(resolve(seqs, store, ["row", "doc_id"]), "media-refs")
    parts = max(1, -(-refs.count() // READ_ROWS))
    # documents meet their payloads near each other: dealt by the place of the first picture, then in order
    first = refs.groupBy("row").agg(F.min_by("place", "pos").alias("first"))
    placed = refs.join(stage(first, "media-first"), "row")
    spread = placed.repartitionByRange(parts, "first", "row").sortWithinPartitions("first", "row", "pos")
    discard(stored)
    return read_media(spread, folder)
