"""Byte-level BPE over whole texts with the tiktoken library and a local rank file.

The pattern's matches are encoded separately, so a text may be cut wherever one match must end and another begin: between
a character that isn't white space and one that is, if no match of the pattern has both in this order.  Whether that holds
is tried on the pattern; with one that fails, texts stay whole.  Long texts are encoded piece by piece, and their digests
are updated piece by piece; memory holds one piece, not a long text's ids.
"""

from __future__ import annotations

import base64
import functools
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .shared import clean_columns
from .words import release, slices

#: Characters in a piece before the next safe boundary is looked for.
PIECE_CHARS = 1 << 16
#: No match crosses from a character that isn't white space to one that is: only a match's first character is a space.
#: Control characters on which pattern engines differ count as neither.
_SAFE = regex.compile(r"(?<=[^\s\x1C-\x1F\x85])(?=[ \t\r\n])")
#: A rank file above this size isn't broadcast.
MAX_RANK_BYTES = 64 << 20


def read_ranks(path: str) -> bytes:
    with open(path, "rb") as f:
        data = f.read(MAX_RANK_BYTES + 1)
    if len(data) > MAX_RANK_BYTES:
        raise ValueError(f"{path} is larger than {MAX_RANK_BYTES} bytes")
    return data


def make_encoding(ranks: bytes, pattern: str):
    import tiktoken

    table = {base64.b64decode(a): int(b) for a, b in (line.split() for line in ranks.splitlines() if line)}
    return tiktoken.Encoding("local_ranks", pat_str=pattern, mergeable_ranks=table, special_tokens={})


#: Characters of each kind that patterns tell apart, on which a pattern is tried.
_PROBES = ("a", "Z", "é", "ß", "中", "ʰ", "7", "²", "٣", "Ⅷ", "'", "'s", "'ll", ".", "-", "_", "/", "\"", "$", "+", "\u0301", "\u200d", "\u00ad", "😀", "\x00", "\x7f", "\ufeff")


@functools.lru_cache(maxsize=16)
def may_cut(pattern: str) -> bool:
    """Whether matches of the pattern end at the places where texts would be cut, tried on all pairs of probes."""
    match = regex.compile(pattern)
    for a in _PROBES:
        for gap in (" ", "\t", "\n", "\r", "\r\n", "  ", " \n"):
            for b in ("", *_PROBES):
                for head in ("", a, " " + a):
                    text = head + a + gap + b
                    if len(head + a) not in {m.end() for m in match.finditer(text)}:
                        return False
    return True


def pieces(text: str, size: int = PIECE_CHARS, cut: bool = True) -> Iterator[str]:
    """The text in order, cut at safe boundaries only; a stretch without one stays whole, as does all of it without ``cut``."""
    at = 0
    while cut and len(text) - at > size:
        found = _SAFE.search(text, at + size)
        if found is None:
            break
        yield text[at : found.start()]
        at = found.start()
    yield text[at:]


class Codec:
    """Encodes and decodes with one rank table; made once per Python worker."""

    _made: dict[int, Codec] = {}

    def __init__(self, ranks: bytes, pattern: str):
        self.encoding = make_encoding(ranks, pattern)
        self.cut = may_cut(pattern)
        top = self.encoding.max_token_value + 1
        self.digits = [b"%d" % i for i in range(top)]
        self.raw = [b""] * top
        for token in self.encoding.token_byte_values():
            self.raw[self.encoding.encode_single_token(token)] = token

    @classmethod
    def of(cls, key: int, ranks: bytes, pattern: str) -> Codec:
        if key not in cls._made:
            cls._made = {key: cls(ranks, pattern)}
        return cls._made[key]

    def encode(self, text: str) -> Iterator[list[int]]:
        for piece in pieces(text, cut=self.cut):
            yield self.encoding.encode_ordinary(piece)

    def decode(self, ids: list[int]) -> bytes:
        raw = self.raw
        return b"".join([raw[i] for i in ids])


def _per_batch(work, out_schema: pa.Schema, ranks, pattern: str):
    """mapInArrow function that calls ``work(codec, row batch)`` on each batch."""

    def run(batches):
        codec = None
        for batch in batches:
            codec = codec or Codec.of(hash((pattern, ranks.value)), ranks.value, pattern)
            yield pa.RecordBatch.from_pydict(work(codec, batch), schema=out_schema)

    return run


def bpe_digests(docs: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every whole text.

    A null or empty text has no tokens.  Rows are independent, so ties and repeated rows give equal rows.  Other
    columns are ignored.
    """
    rows = clean_columns(docs, "doc_id", "text")
    ranks = docs.sparkSession.sparkContext.broadcast(read_ranks(ranks_path))
    id_type = pa.int64() if dict(rows.dtypes)["doc_id"] != "string" else pa.string()
    schema = pa.schema([("doc_id", id_type), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])

    def work(codec: Codec, batch: pa.RecordBatch) -> dict:
        counts, ids_hex, raw_hex = [], [], []
        for value in batch.column(1):
            ids_hash, raw_hash, n = hashlib.sha256(), hashlib.sha256(), 0
            for ids in codec.encode(value.as_py() or ""):
                if ids:
                    ids_hash.update((b" " if n else b"") + b" ".join([codec.digits[i] for i in ids]))
                    raw_hash.update(codec.decode(ids))
                    n += len(ids)
            counts.append(n)
            ids_hex.append(ids_hash.hexdigest())
            raw_hex.append(raw_hash.hexdigest())
        return {"doc_id": batch.column(0), "n_tokens": counts, "ids_sha256": ids_hex, "decoded_sha256": raw_hex}

    kind = "long" if id_type == pa.int64() else "string"
    rows = rows.withColumn("doc_id", rows["doc_id"].cast(kind))
    return rows.mapInArrow(_per_batch(work, schema, ranks, pattern), f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encode_texts(docs: DataFrame, ranks_path: str, pattern: str, text: str = "text", ids: str = "token_ids") -> DataFrame:
    """``docs`` with the ids of each text in a new last column ``ids`` (null or empty text: none).

    All columns are kept, but for one that has the name of the new column, which takes its place.  Repeated rows give
    equal rows, very long texts are encoded piece by piece, an empty table gives an empty result.  The ids are decoded
    again, and a text that doesn't come back to the byte is an error.
    """
    docs = docs if ids == text else docs.drop(ids)
    ranks = docs.sparkSession.sparkContext.broadcast(read_ranks(ranks_path))
    where = docs.columns.index(text)

    def run(batches):
        codec = None
        for batch in batches:
            codec = codec or Codec.of(hash((pattern, ranks.value)), ranks.value, pattern)
            for part in slices(batch, text):
                sizes, parts = [0], []
                for v in part.column(where):
                    own = (v.as_py() or "").encode()
                    ids_ = [np.array(x, np.int32) for x in codec.encode(v.as_py() or "")]
                    if b"".join(codec.decode(x.tolist()) for x in ids_) != own:
                        raise ValueError("ids that don't decode to their text")
                    sizes.append(sizes[-1] + sum(map(len, ids_)))
                    parts += ids_
                made = pa.ListArray.from_arrays(np.array(sizes, np.int32), np.concatenate(parts))
                yield pa.RecordBatch.from_arrays([*part.columns, made], names=[*batch.schema.names, ids])
        release()

    from pyspark.sql import types as T

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField(ids, T.ArrayType(T.IntegerType(), False))]))


def decode_ids(rows: DataFrame, ranks_path: str, pattern: str, ids: str = "token_ids", raw: str = "raw") -> DataFrame:
    """``rows`` with the bytes of each id list in a new last column ``raw`` (binary; null list: empty).

    Decoding is of bytes: a list that ends within a character gives those bytes, not a replacement character.  An id that
    the ranks lack, or that is null, is an error.  A column that has the name of the new one gives way to it.
    """
    rows = rows if raw == ids else rows.drop(raw)
    ranks = rows.sparkSession.sparkContext.broadcast(read_ranks(ranks_path))
    where = rows.columns.index(ids)

    def run(batches):
        codec = None
        for batch in batches:
            codec = codec or Codec.of(hash((pattern, ranks.value)), ranks.value, pattern)
            made = pa.array([codec.decode(v.as_py() or []) for v in batch.column(where)], pa.binary())
            yield pa.RecordBatch.from_arrays([*batch.columns, made], names=[*batch.schema.names, raw])

    from pyspark.sql import types as T

    return rows.mapInArrow(run, T.StructType([*rows.schema.fields, T.StructField(raw, T.BinaryType())]))
