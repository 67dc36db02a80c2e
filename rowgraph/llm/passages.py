"""Removing passages that occur elsewhere, by suffix automata of reference shards.

A window is ``WINDOW`` consecutive words.  Of equal windows the smallest hash of their k-word pieces, the anchor, is
equal and stands in the same place, so

1. anchors of all windows are counted exactly, and each text gets the list of its anchors that stand in two places or more;
2. windows of these are candidates; a run of them with one anchor is a passage;
3. passages are sharded by anchor, so equal windows meet in a shard (those of very frequent anchors window by window);
4. each shard's passages go into a suffix automaton with counts, and the same passages are streamed through it: a window
   is repeated where the matching statistic reaches the whole window in a state that occurs twice or more;
5. the spans of a passage go to all its places by a join, and from there to the documents.

Nothing is broadcast: all automata together grow with the data, so each is built where its shard is.  A given set of
references of bounded size is another case (``cut_references``): there the automata are broadcast, shard by shard under a
checked bound, and whole documents are streamed through them.
"""

from __future__ import annotations

import hashlib
import marshal
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .automaton import SuffixAutomaton
from .keyset import in_table, key_table
from .shared import clean_columns, discard, stage
from .words import mix, ngram_hashes, release, slices, text_buffers, word_hashes, word_spans

WINDOW = 35
#: Words of an anchor, by which passages are cut and sharded.
ANCHOR = 12
#: Words of passages in one shard on average, and places of an anchor beyond which its windows are sharded one by one.
SHARD_WORDS, HOT_PLACES = 50_000, 4096
#: Distinct passages that a task holds before it sends them off.
HELD = 40_000
#: Given references: words in a shard's automaton, shards that are broadcast together, and most words of all of them.
REFERENCE_SHARD, REFERENCE_ROUND, MAX_REFERENCE_WORDS = 100_000, 8, 8_000_000

_U = np.uint64


def anchors(words: np.ndarray, size: int = ANCHOR) -> tuple[np.ndarray, np.ndarray]:
    """(hash, place) of the anchor of each window of one text: the smallest piece, of equal ones the last."""
    pieces = ngram_hashes(words, size, salt=3)
    span = WINDOW - size + 1
    n = len(pieces) - span + 1
    if n <= 0:
        return np.zeros(0, _U), np.zeros(0, np.int64)
    # smallest over 2^k neighbours, then over two overlapping stretches
    best, at, width = pieces, np.arange(len(pieces)), 1
    while width * 2 <= span:
        right = best[width:] <= best[:-width]
        at = np.where(right, at[width:], at[:-width])
        best = np.where(right, best[width:], best[:-width])
        width *= 2
    a, b = slice(0, n), slice(span - width, span - width + n)
    right = best[b] <= best[a]
    return np.where(right, best[b], best[a]), np.where(right, at[b], at[a])


def _texts(column: pa.Array) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Row, bytes, starts, ends and hashes of the words of each text with a window."""
    data, offsets = text_buffers(column)
    starts, ends, first = word_spans(data, offsets)
    hashes = word_hashes(data, starts, ends)
    bounds = first.tolist()
    for row in range(len(bounds) - 1):
        lo, hi = bounds[row], bounds[row + 1]
        if hi - lo >= WINDOW:
            yield row, data, starts[lo:hi], ends[lo:hi], hashes[lo:hi]


def _rows_of(schema: pa.Schema, made: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*made, strict=True), schema, strict=True)], schema=schema)


_MARK = pa.schema([("anchor", pa.int64()), ("text_id", pa.int64()), ("n", pa.int32())])


def anchor_places(rows: DataFrame) -> DataFrame:
    """(anchor, text_id, n): the distinct anchors of each row (text_id, text) and in how many of its places each stands."""

    def run(batches: Iterator[pa.RecordBatch]):
        for whole in batches:
            for batch in slices(whole, "text"):
                ids, found, sizes, own = batch.column(0).to_numpy(), [], [], []
                for row, _, _, _, hashes in _texts(batch.column(1)):
                    best, at = anchors(hashes)
                    new = np.ones(len(at), bool)
                    new[1:] = at[1:] != at[:-1]
                    marks, n = np.unique(best[new], return_counts=True)
                    found.append(marks)
                    sizes.append(n)
                    own.append(np.full(len(marks), ids[row]))
                if found:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(found).view(np.int64)), pa.array(np.concatenate(own)), pa.array(np.concatenate(sizes).astype(np.int32))], schema=_MARK)
        release()

    return rows.mapInArrow(run, "anchor long, text_id long, n int")


def repeated_anchors(rows: DataFrame) -> tuple[DataFrame, int]:
    """(text_id, repeated, frequent) of texts that have anchors with two places or more, and the number of such places.

    ``rows`` has (text_id, text).  Both sides of the join are stored tables, so an anchor that very many texts share can
    be split; the lists are put together from distinct values, so rows that repeat a text add nothing.
    """
    marks = stage(anchor_places(rows), "passage-anchors")
    counts = marks.groupBy("anchor").agg(F.sum("n").alias("places")).filter("places > 1")
    counts = stage(counts, "passage-counts")
    places = counts.agg(F.sum("places")).first()[0] or 0
    hits = marks.join(counts.hint("merge"), "anchor")
    frequent = F.when(F.col("places") > HOT_PLACES, F.col("anchor"))
    found = stage(hits.groupBy("text_id").agg(F.collect_set("anchor").alias("repeated"), F.collect_set(frequent).alias("frequent")), "passage-hits")
    discard(marks, counts)
    return found, places


def _runs(flags: np.ndarray) -> list[tuple[int, int]]:
    """Bounds of the stretches of true values."""
    edges = np.flatnonzero(np.diff(np.concatenate(([False], flags, [False])).astype(np.int8)))
    return list(zip(edges[::2].tolist(), edges[1::2].tolist(), strict=True))


_FOUND = pa.schema([("shard", pa.int64()), ("words", pa.binary()), ("passage", pa.binary()), ("text_key", pa.binary()), ("first", pa.int32())])


def passages(rows: DataFrame, n_shards: int) -> DataFrame:
    """Candidate passages of rows (text_key, text, repeated, frequent), as rows of two kinds.

    With ``shard`` and ``words``: per task and shard, packed (passage, words, n), equal passages of a task put together.
    With ``passage``, ``text_key`` and ``first``: a place of a passage, the latter named by a digest of its words.
    """

    def send(found: dict[bytes, list], places: list[tuple]) -> Iterator[pa.RecordBatch]:
        squeeze = zstandard.ZstdCompressor(level=3).compress
        if found:
            words = list(found)
            shards = mix(np.array([v[1] for v in found.values()], np.int64).view(_U)) % _U(n_shards)
            order = np.argsort(shards, kind="stable")
            cuts = [0, *(np.flatnonzero(np.diff(shards[order])) + 1).tolist(), len(order)]
            made = []
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                part = [(found[words[i]][0], words[i], found[words[i]][2]) for i in order[a:b].tolist()]
                made.append((int(shards[order[a]]), squeeze(marshal.dumps(part)), None, None, None))
            yield _rows_of(_FOUND, made)
        if places:
            yield _rows_of(_FOUND, [(None, None, *x) for x in places])

    def run(batches: Iterator[pa.RecordBatch]):
        for whole in batches:
            found: dict[bytes, list] = {}
            places: list[tuple] = []
            for batch in slices(whole, "text"):
                keys = batch.column(0)
                known, hot = ((lists.values.to_numpy().view(_U), lists.offsets.to_pylist()) for lists in (batch.column(2), batch.column(3)))
                for row, data, starts, ends, hashes in _texts(batch.column(1)):
                    best, at = anchors(hashes)
                    flags = np.isin(best, known[0][known[1][row] : known[1][row + 1]])
                    if not flags.any():
                        continue
                    single = np.isin(best, hot[0][hot[1][row] : hot[1][row + 1]])
                    # a passage ends where windows stop being candidates, or the anchor changes, or each is on its own
                    new = np.ones(len(at), bool)
                    new[1:] = (at[1:] != at[:-1]) | ~flags[:-1] | single[1:]
                    lows = np.flatnonzero(new & flags)
                    stop = np.ones(len(at), bool)
                    stop[:-1] = new[1:] | ~flags[1:]
                    highs = np.flatnonzero(stop & flags)
                    text_key = keys[row].as_py()
                    # the words joined by single spaces, and where each begins
                    joined = b" ".join(data[starts[0] : ends[-1]].tobytes().split())
                    begins = np.concatenate(([0], np.cumsum(ends - starts + 1)))
                    marks = np.where(single[lows], 0, best[lows].view(np.int64))
                    for lo, b, e, mark in zip(lows.tolist(), begins[lows].tolist(), begins[highs + WINDOW].tolist(), marks.tolist(), strict=True):
                        words = joined[b : e - 1]
                        held = found.get(words)
                        if held is None:
                            name = hashlib.blake2b(words, digest_size=16).digest()
                            held = found[words] = [name, mark or int.from_bytes(name[:8], "little", signed=True), 0]
                        held[2] += 1
                        places.append((held[0], text_key, lo))
                    if len(found) >= HELD or len(places) >= 4 * HELD:
                        yield from send(found, places)
                        found, places = {}, []
            yield from send(found, places)
        release()

    return rows.mapInArrow(run, "shard long, words binary, passage binary, text_key binary, first int")


def matched_spans(held: dict[bytes, tuple[bytes, int]]) -> Iterator[tuple[bytes, list[tuple[int, int]]]]:
    """(passage, spans) of the passages of a shard, ``passage -> (words, n)``, that have repeated windows."""
    automaton, ids, coded = SuffixAutomaton(), {}, []
    for passage, (words, n) in held.items():
        code = [ids.setdefault(w, len(ids)) for w in words.split(b" ")]
        coded.append((passage, code))
        automaton.add(code, n)
    automaton.settle()
    for passage, code in coded:
        seen = np.array([size == WINDOW and n > 1 for size, n in automaton.matches(code, WINDOW)], bool)
        if spans := [(lo, hi + WINDOW - 1) for lo, hi in _runs(seen[WINDOW - 1 :])]:
            yield passage, spans


_DECIDED = pa.schema([("passage", pa.binary()), ("lo", pa.int32()), ("hi", pa.int32())])


def decided_spans(shards: DataFrame) -> DataFrame:
    """Rows (passage, lo, hi): words of a passage covered by windows that occur twice or more.

    ``shards`` has (shard, words), sorted by shard.  An automaton is dropped with its shard.
    """

    def rows_of(held: dict) -> Iterator[pa.RecordBatch]:
        made = [(passage, lo, hi) for passage, spans in matched_spans(held) for lo, hi in spans]
        if made:
            yield _rows_of(_DECIDED, made)

    def run(batches: Iterator[pa.RecordBatch]):
        widen = zstandard.ZstdDecompressor().decompress
        current, held = None, {}
        for batch in batches:
            for shard, blob in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if shard != current:
                    yield from rows_of(held)
                    current, held = shard, {}
                for passage, words, n in marshal.loads(widen(blob.as_py())):
                    held[passage] = (words, held[passage][1] + n if passage in held else n)
        yield from rows_of(held)
        held = {}
        release()

    return shards.mapInArrow(run, "passage binary, lo int, hi int")


def repeated_windows(rows: DataFrame) -> DataFrame:
    """Rows (text_key, spans): for each text with repeated windows, (start, end) of the words they cover, in order.

    ``rows`` has (text_key, text); equal texts have equal keys and are different places.
    """
    named = rows.select(F.xxhash64("text_key").alias("text_id"), "text_key", "text")
    hits, n_places = repeated_anchors(named.select("text_id", "text"))
    n_shards = max(1, -(-n_places * (WINDOW + 12) // SHARD_WORDS))
    # a text id may stand for two texts, which adds candidates only
    near = in_table(key_table(hits.select("text_id")), named, F.col("text_id"), "has_").filter("has_")
    near = near.join(hits.hint("merge"), "text_id").select("text_key", "text", "repeated", "frequent")
    found = stage(passages(near, n_shards), "passage-found")
    discard(hits, shuffles=True)
    shards = found.filter("shard is not null").select("shard", "words")
    decided = stage(decided_spans(shards.repartition("shard").sortWithinPartitions("shard")), "passage-decided")
    placed = found.filter("passage is not null").select("passage", "text_key", "first").join(decided.hint("merge"), "passage")
    span = F.struct((F.col("first") + F.col("lo")).alias("start"), (F.col("first") + F.col("hi")).alias("end"))
    out = stage(placed.groupBy("text_key").agg(_merged(F.collect_set(span)).alias("spans")), "passage-spans")
    discard(found, decided, shuffles=True)
    return out


def _merged(spans):
    """Sorted spans with those that meet or overlap put together."""
    pair = "array<struct<start:int,end:int>>"

    def add(done, s):
        last = F.element_at(done, -1)
        grown = F.concat(F.slice(done, 1, F.size(done) - 1), F.array(F.struct(last.start.alias("start"), F.greatest(last.end, s.end).alias("end")))).cast(pair)
        new = F.concat(done, F.array(s)).cast(pair)
        return F.when(F.size(done) == 0, F.array(s).cast(pair)).when(F.try_element_at(done, F.lit(-1)).end >= s.start, grown).otherwise(new)

    return F.aggregate(F.array_sort(spans), F.array().cast(pair), add)


_RESULT = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string())])


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.withColumn("text_key", F.unhex(F.md5(F.coalesce(F.col("text"), F.lit("")).cast("binary"))))


def dedup_passages(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 of every row.

    Null, empty and short texts have no window and keep all words.  Rows that repeat a text are different places, so
    all their windows are repeated.  Other columns are ignored; an empty table gives an empty result.
    """
    rows = clean_columns(docs, "doc_id", "text")
    rows = _keyed(rows.withColumn("doc_id", rows["doc_id"].cast("long")))
    spans = repeated_windows(rows.select("text_key", "text"))
    marked = in_table(key_table(spans.select("text_key")), rows, F.col("text_key"), "has_")
    first = pa.schema([*_RESULT, ("text_key", pa.binary()), ("text", pa.string())])

    def whole(batches: Iterator[pa.RecordBatch]):
        # rows without spans are done here; only the others' texts travel to their spans
        for batch in batches:
            made = []
            for doc_id, text, key, has in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                text = text.as_py() or ""
                words = text.encode().split()
                made.append((doc_id, len(words), 0, hashlib.sha256(b" ".join(words)).hexdigest(), key, text if has else None))
            if made:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*made, strict=True), first, strict=True)], schema=first)

    ddl = "doc_id long, n_words long, n_removed long, kept_sha256 string"
    done = marked.select("doc_id", "text", "text_key", "has_").mapInArrow(whole, ddl + ", text_key binary, text string")
    # merged whatever the sizes: files of spans are packed far below what they take when read
    joined = done.join(spans.hint("merge"), "text_key", "left").select("doc_id", "n_words", "n_removed", "kept_sha256", "text", "spans")

    def run(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            made = []
            for doc_id, n, none, digest, text, found in zip(*(batch.column(k).to_pylist() for k in range(6)), strict=True):
                if found:
                    words, kept, at = text.encode().split(), [], 0
                    for s in found:
                        kept += words[at : s["start"]]
                        at = s["end"]
                    kept += words[at:]
                    none, digest = n - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest()
                made.append((doc_id, n, none, digest))
            if made:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*made, strict=True), _RESULT, strict=True)], schema=_RESULT)

    return joined.mapInArrow(run, ddl)


def cut_passages(docs: DataFrame) -> DataFrame:
    """``docs`` with the repeated passages cut out of ``text``; all rows and columns are kept, whatever those are called.

    A text without repeated windows stays as it is, to the byte, null texts too; otherwise the kept words are joined by
    one space, and a column n_chars, where there is one, is set to the new length.  Rows that repeat a text lose all
    words that windows cover in each of them.  An empty table gives an empty result.
    """
    return _cut(docs, repeated_windows)


def cut_references(docs: DataFrame, references: DataFrame, window: int = WINDOW) -> DataFrame:
    """``docs`` with stretches that also stand in ``references`` (text) cut out of ``text``, else as ``cut_passages``.

    References that are null or shorter than a window match nothing.
    """
    return _cut(docs, lambda rows: reference_spans(rows, references, window))


def _cut(docs: DataFrame, find) -> DataFrame:
    columns = docs.columns
    keyed = docs.select(*(F.col(f"`{c}`").alias(f"in_{i}_") for i, c in enumerate(columns)), F.col("text"))
    where = columns.index("text")
    keyed = _keyed(keyed)
    spans = find(keyed.select("text_key", "text"))
    marked = in_table(key_table(spans.select("text_key")), keyed, F.col("text_key"), "has_").drop("text")
    untouched = marked.filter("not has_").drop("text_key", "has_")
    joined = marked.filter("has_").drop("has_").join(spans.hint("merge"), "text_key", "left").drop("text_key")
    names = joined.columns

    def run(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            i, j = names.index(f"in_{where}_"), names.index("spans")
            made = []
            for text, found in zip(batch.column(i).to_pylist(), batch.column(j).to_pylist(), strict=True):
                if found:
                    words, kept, at = text.encode().split(), [], 0
                    for s in found:
                        kept += words[at : s["start"]]
                        at = s["end"]
                    text = b" ".join(kept + words[at:]).decode()
                made.append(text)
            out = [c for k, c in enumerate(batch.columns) if k != j]
            out[i] = pa.array(made, pa.string())
            yield pa.RecordBatch.from_arrays(out, names=[n for k, n in enumerate(names) if k != j])

    cut = joined.mapInArrow(run, joined.drop("spans").schema)
    size = {f"in_{columns.index('n_chars')}_": F.length(F.col(f"in_{where}_")).cast(docs.schema["n_chars"].dataType)} if "n_chars" in columns else {}
    return cut.withColumns(size).unionByName(untouched).select(*(F.col(f"in_{i}_").alias(c) for i, c in enumerate(columns)))


# ------------------------------------------------------------------------------------------------ given references


def _reference_shards(references: DataFrame, window: int) -> DataFrame:
    """(part, n, blob): automata of the references' texts, each over about ``REFERENCE_SHARD`` words."""

    def run(batches: Iterator[pa.RecordBatch]):
        schema = pa.schema([("part", pa.int64()), ("n", pa.int64()), ("blob", pa.binary())])
        automaton, ids, n, part = SuffixAutomaton(), {}, 0, 0

        def done() -> pa.RecordBatch:
            packed = marshal.dumps((ids, automaton.next, automaton.link, automaton.length))
            return pa.RecordBatch.from_arrays([pa.array([part]), pa.array([n]), pa.array([zstandard.compress(packed, 3)], pa.binary())], schema=schema)

        for batch in batches:
            for text in batch.column(0):
                words = (text.as_py() or "").encode().split()
                if len(words) < window:
                    continue
                # a long text is cut into stretches that share a window less one word
                for at in range(0, len(words) - window + 1, REFERENCE_SHARD):
                    piece = words[at : at + REFERENCE_SHARD + window - 1]
                    automaton.add([ids.setdefault(w, len(ids)) for w in piece])
                    n += len(piece)
                    if n >= REFERENCE_SHARD:
                        yield done()
                        automaton, ids, n, part = SuffixAutomaton(), {}, 0, part + 1
        if n:
            yield done()

    return references.select("text").mapInArrow(run, "part long, n long, blob binary")


def reference_spans(rows: DataFrame, references: DataFrame, window: int = WINDOW) -> DataFrame:
    """(text_key, spans) of the maximal stretches of rows (text_key, text) whose windows occur in ``references`` (text).

    The references are a given set of bounded size: their words are counted first, and more than ``MAX_REFERENCE_WORDS``
    are an error.  Automata of ``REFERENCE_ROUND`` shards are broadcast at a time, and every document is streamed through
    each for its matching statistics.
    """
    spark = rows.sparkSession
    sizes = references.select(F.coalesce(F.size(F.split(F.trim("text"), r"[\x20\x09-\x0D]+")), F.lit(0)).alias("n")).agg(F.sum("n")).first()[0] or 0
    if sizes > MAX_REFERENCE_WORDS:
        raise ValueError(f"{sizes} words of references can't be broadcast; put them with the documents into dedup_passages")
    shards = stage(_reference_shards(references, window), "reference-shards").withColumn("file", F.input_file_name())
    listed = [(r["file"], r["part"]) for r in shards.select("file", "part").orderBy("file", "part").collect()]
    out_schema = pa.schema([("text_key", pa.binary()), ("start", pa.int32()), ("end", pa.int32())])
    parts = [spark.createDataFrame([], "text_key binary, start int, end int")]
    for k in range(0, len(listed), REFERENCE_ROUND):
        wanted = listed[k : k + REFERENCE_ROUND]
        here = reduce(lambda x, y: x | y, [(F.col("file") == f) & (F.col("part") == i) for f, i in wanted])
        given = spark.sparkContext.broadcast([bytes(r["blob"]) for r in shards.filter(here).select("blob").collect()])

        def run(batches: Iterator[pa.RecordBatch], given=given):
            automata = []
            for blob in given.value:
                own = SuffixAutomaton()
                ids, own.next, own.link, own.length = marshal.loads(zstandard.decompress(blob))
                own.count = [1] * len(own.next)
                automata.append((ids, own))
            for batch in batches:
                made = []
                for key, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                    words = (text.as_py() or "").encode().split()
                    for ids, own in automata if len(words) >= window else ():
                        full = np.array([size == window for size, _ in own.matches([ids.get(w, -1) for w in words], window)], bool)
                        made += [(key, lo, hi + window - 1) for lo, hi in _runs(full[window - 1 :])]
                if made:
                    yield _rows_of(out_schema, made)

        parts.append(rows.select("text_key", "text").mapInArrow(run, "text_key binary, start int, end int"))
    spans = reduce(DataFrame.unionByName, parts)
    return stage(spans.groupBy("text_key").agg(_merged(F.collect_set(F.struct("start", "end"))).alias("spans")), "reference-spans")
