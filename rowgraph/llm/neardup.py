"""Near-duplicate documents: sketches, banding, exact verification, components.

1. Each document gives its shingle set's size and digest, its bands and a signature (one byte per coordinate).
   Documents of equal sets are one node from here on.
2. In every band bucket all nodes are checked against the bucket's smallest node, on their full sets.
3. Components of those links.  Only where several components remain are other pairs looked at, by signature, and those
   of different components that may be similar enough are checked on full sets.
   Large buckets are joined to clusters, whose members are dealt out in blocks, each pair of blocks to one task; blocks
   of one component don't meet.  Signatures alone travel there, and a task names the fewest pairs that would join all
   its components.  Where one of those turns out not to be a link, the two blocks meet again with their texts.
   Small buckets give candidate pairs.
   Both kinds of pairs are checked together.
4. Components of all links.

On a cluster each table that is written costs a task per shuffle partition, however few its rows, so a node's buckets are
kept in one row, from which pairs, keys and clusters are read where it lies.
A bucket or cluster is never expanded into its pairs.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import sketch
from .components import components, components_by_kind
from .keyset import in_table, key_table, without_keys
from .shared import clean_columns, counted, discard, kept_at, stage
from .words import release, slices

#: Links: 100 * intersection >= MIN_PERCENT * union.
MIN_PERCENT = 85
#: Buckets with more members than this are compared by cluster.
HOT_BUCKET = 64
#: Members of a cluster in one block.
BLOCK = 256


def min_shared(min_percent: int) -> int:
    """Coordinates of the signature that a pair must share to be checked: the expected number less 5.5 standard deviations."""
    p = min_percent / 100
    return int(sketch.T * p - 5.5 * (sketch.T * p * (1 - p)) ** 0.5)


def sketched(docs: DataFrame, min_percent: int = MIN_PERCENT) -> DataFrame:
    """doc_id, n_shingles, digest, bands, signature of each document (null text: empty set).  Texts are not carried."""
    rows = clean_columns(docs, "doc_id", "text")
    rows = rows.select(rows["doc_id"].cast("long").alias("doc_id"), "text")
    n_bands, n_rows = sketch.banding(min_percent)
    schema = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("digest", pa.binary()), ("bands", pa.list_(pa.int64())), ("signature", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]):
        for whole in batches:
            for batch in slices(whole, "text"):
                sets = sketch.shingle_sets(batch.column(1))
                made = sketch.sketches(sets)
                bands = sketch.band_hashes(made, n_bands, n_rows).view(np.int64)
                marks = sketch.signatures(made)
                full = [len(s) > 0 for s in sets]
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0),
                        pa.array([len(s) for s in sets], pa.int64()),
                        pa.array([sketch.set_digest(s) if f else None for s, f in zip(sets, full, strict=True)], pa.binary()),
                        pa.ListArray.from_arrays(np.arange(0, len(sets) * n_bands + 1, n_bands, dtype=np.int32), bands.ravel()),
                        pa.array([m.tobytes() for m in marks], pa.binary()),
                    ],
                    schema=schema,
                )
        release()

    return rows.mapInArrow(run, "doc_id long, n_shingles long, digest binary, bands array<long>, signature binary")


def check_pairs(pairs: DataFrame, texts: DataFrame, min_percent: int = MIN_PERCENT) -> DataFrame:
    """Those of ``pairs`` (a, b) whose full shingle sets are similar enough.  ``texts`` has (doc_id, text), one row each.

    The rows of a pair meet by two plain joins, which split a text that very many pairs share.
    """
    right = texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b"))
    return check_texts(pairs.join(right, "b"), texts, min_percent)


def check_texts(pairs: DataFrame, texts: DataFrame, min_percent: int = MIN_PERCENT) -> DataFrame:
    """``check_pairs`` for pairs (a, b, text_b) that bring one of their texts."""
    left = texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a"))
    rows = pairs.join(left, "a").select("a", "b", "text_a", "text_b")
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]):
        last, kept = None, None
        for whole in batches:
            for batch in slices(whole, "text_b", 1 << 20):
                good = []
                firsts, seconds = batch.column(0).to_pylist(), sketch.shingle_sets(batch.column(3))
                for k, (a, items) in enumerate(zip(firsts, seconds, strict=True)):
                    if a != last:
                        last, kept = a, sketch.shingle_sets(batch.column(2).slice(k, 1))[0]
                    both, union = sketch.overlap(kept, items)
                    good.append(union > 0 and 100 * both >= min_percent * union)
                yield pa.RecordBatch.from_arrays([c.filter(pa.array(good, pa.bool_())) for c in batch.columns[:2]], schema=schema)
        release()

    return rows.mapInArrow(run, "a long, b long")


def _groups(batches: Iterator[pa.RecordBatch], keys: list[int]) -> Iterator[pa.Table]:
    """Runs of rows with equal values in the key columns, which may go on in the next batch."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [batch.column(k).to_numpy(zero_copy_only=False) for k in keys]
        if held and any(held[-1].column(k)[-1].as_py() != c[0] for k, c in zip(keys, columns, strict=True)):
            yield pa.Table.from_batches(held)
            held = []
        changes = np.flatnonzero(np.logical_or.reduce([np.diff(c) != 0 for c in columns])) + 1
        cuts = [0, *changes.tolist(), batch.num_rows]
        for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
            held.append(batch.slice(lo, hi - lo))
            if hi < batch.num_rows:
                yield pa.Table.from_batches(held)
                held = []
    if held:
        yield pa.Table.from_batches(held)


def _tried(table: pa.Table):
    """Whether two members (positions) have been checked already, one being the smallest node of a bucket of the other's."""
    node, leads = table["node"].to_pylist(), [set(x) for x in table["leads"].to_pylist()]
    return lambda x, y: node[x] in leads[y] or node[y] in leads[x]


def _marks(table: pa.Table) -> np.ndarray:
    return np.frombuffer(b"".join(table["signature"].to_pylist()), np.uint8).reshape(table.num_rows, -1)


def may_link(x: int, others: np.ndarray, size: np.ndarray, mark: np.ndarray, min_percent: int) -> np.ndarray:
    """Those of ``others`` that sizes and signatures allow to be linked with x."""
    low, high = np.minimum(size[others], size[x]), np.maximum(size[others], size[x])
    others = others[100 * low >= min_percent * high]
    return others[(mark[others] == mark[x]).sum(axis=1) >= min_shared(min_percent)] if len(others) else others


_PAIR = pa.schema([("a", pa.int64()), ("b", pa.int64())])


def pairs_across(members: DataFrame, min_percent: int = MIN_PERCENT) -> DataFrame:
    """Candidate pairs (a, b), which may repeat, from the small buckets (band, node, component, cluster, n_shingles, signature, leads).

    Pairs within a component or a cluster and those checked before are left out.
    """
    rows = members.select("band", "node", "component", F.coalesce("cluster", F.lit(-1) - F.col("node")).alias("cluster"), "n_shingles", "signature", "leads")
    rows = rows.repartition("band").sortWithinPartitions("band", "node")

    def run(batches: Iterator[pa.RecordBatch]):
        for g in _groups(batches, [0]):
            node, comp, cluster, size = (g[n].to_numpy() for n in ("node", "component", "cluster", "n_shingles"))
            mark, tried, found = _marks(g), _tried(g), []
            for x in range(len(node) - 1):
                others = np.arange(x + 1, len(node))
                others = may_link(x, others[(comp[others] != comp[x]) & (cluster[others] != cluster[x])], size, mark, min_percent)
                found += [(int(node[x]), int(node[y])) for y in others if not tried(x, y)]
            if found:
                yield pa.RecordBatch.from_arrays([pa.array([min(f) for f in found]), pa.array([max(f) for f in found])], schema=_PAIR)

    return rows.mapInArrow(run, "a long, b long")


def block_counts(grouped: DataFrame, block: int) -> tuple[DataFrame, DataFrame, int]:
    """Blocks of each cluster that has several components, its large components with the blocks before theirs, and how many
    such clusters there are.

    ``grouped`` has (cluster, node, component).  A component of a block's size or more has blocks of its own, which don't
    meet each other; the members of small components are dealt out by component.  What comes together in one place is one
    entry per large component of a cluster.
    """
    per = grouped.groupBy("cluster", "component").agg(F.count("*").alias("n"))
    per = per.withColumn("own", F.when(F.col("n") >= block, F.ceil(F.col("n") / F.lit(block))).cast("int"))
    few = F.ceil(F.coalesce(F.sum(F.when(F.col("own").isNull(), F.col("n"))), F.lit(0)) / F.lit(block)).cast("int")
    owners = F.collect_list(F.when(F.col("own").isNotNull(), F.struct("component", "own")))
    spread = per.groupBy("cluster").agg(few.alias("small"), F.coalesce(F.sum("own"), F.lit(0)).cast("int").alias("large"), owners.alias("owners"), F.count("*").alias("n"))
    spread, n = counted(spread.filter("n > 1").drop("n"), "near-spread")
    schema = pa.schema([("cluster", pa.int64()), ("component", pa.int64()), ("own", pa.int32()), ("before", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            for cluster, owned in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                own = owned.values.field("own")
                before = np.cumsum(own.to_numpy()) - own.to_numpy()
                yield pa.RecordBatch.from_arrays([pa.array([cluster] * len(own), pa.int64()), owned.values.field("component"), own, pa.array(before, pa.int32())], schema=schema)

    large = spread.filter(F.size("owners") > 0).select("cluster", "owners").mapInArrow(run, "cluster long, component long, own int, before int")
    return kept_at(spread.drop("owners"), spread), stage(large, "near-large"), n


def dealt(grouped: DataFrame, spread: DataFrame, large: DataFrame) -> DataFrame:
    """``blocks_of`` by given counts; other columns are carried along."""
    carried = [c for c in grouped.columns if c not in ("cluster", "node", "component")]
    rows = grouped.join(spread, "cluster").join(large, ["cluster", "component"], "left")
    first = F.col("small") + F.col("before")
    alone = F.pmod(F.xxhash64("component"), F.greatest(F.col("small"), F.lit(1)))
    rows = rows.withColumn("block", F.when(F.col("own").isNull(), alone).otherwise(first + F.pmod(F.xxhash64("node"), F.col("own"))).cast("int"))
    every = F.sequence(F.lit(0), F.col("small") + F.col("large") - 1)
    others = F.when(F.col("own").isNull(), every).otherwise(F.filter(every, lambda x: (x < first) | (x >= first + F.col("own"))))
    rows = rows.withColumn("other", F.explode(others))
    return rows.select("cluster", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "node", "component", *carried)


def blocks_of(grouped: DataFrame, block: int) -> DataFrame:
    """Rows (cluster, i, j, block, node, component) of the pairs of blocks (i <= j) in which members must meet."""
    spread, large, _ = block_counts(grouped, block)
    return dealt(grouped, spread, large)


_BLOCK_KEY = ["cluster", "i", "j"]
_GUESS = pa.schema([("cluster", pa.int64()), ("i", pa.int32()), ("j", pa.int32()), ("a", pa.int64()), ("b", pa.int64())])


def _met(batches: Iterator[pa.RecordBatch], min_percent: int, check) -> Iterator[tuple]:
    """(cluster, i, j, pairs) of each pair of blocks: pairs not checked before between components that its own pairs don't
    join yet, where sizes, signatures and ``check(table)(x, y)`` allow them."""
    for g in _groups(batches, [0, 1, 2]):
        node, comp, size, block = (g[n].to_numpy() for n in ("node", "component", "n_shingles", "block"))
        comp, mark, tried, found = comp.copy(), _marks(g), _tried(g), []
        i, j = g["i"][0].as_py(), g["j"][0].as_py()
        linked = check(g)
        for x in np.flatnonzero(block == i).tolist():
            others = np.flatnonzero(block == j)
            if i == j:
                others = others[others > x]
            for y in may_link(x, others[comp[others] != comp[x]], size, mark, min_percent).tolist():
                if comp[x] != comp[y] and not tried(x, y) and linked(x, y):
                    found.append((min(int(node[x]), int(node[y])), max(int(node[x]), int(node[y]))))
                    comp[comp == comp[y]] = comp[x]
        if found:
            yield g["cluster"][0].as_py(), i, j, found


def likely_links(members: DataFrame, min_percent: int = MIN_PERCENT) -> DataFrame:
    """(cluster, i, j, a, b): the fewest pairs by signature that would join the components in each pair of blocks.

    ``members`` has the rows of ``blocks_of`` with n_shingles, signature and leads; no text travels.
    """
    rows = members.select(*_BLOCK_KEY, "block", "node", "component", "n_shingles", "signature", "leads").repartition(*_BLOCK_KEY).sortWithinPartitions(*_BLOCK_KEY, "node")

    def run(batches: Iterator[pa.RecordBatch]):
        for cluster, i, j, found in _met(batches, min_percent, lambda g: lambda x, y: True):
            n = len(found)
            yield pa.RecordBatch.from_arrays([pa.array([cluster] * n), pa.array([i] * n, pa.int32()), pa.array([j] * n, pa.int32()), pa.array([f[0] for f in found]), pa.array([f[1] for f in found])], schema=_GUESS)

    return rows.mapInArrow(run, "cluster long, i int, j int, a long, b long")


def links_in_blocks(members: DataFrame, min_percent: int = MIN_PERCENT) -> DataFrame:
    """Links (a, b) between components of each pair of blocks, checked on full sets in place.

    ``members`` has the rows of ``blocks_of`` with n_shingles, signature, leads and text.
    """
    rows = members.select(*_BLOCK_KEY, "block", "node", "component", "n_shingles", "signature", "leads", "text").repartition(*_BLOCK_KEY).sortWithinPartitions(*_BLOCK_KEY, "node")

    def check(g: pa.Table):
        sets = sketch.shingle_sets(g["text"])

        def linked(x: int, y: int) -> bool:
            both, union = sketch.overlap(sets[x], sets[y])
            return 100 * both >= min_percent * union

        return linked

    def run(batches: Iterator[pa.RecordBatch]):
        for _, _, _, found in _met(batches, min_percent, check):
            yield pa.RecordBatch.from_arrays([pa.array([f[0] for f in found]), pa.array([f[1] for f in found])], schema=_PAIR)
        release()

    return rows.mapInArrow(run, "a long, b long")


def links_across(placed: DataFrame, texts: DataFrame, min_percent: int = MIN_PERCENT) -> tuple[DataFrame, ...]:
    """Tables of links (a, b) that join the components of each cluster and small bucket as all their links would.

    ``placed`` has (node, component, cluster, bands, n_shingles, signature, leads), ``texts`` (doc_id, text).  The likely
    links of clusters and the candidates of small buckets are checked first; a pair of blocks whose likely links all are
    links needs no more, the others are gone through with their texts.
    """
    marks = placed.select("node", "n_shingles", "signature", "leads")
    grouped = placed.filter("cluster is not null").drop("bands")
    spread, large, n_clusters = block_counts(grouped, BLOCK)
    # a small bucket has HOT_BUCKET members at most
    buckets = placed.select(F.explode("bands").alias("band"), "node", "component", "cluster").repartition("band").groupBy("band")
    mixed = buckets.agg(F.collect_list(F.struct("node", "component", "cluster")).alias("m"), F.min("component").alias("lo"), F.max("component").alias("hi"))
    mixed = mixed.filter("lo < hi").select("band", F.explode("m").alias("m")).select("band", "m.*")
    pairs = pairs_across(mixed.join(marks, "node"), min_percent)
    if n_clusters:
        likely = stage(likely_links(dealt(grouped, spread, large), min_percent), "near-likely")
        pairs = pairs.unionByName(likely.select("a", "b"))
    sure = stage(check_pairs(pairs.distinct(), texts, min_percent), "near-sure")
    if not n_clusters:
        return (sure,)
    again, n_again = counted(likely.join(sure, ["a", "b"], "left_anti").select(*_BLOCK_KEY).distinct(), "near-again")
    discard(likely)
    if not n_again:
        return (sure,)
    rest = dealt(grouped, spread, large).join(again, _BLOCK_KEY, "left_semi").join(texts.select(F.col("doc_id").alias("node"), "text"), "node")
    found = stage(links_in_blocks(rest, min_percent), "near-found")
    discard(again, spread, large)
    return sure, found


def near_duplicates(docs: DataFrame, min_percent: int = MIN_PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each row of ``docs``.

    A text without words has an empty set, is linked with nothing and is its own component.  Rows of equal sets are
    linked, whatever their number.  Ids identify documents: rows that repeat an id are one document, whose smallest
    text is the one that is verified.  A row without an id takes the component of an equal set, null if there is none,
    and is kept only in the latter case.  Other columns are ignored; empty tables give empty results.
    """
    sketches = stage(sketched(docs, min_percent), "near-sketches")
    found = sketches.filter(F.col("digest").isNotNull() & F.col("doc_id").isNotNull())
    nodes = stage(found.groupBy("digest").agg(F.min("doc_id").alias("node"), F.min("n_shingles").alias("n_shingles"), F.min("bands").alias("bands"), F.min("signature").alias("signature")), "near-nodes")
    listed = stage(sketches.select("doc_id", "n_shingles", "digest"), "near-listed")
    discard(sketches)

    banded = nodes.select("node", F.explode("bands").alias("band"))
    buckets = stage(banded.groupBy("band").agg(F.min("node").alias("lead"), F.count("*").alias("n_members")).filter("n_members > 1"), "near-buckets")
    # a row for each node that shares a bucket with another: its smaller leads, those of large buckets, and its small buckets
    shared = banded.join(buckets, "band").repartition("node")
    shared = shared.groupBy("node").agg(F.collect_list(F.struct("band", "lead", "n_members")).alias("p"))
    behind = F.filter("p", lambda x: x["lead"] < F.col("node"))
    hot = F.filter(behind, lambda x: x["n_members"] > HOT_BUCKET)
    small = F.filter("p", lambda x: x["n_members"] <= HOT_BUCKET)
    places = shared.select("node", F.array_distinct(behind["lead"]).alias("leads"), F.array_distinct(hot["lead"]).alias("hot_leads"), small["band"].alias("bands"))
    places = stage(places, "near-places")
    discard(buckets, shuffles=True)

    # only texts of nodes that share a bucket with another are fetched
    given = clean_columns(docs, "doc_id", "text").withColumn("doc_id", F.col("doc_id").cast("long"))
    given = in_table(key_table(places.select("node"), unique=True), given, F.col("doc_id"), "has_").filter("has_").drop("has_")
    given = given.groupBy("doc_id").agg(F.min("text").alias("text"))
    texts = stage(given.join(places.select(F.col("node").alias("doc_id"), "leads"), "doc_id"), "near-texts")

    stars = texts.select(F.explode("leads").alias("a"), F.col("doc_id").alias("b"), F.col("text").alias("text_b"))
    links = stage(check_texts(stars, texts, min_percent), "near-links")
    # clusters of the large buckets are found in the same rounds as the components of the links so far
    large = places.select(F.lit(1).alias("kind"), F.explode("hot_leads").alias("a"), F.col("node").alias("b"))
    both = components_by_kind(links.select(F.lit(0).alias("kind"), "a", "b").unionByName(large))
    of_kind = [F.min(F.when(F.col("kind") == k, F.col("component"))) for k in (0, 1)]
    named = both.groupBy("node").agg(of_kind[0].alias("component"), of_kind[1].alias("cluster"))
    placed = places.drop("hot_leads").join(named, "node", "left").join(nodes.select("node", "n_shingles", "signature"), "node")
    placed = stage(placed.withColumn("component", F.coalesce("component", "node")), "near-placed")
    discard(places, links, shuffles=True)

    rest = links_across(placed, texts, min_percent)
    discard(placed, texts, shuffles=True)
    ties = both.filter("kind = 0 and component < node").select(F.col("component").alias("a"), F.col("node").alias("b"))
    final = components(functools.reduce(DataFrame.unionByName, rest, ties))
    discard(both, *rest)
    named = nodes.select("digest", "node").join(final, "node", "left").select("digest", F.coalesce("component", "node").alias("component"))
    named = stage(named, "near-named")
    discard(nodes, final, shuffles=True)
    out = listed.select("doc_id", "n_shingles", "digest").join(named, "digest", "left")
    component = F.coalesce("component", "doc_id")
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.col("doc_id").eqNullSafe(component).alias("kept"))


def drop_duplicates(docs: DataFrame, min_percent: int = MIN_PERCENT) -> DataFrame:
    """The rows of ``docs``, with all their columns, whose id is the smallest of its group.

    Rows without an id stay, as they can't be told apart; rows that repeat an id stay or go together.
    """
    gone = near_duplicates(docs, min_percent).filter(~F.col("kept")).select("doc_id")
    return without_keys(docs, stage(gone.filter(F.col("doc_id").isNotNull()).distinct(), "near-gone"), "doc_id")
