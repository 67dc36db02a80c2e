"""Table graph and row graph, as views over the base tables."""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator
from functools import reduce

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..catalog import Database, LinkSpec


def table_graph(db: Database) -> DataFrame:
    """src_table, dst_table, link, inverse, n_edges: every link both ways with the number of its references; one pruned scan of each child."""
    out = []
    for n in db.tables:
        own = [x for x in db.links if x.child == n]
        if not own:
            continue
        counts = db[n].agg(*(F.count(F.col(x.fk)).alias(f"n{k}") for k, x in enumerate(own)))
        both = [(x.child, x.parent, x.name, False, f"n{k}") for k, x in enumerate(own)] + [(x.parent, x.child, x.name, True, f"n{k}") for k, x in enumerate(own)]
        rows = F.array(*(F.struct(F.lit(src).alias("src_table"), F.lit(dst).alias("dst_table"), F.lit(name).alias("link"), F.lit(inverse).alias("inverse"), F.col(c).alias("n_edges")) for src, dst, name, inverse, c in both))
        out.append(counts.select(F.inline(rows)))
    if not out:
        return db.spark.createDataFrame([], "src_table string, dst_table string, link string, inverse boolean, n_edges long")
    return reduce(DataFrame.unionByName, out)


def _distances(near: dict[str, set[str]], a: str) -> dict[str, int]:
    """Tables that are reached from one, with the links on the shortest way."""
    seen, queue = {a: 0}, deque([a])
    while queue:
        t = queue.popleft()
        for u in near.get(t, ()):
            if u not in seen:
                seen[u] = seen[t] + 1
                queue.append(u)
    return seen


def hops_between(db: Database, a: str, b: str) -> int | None:
    """Links between two tables on the shortest way, None where there is none."""
    near: dict[str, set[str]] = {}
    for x in db.links:
        near.setdefault(x.child, set()).add(x.parent)
        near.setdefault(x.parent, set()).add(x.child)
    return _distances(near, a).get(b)


def table_hops(db: Database) -> DataFrame:
    """src, dst, hops of every two tables that links with references tie together, a table and itself included."""
    names = list(db.tables)

    def ways(batches: Iterator[pd.DataFrame]):
        for pdf in batches:
            for pairs in pdf["pairs"]:
                near: dict[str, set[str]] = {}
                for pair in pairs:
                    near.setdefault(pair["src_table"], set()).add(pair["dst_table"])
                yield pd.DataFrame([(a, b, n) for a in names for b, n in _distances(near, a).items()], columns=["src", "dst", "hops"])

    # one row: as many pairs as the database has links
    met = table_graph(db).filter("n_edges > 0").agg(F.collect_list(F.struct("src_table", "dst_table")).alias("pairs"))
    return met.mapInPandas(ways, "src string, dst string, hops long")


def table_components(db: Database) -> list[set[str]]:
    """Sets of tables that links tie together."""
    left, out = set(db.tables), []
    while left:
        first = next(iter(left))
        part = {t for t in left if hops_between(db, first, t) is not None}
        out.append(part)
        left -= part
    return out


def node_id(db: Database, name: str) -> Column:
    return F.col(db.tables[name].pk).cast("string" if dict(db[name].dtypes)[db.tables[name].pk] == "string" else "bigint")


def node_view(db: Database, name: str) -> DataFrame:
    """ntype, nid, ts of a table's rows: one pruned scan."""
    s = db.tables[name]
    time = F.col(s.time) if s.time else F.lit(None)
    return s.df.select(F.lit(name).alias("ntype"), node_id(db, name).alias("nid"), time.cast("timestamp_ntz").alias("ts"))


def all_nodes(db: Database) -> DataFrame:
    return reduce(DataFrame.unionByName, [node_view(db, n).withColumn("nid", F.col("nid").cast("string")) for n in db.tables])


def edge_view(db: Database, link: LinkSpec, upward: bool = True) -> DataFrame:
    """link, src_type, src, dst_type, dst, ts: messages run from src to dst, ts is the source row's time.

    Upward edges (child to parent) are one pruned scan of the child; the other way needs the parent's time, which is
    joined only where the parent has one.  Null references are no edges.
    """
    child, parent = db.tables[link.child], db.tables[link.parent]
    time = F.col(child.time) if child.time else F.lit(None)
    rows = child.df.filter(F.col(link.fk).isNotNull()).select(node_id(db, link.child).alias("c"), F.col(link.fk).alias("p"), time.cast("timestamp_ntz").alias("ts"))
    kind = "string" if dict(rows.dtypes)["p"] == "string" else "bigint"
    rows = rows.withColumn("p", F.col("p").cast(kind))
    if upward:
        return rows.select(F.lit(link.name).alias("link"), F.lit(link.child).alias("src_type"), F.col("c").alias("src"), F.lit(link.parent).alias("dst_type"), F.col("p").alias("dst"), "ts")
    if parent.time:
        rows = rows.drop("ts").join(node_view(db, link.parent).select(F.col("nid").alias("p"), "ts"), "p")
    else:
        rows = rows.withColumn("ts", F.lit(None).cast("timestamp_ntz"))
    return rows.select(F.lit(link.name).alias("link"), F.lit(link.parent).alias("src_type"), F.col("p").alias("src"), F.lit(link.child).alias("dst_type"), F.col("c").alias("dst"), "ts")


def all_edges(db: Database) -> DataFrame:
    parts = [edge_view(db, x, up) for x in db.links for up in (True, False)]
    return reduce(DataFrame.unionByName, [p.withColumns({"src": F.col("src").cast("string"), "dst": F.col("dst").cast("string")}) for p in parts])


def roundtrip(db: Database) -> DataFrame:
    """link, n_lost, n_new: references rebuilt from edges against the columns they came from (both 0)."""
    out = []
    for x in db.links:
        base = db[x.child].filter(F.col(x.fk).isNotNull()).select(node_id(db, x.child).alias("c"), F.col(x.fk).cast("string").alias("p"))
        back = edge_view(db, x).select(F.col("src").alias("c"), F.col("dst").cast("string").alias("p"))
        side = base.withColumn("w", F.lit(1)).unionByName(back.withColumn("w", F.lit(-1))).groupBy("c", "p").agg(F.sum("w").alias("w"))
        out.append(side.agg(F.coalesce(F.sum(F.when(F.col("w") > 0, F.col("w"))), F.lit(0)).alias("n_lost"), F.coalesce(F.sum(F.when(F.col("w") < 0, -F.col("w"))), F.lit(0)).alias("n_new")).select(F.lit(x.name).alias("link"), "n_lost", "n_new"))
    return reduce(DataFrame.unionByName, out)


def degree_stats(db: Database) -> DataFrame:
    """link, n_parents, n_edges, max_degree over parents that have a child."""
    out = []
    for x in db.links:
        d = db[x.child].filter(F.col(x.fk).isNotNull()).groupBy(x.fk).count()
        out.append(d.agg(F.count("*").alias("n_parents"), F.sum("count").alias("n_edges"), F.max("count").alias("max_degree")).select(F.lit(x.name).alias("link"), "n_parents", "n_edges", "max_degree"))
    return reduce(DataFrame.unionByName, out)


def freeze_counts(db: Database, moments: list) -> DataFrame:
    """ntype, t, n: rows of each table visible at each moment."""
    out = []
    for t in moments:
        seen = db.visible(t)
        out += [node_view(seen, n).agg(F.count("*").alias("n")).select(F.lit(n).alias("ntype"), F.lit(t).cast("timestamp_ntz").alias("t"), "n") for n in db.tables]
    return reduce(DataFrame.unionByName, out)


def db_stats(db: Database) -> DataFrame:
    """ntype, n, lo, hi: rows and time span of each table."""
    parts = [node_view(db, n).agg(F.count("*").alias("n"), F.min("ts").alias("lo"), F.max("ts").alias("hi")).select(F.lit(n).alias("ntype"), "n", "lo", "hi") for n in db.tables]
    return reduce(DataFrame.unionByName, parts)


def receptive_bound(caps: list[int]) -> int:
    """Most rows that a slice can hold besides its seed."""
    total, width = 0, 1
    for m in caps:
        width *= m
        total += width
    return total


def degree_percentiles(db: Database) -> DataFrame:
    """link, p50, p90, mean, n_edges of the number of children that parents with a child have."""
    out = []
    for x in db.links:
        d = db[x.child].filter(F.col(x.fk).isNotNull()).groupBy(x.fk).agg(F.count("*").cast("double").alias("n"))
        out.append(d.agg(F.percentile("n", 0.5).alias("p50"), F.percentile("n", 0.9).alias("p90"), F.avg("n").alias("mean"), F.sum("n").cast("bigint").alias("n_edges")).select(F.lit(x.name).alias("link"), "p50", "p90", "mean", "n_edges"))
    return reduce(DataFrame.unionByName, out)


def row_links(db: Database) -> DataFrame:
    """ntype, n_links, n_rows, n_edges, n_partite: references of a table's rows, and whether none is to its own table."""
    out = []
    for n in db.tables:
        own = [x for x in db.links if x.child == n]
        edges = reduce(lambda a, b: a + b, [F.count(F.col(x.fk)) for x in own], F.lit(0).cast("bigint"))
        out.append(db[n].agg(F.count("*").alias("n_rows"), edges.alias("n_edges")).select(F.lit(n).alias("ntype"), F.lit(len(own)).cast("bigint").alias("n_links"), "n_rows", "n_edges", F.lit(all(x.parent != n for x in own)).alias("n_partite")))
    return reduce(DataFrame.unionByName, out)
