"""Past-only neighbourhoods of seeds, capped and typed."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from datetime import datetime
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import Database, LinkSpec
from ..functions.columns import anchor_weight, draw, hash_unit, race_key, recency_weight, visible_at


@dataclass(frozen=True)
class Strategy:
    """How the m neighbours of a node are chosen.

    "uniform": by md5; "latest": by time, latest first; "recency" and "anchors": by the exponential race, weighted by
    age or by nearness to given moments; "all": no cap.  Ties are broken by the child's key.
    """

    kind: str = "latest"
    salt: str = "s1"
    half_life: float = 365.0
    moments: tuple[datetime, ...] = ()
    width: float = 30.0

    def order(self, seed_key: Column, seed_time: Column, child: Column, ts: Column) -> list[Column]:
        if self.kind == "latest":
            return [ts.desc_nulls_last(), child.asc()]
        h = draw(F.lit(self.salt), seed_key, F.date_format(seed_time, "yyyy-MM-dd"), child)
        if self.kind == "uniform":
            return [h.asc(), child.asc()]
        if self.kind == "recency":
            weight = recency_weight(ts, seed_time, self.half_life)
        elif self.kind == "anchors":
            weight = anchor_weight(ts, [F.lit(a).cast("timestamp_ntz") for a in self.moments], self.width)
        else:
            raise ValueError(f"no order for {self.kind}")
        return [race_key(hash_unit(h), weight).asc(), child.asc()]


def pick(rows: DataFrame, group: Sequence[str], m: int | None, order: list[Column]) -> DataFrame:
    """At most m rows of each group; the cap is part of the window, so each mapper sends at most m rows of a group."""
    if m is None:
        return rows
    return rows.withColumn("pick_rank_", F.row_number().over(Window.partitionBy(*group).orderBy(*order))).filter(F.col("pick_rank_") <= m).drop("pick_rank_")


def with_replacement(rows: DataFrame, group: Sequence[str], m: int, weight: Column, salt: str = "s1") -> DataFrame:
    """m draws from each group, proportional to weight: uniforms against running sums of the weights."""
    w = Window.partitionBy(*group).orderBy("child").rowsBetween(Window.unboundedPreceding, 0)
    summed = rows.withColumn("w_", weight).withColumn("hi_", F.sum("w_").over(w)).withColumn("lo_", F.col("hi_") - F.col("w_"))
    summed = summed.withColumn("all_", F.sum("w_").over(Window.partitionBy(*group)))
    drawn = summed.withColumn("j", F.explode(F.sequence(F.lit(1), F.lit(m))))
    u = hash_unit(draw(F.lit(salt), *(F.col(g) for g in group), F.col("j"))) * F.col("all_")
    return drawn.filter((u >= F.col("lo_")) & (u < F.col("hi_"))).drop("w_", "hi_", "lo_", "all_")


def neighbours(db: Database, link: LinkSpec, frontier: DataFrame, downward: bool = True) -> DataFrame:
    """Rows of frontier (seed_id, seed_time, nid) with their visible neighbours over one link: child, ts.

    Only keys and times are read.  The filter is on the neighbour's own time, not on that of the node it is reached
    from, and a bound by the latest seed time is left to the scan by the caller where it is known.
    """
    child, parent = db.tables[link.child], db.tables[link.parent]
    if downward:
        time = F.col(child.time) if child.time else F.lit(None)
        side = child.df.select(F.col(link.fk).cast("bigint").alias("nid"), F.col(child.pk).cast("bigint").alias("child"), time.cast("timestamp_ntz").alias("ts"))
    else:
        side = child.df.select(F.col(child.pk).cast("bigint").alias("nid"), F.col(link.fk).cast("bigint").alias("child"))
        if parent.time:
            side = side.join(parent.df.select(F.col(parent.pk).cast("bigint").alias("child"), F.col(parent.time).alias("ts")), "child")
        else:
            side = side.withColumn("ts", F.lit(None).cast("timestamp_ntz"))
        side = side.filter("child is not null")
    return frontier.join(side, "nid").filter(visible_at(F.col("ts"), F.col("seed_time")))


def seeds_of(task: DataFrame, key: str, ntype: str) -> DataFrame:
    """seed_id, seed_time, ntype, nid: ids are made of the keys, so no counter is needed."""
    return task.select(*seed_columns(key, ntype)).distinct()


def seed_columns(key: str, ntype: str) -> list[Column]:
    seed_id = F.concat_ws("|", F.col(key), F.date_format("seed_time", "yyyy-MM-dd"))
    return [seed_id.alias("seed_id"), F.col("seed_time"), F.lit(ntype).alias("ntype"), F.col(key).cast("bigint").alias("nid")]


@dataclass(frozen=True)
class Slice:
    """edges: seed_id, seed_time, hop, link, src_type, src, dst_type, dst, ts; messages run from src to dst.

    A slice whose rows carry their features has ``kids`` too: nid and an array of the rows below it that some stamp picks, in
    the order of picking, each with its features and its own array (ts, back, x, kids); ``caps`` then are its hops' caps.
    """

    seeds: DataFrame
    edges: DataFrame
    kids: DataFrame | None = None
    caps: tuple[int, ...] = ()

    @property
    def nodes(self) -> DataFrame:
        """seed_id, ntype, nid with the first hop on which each was reached; the seed is there with hop 0."""
        own = self.seeds.select("seed_id", "ntype", "nid", F.lit(0).alias("hop"))
        met = self.edges.select("seed_id", F.col("src_type").alias("ntype"), F.col("src").alias("nid"), "hop")
        return own.unionByName(met).groupBy("seed_id", "ntype", "nid").agg(F.min("hop").alias("hop"))

    def pack(self) -> DataFrame:
        """One row per seed with its edges as a sorted array; a slice is bounded by its caps."""
        edge = F.struct("hop", "link", "dst", "src", "src_type", "dst_type", "ts")
        packed = self.edges.groupBy("seed_id").agg(F.array_sort(F.collect_list(edge)).alias("edges"))
        return self.seeds.select("seed_id", "seed_time", "ntype", "nid").join(packed, "seed_id", "left")

    def cost(self) -> DataFrame:
        """hop, n_rows, n_seeds: rows that each hop made and for how many seeds; hop 0 are the seeds."""
        own = self.seeds.agg(F.lit(0).alias("hop"), F.count("*").alias("n_rows"), F.countDistinct("seed_id").alias("n_seeds"))
        return own.unionByName(self.edges.groupBy("hop").agg(F.count("*").alias("n_rows"), F.countDistinct("seed_id").alias("n_seeds")))

    def sizes(self) -> DataFrame:
        return self.nodes.groupBy("seed_id").agg((F.count("*") - 1).alias("n_nodes"))


def cut_slice(
    db: Database,
    seeds: DataFrame,
    caps: list[int | None],
    strategy: Strategy,
    links: list[tuple[str, bool]] | None = None,
    cap_scope: str = "node",
    share: bool = False,
    staged: str | None = None,
    edge_hook=None,
    carry: str | None = None,
) -> Slice:
    """A slice of ``len(caps)`` hops around each seed.

    ``links`` names the allowed steps as (link, downward); without it every step into a table of the frontier is taken.
    ``cap_scope`` caps a node's neighbours over all links or per link.  With ``share`` the choice depends on the node
    and the stamp only, so it is made once per (node, stamp) for all seeds of the stamp.  "latest" doesn't depend on the
    seed, so behind the first hop it is always made once: a hub's rows meet its stamps, not each seed that reached it.
    ``staged`` is a folder to which each hop is written, for large runs.  Nodes met again are expanded again; the unions
    keep them once.

    ``carry`` names a column of features that the tables of a chain of downward links have (latest picks only).  Rows then
    are picked once per node for all stamps of the seeds, so that neither rows nor features are joined seed by seed.
    """
    if carry:
        if share or staged or edge_hook:
            raise ValueError("features are carried without sharing, stages and hooks")
        return _cut_carried(db, seeds, caps, strategy, links, carry)
    types, frontier, out = {r["ntype"] for r in seeds.select("ntype").distinct().collect()}, seeds, []
    for hop, m in enumerate(caps, 1):
        steps = [(x, down) for x in db.links for down in (True, False) if (x.parent if down else x.child) in types and (links is None or (x.name, down) in links)]
        if not steps:
            break
        base, once = frontier, share or (strategy.kind == "latest" and hop > 1 and m is not None)
        if once:
            base = frontier.select("seed_time", "ntype", "nid").distinct().withColumn("seed_id", F.date_format("seed_time", "yyyy-MM-dd"))
        found = []
        for link, down in steps:
            at, to = (link.parent, link.child) if down else (link.child, link.parent)
            here = base.filter(F.col("ntype") == at).select("seed_id", "seed_time", "nid")
            near = neighbours(db, link, here, down)
            name = link.name if down else f"{link.name}^"
            found.append(near.select("seed_id", "seed_time", F.lit(hop).alias("hop"), F.lit(name).alias("link"), F.lit(to).alias("src_type"), F.col("child").alias("src"), F.lit(at).alias("dst_type"), F.col("nid").alias("dst"), "ts"))
        rows = reduce(DataFrame.unionByName, found)
        if strategy.kind != "all" and m is not None:
            key = F.col("dst") if once else F.split_part(F.col("seed_id"), F.lit("|"), F.lit(1))
            order = strategy.order(key, F.col("seed_time"), F.col("src"), F.col("ts"))
            rows = pick(rows, ["seed_id", "dst_type", "dst", *(["link"] if cap_scope == "link" else [])], m, [*order, F.col("link")])
        if once:
            who = frontier.select("seed_id", "seed_time", F.col("ntype").alias("dst_type"), F.col("nid").alias("dst")).distinct()
            rows = rows.drop("seed_id").join(who, ["seed_time", "dst_type", "dst"]).select("seed_id", "seed_time", "hop", "link", "src_type", "src", "dst_type", "dst", "ts")
        if edge_hook:
            rows = edge_hook(rows)
        if staged:
            rows.write.mode("overwrite").parquet(f"{staged}/hop{hop}")
            rows = db.spark.read.parquet(f"{staged}/hop{hop}")
        out.append(rows)
        types = {x.child if down else x.parent for x, down in steps}
        frontier = rows.select("seed_id", "seed_time", F.col("src_type").alias("ntype"), F.col("src").alias("nid")).distinct()
    return Slice(seeds, reduce(DataFrame.unionByName, out))


def picked_at(kids: Column, t: Column, m: int) -> Column:
    """The first m of an array of rows that are visible at t."""
    return F.slice(F.filter(kids, lambda k: visible_at(k["ts"], t)), 1, m)


def _cut_carried(db: Database, seeds: DataFrame, caps: list[int | None], strategy: Strategy, links: list[tuple[str, bool]] | None, carry: str) -> Slice:
    """Picks from the last hop up, once per node.

    What a stamp sees of a node's children are the m latest of some of the intervals between stamps, so m rows of each
    interval are kept: an array is bounded by m and the number of stamps, however many children a node has.
    """
    chain = [next(x for x in db.links if x.name == name) for name, down in links or [] if down]
    types = [chain[0].parent, *(x.child for x in chain)] if chain else []
    broken = any(a.child != b.parent for a, b in zip(chain, chain[1:])) or len(set(types)) < len(types)
    if not chain or len(chain) != len(links) or len(chain) != len(caps) or broken or strategy.kind != "latest" or None in caps:
        raise ValueError("features are carried by latest picks down a chain of links, a hop for each")
    times = sorted(r["seed_time"] for r in seeds.select("seed_time").distinct().collect())
    stamps_ = F.array(*(F.lit(t.isoformat(" ")).cast("timestamp_ntz") for t in times)).cast("array<timestamp_ntz>")
    kids = None
    for link, m in reversed(list(zip(chain, caps, strict=True))):
        child = db.tables[link.child]
        ts = F.col(child.time).cast("timestamp_ntz") if child.time else F.lit(None).cast("timestamp_ntz")
        rows = child.df.select(F.col(link.fk).cast("bigint").alias("up"), F.col(child.pk).cast("bigint").alias("child"), ts.alias("ts"), F.col(carry).alias("x"))
        # stamps before the row; a row that is later than all of them is never seen
        turn = F.coalesce(F.size(F.filter(stamps_, lambda t: t < F.col("ts"))), F.lit(0))
        rows = rows.filter("up is not null").withColumn("turn", turn).filter(F.col("turn") < len(times))
        if kids is not None:
            rows = rows.join(kids.withColumnRenamed("nid", "child"), "child", "left").repartition("up")
        rows = pick(rows, ["up", "turn"], m, strategy.order(F.col("up"), F.col("ts"), F.col("child"), F.col("ts")))
        # in descending order these are by time, latest first, those without one last, and equal times by key
        one = F.struct("ts", (-F.col("child")).alias("back"), "x", *([] if kids is None else ["kids"]))
        kids = rows.groupBy(F.col("up").alias("nid")).agg(F.sort_array(F.collect_list(one), asc=False).alias("kids"))
    edges, level = [], seeds.select("seed_id", "seed_time", "nid").join(kids, "nid")
    for hop, (link, m) in enumerate(zip(chain, caps, strict=True), 1):
        level = level.select("seed_id", "seed_time", "nid", F.explode(picked_at(F.col("kids"), F.col("seed_time"), m)).alias("k"))
        edges.append(level.select("seed_id", "seed_time", F.lit(hop).alias("hop"), F.lit(link.name).alias("link"), F.lit(link.child).alias("src_type"), (-F.col("k.back")).alias("src"), F.lit(link.parent).alias("dst_type"), F.col("nid").alias("dst"), F.col("k.ts").alias("ts")))
        if hop < len(caps):
            level = level.select("seed_id", "seed_time", (-F.col("k.back")).alias("nid"), F.col("k.kids").alias("kids"))
    return Slice(seeds, reduce(DataFrame.unionByName, edges), kids, tuple(caps))


def printed_filter_leaks(db: Database, link: LinkSpec, frontier: DataFrame) -> DataFrame:
    """Neighbours under the filter that tests the node being expanded; kept to show what it lets through."""
    child = db.tables[link.child]
    side = child.df.select(F.col(link.fk).cast("bigint").alias("nid"), F.col(child.pk).cast("bigint").alias("child"), F.col(child.time).alias("ts"))
    return frontier.filter(visible_at(F.col("node_ts"), F.col("seed_time"))).join(side, "nid")
