"""Other graphs over the same database: hyperedges, shortcuts, pruned and folded edges, placement."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..catalog import Database
from ..functions.columns import draw, prefix_number, visible_at


def hyperedges(db: Database, fact: str) -> DataFrame:
    """One row per fact row: its key and an array of all its pins (type, key); null references are no pins."""
    s = db.tables[fact]
    pins = [F.when(F.col(x.fk).isNotNull(), F.struct(F.lit(x.parent).alias("ntype"), F.col(x.fk).cast("bigint").alias("nid"))) for x in db.links if x.child == fact]
    own = F.struct(F.lit(fact).alias("ntype"), F.col(s.pk).cast("bigint").alias("nid"))
    return s.df.select(F.col(s.pk).alias("edge"), F.array_compact(F.array(own, *pins)).alias("pins"))


def hyper_pass(hyper: DataFrame, state: DataFrame) -> DataFrame:
    """Every pin gets the sum over its hyperedges of the other pins' states.  state: ntype, nid, h."""
    flat = hyper.select("edge", F.explode("pins").alias("p")).select("edge", "p.ntype", "p.nid").join(state, ["ntype", "nid"])
    total = flat.groupBy("edge").agg(F.sum("h").alias("all_"))
    return flat.join(total, "edge").groupBy("ntype", "nid").agg(F.sum(F.col("all_") - F.col("h")).alias("h"))


def shortcut(facts: DataFrame, entity: str, through: str, as_of: Column | None = None, max_degree: int | None = None) -> DataFrame:
    """a, b, n, last_ts: entities tied by rows that refer to the same ``through`` key, in how many pairs of rows, and the
    latest time by which both were there.

    The pairs of one key grow with the square of its degree.  ``max_degree`` leaves out keys above it; without it all
    keys count, and the join is left to skew handling.
    """
    rows = facts.select(entity, through, "ts")
    if as_of is not None:
        rows = rows.filter(visible_at(F.col("ts"), as_of))
    if max_degree is not None:
        rows = rows.join(rows.groupBy(through).count().filter(F.col("count") <= max_degree).select(through), through, "left_semi")
    a = rows.select(F.col(entity).alias("a"), through, F.col("ts").alias("ts_a"))
    b = rows.select(F.col(entity).alias("b"), through, F.col("ts").alias("ts_b"))
    return a.join(b, through).filter("a <> b").groupBy("a", "b").agg(F.count("*").alias("n"), F.max(F.greatest("ts_a", "ts_b")).alias("last_ts"))


def prune_stale(edges: DataFrame, by: list[str], at: Column, max_age: int | None = None, keep_last: int | None = None, tie: str = "src") -> DataFrame:
    """Edges that aren't older than max_age days at the moment, and of each node's the keep_last newest."""
    if max_age is not None:
        edges = edges.filter(F.col("ts").isNull() | (F.col("ts") > at - F.expr(f"interval '{int(max_age)}' day")))
    if keep_last is not None:
        w = Window.partitionBy(*by).orderBy(F.col("ts").desc_nulls_last(), tie)
        edges = edges.withColumn("rank_", F.row_number().over(w)).filter(F.col("rank_") <= keep_last).drop("rank_")
    return edges


def fold_stale(edges: DataFrame, by: list[str], value: Column, at: Column, max_age: int) -> DataFrame:
    """by, kind, n, total, lo, hi: younger rows as they are, and the older ones of each node as one summary row."""
    old = F.col("ts") <= at - F.expr(f"interval '{int(max_age)}' day")
    seen = edges.filter(visible_at(F.col("ts"), at)).withColumn("value_", value.cast("decimal(18,2)"))
    young = seen.filter(~old).select(*by, F.lit("row").alias("kind"), F.lit(1).cast("bigint").alias("n"), F.col("value_").cast("double").alias("total"), F.col("ts").alias("lo"), F.col("ts").alias("hi"))
    folded = seen.filter(old).groupBy(*by).agg(F.count("*").alias("n"), F.sum("value_").cast("double").alias("total"), F.min("ts").alias("lo"), F.max("ts").alias("hi"))
    return young.unionByName(folded.select(*by, F.lit("folded").alias("kind"), "n", "total", "lo", "hi"))


def part_of(table: str, key: Column, parts: int) -> Column:
    return F.pmod(prefix_number(draw(F.lit(table), key)), F.lit(parts))


def cut_edges(db: Database, child: str, layouts: list[tuple[str, int] | None], parts: int = 16) -> DataFrame:
    """layout, link, n_cut, n_edges: references of ``child`` whose two rows lie in different parts, for each link.

    Parents are dealt by their own keys.  A layout deals children by their own key (None) or beside the parent that a
    reference names, (column, n): with n > 1 each parent's children go to n parts, which a hot parent may need.  One scan.
    """
    spec, links = db.tables[child], [x for x in db.links if x.child == child]
    out = []
    for layout in layouts:
        if layout is None:
            name, at = "by key", part_of(child, F.col(spec.pk), parts)
        else:
            fk, n = layout
            parent = next(x.parent for x in links if x.fk == fk)
            key = F.col(fk) if n == 1 else F.concat_ws("|", F.col(fk), F.pmod(F.col(spec.pk), F.lit(n)))
            name, at = f"by {fk}" + (f" in {n}" if n > 1 else ""), part_of(parent, key, parts)
        for x in links:
            there = F.col(x.fk).isNotNull()
            out.append(F.struct(F.lit(name).alias("layout"), F.lit(x.fk).alias("link"), F.count(F.when(there & (at != part_of(x.parent, F.col(x.fk), parts)), 1)).alias("n_cut"), F.count(F.when(there, 1)).alias("n_edges")))
    return spec.df.agg(F.array(*out).alias("rows")).select(F.inline("rows"))


def write_clustered(db: Database, child: str, by: str, path: str, parts: int) -> None:
    """Writes a fact table with rows of one parent side by side, sorted by parent and time."""
    s = db.tables[child]
    s.df.repartition(parts, by).sortWithinPartitions(by, *([s.time] if s.time else [])).write.mode("overwrite").parquet(path)


def split_columns(db: Database, name: str) -> tuple[DataFrame, DataFrame]:
    """Keys and time apart from attributes, so that sampling never touches the latter."""
    s = db.tables[name]
    keys = [s.pk, *(x.fk for x in db.links if x.child == name and x.fk != s.pk), *([s.time] if s.time else [])]
    return s.df.select(*keys), s.df.select(s.pk, *(c for c in s.df.columns if c not in keys))
