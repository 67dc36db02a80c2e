"""Message passing as joins and aggregates."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .sampling import Slice

POOLS: dict[str, Callable[[Column], Column]] = {
    "sum": F.sum,
    "max": F.max,
    "min": F.min,
    "count": F.count,
    "mean": lambda c: F.sum(c).cast("double") / F.count(c),
}


def pool(messages: DataFrame, dst: list[str], cols: list[str], kinds: list[str]) -> DataFrame:
    """One column per pool and value, named ``<value>_<pool>`` (or ``<value>`` for a single pool)."""
    one = len(kinds) == 1
    return messages.groupBy(*dst).agg(*(POOLS[k](F.col(c)).alias(c if one else f"{c}_{k}") for c in cols for k in kinds))


def pass_plain(state: DataFrame, edges: DataFrame, transform: Callable[[Column], Column], update: Callable[[Column, Column], Column], kind: str = "sum") -> DataFrame:
    """One round on one type: own state and pooled transformed neighbours.  state: nid, h*; edges: src, dst."""
    cols = [c for c in state.columns if c != "nid"]
    sent = edges.join(state.withColumnRenamed("nid", "src"), "src").select("dst", *(transform(F.col(c)).alias(c) for c in cols))
    got = pool(sent, ["dst"], cols, [kind]).select(F.col("dst").alias("nid"), *(F.col(c).alias(f"in_{c}") for c in cols))
    return state.join(got, "nid", "left").select("nid", *(update(F.col(c), F.coalesce(F.col(f"in_{c}"), F.lit(0))).alias(c) for c in cols))


def pass_typed(
    state: DataFrame,
    messages: list[tuple[DataFrame, Callable[[Column], Column]]],
    keys: list[str],
    kind: str = "sum",
    outer: str = "sum",
    weights: list[float] | None = None,
) -> DataFrame:
    """A round into one node type: per-link transform and pool, pool over links, then own state added.

    ``messages`` has for each link rows (keys, h*) at the destination, and its transform.  Links without a message to a
    node count as zero.  ``weights`` weigh links, for pooling that knows the schema.
    """
    cols = [c for c in state.columns if c not in keys]
    parts = []
    for i, (rows, transform) in enumerate(messages):
        w = F.lit(1 if weights is None else weights[i])
        sent = rows.select(*keys, *(transform(F.col(c)).alias(c) for c in cols))
        parts.append(pool(sent, keys, cols, [kind]).select(*keys, *((F.col(c) * w).alias(c) for c in cols)))
    if outer == "concat":
        out = state
        for i, p in enumerate(parts):
            out = out.join(p.select(*keys, *(F.col(c).alias(f"{c}_{i}") for c in cols)), keys, "left")
        return out.na.fill(0)
    joined = pool(reduce(DataFrame.unionByName, parts), keys, cols, [outer])
    both = state.join(joined.select(*keys, *(F.col(c).alias(f"in_{c}") for c in cols)), keys, "left")
    return both.select(*keys, *((F.col(c) + F.coalesce(F.col(f"in_{c}"), F.lit(0))).alias(c) for c in cols))


def join_aggregate(parent: DataFrame, key: str, child: DataFrame, fk: str, aggs: list[Column], early: bool = True) -> DataFrame:
    """A round without learnt parts: the query that joins and groups.

    ``early`` groups the child by its reference first and joins one row per key, which a decomposable aggregate allows.
    """
    if early:
        return parent.select(key).join(child.groupBy(F.col(fk).alias(key)).agg(*aggs), key, "left")
    return parent.select(key).join(child.withColumnRenamed(fk, key), key, "left").groupBy(key).agg(*aggs)


def join_aggregate_path(rows: DataFrame, key: str, sums: list[str], path: list[tuple[DataFrame, str, str]]) -> DataFrame:
    """Sums and the number of ``rows`` over several links: path has (table, its key, its reference to the next table).

    Rows are added up by the reference before every join, so no join is larger than the tables.
    """
    at = rows.groupBy(key).agg(F.count("*").alias("n"), *(F.sum(c).alias(c) for c in sums))
    for parent, pk, fk in path:
        met = at.join(parent.select(F.col(pk).alias(key), F.col(fk).alias("next_")), key)
        key = fk
        at = met.withColumnRenamed("next_", key).groupBy(key).agg(*(F.sum(c).alias(c) for c in ("n", *sums)))
    return at


def run_passes(cut: Slice, states: dict[str, DataFrame], rounds: int | None = None, kind: str = "sum", whole: bool = False) -> DataFrame:
    """seed_id, nid and the seeds' states after the rounds.  ``states`` has for each type (nid, h*).

    Layered (as many rounds as hops, from the outermost in): a row at hop k hears from its rows at hop k + 1.  With
    ``whole`` every row of the slice hears from all its edges in every of ``rounds`` rounds, which a row met at several
    hops does once.  A row's new state is its own and what it hears.
    """
    cols = [c for c in next(iter(states.values())).columns if c != "nid"]
    everyone = reduce(DataFrame.unionByName, [df.select(F.lit(t).alias("ntype"), "nid", *cols) for t, df in states.items()])
    edges = cut.edges.select("seed_id", "hop", "link", "src_type", "src", "dst_type", "dst")
    hops = rounds if whole else edges.agg(F.max("hop")).first()[0] or 0
    keys = ["seed_id", "ntype", "nid"]

    def heard(state: DataFrame, over: DataFrame) -> DataFrame:
        sent = over.join(state.select("seed_id", F.col("ntype").alias("src_type"), F.col("nid").alias("src"), *cols), ["seed_id", "src_type", "src"])
        by_link = pool(sent, ["seed_id", "dst_type", "dst", "link"], cols, [kind])
        return by_link.groupBy("seed_id", F.col("dst_type").alias("ntype"), F.col("dst").alias("nid")).agg(*(F.sum(c).alias(f"in_{c}") for c in cols))

    def updated(state: DataFrame, got: DataFrame) -> DataFrame:
        return state.join(got, keys, "left").select(*keys, *((F.col(c) + F.coalesce(F.col(f"in_{c}"), F.lit(0))).alias(c) for c in cols))

    seeds = cut.seeds.select(*keys)
    if whole:
        state = cut.nodes.select(*keys).join(everyone, ["ntype", "nid"]).select(*keys, *cols)
        over = edges.drop("hop").distinct()
        for _ in range(hops):
            state = updated(state, heard(state, over))
        return state.join(seeds, keys, "left_semi")
    state = None
    for hop in range(hops, -1, -1):
        here = seeds if hop == 0 else edges.filter(F.col("hop") == hop).select("seed_id", F.col("src_type").alias("ntype"), F.col("src").alias("nid")).distinct()
        own = here.join(everyone, ["ntype", "nid"]).select(*keys, *cols)
        state = own if state is None else updated(own, heard(state, edges.filter(F.col("hop") == hop + 1)))
    return state


# pools that know the order of rows


def pool_trend(rows: DataFrame, by: str, value: Column, at: Column) -> DataFrame:
    """slope of the value over time, by least squares, and together, their correlation."""
    return rows.groupBy(by).agg(F.regr_slope(value, at).alias("slope"), F.corr(value, at).alias("together"))


def pool_position(rows: DataFrame, by: str, value: Column, order: list[Column], m: int) -> DataFrame:
    """Sum of the first m values in order, the r-th divided by r.  The cap is part of the window, as in sampling."""
    ranked = rows.withColumn("rank_", F.row_number().over(Window.partitionBy(by).orderBy(*order))).filter(F.col("rank_") <= m)
    return ranked.groupBy(by).agg(F.sum(value / F.col("rank_")).alias("weighted"))


def pool_decay(rows: DataFrame, by: str, value: Column, ts: Column, at: Column, half_life: float) -> DataFrame:
    """Sum of values that halve with each half_life days of age."""
    age = F.datediff(at, ts).cast("double")
    return rows.groupBy(by).agg(F.sum(value * F.exp(-F.lit(0.6931471805599453) * age / half_life)).alias("decayed"))


def pool_last(rows: DataFrame, by: str, value: str, order: list[str]) -> DataFrame:
    """Value of the last row in order."""
    return rows.groupBy(by).agg(F.max(F.struct(*order, value)).alias("m")).select(by, F.col(f"m.{value}").alias("last"))


def pool_fold(rows: DataFrame, by: str, value: str, order: list[str], keep: float = 0.5) -> DataFrame:
    """A recurrence over the rows in order: state = keep * state + value."""
    items = F.array_sort(F.collect_list(F.struct(*order, value)))
    step = F.aggregate(items, F.lit(0.0), lambda s, x: s * keep + x[value].cast("double"))
    return rows.groupBy(by).agg(step.alias("folded"))


def as_of_last(left: DataFrame, right: DataFrame, by: str, t: str, ts: str, cols: list[str]) -> DataFrame:
    """For each left row the last right row at or before its time: both put in one order, then the last value seen."""
    w = Window.partitionBy(by).orderBy("t_", "side_", *[f"r_{c}" for c in cols]).rowsBetween(Window.unboundedPreceding, 0)
    a = left.select(by, F.col(t).alias("t_"), F.lit(1).alias("side_"), *(F.lit(None).cast(dict(right.dtypes)[c]).alias(f"r_{c}") for c in cols), F.lit(None).cast("timestamp_ntz").alias("r_ts"))
    b = right.select(by, F.col(ts).alias("t_"), F.lit(0).alias("side_"), *(F.col(c).alias(f"r_{c}") for c in cols), F.col(ts).alias("r_ts"))
    both = a.unionByName(b)
    seen = both.select(by, "t_", "side_", *(F.last(f"r_{c}", ignorenulls=True).over(w).alias(c) for c in [*cols, "ts"]))
    return seen.filter("side_ = 1").select(by, F.col("t_").alias(t), *cols, F.col("ts").alias("last_ts"))
