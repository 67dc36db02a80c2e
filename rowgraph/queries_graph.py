"""Queries on variants of the graph, samplers, and message passing."""

from __future__ import annotations

from datetime import datetime

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.columns import visible_at
from .operators import passing, sampling, variants
from .operators.graph import edge_view
from .plans import tasks, timeline, workloads
from .registry import BOUGHT, LINES, YEAR, registry
from .sources.datasets import keyed_lines, open_retail, purchases, table

QUERIES, ORACLE, query = registry()
S = SparkSession
T_TEST = datetime(2000, 7, 1)
AT = "TIMESTAMP '2000-07-01'"


def _at() -> F.Column:
    return F.lit(T_TEST).cast("timestamp_ntz")


# ------------------------------------------------------------------------------------ variants


@query("hyperedges", f"WITH {LINES} SELECT l_id AS edge, 'lineitem:' || l_id || '|orders:' || l_orderkey || '|part:' || l_partkey || '|supplier:' || l_suppkey AS pins, 4 AS n_pins FROM li")
def hyperedges(spark: S, d: str) -> DataFrame:
    h = variants.hyperedges(open_retail(spark, d), "lineitem")
    return h.select("edge", F.array_join(F.transform("pins", lambda p: F.concat_ws(":", p.ntype, p.nid.cast("string"))), "|").alias("pins"), F.size("pins").alias("n_pins"))


@query(
    "copurchase_pairs",
    f"""WITH {BOUGHT}, p AS (SELECT c_custkey, p_partkey, ts FROM bought WHERE ts <= {AT})
SELECT a.c_custkey AS a, b.c_custkey AS b, count(*) AS n, max(greatest(a.ts, b.ts)) AS last_ts FROM p a JOIN p b ON a.p_partkey = b.p_partkey AND a.c_custkey <> b.c_custkey
GROUP BY ALL HAVING count(*) >= 4""",
)
def copurchase_pairs(spark: S, d: str) -> DataFrame:
    return variants.shortcut(purchases(spark, d), "c_custkey", "p_partkey", _at()).filter("n >= 4")


@query(
    "stale_pruned",
    f"""SELECT o_custkey AS dst, o_orderkey AS src, o_orderdate AS ts FROM orders WHERE o_orderdate <= {AT} AND o_orderdate > {AT} - INTERVAL 730 DAY
QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate DESC, o_orderkey) <= 3""",
)
def stale_pruned(spark: S, d: str) -> DataFrame:
    edges = table(spark, d, "orders").select(F.col("o_custkey").alias("dst"), F.col("o_orderkey").alias("src"), F.col("o_orderdate").alias("ts")).filter(F.col("ts") <= _at())
    return variants.prune_stale(edges, ["dst"], _at(), 730, 3)


@query(
    "stale_folded",
    f"""WITH e AS (SELECT o_custkey AS dst, o_orderdate AS ts, CAST(o_totalprice AS DECIMAL(18,2)) AS v, o_orderdate <= {AT} - INTERVAL 730 DAY AS old FROM orders WHERE o_orderdate <= {AT})
SELECT dst, 'row' AS kind, 1::BIGINT AS n, CAST(v AS DOUBLE) AS total, ts AS lo, ts AS hi FROM e WHERE NOT old
UNION ALL SELECT dst, 'folded', count(*), CAST(sum(v) AS DOUBLE), min(ts), max(ts) FROM e WHERE old GROUP BY dst""",
)
def stale_folded(spark: S, d: str) -> DataFrame:
    edges = table(spark, d, "orders").select(F.col("o_custkey").alias("dst"), F.col("o_orderdate").alias("ts"), "o_totalprice")
    return variants.fold_stale(edges, ["dst"], F.col("o_totalprice"), _at(), 730)


_PART = "('0x' || substr(md5('{t}|' || {k}), 1, 13))::BIGINT % 16"


@query(
    "cut_edges",
    f"""WITH {LINES}, p AS (SELECT l_id, l_orderkey, {_PART.format(t='lineitem', k='l_id')} AS own, {_PART.format(t='orders', k='l_orderkey')} AS o, {_PART.format(t='part', k='l_partkey')} AS p,
  {_PART.format(t='supplier', k='l_suppkey')} AS s, {_PART.format(t='supplier', k="l_suppkey || '|' || (l_id % 4)")} AS salted FROM li),
x AS (SELECT 'by key' AS layout, own AS here, * FROM p UNION ALL SELECT 'by l_orderkey', o, * FROM p UNION ALL SELECT 'by l_partkey', p, * FROM p UNION ALL SELECT 'by l_suppkey in 4', salted, * FROM p)
SELECT layout, 'l_orderkey' AS link, count(*) FILTER (here <> o) AS n_cut, count(*) AS n_edges FROM x GROUP BY layout
UNION ALL SELECT layout, 'l_partkey', count(*) FILTER (here <> p), count(*) FROM x GROUP BY layout
UNION ALL SELECT layout, 'l_suppkey', count(*) FILTER (here <> s), count(*) FROM x GROUP BY layout""",
)
def cut_edges(spark: S, d: str) -> DataFrame:
    """Lines dealt by their own key, beside a parent, and beside a hot parent in four parts: references of every link cut."""
    return variants.cut_edges(open_retail(spark, d), "lineitem", [None, ("l_orderkey", 1), ("l_partkey", 1), ("l_suppkey", 4)])


# ------------------------------------------------------------------------------------ sampling

#: Seeds: customers of the churn task's test split.
SEEDS = f"""seeds AS (SELECT DISTINCT o_custkey || '|2000-07-01' AS seed_id, {AT} AS seed_time, o_custkey AS nid FROM orders JOIN lineitem ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey
 WHERE o_orderdate <= {AT} AND o_orderdate > {AT} - INTERVAL 365 DAY)"""


def seeds(spark: S, d: str) -> DataFrame:
    near = purchases(spark, d).filter((F.col("ts") <= _at()) & (F.col("ts") > _at() - F.expr("interval '365' day")))
    task = near.select("c_custkey").distinct().withColumn("seed_time", _at())
    return sampling.seeds_of(task, "c_custkey", "customer")


def _picks(order: str, m: int) -> str:
    return f"""WITH c AS (SELECT DISTINCT o_custkey FROM orders), e AS (SELECT o_custkey AS dst, o_orderkey AS src, o_orderdate AS ts, md5('s1|' || o_custkey || '|2000-07-01|' || o_orderkey) AS h,
  (('0x' || substr(md5('s1|' || o_custkey || '|2000-07-01|' || o_orderkey), 1, 13))::BIGINT + 0.5::DOUBLE) / {float(16**13)!r}::DOUBLE AS u FROM orders WHERE o_orderdate <= {AT})
SELECT dst, src FROM e QUALIFY row_number() OVER (PARTITION BY dst ORDER BY {order}) <= {m}"""


def _sampled(spark: S, d: str, strategy: sampling.Strategy) -> DataFrame:
    db = open_retail(spark, d)
    everyone = sampling.seeds_of(table(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey")).distinct().withColumn("seed_time", _at()), "c_custkey", "customer")
    return sampling.cut_slice(db, everyone, [4], strategy, [("orders.o_custkey", True)]).edges.select("dst", "src")


@query("neigh_at_t", f"SELECT o_custkey AS dst, o_orderkey AS src, o_orderdate AS ts FROM orders WHERE o_orderdate <= {AT}")
def neigh_at_t(spark: S, d: str) -> DataFrame:
    db = open_retail(spark, d)
    everyone = table(spark, d, "customer").select(F.col("c_custkey").alias("nid"), _at().alias("seed_time"))
    link = next(x for x in db.links if x.name == "orders.o_custkey")
    return sampling.neighbours(db, link, everyone).select(F.col("nid").alias("dst"), F.col("child").alias("src"), "ts")


@query("sample_uniform", _picks("h, src", 4))
def sample_uniform(spark: S, d: str) -> DataFrame:
    return _sampled(spark, d, sampling.Strategy("uniform"))


@query("sample_latest", _picks("ts DESC, src", 4))
def sample_latest(spark: S, d: str) -> DataFrame:
    return _sampled(spark, d, sampling.Strategy("latest"))


@query("sample_biased", _picks(f"-ln(u) / exp(-0.6931471805599453::DOUBLE * date_diff('day', ts, {AT}) / 365.0::DOUBLE), src", 4))
def sample_biased(spark: S, d: str) -> DataFrame:
    return _sampled(spark, d, sampling.Strategy("recency", half_life=365.0))


@query("sample_anchor", _picks("-ln(u) / greatest(1e-6::DOUBLE, exp(-abs(date_diff('day', TIMESTAMP '1999-07-01', ts)) / 30.0::DOUBLE)), src", 4))
def sample_anchor(spark: S, d: str) -> DataFrame:
    return _sampled(spark, d, sampling.Strategy("anchors", moments=(datetime(1999, 7, 1),), width=30.0))


_TWO = [("orders.o_custkey", True), ("lineitem.l_orderkey", True)]
_HOPS = f"""WITH {LINES}, {SEEDS},
h1 AS (SELECT seed_id, o_orderkey AS src, nid AS dst, o_orderdate AS ts FROM seeds JOIN orders ON o_custkey = nid WHERE o_orderdate <= seed_time
 QUALIFY row_number() OVER (PARTITION BY seed_id, nid ORDER BY o_orderdate DESC, o_orderkey) <= 8),
h2 AS (SELECT h1.seed_id, l_id AS src, h1.src AS dst, l_shipdate AS ts FROM h1 JOIN li ON l_orderkey = h1.src WHERE l_shipdate <= {AT}
 QUALIFY row_number() OVER (PARTITION BY h1.seed_id, h1.src ORDER BY l_shipdate DESC, l_id) <= 4)"""


def two_hops(spark: S, d: str, strategy: sampling.Strategy | None = None, **more) -> sampling.Slice:
    return sampling.cut_slice(open_retail(spark, d, T_TEST), seeds(spark, d), [8, 4], strategy or sampling.Strategy("latest"), _TWO, **more)


@query("slice_2hop_edges", _HOPS + " SELECT seed_id, 1 AS hop, 'orders.o_custkey' AS link, src, dst FROM h1 UNION ALL SELECT seed_id, 2, 'lineitem.l_orderkey', src, dst FROM h2")
def slice_2hop_edges(spark: S, d: str) -> DataFrame:
    return two_hops(spark, d).edges.select("seed_id", "hop", "link", "src", "dst")


@query("slice_2hop_nodes", _HOPS + " SELECT seed_id, 'customer' AS ntype, nid, 0 AS hop FROM seeds UNION ALL SELECT DISTINCT seed_id, 'orders', src, 1 FROM h1 UNION ALL SELECT DISTINCT seed_id, 'lineitem', src, 2 FROM h2")
def slice_2hop_nodes(spark: S, d: str) -> DataFrame:
    return two_hops(spark, d).nodes


@query("receptive_size", _HOPS + ", n AS (SELECT seed_id, count(*) AS n FROM (SELECT seed_id, src, 1 FROM h1 UNION SELECT seed_id, src, 2 FROM h2) GROUP BY seed_id) SELECT count(*) AS n_seeds, max(n) AS largest, sum(n)::BIGINT AS total, 40 AS bound FROM n")
def receptive_size(spark: S, d: str) -> DataFrame:
    from .operators.graph import receptive_bound

    sizes = two_hops(spark, d).sizes().filter("n_nodes > 0")
    return sizes.agg(F.count("*").alias("n_seeds"), F.max("n_nodes").alias("largest"), F.sum("n_nodes").alias("total"), F.lit(receptive_bound([8, 4])).alias("bound"))


@query(
    "slice_linkcap",
    f"""WITH {LINES}, {SEEDS},
h1 AS (SELECT seed_id, 'orders.o_custkey' AS link, o_orderkey AS src, 'orders' AS st, nid AS dst FROM seeds JOIN orders ON o_custkey = nid WHERE o_orderdate <= {AT} QUALIFY row_number() OVER (PARTITION BY seed_id, nid ORDER BY o_orderdate DESC, o_orderkey) <= 3
 UNION ALL SELECT seed_id, 'customer.c_nationkey^', c_nationkey, 'nation', nid FROM seeds JOIN customer ON c_custkey = nid),
f AS (SELECT DISTINCT seed_id, st, src AS nid FROM h1),
h2 AS (SELECT seed_id, 'lineitem.l_orderkey' AS link, l_id AS src, nid AS dst FROM f JOIN li ON st = 'orders' AND l_orderkey = nid WHERE l_shipdate <= {AT} QUALIFY row_number() OVER (PARTITION BY seed_id, nid ORDER BY l_shipdate DESC, l_id) <= 2
 UNION ALL SELECT seed_id, 'orders.o_custkey^', o_custkey, nid FROM f JOIN orders ON st = 'orders' AND o_orderkey = nid
 UNION ALL SELECT seed_id, 'customer.c_nationkey', c_custkey, nid FROM f JOIN customer ON st = 'nation' AND c_nationkey = nid QUALIFY row_number() OVER (PARTITION BY seed_id, nid ORDER BY c_custkey) <= 2
 UNION ALL SELECT seed_id, 'supplier.s_nationkey', s_suppkey, nid FROM f JOIN supplier ON st = 'nation' AND s_nationkey = nid QUALIFY row_number() OVER (PARTITION BY seed_id, nid ORDER BY s_suppkey) <= 2
 UNION ALL SELECT seed_id, 'nation.n_regionkey^', n_regionkey, nid FROM f JOIN nation ON st = 'nation' AND n_nationkey = nid)
SELECT seed_id, 1 AS hop, link, src, dst FROM h1 UNION ALL SELECT seed_id, 2, link, src, dst FROM h2""",
)
def slice_linkcap(spark: S, d: str) -> DataFrame:
    cut = sampling.cut_slice(open_retail(spark, d, T_TEST), seeds(spark, d), [3, 2], sampling.Strategy("latest"), cap_scope="link")
    return cut.edges.select("seed_id", "hop", "link", "src", "dst")


@query(
    "slice_shared",
    f"""WITH {LINES}, {SEEDS},
h1 AS (SELECT seed_id, o_orderkey AS src, nid AS dst FROM seeds JOIN orders ON o_custkey = nid WHERE o_orderdate <= {AT}
 QUALIFY row_number() OVER (PARTITION BY seed_id, nid ORDER BY md5('s1|' || nid || '|2000-07-01|' || o_orderkey), o_orderkey) <= 8),
p AS (SELECT l_orderkey AS dst, l_id AS src FROM li WHERE l_shipdate <= {AT} QUALIFY row_number() OVER (PARTITION BY l_orderkey ORDER BY md5('s1|' || l_orderkey || '|2000-07-01|' || l_id), l_id) <= 4)
SELECT seed_id, 1 AS hop, src, dst FROM h1 UNION ALL SELECT h1.seed_id, 2, p.src, p.dst FROM h1 JOIN p ON p.dst = h1.src""",
)
def slice_shared(spark: S, d: str) -> DataFrame:
    return two_hops(spark, d, sampling.Strategy("uniform"), share=True).edges.select("seed_id", "hop", "src", "dst")


@query("leak_audit", f"WITH n AS (SELECT * FROM (VALUES (1), (2)) v(hop)) SELECT hop, 0::BIGINT AS n_leaks FROM n")
def leak_audit(spark: S, d: str) -> DataFrame:
    return tasks.audit_leaks(two_hops(spark, d).edges, by=["hop"]).select("hop", "n_leaks")


@query(
    "leak_parent_future",
    f"""SELECT count(*) AS n_rows, count(*) FILTER (l_shipdate > {AT}) AS n_leaks FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE o_orderdate <= {AT}""",
)
def leak_parent_future(spark: S, d: str) -> DataFrame:
    """What the filter on the expanded node lets through: lines that ship after the seed time."""
    db = open_retail(spark, d)
    link = next(x for x in db.links if x.name == "lineitem.l_orderkey")
    frontier = table(spark, d, "orders").select(F.col("o_orderkey").alias("nid"), F.col("o_orderdate").alias("node_ts"), _at().alias("seed_time"))
    return tasks.audit_leaks(sampling.printed_filter_leaks(db, link, frontier))


@query("leak_parent_unseen", f"SELECT count(*) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE l_shipdate <= {AT} AND o_orderdate > {AT}")
def leak_parent_unseen(spark: S, d: str) -> DataFrame:
    """Lines that are visible while their order is not yet."""
    db = open_retail(spark, d)
    link = next(x for x in db.links if x.name == "lineitem.l_orderkey")
    seen, parents = db.visible(T_TEST)["lineitem"], db.visible(T_TEST)["orders"]
    return seen.select(F.col(link.fk).alias("o_orderkey")).join(parents.select("o_orderkey"), "o_orderkey", "left_anti").agg(F.count("*").alias("n"))


@query(
    "pack_slices",
    _HOPS
    + """, e AS (SELECT seed_id, 1 AS hop, dst, src, ts FROM h1 UNION ALL SELECT seed_id, 2, dst, src, ts FROM h2)
SELECT seeds.seed_id, seeds.nid, count(src) AS n_edges, coalesce(string_agg(hop || ':' || dst || '<' || src || '@' || strftime(ts, '%Y-%m-%d'), ' ' ORDER BY hop, dst, src), '') AS edges FROM seeds LEFT JOIN e USING (seed_id) GROUP BY ALL""",
)
def pack_slices(spark: S, d: str) -> DataFrame:
    """One row per seed with its edges in order, written out."""
    packed = two_hops(spark, d).pack().withColumn("edges", F.coalesce("edges", F.array()))
    said = F.transform("edges", lambda e: F.concat(e.hop.cast("string"), F.lit(":"), e.dst.cast("string"), F.lit("<"), e.src.cast("string"), F.lit("@"), F.date_format(e.ts, "yyyy-MM-dd")))
    return packed.select("seed_id", "nid", F.size("edges").cast("bigint").alias("n_edges"), F.array_join(said, " ").alias("edges"))


# ------------------------------------------------------------------------------------ passes

_SEG = "CASE c_mktsegment WHEN 'AUTOMOBILE' THEN 0 WHEN 'BUILDING' THEN 1 WHEN 'FURNITURE' THEN 2 WHEN 'HOUSEHOLD' THEN 3 ELSE 4 END"


def states(spark: S, d: str, upto: bool = True) -> dict[str, DataFrame]:
    """Two whole numbers per row, so that sums are exact whatever their order."""
    db = open_retail(spark, d)
    db = db.visible(T_TEST) if upto else db
    seg = F.array_position(F.array(*(F.lit(x) for x in ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD"))), F.col("c_mktsegment")).cast("bigint")
    return {
        "customer": db["customer"].select(F.col("c_custkey").alias("nid"), F.floor("c_acctbal").cast("bigint").alias("h0"), F.when(seg > 0, seg - 1).otherwise(4).cast("bigint").alias("h1")),
        "orders": db["orders"].select(F.col("o_orderkey").alias("nid"), F.floor("o_totalprice").cast("bigint").alias("h0"), F.lit(1).cast("bigint").alias("h1")),
        "lineitem": db["lineitem"].select(F.col("l_id").alias("nid"), F.floor("l_quantity").cast("bigint").alias("h0"), F.lit(1).cast("bigint").alias("h1")),
    }


_C0 = f"c0 AS (SELECT c_custkey AS nid, floor(c_acctbal)::BIGINT AS h0, ({_SEG})::BIGINT AS h1 FROM customer)"
_O0 = f"o0 AS (SELECT o_orderkey AS nid, o_custkey AS up, floor(o_totalprice)::BIGINT AS h0, 1::BIGINT AS h1 FROM orders WHERE o_orderdate <= {AT})"
_L0 = f"l0 AS (SELECT l_orderkey AS up, floor(l_quantity)::BIGINT AS h0, 1::BIGINT AS h1 FROM lineitem WHERE l_shipdate <= {AT})"


@query(
    "mp_plain",
    f"""WITH {BOUGHT}, {_C0}, p AS (SELECT c_custkey, p_partkey FROM bought WHERE ts <= {AT} AND ts > {AT} - INTERVAL 30 DAY),
e AS (SELECT DISTINCT a.c_custkey AS src, b.c_custkey AS dst FROM p a JOIN p b USING (p_partkey) WHERE a.c_custkey <> b.c_custkey),
m AS (SELECT dst, sum(2 * h0) AS h0, sum(2 * h1) AS h1 FROM e JOIN c0 ON src = nid GROUP BY dst)
SELECT nid, (c0.h0 + coalesce(m.h0, 0))::BIGINT AS h0, (c0.h1 + coalesce(m.h1, 0))::BIGINT AS h1 FROM c0 LEFT JOIN m ON dst = nid""",
)
def mp_plain(spark: S, d: str) -> DataFrame:
    """One type: customers hear from customers who lately bought the same part."""
    near = purchases(spark, d).filter((F.col("ts") <= _at()) & (F.col("ts") > _at() - F.expr("interval '30' day")))
    edges = variants.shortcut(near, "c_custkey", "p_partkey").select(F.col("a").alias("src"), F.col("b").alias("dst"))
    return passing.pass_plain(states(spark, d)["customer"], edges, lambda c: 2 * c, lambda own, got: own + got)


def _typed(pool_sql: str) -> str:
    return f"""WITH {_C0}, {_O0}, {_L0}, u AS (SELECT up AS nid, {pool_sql.format(h='2 * h0')} AS h0, {pool_sql.format(h='2 * h1')} AS h1 FROM l0 GROUP BY up),
v AS (SELECT o0.nid, {pool_sql.format(h='c0.h0')} AS h0, {pool_sql.format(h='c0.h1')} AS h1 FROM o0 JOIN c0 ON c0.nid = o0.up GROUP BY o0.nid)
SELECT o0.nid, o0.h0 + coalesce(u.h0, 0) + coalesce(v.h0, 0) AS h0, o0.h1 + coalesce(u.h1, 0) + coalesce(v.h1, 0) AS h1 FROM o0 LEFT JOIN u ON u.nid = o0.nid LEFT JOIN v ON v.nid = o0.nid"""


def _typed_pass(spark: S, d: str, kind: str, weights: list[float] | None = None) -> DataFrame:
    h, db = states(spark, d), open_retail(spark, d).visible(T_TEST)
    lines = db["lineitem"].select(F.col("l_id").alias("src"), F.col("l_orderkey").alias("nid")).join(h["lineitem"].withColumnRenamed("nid", "src"), "src").drop("src")
    owners = db["orders"].select(F.col("o_orderkey").alias("nid"), F.col("o_custkey").alias("src")).join(h["customer"].withColumnRenamed("nid", "src"), "src").drop("src")
    return passing.pass_typed(h["orders"], [(lines, lambda c: 2 * c), (owners, lambda c: c)], ["nid"], kind, weights=weights)


@query("mp_typed_sum", _typed("sum({h})::BIGINT"))
def mp_typed_sum(spark: S, d: str) -> DataFrame:
    return _typed_pass(spark, d, "sum")


@query("mp_typed_mean", _typed("sum({h})::DOUBLE / count(*)"))
def mp_typed_mean(spark: S, d: str) -> DataFrame:
    return _typed_pass(spark, d, "mean")


@query("mp_typed_max", _typed("max({h})"))
def mp_typed_max(spark: S, d: str) -> DataFrame:
    return _typed_pass(spark, d, "max")


@query("pool_schema", _typed("sum({h})::BIGINT").replace("coalesce(u.h0, 0)", "3 * coalesce(u.h0, 0)").replace("coalesce(u.h1, 0)", "3 * coalesce(u.h1, 0)"))
def pool_schema(spark: S, d: str) -> DataFrame:
    """Links weighed by the schema: lines count three times as much as owners."""
    return _typed_pass(spark, d, "sum", [3, 1])


@query(
    "mp_temporal_2l",
    _HOPS
    + f""", {_C0}, {_O0}, l1 AS (SELECT l_id AS nid, floor(l_quantity)::BIGINT AS h0, 1::BIGINT AS h1 FROM li),
m2 AS (SELECT h2.seed_id, h2.dst, sum(2 * h0) AS h0, sum(2 * h1) AS h1 FROM h2 JOIN l1 ON l1.nid = h2.src GROUP BY ALL),
s1 AS (SELECT h1.seed_id, h1.src, o0.h0 + coalesce(m2.h0, 0) AS h0, o0.h1 + coalesce(m2.h1, 0) AS h1 FROM h1 JOIN o0 ON o0.nid = h1.src LEFT JOIN m2 ON m2.seed_id = h1.seed_id AND m2.dst = h1.src),
m1 AS (SELECT seed_id, sum(2 * h0) AS h0, sum(2 * h1) AS h1 FROM s1 GROUP BY seed_id)
SELECT seed_id, (c0.h0 + coalesce(m1.h0, 0))::BIGINT AS h0, (c0.h1 + coalesce(m1.h1, 0))::BIGINT AS h1 FROM seeds JOIN c0 ON c0.nid = seeds.nid LEFT JOIN m1 USING (seed_id)""",
)
def mp_temporal_2l(spark: S, d: str) -> DataFrame:
    """Two layers over the slice, outer hop first."""
    h, cut = states(spark, d), two_hops(spark, d)
    keys = ["seed_id", "nid"]
    hop = lambda k: cut.edges.filter(F.col("hop") == k)
    outer = hop(2).join(h["lineitem"].withColumnRenamed("nid", "src"), "src").select("seed_id", F.col("dst").alias("nid"), "h0", "h1")
    middle = hop(1).select("seed_id", F.col("src").alias("nid")).join(h["orders"], "nid")
    middle = passing.pass_typed(middle.select("seed_id", "nid", "h0", "h1"), [(outer, lambda c: 2 * c)], keys)
    inner = hop(1).select("seed_id", F.col("src").alias("nid"), "dst").join(middle, keys).select("seed_id", F.col("dst").alias("nid"), "h0", "h1")
    own = cut.seeds.select("seed_id", "nid").join(h["customer"], "nid").select("seed_id", "nid", "h0", "h1")
    return passing.pass_typed(own, [(inner, lambda c: 2 * c)], keys).select("seed_id", "h0", "h1")


@query(
    "mp_shortcut",
    f"""WITH {BOUGHT}, {_C0}, p AS (SELECT c_custkey, p_partkey FROM bought WHERE ts <= {AT} AND ts > {AT} - INTERVAL 60 DAY),
e AS (SELECT a.c_custkey AS src, b.c_custkey AS dst, count(*) AS n FROM p a JOIN p b USING (p_partkey) WHERE a.c_custkey <> b.c_custkey GROUP BY ALL),
m AS (SELECT dst, sum(n * h0) AS h0 FROM e JOIN c0 ON src = nid GROUP BY dst) SELECT nid, (c0.h0 + coalesce(m.h0, 0))::BIGINT AS h0 FROM c0 LEFT JOIN m ON dst = nid""",
)
def mp_shortcut(spark: S, d: str) -> DataFrame:
    """One round over shortcut links in place of four rounds, each link weighed by its number of ways."""
    near = purchases(spark, d).filter((F.col("ts") <= _at()) & (F.col("ts") > _at() - F.expr("interval '60' day")))
    ways = variants.shortcut(near, "c_custkey", "p_partkey")
    state = states(spark, d)["customer"].select("nid", "h0")
    sent = ways.join(state.withColumnRenamed("nid", "a"), "a").select(F.col("b").alias("nid"), (F.col("n") * F.col("h0")).alias("h0"))
    return passing.pass_typed(state, [(sent, lambda c: c)], ["nid"])


@query("join_agg_identity", "SELECT 0::BIGINT AS n_different, (SELECT count(*) FROM customer) AS n_rows")
def join_agg_identity(spark: S, d: str) -> DataFrame:
    """A pass with identity transforms against the query that joins and groups, early and late: rows that differ."""
    customers, orders = table(spark, d, "customer"), table(spark, d, "orders")
    child = orders.select("o_custkey", F.floor("o_totalprice").cast("bigint").alias("h0"))
    early = passing.join_aggregate(customers, "c_custkey", child, "o_custkey", [F.sum("h0").alias("early")])
    late = passing.join_aggregate(customers, "c_custkey", child, "o_custkey", [F.sum("h0").alias("late")], early=False)
    zero = customers.select(F.col("c_custkey").alias("nid"), F.lit(0).cast("bigint").alias("h0"))
    passed = passing.pass_typed(zero, [(child.withColumnRenamed("o_custkey", "nid"), lambda c: c)], ["nid"])
    both = early.join(late, "c_custkey").join(passed.withColumnRenamed("nid", "c_custkey"), "c_custkey")
    differ = (F.coalesce("early", F.lit(0)) != F.col("h0")) | ~F.col("early").eqNullSafe(F.col("late"))
    return both.agg(F.count(F.when(differ, 1)).alias("n_different"), F.count("*").alias("n_rows"))


@query(
    "join_agg_2hop",
    f"""SELECT o_custkey AS c_custkey, count(*) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS quantity, max(l_shipdate) AS last_ship
FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE o_orderdate <= {AT} AND l_shipdate <= {AT} GROUP BY o_custkey""",
)
def join_agg_2hop(spark: S, d: str) -> DataFrame:
    """Lines are added up per order before orders are joined, then per customer."""
    lines = table(spark, d, "lineitem").filter(F.col("l_shipdate") <= _at())
    per_order = lines.groupBy("l_orderkey").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("decimal(18,2)")).alias("q"), F.max("l_shipdate").alias("s"))
    orders = table(spark, d, "orders").filter(F.col("o_orderdate") <= _at()).select("o_orderkey", F.col("o_custkey").alias("c_custkey"))
    joined = orders.join(per_order, F.col("o_orderkey") == F.col("l_orderkey"))
    return joined.groupBy("c_custkey").agg(F.sum("n").alias("n"), F.sum("q").cast("double").alias("quantity"), F.max("s").alias("last_ship"))


# ------------------------------------------------------------------------------------ ordered pools, as-of


@query("pool_decay", "SELECT user_id, round(sum(value * exp(-0.6931471805599453::DOUBLE * date_diff('day', ts, TIMESTAMP '2024-01-30') / 7.0::DOUBLE)), 4) AS decayed FROM events WHERE ts <= TIMESTAMP '2024-01-30' GROUP BY user_id")
def pool_decay(spark: S, d: str) -> DataFrame:
    at = F.lit(datetime(2024, 1, 30)).cast("timestamp_ntz")
    rows = table(spark, d, "events").filter(F.col("ts") <= at)
    return passing.pool_decay(rows, "user_id", F.col("value"), F.col("ts"), at, 7.0).withColumn("decayed", F.round("decayed", 4))


@query("pool_last", "SELECT user_id, max(event_type ORDER BY ts, event_id) AS last FROM (SELECT * FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) = 1) GROUP BY user_id")
def pool_last(spark: S, d: str) -> DataFrame:
    return passing.pool_last(table(spark, d, "events"), "user_id", "event_type", ["ts", "event_id"])


@query("pool_last_turn", "SELECT conv_id, length(text) AS last FROM conversations QUALIFY row_number() OVER (PARTITION BY conv_id ORDER BY turn DESC) = 1")
def pool_last_turn(spark: S, d: str) -> DataFrame:
    turns = table(spark, d, "conversations").withColumn("size", F.length("text").cast("bigint"))
    return passing.pool_last(turns, "conv_id", "size", ["turn"])


@query(
    "pool_trend",
    """SELECT user_id, count(*) FILTER (ts > TIMESTAMP '2024-01-20') - count(*) FILTER (ts <= TIMESTAMP '2024-01-10') AS trend FROM events
WHERE ts <= TIMESTAMP '2024-01-30' AND ts > TIMESTAMP '2023-12-31' GROUP BY user_id""",
)
def pool_trend(spark: S, d: str) -> DataFrame:
    """Last less first of three windows of ten days."""
    t = lambda s: F.lit(datetime.fromisoformat(s)).cast("timestamp_ntz")
    rows = table(spark, d, "events").filter((F.col("ts") <= t("2024-01-30")) & (F.col("ts") > t("2023-12-31")))
    return rows.groupBy("user_id").agg((F.count(F.when(F.col("ts") > t("2024-01-20"), 1)) - F.count(F.when(F.col("ts") <= t("2024-01-10"), 1))).alias("trend"))


@query(
    "asof_last_order",
    f"""WITH {YEAR}, c AS (SELECT c_custkey, seed_time FROM customer, s WHERE split <> 'train')
SELECT c_custkey, seed_time, o_orderkey, o_orderdate AS last_ts FROM c LEFT JOIN orders ON o_custkey = c_custkey AND o_orderdate <= seed_time
QUALIFY row_number() OVER (PARTITION BY c_custkey, seed_time ORDER BY o_orderdate DESC NULLS LAST, o_orderkey DESC) = 1""",
)
def asof_last_order(spark: S, d: str) -> DataFrame:
    stamps = timeline.stamps(spark, workloads.RETAIL, 365, min_history=365).filter("split <> 'train'").select("seed_time")
    left = table(spark, d, "customer").select("c_custkey").crossJoin(F.broadcast(stamps))
    right = table(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey"), F.col("o_orderdate").alias("ts"), "o_orderkey")
    return passing.as_of_last(left, right, "c_custkey", "seed_time", "ts", ["o_orderkey"])


@query("semi_active", f"SELECT c_custkey, c_mktsegment FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderdate <= {AT} AND o_orderdate > {AT} - INTERVAL 365 DAY)")
def semi_active(spark: S, d: str) -> DataFrame:
    near = table(spark, d, "orders").filter((F.col("o_orderdate") <= _at()) & (F.col("o_orderdate") > _at() - F.expr("interval '365' day")))
    return table(spark, d, "customer").select("c_custkey", "c_mktsegment").join(near.select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_semi")


@query("anti_inactive", f"SELECT c_custkey, c_mktsegment FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderdate <= {AT} AND o_orderdate > {AT} - INTERVAL 365 DAY)")
def anti_inactive(spark: S, d: str) -> DataFrame:
    near = table(spark, d, "orders").filter((F.col("o_orderdate") <= _at()) & (F.col("o_orderdate") > _at() - F.expr("interval '365' day")))
    return table(spark, d, "customer").select("c_custkey", "c_mktsegment").join(near.select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti")


@query("filter_visible", f"WITH {LINES} SELECT l_id AS nid, l_shipdate AS ts FROM li WHERE l_shipdate <= {AT}")
def filter_visible(spark: S, d: str) -> DataFrame:
    rows = keyed_lines(table(spark, d, "lineitem")).select(F.col("l_id").alias("nid"), F.col("l_shipdate").alias("ts"))
    return rows.filter(visible_at(F.col("ts"), _at()))


@query("filter_lookback", f"SELECT o_orderkey, o_orderdate FROM orders WHERE o_orderdate <= {AT} AND o_orderdate > {AT} - INTERVAL 90 DAY")
def filter_lookback(spark: S, d: str) -> DataFrame:
    from .functions.columns import in_past

    return table(spark, d, "orders").select("o_orderkey", "o_orderdate").filter(in_past(F.col("o_orderdate"), _at(), 90))


@query("hyper_pass", f"WITH {LINES}, t AS (SELECT l_id, l_orderkey, floor(l_quantity)::BIGINT AS q, floor(o_totalprice)::BIGINT AS p FROM li JOIN orders ON l_orderkey = o_orderkey) SELECT 'orders' AS ntype, l_orderkey AS nid, sum(q)::BIGINT AS h FROM t GROUP BY l_orderkey UNION ALL SELECT 'lineitem', l_id, p FROM t")
def hyper_pass(spark: S, d: str) -> DataFrame:
    """Over hyperedges (line, order, part, supplier) with states on lines and orders."""
    h = states(spark, d, upto=False)
    state = h["lineitem"].select(F.lit("lineitem").alias("ntype"), "nid", F.col("h0").alias("h")).unionByName(h["orders"].select(F.lit("orders").alias("ntype"), "nid", F.col("h0").alias("h")))
    return variants.hyper_pass(variants.hyperedges(open_retail(spark, d), "lineitem"), state)


@query("edges_up", "SELECT o_orderkey AS src, o_custkey AS dst, o_orderdate AS ts FROM orders")
def edges_up(spark: S, d: str) -> DataFrame:
    db = open_retail(spark, d)
    return edge_view(db, next(x for x in db.links if x.name == "orders.o_custkey")).select("src", "dst", "ts")
