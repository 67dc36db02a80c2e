"""Further queries: structure, task variants, pools, ablations, links ranked, and the relational operators behind them."""

from __future__ import annotations

from datetime import datetime

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .catalog import infer_links
from .operators import encode, graph, metrics, passing, sampling
from .plans import tasks, timeline, workloads
from .queries_graph import _HOPS, two_hops
from .registry import BOUGHT, DAYS, YEAR, registry
from .sources.datasets import open_retail, purchases, table

QUERIES, ORACLE, query = registry()
S = SparkSession
AT = "TIMESTAMP '2000-07-01'"


def _at() -> F.Column:
    return F.lit(datetime(2000, 7, 1)).cast("timestamp_ntz")


# ------------------------------------------------------------------------------------ structure

_LINKS = [("nation", "n_regionkey", "region"), ("customer", "c_nationkey", "nation"), ("supplier", "s_nationkey", "nation"), ("orders", "o_custkey", "customer"), ("lineitem", "l_orderkey", "orders"), ("lineitem", "l_partkey", "part"), ("lineitem", "l_suppkey", "supplier")]


@query(
    "table_hops",
    "WITH RECURSIVE l AS (" + " UNION ALL ".join(f"SELECT '{x}' AS a, '{y}' AS b FROM {a} HAVING count({f}) > 0" for a, f, b in _LINKS for x, y in ((a, b), (b, a))) + """),
w AS (SELECT name AS src, name AS dst, 0 AS hops FROM (VALUES ('region'), ('nation'), ('customer'), ('supplier'), ('part'), ('orders'), ('lineitem')) t(name) UNION SELECT w.src, l.b, w.hops + 1 FROM w JOIN l ON l.a = w.dst WHERE w.hops < 6)
SELECT src, dst, min(hops)::BIGINT AS hops FROM w GROUP BY ALL""",
)
def table_hops(spark: S, d: str) -> DataFrame:
    """Links between every two tables on the shortest way, over links that have references."""
    return graph.table_hops(open_retail(spark, d))


@query("inferred_links", "SELECT * FROM (VALUES " + ", ".join(f"('{a}', '{f}', '{b}')" for a, f, b in _LINKS) + ") v(child, fk, parent)")
def inferred_links(spark: S, d: str) -> DataFrame:
    """Links proposed from names, types and values, which should be those declared."""
    db = open_retail(spark, d)
    return spark.createDataFrame([(x.child, x.fk, x.parent) for x in infer_links(list(db.tables.values()))], "child string, fk string, parent string")


@query(
    "degree_percentiles",
    " UNION ALL ".join(f"SELECT '{a}.{f}' AS link, quantile_cont(n, 0.5) AS p50, quantile_cont(n, 0.9) AS p90, avg(n) AS mean, sum(n)::BIGINT AS n_edges FROM (SELECT count(*)::DOUBLE AS n FROM {a} GROUP BY {f})" for a, f, _ in _LINKS),
)
def degree_percentiles(spark: S, d: str) -> DataFrame:
    return graph.degree_percentiles(open_retail(spark, d))


@query("row_links", " UNION ALL ".join(f"SELECT '{t}' AS ntype, {sum(a == t for a, _, _ in _LINKS)}::BIGINT AS n_links, count(*) AS n_rows, {' + '.join([f'count({f})' for a, f, _ in _LINKS if a == t] or ['0'])}::BIGINT AS n_edges, TRUE AS n_partite FROM {t}" for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")))
def row_links(spark: S, d: str) -> DataFrame:
    """How many links the rows of each table have, all alike, and whether none stays within its table."""
    return graph.row_links(open_retail(spark, d))


@query("attached_task", f"WITH {YEAR}, {BOUGHT}, t AS (SELECT DISTINCT split, seed_time, c_custkey FROM bought JOIN s ON ts <= seed_time AND ts > seed_time - INTERVAL 365 DAY) SELECT strftime(seed_time, '%Y-%m-%d') AS stamp, count(*) AS n_edges, count(DISTINCT c_custkey) AS n_customers FROM t GROUP BY ALL")
def attached_task(spark: S, d: str) -> DataFrame:
    """The task table as one more table of the database: its edges to customers, by time."""
    task = workloads.customer_churn(spark, d).withColumn("seed_id", F.concat_ws("|", "c_custkey", F.date_format("seed_time", "yyyy-MM-dd"))).withColumnRenamed("c_custkey", "t_custkey")
    db = open_retail(spark, d).attach("churn", task, {"t_custkey": "customer"}, "seed_id")
    edges = graph.edge_view(db, next(x for x in db.links if x.child == "churn"))
    return edges.groupBy(F.date_format("ts", "yyyy-MM-dd").alias("stamp")).agg(F.count("*").alias("n_edges"), F.countDistinct("dst").alias("n_customers"))


# ------------------------------------------------------------------------------------ tasks

_AHEAD = "ts > seed_time AND ts <= seed_time + INTERVAL 365 DAY"


@query(
    "label_kinds",
    f"""WITH {YEAR}, f AS (SELECT o_custkey AS c_custkey, o_orderkey, o_orderdate AS ts, CAST(o_totalprice AS DECIMAL(18,2)) AS v, o_orderstatus AS st FROM orders),
j AS (SELECT split, seed_time, f.* FROM f JOIN s ON ts > seed_time - INTERVAL 365 DAY AND ts <= seed_time + INTERVAL 365 DAY)
SELECT split, seed_time, c_custkey, coalesce(CAST(sum(v) FILTER ({_AHEAD}) AS DOUBLE) / count(v) FILTER ({_AHEAD}), 0) AS label, coalesce(CAST(max(v) FILTER ({_AHEAD}) AS DOUBLE), 0) AS largest,
 coalesce(CAST((list(v ORDER BY ts, v) FILTER ({_AHEAD}))[2] AS DOUBLE), 0) AS second_, coalesce(array_to_string(list_sort(list(DISTINCT st) FILTER ({_AHEAD})), ','), '') AS kinds
FROM j GROUP BY ALL HAVING count(*) FILTER (ts <= seed_time) > 0""",
)
def label_kinds(spark: S, d: str) -> DataFrame:
    """Mean, largest and second next order of a customer, and the set of their kinds, in one pass."""
    orders = table(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey"), F.col("o_orderdate").alias("ts"), F.col("o_totalprice").cast("decimal(18,2)").alias("v"), "o_orderstatus")
    v = F.col("v")
    extra = {"largest": tasks.Label("max", v), "second_": tasks.Label("nth", v, n=2), "kinds": tasks.Label("set", F.col("o_orderstatus"))}
    spec = tasks.TaskSpec("order_kinds", "c_custkey", 365, tasks.Label("avg", v), look_back=365, min_history=365, extra=extra)
    return tasks.build_task_table(spec, orders, workloads.RETAIL).withColumn("kinds", F.array_join("kinds", ","))


@query(
    "where_churn",
    f"WITH {YEAR}, {BOUGHT}, e AS (SELECT c_custkey FROM customer WHERE c_acctbal > 5000) SELECT split, seed_time, e.c_custkey, (count(ts) = 0)::INT AS label FROM e CROSS JOIN s LEFT JOIN bought b ON b.c_custkey = e.c_custkey AND ts > seed_time AND ts <= seed_time + INTERVAL 365 DAY GROUP BY ALL",
)
def where_churn(spark: S, d: str) -> DataFrame:
    """Churn of the customers that a predicate names, active or not."""
    spec = tasks.TaskSpec("where_churn", "c_custkey", 365, tasks.Label("absent"), eligible="where", where=F.col("c_acctbal") > 5000, min_history=365, kind="binary")
    return tasks.build_task_table(spec, purchases(spark, d), workloads.RETAIL, table(spark, d, "customer"))


_CODE = "CASE WHEN n < 8 THEN 'train' WHEN n = 8 THEN 'val' ELSE 'test' END"


@query("multiclass_embeddings", f"SELECT {_CODE} AS split, vec_id, label FROM (SELECT *, ('0x' || substr(md5('split|' || vec_id), 1, 13))::BIGINT % 10 AS n FROM embeddings)")
def multiclass_embeddings(spark: S, d: str) -> DataFrame:
    return workloads.multiclass_embeddings(spark, d)


@query("inputs_before_test", f"SELECT (SELECT count(*) FROM orders WHERE o_orderdate <= {AT}) AS n_orders, (SELECT count(*) FROM lineitem WHERE l_shipdate <= {AT}) AS n_lines, 0::BIGINT AS n_later")
def inputs_before_test(spark: S, d: str) -> DataFrame:
    """What a task's inputs are by default: no row after the test time."""
    task = tasks.Task(workloads.churn_spec(), workloads.customer_churn(spark, d), open_retail(spark, d), workloads.RETAIL)
    orders, lines = task.inputs["orders"], task.inputs["lineitem"]
    later = orders.agg(F.count(F.when(F.col("o_orderdate") > _at(), 1)).alias("n_later"), F.count("*").alias("n_orders"))
    return later.crossJoin(F.broadcast(lines.agg(F.count("*").alias("n_lines"))))


# ------------------------------------------------------------------------------------ pools, paths, ablations


@query(
    "pool_slope",
    "SELECT o_custkey, round(regr_slope(v, m), 5) AS slope, round(corr(v, m), 5) AS together FROM (SELECT o_custkey, floor(o_totalprice) AS v, (year(o_orderdate) * 12 + month(o_orderdate))::DOUBLE AS m FROM orders) GROUP BY o_custkey HAVING count(DISTINCT m) > 2 AND count(DISTINCT v) > 2",
)
def pool_slope(spark: S, d: str) -> DataFrame:
    """Trend of a customer's orders: the slope of their value over months, and how closely the two go together."""
    rows = table(spark, d, "orders").select("o_custkey", F.floor("o_totalprice").cast("double").alias("v"), (F.year("o_orderdate") * 12 + F.month("o_orderdate")).cast("double").alias("m"))
    some = rows.groupBy("o_custkey").agg(F.countDistinct("m").alias("nm"), F.countDistinct("v").alias("nv")).filter("nm > 2 and nv > 2").select("o_custkey")
    trend = passing.pool_trend(rows.join(some, "o_custkey", "left_semi"), "o_custkey", F.col("v"), F.col("m"))
    return trend.select("o_custkey", F.round("slope", 5).alias("slope"), F.round("together", 5).alias("together"))


@query(
    "pool_position",
    "SELECT o_custkey, round(sum(floor(o_totalprice) / r), 4) AS weighted FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate DESC, o_orderkey) AS r FROM orders) WHERE r <= 5 GROUP BY o_custkey",
)
def pool_position(spark: S, d: str) -> DataFrame:
    """Newest orders weigh most: 1, 1/2, 1/3 and so on down to the fifth."""
    rows = table(spark, d, "orders").withColumn("v", F.floor("o_totalprice").cast("double"))
    got = passing.pool_position(rows, "o_custkey", F.col("v"), [F.desc("o_orderdate"), F.col("o_orderkey")], 5)
    return got.select("o_custkey", F.round("weighted", 4).alias("weighted"))


@query(
    "pool_fold",
    "SELECT conv_id, round(sum(length(text) * pow(0.5::DOUBLE, n - r)), 4) AS folded FROM (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS r, count(*) OVER (PARTITION BY conv_id) AS n FROM conversations) GROUP BY conv_id",
)
def pool_fold(spark: S, d: str) -> DataFrame:
    """A recurrence over the turns of a conversation."""
    turns = table(spark, d, "conversations").withColumn("size", F.length("text"))
    return passing.pool_fold(turns, "conv_id", "size", ["turn"]).withColumn("folded", F.round("folded", 4))


@query(
    "join_agg_path",
    f"SELECT c_nationkey, count(*) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS total FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey WHERE l_shipdate <= {AT} AND o_orderdate <= {AT} GROUP BY c_nationkey",
)
def join_agg_path(spark: S, d: str) -> DataFrame:
    """Three links up: lines to orders to customers to nations, added up before each join."""
    db = open_retail(spark, d, datetime(2000, 7, 1))
    lines = db["lineitem"].select("l_orderkey", F.col("l_quantity").cast("decimal(18,2)").alias("total"))
    got = passing.join_aggregate_path(lines, "l_orderkey", ["total"], [(db["orders"], "o_orderkey", "o_custkey"), (db["customer"], "c_custkey", "c_nationkey")])
    return got.select("c_nationkey", "n", F.col("total").cast("double").alias("total"))


@query(
    "mp_layers",
    _HOPS
    + f""", m2 AS (SELECT h2.seed_id, h2.dst, sum(floor(l_quantity)::BIGINT) AS h FROM h2 JOIN li ON li.l_id = h2.src GROUP BY ALL),
m1 AS (SELECT h1.seed_id, sum(floor(o_totalprice)::BIGINT + coalesce(m2.h, 0)) AS h FROM h1 JOIN orders ON o_orderkey = h1.src LEFT JOIN m2 ON m2.seed_id = h1.seed_id AND m2.dst = h1.src GROUP BY ALL)
SELECT seeds.seed_id, (floor(c_acctbal)::BIGINT + coalesce(m1.h, 0))::BIGINT AS h FROM seeds JOIN customer ON c_custkey = nid LEFT JOIN m1 USING (seed_id)""",
)
def mp_layers(spark: S, d: str) -> DataFrame:
    """As many rounds as the slice has hops, from the outermost in."""
    db = open_retail(spark, d, datetime(2000, 7, 1))
    states = {"customer": db["customer"].select(F.col("c_custkey").alias("nid"), F.floor("c_acctbal").cast("bigint").alias("h")), "orders": db["orders"].select(F.col("o_orderkey").alias("nid"), F.floor("o_totalprice").cast("bigint").alias("h")), "lineitem": db["lineitem"].select(F.col("l_id").alias("nid"), F.floor("l_quantity").cast("bigint").alias("h"))}
    return passing.run_passes(two_hops(spark, d), states).select("seed_id", "h")


@query(
    "mp_whole_slice",
    _HOPS
    + f""", k AS (SELECT h1.seed_id, sum(floor(o_totalprice)::BIGINT) AS o FROM h1 JOIN orders ON o_orderkey = h1.src GROUP BY ALL),
q AS (SELECT h1.seed_id, sum(x.q) AS q FROM h1 JOIN (SELECT h2.seed_id, h2.dst, sum(floor(l_quantity)::BIGINT) AS q FROM h2 JOIN li ON li.l_id = h2.src GROUP BY ALL) x ON x.seed_id = h1.seed_id AND x.dst = h1.src GROUP BY ALL)
SELECT seeds.seed_id, (floor(c_acctbal)::BIGINT + 2 * coalesce(k.o, 0) + coalesce(q.q, 0))::BIGINT AS h FROM seeds JOIN customer ON c_custkey = nid LEFT JOIN k USING (seed_id) LEFT JOIN q USING (seed_id)""",
)
def mp_whole_slice(spark: S, d: str) -> DataFrame:
    """Two rounds in which every row of the slice hears from its own neighbours at once, and adds what it hears."""
    db = open_retail(spark, d, datetime(2000, 7, 1))
    states = {"customer": db["customer"].select(F.col("c_custkey").alias("nid"), F.floor("c_acctbal").cast("bigint").alias("h")), "orders": db["orders"].select(F.col("o_orderkey").alias("nid"), F.floor("o_totalprice").cast("bigint").alias("h")), "lineitem": db["lineitem"].select(F.col("l_id").alias("nid"), F.floor("l_quantity").cast("bigint").alias("h"))}
    return passing.run_passes(two_hops(spark, d), states, rounds=2, whole=True).select("seed_id", "h")


@query("slice_cost", _HOPS + " SELECT 0 AS hop, count(*) AS n_rows, count(*) AS n_seeds FROM seeds UNION ALL SELECT 1, count(*), count(DISTINCT seed_id) FROM h1 UNION ALL SELECT 2, count(*), count(DISTINCT seed_id) FROM h2")
def slice_cost(spark: S, d: str) -> DataFrame:
    """Rows that each hop of a slice makes."""
    return two_hops(spark, d).cost()


_CAPS = (2, 4, 8)


@query(
    "ablation_caps",
    f"""WITH e AS (SELECT o_custkey AS dst, floor(o_totalprice)::BIGINT AS v, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate DESC, o_orderkey) AS r, count(*) OVER (PARTITION BY o_custkey) AS n FROM orders WHERE o_orderdate <= {AT})
"""
    + " UNION ALL ".join(f"SELECT '{c or 'all'}' AS cap, dst, count(*) AS n_edges, sum(v)::BIGINT AS total FROM e WHERE {f'r <= {c}' if c else 'true'} GROUP BY dst" for c in (*_CAPS, None)),
)
def ablation_caps(spark: S, d: str) -> DataFrame:
    """A customer's pooled orders with caps and without: what sampling leaves out."""
    db = open_retail(spark, d, datetime(2000, 7, 1))
    seeds = sampling.seeds_of(table(spark, d, "orders").filter(F.col("o_orderdate") <= _at()).select(F.col("o_custkey").alias("c_custkey")).distinct().withColumn("seed_time", _at()), "c_custkey", "customer")
    value = db["orders"].select(F.col("o_orderkey").alias("src"), F.floor("o_totalprice").cast("bigint").alias("v"))
    out = []
    for cap in (*_CAPS, None):
        cut = sampling.cut_slice(db, seeds, [cap], sampling.Strategy("latest" if cap else "all"), [("orders.o_custkey", True)])
        out.append(cut.edges.join(value, "src").groupBy("dst").agg(F.count("*").alias("n_edges"), F.sum("v").alias("total")).withColumn("cap", F.lit(str(cap or "all"))))
    return out[0].unionByName(out[1]).unionByName(out[2]).unionByName(out[3])


# ------------------------------------------------------------------------------------ links ranked

_POP = f"""WITH {BOUGHT}, t AS (SELECT DISTINCT c_custkey, p_partkey FROM bought WHERE ts > {AT} AND ts <= {AT} + INTERVAL 365 DAY),
r AS (SELECT p_partkey, row_number() OVER (ORDER BY n DESC, p_partkey) AS place FROM (SELECT p_partkey, count(*) AS n FROM bought WHERE ts <= {AT} AND ts > {AT} - INTERVAL 365 DAY GROUP BY 1) QUALIFY place <= 50),
h AS (SELECT c_custkey, place, row_number() OVER (PARTITION BY c_custkey ORDER BY place) AS k FROM t JOIN r USING (p_partkey)),
n AS (SELECT c_custkey, count(*) AS n FROM t GROUP BY 1)"""


def _popular(spark: S, d: str) -> tuple[DataFrame, DataFrame]:
    """The fifty parts sold most in the year before, for every customer who buys, and what they buy."""
    bought = purchases(spark, d)
    split = timeline.stamps(spark, workloads.RETAIL, 365, min_history=365).filter("split = 'test'")
    truth = tasks.link_positives(bought, "c_custkey", "p_partkey", split, 365).select("c_custkey", "p_partkey")
    near = bought.filter((F.col("ts") <= _at()) & (F.col("ts") > _at() - F.expr("interval '365' day")))
    best = near.groupBy("p_partkey").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "p_partkey").limit(50)
    # fifty rows for each customer; equal scores go by part
    return truth.select("c_custkey").distinct().crossJoin(F.broadcast(best.withColumnRenamed("n", "score"))), truth


@query("recall_at_k", _POP + " SELECT round(avg(coalesce(x.hit, 0) / n.n::DOUBLE), 9) AS recall FROM n LEFT JOIN (SELECT c_custkey, count(*) AS hit FROM h GROUP BY 1) x USING (c_custkey)")
def recall_at_k(spark: S, d: str) -> DataFrame:
    ranked, truth = _popular(spark, d)
    return metrics.recall_at_k(ranked, truth, ["c_custkey"], "p_partkey", 50).select(F.round("recall", 9).alias("recall"))


@query("map_at_k", _POP + " SELECT round(avg(coalesce(x.s, 0) / least(n.n, 50)), 9) AS map FROM n LEFT JOIN (SELECT c_custkey, sum(k::DOUBLE / place) AS s FROM h GROUP BY 1) x USING (c_custkey)")
def map_at_k(spark: S, d: str) -> DataFrame:
    ranked, truth = _popular(spark, d)
    return metrics.map_at_k(ranked, truth, ["c_custkey"], "p_partkey", 50).select(F.round("map", 9).alias("map"))


# ------------------------------------------------------------------------------------ relational operators


@query("lateral_orders", f"SELECT c_custkey, x.n, x.newest FROM customer c, LATERAL (SELECT count(*) AS n, max(o_orderdate) AS newest FROM orders o WHERE o.o_custkey = c.c_custkey AND o_orderdate <= {AT}) x")
def lateral_orders(spark: S, d: str) -> DataFrame:
    """A subquery that sees the row beside it."""
    said = "SELECT c_custkey, x.n, x.newest FROM {c} c, LATERAL (SELECT count(*) AS n, max(o_orderdate) AS newest FROM {o} o WHERE o.o_custkey = c.c_custkey AND o_orderdate <= TIMESTAMP_NTZ '2000-07-01') x"
    return spark.sql(said, c=table(spark, d, "customer").select("c_custkey"), o=table(spark, d, "orders").select("o_custkey", "o_orderdate"))


_KINDS = ("click", "error", "purchase", "signup", "view")


@query("pivot_events", "SELECT user_id, " + ", ".join(f"count(*) FILTER (event_type = '{k}') AS n_{k}" for k in _KINDS) + " FROM events GROUP BY user_id")
def pivot_events(spark: S, d: str) -> DataFrame:
    wide = table(spark, d, "events").groupBy("user_id").pivot("event_type", list(_KINDS)).count()
    return wide.select("user_id", *(F.coalesce(F.col(k), F.lit(0)).alias(f"n_{k}") for k in _KINDS))


@query("unpivot_events", "SELECT user_id, event_type AS kind, count(*) AS n FROM events GROUP BY ALL")
def unpivot_events(spark: S, d: str) -> DataFrame:
    wide = pivot_events(spark, d).select("user_id", *(F.col(f"n_{k}").alias(k) for k in _KINDS))
    return wide.unpivot("user_id", list(_KINDS), "kind", "n").filter("n > 0")


@query("enc_bins", "WITH q AS (SELECT quantile_cont(c_acctbal, [0.25, 0.5, 0.75]) AS cuts FROM customer) SELECT c_custkey, len(list_filter(cuts, lambda c: c <= c_acctbal))::INT AS bin FROM customer, q")
def enc_bins(spark: S, d: str) -> DataFrame:
    df = table(spark, d, "customer")
    hot = F.array(*encode.Bins("c_acctbal", 4).fit(df).columns())
    return df.select("c_custkey", (F.array_position(hot, 1.0) - 1).cast("int").alias("bin"))


@query("page_text", r"SELECT page_id, length(trim(regexp_replace(regexp_replace(regexp_replace(html, '<(script|style)\b.*?</(script|style)>|<!--.*?-->', ' ', 'gis'), '<[^>]*>', ' ', 'gs'), '\s+', ' ', 'g'))) AS n_chars FROM pages")
def page_text(spark: S, d: str) -> DataFrame:
    return table(spark, d, "pages").select("page_id", F.length(encode.html_text("html")).cast("bigint").alias("n_chars"))


@query("sketch_users", "SELECT event_type, count(DISTINCT user_id) AS n_users, TRUE AS near FROM events GROUP BY event_type")
def sketch_users(spark: S, d: str) -> DataFrame:
    """Distinct users by a sketch that can be merged, against the exact number: within a tenth."""
    got = table(spark, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("n_users"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id", F.lit(12))).alias("about"))
    return got.select("event_type", "n_users", (F.abs(F.col("about") - F.col("n_users")) <= 0.1 * F.col("n_users")).alias("near"))


@query("udaf_gap", "SELECT user_id, median(gap) AS gap FROM (SELECT user_id, floor(epoch(ts))::BIGINT - floor(epoch(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)))::BIGINT AS gap FROM events) WHERE gap IS NOT NULL GROUP BY user_id")
def udaf_gap(spark: S, d: str) -> DataFrame:
    """The user's own aggregate, as a pandas function: the median pause between a user's events."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    seconds = F.unix_timestamp(F.col("ts").cast("timestamp"))
    gaps = table(spark, d, "events").select("user_id", (seconds - F.lag(seconds).over(w)).alias("gap")).filter("gap is not null")

    @F.pandas_udf("double")
    def median(x: pd.Series) -> float:
        return float(x.median())

    return gaps.groupBy("user_id").agg(median("gap").alias("gap"))


@query("grouped_ranks", f"WITH {DAYS} SELECT user_id, event_id, (percent_rank() OVER (PARTITION BY user_id ORDER BY value)) AS place FROM events")
def grouped_ranks(spark: S, d: str) -> DataFrame:
    """The user's own function of a group, as pandas: where each event's value stands among the user's."""

    def ranks(x: pd.DataFrame) -> pd.DataFrame:
        place = (x["value"].rank(method="min") - 1) / max(1, len(x) - 1)
        return pd.DataFrame({"user_id": x["user_id"], "event_id": x["event_id"], "place": place})

    return table(spark, d, "events").select("user_id", "event_id", "value").groupBy("user_id").applyInPandas(ranks, "user_id long, event_id long, place double")
