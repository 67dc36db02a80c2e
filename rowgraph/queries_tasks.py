"""Queries on the database, its graphs, and task tables."""

from __future__ import annotations

from datetime import datetime

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .catalog import check_keys
from .functions.columns import in_future
from .operators import graph, metrics
from .plans import tasks, timeline, workloads
from .registry import BOUGHT, DAYS, HALVES, LINES, TWO_YEARS, YEAR, registry, stamps_sql
from .sources.datasets import open_retail, purchases, table

QUERIES, ORACLE, query = registry()
S = SparkSession
T_TEST = datetime(2000, 7, 1)

# ------------------------------------------------------------------------------------ database

_PK = [("region", "r_regionkey"), ("nation", "n_nationkey"), ("customer", "c_custkey"), ("supplier", "s_suppkey"), ("part", "p_partkey"), ("orders", "o_orderkey"), ("li", "l_id")]
_FK = [("nation", "n_regionkey", "region", "r_regionkey"), ("customer", "c_nationkey", "nation", "n_nationkey"), ("supplier", "s_nationkey", "nation", "n_nationkey"), ("orders", "o_custkey", "customer", "c_custkey"), ("li", "l_orderkey", "orders", "o_orderkey"), ("li", "l_partkey", "part", "p_partkey"), ("li", "l_suppkey", "supplier", "s_suppkey")]
_TIME = {"orders": "o_orderdate", "li": "l_shipdate"}


def _n(t: str) -> str:
    return "lineitem" if t == "li" else t


@query(
    "key_checks",
    f"WITH {LINES} "
    + " UNION ALL ".join(
        [f"SELECT '{_n(t)}' AS \"table\", 'repeated key' AS \"check\", (SELECT count(*) FROM (SELECT {k} FROM {t} WHERE {k} IS NOT NULL GROUP BY {k} HAVING count(*) > 1)) AS violations" for t, k in _PK]
        + [f"SELECT '{_n(t)}', 'null key', (SELECT count(*) FROM {t} WHERE {k} IS NULL)" for t, k in _PK]
        + [f"SELECT '{_n(t)}', '{c} not in {p}', (SELECT count(*) FROM {t} WHERE {c} IS NOT NULL AND {c} NOT IN (SELECT {k} FROM {p}))" for t, c, p, k in _FK]
    ),
)
def key_checks(spark: S, d: str) -> DataFrame:
    return check_keys(open_retail(spark, d))


@query("table_graph", " UNION ALL ".join([f"SELECT '{_n(t)}' AS src_table, '{p}' AS dst_table, '{_n(t)}.{c}' AS link, false AS inverse, count({c}) AS n_edges FROM {_n(t)}" for t, c, p, _ in _FK] + [f"SELECT '{p}', '{_n(t)}', '{_n(t)}.{c}', true, count({c}) FROM {_n(t)}" for t, c, p, _ in _FK]))
def table_graph(spark: S, d: str) -> DataFrame:
    return graph.table_graph(open_retail(spark, d))


@query("nodes_per_type", " UNION ALL ".join(f"SELECT '{_n(t)}' AS ntype, count(*) AS n FROM {_n(t)}" for t, _ in _PK))
def nodes_per_type(spark: S, d: str) -> DataFrame:
    return graph.all_nodes(open_retail(spark, d)).groupBy("ntype").agg(F.count("*").alias("n"))


@query(
    "edges_per_type",
    f"WITH {LINES} "
    + " UNION ALL ".join(
        [f"SELECT '{_n(t)}.{c}' AS link, '{_n(t)}' AS src_type, '{p}' AS dst_type, count(*) AS n, count({_TIME.get(t, 'NULL')}) AS n_timed FROM {t} WHERE {c} IS NOT NULL" for t, c, p, _ in _FK]
        + [f"SELECT '{_n(t)}.{c}', '{p}', '{_n(t)}', count(*), {'count(*)' if p in _TIME else '0'} FROM {t} WHERE {c} IS NOT NULL" for t, c, p, _ in _FK]
    ),
)
def edges_per_type(spark: S, d: str) -> DataFrame:
    return graph.all_edges(open_retail(spark, d)).groupBy("link", "src_type", "dst_type").agg(F.count("*").alias("n"), F.count("ts").alias("n_timed"))


@query("edge_roundtrip", " UNION ALL ".join(f"SELECT '{_n(t)}.{c}' AS link, 0::BIGINT AS n_lost, 0::BIGINT AS n_new" for t, c, _, _ in _FK))
def edge_roundtrip(spark: S, d: str) -> DataFrame:
    return graph.roundtrip(open_retail(spark, d))


@query("degree_stats", " UNION ALL ".join(f"SELECT '{_n(t)}.{c}' AS link, count(*) AS n_parents, sum(n)::BIGINT AS n_edges, max(n) AS max_degree FROM (SELECT {c}, count(*) AS n FROM {_n(t)} WHERE {c} IS NOT NULL GROUP BY {c})" for t, c, _, _ in _FK))
def degree_stats(spark: S, d: str) -> DataFrame:
    return graph.degree_stats(open_retail(spark, d))


_MOMENTS = ("1997-07-01", "2000-07-01")


@query("freeze_counts", " UNION ALL ".join(f"SELECT '{_n(t)}' AS ntype, TIMESTAMP '{m}' AS t, count(*) AS n FROM {_n(t)}" + (f" WHERE {_TIME[t]} IS NULL OR {_TIME[t]} <= TIMESTAMP '{m}'" if t in _TIME else "") for m in _MOMENTS for t, _ in _PK))
def freeze_counts(spark: S, d: str) -> DataFrame:
    return graph.freeze_counts(open_retail(spark, d), [datetime.fromisoformat(m) for m in _MOMENTS])


@query("db_stats", " UNION ALL ".join(f"SELECT '{_n(t)}' AS ntype, count(*) AS n, {f'min({_TIME[t]})' if t in _TIME else 'NULL::TIMESTAMP'} AS lo, {f'max({_TIME[t]})' if t in _TIME else 'NULL::TIMESTAMP'} AS hi FROM {_n(t)}" for t, _ in _PK))
def db_stats(spark: S, d: str) -> DataFrame:
    return graph.db_stats(open_retail(spark, d))


# ------------------------------------------------------------------------------------ stamps

_DENSE = "SELECT 'val' AS split, TIMESTAMP '1999-07-01' AS seed_time UNION ALL SELECT 'test', TIMESTAMP '2000-07-01' UNION ALL SELECT 'train', t FROM (SELECT TIMESTAMP '1999-07-01' - INTERVAL 1 DAY * (365 + {step} * k) AS t FROM range(0, 200) r(k)) WHERE t >= (SELECT min(o_orderdate) FROM orders) + INTERVAL 365 DAY"


@query("seed_stamps", _DENSE.format(step=365))
def seed_stamps(spark: S, d: str) -> DataFrame:
    return timeline.stamps_over(table(spark, d, "orders"), "o_orderdate", workloads.RETAIL, 365, min_history=365)


@query("seed_stamps_dense", _DENSE.format(step=91))
def seed_stamps_dense(spark: S, d: str) -> DataFrame:
    return timeline.stamps_over(table(spark, d, "orders"), "o_orderdate", workloads.RETAIL, 365, stride=91, min_history=365)


# ------------------------------------------------------------------------------------ workloads

_WINDOW = """SELECT split, seed_time, {key}, {label} AS label FROM {facts} JOIN s ON {ts} <= seed_time + INTERVAL {delta} DAY {back}
GROUP BY split, seed_time, {key} HAVING count(*) FILTER ({ts} <= seed_time) > 0"""


def _windowed(stamps: str, facts: str, key: str, ts: str, label: str, delta: int, back: int | None, more: str = "") -> str:
    return f"WITH {stamps}{more} " + _WINDOW.format(key=key, facts=facts, ts=ts, delta=delta, label=label, back="" if back is None else f"AND {ts} > seed_time - INTERVAL {back} DAY")


_SUM = "CAST(coalesce(sum(CAST({v} AS DECIMAL(18,2))) FILTER ({ts} > seed_time), 0) AS DOUBLE)"
_ABSENT = "(count(*) FILTER (ts > seed_time) = 0)::INT"

query("customer_value", _windowed(YEAR, "bought", "c_custkey", "ts", _SUM.format(v="p_retailprice", ts="ts"), 365, 365, ", " + BOUGHT))(workloads.customer_value)
query("customer_value_730", _windowed(TWO_YEARS, "bought", "c_custkey", "ts", _SUM.format(v="p_retailprice", ts="ts"), 730, 730, ", " + BOUGHT))(workloads.customer_value_730)
query("customer_churn", _windowed(YEAR, "bought", "c_custkey", "ts", _ABSENT, 365, 365, ", " + BOUGHT))(workloads.customer_churn)
query("customer_churn_730", _windowed(TWO_YEARS, "bought", "c_custkey", "ts", _ABSENT, 730, 730, ", " + BOUGHT))(workloads.customer_churn_730)


def _churn_k(k: int) -> str:
    return f"""SELECT {k} AS k, split, seed_time, c_custkey, {_ABSENT} AS label FROM bought JOIN
 (SELECT 'val' AS split, TIMESTAMP '1999-07-01' AS seed_time UNION ALL SELECT 'test', TIMESTAMP '2000-07-01'
  UNION ALL SELECT 'train', t FROM (SELECT TIMESTAMP '1999-07-01' - INTERVAL 1 DAY * ({k} + 30 * j) AS t FROM range(0, 200) r(j)) WHERE t >= TIMESTAMP '1996-01-01') s
 ON ts <= seed_time + INTERVAL {k} DAY AND ts > seed_time - INTERVAL 365 DAY GROUP BY split, seed_time, c_custkey HAVING count(*) FILTER (ts <= seed_time) > 0"""


query("customer_churn_k", f"WITH {BOUGHT} " + " UNION ALL ".join(_churn_k(k) for k in (30, 90, 180)))(workloads.customer_churn_k)
query("user_engagement", _windowed(DAYS, "(SELECT * FROM events WHERE event_type = 'purchase')", "user_id", "ts", "(count(*) FILTER (ts > seed_time) > 0)::INT", 2, None))(workloads.user_engagement)
query(
    "order_attention",
    f"""WITH {HALVES}, e AS (SELECT split, seed_time, o_orderkey FROM orders JOIN s ON o_orderdate <= seed_time AND o_orderdate > seed_time - INTERVAL 365 DAY)
SELECT e.split, e.seed_time, e.o_orderkey, count(l_orderkey) AS label FROM e LEFT JOIN lineitem ON l_orderkey = e.o_orderkey AND l_returnflag = 'A'
 AND l_shipdate > e.seed_time AND l_shipdate <= e.seed_time + INTERVAL 182 DAY GROUP BY ALL""",
)(workloads.order_attention)
query(
    "spend_90d",
    f"""WITH {stamps_sql(("val", "1999-07-01"), ("test", "2000-07-01"), ("train", "1999-04-02"), ("train", "1998-04-02"), ("train", "1997-04-02"), ("train", "1996-04-02"))} """
    + _WINDOW.format(key="o_custkey", facts="orders", ts="o_orderdate", delta=90, label=_SUM.format(v="o_totalprice", ts="o_orderdate"), back="AND o_orderdate > seed_time - INTERVAL 365 DAY").replace("SELECT split, seed_time, o_custkey,", "SELECT split, seed_time, o_custkey AS c_custkey,"),
)(workloads.spend_90d)
query("part_sales", _windowed(HALVES, "lineitem", "l_partkey", "l_shipdate", _SUM.format(v="l_quantity", ts="l_shipdate"), 182, 365).replace("SELECT split, seed_time, l_partkey,", "SELECT split, seed_time, l_partkey AS p_partkey,"))(workloads.part_sales)

_SPLIT = "CASE WHEN ('0x' || substr(md5('split|' || {k}), 1, 13))::BIGINT % 10 < 8 THEN 'train' WHEN ('0x' || substr(md5('split|' || {k}), 1, 13))::BIGINT % 10 = 8 THEN 'val' ELSE 'test' END AS split"
query("static_quality", f"SELECT {_SPLIT.format(k='doc_id')}, doc_id, quality AS label FROM labels")(workloads.static_quality)
query("static_toxic", f"SELECT {_SPLIT.format(k='doc_id')}, doc_id, toxic AS label FROM labels")(workloads.static_toxic)


@query("multilabel_task", f"SELECT {_SPLIT.format(k='doc_id')}, doc_id, quality::INT AS label_0, toxic::INT AS label_1 FROM labels")
def multilabel_task(spark: S, d: str) -> DataFrame:
    return workloads.multilabel_task(spark, d).select("split", "doc_id", F.col("label")[0].alias("label_0"), F.col("label")[1].alias("label_1"))


query("static_impute_priority", f"SELECT {_SPLIT.format(k='o_orderkey')}, o_orderkey, o_orderpriority AS label FROM orders")(workloads.static_impute_priority)
query(
    "multiclass_task",
    f"""WITH {DAYS}, n AS (SELECT split, seed_time, user_id, event_type, count(*) AS c FROM events JOIN s ON ts > seed_time AND ts <= seed_time + INTERVAL 2 DAY GROUP BY ALL)
SELECT split, seed_time, user_id, event_type AS label FROM n QUALIFY row_number() OVER (PARTITION BY split, seed_time, user_id ORDER BY c DESC, event_type) = 1""",
)(workloads.multiclass_task)


@query("task_from_sql", _windowed(YEAR, "orders", "o_custkey", "o_orderdate", "count(*) FILTER (o_orderdate > seed_time)", 365, 365).replace("SELECT split, seed_time, o_custkey,", "SELECT split, seed_time, o_custkey AS c_custkey,"))
def task_from_sql(spark: S, d: str) -> DataFrame:
    table(spark, d, "orders").createOrReplaceTempView("task_orders")
    sql = """select o_custkey as c_custkey, count_if(o_orderdate > :t) as label from task_orders
      where o_orderdate > cast(:t as timestamp_ntz) - make_dt_interval(:delta) and o_orderdate <= cast(:t as timestamp_ntz) + make_dt_interval(:delta)
      group by o_custkey having count_if(o_orderdate <= :t) > 0"""
    return tasks.task_from_sql(spark, sql, timeline.stamp_list(workloads.RETAIL, 365, None, 365), 365)


@query("task_stats", f"WITH t AS ({ORACLE['customer_value']}) SELECT split, count(*) AS n, min(label) AS lo, max(label) AS hi, count(*) FILTER (label > 0) AS positives FROM t GROUP BY split")
def task_stats(spark: S, d: str) -> DataFrame:
    return tasks.describe(workloads.customer_value(spark, d))


@query("task_rollup", f"WITH t AS ({ORACLE['customer_churn']}) SELECT split, seed_time, label, count(*) AS n FROM t GROUP BY ROLLUP (split, seed_time, label)")
def task_rollup(spark: S, d: str) -> DataFrame:
    return workloads.customer_churn(spark, d).rollup("split", "seed_time", "label").agg(F.count("*").alias("n"))


@query("task_cube", f"WITH t AS ({ORACLE['customer_churn']}) SELECT split, c_mktsegment, label, count(*) AS n FROM t JOIN customer USING (c_custkey) GROUP BY CUBE (split, c_mktsegment, label)")
def task_cube(spark: S, d: str) -> DataFrame:
    return workloads.customer_churn(spark, d).join(table(spark, d, "customer").select("c_custkey", "c_mktsegment"), "c_custkey").cube("split", "c_mktsegment", "label").agg(F.count("*").alias("n"))


@query(
    "multitask_join",
    f"WITH a AS ({ORACLE['customer_value']}), b AS ({ORACLE['customer_churn']}) SELECT split, seed_time, c_custkey, a.label AS label_a, b.label AS label_b FROM a FULL JOIN b USING (split, seed_time, c_custkey)",
)
def multitask_join(spark: S, d: str) -> DataFrame:
    return tasks.join_tasks(workloads.customer_value(spark, d), workloads.customer_churn(spark, d), ["c_custkey"])


_PAIRS = f"WITH {YEAR}, {BOUGHT}, pos AS (SELECT DISTINCT split, seed_time, c_custkey, p_partkey FROM bought JOIN s ON ts > seed_time AND ts <= seed_time + INTERVAL 365 DAY)"


def _stamps(spark: S) -> DataFrame:
    return timeline.stamps(spark, workloads.RETAIL, 365, min_history=365)


@query("link_task_pos", f"{_PAIRS} SELECT * FROM pos")
def link_task_pos(spark: S, d: str) -> DataFrame:
    return tasks.link_positives(purchases(spark, d), "c_custkey", "p_partkey", _stamps(spark), 365)


@query(
    "link_task_neg",
    f"""{_PAIRS}, k AS (SELECT count(*) AS n FROM part), c AS (SELECT DISTINCT split, seed_time, c_custkey,
 ('0x' || substr(md5('neg|' || c_custkey || '|' || strftime(seed_time, '%Y-%m-%d') || '|' || p_partkey || '|1'), 1, 13))::BIGINT % n AS p_partkey FROM pos, k)
SELECT * FROM c ANTI JOIN pos USING (split, seed_time, c_custkey, p_partkey)""",
)
def link_task_neg(spark: S, d: str) -> DataFrame:
    positives = link_task_pos(spark, d)
    return tasks.link_negatives(positives, "c_custkey", "p_partkey", table(spark, d, "part").count())


@query(
    "tuple_task",
    f"""WITH {YEAR} SELECT split, seed_time, o_custkey, l_partkey, l_suppkey, count(*) AS label FROM lineitem JOIN orders ON l_orderkey = o_orderkey
 JOIN s ON o_orderdate > seed_time AND o_orderdate <= seed_time + INTERVAL 365 DAY GROUP BY ALL""",
)
def tuple_task(spark: S, d: str) -> DataFrame:
    orders = table(spark, d, "orders").select("o_orderkey", "o_custkey", F.col("o_orderdate").alias("ts"))
    facts = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return tasks.tuple_task(facts, ["o_custkey", "l_partkey", "l_suppkey"], _stamps(spark), 365)


# ------------------------------------------------------------------------------------ measures and controls


@query(
    "baseline_constant_mae",
    f"""WITH t AS ({ORACLE['customer_value']}), c AS (SELECT quantile_cont(label, 0.5) AS y FROM t WHERE split = 'train')
SELECT split, round(CAST(sum(CAST(abs(label - y) AS DECIMAL(28,6))) AS DOUBLE) / count(*), 6) AS mae, count(*) AS n FROM t, c GROUP BY split""",
)
def baseline_constant_mae(spark: S, d: str) -> DataFrame:
    from .operators.baselines import constant

    rows = constant(workloads.customer_value(spark, d))
    return rows.groupBy("split").agg(F.round(F.sum(F.abs(F.col("label") - F.col("y_hat")).cast("decimal(28,6)")).cast("double") / F.count("*"), 6).alias("mae"), F.count("*").alias("n"))


_SCORED = f"""WITH {YEAR}, {BOUGHT}, t AS (SELECT split, seed_time, c_custkey, (count(*) FILTER (ts > seed_time) = 0)::INT AS label, -(count(*) FILTER (ts <= seed_time)) AS score, count(*) FILTER (ts <= seed_time) AS past
 FROM bought JOIN s ON ts <= seed_time + INTERVAL 365 DAY AND ts > seed_time - INTERVAL 365 DAY GROUP BY ALL)"""


def churn_scored(spark: S, d: str) -> DataFrame:
    """W2 with a score: fewer purchases in the last year, more likely churn."""
    facts = purchases(spark, d).select("c_custkey", "ts")
    rows = facts.join(F.broadcast(_stamps(spark)), (F.col("ts") > F.col("seed_time") - F.expr("interval '365' day")) & (F.col("ts") <= F.col("seed_time") + F.expr("interval '365' day")))
    ahead = in_future(F.col("ts"), F.col("seed_time"), 365)
    out = rows.groupBy("split", "seed_time", "c_custkey").agg(F.count(F.when(ahead, 1)).alias("n_"), F.count(F.when(~ahead, 1)).alias("past"))
    return out.filter("past > 0").select("split", "seed_time", "c_custkey", (F.col("n_") == 0).cast("int").alias("label"), (-F.col("past")).alias("score"))


@query(
    "metric_ap",
    _SCORED
    + """, g AS (SELECT score, count(*) AS n, sum(label) AS p FROM t WHERE past > 0 AND split = 'test' GROUP BY score),
c AS (SELECT *, sum(p) OVER (ORDER BY score DESC) AS cp, sum(n) OVER (ORDER BY score DESC) AS cn FROM g)
SELECT round(sum(p * (cp::DOUBLE / cn)) / sum(p), 9) AS ap FROM c""",
)
def metric_ap(spark: S, d: str) -> DataFrame:
    return metrics.average_precision(churn_scored(spark, d).filter("split = 'test'")).select(F.round("ap", 9).alias("ap"))


@query(
    "metric_auc",
    _SCORED
    + """, g AS (SELECT score, sum(label) AS p, sum(1 - label) AS q FROM t WHERE past > 0 AND split = 'test' GROUP BY score),
c AS (SELECT *, sum(p) OVER (ORDER BY score DESC) AS cp FROM g) SELECT round(sum(q * (cp - p) + p * q / 2.0::DOUBLE) / (sum(p)::DOUBLE * sum(q)), 9) AS auc FROM c""",
)
def metric_auc(spark: S, d: str) -> DataFrame:
    return metrics.roc_auc(churn_scored(spark, d).filter("split = 'test'")).select(F.round("auc", 9).alias("auc"))


_VALUED = f"""WITH {YEAR}, {BOUGHT}, t AS (SELECT split, seed_time, c_custkey, {_SUM.format(v='p_retailprice', ts='ts')} AS label,
 CAST(coalesce(sum(CAST(p_retailprice AS DECIMAL(18,2))) FILTER (ts <= seed_time), 0) AS DOUBLE) AS y_hat FROM bought JOIN s ON ts <= seed_time + INTERVAL 365 DAY AND ts > seed_time - INTERVAL 365 DAY
 GROUP BY ALL HAVING count(*) FILTER (ts <= seed_time) > 0)"""


def value_persisted(spark: S, d: str) -> DataFrame:
    from .operators.baselines import persistence

    return persistence(workloads.customer_value(spark, d), purchases(spark, d), "c_custkey", F.col("p_retailprice"), 365)


@query("metric_mae", _VALUED + " SELECT round(CAST(sum(CAST(abs(label - y_hat) AS DECIMAL(28,6))) AS DOUBLE) / count(*), 6) AS mae FROM t WHERE split = 'test'")
def metric_mae(spark: S, d: str) -> DataFrame:
    return metrics.mean_abs_error(value_persisted(spark, d).filter("split = 'test'")).select(F.round("mae", 6).alias("mae"))


@query("metric_rmse", _VALUED + " SELECT round(sqrt(CAST(sum(CAST(label - y_hat AS DECIMAL(18,4)) * CAST(label - y_hat AS DECIMAL(18,4))) AS DOUBLE) / count(*)), 6) AS rmse FROM t WHERE split = 'test'")
def metric_rmse(spark: S, d: str) -> DataFrame:
    return metrics.root_mean_square(value_persisted(spark, d).filter("split = 'test'")).select(F.round("rmse", 6).alias("rmse"))
