"""Stamps and the table graph come from the rows of the tables."""

from datetime import datetime as D

from pyspark.sql import functions as F

from rowgraph.catalog import Database, LinkSpec, TableSpec
from rowgraph.operators import graph
from rowgraph.plans import timeline, workloads


def test_stamps_go_back_to_the_first_fact(spark):
    facts = spark.createDataFrame([(D(1997, 7, 1),), (D(1999, 1, 1),), (None,)], "ts timestamp_ntz")
    got = lambda f, **k: sorted((r["split"], r["seed_time"]) for r in timeline.stamps_over(f, "ts", workloads.RETAIL, 365, **k).collect())
    fixed = [("test", D(2000, 7, 1)), ("val", D(1999, 7, 1))]
    assert got(facts) == sorted([*fixed, ("train", D(1998, 7, 1)), ("train", D(1997, 7, 1))])
    assert got(facts, min_history=365) == sorted([*fixed, ("train", D(1998, 7, 1))])
    assert got(facts, min_history=366) == fixed == got(facts.filter("false"))
    older = facts.select(F.lit("1990-03-05").cast("timestamp_ntz").alias("ts"))
    for stride in (None, 91):
        split = timeline.SplitSpec(workloads.RETAIL.t_val, workloads.RETAIL.t_test, D(1990, 3, 5), workloads.RETAIL.max_time)
        assert got(older, stride=stride, min_history=365) == sorted(timeline.stamp_list(split, 365, stride, 365))


def test_the_table_graph_counts_references(spark):
    t = {n: spark.createDataFrame(rows, f"{n} long, f long, g long") for n, rows in (("a", [(1, None, None)]), ("b", [(1, 1, None), (2, None, None), (3, 1, None)]), ("c", [(1, 1, None)]))}
    db = Database.of([TableSpec(n, df, n) for n, df in t.items()], [LinkSpec("b", "f", "a"), LinkSpec("c", "f", "b"), LinkSpec("c", "g", "a")])
    rows = {(r["src_table"], r["dst_table"], r["link"], r["inverse"]): r["n_edges"] for r in graph.table_graph(db).collect()}
    assert rows == {("b", "a", "b.f", False): 2, ("a", "b", "b.f", True): 2, ("c", "b", "c.f", False): 1, ("b", "c", "c.f", True): 1, ("c", "a", "c.g", False): 0, ("a", "c", "c.g", True): 0}


def test_hops_go_over_links_with_references(spark):
    t = {n: spark.createDataFrame([(1, v, w)], f"{n} long, f long, g long") for n, v, w in (("a", None, None), ("b", 1, None), ("c", 1, None), ("d", None, None))}
    db = Database.of([TableSpec(n, df, n) for n, df in t.items()], [LinkSpec("b", "f", "a"), LinkSpec("c", "f", "b"), LinkSpec("c", "g", "a"), LinkSpec("d", "f", "a")])
    got = {(r["src"], r["dst"]): r["hops"] for r in graph.table_hops(db).collect()}
    assert got["c", "a"] == got["a", "c"] == 2 and got["b", "c"] == 1 and got["d", "d"] == 0 and ("d", "a") not in got and len(got) == 10
