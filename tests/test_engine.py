from datetime import datetime as D

import pytest
from pyspark.sql import functions as F

from rowgraph import catalog
from rowgraph.catalog import Database, LinkSpec, TableSpec
from rowgraph.functions import columns as C
from rowgraph.operators import encode, graph, metrics, passing, sampling, variants
from rowgraph.plans import tasks, timeline, workloads
from rowgraph.sources import datasets, io
from tests import ref

T = D(2000, 1, 10)


@pytest.fixture(scope="module")
def store(spark):
    """Customers, products and transactions with a null reference, a row without time, ties, and rows at the bounds."""
    customers = spark.createDataFrame([(1, "x"), (2, "y"), (3, "y")], "c bigint, kind string")
    products = spark.createDataFrame([(10, 1.0), (11, 2.0)], "p bigint, size double")
    tx = [
        (100, 1, 10, 5.0, D(2000, 1, 10)),
        (101, 1, 11, 7.0, D(2000, 1, 11)),
        (102, 1, 10, 1.0, D(2000, 1, 9)),
        (103, 1, 10, 2.0, D(2000, 1, 9)),
        (104, 2, 11, 3.0, None),
        (105, 2, 10, 4.0, D(2000, 1, 20)),
        (106, None, 10, 9.0, D(2000, 1, 5)),
        (107, 2, 11, 8.0, D(2000, 1, 21)),
    ]
    frame = spark.createDataFrame(tx, "id bigint, cust bigint, prod bigint, price double, ts timestamp_ntz")
    return Database.of([TableSpec("customers", customers, "c"), TableSpec("products", products, "p"), TableSpec("tx", frame, "id", "ts")], [LinkSpec("tx", "cust", "customers"), LinkSpec("tx", "prod", "products")])


# ---------------------------------------------------------------- catalog and graph


def test_bad_databases_are_refused(spark):
    t = TableSpec("a", spark.range(1), "id")
    with pytest.raises(ValueError):
        Database.of([t], [LinkSpec("a", "id", "b")])
    with pytest.raises(ValueError):
        Database.of([t], [LinkSpec("a", "nope", "a")])
    with pytest.raises(ValueError):
        Database.of([TableSpec("a", spark.range(1), "nope")], [])


def test_key_checks_find_faults(spark, store):
    assert all(r["violations"] == 0 for r in catalog.check_keys(store).collect())
    bad = Database.of([TableSpec("p", spark.createDataFrame([(1,), (1,), (None,)], "k bigint"), "k"), TableSpec("c", spark.createDataFrame([(1, 5), (2, None)], "k bigint, f bigint"), "k")], [LinkSpec("c", "f", "p")])
    got = {(r["table"], r["check"]): r["violations"] for r in catalog.check_keys(bad).collect()}
    assert got == {("p", "repeated key"): 1, ("p", "null key"): 1, ("c", "repeated key"): 0, ("c", "null key"): 0, ("c", "f not in p"): 1}


def test_inference(spark, sf, store):
    roles = catalog.classify_roles(datasets.open_retail(spark, sf))
    assert roles["lineitem"] == "fact" and roles["nation"] == "dimension"
    kinds = catalog.infer_modalities(datasets.table(spark, sf, "customer"))
    assert kinds["c_acctbal"] == "number" and kinds["c_mktsegment"] == "category" and kinds["c_name"] == "text"
    found = {x.name for x in catalog.infer_links([s for n, s in datasets.open_retail(spark, sf).tables.items() if n in ("nation", "region", "customer")])}
    assert {"nation.n_regionkey", "customer.c_nationkey"} <= found


def test_table_graph_and_hops(spark, sf):
    retail, bought = datasets.open_retail(spark, sf), datasets.open_purchases(spark, sf)
    assert len(graph.table_components(retail)) == 1
    assert graph.hops_between(bought, "customer", "part") == 2  # to another customer: 4
    assert graph.hops_between(retail, "customer", "part") == 3  # to another customer: 6


def test_edges(store):
    e = graph.all_edges(store)
    assert e.count() == 2 * (7 + 8)
    assert e.filter("src_type = dst_type").count() == 0
    down = graph.edge_view(store, store.links[0], upward=False)
    assert down.filter("ts is not null").count() == 0
    assert all(r["n_lost"] == r["n_new"] == 0 for r in graph.roundtrip(store).collect())


def test_corpus_and_activity_open(spark, sf):
    corpus = datasets.open_corpus(spark, sf)
    assert all(r["violations"] == 0 for r in catalog.check_keys(corpus).collect())
    assert all(r["n_lost"] == 0 for r in graph.roundtrip(datasets.open_activity(spark, sf)).collect())


def test_attach_adds_the_task_as_a_table(spark, sf):
    db = datasets.open_purchases(spark, sf)
    task = workloads.customer_churn(spark, sf).withColumn("task_id", F.monotonically_increasing_id())
    more = db.attach("churn", task, {"c_custkey": "customer"}, "task_id")
    assert graph.hops_between(more, "churn", "purchase") == 2


def test_variants(store, spark):
    h = {r["edge"]: [(p["ntype"], p["nid"]) for p in r["pins"]] for r in variants.hyperedges(store, "tx").collect()}
    assert h[100] == [("tx", 100), ("customers", 1), ("products", 10)] and h[106] == [("tx", 106), ("products", 10)]
    facts = store["tx"].filter("cust is not null")
    ways = {(r["a"], r["b"]): r["n"] for r in variants.shortcut(facts, "cust", "prod").collect()}
    assert ways == {(1, 2): 3 + 2, (2, 1): 5}
    assert variants.shortcut(facts, "cust", "prod", max_degree=3).filter("n > 2").count() == 0
    keys, rest = variants.split_columns(store, "tx")
    assert keys.columns == ["id", "cust", "prod", "ts"] and rest.columns == ["id", "price"]


# ---------------------------------------------------------------- time and tasks


def test_stamps_walk_back_over_leap_years():
    listed = timeline.stamp_list(workloads.RETAIL_730, 730)
    assert [t for s, t in listed if s == "train"] == [D(1995, 7, 2)]
    assert [t for s, t in timeline.stamp_list(workloads.RETAIL, 365, min_history=365) if s == "train"] == [D(1998, 7, 1), D(1997, 7, 1), D(1996, 7, 1)]
    dense = [t for s, t in timeline.stamp_list(workloads.RETAIL, 365, stride=91, min_history=365) if s == "train"]
    assert max(dense) == D(1998, 7, 1) and min(dense) >= D(1996, 1, 1)


def test_a_split_whose_validation_window_passes_the_test_time_is_refused():
    books = timeline.SplitSpec(D(2014, 1, 21), D(2016, 1, 1), D(1996, 6, 25), D(2018, 9, 28))
    with pytest.raises(ValueError):
        books.check(730)
    assert books.check(730, allow_overrun=True)
    assert timeline.SplitSpec(D(2019, 1, 1), D(2021, 1, 1), D(2009, 2, 2), D(2023, 9, 3)).check(730)
    with pytest.raises(ValueError):
        timeline.SplitSpec(D(2019, 1, 1), D(2023, 1, 1), D(2009, 2, 2), D(2023, 9, 3)).check(730)


def test_windows_are_open_below_and_closed_above(store):
    split = timeline.SplitSpec(D(2000, 1, 10), D(2000, 1, 20), D(2000, 1, 1), D(2000, 2, 20))
    spec = tasks.TaskSpec("v", "cust", 10, tasks.Label("sum", F.col("price")), look_back=10)
    got = {(r["seed_time"].day, r["cust"]): r["label"] for r in tasks.build_task_table(spec, store["tx"], split).filter("split <> 'train' and cust is not null").collect()}
    # at the 10th the row of that moment is past and that of the 20th is future; at the 20th rows of the 10th are too old
    assert got == {(10, 1): 7.0, (20, 1): 0.0, (20, 2): 8.0}
    churn = tasks.with_label(spec, "absent", "binary")
    got = {(r["seed_time"].day, r["cust"]): r["label"] for r in tasks.build_task_table(churn, store["tx"], split).filter("split <> 'train' and cust is not null").collect()}
    assert got == {(10, 1): 0, (20, 1): 1, (20, 2): 0}


GOLD = {
    "customer_churn": {"train": (351, 80), "val": (116, 28), "test": (116, 28)},
    "customer_churn_730": {"train": (83, 3), "val": (144, 7), "test": (143, 14)},
    "user_engagement": {"train": (165, 98), "val": (15, 6), "test": (15, 8)},
    "order_attention": {"train": (1622, 139), "val": (230, 25), "test": (222, 23)},
}


@pytest.mark.parametrize("name", GOLD)
def test_golden_counts(spark, sf, name):
    rows = getattr(workloads, name)(spark, sf).groupBy("split").agg(F.count("*").alias("n"), F.count(F.when(F.col("label") > 0, 1)).alias("p")).collect()
    assert {r["split"]: (r["n"], r["p"]) for r in rows} == GOLD[name]


def test_value_range(spark, sf):
    r = {r["split"]: r for r in tasks.describe(workloads.customer_value(spark, sf)).collect()}
    assert (r["train"]["hi"], r["val"]["hi"], r["test"]["hi"]) == (25470.70, 23694.50, 18184.00) and r["train"]["lo"] == 0


def test_arithmetic_stamps_equal_the_range_join(spark, sf):
    facts = datasets.table(spark, sf, "events").select("event_id", "ts")
    first, n = D(2024, 1, 5), 9
    fast = timeline.matching_stamps(facts, "ts", first, 2, n, 5, 2)
    stamps = timeline.stamps_frame(spark, [("x", D(2024, 1, 5 + 2 * k)) for k in range(n)])
    slow = facts.join(stamps, (F.col("ts") > F.col("seed_time") - C.days(5)) & (F.col("ts") <= F.col("seed_time") + C.days(2)))
    a = {(r["event_id"], r["seed_time"]) for r in fast.collect()}
    assert a == {(r["event_id"], r["seed_time"]) for r in slow.collect()} and a


def test_link_negatives_are_no_positives(spark, sf):
    pos = tasks.link_positives(datasets.purchases(spark, sf), "c_custkey", "p_partkey", timeline.stamps(spark, workloads.RETAIL, 365, min_history=365), 365)
    neg = tasks.link_negatives(pos, "c_custkey", "p_partkey", 200, 2)
    assert neg.count() > 0 and neg.join(pos, pos.columns).count() == 0


def test_mined_tasks_build(spark, sf):
    mined = tasks.mine_tasks({"orders": ("c_custkey", "o_totalprice")}, 180)
    facts = datasets.table(spark, sf, "orders").select(F.col("o_custkey").alias("c_custkey"), F.col("o_orderdate").alias("ts"), "o_totalprice")
    for spec in mined:
        assert tasks.build_task_table(spec, facts, workloads.RETAIL).count() > 100


# ---------------------------------------------------------------- sampling


def edges_of(cut):
    return sorted((r["hop"], r["src"], r["dst"]) for r in cut.edges.collect())


def seed(spark, nid, t=T, ntype="customers"):
    return spark.createDataFrame([(f"{nid}|{t:%Y-%m-%d}", t, ntype, nid)], "seed_id string, seed_time timestamp_ntz, ntype string, nid bigint")


def test_past_only_and_rows_without_time_are_seen(spark, store):
    cut = sampling.cut_slice(store, seed(spark, 1), [None], sampling.Strategy("all"), [("tx.cust", True)])
    assert edges_of(cut) == [(1, 100, 1), (1, 102, 1), (1, 103, 1)]
    cut = sampling.cut_slice(store, seed(spark, 2), [None], sampling.Strategy("all"), [("tx.cust", True)])
    assert edges_of(cut) == [(1, 104, 2)]


def test_latest_breaks_ties_by_key(spark, store):
    cut = sampling.cut_slice(store, seed(spark, 1), [2], sampling.Strategy("latest"), [("tx.cust", True)])
    assert edges_of(cut) == [(1, 100, 1), (1, 102, 1)]


def test_an_old_parent_does_not_let_its_future_children_in(spark):
    parents = spark.createDataFrame([(1, D(1999, 1, 1))], "id bigint, ts timestamp_ntz")
    children = spark.createDataFrame([(5, 1, D(1999, 6, 1)), (6, 1, D(2001, 1, 1))], "id bigint, up bigint, ts timestamp_ntz")
    db = Database.of([TableSpec("p", parents, "id", "ts"), TableSpec("c", children, "id", "ts")], [LinkSpec("c", "up", "p")])
    cut = sampling.cut_slice(db, seed(spark, 1, ntype="p"), [9], sampling.Strategy("latest"))
    assert edges_of(cut) == [(1, 5, 1)]
    frontier = parents.select(F.col("id").alias("nid"), F.col("ts").alias("node_ts"), F.lit(T).cast("timestamp_ntz").alias("seed_time"))
    assert tasks.audit_leaks(sampling.printed_filter_leaks(db, db.links[0], frontier)).first()["n_leaks"] == 1


def test_unions_keep_shared_parents_once_and_the_seed(spark, store):
    cut = sampling.cut_slice(store, seed(spark, 1), [9, 9, 9], sampling.Strategy("latest"))
    nodes = {(r["ntype"], r["nid"]): r["hop"] for r in cut.nodes.collect()}
    assert nodes[("customers", 1)] == 0 and nodes[("products", 10)] == 2 and nodes[("tx", 106)] == 3
    both = [e for e in edges_of(cut) if e[0] == 2 and e[1] == 10]
    assert len(both) == 3  # three transactions reach the same product
    packed = cut.pack().first()
    assert len(packed["edges"]) == len(edges_of(cut))


def test_slices_equal_the_reference_and_keep_the_bound(spark, sf):
    from rowgraph.queries_graph import seeds, two_hops

    cut = two_hops(spark, sf)
    got = {}
    for r in cut.edges.collect():
        got.setdefault(int(r["seed_id"].split("|")[0]), set()).add((r["hop"], r["src"], r["dst"]))
    orders, lines = {}, {}
    for r in datasets.table(spark, sf, "orders").collect():
        orders.setdefault(r["o_custkey"], []).append((r["o_orderkey"], r["o_orderdate"]))
    for r in datasets.keyed_lines(datasets.table(spark, sf, "lineitem")).collect():
        lines.setdefault(r["l_orderkey"], []).append((r["l_id"], r["l_shipdate"]))
    for s in seeds(spark, sf).collect():
        assert got.get(s["nid"], set()) == set(ref.slice_edges([orders, lines], s["nid"], D(2000, 7, 1), [8, 4]))
    assert cut.sizes().agg(F.max("n_nodes")).first()[0] <= graph.receptive_bound([8, 4])


def test_shared_slices_equal_own_ones_for_latest(spark, sf):
    from rowgraph.queries_graph import two_hops

    a, b = (two_hops(spark, sf, share=s).edges.select("seed_id", "hop", "src", "dst") for s in (False, True))
    assert a.exceptAll(b).count() == 0 and b.exceptAll(a).count() == 0


def test_future_rows_change_nothing(spark, sf):
    db, links = datasets.open_retail(spark, sf), [("orders.o_custkey", True), ("lineitem.l_orderkey", True)]
    from rowgraph.queries_graph import seeds

    at = D(2000, 7, 1)
    cut = lambda d: sampling.cut_slice(d, seeds(spark, sf), [3, 2], sampling.Strategy("uniform"), links).edges.select("seed_id", "hop", "src", "dst")
    a, b = cut(db), cut(db.visible(at))
    assert a.exceptAll(b).count() == 0 and b.exceptAll(a).count() == 0


def test_draws_follow_their_weights(spark):
    rows = spark.range(2000).withColumn("w", F.explode(F.array(F.lit(1.0), F.lit(3.0)))).withColumn("child", F.col("w").cast("bigint"))
    u = C.hash_unit(C.draw(F.lit("s"), F.col("id"), F.col("child")))
    first = sampling.pick(rows.withColumn("k", C.race_key(u, F.col("w"))), ["id"], 1, [F.col("k")])
    share = first.filter("child = 3").count() / 2000
    assert abs(share - 0.75) < 0.04
    drawn = sampling.with_replacement(rows.withColumnRenamed("id", "dst"), ["dst"], 4, F.col("w"))
    assert drawn.count() == 8000 and abs(drawn.filter("child = 3").count() / 8000 - 0.75) < 0.03


def test_sampling_reads_keys_and_times_only(spark, sf):
    db = datasets.open_retail(spark, sf)
    cut = sampling.cut_slice(db, seed(spark, 1, D(2000, 7, 1), "customer"), [4], sampling.Strategy("latest"), [("orders.o_custkey", True)])
    plan = cut.edges._jdf.queryExecution().executedPlan().toString()
    assert "o_totalprice" not in plan and "o_orderpriority" not in plan and "WindowGroupLimit" in plan


def test_stamp_literals_reach_the_scan(spark, sf):
    plan = datasets.open_retail(spark, sf).visible(D(1997, 1, 1))["orders"]._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [Or(IsNull(o_orderdate),LessThanOrEqual" in plan


# ---------------------------------------------------------------- passing, encoders, measures


def test_passes_do_not_depend_on_order(spark, sf):
    from rowgraph.queries_graph import mp_typed_sum

    a = mp_typed_sum(spark, sf)
    b = mp_typed_sum(spark, sf).repartition(7)
    assert a.exceptAll(b).count() == 0


def test_pools(spark):
    state = spark.createDataFrame([(1, 10), (2, 20)], "nid bigint, h bigint")
    got = spark.createDataFrame([(1, 1), (1, 5)], "nid bigint, h bigint")
    for kind, want in (("sum", 16), ("max", 15), ("min", 11), ("count", 12), ("mean", 13)):
        out = {r["nid"]: r["h"] for r in passing.pass_typed(state, [(got, lambda c: c)], ["nid"], kind).collect()}
        assert out == {1: want, 2: 20}
    side = passing.pass_typed(state, [(got, lambda c: c), (got, lambda c: c)], ["nid"], outer="concat").filter("nid = 1").first()
    assert (side["h"], side["h_0"], side["h_1"]) == (10, 6, 6)
    folded = passing.pool_fold(got.withColumn("o", F.col("h")), "nid", "h", ["o"]).first()["folded"]
    assert folded == 0.5 * 1 + 5


def test_encoders(spark):
    df = spark.createDataFrame([(1, 1.0, "a"), (2, 3.0, "b"), (3, None, "a"), (4, 5.0, None)], "k bigint, x double, c string")
    e = encode.TableEncoder([encode.Numeric("x"), encode.Category("c", 1), encode.Category("c", 4, hashed=True), encode.Text("c", 4)]).fit(df)
    x = {r["k"]: r["x"] for r in e.transform(df, ["k"]).collect()}
    assert x[3][:2] == [0.0, 1.0] and x[2][:2] == [0.0, 0.0] and x[1][2:4] == [1.0, 0.0] and x[4][2:4] == [0.0, 1.0]
    assert len({len(v) for v in x.values()}) == 1
    import pandas as pd

    udf = encode.pretrained(lambda s: s.map(lambda b: [float(len(b))]))
    got = spark.createDataFrame([(b"abc",)], "img binary").select(udf("img").alias("v")).first()["v"]
    assert got == [3.0] and pd is not None


def test_average_precision_and_ties(spark):
    for rows in ([(1, 0.9), (0, 0.9), (1, 0.5), (0, 0.1)], [(1, 1.0), (1, 0.3)], [(0, 1.0), (1, 1.0), (0, 1.0)], [(0, 0.2), (0, 0.1)], [(i % 3 == 0, float(i * 7919 % 101)) for i in range(400)]):
        rows = [(int(y), float(s)) for y, s in rows]
        got = metrics.average_precision(spark.createDataFrame(rows, "label int, score double")).first()["ap"]
        want = ref.average_precision(rows)
        assert (got is None and want is None) or got == pytest.approx(want)
    constant = spark.createDataFrame([(1, 0.0), (0, 0.0), (0, 0.0), (0, 0.0)], "label int, score double")
    assert metrics.average_precision(constant).first()["ap"] == 0.25
    assert metrics.roc_auc(constant).first()["auc"] == 0.5


def test_link_measures(spark):
    ranked = spark.createDataFrame([(1, 10, 3.0), (1, 11, 2.0), (1, 12, 1.0), (2, 10, 1.0)], "s bigint, d bigint, score double")
    truth = spark.createDataFrame([(1, 11), (1, 12), (2, 13)], "s bigint, d bigint")
    assert metrics.recall_at_k(ranked, truth, ["s"], "d", 2).first()["recall"] == 0.25
    assert metrics.map_at_k(ranked, truth, ["s"], "d", 2).first()["map"] == pytest.approx((0.25 + 0) / 2)


def test_sql_functions(spark):
    C.register_functions(spark)
    assert spark.sql("select visible_at(null, timestamp_ntz'2000-01-01') a, in_future(timestamp_ntz'2000-01-02', timestamp_ntz'2000-01-01', 1) b, hash_unit('x') c").first()[:2] == (True, True)
    assert [r[0] for r in spark.sql("select * from stamps_between('2000-01-01', '2000-01-10', 4)").collect()] == ["2000-01-01", "2000-01-05", "2000-01-09"]


# ---------------------------------------------------------------- sources and sinks


def test_files(spark, tmp_path):
    df = spark.createDataFrame([(1, "a"), (2, "b")], "k int, v string")
    for fmt in ("parquet", "csv", "json", "orc"):
        io.write(df, f"{tmp_path}/{fmt}", fmt=fmt)
        assert sorted(map(tuple, io.read(spark, fmt, f"{tmp_path}/{fmt}", "k int, v string").collect())) == [(1, "a"), (2, "b")]
    (tmp_path / "bin").mkdir()
    (tmp_path / "bin" / "x").write_bytes(b"\x01")
    assert io.read(spark, "binaryFile", f"{tmp_path}/bin").count() == 1
    with pytest.raises(ValueError):
        io.read(spark, "csv", f"{tmp_path}/csv")
    assert io.jdbc_options("u", "t", "k", 0, 9, 3)["numPartitions"] == "3"
    io.write(df, f"{tmp_path}/p", ["k"])
    assert io.read(spark, "parquet", f"{tmp_path}/p").filter("k = 1").count() == 1


def test_views(spark, store):
    store.register("t_")
    assert spark.sql("select count(*) from t_tx join t_customers on cust = c").first()[0] == 7
