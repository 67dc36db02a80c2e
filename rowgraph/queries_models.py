"""The four tasks under every model: the trained network, hand features and the entity's own columns under boosted trees,
and a constant; and models of links, several labels and classes."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .catalog import Database
from .operators import baselines, board, encode, sampling, train
from .plans import tasks, timeline, workloads
from .plans.timeline import SplitSpec
from .registry import registry
from .sources.datasets import open_activity, open_retail, purchases, table

QUERIES, ORACLE, query = registry()
S = SparkSession


@dataclass(frozen=True)
class Setup:
    """What a task's models read: its table and database, slices, encoders, and facts for hand features."""

    build: Callable[[S, str], DataFrame]
    kind: str
    key: str
    ntype: str
    open_: Callable[[S, str], Database]
    split: SplitSpec
    links: list[tuple[str, bool]]
    caps: list[int]
    encoders: dict[str, list]
    facts: Callable[[S, str], DataFrame]
    value: str
    widths: tuple[int, ...]
    numbers: tuple[str, ...]
    categories: tuple[str, ...] = ()
    scale: float = 1.0
    delta: int = 365
    stamps: dict = field(default_factory=dict)


def _retail(spark: S, d: str) -> Database:
    return open_retail(spark, d, workloads.RETAIL.t_test)


def _activity(spark: S, d: str) -> Database:
    return open_activity(spark, d).visible(workloads.ACTIVITY.t_test)


def _lines(spark: S, d: str) -> DataFrame:
    return table(spark, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), F.col("l_shipdate").alias("ts"), "l_quantity")


def _events(spark: S, d: str) -> DataFrame:
    return table(spark, d, "events").select("user_id", "ts", "value")


_CUSTOMER = [encode.Numeric("c_acctbal"), encode.Category("c_mktsegment", 5)]
_ORDERS = [encode.Numeric("o_totalprice"), encode.Category("o_orderstatus", 3)]
_LINE = [encode.Numeric("l_quantity"), encode.Numeric("l_discount")]
_SPEND = Setup(workloads.customer_churn, "binary", "c_custkey", "customer", _retail, workloads.RETAIL, [("orders.o_custkey", True), ("lineitem.l_orderkey", True)], [6, 3], {"customer": _CUSTOMER, "orders": _ORDERS, "lineitem": _LINE}, purchases, "p_retailprice", (7, 30, 90, 365), ("c_acctbal",), ("c_mktsegment",), stamps={"min_history": 365})
SETUPS = {
    "churn": _SPEND,
    "value": replace(_SPEND, build=workloads.customer_value, kind="regression", scale=1000.0),
    "engagement": Setup(workloads.user_engagement, "binary", "user_id", "customer", _activity, workloads.ACTIVITY, [("events.user_id", True)], [10], {"customer": _CUSTOMER, "events": [encode.Numeric("value"), encode.Category("event_type", 5)]}, _events, "value", (1, 2, 4, 7), ("c_acctbal",), ("c_mktsegment",), delta=2),
    "attention": Setup(workloads.order_attention, "regression", "o_orderkey", "orders", _retail, workloads.RETAIL, [("lineitem.l_orderkey", True), ("orders.o_custkey", False)], [8], {"orders": _ORDERS, "lineitem": [*_LINE, encode.Category("l_returnflag", 3)], "customer": _CUSTOMER}, _lines, "l_quantity", (30, 90, 365), ("o_totalprice",), ("o_orderstatus",), delta=182, stamps={"min_history": 365}),
}


def _encoders(db: Database, s: Setup) -> tuple[dict[str, encode.TableEncoder], dict[str, int]]:
    """Fitted encoders and sizes of the types' features; rows that aren't seeds have their age besides."""
    fitted, sizes = {}, {}
    for name, encoders in s.encoders.items():
        spec = db.tables[name]
        fitted[name] = encode.TableEncoder(encoders).fit(spec.df, spec.time, s.split.t_val)
        sizes[name] = len([c for e in fitted[name].encoders for c in e.columns()]) + (name != s.ntype)
    return fitted, sizes


def packed_task(spark: S, d: str, s: Setup) -> tuple[DataFrame, dict[str, int], list[tuple[str, str]]]:
    """Packed slices with split, seed_time and key, sizes of the types' features, and the model's links."""
    db, task = s.open_(spark, d), s.build(spark, d)
    seeds = sampling.seeds_of(task, s.key, s.ntype)
    labels = task.select(F.col(s.key).cast("bigint").alias("nid"), "seed_time", "split", (F.col("label") / s.scale).alias("label"))
    cut = sampling.cut_slice(db, seeds, s.caps, sampling.Strategy("latest"), s.links)
    joined = seeds.join(labels, ["nid", "seed_time"])
    fitted, sizes = _encoders(db, s)
    feats = {name: f.transform(db[name].withColumnRenamed(db.tables[name].pk, "nid"), ["nid"]) for name, f in fitted.items()}
    packed = train.pack_features(cut, joined, feats, age=True).join(joined.select("seed_id", "split", "seed_time", F.col("nid").alias(s.key)), "seed_id")
    links = []
    for name, down in s.links:
        x = next(y for y in db.links if y.name == name)
        links.append((name if down else f"{name}^", x.parent if down else x.child))
    return packed, sizes, links


def laid_task(spark: S, d: str, s: Setup, splits: tuple[str, ...]) -> tuple[DataFrame, dict[str, int], list[tuple[str, str]]]:
    """The same for a chain of downward links and some splits: slices laid out as plain numbers, with split.

    The task table is kept, as stamps and labelled seeds are read from it, one of each row; rows of the slices bring their
    features along.
    """
    db, task = s.open_(spark, d), s.build(spark, d).filter(F.col("split").isin(*splits)).cache()
    seeds = sampling.seeds_of(task, s.key, s.ntype)
    labelled = task.select(*sampling.seed_columns(s.key, s.ntype), "split", (F.col("label") / s.scale).alias("label"))
    fitted, sizes = _encoders(db, s)
    tables = {n: replace(t, df=fitted[n].transform(t.df, t.df.columns, "x")) if n in fitted and n != s.ntype else t for n, t in db.tables.items()}
    cut = sampling.cut_slice(replace(db, tables=tables), seeds, s.caps, sampling.Strategy("latest"), s.links, carry="x")
    own = fitted[s.ntype].transform(db[s.ntype].withColumnRenamed(db.tables[s.ntype].pk, "nid"), ["nid"])
    return train.pack_features(cut, labelled, {s.ntype: own}, age=True), sizes, [(x.name, x.parent) for n, _ in s.links for x in db.links if x.name == n]


def predictions(spark: S, d: str, name: str, steps: int = 10, trees: int = 3) -> DataFrame:
    """model, split, seed_time, key, label, score of the validation and test rows under each model of a task."""
    s, out = SETUPS[name], []
    packed, sizes, links = packed_task(spark, d, s)
    packed = packed.repartition(8, "seed_id").cache()
    model = train.Model(s.ntype, sizes, links, d=8, loss="logistic" if s.kind == "binary" else "absolute", hidden=8).init(5)
    train.fit([model], [packed.filter("split = 'train'").drop("split", "seed_time", s.key)], steps=steps, rate=0.05)
    rest = packed.filter("split <> 'train'")
    scored = train.predict(model, rest.drop("split", "seed_time", s.key)).select("seed_id", F.col("score") * s.scale)
    task = s.build(spark, d)
    named = rest.select("seed_id", "split", "seed_time", s.key).join(scored.toDF("seed_id", "score"), "seed_id")
    keys = ["split", "seed_time", s.key]
    out.append(task.join(named, keys).select(F.lit("network").alias("model"), *keys, "label", "score"))
    spec = s.open_(spark, d).tables[s.ntype]
    listed = timeline.stamps(spark, s.split, s.delta, **s.stamps)
    recent = baselines.recent_features(task, s.facts(spark, d), s.key, s.value, s.widths, listed)
    flat = baselines.flat_table(task, spec.df.withColumnRenamed(spec.pk, s.key), s.key, [*s.numbers, *s.categories], recent).cache()
    hand = [f"{p}_{w}" for w in s.widths for p in ("n", "sum")]
    for which, inputs in (("hand features", [*s.numbers, *hand]), ("entity only", list(s.numbers))):
        fitted = baselines.fit_boosted(flat, "label", s.kind, inputs, s.categories, trees=trees, depth=3)
        out.append(baselines.boosted_scores(fitted, flat.filter("split <> 'train'"), s.kind).select(F.lit(which).alias("model"), *keys, "label", "score"))
    if s.kind == "binary":
        out.append(task.filter("split <> 'train'").select(F.lit("constant").alias("model"), *keys, "label", F.lit(0.0).alias("score")))
    else:
        out.append(baselines.constant(task).filter("split <> 'train'").select(F.lit("constant").alias("model"), *keys, "label", F.col("y_hat").cast("double").alias("score")))
    return reduce(DataFrame.unionByName, out)


def compared(spark: S, d: str, name: str) -> DataFrame:
    """task, model, metric, value on the test rows, one row for each model of a task."""
    s = SETUPS[name]
    rows = predictions(spark, d, name).filter("split = 'test'").withColumn("y_hat", F.col("score")).cache()
    return reduce(DataFrame.unionByName, [board.evaluate(rows.filter(F.col("model") == m), s.kind, name, m) for m in ("network", "hand features", "entity only", "constant")])


def _register(name: str) -> None:
    query(f"compare_{name}")(lambda spark, d: compared(spark, d, name))


for _name in SETUPS:
    _register(_name)


# ------------------------------------------------------------------------------------ links, classes, several labels, two tasks


def _ranked_pairs(spark: S, d: str) -> DataFrame:
    """split, seed_time, c_custkey, p_partkey, label: pairs of the last train and of the test stamp, bought or drawn."""
    stamps = timeline.stamps(spark, workloads.RETAIL, 365, min_history=365).filter("split = 'test' or seed_time = timestamp_ntz '1998-07-01'")
    pos = tasks.link_positives(purchases(spark, d), "c_custkey", "p_partkey", stamps, 365)
    neg = tasks.link_negatives(pos, "c_custkey", "p_partkey", table(spark, d, "part").count())
    both = pos.withColumn("label", F.lit(1.0)).unionByName(neg.withColumn("label", F.lit(0.0)))
    return both.select("split", "seed_time", "c_custkey", "p_partkey", "label")


@query("train_links")
def train_links(spark: S, d: str) -> DataFrame:
    """Average precision on the test stamp's pairs of a two-tower model, of sales so far, and of chance.

    A side's slice is packed once for each seed, as plain numbers, and pairs get it by a join for one split at a time.
    """
    db, pairs = _retail(spark, d), _ranked_pairs(spark, d).cache()
    sides = []
    for key, ntype, link, encoders, child in (("c_custkey", "customer", "orders.o_custkey", _CUSTOMER, _ORDERS), ("p_partkey", "part", "lineitem.l_partkey", [encode.Numeric("p_retailprice"), encode.Numeric("p_size")], _LINE)):
        feats, sizes = {}, {}
        for name, own in ((ntype, encoders), (link.split(".")[0], child)):
            spec = db.tables[name]
            fitted = encode.TableEncoder(own).fit(spec.df, spec.time, workloads.RETAIL.t_val)
            feats[name] = fitted.transform(spec.df.withColumnRenamed(spec.pk, "nid"), ["nid"])
            sizes[name] = len([c for e in fitted.encoders for c in e.columns()]) + (name != ntype)
        sides.append((key, ntype, link, feats, train.Model(ntype, sizes, [(link, ntype)], d=8)))
    day = F.date_format("seed_time", "yyyy-MM-dd")

    def rows_of(split: str) -> DataFrame:
        own, flats = pairs.filter(F.col("split") == split), []
        for key, ntype, link, feats, _ in sides:
            seeds = sampling.seeds_of(own.select(key, "seed_time").distinct(), key, ntype)
            cut = sampling.cut_slice(db, seeds, [4], sampling.Strategy("latest"), [(link, True)])
            flats.append(train.flat_slices(train.pack_features(cut, seeds.withColumn("label", F.lit(0.0)), feats, age=True)))
        named = own.select(*(F.concat_ws("|", key, day).alias(f"side_{k}") for k, (key, *_) in enumerate(sides)), "label")
        return train.pack_flat_tuples(named.withColumn("seed_id", F.concat_ws("|", "side_0", "side_1")), flats)

    model = train.TupleModel([m for *_, m in sides], "mlp", hidden=8).init(2)
    train.fit([model], [rows_of("train").drop("seed_id")], steps=8, rate=0.05)
    test = train.predict(model, rows_of("test")).select("label", "score").cache()
    sold = purchases(spark, d).filter(F.col("ts") <= F.lit(workloads.RETAIL.t_test).cast("timestamp_ntz")).groupBy("p_partkey").agg(F.count("*").alias("n"))
    by_sales = pairs.filter("split = 'test'").join(sold, "p_partkey", "left").select("label", F.coalesce("n", F.lit(0)).cast("double").alias("score")).cache()
    out = [("two towers", test), ("sales so far", by_sales), ("chance", by_sales.withColumn("score", F.lit(0.0)))]
    return reduce(DataFrame.unionByName, [board.evaluate(r, "binary", "links", m) for m, r in out])


@query("train_classes")
def train_classes(spark: S, d: str) -> DataFrame:
    """Accuracy of a softmax head over stored vectors, and of the most frequent class, on rows that were held out."""
    task = workloads.multiclass_embeddings(spark, d)
    vectors = table(spark, d, "embeddings").select("vec_id", F.col("embedding").alias("x"))
    none = {"hop": "array<int>", "link": "array<string>", "src_type": "array<string>", "dst": "array<string>", "src": "array<string>", "feats": "array<array<float>>"}
    rows = task.join(vectors, "vec_id").select("split", F.col("vec_id").cast("string").alias("seed_id"), F.col("label").cast("double").alias("label"), "x", *(F.array().cast(t).alias(c) for c, t in none.items())).cache()
    model = train.Model("embeddings", {"embeddings": 64}, [], d=16, loss="softmax", classes=10).init(1)
    train.fit([model], [rows.filter("split = 'train'").drop("split")], steps=40, rate=0.05)
    rest = rows.filter("split <> 'train'").drop("split")
    said = train.predict(model, rest).withColumn("y_hat", F.col("score"))
    most = rows.filter("split = 'train'").groupBy("label").count().agg(F.max_by("label", F.struct("count", "label")).alias("y_hat"))
    usual = rest.crossJoin(F.broadcast(most))
    return board.evaluate(said, "multiclass", "embedding class", "softmax").unionByName(board.evaluate(usual, "multiclass", "embedding class", "most frequent"))


@query("train_labels")
def train_labels(spark: S, d: str) -> DataFrame:
    """Average precision of two labels learnt together from a document's words, its language's and its source's rows."""
    task = workloads.multilabel_task(spark, d)
    docs = table(spark, d, "documents")
    coded = encode.TableEncoder([encode.Numeric("n_chars"), encode.Text("text", 16)]).fit(docs).transform(docs, ["doc_id"])
    up = docs.select("doc_id", F.explode(F.array(F.struct(F.lit("documents.source").alias("link"), F.lit("source").alias("t"), F.col("source").alias("k")), F.struct(F.lit("documents.lang").alias("link"), F.lit("lang").alias("t"), F.col("lang").alias("k")))).alias("e"))
    places = F.pmod(F.xxhash64("e.k"), F.lit(8))
    hot = F.transform(F.sequence(F.lit(0), F.lit(7)), lambda i: (i == places).cast("float"))
    edges = up.groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct(F.lit(1).alias("hop"), F.concat(F.col("e.link"), F.lit("^")).alias("link"), F.col("e.t").alias("src_type"), F.col("doc_id").cast("string").alias("dst"), F.col("e.k").alias("src"), hot.alias("feats")))).alias("e"))
    rows = task.join(coded, "doc_id").join(edges, "doc_id").select("split", F.col("doc_id").cast("string").alias("seed_id"), F.col("label").cast("array<double>").alias("label"), "x", *(F.col(f"e.{c}").alias(c) for c in ("hop", "link", "src_type", "dst", "src", "feats"))).cache()
    model = train.Model("documents", {"documents": 18, "source": 8, "lang": 8}, [("documents.source^", "documents"), ("documents.lang^", "documents")], d=8, loss="multilabel", classes=2, hidden=8).init(3)
    train.fit([model], [rows.filter("split = 'train'").drop("split")], steps=25, rate=0.05)
    got = train.predict(model, rows.filter("split <> 'train'").drop("split")).cache()
    one = lambda k: got.select(F.col("label")[k].alias("label"), F.col("score")[k].alias("score"))
    out = [board.evaluate(one(k) if m == "network" else one(k).withColumn("score", F.lit(0.0)), "binary", t, m) for k, t in enumerate(("quality", "toxic")) for m in ("network", "constant")]
    return reduce(DataFrame.unionByName, out)


@query("train_together")
def train_together(spark: S, d: str) -> DataFrame:
    """Customer value and part sales learnt with one encoder of lines, and each by itself: mean absolute error on the test rows.

    Slices are laid out and made into batches once, for all trainings and the test rows.
    """
    lines = [("lineitem.l_partkey", True)]
    parts = replace(SETUPS["value"], build=workloads.part_sales, key="p_partkey", ntype="part", links=lines, caps=[6], encoders={"part": [encode.Numeric("p_retailprice"), encode.Numeric("p_size")], "lineitem": _LINE}, scale=10.0, delta=182)
    setups = {"customer value": SETUPS["value"], "part sales": parts}
    ready = {}
    for name, s in setups.items():
        packed, sizes, links = laid_task(spark, d, s, ("train", "test"))
        model = train.Model(s.ntype, sizes, links, d=8, loss="absolute")
        ready[name] = (train.prepared(model, packed).persist(StorageLevel.DISK_ONLY), model)
    out = []
    for mode in ("together", "alone"):
        models = {n: replace(m, params={}).init(7) for n, (_, m) in ready.items()}
        for name, m in models.items():
            # heads are each task's own
            m.params = {(f"head:{name}" if k == "head" else k): v for k, v in m.params.items()}
        groups = [list(models)] if mode == "together" else [[n] for n in models]
        for g in groups:
            named = [_Own(models[n], f"head:{n}") for n in g]
            train.fit(named, [ready[n][0].filter("split = 'train'") for n in g], steps=10, rate=0.05)
            for n, m in zip(g, named, strict=True):
                scale = setups[n].scale
                got = train.predict(m, ready[n][0].filter("split = 'test'")).select((F.col("label") * scale).alias("label"), (F.col("score") * scale).alias("y_hat"))
                out.append(board.evaluate(got, "regression", n, mode))
    return reduce(DataFrame.unionByName, out)


@dataclass
class _Own:
    """A model whose head is kept under a name of its own, so that the other parameters can be shared with another task."""

    model: train.Model
    head: str
    params: dict = field(default_factory=dict)

    def __post_init__(self):
        self.params = self.params or self.model.params

    def _plain(self) -> train.Model:
        return replace(self.model, params={("head" if k == self.head else k): v for k, v in self.params.items()})

    def batch(self, pdf):
        return self.model.batch(pdf)

    def loss_and_grad(self, b):
        loss, g = self._plain().loss_and_grad(b)
        return loss, {(self.head if k == "head" else k): v for k, v in g.items()}

    def score(self, pdf):
        return self._plain().score(pdf)
