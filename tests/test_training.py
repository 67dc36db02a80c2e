import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from rowgraph.operators import metrics as train_metrics
from rowgraph.operators import train
from rowgraph.queries_features import planted_models, planted_values


def toy(loss="logistic", pool="mean", classes=1, **more):
    rng = np.random.default_rng(0)
    rows = []
    for i in range(6):
        hop, link, kinds, dst, src, feats = [], [], [], [], [], []
        for k in range(3):
            hop.append(1), link.append("f.e"), kinds.append("f"), dst.append(str(i)), src.append(f"f{i}{k}"), feats.append([rng.normal()])
        for k in range(3):
            hop.append(2), link.append("f.i^"), kinds.append("i"), dst.append(f"f{i}{k}"), src.append(f"i{k % 2}"), feats.append([rng.normal(), 1.0])
        rows.append({"seed_id": str(i), "label": [float(i % 2), float(i % 3 == 0)] if loss == "multilabel" else float(i % max(2, classes)), "x": [rng.normal()], "hop": hop, "link": link, "src_type": kinds, "dst": dst, "src": src, "feats": feats})
    model = train.Model("e", {"e": 1, "f": 1, "i": 2}, [("f.e", "e"), ("f.i^", "f")], d=5, loss=loss, pool=pool, classes=classes, **more).init(1)
    return model, pd.DataFrame(rows)


KINDS = [("logistic", "mean", 1, {}), ("squared", "sum", 1, {}), ("softmax", "mean", 3, {"hidden": 4}), ("absolute", "mean", 1, {}), ("logistic", "max", 1, {"hidden": 3}), ("multilabel", "mean", 2, {})]
KINDS += [("squared", "mean", 1, {"fuse": "residual"}), ("squared", "mean", 1, {"fuse": "mean", "spans": {"i": [1, 1]}}), ("squared", "mean", 1, {"share": {"e": "one", "f": "one"}})]


@pytest.mark.parametrize(("loss", "pool", "classes", "more"), KINDS)
def test_gradients_by_finite_differences(loss, pool, classes, more):
    model, pdf = toy(loss, pool, classes, **more)
    check_gradients(model, pdf)


def check_gradients(model, pdf):
    b = model.batch(pdf)
    _, g = model.loss_and_grad(b)
    rng = np.random.default_rng(2)
    for name, p in model.params.items():
        for _ in range(4):
            at = tuple(rng.integers(0, s) for s in p.shape)
            old, eps = p[at], 1e-6
            p[at] = old + eps
            up = model.loss_and_grad(b)[0]
            p[at] = old - eps
            down = model.loss_and_grad(b)[0]
            p[at] = old
            assert g[name][at] == pytest.approx((up - down) / (2 * eps), rel=1e-4, abs=1e-5)


def test_frozen_encoders_do_not_move():
    model, pdf = toy()
    model.frozen = ("enc",)
    g = model.loss_and_grad(model.batch(pdf))[1]
    assert all((v == 0).all() for k, v in g.items() if k.startswith("enc")) and (g["head"] != 0).any()


@pytest.mark.parametrize("sync", ["grad", "average"])
def test_losses_fall_and_tasks_train_jointly(spark, sync):
    model, pdf = toy()
    other, pdf2 = toy()
    schema = train.PACKED
    a, b = spark.createDataFrame(pdf, schema).repartition(2).cache(), spark.createDataFrame(pdf2.assign(label=1 - pdf2["label"]), schema).cache()
    history = train.fit([model], [a], steps=8, rate=0.1, sync=sync)
    assert history[-1] < history[0]
    model, _ = toy()
    train.fit([model, other], [a, b], steps=2)
    assert model.params["head"] is other.params["head"]
    assert train.predict(model, a).filter(F.col("score").isNull()).count() == 0


def test_a_signal_two_hops_away_is_learnt_and_entity_columns_cannot_see_it(spark):
    got = dict(planted_models(spark, 300, 40))
    assert got["two hops"] > 0.9 > 0.75 > got["entity only"] and got["two hops"] > got["base rate"] + 0.2


def test_a_value_two_hops_away_is_learnt_and_entity_columns_cannot_see_it(spark):
    got = dict(planted_values(spark, 300, 50))
    assert got["two hops"] < 0.4 < 0.7 < min(got["entity only"], got["median"])


def pairs(n=3, kind="dot", hidden=0):
    """Rows of two or three sides of one kind, as a model over tuples takes them."""
    sides = [toy(loss="squared") for _ in range(n)]
    model = train.TupleModel([m for m, _ in sides], kind, hidden).init(2)
    frame = pd.DataFrame({"seed_id": [str(i) for i in range(6)], "label": [float(i % 2) for i in range(6)]})
    for k, (_, pdf) in enumerate(sides):
        turned = pdf.iloc[[(i + k) % 6 for i in range(6)]].reset_index(drop=True)
        frame = pd.concat([frame, turned[train._COLUMNS].add_prefix(f"{k}_")], axis=1)
    return model, frame


@pytest.mark.parametrize(("n", "kind", "hidden"), [(2, "dot", 0), (2, "bilinear", 0), (2, "mlp", 4), (3, "mlp", 0), (3, "pool", 4)])
def test_heads_over_several_vectors(n, kind, hidden):
    model, frame = pairs(n, kind, hidden)
    check_gradients(model, frame)


def test_links_are_learnt(spark):
    """Whether two rows go together depends on both: the signs of their attributes are equal."""
    rng = np.random.default_rng(5)
    x = rng.choice([-1.0, 1.0], size=(240, 2)).tolist()
    none = {"hop": [], "link": [], "src_type": [], "dst": [], "src": [], "feats": []}
    rows = [{"seed_id": str(i), "label": float(a == b), **{f"{k}_{c}": v for k, z in ((0, a), (1, b)) for c, v in {"x": [z], **none}.items()}} for i, (a, b) in enumerate(x)]
    schema = "seed_id string, label double, " + ", ".join(f"{k}_{c} {t}" for k in (0, 1) for c, t in (x.strip().split(" ", 1) for x in train.PACKED.split(", ")[2:]))
    frame = spark.createDataFrame(pd.DataFrame(rows), schema).repartition(2).cache()
    for kind, hidden in (("dot", 0), ("mlp", 8)):
        model = train.TupleModel([train.Model("a", {"a": 1}, [], d=6), train.Model("b", {"b": 1}, [], d=6)], kind, hidden).init(4)
        train.fit([model], [frame.filter("cast(seed_id as int) < 160")], steps=50, rate=0.1)
        scored = train.predict(model, frame.filter("cast(seed_id as int) >= 160"))
        assert train_metrics.average_precision(scored).first()["ap"] > {"dot": 0.75, "mlp": 0.95}[kind]


def test_averaged_copies_do_not_see_each_other(spark):
    """Partitions that one worker goes through in turn give what they give alone."""
    model, pdf = toy()
    big = pd.concat([pdf.assign(seed_id=str(k)) for k in range(8)], ignore_index=True)
    frame = spark.createDataFrame(big, train.PACKED)
    at = {k: v.copy() for k, v in model.params.items()}
    parts = frame.repartition(6, "seed_id").cache()
    train.fit([model], [parts], steps=1, rate=0.3, sync="average")
    rows, total = parts.select(F.spark_partition_id().alias("p"), "*").toPandas(), 0.0
    for _, own in rows.groupby("p"):
        alone = train.Model(model.seed_type, model.sizes, model.links, 5, params={k: v.copy() for k, v in at.items()})
        for _ in range(5):
            _, g = alone.loss_and_grad(alone.batch(own.reset_index(drop=True)))
            alone.params = {k: v - 0.3 * g[k] / len(own) for k, v in alone.params.items()}
        total = total + train._flat(alone.params) * len(own)
    assert np.allclose(train._flat(model.params), total / len(rows), atol=1e-9)


def test_several_labels_are_learnt_and_predicted(spark):
    model, pdf = toy("multilabel", classes=2)
    frame = spark.createDataFrame(pdf, train.PACKED.replace("label double", "label array<double>")).repartition(2).cache()
    history = train.fit([model], [frame], steps=10, rate=0.1)
    assert history[-1] < history[0] and all(len(r["score"]) == 2 for r in train.predict(model, frame).collect())


def test_encoders_that_are_shared_are_one():
    model, _ = toy(share={"e": "one", "f": "one"})
    assert "enc:one" in model.params and not {"enc:e", "enc:f"} & set(model.params)
    with pytest.raises(ValueError):
        toy(share={"e": "one", "i": "one"})


def test_heads():
    rng = np.random.default_rng(0)
    a, b = rng.normal(size=(4, 3)), rng.normal(size=(4, 3))
    assert np.allclose(train.link_score(a, b), np.einsum("ij,ij->i", a, b))
    assert np.allclose(train.link_score(a, b, "bilinear", np.eye(3)), train.link_score(a, b))
    with pytest.raises(ValueError):
        train.link_score(a, b, "mlp", np.ones(6))
    z, y = rng.normal(size=(4, 2)), np.array([[0, 1], [1, 1], [0, 0], [1, 0]])
    loss, g = train.multilabel_loss(z, y)
    eps = 1e-6
    z2 = z.copy()
    z2[1, 0] += eps
    assert (train.multilabel_loss(z2, y)[0] - loss) / eps == pytest.approx(g[1, 0], abs=1e-4)


def test_every_model_of_a_task_is_scored_by_its_predictions(spark, sf, monkeypatch):
    """The board's numbers against plain loops over the predictions, which cover every test row under every model."""
    from tests.ref import average_precision
    from rowgraph import queries_models
    from rowgraph.operators import board
    from rowgraph.plans import workloads

    rows = queries_models.predictions(spark, sf, "engagement", 3, 2).cache()
    wanted = {(r["seed_time"], r["user_id"]) for r in workloads.user_engagement(spark, sf).filter("split = 'test'").collect()}
    by = {}
    for r in rows.filter("split = 'test'").collect():
        by.setdefault(r["model"], {})[(r["seed_time"], r["user_id"])] = (r["label"], r["score"])
    assert set(by) == {"network", "hand features", "entity only", "constant"} and all(set(v) == wanted for v in by.values())
    for name, found in by.items():
        got = board.evaluate(rows.filter(F.col("split") == "test").filter(F.col("model") == name), "binary", "engagement", name).first()
        assert got["value"] == pytest.approx(average_precision(list(found.values())))


def test_a_task_is_scored_by_its_own_rows(spark, sf):
    from rowgraph.plans import tasks, workloads
    from rowgraph.sources.datasets import open_activity

    table = workloads.user_engagement(spark, sf)
    spec = tasks.TaskSpec("engagement", "user_id", 2, tasks.Label("exists"), eligible="ever", kind="binary")
    task = tasks.Task(spec, table, open_activity(spark, sf), workloads.ACTIVITY)
    said = table.select("seed_time", "user_id", F.col("label").cast("double").alias("score"))
    assert task.score(said, "oracle").first()["value"] == 1 and task.train.count() + task.val.count() + task.test.count() == table.count()
    assert task.inputs["events"].filter(F.col("ts") > F.lit(workloads.ACTIVITY.t_test).cast("timestamp_ntz")).count() == 0
    with pytest.raises(Exception, match="without a prediction"):
        task.score(said.limit(1), "lazy").collect()
