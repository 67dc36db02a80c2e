"""Slices whose rows bring their features along against slices that get them by joins."""

from dataclasses import replace
from datetime import datetime as D

import numpy as np
import pytest
from pyspark.sql import functions as F

from rowgraph.catalog import Database, LinkSpec, TableSpec
from rowgraph.operators import sampling, train

LINKS = [("b.fk", True), ("c.fk", True)]
TIMES = [D(2000, 1, 1), D(2000, 2, 1), D(2000, 4, 1)]


def shop(spark):
    """Children with equal times, none, later than every stamp, without a parent, and one parent with many of them."""
    rng = np.random.default_rng(4)
    day = lambda k: None if k % 11 == 0 else D(1999, 11, 1 + int(k % 9)) if k % 2 else D(2000, 1 + int(k % 6), 1)
    a = [(k, [float(k), 1.0]) for k in range(6)]
    b = [(k, None if k % 13 == 5 else 0 if k < 40 else int(rng.integers(1, 5)), day(k), [float(k % 7), 0.5]) for k in range(70)]
    c = [(k, 60 if k < 50 else int(rng.integers(0, 70)), day(k + 3), [float(k % 5), 0.25, 2.0]) for k in range(260)]
    return Database.of(
        [
            TableSpec("a", spark.createDataFrame(a, "id bigint, x array<float>"), "id"),
            TableSpec("b", spark.createDataFrame(b, "id bigint, fk bigint, ts timestamp_ntz, x array<float>"), "id", "ts"),
            TableSpec("c", spark.createDataFrame(c, "id bigint, fk bigint, ts timestamp_ntz, x array<float>"), "id", "ts"),
        ],
        [LinkSpec("b", "fk", "a"), LinkSpec("c", "fk", "b")],
    )


def seeds_and_labels(spark):
    task = spark.createDataFrame([("train" if k < 2 else "test", t, n) for k, t in enumerate(TIMES) for n in range(6)], "split string, seed_time timestamp_ntz, id bigint")
    seeds = sampling.seeds_of(task, "id", "a")
    return seeds, seeds.join(task.withColumnRenamed("id", "nid"), ["nid", "seed_time"]).withColumn("label", F.col("nid") * 1.5)


def test_carried_slices_have_the_same_edges(spark):
    db, (seeds, _) = shop(spark), seeds_and_labels(spark)
    for caps, links in (([3, 2], LINKS), ([2], LINKS[:1]), ([100, 100], LINKS)):
        whole = sampling.cut_slice(db, seeds, caps, sampling.Strategy("latest"), links).edges
        carried = sampling.cut_slice(db, seeds, caps, sampling.Strategy("latest"), links, carry="x")
        got = sorted(map(repr, carried.edges.select(*whole.columns).collect()))
        assert got and got == sorted(map(repr, whole.collect()))
        # however many rows a node has, its array is bounded by the cap and the stamps
        assert carried.kids.agg(F.max(F.size("kids"))).first()[0] <= caps[0] * len(TIMES)


def test_carried_slices_of_no_seed_are_empty(spark):
    db, (seeds, _) = shop(spark), seeds_and_labels(spark)
    assert sampling.cut_slice(db, seeds.limit(0), [3, 2], sampling.Strategy("latest"), LINKS, carry="x").edges.count() == 0


@pytest.mark.parametrize("wrong", [{"strategy": sampling.Strategy("uniform")}, {"links": [("b.fk", True), ("b.fk", False)]}, {"caps": [3, None]}, {"share": True}])
def test_features_are_carried_by_latest_picks_down_a_chain_only(spark, wrong):
    given = {"caps": [3, 2], "strategy": sampling.Strategy("latest"), "links": LINKS, **wrong}
    with pytest.raises(ValueError):
        sampling.cut_slice(shop(spark), seeds_and_labels(spark)[0], carry="x", **given)


def test_laid_out_batches_train_and_score_like_packed_ones(spark):
    db, (seeds, joined) = shop(spark), seeds_and_labels(spark)
    feats = {n: db[n].select(F.col("id").alias("nid"), "x") for n in "abc"}
    cut = lambda **more: sampling.cut_slice(db, seeds, [3, 2], sampling.Strategy("latest"), LINKS, **more)
    packed = train.pack_features(cut(), joined, feats, age=True).join(joined.select("seed_id", "split"), "seed_id").cache()
    model = train.Model("a", {"a": 2, "b": 3, "c": 4}, [("b.fk", "a"), ("c.fk", "b")], d=5, loss="squared")
    laid = train.prepared(model, train.pack_features(cut(carry="x"), joined, {"a": feats["a"]}, age=True)).cache()
    assert {r["split"] for r in laid.collect()} == {"train", "test"}
    for loss in ("squared", "absolute"):
        one, two = (replace(model, params={}, loss=loss).init(3) for _ in range(2))
        before = train.fit([one], [packed.filter("split = 'train'").drop("split")], steps=6, rate=0.05)
        after = train.fit([two], [laid.filter("split = 'train'")], steps=6, rate=0.05)
        assert np.allclose(before, after) and all(np.allclose(one.params[k], two.params[k]) for k in one.params)
        said = lambda m, rows: {r["seed_id"]: (r["label"], r["score"]) for r in train.predict(m, rows).collect()}
        want, got = said(one, packed.filter("split = 'test'")), said(two, laid.filter("split = 'test'"))
        assert len(want) == 6 and set(want) == set(got) and all(np.allclose(want[k], got[k]) for k in want)


def test_tasks_learnt_together_are_prepared_once(spark, sf, monkeypatch):
    """All trainings and the test rows read one set of batches for each task."""
    from rowgraph import queries_models

    made, prepared = [], train.prepared
    monkeypatch.setattr(train, "prepared", lambda model, packed: made.append(model.seed_type) or prepared(model, packed))
    rows = queries_models.train_together(spark, sf).collect()
    assert sorted(made) == ["customer", "part"]
    assert {(r["task"], r["model"]) for r in rows} == {(t, m) for t in ("customer value", "part sales") for m in ("together", "alone")} and all(r["value"] > 0 for r in rows)
