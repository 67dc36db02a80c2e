"""Pairs whose sides are packed once for each seed against pairs that carry their slices."""

import numpy as np
import pandas as pd

from rowgraph.operators import train


def test_flat_pairs_give_the_same_loss_gradients_and_scores(spark):
    rng = np.random.default_rng(3)
    sides, seeds = [], []
    for k, n in enumerate((5, 4)):
        model = train.Model(f"s{k}", {f"s{k}": 2, f"c{k}": 3}, [(f"c{k}.fk", f"s{k}")], d=6)
        rows = []
        for i in range(n):
            m = i % 4  # a seed without rows too
            rows.append((f"{k}-{i}", 0.0, rng.random(2).round(3).tolist(), [1] * m, [f"c{k}.fk"] * m, [f"c{k}"] * m, [str(i)] * m, [f"{i}-{j}" for j in range(m)], rng.random((m, 3)).round(3).tolist()))
        sides.append(model)
        seeds.append(spark.createDataFrame(rows, train.PACKED))
    pairs = [(f"{i}|{j}", float((i + j) % 2), f"0-{i}", f"1-{j}") for i in range(5) for j in range(4) if i != 2 or j < 2]
    rows = spark.createDataFrame(pairs, "seed_id string, label double, side_0 string, side_1 string")
    order = lambda df: df.toPandas().sort_values("seed_id").reset_index(drop=True)
    whole = order(train.pack_tuples(rows, seeds))
    flat = order(train.pack_flat_tuples(rows, [train.flat_slices(s) for s in seeds]))
    assert len(whole) == len(flat) == len(pairs)
    for kind, hidden in (("dot", 0), ("bilinear", 0), ("mlp", 4), ("pool", 4)):
        model = train.TupleModel(sides, kind, hidden).init(2)
        (a, g), (b, h) = model.loss_and_grad(model.batch(whole)), model.loss_and_grad(model.batch(flat))
        assert abs(a - b) < 1e-9 and all(np.allclose(g[k], h[k]) for k in g)
        assert np.allclose(model.score(whole), model.score(flat))
        assert sum(len(x["x0"]) for x in model.batch(flat)["sides"]) == 9  # each seed once
        empty = model.batch(flat.iloc[:0])
        assert empty["n"] == 0 and isinstance(flat, pd.DataFrame)
