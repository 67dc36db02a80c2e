"""A typed message-passing network over packed slices, trained with numpy in the executors.

Slices are layered: features of hop-2 rows are pooled into hop-1 rows, those into the seed.  Columns of a row are fused by
type, every link has a linear message, and heads are on one seed or on several seeds' vectors together.
"""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .sampling import Slice, picked_at

PACKED = "seed_id string, label double, x array<float>, hop array<int>, link array<string>, src_type array<string>, dst array<string>, src array<string>, feats array<array<float>>"
_COLUMNS = ["x", "hop", "link", "src_type", "dst", "src", "feats"]
#: Seeds in a batch of index arrays.
BATCH = 2048


def _label(seeds: DataFrame) -> Column:
    return F.col("label").cast("array<double>" if dict(seeds.dtypes)["label"].startswith("array") else "double")


def pack_features(cut: Slice, seeds: DataFrame, features: dict[str, DataFrame], age: bool = False) -> DataFrame:
    """One row per seed: label, its own features x, and parallel arrays over its edges with the source row's features.

    With ``age`` each source row's features get one more: its age in years at the seed time (0 without a time).

    ``seeds`` has seed_id, seed_time, ntype, nid and label, a number or (several labels) an array; ``features`` has per type (nid, x).

    A slice that carries its rows' features is laid out hop by hop instead, as plain numbers: x_k are the features of hop k's
    rows one after the other, n_k how many of them each row of the hop before has.  Other columns of ``seeds`` are kept.
    """
    if cut.kids is not None:
        return _laid_out(cut, seeds, features, age)
    parts = []
    for name, f in features.items():
        e = cut.edges.filter(F.col("src_type") == name).join(f.select(F.col("nid").alias("src"), "x"), "src")
        if age:
            years = F.coalesce(F.datediff("seed_time", "ts") / 365.0, F.lit(0.0)).cast("float")
            e = e.withColumn("x", F.concat("x", F.array(years)))
        parts.append(e.select("seed_id", "hop", "link", "src_type", F.col("dst").cast("string"), F.col("src").cast("string"), "x"))
    edges = parts[0]
    for p in parts[1:]:
        edges = edges.unionByName(p)
    rows = F.array_sort(F.collect_list(F.struct("hop", "link", "dst", "src", "src_type", "x")))
    packed = edges.groupBy("seed_id").agg(rows.alias("e"))
    ntype = seeds.select("ntype").first()["ntype"]
    own = seeds.join(features[ntype], "nid").select("seed_id", _label(seeds).alias("label"), "x")
    out = own.join(packed, "seed_id", "left")
    pull = lambda n: F.coalesce(F.transform("e", lambda s: s[n]), F.array().cast(dict(hop="array<int>", x="array<array<float>>").get(n, "array<string>")))
    return out.select("seed_id", "label", "x", *(pull(n).alias("feats" if n == "x" else n) for n in ("hop", "link", "src_type", "dst", "src", "x")))


def _picking(t: Column, m: int):
    return lambda k: F.coalesce(picked_at(k["kids"], t, m), F.array())


def _laid_out(cut: Slice, seeds: DataFrame, features: dict[str, DataFrame], age: bool) -> DataFrame:
    (own,), t = features.values(), F.col("seed_time")
    others = [c for c in seeds.columns if c not in ("seed_id", "seed_time", "ntype", "nid", "label")]
    out = seeds.join(own.select("nid", "x"), "nid").join(cut.kids, "nid", "left")
    out = out.select("seed_id", "seed_time", *others, _label(seeds).alias("label"), "x", F.coalesce(picked_at(F.col("kids"), t, cut.caps[0]), F.array()).alias("at_1"))
    for hop, m in enumerate(cut.caps[1:], 2):
        below = F.transform(f"at_{hop - 1}", _picking(t, m))
        out = out.withColumn(f"of_{hop}", below).withColumn(f"at_{hop}", F.flatten(f"of_{hop}"))

    def numbers(k: Column) -> Column:
        years = F.coalesce(F.datediff(t, k["ts"]) / 365.0, F.lit(0.0)).cast("float")
        return F.concat(k["x"], F.array(years)) if age else k["x"]

    hops = []
    for hop in range(1, len(cut.caps) + 1):
        many = F.array(F.size("at_1")) if hop == 1 else F.transform(f"of_{hop}", F.size)
        hops += [many.cast("array<int>").alias(f"n_{hop}"), F.flatten(F.transform(f"at_{hop}", numbers)).alias(f"x_{hop}")]
    return out.select("seed_id", *others, "label", "x", *hops)


def flat_slices(packed: DataFrame) -> DataFrame:
    """seed_id, flat: features alone of slices of one hop over one link, the seed's own first, then those of its rows."""
    return packed.select("seed_id", F.concat("x", F.flatten("feats")).alias("flat"))


def relu(x: np.ndarray) -> np.ndarray:
    return np.maximum(x, 0)


def with_one(x: np.ndarray) -> np.ndarray:
    return np.hstack([x, np.ones((len(x), 1))])


@dataclass
class Model:
    """Parameters by name.  Types and links are known from their feature sizes and names.

    ``fuse`` makes a row's vector of its columns: "linear" (side by side, one linear map), "mean" (each column of ``spans``
    through its own map and ReLU, then the mean) or "residual" (linear plus a second layer over its ReLU).  Types that
    ``share`` maps to one name have one encoder.  ``hidden`` is the width of the head's hidden layer, 0 for a linear head.
    Losses: logistic, softmax, squared, absolute, and multilabel (a logistic loss for each of ``classes`` labels).
    """

    seed_type: str
    sizes: dict[str, int]
    links: list[tuple[str, str]]
    d: int = 16
    loss: str = "logistic"
    pool: str = "mean"
    classes: int = 1
    frozen: tuple[str, ...] = ()
    params: dict[str, np.ndarray] = field(default_factory=dict)
    fuse: str = "linear"
    spans: dict[str, list[int]] = field(default_factory=dict)
    share: dict[str, str] = field(default_factory=dict)
    hidden: int = 0

    def init(self, seed: int = 0) -> Model:
        rng = np.random.default_rng(seed)
        p: dict[str, np.ndarray] = {}
        for t, n in sorted(self.sizes.items()):
            name = self._encoder(t)
            if name in p:
                if len(p[name]) != self._rows(t):
                    raise ValueError(f"{t} can't share the encoder of rows of another size")
                continue
            p[name] = rng.standard_normal((self._rows(t), self.d)) / np.sqrt(n + 1)
            if self.fuse == "residual":
                p[f"{name}:more"] = rng.standard_normal((self.d, self.d)) / np.sqrt(self.d)
        for name, _ in sorted(self.links):
            p[f"msg:{name}"] = rng.standard_normal((self.d, self.d)) / np.sqrt(self.d)
        p.update(_mlp_init(rng, "head", self.d, self.hidden, self.classes))
        self.params = p
        return self

    def _encoder(self, kind: str) -> str:
        return f"enc:{self.share.get(kind, kind)}"

    def _widths(self, kind: str) -> list[int]:
        return self.spans.get(kind) or [1] * self.sizes[kind]

    def _rows(self, kind: str) -> int:
        return self.sizes[kind] + (len(self._widths(kind)) if self.fuse == "mean" else 1)

    # ---------------------------------------------------------------- batches

    def batch(self, pdf: pd.DataFrame) -> dict:
        """Index arrays of a batch of packed slices; a row met twice in a hop of one seed is one node."""
        n = len(pdf)
        out = {"x0": np.array(pdf["x"].tolist(), float).reshape(n, -1), "y": np.array(pdf["label"].tolist(), float) if "label" in pdf else None, "n": n, "hops": []}
        sizes = [len(h) for h in pdf["hop"]]
        flat = {c: np.array([v for row in pdf[c] for v in row], object if c == "feats" else None) if sum(sizes) else np.zeros(0) for c in ("hop", "link", "src_type", "dst", "src")}
        feats = [v for row in pdf["feats"] for v in row]
        owner = np.repeat(np.arange(n), sizes)
        parent_of = dict(self.links)
        places = pd.Series(np.arange(n), index=pd.MultiIndex.from_arrays([np.arange(n), [""] * n, [""] * n]) if n else None)
        for hop in range(1, int(flat["hop"].max(initial=0)) + 1):
            at = np.flatnonzero(flat["hop"] == hop)
            links, kinds, own = flat["link"][at], flat["src_type"][at], owner[at]
            if hop == 1:
                target = places.reindex(pd.MultiIndex.from_arrays([own, [""] * len(at), [""] * len(at)])).to_numpy()
            else:
                target = places.reindex(pd.MultiIndex.from_arrays([own, [parent_of[x] for x in links], flat["dst"][at]])).to_numpy()
            met = ~np.isnan(target.astype(float))
            at, links, kinds, own, target = at[met], links[met], kinds[met], own[met], target[met].astype(int)
            key = pd.MultiIndex.from_arrays([own, kinds, flat["src"][at]])
            node, distinct = pd.factorize(key)
            first = np.unique(node, return_index=True)[1]
            groups = [(k, rows := np.flatnonzero(kinds[first] == k), np.array([feats[at[first[r]]] for r in rows], float)) for k in sorted(set(kinds[first].tolist()))]
            edges = {k: (node[links == k], target[links == k]) for k in sorted(set(links.tolist()))}
            out["hops"].append({"groups": groups, "edges": edges, "n": len(distinct)})
            places = pd.Series(np.arange(len(distinct)), index=distinct)
        return out

    def batch_flat(self, flats: list[np.ndarray]) -> dict:
        """The same of ``flat_slices``; the model has one link, and the other type is that of its rows."""
        (link, _), width = self.links[0], self.sizes[self.seed_type]
        kind = next(t for t in self.sizes if t != self.seed_type)
        wide, n = self.sizes[kind], len(flats)
        values = np.concatenate(flats) if n else np.zeros(0)
        ends = np.cumsum([len(v) for v in flats], dtype=int)
        starts = ends - np.diff(ends, prepend=0)
        many = (ends - starts - width) // wide
        target = np.repeat(np.arange(n), many)
        turn = np.arange(len(target)) - np.repeat(np.cumsum(many) - many, many)
        x = values[(starts[target] + width + turn * wide)[:, None] + np.arange(wide)]
        hop = {"groups": [(kind, np.arange(len(x)), x)], "edges": {link: (np.arange(len(x)), target)}, "n": len(x)}
        return {"x0": values[starts[:, None] + np.arange(width)], "y": None, "n": n, "hops": [hop] if len(x) else []}

    def batch_laid(self, b: dict) -> dict:
        """The same of ``laid`` arrays; the model's links are the chain's, hop by hop."""
        out = {"x0": b["x"][0], "y": b["y"], "n": len(b["x"][0]), "hops": []}
        every = slice(None)
        for (link, _), x, many in zip(self.links, b["x"][1:], b["many"], strict=True):
            if not len(x):
                break
            out["hops"].append({"groups": [(link.split(".")[0], every, x)], "edges": {link: (every, np.repeat(np.arange(len(many)), many))}, "n": len(x)})
        return out

    # ---------------------------------------------------------------- forward and backward

    def _encode(self, kind: str, x: np.ndarray) -> tuple:
        """A row's vector, and what its gradient needs."""
        w = self.params[self._encoder(kind)]
        if self.fuse == "mean":
            at, base, parts, z = 0, 0, [], 0.0
            for k in self._widths(kind):
                full = with_one(x[:, at : at + k])
                pre = full @ w[base : base + k + 1]
                parts.append((full, pre, slice(base, base + k + 1)))
                z = z + relu(pre)
                at, base = at + k, base + k + 1
            return parts, z / len(parts)
        full = with_one(x)
        z = full @ w
        if self.fuse == "residual":
            return (full, z), z + relu(z) @ self.params[f"{self._encoder(kind)}:more"]
        return full, z

    def _encode_back(self, kind: str, kept, dz: np.ndarray, g: dict[str, np.ndarray]) -> None:
        name = self._encoder(kind)
        if self.fuse == "mean":
            for full, pre, rows in kept:
                g[name][rows] += full.T @ (dz * (pre > 0)) / len(kept)
            return
        if self.fuse == "residual":
            full, z = kept
            g[f"{name}:more"] += relu(z).T @ dz
            dz = dz + (dz @ self.params[f"{name}:more"].T) * (z > 0)
            kept = full
        g[name] += kept.T @ dz

    def _pooled(self, h: np.ndarray, s: np.ndarray, t: np.ndarray, n: int) -> tuple:
        if self.pool == "max":
            top = np.full((n, self.d), -np.inf)
            np.maximum.at(top, t, h[s])
            top[np.isinf(top)] = 0
            hit = (h[s] == top[t]).astype(float)
            ties = np.zeros((n, self.d))
            np.add.at(ties, t, hit)
            return top, hit / np.maximum(ties[t], 1)
        pooled = _summed(h[s], t, n)
        count = np.ones(n) if self.pool == "sum" else np.maximum(np.bincount(t, minlength=n), 1)
        return pooled / count[:, None], (1 / count[t])[:, None]

    def embed(self, b: dict) -> dict:
        """Vectors of the seeds (``h``) and all that their gradient needs."""
        levels = [{"n": b["n"], "groups": [(self.seed_type, np.arange(b["n"]), b["x0"])], "edges": {}}]
        levels += [{"n": h["n"], "groups": h["groups"], "edges": {}} for h in b["hops"]]
        for lv, h in zip(levels, b["hops"]):
            lv["edges"] = h["edges"]
        for k in range(len(levels) - 1, -1, -1):
            lv = levels[k]
            lv["z"], lv["kept"], lv["links"] = np.zeros((lv["n"], self.d)), [], []
            for kind, at, x in lv["groups"]:
                kept, z = self._encode(kind, x)
                if isinstance(at, slice):
                    lv["z"] += z
                else:
                    lv["z"][at] += z
                lv["kept"].append((kind, at, kept))
            for link, (s, t) in lv["edges"].items():
                pooled, share = self._pooled(levels[k + 1]["h"], s, t, lv["n"])
                lv["z"] += pooled @ self.params[f"msg:{link}"]
                lv["links"].append((link, s, t, pooled, share))
            lv["h"] = relu(lv["z"])
        return {"levels": levels, "h": levels[0]["h"]}

    def back(self, f: dict, dh: np.ndarray, g: dict[str, np.ndarray]) -> None:
        """Adds to ``g`` the gradient of a loss whose gradient by the seeds' vectors is ``dh``."""
        for k, lv in enumerate(f["levels"]):
            dz = dh * (lv["z"] > 0)
            for kind, at, kept in lv["kept"]:
                self._encode_back(kind, kept, dz[at], g)
            if k < len(f["levels"]) - 1:
                dh = np.zeros((f["levels"][k + 1]["n"], self.d))
                for link, s, t, pooled, share in lv["links"]:
                    g[f"msg:{link}"] += pooled.T @ dz
                    near = (dz @ self.params[f"msg:{link}"].T)[t] * share
                    dh += near if isinstance(s, slice) else _summed(near, s, len(dh))

    def loss_and_grad(self, b: dict) -> tuple[float, dict[str, np.ndarray]]:
        """Sum of losses over the batch and its gradient."""
        b = self.batch_laid(b) if "many" in b else b
        f, g = self.embed(b), {k: np.zeros_like(v) for k, v in self.params.items()}
        out, kept = _mlp(self.params, "head", f["h"])
        loss, d = loss_of(self.loss, out, b["y"])
        self.back(f, _mlp_back(self.params, "head", kept, d, g), g)
        return loss, _freeze(g, self.frozen)

    def outputs(self, pdf: pd.DataFrame | dict) -> np.ndarray:
        b = self.batch_laid(pdf) if isinstance(pdf, dict) else self.batch(pdf)
        return _mlp(self.params, "head", self.embed(b)["h"])[0]

    def score(self, pdf: pd.DataFrame | dict) -> np.ndarray:
        out = self.outputs(pdf)
        return out.argmax(axis=1).astype(float) if self.loss == "softmax" else out[:, 0]


def _freeze(g: dict[str, np.ndarray], frozen: tuple[str, ...]) -> dict[str, np.ndarray]:
    for k in g:
        if k.split(":")[0] in frozen:
            g[k][:] = 0
    return g


def _mlp_init(rng, name: str, n_in: int, hidden: int, n_out: int) -> dict[str, np.ndarray]:
    if not hidden:
        return {name: rng.standard_normal((n_in + 1, n_out)) * 0.1}
    return {f"{name}:first": rng.standard_normal((n_in + 1, hidden)) / np.sqrt(n_in + 1), name: rng.standard_normal((hidden + 1, n_out)) * 0.1}


def _mlp(p: dict, name: str, x: np.ndarray) -> tuple[np.ndarray, tuple]:
    full, pre = with_one(x), None
    if f"{name}:first" in p:
        pre = full @ p[f"{name}:first"]
    top = full if pre is None else with_one(relu(pre))
    return top @ p[name], (full, pre, top)


def _mlp_back(p: dict, name: str, kept: tuple, d: np.ndarray, g: dict) -> np.ndarray:
    """Adds the layers' gradients and returns that by the input."""
    full, pre, top = kept
    g[name] += top.T @ d
    d = d @ p[name][:-1].T
    if pre is None:
        return d
    d = d * (pre > 0)
    g[f"{name}:first"] += full.T @ d
    return d @ p[f"{name}:first"][:-1].T


def loss_of(kind: str, out: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
    """Sum of losses and its gradient by the outputs."""
    if kind == "logistic":
        z = out[:, 0]
        return float(np.logaddexp(0, z).sum() - (y * z).sum()), (1 / (1 + np.exp(-z)) - y)[:, None]
    if kind == "multilabel":
        return multilabel_loss(out, y)
    if kind == "softmax":
        z = out - out.max(axis=1, keepdims=True)
        logs = z - np.log(np.exp(z).sum(axis=1, keepdims=True))
        at = (np.arange(len(y)), y.astype(int))
        d = np.exp(logs)
        d[at] -= 1
        return -float(logs[at].sum()), d
    e = out[:, 0] - y
    if kind == "absolute":
        return float(np.abs(e).sum()), np.sign(e)[:, None]
    if kind == "squared":
        return float((e * e).sum() / 2), e[:, None]
    raise ValueError(f"no loss {kind}")


def multilabel_loss(z: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
    """Sum of logistic losses over labels, and its gradient."""
    return float(np.logaddexp(0, z).sum() - (y * z).sum()), 1 / (1 + np.exp(-z)) - y


# ------------------------------------------------------------------ heads on two or more vectors


@dataclass
class TupleModel:
    """A head over the vectors of several seeds of one row: links (two) and tuples.

    ``sides`` are models without use of their own heads, whose parameters are shared by name; packed rows have each side's
    columns with its number in front (0_x, 1_hop, ...).  Kinds: "dot" and "bilinear" of two vectors, "mlp" over all side by
    side, "pool" over their mean; the latter two with a hidden layer where ``hidden`` is set.
    """

    sides: list[Model]
    kind: str = "dot"
    hidden: int = 0
    loss: str = "logistic"
    frozen: tuple[str, ...] = ()
    params: dict[str, np.ndarray] = field(default_factory=dict)

    def init(self, seed: int = 0) -> TupleModel:
        if self.kind in ("dot", "bilinear") and len(self.sides) != 2:
            raise ValueError(f"{self.kind} is of two vectors")
        p, d, rng = {}, self.sides[0].d, np.random.default_rng(seed)
        for k, side in enumerate(self.sides):
            for name, v in side.init(seed + k).params.items():
                if not name.startswith("head"):
                    p.setdefault(name, v)
        if self.kind == "dot":
            p["pair"] = np.zeros((1, 1))
        elif self.kind == "bilinear":
            p["pair"] = np.eye(d) + rng.standard_normal((d, d)) * 0.01
        else:
            p.update(_mlp_init(rng, "pair", d * (len(self.sides) if self.kind == "mlp" else 1), self.hidden, 1))
        self.params = p
        return self

    def batch(self, pdf: pd.DataFrame) -> dict:
        out = {"n": len(pdf), "y": np.array(pdf["label"].tolist(), float) if "label" in pdf else None}
        if "0_flat" in pdf:
            # a seed that several rows share is there once
            out["sides"], out["at"] = [], []
            for k, side in enumerate(self.sides):
                at, distinct = pd.factorize(pdf[f"side_{k}"])
                first = np.full(len(distinct), len(at))
                np.minimum.at(first, at, np.arange(len(at)))
                flats = pdf[f"{k}_flat"].to_numpy()
                out["sides"].append(side.batch_flat([flats[i] for i in first]))
                out["at"].append(at.astype(np.int32))
            return out
        out["sides"] = [side.batch(pdf[[f"{k}_{c}" for c in _COLUMNS]].set_axis(_COLUMNS, axis=1)) for k, side in enumerate(self.sides)]
        return out

    def _joined(self, b: dict) -> tuple[np.ndarray, list[dict], object]:
        for side in self.sides:
            side.params = self.params
        f = [side.embed(x) for side, x in zip(self.sides, b["sides"], strict=True)]
        h = [x["h"] for x in f] if "at" not in b else [x["h"][at] for x, at in zip(f, b["at"], strict=True)]
        if self.kind in ("dot", "bilinear"):
            left = h[0] @ self.params["pair"] if self.kind == "bilinear" else h[0]
            return (left * h[1]).sum(axis=1, keepdims=True) + (self.params["pair"] if self.kind == "dot" else 0), f, h
        out, kept = _mlp(self.params, "pair", np.hstack(h) if self.kind == "mlp" else np.mean(h, axis=0))
        return out, f, kept

    def loss_and_grad(self, b: dict) -> tuple[float, dict[str, np.ndarray]]:
        out, f, kept = self._joined(b)
        g = {k: np.zeros_like(v) for k, v in self.params.items()}
        loss, d = loss_of(self.loss, out, b["y"])
        if self.kind == "dot":
            g["pair"] += d.sum()
            dh = [d * kept[1], d * kept[0]]
        elif self.kind == "bilinear":
            w = self.params["pair"]
            g["pair"] += (kept[0] * d).T @ kept[1]
            dh = [d * (kept[1] @ w.T), d * (kept[0] @ w)]
        else:
            dx = _mlp_back(self.params, "pair", kept, d, g)
            dh = np.split(dx, len(f), axis=1) if self.kind == "mlp" else [dx / len(f)] * len(f)
        if "at" in b:
            dh = [_summed(y, at, len(x["h"])) for x, y, at in zip(f, dh, b["at"], strict=True)]
        for side, x, y in zip(self.sides, f, dh, strict=True):
            side.back(x, y, g)
        return loss, _freeze(g, self.frozen)

    def score(self, pdf: pd.DataFrame) -> np.ndarray:
        return self._joined(self.batch(pdf))[0][:, 0]


def pack_tuples(rows: DataFrame, sides: list[DataFrame]) -> DataFrame:
    """seed_id, label and each side's packed columns for ``rows`` (seed_id, label, side_0, side_1, ... seed ids of packed sides)."""
    out = rows
    for k, side in enumerate(sides):
        out = out.join(side.select(F.col("seed_id").alias(f"side_{k}"), *(F.col(c).alias(f"{k}_{c}") for c in _COLUMNS)), f"side_{k}")
    return out.select("seed_id", F.col("label").cast("double").alias("label"), *(f"{k}_{c}" for k in range(len(sides)) for c in _COLUMNS))


def pack_flat_tuples(rows: DataFrame, sides: list[DataFrame]) -> DataFrame:
    """``rows`` (seed_id, label, side_0, side_1, ...) with each side's flat slice; the last join is by side 0, so its rows lie together."""
    out = rows
    for k in reversed(range(len(sides))):
        out = out.join(sides[k].select(F.col("seed_id").alias(f"side_{k}"), F.col("flat").alias(f"{k}_flat")), f"side_{k}")
    return out.select(*rows.columns, *(f"{k}_flat" for k in range(len(sides))))


def _summed(x: np.ndarray, at: np.ndarray, n: int) -> np.ndarray:
    """Rows of x added up by their place."""
    return np.stack([np.bincount(at, weights=c, minlength=n) for c in x.T], axis=1)


def link_score(a: np.ndarray, b: np.ndarray, kind: str = "dot", w: np.ndarray | None = None) -> np.ndarray:
    """Score of pairs of stored vectors: dot, or bilinear (w: d x d).  Heads that are learned are those of ``TupleModel``."""
    if kind not in ("dot", "bilinear"):
        raise ValueError(f"no score {kind}")
    return ((a if kind == "dot" else a @ w) * b).sum(axis=1)


# ------------------------------------------------------------------ training


def _flat(p: dict[str, np.ndarray]) -> np.ndarray:
    return np.concatenate([p[k].ravel() for k in sorted(p)])


def _unflat(model, v: np.ndarray) -> dict[str, np.ndarray]:
    out, at = {}, 0
    for k in sorted(model.params):
        n = model.params[k].size
        out[k] = v[at : at + n].reshape(model.params[k].shape)
        at += n
    return out


def laid(rows: pa.RecordBatch) -> dict:
    """Arrays of laid-out slices: labels, each hop's features as a table, and how many rows each row of the hop before has."""
    hops = sum(c.startswith("n_") for c in rows.schema.names)
    values = lambda c: rows.column(c).flatten().to_numpy(zero_copy_only=False)
    many = [values(f"n_{k}") for k in range(1, hops + 1)]
    counts = [rows.num_rows, *(int(n.sum()) for n in many)]
    x = [values(c).reshape(n, -1) if n else np.zeros((0, 0), np.float32) for c, n in zip(["x", *(f"x_{k}" for k in range(1, hops + 1))], counts, strict=True)]
    return {"y": rows.column("label").to_numpy(zero_copy_only=False).astype(float), "x": x, "many": [n.astype(np.int32) for n in many]}


def prepared(model, packed: DataFrame) -> DataFrame:
    """Packed slices as batches of index arrays (blob, compressed), made once for all steps of a training.

    Laid-out slices have one number as label; their batches are of one split each (split, ids, blob) and can be scored too.
    """
    if "n_1" in packed.columns:
        return packed.mapInArrow(_prepare_laid, "split string, ids binary, blob binary")

    def work(batches: Iterator[pd.DataFrame]):
        for pdf in batches:
            for k in range(0, len(pdf), BATCH):
                yield pd.DataFrame({"blob": [_squeezed(model.batch(pdf.iloc[k : k + BATCH].reset_index(drop=True)))]})

    return packed.mapInPandas(work, "blob binary")


def _squeezed(thing) -> bytes:
    return zlib.compress(pickle.dumps(thing, protocol=5), 1)


def _opened(blob: bytes):
    return pickle.loads(zlib.decompress(blob))


def _prepare_laid(batches: Iterator[pa.RecordBatch]):
    schema = pa.schema([("split", pa.string()), ("ids", pa.binary()), ("blob", pa.binary())])
    for rows in batches:
        for split in rows.column("split").unique().to_pylist():
            own = rows.filter(pc.equal(rows.column("split"), split))
            for k in range(0, own.num_rows, BATCH):
                part = own.slice(k, BATCH)
                yield pa.record_batch([[split], [_squeezed(part.column("seed_id").to_pylist())], [_squeezed(laid(part))]], schema=schema)


def fit(models: list, packed: list[DataFrame], steps: int = 40, rate: float = 0.05, sync: str = "grad", local_steps: int = 5) -> list[float]:
    """Trains in place; several models that share parameter names train jointly on their own tasks.

    "grad": every step sums gradients over all partitions and takes one step of an adaptive method on the driver.
    "average": every round each partition takes local steps on a copy of its own and the copies' last parameters are
    averaged by rows.  What comes to the driver is one vector of the parameters' size; rows are added up in the executors.
    Frames that have batches already (blob) are read as they are, so that several trainings can share them.
    """
    history, m, v = [], None, None
    shared: dict[str, np.ndarray] = {}
    for x in models:
        for k in x.params:
            shared.setdefault(k, x.params[k])
        x.params = {k: shared[k] for k in x.params}
    ready = [_in_few(df.select("blob")) if "blob" in df.columns else prepared(model, df).cache() for model, df in zip(models, packed, strict=True)]
    for _ in range(steps):
        total, count, loss = {k: np.zeros_like(p) for k, p in shared.items()}, 0, 0.0
        weight = dict.fromkeys(shared, 0)
        for model, df in zip(models, ready, strict=True):
            got = _round(model, df, sync, rate, local_steps)
            if got is None:
                continue
            n, part_loss, vec = got
            for k, g in _unflat(model, vec).items():
                total[k] += g
                weight[k] += n
            count += n
            loss += part_loss
        if not count:
            break
        history.append(loss / count)
        if sync == "average":
            for k in shared:
                shared[k][...] = total[k] / weight[k] if weight[k] else shared[k]
            continue
        g = {k: x / count for k, x in total.items()}
        m = g if m is None else {k: 0.9 * m[k] + 0.1 * g[k] for k in g}
        v = {k: x * x for k, x in g.items()} if v is None else {k: 0.99 * v[k] + 0.01 * g[k] * g[k] for k in g}
        for k in shared:
            shared[k] -= rate * m[k] / (np.sqrt(v[k]) + 1e-8)
    for df, given in zip(ready, packed, strict=True):
        if "blob" not in given.columns:
            df.unpersist()
    return history


def _round(model, df: DataFrame, sync: str, rate: float, local_steps: int):
    """(rows, loss, vector): the sum of gradients, or of parameters by rows; None without rows."""
    given = df.sparkSession.sparkContext.broadcast(model)

    def work(batches: Iterator[pd.DataFrame]):
        # a broadcast value lives on in the worker, so parameters that change are this task's own
        own = replace(given.value, params={k: p.copy() for k, p in given.value.params.items()})
        grad, n, loss = None, 0, 0.0
        ready = (_opened(x) for pdf in batches for x in pdf["blob"])
        if sync == "average":
            ready = list(ready)  # a partition's index arrays are gone through local_steps times
        for turn in range(local_steps if sync == "average" else 1):
            for b in ready:
                part, g = own.loss_and_grad(b)
                if sync == "average":
                    for k in own.params:
                        own.params[k] = own.params[k] - rate * g[k] / _rows_in(b)
                else:
                    grad = _flat(g) if grad is None else grad + _flat(g)
                if turn == 0:
                    n, loss = n + _rows_in(b), loss + part
        if sync == "average" and n:
            grad = _flat(own.params) * n
        if grad is not None:
            yield pd.DataFrame({"n": [n], "loss": [loss], "vec": [grad.tolist()]})

    rows = df.mapInPandas(work, "n long, loss double, vec array<double>")
    size = sum(p.size for p in model.params.values())
    sums = rows.select("n", "loss", F.posexplode("vec").alias("k", "g")).groupBy("k").agg(F.sum("g").alias("g"), F.sum("n").alias("n"), F.sum("loss").alias("loss"))
    got = sums.agg(F.array_sort(F.collect_list(F.struct("k", "g"))).alias("v"), F.max("n").alias("n"), F.max("loss").alias("loss")).first()
    given.unpersist()
    if not got["n"]:
        return None
    vec = np.array([r["g"] for r in got["v"]])
    assert len(vec) == size
    return got["n"], got["loss"], vec


def _in_few(batches: DataFrame) -> DataFrame:
    """Kept batches in two parts a core: a step over them is short, so that many parts would cost more than the step."""
    return batches.coalesce(2 * batches.sparkSession.sparkContext.defaultParallelism)


def _rows_in(b: dict) -> int:
    return b["n"] if "n" in b else len(b["y"])


def predict(model, packed: DataFrame) -> DataFrame:
    """seed_id, label, score of packed slices or of batches with ids; with several labels the scores are an array."""
    given = packed.sparkSession.sparkContext.broadcast(model)
    many = getattr(model, "loss", "") == "multilabel"
    if "blob" in packed.columns:

        def score(batches: Iterator[pd.DataFrame]):
            for pdf in batches:
                for ids, blob in zip(pdf["ids"], pdf["blob"]):
                    b = _opened(blob)
                    yield pd.DataFrame({"seed_id": _opened(ids), "label": b["y"], "score": given.value.score(b)})

        return _in_few(packed.select("ids", "blob")).mapInPandas(score, "seed_id string, label double, score double")

    def work(batches: Iterator[pd.DataFrame]):
        for pdf in batches:
            if len(pdf):
                score = list(given.value.outputs(pdf)) if many else given.value.score(pdf)
                yield pd.DataFrame({"seed_id": pdf["seed_id"], "label": pdf["label"], "score": score})

    kind = "array<double>" if many else "double"
    return packed.mapInPandas(work, f"seed_id string, label {kind}, score {kind}")


# ------------------------------------------------------------------ pre-training and transfer


def transfer(source: Model, target: Model) -> list[str]:
    """Copies parameters of equal name and shape into ``target`` (encoders, messages, head) and names what was copied.

    A new database whose types have columns of the same kinds, encoded alike, can start from a trained one.
    """
    moved = []
    for k, v in source.params.items():
        if k in target.params and target.params[k].shape == v.shape:
            target.params[k] = v.copy()
            moved.append(k)
    return moved


def pretrain(model: Model, mined: list[DataFrame], steps: int, rate: float = 0.05) -> list[float]:
    """Trains encoders and messages on tasks mined from history, each with a head of its own."""
    models = []
    for i in range(len(mined)):
        own = replace(model, loss="squared", classes=1, hidden=0, frozen=(), params={}).init(i)
        own.params = {**model.params, "head": own.params["head"]}
        models.append(own)
    history: list[float] = []
    for _ in range(steps):
        for own, df in zip(models, mined, strict=True):
            history += fit([own], [df], steps=1, rate=rate)
            model.params.update({k: v for k, v in own.params.items() if k != "head"})
            for other in models:
                other.params.update({k: v for k, v in own.params.items() if k != "head"})
    return history


def finetune(model: Model, packed: DataFrame, steps: int, rate: float = 0.05, frozen: tuple[str, ...] = ()) -> list[float]:
    model.frozen = frozen
    return fit([model], [packed], steps=steps, rate=rate)
