"""Message-passing layers over DataFrames: edges meet embeddings in a join, dense steps run in Arrow batches."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class LayerSpec:
    """kind: gcn, sage, gat or hgt. params: matrices by name (and by type for hgt). last: no activation."""

    kind: str
    params: dict
    heads: int = 1
    last: bool = False


def make_layer(kind: str, width: int, out: int, seed: int, *, heads: int = 1, types: int = 1, last: bool = False) -> LayerSpec:
    r = np.random.default_rng(seed)
    m = lambda a, b: r.normal(0, 1 / np.sqrt(a), (a, b))
    params = {"gcn": lambda: {"w": m(width, out)}, "sage": lambda: {"self": m(width, out), "nbr": m(width, out)}, "gat": lambda: {"w": m(width, out), "a": m(2 * out // heads, heads)}, "hgt": lambda: {"q": m(width, out), "k": np.stack([m(width, out) for _ in range(types)]), "v": np.stack([m(width, out) for _ in range(types)]), "o": m(out, out), "prior": np.ones(types)}}[kind]()
    return LayerSpec(kind, params, heads, last)


def _dense(layer: LayerSpec, h: np.ndarray, nbrs: list[np.ndarray], types: list[np.ndarray], scale: list[np.ndarray], own: np.ndarray) -> np.ndarray:
    """Rows of new embeddings from own embeddings and neighbours' embeddings of a block of vertices."""
    p, out = layer.params, []
    size = np.array([len(x) for x in nbrs])
    flat = np.concatenate([x for x in nbrs if len(x)]) if size.sum() else np.zeros((0, h.shape[1]))
    row = np.repeat(np.arange(len(h)), size)

    def total(x):
        y = np.zeros((len(h), x.shape[1]))
        np.add.at(y, row, x)
        return y

    def softmax(s):
        top = np.full((len(h), s.shape[1]), -np.inf)
        np.maximum.at(top, row, s)
        e = np.exp(s - top[row])
        return e / np.maximum(total(e)[row], 1e-300)

    if layer.kind == "gcn":
        y = (total(flat * np.concatenate([s for s in scale if len(s)])[:, None] if len(flat) else flat) + h * own[:, None]) @ p["w"]
    elif layer.kind == "sage":
        y = h @ p["self"] + total(flat) / np.maximum(size, 1)[:, None] @ p["nbr"]
    elif layer.kind == "gat":
        # The vertex itself is one of its neighbours.
        row = np.r_[row, np.arange(len(h))]
        z, zs = np.r_[flat, h] @ p["w"], h @ p["w"]
        split = lambda x: x.reshape(len(x), layer.heads, -1)
        a = p["a"].reshape(2, -1, layer.heads)
        s = np.einsum("nhd,dh->nh", split(zs)[row], a[0]) + np.einsum("nhd,dh->nh", split(z), a[1])
        weight = softmax(np.where(s > 0, s, 0.2 * s))
        y = total((split(z) * weight[:, :, None]).reshape(len(z), -1))
    else:
        t = np.concatenate([x for x in types if len(x)]).astype(int) % len(p["k"]) if len(flat) else np.zeros(0, int)
        k, v = np.einsum("nd,ndo->no", flat, p["k"][t]), np.einsum("nd,ndo->no", flat, p["v"][t])
        split = lambda x: x.reshape(len(x), layer.heads, -1)
        q = split(h @ p["q"])
        s = (q[row] * split(k)).sum(2) / np.sqrt(q.shape[2]) * p["prior"][t][:, None]
        y = total((split(v) * softmax(s)[:, :, None]).reshape(len(v), -1)) @ p["o"]
        if h.shape[1] == y.shape[1]:
            y = y + h
    out = y if layer.last else np.maximum(y, 0)
    return out


def apply_layer(h: DataFrame, hop: DataFrame, layer: LayerSpec, degree: DataFrame | None = None) -> DataFrame:
    """(vid, h) one layer on, for embeddings (vid, h) and sampled edges (vid, nbr, etype).

    A vertex's sample is bounded by the fanout, so its neighbours' rows fit one array; gcn uses sampled degrees, those
    of hop unless others (vid, deg) are given.
    """
    degree = hop.groupBy("vid").agg(F.count("*").alias("deg")) if degree is None else degree
    messages = hop.join(h.select(F.col("vid").alias("nbr"), F.col("h").alias("hn")), "nbr").join(degree.select(F.col("vid").alias("nbr"), F.col("deg").alias("dn")), "nbr", "left")
    grouped = messages.groupBy("vid").agg(F.array_sort(F.collect_list(F.struct("nbr", "etype", F.coalesce("dn", F.lit(0)).alias("dn"), "hn"))).alias("m"))
    rows = h.join(grouped, "vid", "left").select("vid", "h", "m")

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            own = np.array(b.column("h").to_pylist(), float)
            m = b.column("m").to_pylist()
            nbrs = [np.array([x["hn"] for x in r or ()], float).reshape(-1, own.shape[1]) for r in m]
            types = [np.array([x["etype"] for x in r or ()]) for r in m]
            scale = [1 / np.sqrt((len(r or ()) + 1.0) * (np.array([x["dn"] for x in r or ()]) + 1.0)) for r in m]
            y = _dense(layer, own, nbrs, types, scale, 1 / (np.array([len(r or ()) for r in m]) + 1.0))
            yield pa.RecordBatch.from_arrays([b.column("vid"), pa.array(list(y), pa.list_(pa.float64()))], ["vid", "h"])

    return rows.mapInArrow(run, "vid long, h array<double>")
