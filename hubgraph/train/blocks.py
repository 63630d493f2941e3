"""Mini-batch training of message-passing encoders over sampled blocks, for vertex classes and for links.

A batch's seeds draw their two-hop samples once an epoch; what a batch needs (features of all vertices in its blocks)
goes to one task, which runs the encoder forward and back in numpy and returns gradients. The driver adds up the
gradients of `trainers` batches and takes one step, so weights alone travel: the batch grows with the trainers.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from hubgraph.core.portable import bits, uniform
from hubgraph.session import stage


@dataclass
class Trained:
    """Weights by name, the loss of each step, and seconds of each epoch."""

    weights: dict[str, np.ndarray]
    losses: list[float] = field(default_factory=list)
    moments: dict[str, tuple] = field(default_factory=dict)
    seconds: list[float] = field(default_factory=list)


def first_weights(kind: str, width: int, hidden: int, out: int, seed: int = 0) -> dict[str, np.ndarray]:
    r = np.random.default_rng(seed)
    m = lambda a, b: r.normal(0, np.sqrt(2 / a), (a, b))
    sizes = ((1, width, hidden), (2, hidden, out))
    return {f"nbr{k}": m(a, b) for k, a, b in sizes} | ({f"self{k}": m(a, b) for k, a, b in sizes} if kind == "sage" else {})


def _mix(kind: str, n: int, row: np.ndarray, col: np.ndarray):
    """Forward and transposed aggregation over edges row <- col among n vertices: mean, or symmetric with self loops."""
    if kind == "gcn":
        row, col = np.r_[row, np.arange(n)], np.r_[col, np.arange(n)]
        d = np.maximum(np.bincount(row, minlength=n), 1)
        w = 1 / np.sqrt(d[row] * np.maximum(np.bincount(row, minlength=n), 1)[col])
    else:
        w = 1 / np.maximum(np.bincount(row, minlength=n), 1)[row]

    def run(x, to, of):
        y = np.zeros_like(x)
        np.add.at(y, to, x[of] * w[:, None])
        return y

    return (lambda x: run(x, row, col)), (lambda x: run(x, col, row))


def encode(kind: str, p: dict, x: np.ndarray, edges1, edges2):
    """Two layers over one block of vertices: the outer hop's edges feed layer 1, the inner hop's layer 2; embeddings
    and what the way back needs."""
    f1, b1 = _mix(kind, len(x), *edges1)
    f2, b2 = _mix(kind, len(x), *edges2)
    m1 = f1(x)
    z1 = m1 @ p["nbr1"] + (x @ p["self1"] if kind == "sage" else 0)
    h1 = np.maximum(z1, 0)
    m2 = f2(h1)
    return m2 @ p["nbr2"] + (h1 @ p["self2"] if kind == "sage" else 0), (x, m1, z1, h1, m2, b2)


def back(kind: str, p: dict, held, gy: np.ndarray) -> dict[str, np.ndarray]:
    x, m1, z1, h1, m2, b2 = held
    g = {"nbr2": m2.T @ gy}
    gh = b2(gy @ p["nbr2"].T)
    if kind == "sage":
        g["self2"] = h1.T @ gy
        gh = gh + gy @ p["self2"].T
    gz = gh * (z1 > 0)
    g["nbr1"] = m1.T @ gz
    if kind == "sage":
        g["self1"] = x.T @ gz
    return g


def two_hops(adjacency: DataFrame, seeds: DataFrame, fanouts: tuple[int | None, int | None], salt: str) -> DataFrame:
    """(batch, hop, vid, nbr) for seeds (batch, vid): a function of vertex, hop and salt alone; fanout None takes all."""
    out, front = None, seeds.select("batch", "vid").distinct()
    for hop, fanout in enumerate(fanouts):
        lists = adjacency.join(front.select("vid").distinct(), "vid", "left_semi").select("vid", "nbr", "eid")
        if fanout:
            best = Window.partitionBy("vid").orderBy(uniform(f"{salt}{hop}", "vid", "eid"), "eid")
            lists = lists.withColumn("r", F.row_number().over(best)).where(F.col("r") <= fanout)
        block = stage(lists.join(front, "vid").select("batch", F.lit(hop).alias("hop"), "vid", "nbr"))
        out = block if out is None else out.unionByName(block)
        front = block.select("batch", F.col("nbr").alias("vid")).union(front).distinct()
    return out


def assign_batches(seeds: DataFrame, size: int, salt: str = "q") -> DataFrame:
    """seeds with batch: about `size` seeds each, dealt by hash, so that no global order is needed."""
    batches = max(1, -(-seeds.count() // size))
    return seeds.withColumn("batch", (bits(salt, "vid") % batches).cast("int"))


def edge_seeds(edges: DataFrame) -> DataFrame:
    """Both ends of edges, each vertex once."""
    return edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct()


def _inputs(adjacency, features, seeds, fanouts, salt, extra=()):
    """One row for each batch: its vertices with features, its edges by hop, and its seeds."""
    blocks = two_hops(adjacency, seeds, fanouts, salt)
    needed = blocks.select("batch", F.explode(F.array("vid", "nbr")).alias("vid")).union(seeds.select("batch", "vid")).distinct()
    nodes = needed.join(features, "vid").groupBy("batch").agg(F.collect_list(F.struct("vid", "h")).alias("nodes"))
    edges = blocks.groupBy("batch").agg(F.collect_list(F.struct("hop", "vid", "nbr")).alias("edges"))
    own = seeds.groupBy("batch").agg(F.collect_list(F.struct("vid", *extra)).alias("seeds"))
    return stage(own.join(nodes, "batch").join(edges, "batch", "left"))


def _unpack(r):
    vid = np.array([n["vid"] for n in r["nodes"]], np.int64)
    order = np.argsort(vid)
    x, vid = np.array([n["h"] for n in r["nodes"]], float)[order], vid[order]
    e = np.array([(k["hop"], k["vid"], k["nbr"]) for k in r["edges"] or ()], np.int64).reshape(-1, 3)
    at = lambda v: np.searchsorted(vid, v)
    inner, outer = e[e[:, 0] == 0], e
    return x, at, (at(outer[:, 1]), at(outer[:, 2])), (at(inner[:, 1]), at(inner[:, 2]))


def _steps(inputs: DataFrame, p: dict, task, trainers: int, rate: float, out: Trained) -> dict:
    """One pass over the batches: each step adds up the gradients of `trainers` batches and moves by their moments."""
    batches = sorted(r.batch for r in inputs.select("batch").collect())
    for k in range(0, len(batches), trainers):

        def run(frames, p=p):
            for b in frames:
                for r in b.to_pylist():
                    g, loss, n = task(r, p)
                    yield pa.RecordBatch.from_pydict({"g": pa.array([b"".join(g[name].tobytes() for name in sorted(p))]), "loss": pa.array([float(loss)]), "n": pa.array([int(n)], pa.int64())})

        parts = inputs.where(F.col("batch").isin(batches[k : k + trainers])).mapInArrow(run, "g binary, loss double, n long").collect()
        n = max(1, sum(r.n for r in parts))
        flat = sum(np.frombuffer(r.g) for r in parts) / n
        out.losses.append(sum(r.loss for r in parts) / n)
        at, new = 0, {}
        for name in sorted(p):
            g = flat[at : at + p[name].size].reshape(p[name].shape)
            at += p[name].size
            one, two, t = out.moments.get(name, (0, 0, 0))
            one, two, t = 0.9 * one + 0.1 * g, 0.999 * two + 0.001 * g * g, t + 1
            out.moments[name] = one, two, t
            new[name] = p[name] - rate * (one / (1 - 0.9**t)) / (np.sqrt(two / (1 - 0.999**t)) + 1e-8)
        p = new
    return p


def train_vertices(adjacency: DataFrame, features: DataFrame, labelled: DataFrame, classes: int, *, kind: str = "sage", hidden: int = 32, fanouts=(8, 4), epochs: int = 4, batch: int = 16, trainers: int = 4, rate: float = 0.02, seed: int = 0) -> Trained:
    """Classes of vertices from labelled (vid, label), features (vid, h) and adjacency (vid, nbr, eid)."""
    width = features.select(F.size("h").alias("n")).first().n
    out = Trained(first_weights(kind, width, hidden, classes, seed))
    seeds = stage(assign_batches(labelled, batch))

    def task(r, p):
        x, at, e1, e2 = _unpack(r)
        y, held = encode(kind, p, x, e1, e2)
        own, label = at([s["vid"] for s in r["seeds"]]), np.array([s["label"] for s in r["seeds"]])
        z = y[own] - y[own].max(1, keepdims=True)
        q = np.exp(z) / np.exp(z).sum(1, keepdims=True)
        loss = -np.log(np.maximum(q[np.arange(len(own)), label], 1e-12)).sum()
        q[np.arange(len(own)), label] -= 1
        gy = np.zeros_like(y)
        np.add.at(gy, own, q)
        return back(kind, p, held, gy), loss, len(own)

    for epoch in range(epochs):
        begin = time.time()
        inputs = _inputs(adjacency, features, seeds, fanouts, f"v{epoch}", ("label",))
        out.weights = _steps(inputs, out.weights, task, trainers, rate, out)
        out.seconds.append(time.time() - begin)
    return out


def predict_vertices(adjacency: DataFrame, features: DataFrame, targets: DataFrame, trained: Trained, *, kind: str = "sage", fanouts=(8, 4), batch: int = 256) -> DataFrame:
    """(vid, predicted) of targets (vid); fanouts of None use all neighbours."""
    inputs = _inputs(adjacency, features, assign_batches(targets.select("vid").distinct(), batch), fanouts, "p")
    p = trained.weights

    def run(frames):
        for b in frames:
            for r in b.to_pylist():
                x, at, e1, e2 = _unpack(r)
                y, _ = encode(kind, p, x, e1, e2)
                vid = [s["vid"] for s in r["seeds"]]
                yield pa.RecordBatch.from_pydict({"vid": pa.array(vid, pa.int64()), "predicted": pa.array(y[at(vid)].argmax(1).astype(np.int32))})

    return inputs.mapInArrow(run, "vid long, predicted int")


def decode(p: dict, a: np.ndarray, b: np.ndarray):
    """The feed-forward decoder of two layers over both ends' embeddings: scores, and what the way back needs."""
    x = np.c_[a, b, a * b]
    z = x @ p["d1"]
    return (np.maximum(z, 0) @ p["d2"])[:, 0], (x, z)


def train_links(adjacency: DataFrame, features: DataFrame, positives: DataFrame, negatives: DataFrame, *, kind: str = "sage", hidden: int = 16, fanouts=(8, 4), epochs: int = 4, batch: int = 128, trainers: int = 4, rate: float = 0.02, seed: int = 0) -> Trained:
    """Encoder and decoder from positive and negative edges (src, dst); batches deal edges by hash of both ends."""
    width = features.select(F.size("h").alias("n")).first().n
    r = np.random.default_rng(seed + 1)
    decoder = {"d1": r.normal(0, np.sqrt(1 / hidden), (3 * hidden, hidden)), "d2": r.normal(0, np.sqrt(1 / hidden), (hidden, 1))}
    out = Trained(first_weights(kind, width, hidden, hidden, seed) | decoder)
    every = positives.select("src", "dst", F.lit(1).alias("y")).union(negatives.select("src", "dst", F.lit(0).alias("y")))
    batches = max(1, -(-every.count() // batch))
    pairs = stage(every.withColumn("batch", (bits("q", "src", "dst") % batches).cast("int")))
    ends = pairs.select("batch", F.explode(F.array("src", "dst")).alias("vid")).distinct()

    def task(row, p):
        x, at, e1, e2 = _unpack(row)
        h, held = encode(kind, p, x, e1, e2)
        s, d, y = (np.array([k[c] for k in row["pairs"]]) for c in ("src", "dst", "y"))
        s, d = at(s), at(d)
        score, (joint, z) = decode(p, h[s], h[d])
        q = 1 / (1 + np.exp(-np.clip(score, -30, 30)))
        loss = -(y * np.log(np.maximum(q, 1e-12)) + (1 - y) * np.log(np.maximum(1 - q, 1e-12))).sum()
        gs = (q - y)[:, None]
        gz = (gs @ p["d2"].T) * (z > 0)
        gx = gz @ p["d1"].T
        n, gh = h.shape[1], np.zeros_like(h)
        np.add.at(gh, s, gx[:, :n] + gx[:, 2 * n :] * h[d])
        np.add.at(gh, d, gx[:, n : 2 * n] + gx[:, 2 * n :] * h[s])
        return back(kind, p, held, gh) | {"d1": joint.T @ gz, "d2": np.maximum(z, 0).T @ gs}, loss, len(y)

    for epoch in range(epochs):
        begin = time.time()
        inputs = _inputs(adjacency, features, ends, fanouts, f"l{epoch}")
        inputs = stage(inputs.join(pairs.groupBy("batch").agg(F.collect_list(F.struct("src", "dst", "y")).alias("pairs")), "batch"))
        out.weights = _steps(inputs, out.weights, task, trainers, rate, out)
        out.seconds.append(time.time() - begin)
    return out
