"""Training side: splits, negative samples, a small trained classifier over sampled blocks, and its measures."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from hubgraph.core.portable import bits, uniform


def corrupt_edges(edges: DataFrame, vertices: DataFrame, per_positive: int = 1, salt: str = "n") -> DataFrame:
    """Negatives: the target of each edge replaced by a hashed vertex of the same type."""
    typed = vertices.select("vid", F.shiftright("vid", 40).alias("vtype"))
    ranked = typed.withColumn("r", F.row_number().over(Window.partitionBy("vtype").orderBy("vid")) - 1)
    size = typed.groupBy("vtype").agg(F.count("*").alias("n"))
    drawn = edges.select("eid", "src", "etype", F.shiftright("dst", 40).alias("vtype"), F.explode(F.sequence(F.lit(0), F.lit(per_positive - 1))).alias("k")).join(F.broadcast(size), "vtype")
    drawn = drawn.withColumn("r", bits(salt, "eid", "k") % F.col("n"))
    return drawn.join(ranked, ["vtype", "r"]).select("eid", "k", "src", F.col("vid").alias("dst"), "etype")


def sample_edges(edges: DataFrame, n: int, salt: str = "m") -> DataFrame:
    return edges.orderBy(uniform(salt, "eid"), "eid").limit(n)


def inductive_split(graph, share: float = 0.2, salt: str = "t") -> tuple[DataFrame, DataFrame]:
    """Test vertices, and the edges that training may see: none that touches a test vertex."""
    test = graph.vertices().where(uniform(salt, "vid") < share)
    seen = graph.edges
    for end in ("src", "dst"):
        seen = seen.join(test.withColumnRenamed("vid", end), end, "left_anti")
    return test, seen


def auc(scores: DataFrame) -> DataFrame:
    """One row: area under the curve of (label, score) by rank sums, ties shared."""
    by = Window.orderBy("score")
    groups = scores.groupBy("score").agg(F.sum("label").alias("p"), F.count("*").alias("n"))
    ranked = groups.withColumn("upto", F.sum("n").over(by)).withColumn("rank", F.col("upto") - (F.col("n") - 1) / 2)
    a = ranked.agg(F.sum(F.col("rank") * F.col("p")).alias("s"), F.sum("p").alias("np"), F.sum("n").alias("nt"))
    return a.select(F.round((F.col("s") - F.col("np") * (F.col("np") + 1) / 2) / (F.col("np") * (F.col("nt") - F.col("np"))), 6).alias("auc"))


def train_softmax(rows: DataFrame, classes: int, *, rounds: int = 30, rate: float = 2.0) -> tuple[np.ndarray, list[float]]:
    """Weights and losses of a softmax layer over (h, label), by synchronous steps: every partition sends its gradient
    sums, the driver adds them up; the result does not depend on the number of partitions."""
    rows = rows.select("h", "label").persist()
    width = rows.select(F.size("h").alias("n")).first().n + 1
    w, losses = np.zeros((width, classes)), []
    for _ in range(rounds):

        def step(batches, w=w):
            g, loss, n = np.zeros_like(w), 0.0, 0
            for b in batches:
                if not b.num_rows:
                    continue
                x = np.c_[np.array(b.column("h").to_pylist(), float), np.ones(b.num_rows)]
                y = b.column("label").to_numpy()
                z = x @ w
                p = np.exp(z - z.max(1, keepdims=True))
                p /= p.sum(1, keepdims=True)
                loss -= np.log(np.maximum(p[np.arange(len(y)), y], 1e-12)).sum()
                p[np.arange(len(y)), y] -= 1
                g += x.T @ p
                n += len(y)
            yield pa.RecordBatch.from_arrays([pa.array([g.tobytes()]), pa.array([loss]), pa.array([n], pa.int64())], ["g", "loss", "n"])

        parts = rows.mapInArrow(step, "g binary, loss double, n long").collect()
        n = sum(p.n for p in parts)
        losses.append(sum(p.loss for p in parts) / n)
        w = w - rate / n * sum(np.frombuffer(p.g).reshape(w.shape) for p in parts)
    rows.unpersist()
    return w, losses


def accuracy(rows: DataFrame, w: np.ndarray) -> float:
    def run(batches):
        for b in batches:
            x = np.c_[np.array(b.column("h").to_pylist(), float).reshape(b.num_rows, -1), np.ones(b.num_rows)]
            yield pa.RecordBatch.from_arrays([pa.array((x @ w).argmax(1) == b.column("label").to_numpy())], ["ok"])

    return rows.select("h", "label").mapInArrow(run, "ok boolean").agg(F.avg(F.col("ok").cast("double"))).first()[0]
