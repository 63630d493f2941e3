"""Embeddings in chunks of local ids: what each worker keeps, written so that a read touches only the chunks it needs."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

CHUNK = 32768


def fill_static_cache(lids: DataFrame, h: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """(worker, chunk, lid, vid, h) for lids (worker, vid, lid): every vertex that a worker reads has its embedding there."""
    return lids.join(h.select("vid", "h"), "vid").select("worker", F.floor(F.col("lid") / chunk).cast("long").alias("chunk"), "lid", "vid", "h")


class EmbeddingStore:
    """Layers under one path, in a folder for each worker, rows sorted by local id so that chunks prune row groups."""

    def __init__(self, spark, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def write(self, layer: int, filled: DataFrame) -> None:
        rows = filled.repartition("worker", "chunk").sortWithinPartitions("worker", "lid")
        rows.write.mode("overwrite").option("compression", "zstd").partitionBy("worker").parquet(f"{self.path}/layer={layer}")

    def read(self, layer: int, worker: int | None = None, chunks: list[int] | None = None) -> DataFrame:
        rows = self.spark.read.parquet(f"{self.path}/layer={layer}")
        if worker is not None:
            rows = rows.where(F.col("worker") == worker)
        return rows if chunks is None else rows.where(F.col("chunk").isin(chunks))


def save_partitions(edges: DataFrame, path: str) -> None:
    """Edges (…, part) in a folder for each part, sorted as the layout wants them; overwrites by part."""
    rows = edges.repartition("part").sortWithinPartitions("part", "src", "etype", "dst")
    rows.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("part").parquet(path)


def load_partition(spark, path: str, part: int | None = None) -> DataFrame:
    rows = spark.read.parquet(path)
    return rows if part is None else rows.where(F.col("part") == part)


class MlpDecoder:
    """Two feed-forward layers over both ends' embeddings, in Arrow batches."""

    def __init__(self, first: np.ndarray, second: np.ndarray):
        self.first, self.second = first, second

    def score(self, h: DataFrame, edges: DataFrame) -> DataFrame:
        """(eid, score) of edges (eid, src, dst)."""
        ends = edges.select("eid", "src", "dst")
        for end, name in (("src", "a"), ("dst", "b")):
            ends = ends.join(h.select(F.col("vid").alias(end), F.col("h").alias(name)), end)
        first, second = self.first, self.second

        def rows(col):
            flat = col.flatten().to_numpy(zero_copy_only=False).astype(float)
            return flat.reshape(len(col), -1) if len(col) else flat.reshape(0, first.shape[0] // 2)

        def run(batches):
            for b in batches:
                x = np.c_[rows(b.column("a")), rows(b.column("b"))]
                yield pa.RecordBatch.from_arrays([b.column("eid"), pa.array((np.maximum(x @ first, 0) @ second)[:, 0])], ["eid", "score"])

        return ends.select("eid", "a", "b").mapInArrow(run, "eid long, score double")
