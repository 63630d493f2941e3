"""A part's edges as sorted arrays, and what four layouts take."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass
class PartLayout:
    """Local ids are positions in global_id; edge ids are positions in the edges sorted by source, type and target.

    out_start[v] is the first edge of v. Types are kept as runs: for each (v, type) the type and where its run ends.
    Incoming edges hold positions of edges, not copies.
    """

    global_id: np.ndarray
    out_start: np.ndarray
    out_dst: np.ndarray
    run_start: np.ndarray
    run_type: np.ndarray
    run_end: np.ndarray
    in_start: np.ndarray
    in_edge: np.ndarray

    def to_local(self, ids) -> np.ndarray:
        at = np.searchsorted(self.global_id, ids)
        hit = self.global_id[np.minimum(at, len(self.global_id) - 1)] == ids
        return np.where(hit, at, -1)

    def edge_type(self, position) -> np.ndarray:
        return self.run_type[np.searchsorted(self.run_end, position, side="right")]

    def source(self, position) -> np.ndarray:
        return np.searchsorted(self.out_start, position, side="right") - 1

    def neighbours(self, vertex: int, etype: int | None = None) -> np.ndarray:
        s, e = self.out_start[vertex], self.out_start[vertex + 1]
        if etype is not None:
            runs = range(self.run_start[vertex], self.run_start[vertex + 1])
            k = next((r for r in runs if self.run_type[r] == etype), None)
            if k is None:
                return self.out_dst[:0]
            s, e = max(s, self.run_end[k - 1] if k else 0), self.run_end[k]
        return self.out_dst[s:e]

    def nbytes(self) -> dict[str, int]:
        return {k: v.nbytes for k, v in vars(self).items()}


def build_layout(src: np.ndarray, dst: np.ndarray, etype: np.ndarray) -> PartLayout:
    ids = np.unique(np.r_[src, dst])
    s, d = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    order = np.lexsort((d, etype, s))
    s, d, t = s[order], d[order].astype(np.int32), etype[order].astype(np.int32)
    starts = np.arange(len(ids) + 1)
    new = np.r_[True, (s[1:] != s[:-1]) | (t[1:] != t[:-1])] if len(s) else np.zeros(0, bool)
    head = np.nonzero(new)[0]
    into = np.lexsort((np.arange(len(d)), t, d)).astype(np.int32)
    return PartLayout(ids, np.searchsorted(s, starts), d, np.searchsorted(s[head], starts), t[head], np.r_[head[1:], len(s)].astype(np.int64) if len(s) else head, np.searchsorted(d[into], starts), into)


def write_layouts(edges: DataFrame) -> DataFrame:
    """(part, field, dtype, n, data): each part's arrays as binary rows, built where the part lies."""

    def build(key, table):
        import pyarrow as pa

        layout = build_layout(*(table[c].to_numpy() for c in ("src", "dst", "etype")))
        rows = [(key[0].as_py(), k, v.dtype.str, len(v), v.tobytes()) for k, v in vars(layout).items()]
        part, field, dtype, n, data = zip(*rows, strict=True)
        return pa.table({"part": pa.array(part, pa.int32()), "field": field, "dtype": dtype, "n": pa.array(n, pa.int64()), "data": pa.array(data, pa.binary())})

    return edges.select("part", "src", "dst", "etype").groupBy("part").applyInArrow(build, "part int, field string, dtype string, n long, data binary")


def read_layout(rows: list) -> PartLayout:
    return PartLayout(**{r["field"]: np.frombuffer(r["data"], r["dtype"]) for r in rows})


def footprint(graph) -> DataFrame:
    """(layout, bytes) of the whole graph by counts times widths, for the compact layout and three others."""
    e = graph.edges
    counts = e.agg(F.count("*").alias("e")).crossJoin(graph.vertices().agg(F.count("*").alias("v")))
    out_runs, in_runs = (e.select(c, "etype").distinct().agg(F.count("*").alias(n)) for c, n in (("src", "ro"), ("dst", "ri")))
    typed = e.select("etype", F.explode(F.array("src", "dst")).alias("vid")).distinct().agg(F.count("*").alias("tv"))
    c = counts.crossJoin(out_runs).crossJoin(in_runs).crossJoin(typed)
    sizes = {
        "compact": 8 * F.col("v") + 16 * F.col("v") + 8 * F.col("e") + 8 * (F.col("ro") + F.col("ri")) + 16 * F.col("v"),
        "explicit_type": 8 * F.col("v") + 16 * F.col("v") + 8 * F.col("e") + 8 * F.col("e") + 8 * (F.col("ro") + F.col("ri")),
        "explicit_ids": 24 * F.col("v") + 16 * F.col("v") + 8 * F.col("e") + 16 * F.col("e") + 8 * (F.col("ro") + F.col("ri")),
        "per_type_graphs": 24 * F.col("tv") + 16 * F.col("tv") + 24 * F.col("e"),
    }
    return c.select(F.explode(F.array(*(F.struct(F.lit(k).alias("layout"), v.cast("long").alias("bytes")) for k, v in sizes.items()))).alias("x")).select("x.*")
