"""The graph that all methods work on: an edge table with integer ids and types, and its derived adjacency."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

EDGE_COLUMNS = ("eid", "src", "dst", "etype", "weight")
TYPE_SHIFT = 40  # vid = type * 2**40 + key


@dataclass(frozen=True)
class PropertyGraph:
    """A heterogeneous multigraph; eid is unique, parallel edges are kept."""

    name: str
    edges: DataFrame

    def vertices(self) -> DataFrame:
        return self.edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct()

    def adjacency(self, direction: str = "both") -> DataFrame:
        """(vid, nbr, eid, etype, weight); a self loop counts once in each direction."""
        return both_ends(self.edges, ["eid", "etype", "weight"], direction)

    def degrees(self, direction: str = "both") -> DataFrame:
        ends = {"out": F.col("src"), "in": F.col("dst"), "both": F.explode(F.array("src", "dst"))}[direction]
        return self.edges.select(ends.alias("vid")).groupBy("vid").agg(F.count("*").alias("degree"))


def both_ends(edges: DataFrame, columns: list[str], direction: str = "both") -> DataFrame:
    """(vid, nbr, columns) of edges seen from their sources, their targets, or both, in one pass over the edges."""
    out = F.struct(F.col("src").alias("vid"), F.col("dst").alias("nbr"))
    into = F.struct(F.col("dst").alias("vid"), F.col("src").alias("nbr"))
    ends = {"out": F.array(out), "in": F.array(into), "both": F.array(out, into)}[direction]
    return edges.select(F.explode(ends).alias("end"), *columns).select("end.vid", "end.nbr", *columns)
