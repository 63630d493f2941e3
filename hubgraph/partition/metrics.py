"""Quality of a partitioning: replication factor, balances, interior share, degree distribution."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def replicas(edges: DataFrame) -> DataFrame:
    """(vid, part): where each vertex of a vertex-cut lives."""
    return edges.select("part", F.explode(F.array("src", "dst")).alias("vid")).distinct()


def partition_bits(resident: DataFrame) -> DataFrame:
    """(vid, bits), one bit a part; for up to 63 parts."""
    return resident.groupBy("vid").agg(F.bit_or(F.expr("shiftleft(1L, part)")).alias("bits"))


def home_partition(edges: DataFrame) -> DataFrame:
    """(vid, home): the part with most of a vertex's edges, ties to the lower id."""
    local = edges.select("part", F.explode(F.array("src", "dst")).alias("vid")).groupBy("vid", "part").agg(F.count("*").alias("n"))
    return local.groupBy("vid").agg(F.max_by("part", F.struct("n", -F.col("part"))).alias("home"))


def partition_report(edges: DataFrame, parts: int, resident: DataFrame | None = None) -> DataFrame:
    """One row: rf, vb, eb, empty parts, interior share. A balance is null where a part is empty."""
    spark = edges.sparkSession
    resident = replicas(edges) if resident is None else resident
    all_parts = spark.range(parts).select(F.col("id").cast("int").alias("part"))
    ne = edges.groupBy("part").agg(F.count("*").alias("ne"))
    nv = resident.groupBy("part").agg(F.count("*").alias("nv"))
    table = all_parts.join(ne, "part", "left").join(nv, "part", "left").fillna(0)
    spread = resident.groupBy("vid").agg(F.count("*").alias("k")).agg(F.count("*").alias("v"), F.avg(F.when(F.col("k") == 1, 1.0).otherwise(0.0)).alias("inside"))
    return _report(table, spread)


def counted_report(counts: DataFrame) -> DataFrame:
    """The same row from (part, ne, nv, v, inside), a row a part; v vertices, of which `inside` lie in one part only."""
    return _report(counts, counts.groupBy("v").agg((F.max("inside") / F.col("v")).alias("inside")))


def _report(table: DataFrame, spread: DataFrame) -> DataFrame:
    balance = table.agg(F.sum("nv").alias("total"), (F.max("nv") / F.nullif(F.min("nv"), F.lit(0))).alias("vb"), (F.max("ne") / F.nullif(F.min("ne"), F.lit(0))).alias("eb"), F.count_if(F.col("ne") == 0).alias("empty_parts"))
    return balance.crossJoin(spread).select(F.round(F.col("total") / F.nullif(F.col("v"), F.lit(0)), 6).alias("rf"), F.round("vb", 6).alias("vb"), F.round("eb", 6).alias("eb"), "empty_parts", F.round("inside", 6).alias("interior"))


def degree_stats(graph) -> DataFrame:
    d = graph.degrees()
    return d.agg(F.count("*").alias("v"), (F.sum("degree") / 2).cast("long").alias("e"), F.round(F.avg("degree"), 6).alias("avg_degree"), F.max("degree").alias("max_degree"))


def degree_histogram(graph) -> DataFrame:
    """Vertices by the power of two below their degree."""
    return graph.degrees().groupBy((F.length(F.bin("degree")) - 1).alias("bin")).agg(F.count("*").alias("n"), F.sum("degree").alias("ends"))


def tail_exponent(graph, x_min: int = 4) -> DataFrame:
    """Maximum-likelihood exponent of the degrees from x_min on."""
    d = graph.degrees().where(F.col("degree") >= x_min)
    return d.agg(F.count("*").alias("n"), F.round(1 + 1 / F.avg(F.log(F.col("degree") / (x_min - 0.5))), 6).alias("exponent"))
