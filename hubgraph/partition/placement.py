"""Hash placements: edges by id, by one end or on a grid, and vertices by id (an edge-cut)."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubgraph.core.portable import bucket, sql_bucket


def grid_shape(parts: int) -> tuple[int, int]:
    rows = next(r for r in range(int(parts**0.5), 0, -1) if parts % r == 0)
    return rows, parts // rows


def place(edges: DataFrame, parts: int, kind: str, salt: str = "p") -> DataFrame:
    """edges with `part` under random, hash1d (by source), hash1d_dst (by target) or hash2d (grid: at most rows + columns - 1 replicas)."""
    rows, columns = grid_shape(parts)
    by = {"random": bucket(parts, salt, "eid"), "hash1d": bucket(parts, salt, "src"), "hash1d_dst": bucket(parts, salt, "dst"), "hash2d": bucket(rows, salt + "r", "src") * columns + bucket(columns, salt + "c", "dst")}
    return edges.withColumn("part", by[kind].cast("int"))


def sql_place(parts: int, kind: str, salt: str = "p") -> str:
    rows, columns = grid_shape(parts)
    return {"random": sql_bucket(parts, salt, "eid"), "hash1d": sql_bucket(parts, salt, "src"), "hash1d_dst": sql_bucket(parts, salt, "dst"), "hash2d": f"({sql_bucket(rows, salt + 'r', 'src')} * {columns} + {sql_bucket(columns, salt + 'c', 'dst')})"}[kind]


def hash_edge_cut(graph, parts: int, salt: str = "v") -> DataFrame:
    """(vid, part): each vertex is owned by one part."""
    return graph.vertices().withColumn("part", bucket(parts, salt, "vid"))


def materialise_edge_cut(owner: DataFrame, edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Edges on each part that owns an end (cut edges twice), and each part's owned vertices with their one-hop halo."""
    a, b = owner.select(F.col("vid").alias("src"), F.col("part").alias("ps")), owner.select(F.col("vid").alias("dst"), F.col("part").alias("pd"))
    both = edges.join(a, "src").join(b, "dst").withColumn("part", F.explode(F.array_distinct(F.array("ps", "pd")))).drop("ps", "pd")
    resident = both.select("part", F.explode(F.array("src", "dst")).alias("vid")).distinct()
    return both, resident


def label_propagation_cut(graph, parts: int, *, rounds: int = 4, slack: float = 1.1, stage=lambda d: d) -> DataFrame:
    """Edge-cut by label propagation: a vertex moves to the part most of its neighbours are in, best gains first, while
    the part is below its cap of vertices."""
    owner = stage(hash_edge_cut(graph, parts, "lp"))
    adjacency = graph.adjacency().groupBy("vid", "nbr").agg(F.count("*").alias("w"))
    cap = int(owner.count() / parts * slack) + 1
    from pyspark.sql.window import Window

    for _ in range(rounds):
        votes = adjacency.join(owner.select(F.col("vid").alias("nbr"), F.col("part").alias("to")), "nbr").groupBy("vid", "to").agg(F.sum("w").alias("votes"))
        own = votes.join(owner, "vid").groupBy("vid", "part").agg(F.max(F.struct("votes", (-F.col("to")).alias("to"))).alias("best"), F.max(F.when(F.col("to") == F.col("part"), F.col("votes"))).alias("stay"))
        moves = own.select("vid", "part", (-F.col("best.to")).alias("to"), (F.col("best.votes") - F.coalesce("stay", F.lit(0))).alias("gain")).where("gain > 0 and to <> part")
        size = owner.groupBy(F.col("part").alias("to")).agg(F.count("*").alias("n"))
        ranked = moves.join(F.broadcast(size), "to", "left").withColumn("r", F.row_number().over(Window.partitionBy("to").orderBy(F.desc("gain"), "vid")))
        taken = ranked.where(F.col("r") <= F.lit(cap) - F.coalesce("n", F.lit(0))).select("vid", "to")
        owner = stage(owner.join(taken, "vid", "left").select("vid", F.coalesce("to", "part").cast("int").alias("part")))
    return owner


def _bounded(up: DataFrame, limit: int) -> DataFrame:
    """(vid, up) of (vid, size, up): each cluster in pieces, in order of vid, of a size of limit or a single vertex more."""
    from pyspark.sql.window import Window

    before = F.sum("size").over(Window.partitionBy("up").orderBy("vid").rowsBetween(Window.unboundedPreceding, -1))
    piece = up.withColumn("piece", F.floor(F.coalesce(before, F.lit(0)) / F.lit(limit)))
    return piece.select("vid", F.min("vid").over(Window.partitionBy("up", "piece")).alias("up"))


def _cut_weight(links: DataFrame, cut: DataFrame) -> int:
    a, b = cut.select("vid", F.col("part").alias("pa")), cut.select(F.col("vid").alias("nbr"), F.col("part").alias("pb"))
    return links.join(a, "vid").join(b, "nbr").where("pa <> pb").agg(F.coalesce(F.sum("w"), F.lit(0))).first()[0]


def refine_cut(links: DataFrame, weight: DataFrame, cut: DataFrame, cap: float, *, passes: int = 2, stage=lambda d: d) -> DataFrame:
    """cut (vid, part) after moves of vertices to the part most of their links go to, where they gain and the part has
    room. Moves of a pass go to higher parts or to lower ones only; a pass that does not lower the cut is taken back."""
    from pyspark.sql.window import Window

    cut = stage(cut)
    held = _cut_weight(links, cut)
    for k in range(passes):
        votes = links.join(cut.select(F.col("vid").alias("nbr"), F.col("part").alias("to")), "nbr").groupBy("vid", "to").agg(F.sum("w").alias("votes")).join(cut, "vid")
        stay = F.max(F.when(F.col("to") == F.col("part"), F.col("votes")))
        way = F.col("to") > F.col("part") if k % 2 == 0 else F.col("to") < F.col("part")
        best = votes.groupBy("vid", "part").agg(stay.alias("stay"), F.max(F.when(way, F.struct("votes", (-F.col("to")).alias("to")))).alias("best"))
        moves = best.select("vid", (-F.col("best.to")).alias("to"), (F.col("best.votes") - F.coalesce("stay", F.lit(0))).alias("gain")).where("gain > 0").join(weight, "vid")
        load = cut.join(weight, "vid").groupBy(F.col("part").alias("to")).agg(F.sum("size").alias("load"))
        filled = moves.join(F.broadcast(load), "to", "left").withColumn("sum", F.sum("size").over(Window.partitionBy("to").orderBy(F.desc("gain"), "vid").rowsBetween(Window.unboundedPreceding, 0)))
        taken = filled.where(F.col("sum") + F.coalesce("load", F.lit(0)) <= F.lit(cap)).select("vid", "to")
        moved = stage(cut.join(taken, "vid", "left").select("vid", F.coalesce("to", "part").cast("int").alias("part")))
        now = _cut_weight(links, moved)
        if now < held:
            cut, held = moved, now
    return cut


def multilevel_edge_cut(graph, parts: int, *, coarsest: int = 2000, slack: float = 1.2, passes: int = 2, stage=lambda d: d) -> DataFrame:
    """Multilevel edge-cut: heavy-edge matching, greedy growing of the coarsest graph, label refinement of each level.

    Levels are made until `coarsest` vertices (at least 16 a part) are left, which alone reach the driver. Clusters are
    held to a size that leaves so many. Where matching stalls, vertices of one favourite neighbour merge (two hops),
    and those without links by hash; where that stalls too, any vertices do, by hash, and refinement mends the cut.
    """
    coarsest = max(coarsest, 16 * parts)
    links = stage(graph.adjacency().where("vid <> nbr").groupBy("vid", "nbr").agg(F.sum(F.lit(1)).alias("w")))
    weight = stage(graph.vertices().withColumn("size", F.lit(1).cast("long")))
    n = total = weight.count()
    limit, chain, how = max(2, -(-4 * total // coarsest)), [], 0
    while n > coarsest:
        best = links.groupBy("vid").agg(F.max_by("nbr", F.struct("w", F.xxhash64(F.least("vid", "nbr"), F.greatest("vid", "nbr")))).alias("mate"))
        loose = F.pmod(F.xxhash64(F.lit(len(chain)), "vid"), F.lit(coarsest // 4)) + F.lit(1)
        if how == 0:
            other = best.select(F.col("vid").alias("mate"), F.col("mate").alias("back"))
            # Mutual choices merge; a vertex whose choice was taken joins the pair that took it.
            up = best.join(other, "mate").select("vid", F.when(F.col("back") == F.col("vid"), F.least("vid", "mate")).otherwise(F.least("mate", "back")).alias("up"))
            up = weight.join(up, "vid", "left").select("vid", "size", F.struct(F.lit(0).alias("kind"), F.coalesce("up", "vid").alias("id")).alias("up"))
        elif how == 1:
            up = weight.join(best, "vid", "left").select("vid", "size", F.struct(F.when(F.col("mate").isNull(), 1).otherwise(0).alias("kind"), F.coalesce("mate", loose).alias("id")).alias("up"))
        else:
            up = weight.select("vid", "size", F.struct(F.lit(1).alias("kind"), loose.alias("id")).alias("up"))
        up = stage(_bounded(up, limit))
        left = up.agg(F.countDistinct("up")).first()[0]
        if left > 0.9 * n and left > coarsest:
            how = (how + 1) % 3
            if left == n:
                if how == 0:
                    limit *= 2
                continue
        else:
            how = 0
        chain.append((up, links, weight))
        to = up.select(F.col("vid").alias("nbr"), F.col("up").alias("nup"))
        links = stage(links.join(up, "vid").join(to, "nbr").where("up <> nup").groupBy(F.col("up").alias("vid"), F.col("nup").alias("nbr")).agg(F.sum("w").alias("w")))
        weight = stage(weight.join(up, "vid").groupBy(F.col("up").alias("vid")).agg(F.sum("size").alias("size")))
        n = left
    # As arrays: the coarsest graph may be dense, and a Row a link would not fit the driver.
    held, ends = weight.orderBy("vid").toArrow(), links.toArrow()
    vid, size = (held.column(c).to_numpy().astype(np.int64) for c in ("vid", "size"))
    a, b = (np.searchsorted(vid, ends.column(c).to_numpy()) for c in ("vid", "nbr"))
    order = np.argsort(a, kind="stable")
    b, w, first = b[order], ends.column("w").to_numpy()[order], np.searchsorted(a[order], np.arange(len(vid) + 1))
    cap, load, owner = slack * total / parts, [0] * parts, np.full(len(vid), -1)
    for v in np.lexsort((vid, -size)).tolist():
        to, share = owner[b[first[v] : first[v + 1]]], w[first[v] : first[v + 1]]
        gain = np.bincount(to[to >= 0], share[to >= 0], parts)
        p = min(range(parts), key=lambda p: (load[p] + size[v] > cap, -gain[p], load[p], p))
        owner[v] = p
        load[p] += int(size[v])
    cut = links.sparkSession.createDataFrame(list(zip(vid.tolist(), owner.tolist(), strict=True)), "vid long, part int")
    cut = refine_cut(links, weight, cut, cap, passes=passes, stage=stage)
    for up, links, weight in reversed(chain):
        cut = up.join(cut.withColumnRenamed("vid", "up"), "up").select("vid", "part")
        cut = refine_cut(links, weight, cut, cap, passes=passes, stage=stage)
    return cut
