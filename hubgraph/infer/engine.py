"""Full-graph inference a layer at a time, and the sample-wise way that it is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from hubgraph.core.portable import uniform
from hubgraph.infer.layers import LayerSpec, apply_layer
from hubgraph.session import stage


def one_hop(graph, fanout: int, layer: int, salt: str = "i", columns: tuple[str, ...] = ("etype",)) -> DataFrame:
    """(vid, nbr, columns): each vertex's sampled neighbours in a layer, a function of (vertex, layer, salt) alone."""
    best = Window.partitionBy("vid").orderBy(uniform(f"{salt}{layer}", "vid", "eid"), "eid")
    return graph.adjacency().withColumn("r", F.row_number().over(best)).where(F.col("r") <= fanout).select("vid", "nbr", *columns)


def layerwise_infer(graph, h0: DataFrame, layers: list[LayerSpec], fanouts: list[int], salt: str = "i") -> DataFrame:
    """(vid, h): every layer for all vertices, each result written before the next. Hop h of a sample feeds layer
    K - h, so layer k uses the fanouts from the end."""
    h, last = h0, len(layers)
    for k, layer in enumerate(layers):
        h = stage(apply_layer(h, one_hop(graph, fanouts[last - 1 - k], k, salt), layer))
    return h


def samplewise_infer(graph, h0: DataFrame, layers: list[LayerSpec], fanouts: list[int], targets: DataFrame, salt: str = "i") -> DataFrame:
    """(vid, h) of the targets, from their own K-hop samples; layer k is evaluated for all that lies K - k hops away.
    A neighbour's sampled degree, which gcn needs, is its degree or the fanout: no sample of its own is drawn for it."""
    degree = stage(graph.degrees())
    last, frontiers, hops = len(layers), [targets.select("vid").distinct()], []
    for k in reversed(range(last)):
        hop = stage(one_hop(graph, fanouts[last - 1 - k], k, salt).join(frontiers[-1], "vid", "left_semi"))
        hops.append(hop)
        frontiers.append(stage(hop.select(F.col("nbr").alias("vid")).union(frontiers[-1]).distinct()))
    h = h0.join(frontiers[-1], "vid", "left_semi")
    for k, layer in enumerate(layers):
        sampled = degree.select("vid", F.least("degree", F.lit(fanouts[last - 1 - k])).alias("deg"))
        h = stage(apply_layer(h, hops[last - 1 - k], layer, sampled).join(frontiers[last - 1 - k], "vid", "left_semi"))
    return h


def compute_counts(graph, fanouts: list[int], salt: str = "i") -> DataFrame:
    """Vertex evaluations of both ways over all vertices and of naive link prediction (both ends of every edge).

    Counts trees: a vertex at depth j is evaluated in each layer up to K - j.
    """
    layers = len(fanouts)
    size = graph.vertices().select("vid", F.lit(1).cast("long").alias("n"))
    tree = size
    for k in range(layers):  # evaluations of layer k + 1 over trees: itself and what its neighbours need below
        if k:
            hop = one_hop(graph, fanouts[layers - 1 - k], k, salt)
            below = hop.join(tree.select(F.col("vid").alias("nbr"), "n"), "nbr").groupBy("vid").agg(F.sum("n").alias("s"))
            tree = stage(tree.join(below, "vid", "left").select("vid", (F.lit(1) + F.col("n") + F.coalesce("s", F.lit(0))).cast("long").alias("n")))
    naive = tree.agg(F.sum("n").alias("naive"), (F.count("*") * layers).alias("layerwise"))
    ends = graph.edges.select(F.explode(F.array("src", "dst")).alias("vid")).join(tree, "vid").agg(F.sum("n").alias("naive_links"))
    return naive.crossJoin(ends).select("layerwise", "naive", "naive_links", F.round(F.col("naive") / F.col("layerwise"), 6).alias("ratio"), F.round(F.col("naive_links") / F.col("layerwise"), 6).alias("link_ratio"))


def score_edges(h: DataFrame, edges: DataFrame) -> DataFrame:
    """(eid, score): the dot product of both ends' embeddings."""
    a, b = h.select(F.col("vid").alias("src"), F.col("h").alias("hs")), h.select(F.col("vid").alias("dst"), F.col("h").alias("hd"))
    dot = F.aggregate(F.zip_with("hs", "hd", lambda x, y: x * y), F.lit(0.0), lambda acc, x: acc + x)
    return edges.join(a, "src").join(b, "dst").select("eid", F.round(dot, 6).alias("score"))


def static_cache(home: DataFrame, resident: DataFrame, hop: DataFrame) -> DataFrame:
    """(worker, vid, own): what each worker keeps: its part's vertices, and sampled neighbours that are not resident."""
    own = resident.select(F.col("part").alias("worker"), "vid")
    needed = hop.join(home.select("vid", F.col("home").alias("worker")), "vid").select("worker", F.col("nbr").alias("vid")).distinct()
    remote = needed.join(own, ["worker", "vid"], "left_anti")
    return own.withColumn("remote", F.lit(False)).unionByName(remote.withColumn("remote", F.lit(True)))


#: Sort keys of local ids by order.
ORDERS = {"ns": ["vid"], "ds": ["degree_desc", "vid"], "ps": ["home", "vid"], "pds": ["home", "degree_desc", "vid"]}


def reorder(cached: DataFrame, home: DataFrame, degree: DataFrame, key: str) -> DataFrame:
    """(worker, vid, lid): local ids of each worker's cached vertices in the order of the key."""
    keyed = cached.join(home, "vid").join(degree, "vid").withColumn("degree_desc", -F.col("degree"))
    return keyed.select("worker", "vid", (F.row_number().over(Window.partitionBy("worker").orderBy(*ORDERS[key])) - 1).alias("lid"))


def reorder_hub_cluster(cached: DataFrame, degree: DataFrame) -> DataFrame:
    """(worker, vid, lid): vertices above their worker's mean degree first, each side in the order of ids."""
    keyed = cached.join(degree, "vid").select("worker", "vid", "degree")
    mean = keyed.groupBy("worker").agg(F.avg("degree").alias("mean"))
    order = Window.partitionBy("worker").orderBy(F.when(F.col("degree") > F.col("mean"), 0).otherwise(1), "vid")
    return keyed.join(F.broadcast(mean), "worker").select("worker", "vid", (F.row_number().over(order) - 1).alias("lid"))


def breadth_first_levels(graph) -> DataFrame:
    """(vid, level): steps from the vertex of the highest degree; vertices that it cannot reach are left out."""
    adjacency = stage(graph.adjacency().select("vid", "nbr").distinct())
    near = stage(graph.degrees().orderBy(F.desc("degree"), "vid").limit(1).select("vid"))
    reached, level = near.withColumn("level", F.lit(0)), 0
    while not near.isEmpty():
        level += 1
        near = stage(adjacency.join(near, "vid").select(F.col("nbr").alias("vid")).distinct().join(reached, "vid", "left_anti"))
        reached = reached.unionByName(near.withColumn("level", F.lit(level)))
    return reached


def reorder_breadth_first(cached: DataFrame, levels: DataFrame) -> DataFrame:
    """(worker, vid, lid): each worker's cached vertices by level, then id; those without a level last."""
    order = Window.partitionBy("worker").orderBy(F.col("level").asc_nulls_last(), "vid")
    return cached.join(levels, "vid", "left").select("worker", "vid", (F.row_number().over(order) - 1).alias("lid"))


def locality(lids: DataFrame, placed: DataFrame) -> DataFrame:
    """(worker, edges, mean_gap, mean_bits): how far apart the local ids of an edge's ends lie, and the bits of the gap."""
    a = lids.select(F.col("worker").alias("part"), F.col("vid").alias("src"), F.col("lid").alias("a"))
    b = lids.select(F.col("worker").alias("part"), F.col("vid").alias("dst"), F.col("lid").alias("b"))
    gap = F.abs(F.col("a") - F.col("b")).cast("long")
    near = placed.select("part", "src", "dst").join(a, ["part", "src"]).join(b, ["part", "dst"]).select("part", gap.alias("gap"))
    return near.groupBy(F.col("part").cast("long").alias("worker")).agg(F.count("*").alias("edges"), F.round(F.avg("gap"), 6).alias("mean_gap"), F.round(F.avg(F.length(F.bin("gap"))), 6).alias("mean_bits"))


def access_trace(lids: DataFrame, home: DataFrame, hop: DataFrame, *, chunk: int, batch: int) -> DataFrame:
    """(worker, step, chunk): the distinct chunks that each batch of a worker's own vertices reads, in lid order."""
    mine = lids.join(home.select("vid", F.col("home").alias("worker")), ["vid", "worker"])
    step = mine.withColumn("step", F.floor((F.row_number().over(Window.partitionBy("worker").orderBy("lid")) - 1) / batch)).select("worker", "vid", "step")
    reads = step.join(hop.select("vid", "nbr"), "vid").select("worker", "step", F.col("nbr").alias("vid"))
    return reads.join(lids, ["worker", "vid"]).select("worker", "step", F.floor(F.col("lid") / chunk).alias("chunk")).distinct()


def simulate_cache(trace: DataFrame, capacity: int, policy: str) -> DataFrame:
    """(worker, reads, hits) of a chunk cache of `capacity`: none, fifo or lru; each worker's trace is walked in order."""

    def walk(key, frame):
        import pandas as pd

        held, hits = {}, 0
        for c in frame.sort_values(["step", "chunk"])["chunk"]:
            if policy != "none" and c in held:
                hits += 1
                if policy == "lru":
                    held[c] = held.pop(c)
                continue
            if policy != "none":
                if len(held) >= capacity:
                    held.pop(next(iter(held)))
                held[c] = True
        return pd.DataFrame({"worker": [key[0]], "reads": [len(frame)], "hits": [hits]})

    return trace.groupBy("worker").applyInPandas(walk, "worker int, reads long, hits long")
