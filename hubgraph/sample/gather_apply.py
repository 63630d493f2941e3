"""K-hop neighbour sampling in two steps: each part answers for its share of a vertex's edges, then answers merge."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from hubgraph.core.model import both_ends
from hubgraph.core.portable import uniform
from hubgraph.session import stage


@dataclass(frozen=True)
class SampleConfig:
    """weighted: scores u**(1/w). rounding (uniform only): "global_topk" is exact, "bernoulli" takes floor and coin of
    each part's share, "largest_remainder" deals exactly f over the parts. include_self keeps seeds in the frontier."""

    weighted: bool = False
    direction: str = "both"
    etypes: tuple[int, ...] | None = None
    rounding: str = "global_topk"
    salt: str = "s"
    include_self: bool = False
    metapath: tuple[tuple[int, ...], ...] | None = None
    replace_frontier: bool = True


def score(cfg: SampleConfig, hop: int):
    """Larger is better. Equal for an edge wherever it lives, so the sample does not depend on the partitioning."""
    u = uniform(f"{cfg.salt}{hop}", "vid", "eid")
    if not cfg.weighted:
        return u
    w = F.coalesce("weight", F.lit(1.0))
    return F.when(w > 0, F.round(F.pow(u, 1 / w), 9))


def local_adjacency(edges: DataFrame, direction: str = "both") -> DataFrame:
    """(part, vid, nbr, eid, etype, weight): the lists that each part holds."""
    return both_ends(edges, ["part", "eid", "etype", "weight"], direction)


def routes(adjacency: DataFrame) -> DataFrame:
    """(vid, part): the parts that hold some of a vertex's list, which is where requests for it go."""
    return adjacency.select("vid", "part").distinct()


def gather(adjacency: DataFrame, seeds: DataFrame, fanout: int, cfg: SampleConfig, hop: int, held: DataFrame | None = None) -> DataFrame:
    """Each part's partial answer for each seed. Requests (vid, part) go to the parts that hold some of the list
    (`held`, by default looked up), so lists and requests meet on both and a hub's list is spread over its parts."""
    types = cfg.metapath[hop] if cfg.metapath else cfg.etypes
    lists = adjacency if types is None else adjacency.where(F.col("etype").isin(*types))
    requests = (routes(adjacency) if held is None else held).join(seeds, "vid")
    asked = lists.join(requests, ["vid", "part"]).withColumn("score", score(cfg, hop)).where("score is not null")
    best = Window.partitionBy("part", "vid").orderBy(F.desc("score"), "eid")
    ranked = asked.withColumn("r", F.row_number().over(best))
    if cfg.weighted or cfg.rounding == "global_topk":
        return ranked.where(F.col("r") <= fanout)
    local = asked.groupBy("vid", "part").agg(F.count("*").alias("local"))
    total = local.groupBy("vid").agg(F.sum("local").alias("total"))
    share = local.join(total, "vid").withColumn("q", F.least(F.lit(fanout), F.col("total")) * F.col("local") / F.col("total"))
    if cfg.rounding == "bernoulli":
        coin = (uniform(f"{cfg.salt}c{hop}", "vid", "part") < F.col("q") - F.floor("q")).cast("int")
        share = share.withColumn("quota", F.floor("q") + coin)
    else:
        order = Window.partitionBy("vid").orderBy(F.desc(F.round(F.col("q") - F.floor("q"), 9)), "part")
        spare = F.least(F.lit(fanout), F.col("total")) - F.sum(F.floor("q")).over(Window.partitionBy("vid"))
        share = share.withColumn("quota", F.floor("q") + (F.row_number().over(order) <= spare).cast("int"))
    return ranked.join(share.select("vid", "part", "quota"), ["vid", "part"]).where("r <= quota").drop("quota")


def apply(partial: DataFrame, fanout: int, cfg: SampleConfig) -> DataFrame:
    """Merged answers: the best over all parts, or all of them where quotas have been met already."""
    if not cfg.weighted and cfg.rounding != "global_topk":
        return partial
    best = Window.partitionBy("vid").orderBy(F.desc("score"), "eid")
    return partial.withColumn("r", F.row_number().over(best)).where(F.col("r") <= fanout)


def khop_sample(edges: DataFrame, seeds: DataFrame, fanouts: list[int], cfg: SampleConfig = SampleConfig()) -> DataFrame:
    """(hop, vid, nbr, eid, etype, score) for edges (…, part) and seeds (vid); later frontiers are written out."""
    adjacency = local_adjacency(edges, cfg.direction)
    held = stage(routes(adjacency)) if len(fanouts) > 1 else None
    frontier, blocks = seeds.select("vid").distinct(), None
    for hop, fanout in enumerate(fanouts):
        block = apply(gather(adjacency, frontier, fanout, cfg, hop, held), fanout, cfg).select(F.lit(hop).alias("hop"), "vid", "nbr", "eid", "etype", "score")
        if hop + 1 < len(fanouts) and hop >= 1:
            block = stage(block)
        blocks = block if blocks is None else blocks.unionByName(block)
        nxt = block.select(F.col("nbr").alias("vid"))
        frontier = (nxt.union(frontier) if cfg.include_self else nxt).distinct()
    return blocks


def workload(edges: DataFrame, seeds: DataFrame, fanout: int, cfg: SampleConfig = SampleConfig()) -> DataFrame:
    """(part, requests, scanned, returned, load) of one hop: load is edges scanned over the least of any part."""
    adjacency = local_adjacency(edges, cfg.direction)
    asked = adjacency.join(seeds, "vid").groupBy("part").agg(F.countDistinct("vid").alias("requests"), F.count("*").alias("scanned"))
    sent = gather(adjacency, seeds, fanout, cfg, 0).groupBy("part").agg(F.count("*").alias("returned"))
    least = Window.partitionBy(F.lit(1))
    return asked.join(sent, "part", "left").select("part", "requests", "scanned", "returned", F.round(F.col("scanned") / F.min("scanned").over(least), 6).alias("load"))


def owner_workload(graph, owner: DataFrame, seeds: DataFrame, fanout: int) -> DataFrame:
    """The same for an owner sampler: a vertex's whole list is scanned by the part that owns it."""
    degree = graph.degrees().join(seeds, "vid").join(owner, "vid")
    load = degree.groupBy("part").agg(F.count("*").alias("requests"), F.sum("degree").alias("scanned"), F.sum(F.least("degree", F.lit(fanout))).alias("returned"))
    return load.select("part", "requests", "scanned", "returned", F.round(F.col("scanned") / F.min("scanned").over(Window.partitionBy(F.lit(1))), 6).alias("load"))


def owner_sample(graph, owner: DataFrame, seeds: DataFrame, fanout: int, cfg: SampleConfig = SampleConfig()) -> DataFrame:
    """One hop by owners: whole lists are ranked where they live."""
    asked = graph.adjacency(cfg.direction).join(seeds, "vid").join(owner, "vid").withColumn("score", score(cfg, 0)).where("score is not null")
    best = Window.partitionBy("vid").orderBy(F.desc("score"), "eid")
    return asked.withColumn("r", F.row_number().over(best)).where(F.col("r") <= fanout).select("part", "vid", "nbr", "eid", "etype", "score")


def typed_fanout_sample(edges: DataFrame, seeds: DataFrame, fanouts: dict[int, int], cfg: SampleConfig = SampleConfig()) -> DataFrame:
    """One hop with a fanout of its own for each edge type: parts answer by (vid, type), then answers merge."""
    adjacency = local_adjacency(edges, cfg.direction).where(F.col("etype").isin(*fanouts))
    most = F.create_map(*(F.lit(x) for kv in fanouts.items() for x in kv))[F.col("etype")]
    asked = adjacency.join(routes(adjacency).join(seeds, "vid"), ["vid", "part"]).withColumn("score", score(cfg, 0)).where("score is not null")
    for keys in (["part", "vid", "etype"], ["vid", "etype"]):
        best = Window.partitionBy(*keys).orderBy(F.desc("score"), "eid")
        asked = asked.withColumn("r", F.row_number().over(best)).where(F.col("r") <= most)
    return asked.select("vid", "nbr", "eid", "etype", "score")


def as_of_sample(edges: DataFrame, seeds: DataFrame, fanout: int, cfg: SampleConfig = SampleConfig()) -> DataFrame:
    """One hop over edges (…, ts) for seeds (vid, at): only edges that were there at the seed's time are drawn."""
    asked = both_ends(edges, ["eid", "etype", "weight", "ts"], cfg.direction).join(seeds, "vid").where("ts <= at").withColumn("score", score(cfg, 0)).where("score is not null")
    best = Window.partitionBy("vid", "at").orderBy(F.desc("score"), "eid")
    return asked.withColumn("r", F.row_number().over(best)).where(F.col("r") <= fanout).select("vid", "nbr", "eid", "score")


def balanced_seeds(home: DataFrame, per_part: int, salt: str = "b") -> DataFrame:
    order = Window.partitionBy("home").orderBy(uniform(salt, "vid"), "vid")
    return home.withColumn("r", F.row_number().over(order)).where(F.col("r") <= per_part).select("vid")


def single_part_seeds(home: DataFrame, n: int, part: int = 0, salt: str = "b") -> DataFrame:
    return home.where(F.col("home") == part).orderBy(uniform(salt, "vid"), "vid").limit(n).select("vid")


def khop_closure(graph, seeds: DataFrame, hops: int) -> DataFrame:
    """(hop, n): vertices within each distance, without sampling."""
    reached, sizes = seeds.select("vid").distinct(), None
    adjacency = graph.adjacency().select("vid", "nbr")
    for hop in range(hops + 1):
        row = reached.agg(F.lit(hop).alias("hop"), F.count("*").alias("n"))
        sizes = row if sizes is None else sizes.union(row)
        reached = stage(adjacency.join(reached, "vid").select(F.col("nbr").alias("vid")).union(reached).distinct())
    return sizes


def frontier_sizes(blocks: DataFrame) -> DataFrame:
    """(hop, seeds, rows, reached) of K-hop blocks."""
    return blocks.groupBy("hop").agg(F.countDistinct("vid").alias("seeds"), F.count("*").alias("rows"), F.countDistinct("nbr").alias("reached"))


def traffic(placed: DataFrame, seeds: DataFrame, fanout: int) -> DataFrame:
    """(shipped, kept): rows that the parts send for one hop, and rows left once they are merged."""
    ends = placed.select("part", F.explode(F.array("src", "dst")).alias("vid")).join(seeds.select("vid"), "vid")
    local = ends.groupBy("vid", "part").agg(F.count("*").alias("n"))
    seed = local.groupBy("vid").agg(F.sum(F.least("n", F.lit(fanout))).alias("shipped"), F.least(F.sum("n"), F.lit(fanout)).alias("kept"))
    return seed.agg(F.sum("shipped").alias("shipped"), F.sum("kept").alias("kept"))
