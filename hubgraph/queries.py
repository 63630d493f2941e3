"""Registered queries of the graph engine, and the DuckDB SQL that they are held against."""

from __future__ import annotations

from pyspark.sql import functions as F

from hubgraph.core.portable import sql_bucket, sql_uniform, uniform
from hubgraph.infer import engine
from hubgraph.infer.layers import LayerSpec, make_layer
from hubgraph.layout import compact
from hubgraph.operators import sql_suite
from hubgraph.partition import expansion, metrics, placement
from hubgraph.sample import gather_apply as ga
from hubgraph.session import stage, table
from hubgraph.sources import graphs
from hubgraph.streaming import events as streams
from hubgraph.train import links

PARTS = 8
QUERIES, ORACLES = {}, {}


def _add(name, query, sql=None):
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def _cte(graph, *more):
    return f"WITH e AS ({(graphs.SQL | graphs.MORE_SQL)[graph]})" + "".join(f", {m}" for m in more)


_ADJ = "adj AS (SELECT src AS vid, dst AS nbr, eid, etype, weight{p} FROM {e} UNION ALL SELECT dst, src, eid, etype, weight{p} FROM {e})"
_DEG = "deg AS (SELECT vid, count(*) AS degree FROM adj GROUP BY vid)"


def _adj(e="e", part=False):
    return _ADJ.format(e=e, p=", part" if part else "")


def _placed(kind, parts=PARTS):
    return f"p AS (SELECT *, {placement.sql_place(parts, kind)}::INTEGER AS part FROM e)"


# Dataset statistics and degree distributions.
for _g in graphs.SQL | graphs.MORE_SQL:
    _add(f"graph_stats_{_g}", lambda s, d, g=_g: metrics.degree_stats(graphs.GRAPHS[g](s, d)), _cte(_g, _adj(), _DEG) + " SELECT count(*) AS v, (sum(degree) / 2)::BIGINT AS e, round(avg(degree), 6) AS avg_degree, max(degree) AS max_degree FROM deg")
    _add(f"degree_hist_{_g}", lambda s, d, g=_g: metrics.degree_histogram(graphs.GRAPHS[g](s, d)), _cte(_g, _adj(), _DEG) + " SELECT (length(bin(degree)) - 1)::INTEGER AS bin, count(*) AS n, sum(degree)::BIGINT AS ends FROM deg GROUP BY 1")
_add("tail_exponent_lexicon", lambda s, d: metrics.tail_exponent(graphs.lexicon(s, d)), _cte("lexicon", _adj(), _DEG) + " SELECT count(*) AS n, round(1 + 1 / avg(ln(degree / 3.5)), 6) AS exponent FROM deg WHERE degree >= 4")

_REPORT = (
    f" , parts AS (SELECT range::INTEGER AS part FROM range({PARTS})), ne AS (SELECT part, count(*) AS ne FROM p GROUP BY part), res AS (SELECT DISTINCT part, unnest([src, dst]) AS vid FROM p), nv AS (SELECT part, count(*) AS nv FROM res GROUP BY part),"
    " t AS (SELECT coalesce(ne, 0) AS ne, coalesce(nv, 0) AS nv FROM parts LEFT JOIN ne USING (part) LEFT JOIN nv USING (part)), k AS (SELECT vid, count(*) AS k FROM res GROUP BY vid)"
    " SELECT round(sum(nv) / (SELECT count(*) FROM k), 6) AS rf, round(max(nv) / nullif(min(nv), 0), 6) AS vb, round(max(ne) / nullif(min(ne), 0), 6) AS eb, count(*) FILTER (ne = 0) AS empty_parts, round((SELECT avg(CASE WHEN k = 1 THEN 1.0 ELSE 0.0 END) FROM k), 6) AS interior FROM t"
)
for _g in graphs.SQL | graphs.MORE_SQL:
    for _k in ("random", "hash1d", "hash1d_dst", "hash2d"):
        _add(f"part_quality_{_k}_{_g}", lambda s, d, g=_g, k=_k: metrics.partition_report(stage(placement.place(graphs.GRAPHS[g](s, d).edges, PARTS, k).select("eid", "src", "dst", "part")), PARTS), _cte(_g, _placed(_k)) + _REPORT)

_EDGE_CUT = f"v AS (SELECT DISTINCT unnest([src, dst]) AS vid FROM e), o AS (SELECT vid, {sql_bucket(PARTS, 'v', 'vid')} AS part FROM v), p AS (SELECT eid, src, dst, unnest(list_distinct([a.part, b.part])) AS part FROM e JOIN o a ON a.vid = src JOIN o b ON b.vid = dst)"


def _edge_cut_quality(owner, graph):
    both, resident = placement.materialise_edge_cut(owner, graph.edges)
    return metrics.partition_report(stage(both.select("eid", "src", "dst", "part")), PARTS, resident)


for _g in ("trade", "folded", "lexicon"):
    _add(f"part_quality_hash_edgecut_{_g}", lambda s, d, g=_g: _edge_cut_quality(placement.hash_edge_cut(graphs.GRAPHS[g](s, d), PARTS), graphs.GRAPHS[g](s, d)), _cte(_g, _EDGE_CUT) + _REPORT)


# Expansion: the cover is held against the raw table, the quality is reported.
def _cover(result, parts=4):
    e = result.edges
    return e.agg(F.count("*").alias("edges"), (F.count("*") - F.countDistinct("eid")).alias("duplicates"), F.count_if(F.col("part").isNull() | (F.col("part") < 0) | (F.col("part") >= parts)).alias("unassigned"))


_COVER_SQL = " SELECT count(*) AS edges, 0::BIGINT AS duplicates, 0::BIGINT AS unassigned FROM e"
EXPANSIONS = {"bse": expansion.bse_partition, "tse": expansion.tse_partition}
for _n, _f in EXPANSIONS.items():
    _add(f"part_cover_{_n}", lambda s, d, f=_f: _cover(f(graphs.folded(s, d), 4)), _cte("folded") + _COVER_SQL)
    for _g in graphs.SQL:
        for _p in (4, 8):
            _add(f"part_quality_{_n}_{_g}_{_p}", lambda s, d, f=_f, g=_g, p=_p: expansion.quality(f, graphs.GRAPHS[g](s, d), p))
    for _g in ("lexicon", "folded"):
        _add(f"part_quality_{_n}_grid_start_{_g}", lambda s, d, f=_f, g=_g: expansion.quality(f, graphs.GRAPHS[g](s, d), 8, start="grid"))
for _n, _o in (("vertex_only", {"beta": 0.0}), ("edge_only", {"alpha": 0.0}), ("unsteered", {"alpha": 0.0, "beta": 0.0})):
    _add(f"part_quality_bse_{_n}_lexicon", lambda s, d, o=_o: expansion.quality(expansion.bse_partition, graphs.lexicon(s, d), 4, **o))
for _g in graphs.SQL:
    for _p in (4, 8):
        _add(f"balance_claim_{_g}_{_p}", lambda s, d, g=_g, p=_p: expansion.balance_claim(stage(expansion.balance_study(graphs.GRAPHS[g](s, d), p))))
# The rounds as a large graph runs them, however small this one is; without a bound of a round, so that they are few.
_add("part_cover_bse_rounds_web", lambda s, d: _cover(expansion.bse_partition(graphs.web(s, d), 4, lambda0=0.5, round_share=None, max_rounds=10, local_limit=0)), _cte("web") + _COVER_SQL)


def _trace(s, d):
    return s.createDataFrame(expansion.bse_partition(graphs.folded(s, d), 4).trace)


_add("part_trace_bse", _trace)
_OWNED = " SELECT count(*) AS vertices, 0::BIGINT AS duplicates FROM (SELECT DISTINCT unnest([src, dst]) FROM e)"
for _n, _f in (("lp", placement.label_propagation_cut), ("mlec", placement.multilevel_edge_cut)):
    _add(f"part_cover_{_n}", lambda s, d, f=_f: f(graphs.trade(s, d), PARTS, stage=stage).agg(F.count("*").alias("vertices"), (F.count("*") - F.countDistinct("vid")).alias("duplicates")), _cte("trade") + _OWNED)
    _add(f"part_quality_{_n}_trade", lambda s, d, f=_f: _edge_cut_quality(f(graphs.trade(s, d), PARTS, stage=stage), graphs.trade(s, d)))

# Roles and homes.
_add("home_partition_folded", lambda s, d: metrics.home_partition(placement.place(graphs.folded(s, d).edges, PARTS, "hash2d")), _cte("folded", _placed("hash2d")) + " SELECT vid, arg_max(part, {'n': n, 'p': -part})::INTEGER AS home FROM (SELECT vid, part, count(*) AS n FROM (SELECT part, unnest([src, dst]) AS vid FROM p) GROUP BY 1, 2) GROUP BY vid")
_add("partition_bits_lexicon", lambda s, d: metrics.partition_bits(metrics.replicas(placement.place(graphs.lexicon(s, d).edges, PARTS, "hash1d"))), _cte("lexicon", _placed("hash1d")) + " SELECT vid, bit_or(1::BIGINT << part) AS bits FROM (SELECT DISTINCT part, unnest([src, dst]) AS vid FROM p) GROUP BY vid")

_add("vertex_roles_lexicon", lambda s, d: metrics.partition_bits(metrics.replicas(placement.place(graphs.lexicon(s, d).edges, PARTS, "hash2d"))).select("vid", (F.bit_count("bits") == 1).alias("interior")), _cte("lexicon", _placed("hash2d")) + " SELECT vid, count(DISTINCT part) = 1 AS interior FROM (SELECT part, unnest([src, dst]) AS vid FROM p) GROUP BY vid")

# Sampling.
FANOUTS = [10, 5]


def _seeds(graph, n=200):
    return graph.vertices().orderBy(uniform("seed", "vid"), "vid").limit(n)


_SEEDS = f"seeds AS (SELECT vid FROM (SELECT DISTINCT unnest([src, dst]) AS vid FROM e) ORDER BY {sql_uniform('seed', 'vid')}, vid LIMIT 200)"


def _hop_sql(hop, fanout, frontier, weighted, types=None):
    score = sql_uniform(f"s{hop}", "vid", "eid")
    if weighted:
        score = f"round(pow({score}, 1 / weight), 9)"
    where = f" WHERE etype IN ({', '.join(map(str, types))})" if types else ""
    return f"hop{hop} AS (SELECT {hop} AS hop, vid, nbr, eid, etype, score FROM (SELECT *, row_number() OVER (PARTITION BY vid ORDER BY score DESC, eid) AS r FROM (SELECT vid, nbr, eid, etype, {score} AS score FROM adj JOIN {frontier} USING (vid){where})) WHERE r <= {fanout}), next{hop} AS (SELECT DISTINCT nbr AS vid FROM hop{hop})"


def _khop_sql(graph, weighted=False, types=(None, None)):
    return _cte(graph, _adj(), _SEEDS, _hop_sql(0, 10, "seeds", weighted, types[0]), _hop_sql(1, 5, "next0", weighted, types[1])) + " SELECT * FROM hop0 UNION ALL SELECT * FROM hop1"


def _khop(graph, cfg, kind="hash2d"):
    return ga.khop_sample(placement.place(graph.edges, PARTS, kind), _seeds(graph), FANOUTS, cfg)


for _g in ("trade", "folded", "lexicon", "commerce"):
    _add(f"sample_uniform_khop_{_g}", lambda s, d, g=_g: _khop(graphs.GRAPHS[g](s, d), ga.SampleConfig()), _khop_sql(_g))
for _g in ("trade", "folded"):
    _add(f"sample_weighted_khop_{_g}", lambda s, d, g=_g: _khop(graphs.GRAPHS[g](s, d), ga.SampleConfig(weighted=True)), _khop_sql(_g, True))
_add("sample_weighted_unit_lexicon", lambda s, d: _khop(graphs.lexicon(s, d), ga.SampleConfig(weighted=True)), _khop_sql("lexicon", True))
_add("sample_metapath_commerce", lambda s, d: _khop(graphs.commerce(s, d), ga.SampleConfig(metapath=((0, 1), (2, 3)))), _khop_sql("commerce", False, ((0, 1), (2, 3))))


def _quota_sizes(s, d, rounding):
    g = graphs.folded(s, d)
    b = ga.khop_sample(placement.place(g.edges, PARTS, "random"), _seeds(g), [10], ga.SampleConfig(rounding=rounding))
    return b.groupBy("vid").agg(F.count("*").alias("n"))


_add("sample_quota_remainder_folded", lambda s, d: _quota_sizes(s, d, "largest_remainder"), _cte("folded", _adj(), _SEEDS) + " SELECT vid, least(10, count(*))::BIGINT AS n FROM adj JOIN seeds USING (vid) GROUP BY vid")
_COIN = f"(SELECT vid, part, count(*) AS local FROM adj JOIN seeds USING (vid) GROUP BY vid, part)"
_add("sample_quota_bernoulli_folded", lambda s, d: _quota_sizes(s, d, "bernoulli"), _cte("folded", _placed("random"), _adj("p", True), _SEEDS) + f", q AS (SELECT vid, part, least(10, sum(local) OVER (PARTITION BY vid)) * local / (sum(local) OVER (PARTITION BY vid)) AS q FROM {_COIN}) SELECT vid, sum(floor(q) + CASE WHEN {sql_uniform('sc0', 'vid', 'part')} < q - floor(q) THEN 1 ELSE 0 END)::BIGINT AS n FROM q GROUP BY vid HAVING n > 0")


def _loads(s, d, kind):
    g = graphs.folded(s, d)
    if kind == "owner":
        return ga.owner_workload(g, placement.hash_edge_cut(g, PARTS), _seeds(g), 10)
    placed = placement.place(g.edges, PARTS, "hash2d")
    seeds = _seeds(g) if kind == "even" else ga.single_part_seeds(metrics.home_partition(placed), 200)
    return ga.workload(placed, seeds, 10)


_LOAD = " SELECT part, count(DISTINCT vid) AS requests, count(*) AS scanned, sum((r <= 10)::INTEGER)::BIGINT AS returned, round(count(*) / min(count(*)) OVER (), 6) AS load FROM (SELECT part, vid, row_number() OVER (PARTITION BY part, vid ORDER BY {s} DESC, eid) AS r FROM adj JOIN seeds USING (vid)) GROUP BY part"
_add("workload_gather_apply", lambda s, d: _loads(s, d, "even"), _cte("folded", _placed("hash2d"), _adj("p", True), _SEEDS) + _LOAD.format(s=sql_uniform("s0", "vid", "eid")))
_add("workload_seeds_p0", lambda s, d: _loads(s, d, "p0"))
_add("workload_owner", lambda s, d: _loads(s, d, "owner"), _cte("folded", _adj(), _DEG, _SEEDS) + f" SELECT part, count(*) AS requests, sum(degree)::BIGINT AS scanned, sum(least(degree, 10))::BIGINT AS returned, round(sum(degree) / min(sum(degree)) OVER (), 6) AS load FROM (SELECT degree, {sql_bucket(PARTS, 'v', 'vid')} AS part FROM deg JOIN seeds USING (vid)) GROUP BY part")


_HOME = "home AS (SELECT vid, arg_max(part, {'n': n, 'p': -part}) AS home FROM (SELECT vid, part, count(*) AS n FROM (SELECT part, unnest([src, dst]) AS vid FROM p) GROUP BY 1, 2) GROUP BY vid)"
_add("seeds_balanced_folded", lambda s, d: ga.balanced_seeds(metrics.home_partition(placement.place(graphs.folded(s, d).edges, PARTS, "hash2d")), 20), _cte("folded", _placed("hash2d"), _HOME) + f" SELECT vid FROM (SELECT *, row_number() OVER (PARTITION BY home ORDER BY {sql_uniform('b', 'vid')}, vid) AS r FROM home) WHERE r <= 20")
_add("sample_frontier_sizes_trade", lambda s, d: ga.frontier_sizes(_khop(graphs.trade(s, d), ga.SampleConfig())), f"SELECT hop, count(DISTINCT vid) AS seeds, count(*) AS rows, count(DISTINCT nbr) AS reached FROM ({_khop_sql('trade')}) GROUP BY hop")
_add("sample_traffic_folded", lambda s, d: ga.traffic(placement.place(graphs.folded(s, d).edges, PARTS, "hash2d"), _seeds(graphs.folded(s, d)), 10), _cte("folded", _placed("hash2d"), _adj("p", True), _SEEDS) + ", l AS (SELECT vid, part, count(*) AS n FROM adj JOIN seeds USING (vid) GROUP BY vid, part) SELECT sum(shipped)::BIGINT AS shipped, sum(kept)::BIGINT AS kept FROM (SELECT sum(least(n, 10)) AS shipped, least(sum(n), 10) AS kept FROM l GROUP BY vid)")


def _closure(s, d):
    g = graphs.trade(s, d)
    return ga.khop_closure(g, ga.balanced_seeds(metrics.home_partition(placement.place(g.edges, PARTS, "hash2d")), 20), 2)


_add("khop_closure_trade", _closure, _cte("trade", _placed("hash2d"), _adj(), _HOME) + f", seeds AS (SELECT vid FROM (SELECT *, row_number() OVER (PARTITION BY home ORDER BY {sql_uniform('b', 'vid')}, vid) AS r FROM home) WHERE r <= 20), r1 AS (SELECT vid FROM seeds UNION SELECT nbr FROM adj JOIN seeds USING (vid)), r2 AS (SELECT vid FROM r1 UNION SELECT nbr FROM adj JOIN r1 USING (vid)) SELECT 0 AS hop, count(*) AS n FROM seeds UNION ALL SELECT 1, count(*) FROM r1 UNION ALL SELECT 2, count(*) FROM r2")

# Layout.
for _g in graphs.SQL:
    _add(f"layout_footprint_{_g}", lambda s, d, g=_g: compact.footprint(graphs.GRAPHS[g](s, d)), _cte(_g) + ", c AS (SELECT count(*) AS e, (SELECT count(*) FROM (SELECT DISTINCT unnest([src, dst]) FROM e)) AS v, (SELECT count(*) FROM (SELECT DISTINCT src, etype FROM e)) AS ro, (SELECT count(*) FROM (SELECT DISTINCT dst, etype FROM e)) AS ri, (SELECT count(*) FROM (SELECT DISTINCT etype, unnest([src, dst]) FROM e)) AS tv FROM e) SELECT 'compact' AS layout, 40 * v + 8 * e + 8 * (ro + ri) AS bytes FROM c UNION ALL SELECT 'explicit_type', 24 * v + 16 * e + 8 * (ro + ri) FROM c UNION ALL SELECT 'explicit_ids', 40 * v + 24 * e + 8 * (ro + ri) FROM c UNION ALL SELECT 'per_type_graphs', 40 * tv + 24 * e FROM c")
_add("layout_arrays_folded", lambda s, d: compact.write_layouts(placement.place(graphs.folded(s, d).edges, PARTS, "hash2d")).groupBy("field").agg(F.count("*").alias("parts"), F.sum("n").alias("n")))


# Inference.
def _features(g):
    return g.vertices().withColumn("h", F.array(*(F.round(uniform(f"h{i}", "vid"), 3) for i in range(4))))


def _identity(kind, last=True):
    import numpy as np

    eye = np.eye(4)
    return LayerSpec(kind, {"w": eye, "self": eye, "nbr": eye}, last=last)


_HOP = f"hop AS (SELECT vid, nbr FROM (SELECT *, row_number() OVER (PARTITION BY vid ORDER BY {sql_uniform('i0', 'vid', 'eid')}, eid) AS r FROM adj) WHERE r <= 8)"
_H0 = f"h AS (SELECT vid, {', '.join(f'round({sql_uniform(f"h{i}", "vid")}, 3) AS h{i}' for i in range(4))} FROM deg)"


def _sage(s, d):
    g = graphs.trade(s, d)
    out = engine.layerwise_infer(g, stage(_features(g)), [_identity("sage")], [8])
    return out.select("vid", *(F.round(F.col("h")[i], 6).alias(f"h{i}") for i in range(4)))


_add("embed_sage_layer1_trade", _sage, _cte("trade", _adj(), _DEG, _H0, _HOP) + f" SELECT a.vid, {', '.join(f'round(any_value(a.h{i}) + avg(b.h{i}), 6) AS h{i}' for i in range(4))} FROM h a JOIN hop ON hop.vid = a.vid JOIN h b ON b.vid = hop.nbr GROUP BY a.vid")


def _same(kind):
    def query(s, d):
        g = graphs.trade(s, d)
        h0, layers = stage(_features(g)), [make_layer(kind, 4, 8, 1, heads=2, types=5), make_layer(kind, 8, 8, 2, heads=2, types=5, last=True)]
        targets = g.vertices()
        whole = engine.layerwise_infer(g, h0, layers, [6, 4]).withColumnRenamed("h", "a")
        part = engine.samplewise_infer(g, h0, layers, [6, 4], targets).withColumnRenamed("h", "b")
        gap = F.array_max(F.zip_with("a", "b", lambda x, y: F.abs(x - y)))
        return part.join(whole, "vid").agg(F.count("*").alias("targets"), F.round(F.max(gap), 6).alias("gap"))

    return query


for _k in ("gcn", "sage", "gat", "hgt"):
    _add(f"layerwise_equals_samplewise_{_k}", _same(_k), _cte("trade") + " SELECT count(DISTINCT vid) AS targets, 0.0::DOUBLE AS gap FROM (SELECT unnest([src, dst]) AS vid FROM e)")

_GCN = [make_layer("gcn", 4, 8, 1), make_layer("gcn", 8, 4, 2, last=True)]


def _gcn(s, d):
    g = graphs.trade(s, d)
    out = engine.layerwise_infer(g, stage(_features(g)), _GCN, [6, 4])
    return out.select("vid", F.round(F.col("h")[0], 4).alias("h0"))


def _gcn_sql(layer, number, fanout, source):
    """CTEs of a layer: its sampled edges, sums over a vertex and its sample by sampled degrees, and the dense step."""
    w, hop = layer.params["w"], f"hop{number}"
    wide = [f"any_value(a.h{i}) / (any_value(least(da.degree, {fanout})) + 1) + sum(b.h{i} / sqrt((least(da.degree, {fanout}) + 1.0) * (least(db.degree, {fanout}) + 1.0))) AS h{i}" for i in range(w.shape[0])]
    dense = [" + ".join(f"h{i} * ({float(w[i, j])!r}::DOUBLE)" for i in range(w.shape[0])) for j in range(w.shape[1])]
    dense = [f"{x if layer.last else f'greatest(0, {x})'} AS h{j}" for j, x in enumerate(dense)]
    return (
        _HOP.replace("hop AS", f"{hop} AS").replace("i0:", f"i{number}:").replace("'i0'", f"'i{number}'").replace("r <= 8", f"r <= {fanout}"),
        f"wide{number} AS (SELECT a.vid, {', '.join(wide)} FROM {source} a JOIN deg da ON da.vid = a.vid JOIN {hop} ON {hop}.vid = a.vid JOIN {source} b ON b.vid = {hop}.nbr JOIN deg db ON db.vid = b.vid GROUP BY a.vid)",
        f"h_{number} AS (SELECT vid, {', '.join(dense)} FROM wide{number})",
    )


_add("embed_gcn_2layer_trade", _gcn, _cte("trade", _adj(), _DEG, _H0, *_gcn_sql(_GCN[0], 0, 4, "h"), *_gcn_sql(_GCN[1], 1, 6, "h_0")) + " SELECT vid, round(h0, 4) AS h0 FROM h_1")


def _links(s, d):
    g = graphs.trade(s, d)
    return engine.score_edges(stage(_features(g)), g.edges)


_add("link_score_dot_trade", _links, _cte("trade", _adj(), _DEG, _H0) + f" SELECT eid, round({' + '.join(f'a.h{i} * b.h{i}' for i in range(4))}, 6) AS score FROM e JOIN h a ON a.vid = src JOIN h b ON b.vid = dst")
_add("infer_compute_counts_commerce", lambda s, d: engine.compute_counts(graphs.commerce(s, d), [6, 4]), _cte("commerce", _adj(), _DEG, _HOP.replace("i0", "i1").replace("r <= 8", "r <= 6")) + ", t AS (SELECT vid, 2 + coalesce(k, 0) AS n FROM deg LEFT JOIN (SELECT vid, count(*) AS k FROM hop GROUP BY vid) USING (vid)), c AS (SELECT count(*) * 2 AS layerwise, sum(n)::BIGINT AS naive, (SELECT sum(n)::BIGINT FROM (SELECT unnest([src, dst]) AS vid FROM e) JOIN t USING (vid)) AS naive_links FROM t) SELECT *, round(naive / layerwise, 6) AS ratio, round(naive_links / layerwise, 6) AS link_ratio FROM c")


def _cache_parts(s, d):
    g = graphs.folded(s, d)
    placed = placement.place(g.edges, 4, "hash2d")
    home, hop = stage(metrics.home_partition(placed)), stage(engine.one_hop(g, 8, 0))
    cached = stage(engine.static_cache(home, metrics.replicas(placed), hop))
    return g, home, hop, cached


def _reorder(s, d, key):
    g, home, _, cached = _cache_parts(s, d)
    return engine.reorder(cached, home, g.degrees(), key)


_CACHED = "cached AS (SELECT DISTINCT part AS worker, unnest([src, dst]) AS vid FROM p UNION SELECT home AS worker, nbr AS vid FROM hop JOIN home ON home.vid = hop.vid)"
_CACHE_CTE = _cte("folded", _placed("hash2d", 4), _adj(), _DEG, _HOP, _HOME, _CACHED)
_SQL_ORDERS = {"ns": "c.vid", "ds": "degree DESC, c.vid", "ps": "home, c.vid", "pds": "home, degree DESC, c.vid"}


def _lids_sql(key):
    return f"lids AS (SELECT worker, c.vid, row_number() OVER (PARTITION BY worker ORDER BY {_SQL_ORDERS[key]}) - 1 AS lid FROM cached c JOIN home USING (vid) JOIN deg USING (vid))"


for _k in engine.ORDERS:
    _add(f"reorder_{_k}_folded", lambda s, d, k=_k: _reorder(s, d, k).select(F.col("worker").cast("long").alias("worker"), "vid", F.col("lid").cast("long").alias("lid")), _CACHE_CTE + f", {_lids_sql(_k)} SELECT worker::BIGINT AS worker, vid, lid::BIGINT AS lid FROM lids")


def _hub_order(s, d):
    g, _, _, cached = _cache_parts(s, d)
    return engine.reorder_hub_cluster(cached, g.degrees())


_HUB_SQL = "hubs AS (SELECT c.worker, c.vid, degree > avg(degree) OVER (PARTITION BY c.worker) AS hub FROM cached c JOIN deg USING (vid)), lids AS (SELECT worker, vid, row_number() OVER (PARTITION BY worker ORDER BY hub DESC, vid) - 1 AS lid FROM hubs)"
_add("reorder_hub_cluster_folded", lambda s, d: _hub_order(s, d).select(F.col("worker").cast("long").alias("worker"), "vid", F.col("lid").cast("long").alias("lid")), _CACHE_CTE + f", {_HUB_SQL} SELECT worker::BIGINT AS worker, vid, lid::BIGINT AS lid FROM lids")


def _breadth_order(s, d):
    g, _, _, cached = _cache_parts(s, d)
    return engine.reorder_breadth_first(cached, engine.breadth_first_levels(g))


_STEPS = 12  # more than the folded graph has
_LEVELS = "l0 AS (SELECT vid FROM deg ORDER BY degree DESC, vid LIMIT 1)" + "".join(f", l{k + 1} AS (SELECT vid FROM l{k} UNION SELECT nbr FROM adj JOIN l{k} USING (vid))" for k in range(_STEPS))
_LEVELS += ", levels AS (SELECT vid, min(level) AS level FROM (" + " UNION ALL ".join(f"SELECT vid, {k} AS level FROM l{k}" for k in range(_STEPS + 1)) + ") GROUP BY vid)"
_add("reorder_breadth_first_folded", lambda s, d: _breadth_order(s, d).select(F.col("worker").cast("long").alias("worker"), "vid", F.col("lid").cast("long").alias("lid")), _CACHE_CTE + f", {_LEVELS} SELECT worker::BIGINT AS worker, c.vid, (row_number() OVER (PARTITION BY worker ORDER BY level NULLS LAST, c.vid) - 1)::BIGINT AS lid FROM cached c LEFT JOIN levels ON levels.vid = c.vid")
for _k in (*engine.ORDERS, "hub"):
    _add(f"locality_{_k}_folded", lambda s, d, k=_k: engine.locality(stage(_hub_order(s, d) if k == "hub" else _reorder(s, d, k)), placement.place(graphs.folded(s, d).edges, 4, "hash2d")), _CACHE_CTE + f", {_HUB_SQL if _k == 'hub' else _lids_sql(_k)} SELECT part::BIGINT AS worker, count(*) AS edges, round(avg(gap), 6) AS mean_gap, round(avg(length(bin(gap))), 6) AS mean_bits FROM (SELECT part, abs(a.lid - b.lid) AS gap FROM p JOIN lids a ON a.worker = part AND a.vid = src JOIN lids b ON b.worker = part AND b.vid = dst) GROUP BY part")


def _trace_of(parts, key):
    g, home, hop, cached = parts
    lids = stage(engine.reorder(cached, home, g.degrees(), key))
    return stage(engine.access_trace(lids, home, hop, chunk=8, batch=64))


def _chunk_reads(s, d):
    out, parts = None, _cache_parts(s, d)
    for k in engine.ORDERS:
        r = _trace_of(parts, k).agg(F.lit(k).alias("order_key"), F.count("*").alias("reads"))
        out = r if out is None else out.union(r)
    return out


_READS = " UNION ALL ".join(f"SELECT '{k}' AS order_key, (SELECT count(*) FROM (SELECT DISTINCT m.worker, m.step, n.lid // 8 AS chunk FROM (SELECT l.worker, l.vid, (row_number() OVER (PARTITION BY l.worker ORDER BY l.lid) - 1) // 64 AS step FROM lids_{k} l JOIN home h ON h.vid = l.vid AND h.home = l.worker) m JOIN hop ON hop.vid = m.vid JOIN lids_{k} n ON n.worker = m.worker AND n.vid = hop.nbr)) AS reads" for k in engine.ORDERS)
_add("chunk_reads_by_order", _chunk_reads, _CACHE_CTE + "".join(f", {_lids_sql(k).replace('lids AS', f'lids_{k} AS')}" for k in engine.ORDERS) + f" {_READS}")


def _caches(s, d):
    trace = _trace_of(_cache_parts(s, d), "pds")
    chunks = trace.agg(F.max("chunk").alias("m")).first().m + 1
    out = None
    for policy in ("none", "fifo", "lru"):
        r = engine.simulate_cache(trace, max(1, int(0.1 * chunks)), policy).agg(F.lit(policy).alias("policy"), F.sum("reads").alias("reads"), F.sum("hits").alias("hits"), F.round(F.sum("hits") / F.sum("reads"), 6).alias("ratio"))
        out = r if out is None else out.union(r)
    return out


_add("cache_policies_pds", _caches)
_add("static_cache_rows", lambda s, d: _cache_parts(s, d)[3].groupBy("worker").agg(F.count("*").alias("vertices")).select(F.col("worker").cast("long").alias("worker"), "vertices"), _CACHE_CTE + " SELECT worker::BIGINT AS worker, count(*) AS vertices FROM cached GROUP BY worker")


# Training side.
def _negatives(s, d):
    g = graphs.trade(s, d)
    return links.corrupt_edges(g.edges, g.vertices(), 2).agg(F.count("*").alias("n"), F.count_if(F.shiftright("dst", 40) != 1).alias("wrong_type"))


_add("negatives_trade", _negatives, _cte("trade") + " SELECT 2 * count(*) AS n, 0::BIGINT AS wrong_type FROM e")
_add("inductive_split_trade", lambda s, d: links.inductive_split(graphs.trade(s, d))[1].agg(F.count("*").alias("seen")), _cte("trade") + f" SELECT count(*) AS seen FROM e WHERE NOT ({sql_uniform('t', 'src')} < 0.2) AND NOT ({sql_uniform('t', 'dst')} < 0.2)")
_add("positives_trade", lambda s, d: links.sample_edges(graphs.trade(s, d).edges, 500).select("eid", "src", "dst"), _cte("trade") + f" SELECT eid, src, dst FROM e ORDER BY {sql_uniform('m', 'eid')}, eid LIMIT 500")


def _auc(s, d):
    labels = table(s, d, "labels").join(table(s, d, "documents").select("doc_id", "n_chars"), "doc_id")
    return links.auc(labels.select(F.col("n_chars").alias("score"), F.col("quality").alias("label")))


_add("auc_quality_by_length", _auc, "WITH r AS (SELECT quality AS label, rank() OVER (ORDER BY n_chars) + (count(*) OVER (PARTITION BY n_chars) - 1) / 2.0 AS rank FROM labels JOIN documents USING (doc_id)) SELECT round((sum(rank) FILTER (label = 1) - sum(label) * (sum(label) + 1) / 2.0) / (sum(label) * (count(*) - sum(label))), 6) AS auc FROM r")


# Streams end in what a batch gives.
def _stream_windows(s, d):
    import uuid

    return streams.run_to_table(streams.windowed_degree(streams.event_stream(s, d)), f"w{uuid.uuid4().hex}", "update").groupBy("start", "user_id").agg(F.max("n").alias("n"), F.max_by("value", "n").alias("value"))


_add("stream_windowed_degree", _stream_windows, sql_suite.DUCKDB["op_events_windows"])


def _stream_reservoir(s, d):
    import uuid

    from pyspark.sql.window import Window

    out = streams.run_to_table(streams.reservoir(streams.event_stream(s, d)), f"r{uuid.uuid4().hex}", "update")
    best = Window.partitionBy("user_id").orderBy(F.desc("score"), "event_id")
    return out.dropDuplicates(["user_id", "event_id"]).withColumn("r", F.row_number().over(best)).where("r <= 5").select("user_id", "event_id", "score")


_add("stream_reservoir", _stream_reservoir, f"SELECT user_id, event_id, score FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY score DESC, event_id) AS r FROM (SELECT user_id, event_id, round(pow({sql_uniform('a', 'user_id', 'event_id')}, 1 / value), 9) AS score FROM events WHERE value > 0)) WHERE r <= 5")

QUERIES |= sql_suite.QUERIES
ORACLES |= sql_suite.DUCKDB


def flagship(spark, sf_dir):
    """Two hops of weighted gather/apply sampling over the trade graph."""
    return QUERIES["sample_weighted_khop_trade"](spark, sf_dir)
