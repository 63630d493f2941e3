"""More registered queries: samplers by type and time, seeds and batches, stores, decoders, training, streams."""

from __future__ import annotations

import time
import uuid

import numpy as np
from pyspark.sql import functions as F

from hubgraph.core.portable import sql_bits, sql_bucket, sql_uniform, uniform
from hubgraph.infer import engine
from hubgraph.infer.store import EmbeddingStore, MlpDecoder, fill_static_cache, load_partition, save_partitions
from hubgraph.partition import metrics, placement
from hubgraph.queries import _CACHE_CTE, _DEG, _H0, _HOME, _HOP, _LOAD, _SEEDS, PARTS, _adj, _cache_parts, _cte, _features, _hop_sql, _lids_sql, _placed, _reorder, _seeds
from hubgraph.sample import gather_apply as ga
from hubgraph.session import shared_dir, stage, table
from hubgraph.sources import graphs
from hubgraph.streaming import events as streams
from hubgraph.train import blocks, links

QUERIES, ORACLES = {}, {}


def _add(name, query, sql=None):
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def _temporary(spark):
    return f"{shared_dir(spark)}/hubgraph-{uuid.uuid4().hex}"


# Samplers: directions, fanouts by type, edges as of a time, owners; seeds and batches.
def _directed(g, direction):
    return lambda s, d: ga.khop_sample(placement.place(graphs.GRAPHS[g](s, d).edges, PARTS, "hash2d"), _seeds(graphs.GRAPHS[g](s, d)), [10], ga.SampleConfig(direction=direction))


for _d, _a, _b in (("out", "src", "dst"), ("in", "dst", "src")):
    for _g in ("folded", "commerce"):
        _add(f"sample_{_d}_{_g}", _directed(_g, _d), _cte(_g, f"adj AS (SELECT {_a} AS vid, {_b} AS nbr, eid, etype, weight FROM e)", _SEEDS, _hop_sql(0, 10, "seeds", False)) + " SELECT * FROM hop0")

BY_TYPE = {0: 3, 1: 5, 2: 2, 3: 1}
_add(
    "sample_typed_fanout_commerce",
    lambda s, d: ga.typed_fanout_sample(placement.place(graphs.commerce(s, d).edges, PARTS, "hash2d"), _seeds(graphs.commerce(s, d)), BY_TYPE),
    _cte("commerce", _adj(), _SEEDS)
    + f" SELECT vid, nbr, eid, etype, score FROM (SELECT *, row_number() OVER (PARTITION BY vid, etype ORDER BY score DESC, eid) AS r FROM (SELECT vid, nbr, eid, etype, {sql_uniform('s0', 'vid', 'eid')} AS score FROM adj JOIN seeds USING (vid))) WHERE r <= CASE etype {' '.join(f'WHEN {k} THEN {v}' for k, v in BY_TYPE.items())} ELSE 0 END",
)


def _as_of(s, d):
    edges = graphs.activity(s, d).edges
    seeds = edges.groupBy(F.col("src").alias("vid")).agg((F.max("ts") - F.expr("INTERVAL 10 DAYS")).alias("at"))
    return ga.as_of_sample(edges, seeds, 5, ga.SampleConfig(direction="out")).select("vid", "eid", "score")


_add("sample_as_of_activity", _as_of, f"SELECT vid, eid, score FROM (SELECT *, row_number() OVER (PARTITION BY vid ORDER BY score DESC, eid) AS r FROM (SELECT user_id AS vid, event_id AS eid, {sql_uniform('s0', 'user_id', 'event_id')} AS score, ts, max(ts) OVER (PARTITION BY user_id) - INTERVAL 10 DAYS AS until FROM events) WHERE ts <= until) WHERE r <= 5")


def _owner(s, d):
    g = graphs.folded(s, d)
    return ga.owner_sample(g, placement.hash_edge_cut(g, PARTS), _seeds(g), 10)


_add("sample_owner_folded", _owner, _cte("folded", _adj(), _SEEDS, _hop_sql(0, 10, "seeds", False)) + f" SELECT {sql_bucket(PARTS, 'v', 'vid')} AS part, vid, nbr, eid, etype, score FROM hop0")
_M = f"m AS (SELECT src, dst FROM e ORDER BY {sql_uniform('m', 'eid')}, eid LIMIT 500)"
_add("edge_seeds_trade", lambda s, d: blocks.edge_seeds(links.sample_edges(graphs.trade(s, d).edges, 500)), _cte("trade", _M) + " SELECT DISTINCT unnest([src, dst]) AS vid FROM m")
_add("batches_trade", lambda s, d: blocks.assign_batches(graphs.trade(s, d).vertices(), 64).groupBy("batch").agg(F.count("*").alias("n"), F.min("vid").alias("low")), _cte("trade") + f", v AS (SELECT DISTINCT unnest([src, dst]) AS vid FROM e) SELECT ({sql_bits('q', 'vid')} % ((SELECT count(*) FROM v) + 63) // 64)::INTEGER AS batch, count(*) AS n, min(vid) AS low FROM v GROUP BY 1".replace("% ((SELECT count(*) FROM v) + 63) // 64)", "% (((SELECT count(*) FROM v) + 63) // 64))"))
_add("workload_seeds_part0", lambda s, d: ga.workload(placement.place(graphs.folded(s, d).edges, PARTS, "hash2d"), ga.single_part_seeds(metrics.home_partition(placement.place(graphs.folded(s, d).edges, PARTS, "hash2d")), 200), 10), _cte("folded", _placed("hash2d"), _adj("p", True), _HOME, f"seeds AS (SELECT vid FROM home WHERE home = 0 ORDER BY {sql_uniform('b', 'vid')}, vid LIMIT 200)") + _LOAD.format(s=sql_uniform("s0", "vid", "eid")))
_add("khop_closure_seeds_trade", lambda s, d: ga.khop_closure(graphs.trade(s, d), _seeds(graphs.trade(s, d)), 2), _cte("trade", _adj(), _SEEDS) + ", r1 AS (SELECT vid FROM seeds UNION SELECT nbr FROM adj JOIN seeds USING (vid)), r2 AS (SELECT vid FROM r1 UNION SELECT nbr FROM adj JOIN r1 USING (vid)) SELECT 0 AS hop, count(*) AS n FROM seeds UNION ALL SELECT 1, count(*) FROM r1 UNION ALL SELECT 2, count(*) FROM r2")
_add("global_degrees_commerce", lambda s, d: graphs.commerce(s, d).degrees("out").withColumnRenamed("degree", "out_degree").join(graphs.commerce(s, d).degrees("in").withColumnRenamed("degree", "in_degree"), "vid", "full").na.fill(0), _cte("commerce") + " SELECT vid, count(*) FILTER (o) AS out_degree, count(*) FILTER (NOT o) AS in_degree FROM (SELECT src AS vid, true AS o FROM e UNION ALL SELECT dst, false FROM e) GROUP BY vid")


# Written and read back.
def _saved(s, d):
    path = _temporary(s)
    save_partitions(placement.place(graphs.folded(s, d).edges, PARTS, "hash2d").select("eid", "src", "dst", "etype", "part"), path)
    return load_partition(s, path, 3).select("eid", "src", "dst", "etype")


_add("part_saved_and_loaded_folded", _saved, _cte("folded", _placed("hash2d")) + " SELECT eid, src, dst, etype FROM p WHERE part = 3")


def _format(name):
    def query(s, d):
        edges, path = graphs.trade(s, d).edges.select("src", "dst", "etype"), _temporary(s)
        if name == "text":
            edges.select(F.concat_ws("\t", "src", "dst", "etype").alias("value")).write.text(path)
            cut = F.split("value", "\t")
            return s.read.text(path).select(cut[0].cast("long").alias("src"), cut[1].cast("long").alias("dst"), cut[2].cast("int").alias("etype"))
        edges.write.format(name).save(path)
        return s.read.format(name).schema("src long, dst long, etype int").load(path)

    return query


for _n in ("csv", "json", "orc", "text"):
    _add(f"op_edges_through_{_n}", _format(_n), _cte("trade") + " SELECT src, dst, etype FROM e")


def _bucketed(s, d):
    name = f"hubgraph_{uuid.uuid4().hex}"
    graphs.trade(s, d).edges.select("eid", "src", "dst").write.bucketBy(8, "src").sortBy("src").option("path", _temporary(s)).saveAsTable(name)
    return s.table(name).groupBy("src").agg(F.count("*").alias("n"))


_add("op_bucketed_table", _bucketed, _cte("trade") + " SELECT src, count(*) AS n FROM e GROUP BY src")


def _generated_hubs(s, d):
    keys = table(s, d, "orders").select(F.col("o_orderkey").cast("decimal(12,0)").alias("id"))
    return keys.crossJoin(keys.agg(F.count("*").cast("decimal(12,0)").alias("n"))).select(F.expr("(id * id * id) div (n * n)").alias("src")).groupBy("src").agg(F.count("*").alias("n"))


_add("op_generated_hubs", _generated_hubs, "SELECT (o_orderkey::HUGEINT * o_orderkey * o_orderkey // (o.n * o.n))::BIGINT AS src, count(*) AS n FROM orders, (SELECT count(*)::HUGEINT AS n FROM orders) o GROUP BY 1")


def _store(s, d):
    g, _, _, _ = _cache_parts(s, d)
    store = EmbeddingStore(s, _temporary(s))
    store.write(0, fill_static_cache(_reorder(s, d, "pds"), _features(g), 64))
    return store.read(0, 1, [0, 2]).select(F.col("worker").cast("long").alias("worker"), "chunk", F.col("lid").cast("long").alias("lid"), "vid", F.col("h")[0].alias("h0"))


_add("embedding_store_chunks_folded", _store, _CACHE_CTE + f", {_lids_sql('pds')}, {_H0} SELECT worker::BIGINT AS worker, lid // 64 AS chunk, lid::BIGINT AS lid, l.vid, h0 FROM lids l JOIN h ON h.vid = l.vid WHERE worker = 1 AND lid // 64 IN (0, 2)")


def _hit_ratio(s, d):
    _, home, hop, cached = _cache_parts(s, d)
    reads = hop.join(home, "vid").select(F.col("home").alias("worker"), F.col("nbr").alias("vid"))
    held = cached.select("worker", "vid", F.lit(1).alias("hit"))
    own = cached.groupBy("worker").agg(F.count_if("remote").alias("remote"))
    got = reads.join(held, ["worker", "vid"], "left").groupBy("worker").agg(F.count("*").alias("reads"), F.count("hit").alias("hits"))
    return got.join(own, "worker").select(F.col("worker").cast("long").alias("worker"), "reads", "hits", "remote")


_add("static_cache_report_folded", _hit_ratio, _CACHE_CTE + ", own AS (SELECT DISTINCT part AS worker, unnest([src, dst]) AS vid FROM p), r AS (SELECT home AS worker, count(*) AS reads FROM hop JOIN home ON home.vid = hop.vid GROUP BY home), x AS (SELECT worker, count(*) AS remote FROM cached ANTI JOIN own USING (worker, vid) GROUP BY worker) SELECT worker::BIGINT AS worker, reads, reads AS hits, coalesce(remote, 0) AS remote FROM r LEFT JOIN x USING (worker)")

# Decoders and messages with edge features.
_W1 = np.array([[((i + 2 * j) % 5 - 2) / 4 for j in range(3)] for i in range(8)])
_W2 = np.array([[1.0], [-0.5], [0.25]])


def _mlp(s, d):
    g = graphs.trade(s, d)
    return MlpDecoder(_W1, _W2).score(stage(_features(g)), g.edges).select("eid", F.round("score", 8).alias("score"))


_ENDS = [f"{t}.h{i}" for t in "ab" for i in range(4)]
_add("link_score_mlp_trade", _mlp, _cte("trade", _adj(), _DEG, _H0) + f" SELECT eid, round({' + '.join(f'{_W2[j, 0]} * greatest(0, ' + ' + '.join(f'{_W1[i, j]} * {x}' for i, x in enumerate(_ENDS)) + ')' for j in range(3))}, 8) AS score FROM e JOIN h a ON a.vid = src JOIN h b ON b.vid = dst")


def _edge_message(s, d):
    g = graphs.trade(s, d)
    h = stage(_features(g))
    hop = engine.one_hop(g, 8, 0, columns=("weight",))
    message = hop.join(h.select(F.col("vid").alias("nbr"), F.col("h").alias("hn")), "nbr").groupBy("vid").agg(*(F.avg(F.col("weight") * F.col("hn")[i]).alias(f"m{i}") for i in range(4)))
    return message.join(h, "vid").select("vid", *(F.round(F.col("h")[i] + F.col(f"m{i}"), 8).alias(f"h{i}") for i in range(4)))


_WHOP = _HOP.replace("SELECT vid, nbr FROM", "SELECT vid, nbr, weight FROM")
_add("embed_edge_weight_trade", _edge_message, _cte("trade", _adj(), _DEG, _H0, _WHOP) + f" SELECT a.vid, {', '.join(f'round(any_value(a.h{i}) + avg(hop.weight * b.h{i}), 8) AS h{i}' for i in range(4))} FROM h a JOIN hop ON hop.vid = a.vid JOIN h b ON b.vid = hop.nbr GROUP BY a.vid")


# Training: documents by language from hashed token counts over the lexicon graph, and links over the commerce graph.
def _lexicon_task(s, d, width=64):
    g = graphs.lexicon(s, d)
    adjacency = stage(g.adjacency().select("vid", "nbr", "eid"))
    # Of the token, whichever end it is.
    counts = adjacency.select("vid", F.pmod(F.xxhash64(F.greatest("vid", "nbr")), F.lit(width)).alias("k")).groupBy("vid", "k").agg(F.count("*").alias("n"))
    held = counts.groupBy("vid").agg(F.map_from_entries(F.collect_list(F.struct("k", "n"))).alias("m"), F.sqrt(F.sum(F.col("n") * F.col("n"))).alias("norm"))
    features = stage(held.select("vid", F.array(*(F.coalesce(F.col("m")[F.lit(i).cast("long")], F.lit(0)) / F.col("norm") for i in range(width))).alias("h")))
    langs = table(s, d, "documents").where("lang is not null").select("doc_id", "lang")
    names = langs.select("lang").distinct().orderBy("lang")
    index = s.createDataFrame([(r.lang, k) for k, r in enumerate(names.collect())], "lang string, label int")
    labelled = langs.join(F.broadcast(index), "lang").select(F.col("doc_id").alias("vid"), "label").join(adjacency.select("vid").distinct(), "vid", "left_semi")
    return adjacency, features, stage(labelled.withColumn("test", uniform("t", "vid") < 0.2)), index.count()


def _accuracy(s, d):
    adjacency, features, labelled, classes = _lexicon_task(s, d)
    out = None
    for kind in ("sage", "gcn"):
        trained = blocks.train_vertices(adjacency, features, labelled.where("not test").select("vid", "label"), classes, kind=kind)
        for name, fanouts in (("sampled", (8, 4)), ("all", (None, 4))):
            got = blocks.predict_vertices(adjacency, features, labelled.where("test"), trained, kind=kind, fanouts=fanouts).join(labelled, "vid")
            row = got.groupBy("label").agg(F.avg((F.col("label") == F.col("predicted")).cast("double")).alias("a"), F.count("*").alias("n"))
            row = row.agg(F.lit(kind).alias("model"), F.lit(name).alias("neighbours"), F.round(F.avg("a"), 4).alias("macro_accuracy"), F.sum("n").alias("n"), F.lit(round(trained.losses[0], 4)).alias("first_loss"), F.lit(round(trained.losses[-1], 4)).alias("last_loss"), F.lit(round(sum(trained.seconds), 2)).alias("seconds"))
            out = row if out is None else out.union(row)
    return out


_add("train_accuracy_lexicon", _accuracy)


def _link_training(s, d):
    g = graphs.trade(s, d)
    adjacency, features = stage(g.adjacency().select("vid", "nbr", "eid")), stage(_features(g))
    positives = stage(links.sample_edges(g.edges, 1000).select("eid", "src", "dst", "etype"))
    negatives = stage(links.corrupt_edges(positives, g.vertices(), 1))
    rows = []
    for trainers in (1, 2, 4):
        t = blocks.train_links(adjacency, features, positives, negatives, trainers=trainers, epochs=2)
        rows += [(trainers, k, float(loss), sum(t.seconds)) for k, loss in enumerate(t.losses)]
    return s.createDataFrame(rows, "trainers int, step int, loss double, seconds double")


_add("train_links_trade", _link_training)


# Measures by the clock: they differ from run to run, so no SQL stands beside them.
def _timed(action):
    begin = time.time()
    action()
    return round(time.time() - begin, 3)


def _noop(df):
    df.write.format("noop").mode("overwrite").save()


def _partition_seconds(s, d):
    g = graphs.folded(s, d)
    rows = [(k, _timed(lambda k=k: _noop(placement.place(g.edges, PARTS, k)))) for k in ("random", "hash1d", "hash2d")]
    return s.createDataFrame(rows, "algo string, seconds double")


def _sampling_rate(s, d):
    g = graphs.folded(s, d)
    placed, owner = stage(placement.place(g.edges, PARTS, "hash2d")), stage(placement.hash_edge_cut(g, PARTS))
    rows = []
    for clients in (1, 2, 4):
        seeds = stage(_seeds(g, 200 * clients))
        n = seeds.count()
        for name, run in (("gather_apply", lambda seeds=seeds: _noop(ga.khop_sample(placed, seeds, [10]))), ("owner", lambda seeds=seeds: _noop(ga.owner_sample(g, owner, seeds, 10)))):
            rows.append((name, clients, n / max(_timed(run), 1e-3)))
    return s.createDataFrame(rows, "sampler string, clients int, subgraphs_per_second double")


def _phase_times(s, d):
    g, home, hop, cached = _cache_parts(s, d)
    h, lids = stage(_features(g)), stage(engine.reorder(cached, home, g.degrees(), "pds"))
    fill = _timed(lambda: _noop(fill_static_cache(lids, h)))
    from hubgraph.infer.layers import make_layer

    layers = [make_layer("sage", 4, 8, 1), make_layer("sage", 8, 8, 2, last=True)]
    whole = _timed(lambda: _noop(engine.layerwise_infer(g, h, layers, [6, 4])))
    naive = _timed(lambda: _noop(engine.samplewise_infer(g, h, layers, [6, 4], g.vertices())))
    return s.createDataFrame([("fill", fill), ("layerwise", whole), ("samplewise", naive)], "phase string, seconds double")


_add("seconds_of_partitioning_folded", _partition_seconds)
_add("sampling_rate_folded", _sampling_rate)
_add("phase_seconds_folded", _phase_times)


# Streams end in what a batch gives.
def _table(stream, mode):
    return streams.run_to_table(stream, f"t{uuid.uuid4().hex}", mode)


def _sliding(s, d):
    out = streams.event_stream(s, d).groupBy(F.window("ts", "1 day", "12 hours"), "event_type").agg(F.count("*").alias("n"))
    return _table(out.select(F.col("window.start").alias("start"), "event_type", "n"), "update").groupBy("start", "event_type").agg(F.max("n").alias("n"))


_add("stream_sliding_degree", _sliding, "SELECT start, event_type, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 12 HOURS, ts), time_bucket(INTERVAL 12 HOURS, ts) - INTERVAL 12 HOURS]) AS start, event_type FROM events) GROUP BY 1, 2")


def _sessions(s, d):
    batch = table(s, d, "events").groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count("*").alias("n"))
    return batch.select("user_id", F.col("session_window.start").alias("start"), "n")


_add("batch_session_degree", _sessions, "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(gap) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM (SELECT user_id, ts, event_id, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOURS THEN 1 ELSE 0 END AS gap FROM events)) GROUP BY user_id, k")
_add("stream_deduplicated", lambda s, d: _table(streams.deduplicated(streams.event_stream(s, d).withColumn("again", F.explode(F.array(F.lit(1), F.lit(2))))).select("event_id", "user_id"), "append"), "SELECT event_id, user_id FROM events")
_add("stream_static_join", lambda s, d: _table(streams.event_stream(s, d).join(table(s, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id").select("event_id", "c_mktsegment"), "append"), "SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id")


def _click_to_purchase(s, d):
    side = lambda kind, p: streams.event_stream(s, d).where(F.col("event_type") == kind).select(F.col("event_id").alias(f"{p}_id"), F.col("user_id").alias(f"{p}_user"), F.col("ts").alias(f"{p}_ts"))
    near = (F.col("c_user") == F.col("p_user")) & (F.col("p_ts") >= F.col("c_ts")) & (F.col("p_ts") <= F.col("c_ts") + F.expr("INTERVAL 6 HOURS"))
    return _table(side("click", "c").join(side("purchase", "p"), near).select("c_id", "p_id"), "append")


_add("stream_click_to_purchase", _click_to_purchase, "SELECT c.event_id AS c_id, p.event_id AS p_id FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 6 HOURS")


def _placed_stream(s, d):
    return _table(placement.place(streams.event_stream(s, d).select(F.col("event_id").alias("eid"), F.col("user_id").alias("src"), (F.lit(graphs.TYPE) + F.get_json_object("props", "$.k").cast("long")).alias("dst")), PARTS, "hash2d").select("eid", "part"), "append")


_add("stream_placed_hash2d", _placed_stream, f"SELECT eid, {placement.sql_place(PARTS, 'hash2d')}::INTEGER AS part FROM (SELECT event_id AS eid, user_id AS src, {graphs.TYPE} + CAST(json_extract(props, '$.k') AS BIGINT) AS dst FROM events)")
