import math
import random

import numpy as np
import pytest

from hubgraph.core.model import PropertyGraph
from hubgraph.layout.compact import build_layout
from hubgraph.partition import expansion, metrics
from hubgraph.sample import gather_apply as ga
from hubgraph.sample.draws import alias_draw, build_alias, skip_positions

EDGES = "eid long, src long, dst long, etype int, weight double"


def star(spark, leaves=12):
    return PropertyGraph("star", spark.createDataFrame([(i, 0, i + 1, i % 3, 1.0) for i in range(leaves)], EDGES))


def test_steering_keeps_the_geometric_mean():
    nv, ne, speed = [5, 1, 2], [9, 3, 0], [0.1] * 3
    vs, es = expansion.share_score(nv), expansion.share_score(ne)
    out = [expansion.next_lambda(s, v, e, 1, 1) for s, v, e in zip(speed, vs, es, strict=True)]
    assert sum(map(math.log, out)) == pytest.approx(3 * math.log(0.1))
    assert expansion.next_lambda(0.1, 1, 1, 1, 1) == pytest.approx(0.1)
    assert expansion.share_score([0, 0]) == [1.0, 1.0]
    assert expansion.quota(0.1, 5) == 1 and expansion.quota(5.0, 5) == 5


def test_every_edge_gets_one_part(spark):
    rows = [(i, i % 7, 100 + i % 11, 0, 1.0) for i in range(60)] + [(100, 900, 901, 0, 1.0)]
    g = PropertyGraph("g", spark.createDataFrame(rows, EDGES))
    for steer in (True, False):
        e = expansion.expand(g, 3, steer=steer, lambda0=0.3, max_rounds=3).edges.toPandas()
        assert sorted(e.eid) == sorted(r[0] for r in rows) and e.part.between(0, 2).all()


@pytest.mark.parametrize("start", ["vertices", "grid"])
def test_rounds_in_one_task_equal_distributed_rounds(spark, start):
    r = random.Random(3)
    rows = [(i, int(40 * r.random() ** 2), 100 + int(30 * r.random() ** 2), 0, 1.0) for i in range(400)] + [(1000, 900, 901, 0, 1.0)]
    g = PropertyGraph("g", spark.createDataFrame(rows, EDGES))
    a, b = (expansion.bse_partition(g, 3, lambda0=0.3, max_rounds=2, round_share=0.2, start=start, local_limit=limit) for limit in (10_000, 0))
    assert a.trace == b.trace
    assert sorted(map(tuple, a.edges.collect())) == sorted(map(tuple, b.edges.collect()))


def test_expansion_of_an_empty_graph_and_of_fewer_vertices_than_parts(spark):
    assert expansion.bse_partition(PropertyGraph("g", spark.createDataFrame([], EDGES)), 3).edges.count() == 0
    loop = expansion.bse_partition(PropertyGraph("g", spark.createDataFrame([(7, 5, 5, 0, 1.0)], EDGES)), 3).edges.collect()
    assert len(loop) == 1 and 0 <= loop[0].part < 3


def test_steering_balances_vertices_of_a_power_law_graph(spark):
    from hubgraph.sources.graphs import lexicon

    g = lexicon(spark, "/root/testdata/sf0.01")
    steered, plain = (metrics.partition_report(f(g, 8).edges, 8).first() for f in (expansion.bse_partition, expansion.tse_partition))
    assert steered.vb < plain.vb


def test_parts_begin_in_their_own_slot_of_the_grid(spark):
    from hubgraph.partition.placement import place

    rows = [(i, i % 13, 100 + i % 17, 0, 1.0) for i in range(200)]
    g = PropertyGraph("g", spark.createDataFrame(rows, EDGES))
    ends = {(p, v) for r in place(g.edges, 4, "hash2d").collect() for p, v in ((r.part, r.src), (r.part, r.dst))}
    begin = expansion.start_vertices(g.edges, None, 4, "grid", "s")
    assert [p for _, p in sorted(begin, key=lambda x: x[1])] == [0, 1, 2, 3] and all((p, v) in ends for v, p in begin)
    other = [expansion.bse_partition(g, 4, start=start).edges.count() for start in ("grid", "vertices")]
    assert other == [200, 200]


@pytest.mark.parametrize("limit", [10_000, 0])
def test_balance_study_measures_what_the_partitioner_makes(spark, limit):
    r = random.Random(5)
    rows = [(i, int(20 * r.random() ** 2), 100 + int(15 * r.random() ** 2), 0, 1.0) for i in range(60)]
    g = PropertyGraph("g", spark.createDataFrame(rows, EDGES))
    starts = ("grid", "vertices") if limit else ("grid",)  # the distributed rounds are slow
    study = expansion.balance_study(g, 2, orders=1, shares=(None,), starts=starts, local_limit=limit).collect()
    assert sorted((x.start, x.steered) for x in study) == [(x, y) for x in starts for y in (False, True)]
    for x in study:
        made = expansion.expand(g, 2, steer=x.steered, round_share=None, start=x.start, salt="s0")
        want = metrics.partition_report(made.edges, 2).first()
        assert (round(x.rf, 6), round(x.vb, 6), round(x.eb, 6), x.rounds) == (want.rf, want.vb, want.eb, len(made.trace) // 2)


def test_report_of_an_empty_part_is_null(spark):
    e = spark.createDataFrame([(0, 1, 2, 0), (1, 2, 3, 0)], "eid long, src long, dst long, part int")
    r = metrics.partition_report(e, 2).first()
    assert r.vb is None and r.eb is None and r.empty_parts == 1 and r.rf == 1.0


def test_hub_load_is_spread_by_parts_and_not_by_owner(spark):
    from pyspark.sql import functions as F

    from hubgraph.partition.placement import hash_edge_cut, place

    g = star(spark, 400)
    hub = spark.createDataFrame([(0,)], "vid long")
    spread = ga.workload(place(g.edges, 4, "random"), hub, 10).toPandas()
    assert len(spread) == 4 and spread.load.max() < 2
    assert ga.owner_workload(g, hash_edge_cut(g, 4), hub, 10).count() == 1
    sizes = {k: ga.khop_sample(place(g.edges, 4, "random"), hub, [10], ga.SampleConfig(rounding=k)).agg(F.count("*")).first()[0] for k in ("global_topk", "largest_remainder")}
    assert sizes == {"global_topk": 10, "largest_remainder": 10}


def test_layout_gives_edges_back():
    r = np.random.default_rng(0)
    s, d, t = r.integers(0, 9, 40), r.integers(5, 20, 40), r.integers(0, 3, 40)
    x = build_layout(s, d, t)
    p = np.arange(40)
    back = sorted(zip(x.global_id[x.source(p)], x.global_id[x.out_dst], x.edge_type(p), strict=True))
    assert back == sorted(zip(s, d, t, strict=True))
    assert sum(len(x.neighbours(v, k)) for v in range(len(x.global_id)) for k in range(3)) == 40


def test_draws():
    rng = np.random.default_rng(1)
    for n, total in ((0, 5), (1, 1), (5, 5), (4, 50)):
        p = skip_positions(n, total, rng)
        assert len(set(p)) == n and p == sorted(p) and all(0 <= x < total for x in p)
    hits = np.bincount(alias_draw(*build_alias([1, 2, 4, 8]), 60_000, rng), minlength=4) / 60_000
    assert np.allclose(hits, np.array([1, 2, 4, 8]) / 15, atol=0.01)


def test_queries_match_sql(spark):
    import duckdb

    import __spark_entry__ as entry

    d, con = "/root/testdata/sf0.001", duckdb.connect()
    for t in ("lineitem", "part", "supplier", "customer", "orders", "documents", "events"):
        con.sql(f"create view {t} as select * from '{d}/{t}.parquet'")
    queries, sql = entry.queries(), entry.oracle_sql()
    for name in ("graph_stats_folded", "part_quality_hash2d_folded", "sample_weighted_khop_trade", "op_agg_cube"):
        got, want = queries[name](spark, d).toPandas(), con.sql(sql[name]).df()
        cols = sorted(want.columns)
        key = lambda f: sorted(map(repr, f[cols].astype(object).where(f[cols].notna(), None).values.tolist()))
        assert sorted(got.columns) == cols and len(got) == len(want), name
        if got[cols].dtypes.equals(want[cols].dtypes):
            assert key(got) == key(want), name
