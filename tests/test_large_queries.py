"""Queries that failed or went wrong on larger tables."""

import duckdb
import pytest

import __spark_entry__ as entry

SMALL = "/root/testdata/sf0.001"


def rows_of_sql(name, folder=SMALL):
    con = duckdb.connect()
    con.sql("set TimeZone = 'UTC'")
    for t in ("orders", "customer", "lineitem", "events"):
        con.sql(f"create view {t} as select * from '{folder}/{t}.parquet{'' if folder == SMALL else '/*.parquet'}'")
    return con.sql(entry.oracle_sql()[name])


def same(got, want):
    return sorted(map(tuple, got.select(*want.columns).collect()), key=repr) == sorted(want.fetchall(), key=repr)


@pytest.mark.parametrize("name", ["stream_deduplicated", "stream_placed_hash2d", "stream_static_join"])
def test_streams_that_only_add_rows_end_in_files(spark, name):
    got = entry.queries()[name](spark, SMALL)
    assert got.inputFiles()  # a memory table holds all rows on the driver
    assert same(got, rows_of_sql(name))


def test_lateral_limit_keeps_the_order_across_tasks(spark, tmp_path):
    rows = [(i, i % 7, float(i * 37 % 1000)) for i in range(2000)] + [(5000, 8, None), (5001, 8, 1.0), (5003, 9, 2.0), (5002, 9, 2.0)]
    spark.createDataFrame(rows, "o_orderkey long, o_custkey long, o_totalprice double").repartition(16).write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame([(i,) for i in range(12)], "c_custkey long").write.parquet(f"{tmp_path}/customer.parquet")
    best = {}
    for key, customer, price in rows:
        best[customer] = min(best.get(customer, (9e9, 0)), (9e8 if price is None else -price, key))
    got = entry.queries()["op_subquery_lateral"](spark, str(tmp_path))
    assert "row_number() windowspecdefinition(o_custkey" not in got._jdf.queryExecution().optimizedPlan().toString()  # numbers rows as they come from a shuffle
    got = got.collect()
    assert {r.c_custkey: r.o_orderkey for r in got} == {c: key for c, (_, key) in best.items()} and len(got) == len(best)


def test_distinct_parts_are_counted_apart_from_sketches(spark):
    got = entry.queries()["op_agg_approximate"](spark, SMALL)
    aggregates = [x for x in got._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Aggregate [" in x]
    assert any("percentile" in x for x in aggregates) and not any("percentile" in x and "count(distinct" in x for x in aggregates)
    assert same(got, rows_of_sql("op_agg_approximate"))


@pytest.mark.parametrize("name", ["op_generated_hubs", "op_recursive"])
def test_queries_over_made_up_data_read_a_table(spark, name):
    got = entry.queries()[name](spark, SMALL)
    assert "o_orderkey" in got._jdf.queryExecution().analyzed().toString()
    want = rows_of_sql(name)
    assert len(want.fetchall()) > 20 and same(got, want)


def test_a_study_deals_no_copies_of_the_edges(spark):
    from hubgraph.core.model import PropertyGraph
    from hubgraph.partition import expansion

    kinds = "eid long, src long, dst long, etype int, weight double"
    g = PropertyGraph("g", spark.createDataFrame([(i, i % 7, 100 + i % 5, 0, 1.0) for i in range(40)], kinds))
    study = expansion.balance_study(g, 2, orders=1, shares=(None,))
    assert "Exchange" not in study._jdf.queryExecution().executedPlan().toString()  # a copy of all edges for each run before
    assert study.count() == 4
    assert expansion.balance_study(PropertyGraph("g", spark.createDataFrame([], kinds)), 2).count() == 0


def test_a_study_of_many_parts_runs_over_arrays_up_to_the_limit_of_edges(spark, monkeypatch):
    from hubgraph.core.model import PropertyGraph
    from hubgraph.partition import expansion

    monkeypatch.setattr(expansion, "expand", None)  # the rounds of a graph beyond the limit; parts counted against it before
    g = PropertyGraph("g", spark.createDataFrame([(i, i % 7, 100 + i % 5, 0, 1.0) for i in range(40)], "eid long, src long, dst long, etype int, weight double"))
    assert expansion.balance_study(g, 16, orders=1, shares=(None,), starts=("vertices",), local_limit=40).count() == 2


def test_arrays_of_rounds_hold_few_bytes_an_edge():
    import tracemalloc

    import numpy as np

    from hubgraph.partition import expansion

    rng = np.random.default_rng(3)
    s, d = (rng.integers(0, 5000, 400_000).astype("int32") for _ in range(2))
    columns, deg = [(rng.integers(0, 8, len(s))).astype("int8"), s, d], np.bincount(s, minlength=5000) + np.bincount(d, minlength=5000)
    tracemalloc.start()
    g = expansion.EdgeArrays(columns, deg, rng.permutation(5000))
    part, _ = expansion.array_rounds(g, [(p, p) for p in range(8)], parts=8, steer=True, lambda0=0.1, alpha=1.0, beta=1.0, tau=1.1, max_rounds=200, tail=0.02, cap=expansion.round_cap(len(s), 8, 0.02))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert set(part) == set(range(8)) and peak < 45 * len(s)


def test_the_vertex_orders_of_a_study_run_side_by_side(spark):
    from hubgraph.core.model import PropertyGraph
    from hubgraph.partition import expansion

    g = PropertyGraph("g", spark.createDataFrame([(i, i % 7, 100 + i % 5, 0, 1.0) for i in range(40)], "eid long, src long, dst long, etype int, weight double"))
    study = expansion.balance_study(g, 2, orders=3, shares=(None,), starts=("vertices",))
    counts = study.rdd.mapPartitions(lambda rows: [len({r.vertex_order for r in rows})]).collect()
    assert sorted(counts)[-3:] == [1, 1, 1]  # one task ran all of them before


def test_edges_around_vertices_come_in_chunks_and_once(monkeypatch):
    import numpy as np

    from hubgraph.partition import expansion

    monkeypatch.setattr(expansion, "CHUNK", 1000)  # one array of all before
    rng = np.random.default_rng(4)
    s, d = (rng.integers(0, 900, 20_000).astype("int32") for _ in range(2))
    g = expansion.EdgeArrays([np.zeros(len(s), "int8"), s.copy(), d.copy()], np.bincount(s, minlength=900) + np.bincount(d, minlength=900), np.arange(900), keep=False)
    chunks = g.around(np.arange(450), np.full(len(s), -1, "int8"))
    assert g.edge is None and len(chunks) > 10 and max(map(len, chunks)) < 1100
    assert sorted(np.concatenate(chunks).tolist()) == np.flatnonzero((g.s < 450) | (g.d < 450)).tolist()


@pytest.mark.parametrize("start", ["vertices", "grid"])
def test_quality_of_an_expansion_is_counted_without_its_edges(spark, monkeypatch, start):
    from hubgraph.core.model import PropertyGraph
    from hubgraph.partition import expansion, metrics

    g = PropertyGraph("g", spark.createDataFrame([(i, i * i % 23, 100 + i * i * i % 17, 0, 1.0) for i in range(300)], "eid long, src long, dst long, etype int, weight double"))
    want = [metrics.partition_report(f(g, 3, start=start).edges, 3).collect() for f in (expansion.bse_partition, expansion.tse_partition)]
    report = metrics.partition_report
    monkeypatch.setattr(metrics, "partition_report", None)  # shuffles the ends of all edges, which one task had written, before
    assert [expansion.quality(f, g, 3, start=start).collect() for f in (expansion.bse_partition, expansion.tse_partition)] == want
    monkeypatch.setattr(metrics, "partition_report", report)
    empty = PropertyGraph("g", g.edges.where("eid < 0"))
    assert expansion.quality(expansion.bse_partition, empty, 3).first().empty_parts == 3


def test_places_of_ids_are_those_of_a_search():
    import numpy as np

    from hubgraph.partition import expansion

    rng = np.random.default_rng(6)
    for ids in (np.arange(5000), np.unique(rng.integers(-(1 << 60), 1 << 60, 5000)), np.array([7]), np.zeros(0, "int64")):
        x = np.concatenate([rng.permutation(ids), np.array([1 << 61, -(1 << 61)])])
        assert expansion.Places(ids).of(x).tolist() == [*np.searchsorted(ids, x[:-2]).tolist(), -1, -1]


@pytest.mark.parametrize("parts", [5, 20, 200])
def test_claims_are_kept_in_the_parts_of_edges(parts):
    import numpy as np

    from hubgraph.partition import expansion

    rng = np.random.default_rng(7)
    eid, s, d = np.arange(9000), *(rng.integers(0, 900, 9000).astype("int32") for _ in range(2))
    turn, deg = (eid % parts).astype("int8" if parts < 128 else "int16"), np.bincount(s, minlength=900) + np.bincount(d, minlength=900)
    g = expansion.EdgeArrays([turn, s.copy(), d.copy()], deg, rng.permutation(900))
    part, _ = expansion.array_rounds(g, [(p, p) for p in range(parts)], parts=parts, steer=True, lambda0=0.1, alpha=1.0, beta=1.0, tau=1.1, max_rounds=0, tail=0.02, cap=1e9)
    for e, p in zip(g.edge.tolist(), part.tolist(), strict=True):  # the last pass: the turn breaks the tie of two empty parts
        near = [q for q in (int(s[e]), int(d[e])) if q < parts]
        assert p == (min(near, key=lambda q: (e + q) % parts) if near else e % parts)
    assert part.dtype == (np.int8 if parts < 12 else np.int16 if parts < 182 else np.int32)  # a second array of claims before


@pytest.mark.parametrize("parts", [3, 300])
def test_one_task_takes_in_a_graph_as_few_rows(spark, monkeypatch, parts):
    import numpy as np

    from hubgraph.core.model import PropertyGraph
    from hubgraph.partition import expansion

    g = PropertyGraph("g", spark.range(0, 90_000, 1, 3).selectExpr("id * 7919 as eid", "id % 701 as src", "(1L << 40) + id * id % 977 as dst"))
    packed, total = expansion.pack_edges(g, parts)
    assert total == 90_000 and packed.count() <= 3 * 2  # a row for each edge and each vertex before
    want = sorted(map(tuple, g.edges.collect()))
    assert sorted(map(tuple, expansion.unpacked(packed).collect())) == want
    batches = expansion._rows(packed, keep=True).toArrow().to_batches()
    for order in (batches, [b.slice(i, 1) for b in batches for i in reversed(range(b.num_rows))]):  # edges before vertices, too
        vid, deg, turn, s, d, eid = expansion._arrays(iter(order), parts, total, keep=True)
        assert sorted(zip(eid.tolist(), vid[s].tolist(), vid[d].tolist(), strict=True)) == want and (turn == eid % parts).all()
        assert (np.diff(vid) > 0).all() and deg.tolist() == sum(np.bincount(x, minlength=len(vid)) for x in (s, d)).tolist()
    empty, total = expansion.pack_edges(PropertyGraph("g", g.edges.where("eid < 0")), parts)
    assert total == 0 and expansion.unpacked(empty).count() == 0


def test_hashes_of_arrays_are_those_of_rows(spark):
    import numpy as np

    from hubgraph.core.portable import bits
    from hubgraph.partition import expansion

    vid = np.unique([x for k in range(63) for x in ((1 << k) - 1, 10 ** (k % 19), -(1 << k))] + list(range(1 << 40, (1 << 40) + 20_000)))
    want = np.array(spark.createDataFrame([(int(v),) for v in vid], "vid long").select(bits("s3", "vid").alias("h")).toPandas().h)
    assert expansion.hashes("s3", vid).tolist() == want.tolist()
    assert expansion.order_by_hash("s3", vid).tolist() == np.lexsort((vid, want)).tolist()


def test_pairs_of_documents_and_tokens_meet_without_a_shuffle_of_pairs(spark, tmp_path):
    from hubgraph.sources import graphs

    rows = [(1, "a b a"), (1, "B c"), (1, None), (2, None), (2, ""), (3, "été d'été"), (None, "a b"), (None, "b"), (4, "a b a"), (4, "a b a")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    edges = graphs.lexicon(spark, str(tmp_path)).edges
    assert "token" not in "".join(x for x in edges._jdf.queryExecution().executedPlan().toString().splitlines() if "Exchange" in x)
    con = duckdb.connect()
    con.sql(f"create view documents as select * from '{tmp_path}/documents.parquet/*.parquet'")
    assert same(edges.select("eid", "src", "dst"), con.sql(f"select eid, src, dst from ({graphs.SQL['lexicon']})"))


def test_a_batch_holds_few_blobs(spark, monkeypatch):
    from hubgraph.core.model import PropertyGraph
    from hubgraph.partition import expansion
    from hubgraph.session import ARROW_BYTES

    def sizes_of(batches):
        import pyarrow as pa

        for b in batches:
            yield pa.RecordBatch.from_pydict({"n": pa.array([b.nbytes], pa.int64())})

    held = spark.conf.get(ARROW_BYTES)
    try:
        spark.conf.set(ARROW_BYTES, "64m")
        monkeypatch.setattr(expansion, "BLOB", 1 << 9)
        packed, _ = expansion.pack_edges(PropertyGraph("g", spark.range(0, 600_000, 1, 1).selectExpr("id * 7919 as eid", "id % 701 as src", "id % 977 + 1000 as dst")), 4)
        sizes = expansion._rows(packed, keep=True).mapInArrow(sizes_of, "n long").collect()
        assert max(r.n for r in sizes) < 6 << 20  # all blobs in one batch before
    finally:
        spark.conf.set(ARROW_BYTES, held)


def test_edges_are_sorted_in_place(monkeypatch):
    import numpy as np

    from hubgraph.partition import expansion

    monkeypatch.setattr(expansion, "CHUNK", 1000)
    rng = np.random.default_rng(8)
    for n in (0, 1, 2, 999, 20_001):
        s, d = (rng.integers(0, 50, n).astype("int32") for _ in range(2))
        deg = np.bincount(s, minlength=50) + np.bincount(d, minlength=50)
        g = expansion.EdgeArrays([(np.arange(n) % 7).astype("int8"), s.copy(), d.copy()], deg, rng.permutation(50))
        assert sum(x.base.nbytes for x in (g.edge, g.to) if x.base is not None) <= 8 * n + 16  # no number of 8 bytes stays
        assert g.edge.tolist() == np.argsort(g.number_of[s], kind="stable").tolist() and g.to.tolist() == np.argsort(g.d, kind="stable").tolist()
        assert (g.s == g.number_of[s][g.edge]).all() and (g.d == g.number_of[d][g.edge]).all() and (g.turn == g.edge % 7).all()
