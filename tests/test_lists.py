"""The rounds over lists of neighbours against those over arrays of edges."""

import random

import pytest

KINDS = "eid long, src long, dst long, etype int, weight double"


def hubs(n=600, seed=3):
    r = random.Random(seed)  # parallel edges, loops and hubs; some targets are sources as well
    return [(r.getrandbits(59), int(40 * r.random() ** 3), int(45 * r.random() ** 2) + 1000 * (i % 2), 0, 1.0) for i in range(n)]


@pytest.mark.parametrize("parts", [1, 3, 8, 12])
def test_rounds_over_lists_are_those_over_arrays(monkeypatch, parts):
    np = pytest.importorskip("numpy")
    from hubgraph.partition import expansion, lists

    monkeypatch.setattr(expansion, "CHUNK", 64)
    monkeypatch.setattr(lists, "VERTICES", 16)
    for seed in range(12):
        eid, s, d = (np.array(x) for x in list(zip(*hubs(300, seed), strict=True))[:3])
        ids, at = np.unique(np.concatenate([s, d]), return_inverse=True)
        s, d = (x.astype("int32") for x in np.split(at, 2))
        g = lists.Lists.__new__(lists.Lists)
        g.ids, g.total, g.shift, g.sides = ids, len(s), (parts - 1).bit_length(), []
        for x, y in ((s, d), (d, s)):
            order = np.argsort(x, kind="stable")
            g.sides.append((np.searchsorted(x[order], np.arange(len(ids) + 1)).astype("int32"), ((y.astype("uint32") << g.shift) | (eid % parts).astype("uint32"))[order]))
        order, grid = lists.Order(g, f"s{seed}"), lists.small_grid(ids, parts)
        for start in ("grid", "vertices"):
            seeds = order.seeds(g, start, parts, grid)
            if start == "grid":
                assert seeds == expansion.first_in_slots(ids, s, d, order.tied, expansion.grid_of(ids, parts), parts)
            for steer, share in ((True, None), (False, None), (True, 0.05), (False, 0.05)):
                rules = {"parts": parts, "steer": steer, "lambda0": 0.3, "alpha": 1.0, "beta": 1.0, "tau": 1.1, "max_rounds": 40, "tail": 0.02, "cap": expansion.round_cap(len(s), parts, share)}
                arrays = expansion.EdgeArrays([(eid % parts).astype("int8"), s.copy(), d.copy()], g.deg().astype("int64"), order.tied, keep=False)
                part, trace = expansion.array_rounds(arrays, seeds, **rules)
                ne, nv, inside = expansion.held_counts(arrays, part, parts)
                got = lists.list_rounds(g, order, seeds, **rules)
                assert (got[0].tolist(), got[1].tolist(), got[2], got[3]) == (ne.tolist(), nv.tolist(), inside, trace)


def test_packed_lists_hold_every_edge_in_any_order_of_rows(spark, monkeypatch):
    np = pytest.importorskip("numpy")
    from hubgraph.core.model import PropertyGraph
    from hubgraph.partition import lists

    rows = hubs(500)
    packed, total, heads = lists.pack_lists(PropertyGraph("g", spark.createDataFrame(rows, KINDS).repartition(3)), 5)
    batches = lists.rows_of(packed).toArrow().to_batches(max_chunksize=1)
    for order in (batches, batches[::-1]):
        g = lists.Lists(iter(order), 5, total, heads)
        for side, (begin, code) in enumerate(g.sides):
            here, there = np.repeat(g.ids, np.diff(begin)), g.ids[code >> g.shift]
            s, d = (there, here) if side else (here, there)
            assert sorted(zip(s.tolist(), d.tolist(), (code & 7).tolist(), strict=True)) == sorted((x[1], x[2], x[0] % 5) for x in rows)
    with pytest.raises(ValueError):
        lists.Lists(iter(batches[:-1]), 5, total, heads)


def test_counts_of_a_graph_beyond_the_arrays_need_no_distributed_rounds(spark, monkeypatch):
    from hubgraph.core.model import PropertyGraph
    from hubgraph.partition import expansion, lists, metrics

    g = PropertyGraph("g", spark.createDataFrame(hubs(300), KINDS))
    want = [metrics.partition_report(f(g, 3, start=x).edges, 3).first() for f in (expansion.bse_partition, expansion.tse_partition) for x in ("grid", "vertices")]
    study = expansion.balance_study(g, 2, orders=3, shares=(0.02,)).collect()
    monkeypatch.setattr(expansion, "LOCAL_LIMIT", 10)
    monkeypatch.setattr(expansion, "start_vertices", None)  # distributed rounds write out all edges in each round, before
    monkeypatch.setattr(lists, "PAIRED", 10)
    assert [expansion.quality(f, g, 3, start=x).first() for f in (expansion.bse_partition, expansion.tse_partition) for x in ("grid", "vertices")] == want
    assert sorted(expansion.balance_study(g, 2, orders=3, shares=(0.02,)).collect()) == sorted(study)


def test_packed_lists_take_few_bytes_an_edge(spark, tmp_path, monkeypatch):
    from hubgraph.core.model import PropertyGraph
    from hubgraph.partition import lists

    monkeypatch.setattr(lists, "stage", lambda df, **options: df.write.options(**options).parquet(f"{tmp_path}/p") or spark.read.parquet(f"{tmp_path}/p"))
    g = PropertyGraph("g", spark.range(0, 300_000, 1, 2).selectExpr("xxhash64(id) & 1152921504606846975 as eid", "id div 100 as src", "(1L << 40) + (xxhash64(id % 3001) & 1099511627775) as dst"))
    lists.pack_lists(g, 4)
    assert sum(f.stat().st_size for f in (tmp_path / "p").glob("*.parquet")) < 6 * 300_000  # about 26 an edge before
