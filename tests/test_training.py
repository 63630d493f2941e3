import numpy as np
import pytest

from hubgraph.infer.store import EmbeddingStore, MlpDecoder, fill_static_cache, load_partition, save_partitions
from hubgraph.sample import gather_apply as ga
from hubgraph.train import blocks


@pytest.mark.parametrize("kind", ["sage", "gcn"])
def test_gradients_by_differences(kind):
    r = np.random.default_rng(1)
    x, p = r.normal(size=(7, 4)), blocks.first_weights(kind, 4, 5, 3)
    outer = (np.array([0, 0, 1, 2, 3, 3]), np.array([1, 2, 4, 5, 6, 0]))
    inner = (outer[0][:3], outer[1][:3])
    want = r.normal(size=(7, 3))
    loss = lambda q: float((blocks.encode(kind, q, x, outer, inner)[0] * want).sum())
    got = blocks.back(kind, p, blocks.encode(kind, p, x, outer, inner)[1], want)
    for name, w in p.items():
        for at in ((0, 0), (2, 1), (w.shape[0] - 1, w.shape[1] - 1)):
            up, down = ({k: v.copy() for k, v in p.items()} for _ in range(2))
            up[name][at] += 1e-5
            down[name][at] -= 1e-5
            assert got[name][at] == pytest.approx((loss(up) - loss(down)) / 2e-5, abs=1e-5)


def _two_groups(spark, n=60):
    r = np.random.default_rng(2)
    edges = [(int(a), int(b)) for a in range(n) for b in r.choice(np.arange(a % 2, n, 2), 4)]
    adjacency = spark.createDataFrame([(a, b, k) for k, (a, b) in enumerate(edges)] + [(b, a, k) for k, (a, b) in enumerate(edges)], "vid long, nbr long, eid long")
    features = spark.createDataFrame([(i, [float(i % 2 == 0) + float(r.normal(0, 0.8)), float(r.normal())]) for i in range(n)], "vid long, h array<double>")
    return edges, adjacency, features


@pytest.mark.parametrize("kind", ["sage", "gcn"])
def test_classes_of_two_groups_are_learned(spark, kind):
    _, adjacency, features = _two_groups(spark)
    labelled = spark.createDataFrame([(i, i % 2) for i in range(40)], "vid long, label int")
    trained = blocks.train_vertices(adjacency, features, labelled, 2, kind=kind, hidden=8, epochs=8, batch=8, trainers=1, rate=0.05)
    assert trained.losses[-1] < trained.losses[0]
    got = blocks.predict_vertices(adjacency, features, spark.createDataFrame([(i,) for i in range(40, 60)], "vid long"), trained, kind=kind, fanouts=(None, None)).collect()
    assert sum(x.predicted == x.vid % 2 for x in got) >= 16


def test_links_within_groups_are_learned(spark):
    edges, adjacency, features = _two_groups(spark)
    positives = spark.createDataFrame(edges, "src long, dst long")
    negatives = spark.createDataFrame([(a, (b + 1) % 60) for a, b in edges], "src long, dst long")
    trained = blocks.train_links(adjacency, features, positives, negatives, hidden=8, epochs=8, batch=64, rate=0.05)
    assert np.mean(trained.losses[-2:]) < 0.8 * np.mean(trained.losses[:2])


def test_store_partitions_and_decoder_round_trip(spark, tmp_path):
    lids = spark.createDataFrame([(w, 10 * w + i, i) for w in range(2) for i in range(5)], "worker int, vid long, lid long")
    h = spark.createDataFrame([(v, [float(v), 1.0]) for v in [*range(5), *range(10, 15)]], "vid long, h array<double>")
    store = EmbeddingStore(spark, str(tmp_path / "store"))
    store.write(0, fill_static_cache(lids, h, 2))
    assert {r.vid for r in store.read(0, 1, [0, 2]).collect()} == {10, 11, 14}
    edges = spark.createDataFrame([(i, i, (i + 1) % 5, i % 3, 0) for i in range(5)], "eid long, src long, dst long, part int, etype int")
    save_partitions(edges, str(tmp_path / "parts"))
    assert {r.eid for r in load_partition(spark, str(tmp_path / "parts"), 1).collect()} == {1, 4}
    score = MlpDecoder(np.eye(4), np.array([[1.0], [0], [0], [-1]])).score(h, edges)
    assert {r.eid: r.score for r in score.collect()} == {i: i - 1.0 for i in range(5)}


def test_types_have_fanouts_of_their_own(spark):
    edges = spark.createDataFrame([(k, 0, 1 + k, k % 2, 1.0, k % 3) for k in range(20)], "eid long, src long, dst long, etype int, weight double, part int")
    got = ga.typed_fanout_sample(edges, spark.createDataFrame([(0,)], "vid long"), {0: 3, 1: 5}).collect()
    assert sorted(r.etype for r in got) == [0] * 3 + [1] * 5
