import random

from hubgraph.core.model import PropertyGraph
from hubgraph.partition.placement import multilevel_edge_cut
from hubgraph.session import stage

EDGES = "eid long, src long, dst long, etype int, weight double"


def cut_of(spark, pairs, parts, **options):
    g = PropertyGraph("g", spark.createDataFrame([(i, a, b, 0, 1.0) for i, (a, b) in enumerate(pairs)], EDGES))
    owner = dict(map(tuple, multilevel_edge_cut(g, parts, stage=stage, **options).collect()))
    assert set(owner) == {v for p in pairs for v in p}
    load = [sum(p == k for p in owner.values()) for k in range(parts)]
    return sum(owner[a] != owner[b] for a, b in pairs) / len(pairs), max(load) * parts / len(owner)


def communities(r, each=600):
    pairs = [(100 * c + r.randrange(100), 100 * c + r.randrange(100)) for c in range(4) for _ in range(each)]
    return [(a, b) for a, b in pairs if a != b]


def test_a_stall_of_matching_does_not_hash_the_rest(spark):
    """Pairs without further links: matching stalls with 1500 of them left, beside communities."""
    pairs = [(1000 + 2 * i, 1001 + 2 * i) for i in range(1500)] + communities(random.Random(4))
    cut, balance = cut_of(spark, pairs, 4, coarsest=64)
    assert cut < 0.2 and balance <= 1.25


def test_leaves_of_a_hub_do_not_fill_one_part(spark):
    _, balance = cut_of(spark, [(0, i + 1) for i in range(600)], 4, coarsest=64)
    assert balance <= 1.25


def test_communities_are_found(spark):
    r = random.Random(4)
    pairs = communities(r) + [(a, b) for a, b in ((r.randrange(400), r.randrange(400)) for _ in range(60)) if a != b]
    cut, balance = cut_of(spark, pairs, 4, coarsest=64)
    assert cut < 0.2 and balance <= 1.25
