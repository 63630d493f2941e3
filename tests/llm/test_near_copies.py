import random

import pytest

from hubgraph.llm import simhash

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def frame(spark, texts):
    return spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in texts], SCHEMA)


def shingle_set(text):
    w = text.lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(len(w) - 4, min(len(w), 1)))}


def wanted(texts):
    """Smallest id of each group, all pairs compared."""
    sets, parent = [shingle_set(t) for _, t in texts], list(range(len(texts)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(sets)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if 5 * both >= 4 * (len(sets[i]) + len(sets[j]) - both) and (a := root(i)) != (b := root(j)):
                parent[max(a, b)] = min(a, b)
    return {d: texts[root(i)][0] for i, (d, _) in enumerate(texts)}


def words(r, n):
    return [f"w{r.randrange(10**9)}" for _ in range(n)]


def changed(r, text, n):
    out = list(text)
    for at in r.sample(range(len(out)), n):
        out[at] = words(r, 1)[0]
    return out


@pytest.mark.parametrize("hot", [4096, 32])
def test_near_copies_among_documents_that_share_a_passage(spark, monkeypatch, hot):
    monkeypatch.setattr(simhash, "HOT", hot, raising=False)
    r = random.Random(5)
    passage = words(r, 400)
    docs = [words(r, 100) + passage for _ in range(150)]
    docs += [changed(r, d[:100], 4) + passage for d in docs[:50]]
    r.shuffle(docs)
    texts = [(i, " ".join(d)) for i, d in enumerate(docs)]
    want = wanted(texts)
    assert len(set(want.values())) == 150
    assert dict(map(tuple, simhash.near_duplicate_groups(frame(spark, texts)).collect())) == want


def test_long_texts_about_the_limit(spark):
    r = random.Random(6)
    docs = []
    for k in range(40):
        base = words(r, 1500)
        docs += [base, changed(r, base, 31 + k % 10)]
    texts = [(i, " ".join(d)) for i, d in enumerate(docs)]
    want = wanted(texts)
    assert 41 < len(set(want.values())) < 79
    assert dict(map(tuple, simhash.near_duplicate_groups(frame(spark, texts)).collect())) == want


def test_simhash_links_pass_the_test_of_shingles(spark):
    # Two words of three-word shingles repeated: one fingerprint, but no five-word shingle set in common.
    texts = [(1, "a b c " * 2), (2, "b c a " * 40 + "x y z w v"), (3, "a b c " * 3)]
    got = dict(map(tuple, simhash.near_duplicate_groups(frame(spark, texts)).collect()))
    assert got == wanted(texts)
