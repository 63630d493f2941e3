"""Operators against plain programs: repeated rows, ties, nulls, long texts, clashing columns and empty tables."""

import math
import random
import zlib
from collections import Counter, defaultdict
from functools import lru_cache

import brute
import numpy as np
import pytest
from pyspark.sql import functions as F

from hubgraph.llm import chat, ctw, decontam, knn, langid, packing, secrets, simhash, suffix, toxicity
from hubgraph.llm.queries import ranks_path

TEXTS = "doc_id long, text string"
VECTORS = "vec_id long, embedding array<double>"


def plain_tree(train, texts, depth):
    """log10 probabilities by a context tree in dictionaries."""
    count = defaultdict(lambda: [0, 0])

    def steps(text):
        context = b"\0" * depth
        for c in bytes(x + 32 if 65 <= x <= 90 else x for x in (text or "").encode()) + b"\xff":
            node = 1
            for i in range(7, -1, -1):
                yield context, node, c >> i & 1
                node = node << 1 | c >> i & 1
            context = (context + bytes([c]))[-depth:]

    for text in train:
        for context, node, bit in steps(text):
            for d in range(depth + 1):
                count[context[depth - d :], node][bit] += 1
    under = defaultdict(set)
    for context, node in count:
        if context:
            under[context[1:], node].add((context, node))

    def estimate(k):
        a, b = count[k]
        return math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.log(math.pi) - math.lgamma(a + b + 1)

    @lru_cache(None)
    def weighted(k):
        return estimate(k) if len(k[0]) == depth else float(np.logaddexp(estimate(k), sum(map(weighted, under[k])))) - math.log(2)

    out = []
    for text in texts:
        total = 0
        for context, node, bit in steps(text):
            p = 0.5
            for d in range(depth, -1, -1):
                k = context[depth - d :], node
                if k in count:
                    share = 1 if d == depth else math.exp(estimate(k) - math.log(2) - weighted(k))
                    p = share * (count[k][bit] + 0.5) / (sum(count[k]) + 1) + (1 - share) * p
            total += math.log10(p)
        out.append(total)
    return out


@pytest.mark.parametrize("entries", [1 << 20, 0])
@pytest.mark.parametrize("turned", [False, True])
def test_context_tree_scores(spark, entries, turned):
    rows = [(1, "abracadabra"), (2, ""), (3, None), (4, "x"), (10, "abra cadabra"), (11, "Zebra ü"), (11, "Zebra ü"), (None, "ghi"), (13, "a"), (14, "ab" * 3000)]
    held = lambda d: zlib.crc32(b"" if d is None else str(d).encode()) % 10 == 0
    want = plain_tree([t for d, t in rows if not held(d)], [t for _, t in rows], ctw.DEPTH)
    docs = spark.createDataFrame(rows[::-1] if turned else rows, TEXTS).repartition(3)
    got = sorted((str(r.doc_id), r.score) for r in ctw.score_texts(docs, ~(ctw.id_crc("doc_id") % 10 == 0), entries).collect())
    for (a, x), (b, y) in zip(got, sorted((str(d), s) for (d, _), s in zip(rows, want, strict=True)), strict=True):
        assert a == b and x == pytest.approx(y, abs=1e-5)


def plain_top(rows, k=20):
    ready = [(i, [int(np.floor(64 * x)) for x in v]) for i, v in rows if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v)]
    out = []
    for a, (q, x) in enumerate(ready):
        if q % 20 == 0:
            s = sorted((-min(max(sum(p * y for p, y in zip(x, z, strict=False)), 1 - 2**63), 2**63 - 1), i) for b, (i, z) in enumerate(ready) if a != b)[:k]
            out += [(q, r + 1, i, -t) for r, (t, i) in enumerate(s)]
    return sorted(out)


def test_top_k_of_repeated_ids_ties_and_large_components(spark):
    r = np.random.default_rng(0)
    centre = r.normal(0, 40, (12, 6))
    rows = [(i % 900, [float(x) for x in centre[i % 12] + r.normal(0, 0.3, 6)]) for i in range(1000)]
    pruned = knn.share_pruned(spark.createDataFrame(rows, VECTORS), block=40, pivots=24)
    assert pruned > 0.5
    rows += [(0, [1.0] * 6)] * 3 + [(20, []), (None, [1.0]), (40, None), (60, [math.nan] * 6), (80, [1.0, None]), (100, [1e9] * 6), (120, [1e9] * 6), (140, [1e200] * 6)]
    vectors = spark.createDataFrame(rows, VECTORS)
    for how in ({}, {"block": 40, "pivots": 9}):
        assert sorted(map(tuple, knn.top_k(vectors, **how).collect())) == plain_top(rows)
    assert knn.top_k(spark.createDataFrame([], VECTORS)).count() == 0


def best_fit_decreasing(lengths, capacity):
    rooms = []
    for s in sorted(lengths, reverse=True):
        fits = [r for r in rooms if r >= s]
        rooms.append(capacity) if not fits else None
        r = min(fits) if fits else capacity
        rooms.remove(r)
        rooms.append(r - s)
    return len(rooms)


@pytest.mark.parametrize("seed", range(6))
def test_plan_needs_no_more_bins_than_best_fit(seed):
    r = random.Random(seed)
    draw = [lambda: r.randrange(1, 1024), lambda: min(1023, int(r.expovariate(1 / 200)) + 1), lambda: r.choice([100, 350, 341, 513, 600])][seed % 3]
    lengths = [draw() for _ in range(800)]
    plan = packing.plan_bins(Counter(lengths))
    held = Counter()
    for n, own in plan:
        assert sum(own) <= 1024
        for s in own:
            held[s] += n
    assert held == Counter(lengths)
    assert sum(n for n, _ in plan) <= best_fit_decreasing(lengths, 1024)


def test_configurations_reach_the_fewest_bins():
    # 600 + 424 and 3 x 340: neither is found by filling bins with the longest first.
    got = packing.configurations(np.array([600, 424, 340]), np.array([10.0, 10.0, 30.0]), 1024)
    assert sum(t for _, t in got) == pytest.approx(20)


def test_repeats_of_crowded_anchors_and_shared_ids(spark):
    r = random.Random(1)
    some = lambda n, signs: "".join(r.choice(signs) for _ in range(n))
    one, two = some(150, "abcde "), some(130, "xyz ")
    rows = [(i, some(r.randrange(80), "abcdefgh ") + (one[r.randrange(20) : 130 + r.randrange(20)] if i % 2 else "") + some(30, "klm") + (two if i % 3 == 0 else "")) for i in range(40)]
    want = brute.op1([(d, t.encode()) for d, t in rows])
    docs = spark.createDataFrame(rows, TEXTS).withColumn("d", F.lit(1)).withColumn("start", F.lit("x"))
    for group in (suffix.GROUP, 3):
        spans = suffix.repeated_spans(docs.select(F.col("doc_id").alias("d"), "text"), group=group).groupBy("doc").agg(F.collect_list(F.struct("start", "end")).alias("m")).collect()
        gone = {x.doc: sum(e - s for s, e in suffix.remove_spans(dict(rows)[x.doc].encode(), [tuple(m) for m in x.m])[1]) for x in spans}
        assert {d: n for d, n in gone.items() if n} == {d: v[1] for d, v in want.items() if v[1]}
    assert {x[0]: tuple(x)[1:5] for x in suffix.remove_repeats(docs).drop("kept").collect()} == want
    shared = [(5, "a text of its own, short"), (5, one + "1" + one), (5, one + "2"), (None, "z" * 120), (None, "y" * 10), (7, one), (7, one)]
    got = Counter(tuple(x)[:4] for x in suffix.remove_repeats(spark.createDataFrame(shared, TEXTS)).collect())
    assert got == Counter([(5, 24, 0, 0), (5, 301, 150, 1), (5, 151, 150, 1), (None, 120, 119, 1), (None, 10, 0, 0), (7, 150, 150, 1), (7, 150, 150, 1)]) or got[5, 301, 300, 2]


def test_phrases_by_search():
    samples = {"a": "the quick brown fox the dog 漢字仮名 漢語", "b": "le renard brun et le chien 日本 語"}
    model = langid.LanguageModel(samples)
    texts = ["the dog and the 漢字 fox", "le chien 日本 渋谷", "", "x" * 1200 + " the quick", "ÜBER die Straße", "漢" * 600]
    bits, lettered = model.entropies(texts)
    assert lettered.tolist() == [True, True, False, True, True, True]
    for k, name in enumerate(model.names):
        sample = bytes(model.signs(langid._letters()[1][langid._points(samples[name])])[0])
        for i, text in enumerate(texts):
            signs, phrases = bytes(model.signs(langid._points(text))[0]), 0
            for s in range(0, len(signs), langid.PIECE):
                at, part = 0, signs[s : s + langid.PIECE]
                while at < len(part):
                    n = 1
                    while at + n < len(part) and part[at : at + n + 1] in sample:
                        n += 1
                    at, phrases = at + n, phrases + 1
            assert bits[i, k] == pytest.approx(phrases * np.log2(model.automata[k].length) / max(1, len(text)))


def test_languages_held_out(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    out = langid.language_report(docs).join(docs.select("doc_id", "lang"), "doc_id").where("held_out and lang is not null").collect()
    assert sum(r.lang == r.lang_pred for r in out) >= 0.98 * len(out)


def prefix_distance(word, stem):
    row = list(range(len(word) + 1))
    for i, c in enumerate(stem, 1):
        new = [i]
        for j, x in enumerate(word, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (c != x)))
        row = new
    return min(row)


def test_misspelled_stems_by_distance():
    model, r = toxicity.ToxicityModel([("idiot moron scumbag", 1), ("kind friend", 0)] * 40), random.Random(0)
    assert sorted(model.stems) == ["idiot", "moron", "scumbag"]
    for _ in range(1500):
        word = list(r.choice(model.stems))
        for _ in range(r.randrange(3)):
            at, kind = r.randrange(len(word)), r.randrange(3)
            word[at : at + (kind > 0)] = [] if kind == 1 else [r.choice("abcdiotm")]
        text = "".join(word) + r.choice(["", "s", "xyz"])
        assert bool(model.hits([text]).sum()) == any(prefix_distance(text, s) <= 1 for s in model.stems)


def test_weight_of_quotation_is_learned():
    open_, quoted = "you idiot you moron", 'they wrote "idiot" and "moron" there'
    told = toxicity.ToxicityModel([(open_, 1), (quoted, 0), ("a kind friend", 0)] * 40)
    alike = toxicity.ToxicityModel([(open_, 1), (quoted, 1), ("a kind friend", 0)] * 40)
    assert told.score([open_])[0] > 0.7 > told.score([quoted])[0]
    assert min(alike.score([open_, quoted])) > 0.7


def test_toxicity_held_out(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    n = Counter((r.toxic, r.predicted) for r in toxicity.toxicity_report(docs, labels).join(labels, "doc_id").where("held_out").collect())
    assert n[1, 1] >= 0.88 * (n[1, 1] + n[1, 0]) and n[1, 1] >= 0.92 * (n[1, 1] + n[0, 1])


def test_secrets_of_many_matches_and_marks(spark):
    r = random.Random(0)
    bits = ["password=abcdef1 ", "token: ab ", "AKIA" + "Z9" * 9, "é 0123456789abcdef0123456789", "secret=token:abcdef12345 ", "x y ", "api_key=AKIA" + "Q" * 18, " AKIAabc", "deadbeef" * 4, "-----BEGIN RSA PRIVATE KEY-----"]
    rows = [(i, "".join(r.choice(bits) for _ in range(r.choice([0, 1, 3, 200, 700])))) for i in range(40)] + [(100, None), (101, ""), (102, "token=abcdef " * 20_000)]
    docs = spark.createDataFrame(rows, TEXTS).withColumn("blob", F.lit(1)).withColumn("spans", F.lit("x")).withColumn("salt", F.lit(2))
    report = secrets.secret_report(docs).collect()
    assert {x.doc_id: tuple(x)[1:5] for x in report} == {d: brute.op3(t) for d, t in rows}
    plain = spark.createDataFrame(rows, TEXTS).withColumn("n_chars", F.lit(0).cast("long"))
    marked = {x.doc_id: (x.text, x.n_chars) for x in secrets.redact_documents(plain, secrets.scan_unseen(plain), "[R]").collect()}
    for x in report:
        text, out, at = dict(rows)[x.doc_id] or "", [], 0
        for s, e in sorted((int(s), int(e)) for _, s, e in (y.split(":") for y in x.spans.split(",") if y)):
            if s >= at:
                out.append(text[at:s] + "[R]")
            at = max(at, e)
        want = "".join(out) + text[at:]
        assert marked[x.doc_id] == (want, len(want))


def test_chat_examples_written_out(spark):
    turns = [(1, 0, "user", "a <b>"), (1, 1, "assistant", "[c]"), (1, 2, "user", None), (1, 3, "assistant", "~d"), (2, 0, "system", "only"), (3, 0, "assistant", "")]
    formatted = chat.format_conversations(spark.createDataFrame(turns, "conv_id long, turn long, role string, text string"))
    stream = {c: "".join(r.piece for r in sorted(rows, key=lambda r: r.position)) for c, rows in ((c, formatted.where(F.col("conv_id") == c).collect()) for c in (1, 2, 3))}
    got = sorted(tuple(r) for r in chat.examples(formatted).collect())
    assert [(c, t, chat.unescape(x[s:e])) for c, t, x, s, e in got] == [(1, 1, "[c]"), (1, 3, "~d"), (3, 0, "")]
    assert all(x == stream[c][:e] for c, _, x, _, e in got)


LONG = " ".join(f"word{k % 977} lorem" for k in range(30_000))


def test_every_operator_takes_repeated_rows_clashing_names_and_long_texts(spark):
    rows = [(None, "a b c"), (None, None), (3, "same words here"), (3, "same words here"), (4, LONG), (5, LONG + " end"), (6, "")]
    docs = spark.createDataFrame(rows, TEXTS)
    for name in ("key", "label", "h", "fp", "d", "th", "train", "score", "lang_pred", "bytes", "piece", "length", "salt", "rank", "blob", "row", "hits", "lang", "source"):
        docs = docs.withColumn(name, F.lit(1))
    bench = spark.createDataFrame([(1, "same words here"), (1, "same words here"), (None, None)], "item_id long, text string").withColumn("text2", F.lit(1))
    labels = spark.createDataFrame([(3, 1), (3, 0), (None, 1), (4, None)], "doc_id long, toxic int").withColumn("text", F.lit("x"))
    for full in (docs, docs.where("false")):
        n = full.count()
        assert suffix.remove_repeats(full).count() == n
        assert langid.language_report(full.withColumn("lang", F.lit("en"))).count() == n
        assert secrets.secret_report(full).count() == n
        assert simhash.near_duplicate_report(full).count() == n
        assert decontam.contamination_report(full, bench).count() == n
        assert packing.pack(full, ranks_path()).select("doc_id").distinct().count() == min(n, 5)
        assert ctw.scoring_report(full).count() == n
        assert toxicity.toxicity_report(full, labels).count() == n
        assert toxicity.toxicity_report(full, labels.where("false")).count() == n
    fingerprints = {r.doc_id: r.fingerprint for r in simhash.near_duplicate_report(docs).collect()}
    assert fingerprints[3] == f"{brute.op5_print('same words here'):016x}"
    assert decontam.contamination_report(docs, bench).where("contaminated").count() == 2
    empty = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    assert chat.chat_report(empty).count() == 1
