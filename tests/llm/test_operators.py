import sys
from pathlib import Path

import numpy as np
import pytest

sys.path.insert(0, str(Path(__file__).parent))
import brute

from hubgraph.llm import chat, ctw, decontam, knn, langid, packing, secrets, simhash, suffix, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, extra string"
LONG = "the quick brown fox jumps over the lazy dog while seventeen bakers count their many golden loaves at dawn again "


@pytest.fixture(scope="module")
def rows():
    secret = "password = 'hunter2hunter2' token:abc AKIA" + "A1" * 10 + " " + "0f" * 16 + " secret=token: abcdef12"
    texts = ["", None, "   ", "one", LONG * 3, LONG * 3, LONG + "x" + LONG, "a" * 500, secret, "Ünï ß word " * 40, LONG * 400, "bonjour le monde " * 20]
    return [(i, t, "en" if i % 2 else "fr", "s", 0, None) for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA)


def frame(df):
    return {r[0]: tuple(r)[1:] for r in df.collect()}


def test_repeats(docs, rows):
    got = frame(suffix.remove_repeats(docs).drop("kept"))
    assert got == brute.op1([(r[0], (r[1] or "").encode()) for r in rows])


def test_matching_statistics():
    texts = [b"banana bandana", b"ananas", b"nab"]
    index = suffix.RunLengthIndex(texts)
    index.classes(3, np.arange(index.n))
    lengths, _, _ = index.matching_statistics([b"xananab"])
    assert lengths.tolist() == [0, 5, 4, 3, 3, 2, 1]


def test_language(docs, spark):
    got = frame(langid.language_report(docs))
    assert got[0][1:] == ("und", 0.0) and got[1][1] == "und"
    assert all(0 <= s <= 1 for _, _, s in got.values())
    assert langid.language_report(spark.createDataFrame([], SCHEMA)).count() == 0


def test_secrets(docs, rows, spark):
    got = frame(secrets.secret_report(docs))
    assert {k: v[:4] for k, v in got.items()} == {r[0]: brute.op3(r[1]) for r in rows}
    ledger = secrets.scan_unseen(docs)
    assert secrets.scan_unseen(docs, ledger).count() == 0
    more = docs.union(spark.createDataFrame([(99, "token=abcdef99", "en", "s", 0, None)], SCHEMA))
    assert {r.blob for r in secrets.scan_unseen(more, ledger).collect()} == {brute.sha("token=abcdef99")}


def test_chat_round_trip(spark, tmp_path):
    hard = ["~1 <|end|> [INST] ~", "", None, "a\nb"]
    conv = spark.createDataFrame([(1, k, "assistant" if k % 2 else "us\ner", t) for k, t in enumerate(hard)] + [(None, None, None, None)], "conv_id long, turn long, role string, text string")
    out = chat.format_conversations(conv)
    out.write.parquet(str(tmp_path / "out"))
    back = spark.read.parquet(str(tmp_path / "out")).where("conv_id = 1").orderBy("position").collect()
    assert [chat.parse_piece(r.piece)[1] for r in back] == [t or "" for t in hard]
    stream = "".join(r.piece for r in back)
    assert [chat.unescape(stream[r.loss_start : r.loss_end]) for r in back if r.loss_end] == ["", "a\nb"]
    assert frame(chat.chat_report(conv))[-1][0] == 2


def test_simhash(docs, rows, spark):
    got = frame(simhash.near_duplicate_report(docs))
    assert got == brute.op5([(r[0], r[1]) for r in rows])
    assert simhash.near_duplicate_report(spark.createDataFrame([], SCHEMA)).count() == 0


def test_golay_keys_meet():
    r = np.random.default_rng(3)
    x = r.integers(0, 1 << 63, 400, dtype=np.uint64)
    y = x ^ (np.uint64(1) << r.integers(0, 64, 400, dtype=np.uint64)) ^ (np.uint64(1) << r.integers(0, 64, 400, dtype=np.uint64))
    held = [{} for _ in range(2)]
    for k, v in enumerate((x, y)):
        for row, key in zip(*simhash.fuzzy_keys(v), strict=True):
            held[k].setdefault(int(row), set()).add(int(key))
    assert all(held[0][i] & held[1][i] for i in range(400))
    for n in (50, 5000):
        a, b = simhash.forest(np.unique(np.r_[x[:n], y[:n]]))
        assert len(a) == len(b)


def test_benchmark(docs, rows, spark):
    items = [(1, LONG), (2, "lazy dog"), (3, None), (10, "ß word ünï")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    want = brute.op6([(r[0], r[1]) for r in rows], items)
    assert frame(decontam.contamination_report(docs, bench)) == want
    blocks = decontam.decontaminate(docs, bench, block_chars=60).collect()
    assert {r.doc_id: (r.n_words, r.n_hit) for r in blocks} == {k: v[:2] for k, v in want.items()}


def test_packing(docs, rows):
    import public_tokenizers
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    got = packing.pack(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), with_ids=True).toPandas()
    for r in rows:
        ids = tokenizer.encode(r[1] or "", add_special_tokens=False).ids + [2]
        assert [x for p in got[got.doc_id == r[0]].sort_values("piece").ids for x in p] == ids
    for _, s in got.sort_values("offset").groupby("sequence_id"):
        assert s.offset.tolist() == [0, *s.length.cumsum()[:-1].tolist()] and s.length.sum() <= 1024


def test_split_rules():
    import public_tokenizers
    import regex

    for text in ("a  b", " x\n\n y", "tab\t\tz ", "it's 12ab!? ünï 　x", "  "):
        points = np.array([ord(c) for c in text], np.uint32)
        cut = [*packing.split_points(points, np.array([0, len(text)])).tolist(), len(text)]
        parts = [text[a:b] for a, b in zip(cut[:-1], cut[1:], strict=True)]
        assert "'" in text or parts == regex.findall(public_tokenizers.PATTERN, text)


def test_top_k(spark):
    r = np.random.default_rng(0)
    rows = [(i, [float(x) for x in r.normal(0, 1, 5)]) for i in range(70)] + [(80, None), (100, [float("nan")] * 5), (120, [1.0, None, 0.0, 0.0, 0.0])]
    got = knn.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>"))
    assert sorted(map(tuple, got.collect())) == brute.op8(rows)


def test_scoring(docs, rows):
    want = brute.op9([(r[0], r[1]) for r in rows])
    for k, v in frame(ctw.scoring_report(docs)).items():
        assert v[:4] == want[k][:4] and v[4] == pytest.approx(want[k][4]) and v[5] < 0


def test_context_tree_is_a_distribution():
    data, off = np.frombuffer(b"abracadabra abracadabra", np.uint8), np.array([0, 23])
    code, n = np.unique(ctw.laid_out(data, off)[0], return_counts=True)
    tree = ctw.ContextTree(code, n)
    for context in (code[3] >> np.uint64(8), np.uint64(0x7A7A7A7A)):
        every = (context << np.uint64(8)) + np.arange(256, dtype=np.uint64)
        assert (10 ** tree.log10(every)).sum() == pytest.approx(1)


def test_toxicity(spark):
    bad, good = "you are an idiot and a moron", "you are a kind person and a friend"
    model = toxicity.ToxicityModel([(bad, 1), (good, 0)] * 40)
    s = model.score([bad, good, "such an idioot", "", 'he said "idiot" once'])
    assert s[0] > 0.7 > s[1] and s[2] > s[1] and s[3] < 0.7
    rows = spark.createDataFrame([(1, bad, None, None, 0, None), (2, None, None, None, 0, None)], SCHEMA)
    assert {r.doc_id: r.predicted for r in toxicity.score_toxicity(rows, model).collect()} == {1: 1, 2: 0}


def test_pipeline_stages(spark, docs):
    import corpus_pipeline

    d = "/root/testdata/sf0.001"
    kept = docs.drop("extra")
    for _, run in corpus_pipeline.STAGES[:-1]:
        kept = run(spark, kept, d)
        assert kept.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    ids = {r.doc_id: r.text for r in kept.collect()}
    assert 4 in ids and 5 not in ids and 0 not in ids and "hunter2" not in ids[8]
