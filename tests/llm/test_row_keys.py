import brute
import corpus_pipeline
from hubgraph.llm import decontam

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
PASSAGE = "the quick brown fox jumps over the lazy dog while seventeen bakers count their many golden loaves at dawn again"


def frame(spark, rows):
    return spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], SCHEMA)


def pairs(df):
    return sorted(((r.doc_id, r.text) for r in df.select("doc_id", "text").collect()), key=repr)


def test_near_dedup_keeps_rows_of_null_and_repeated_ids(spark):
    a, b, c, d, e = (" ".join(f"{x}{k}" for k in range(60)) for x in "abcde")
    rows = [(None, a), (None, b), (7, c), (7, d), (9, d + " more"), (None, e), (None, e), (3, a + " more"), (8, b), (8, b)]
    got = pairs(corpus_pipeline.drop_near_duplicates(spark, frame(spark, rows), None))
    assert got == sorted([(3, a + " more"), (8, b), (7, c), (7, d), (None, e)], key=repr)


def test_decontamination_judges_each_row_by_itself(spark, monkeypatch):
    rows = [(None, PASSAGE), (None, "clean one"), (None, None), (5, "x " + PASSAGE), (5, "clean two"), (6, "clean two")]
    want = [(None, "clean one"), (None, None), (5, "clean two"), (6, "clean two")]
    bench = spark.createDataFrame([(1, PASSAGE), (2, "some other words that no document has in a row at all")], "item_id long, text string")
    for limit in (decontam.BLOCK_CHARS, 60):
        assert pairs(decontam.uncontaminated(frame(spark, rows), bench, block_chars=limit)) == sorted(want, key=repr)
    monkeypatch.setattr(corpus_pipeline, "table", lambda *_: bench)
    assert pairs(corpus_pipeline.drop_contaminated(spark, frame(spark, rows), None)) == sorted(want, key=repr)


def test_blocks_of_a_benchmark_give_the_rows_of_one_scan(spark):
    rows = [(None, "a " + PASSAGE), (None, PASSAGE + " lazy dog b"), (None, "clean"), (4, "lazy dog"), (4, "no"), (4, "lazy dog"), (5, None)]
    bench = spark.createDataFrame([(1, PASSAGE), (2, "lazy dog"), (3, "b")], "item_id long, text string")
    columns = ("doc_id", "n_words", "n_hit", "items", "text")
    one, many = (sorted((tuple(r) for r in decontam.decontaminate(frame(spark, rows), bench, clean=True, block_chars=n).select(*columns).collect()), key=repr) for n in (decontam.BLOCK_CHARS, 40))
    assert one == many and len(one) == len(rows)
    want = brute.op6(list(enumerate(t for _, t in rows)), [(1, PASSAGE), (2, "lazy dog"), (3, "b")])
    got = decontam.decontaminate(frame(spark, rows), bench, block_chars=40).collect()
    assert sorted((r.n_words, r.n_hit) for r in got) == sorted(v[:2] for v in want.values())
