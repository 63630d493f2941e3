"""op4 writes each prefix and target out, and reads its digest from them."""

from pyspark.sql import functions as F

from hubgraph.llm import chat


def test_every_reply_is_written_out_with_its_prefix(spark):
    turns = [(1, 0, "user", "a<"), (1, 1, "assistant", "[b]"), (1, 2, "user", "c"), (1, 3, "assistant", None), (1, 4, "user", "d"), (2, 0, "user", "e"), (3, 0, "assistant", "f")]
    conversations = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string")
    rows = chat.format_conversations(conversations).orderBy("conv_id", "position").collect()
    streams = {}
    for r in rows:
        stream = streams.get(r.conv_id, "")
        if r.loss_end is None:
            assert r.prefix is None and r.target is None
        else:
            assert (stream + r.piece)[: r.loss_end] == r.prefix + r.target and len(r.prefix) == r.loss_start
        streams[r.conv_id] = stream + r.piece
    assert [(r.conv_id, r.position, chat.unescape(r.target)) for r in rows if r.target is not None] == [(1, 1, "[b]"), (1, 3, ""), (3, 0, "f")]
    report = {r.conv_id: r for r in chat.chat_report(conversations).collect()}
    made = chat.examples(chat.format_conversations(conversations)).groupBy("conv_id").agg(F.count("*").alias("n"), F.sum(F.length("text")).alias("chars")).collect()
    assert {r.conv_id: (r.n, r.chars) for r in made} == {k: (report[k].n_examples, report[k].expanded_chars) for k in (1, 3)}
    assert (report[2].n_examples, report[2].expanded_chars, report[2].n_turns) == (0, 0, 1)


def test_long_conversations_are_handed_on_in_pieces():
    import pyarrow as pa

    n = 600
    batch = pa.RecordBatch.from_pydict({"conv_id": [7] * n, "role": ["user", "assistant"] * (n // 2), "text": ["x" * 200] * n})
    out = list(chat._write([batch]))
    assert len(out) > 3 and sum(b.num_rows for b in out) == n
    assert max(b.nbytes for b in out) < 3 * chat.BATCH
