"""Chat formatting by prefix-target expansion.

A conversation is written as a stream of marked turns. Each assistant turn becomes an example of its own, written out:
its prefix is the stream up to that reply, its target the reply, which alone is trainable. The examples of a
conversation of n turns thus come to the order of n * n text.
"""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Control strings hold "<" or "[" and a line end marks the role; none of the three is left in an escaped text.
ESCAPES = (("~", "~0"), ("<", "~1"), ("[", "~2"), ("\n", "~3"))
OPEN, TEXT, CLOSE = "<|turn|>", "<|text|>", "<|end|>"
PROBE = "</s>[INST] ok [/INST]"
BATCH = 4_000_000  # characters of pieces and examples that are handed on at once


def escape(text: str, *, role: bool = False) -> str:
    for plain, code in ESCAPES if role else ESCAPES[:3]:
        text = text.replace(plain, code)
    return text


def unescape(text: str) -> str:
    for plain, code in reversed(ESCAPES):
        text = text.replace(code, plain)
    return text


def _write(batches):
    """Rows sorted by conversation and turn to stream pieces with offsets, and an example for each assistant turn; what is
    held is the stream of one conversation and the examples of a batch."""
    held, stream, turn = object(), "", 0
    out, size = [], 0
    for b in batches:
        for conv, role, text in zip(*(b.column(c).to_pylist() for c in ("conv_id", "role", "text")), strict=True):
            if conv != held:
                held, stream, turn = conv, "", 0
            head = f"{OPEN}{escape(role or '', role=True)}{TEXT}"
            body = escape(text or "")
            piece, at = head + body + CLOSE, len(stream)
            if role == "assistant":
                prefix = stream + head
                out.append((conv, turn, piece, at, len(prefix), len(prefix) + len(body), prefix, body))
                size += len(prefix) + len(body)
            else:
                out.append((conv, turn, piece, at, None, None, None, None))
            size += len(piece)
            stream, turn = stream + piece, turn + 1
            if size >= BATCH or len(out) >= 10_000:
                yield _pieces(out)
                out, size = [], 0
    if out:
        yield _pieces(out)


def _pieces(out):
    kinds = {"conv_id": pa.int64(), "position": pa.int64(), "piece": pa.string(), "at": pa.int64(), "loss_start": pa.int64(), "loss_end": pa.int64(), "prefix": pa.string(), "target": pa.string()}
    return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out, strict=True), kinds.values(), strict=True)], list(kinds))


def format_conversations(conversations: DataFrame) -> DataFrame:
    """(conv_id, position, piece, at, loss_start, loss_end, prefix, target), one row a turn, in order within each conversation.

    at is the piece's place in the conversation's stream. prefix and target, set for assistant turns, are the example:
    the stream up to the reply, and the reply, on which alone the loss is taken; loss_start and loss_end are the target's
    span in the stream. Null roles and texts count as empty, null turns come first, equal turns are ordered by role and
    text, repeated rows stay, and rows of a null conv_id make one conversation. Rows go through sorted partitions: a task
    holds the stream of one conversation and, of its examples, some 4 million characters or a single one. An empty table
    gives an empty result; other columns are ignored.
    """
    rows = conversations.select("conv_id", "turn", "role", "text").repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return rows.mapInArrow(_write, "conv_id long, position long, piece string, at long, loss_start long, loss_end long, prefix string, target string")


def examples(formatted: DataFrame) -> DataFrame:
    """(conv_id, target, text, loss_start, loss_end): one row for each assistant turn; target is the turn's position.

    text holds all preceding turns and the reply; text[:loss_start] is context, text[loss_start:loss_end], the reply
    alone, is trained on.
    """
    made = formatted.where("loss_end is not null")
    return made.select("conv_id", F.col("position").alias("target"), F.concat("prefix", "target").alias("text"), "loss_start", "loss_end")


def parse_piece(piece: str) -> tuple[str, str]:
    """(role, text) of a piece."""
    role, _, body = piece.removeprefix(OPEN).removesuffix(CLOSE).partition(TEXT)
    return unescape(role), unescape(body)


def _read(batches):
    """Stream pieces and examples, sorted, back to digests: turns from the pieces, what is trained on from the examples."""

    def row(s):
        return (s[0], s[1], s[2].hexdigest(), s[3], s[4].hexdigest(), s[5], s[6], s[7])

    state = None
    for b in batches:
        out = []
        for conv, piece, prefix, target in zip(*(b.column(c).to_pylist() for c in ("conv_id", "piece", "prefix", "target")), strict=True):
            if state is None or state[0] != conv:
                if state is not None:
                    out.append(row(state))
                state = [conv, 0, hashlib.sha256(), 0, hashlib.sha256(), 0, 0, 0]
            role, text = parse_piece(piece)
            state[1] += 1
            state[2].update(f"{role}\n{text}\n".encode("utf-8", "surrogatepass"))
            if target is not None:
                masked = unescape(target)
                state[3] += len(masked)
                state[4].update(masked.encode("utf-8", "surrogatepass"))
                state[6] += 1
                state[7] += len(prefix) + len(target)
            state[5] += len(piece)
        if out:
            yield _digests(out)
    if state is not None:
        yield _digests([row(state)])


def _digests(out):
    names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars", "n_examples", "expanded_chars"]
    return pa.RecordBatch.from_arrays([pa.array(x, pa.string() if n.endswith("sha256") else pa.int64()) for n, x in zip(names, zip(*out, strict=True), strict=True)], names)


def chat_report(conversations: DataFrame) -> DataFrame:
    """The digest of query op4; formatted_chars counts the stream, expanded_chars all examples."""
    spark = conversations.sparkSession
    probe = spark.createDataFrame([(-1, 0, "user", PROBE), (-1, 1, "assistant", PROBE)], "conv_id long, turn long, role string, text string")
    formatted = format_conversations(conversations.select("conv_id", "turn", "role", "text").unionByName(probe))
    # The stream comes back in the order it was written in: the digest reads it in the same partition.
    return formatted.mapInArrow(_read, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long, n_examples long, expanded_chars long")
