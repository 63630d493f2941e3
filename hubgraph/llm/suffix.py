"""Long repeated strings by a run-length index.

Where two documents share a string of `length` bytes, they share the smallest of its hashed k-byte substrings, at the
same place in it. So each document is cut to anchors, the smallest substrings of all its windows, each with its
context: the bytes that any window around it can hold. Equal contexts are all settled by their hashes
(64 bits of the anchor and 64 of the context). Where an
anchor has several contexts, the earliest row of each goes, as bytes, to an index block: a run-length encoded
Burrows-Wheeler transform with text positions at the run ends. Matching statistics of the contexts are streamed
against it and every match of `length` bytes or more whose first occurrence is earlier is marked.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubgraph.llm.common import BYTE_VALUES, U64, Rolling, flat, mix, slices, stage

LENGTH, ANCHOR = 100, 32
#: Contexts of one anchor that an index block takes at most; beyond that all their strings are grouped one by one.
GROUP = 16384
BLOCK_BYTES = 120_000
_BYTES = Rolling(0x9E3779B97F4A7C15)


def anchors(data: np.ndarray, off: np.ndarray, length: int = LENGTH, k: int = ANCHOR):
    """Of all anchors of texts laid end to end: document, start and end of the context in the text, place of the anchor
    in the context, anchor hash, context hash."""
    n, w = len(data), length - k + 1
    if n < length:
        return (np.zeros(0, np.int64),) * 4 + (np.zeros(0, U64),) * 2
    prefix = _BYTES.prefix(BYTE_VALUES[data])
    h = mix((prefix[k:] - prefix[: n - k + 1]) * _BYTES.down[: n - k + 1])
    # The least of w values in a row, by doubling; the place in the low half makes it the first of equal hashes.
    low, span = (h & U64(0xFFFFFFFF00000000)) | np.arange(len(h), dtype=U64), 1
    while 2 * span <= w:
        low = np.minimum(low[:-span], low[span:])
        span *= 2
    low = np.minimum(low[: len(h) - w + 1], low[w - span : w - span + len(h) - w + 1])
    inside = np.ones(len(low), bool)  # windows of one document: none that starts within length - 1 before an end
    for end in off[1:-1]:
        inside[max(0, end - length + 1) : end] = False
    pos = (low & U64(0xFFFFFFFF)).astype(np.int64)[inside]
    pos = pos[np.r_[True, pos[1:] != pos[:-1]]] if len(pos) else pos
    d = np.searchsorted(off, pos, side="right") - 1
    lo, hi = np.maximum(pos - (length - k), off[d]), np.minimum(pos + length, off[d + 1])
    ctx = _BYTES.spans(prefix, lo, hi) ^ mix((pos - lo).astype(U64) * U64(0xD6E8FEB86659FD93) + (hi - pos).astype(U64))
    return d, lo - off[d], hi - off[d], pos - lo, h[pos], ctx


class RunLengthIndex:
    """Run-length BWT of texts, each ended by a sign of its own, with text positions at the ends of runs."""

    def __init__(self, texts: list[bytes]):
        size = np.array([len(t) for t in texts], np.int64)
        self.bounds = np.r_[0, np.cumsum(size + 1)]
        n = int(self.bounds[-1])
        self.text = np.zeros(n, np.int64)  # bytes are 1 to 256, ends are below
        raw = np.frombuffer(b"\0".join(texts) + b"\0", np.uint8)
        self.text[:] = raw.astype(np.int64) + 1
        ends = self.bounds[1:] - 1
        self.text[ends] = 0
        rank, self.depth_ranks = self._sort(ends, int(size.max(initial=0)) + 1)
        sa = np.empty(n, np.int64)
        sa[rank] = np.arange(n)
        bwt = self.text[sa - 1]
        head = np.r_[0, np.nonzero(np.diff(bwt))[0] + 1]
        self.head, self.char = head, bwt[head]
        self.tail = np.r_[head[1:], n] - 1
        self.head_at, self.tail_at = sa[self.head], sa[self.tail]  # sampled positions
        self.n = n
        count = np.bincount(self.text, minlength=257)
        self.first = np.cumsum(count) - count
        # Rank of a character before each of its runs; runs of one character lie together, in order.
        self.by_char = np.argsort(self.char, kind="stable")
        run = (self.tail - self.head + 1)[self.by_char]
        self.char_start = np.searchsorted(self.char[self.by_char], np.arange(258))
        before = np.cumsum(run) - run
        self.before = before - before[np.minimum(self.char_start[self.char[self.by_char]], len(before) - 1)]
        self.sorted_key = self.char[self.by_char] * np.int64(n + 1) + self.head[self.by_char]
        self._sa = sa

    def _sort(self, ends: np.ndarray, longest: int):
        n = len(self.text)
        wide = np.r_[self.text, np.zeros(8, np.int64)]
        key = np.zeros(n, np.uint64)
        stop = np.zeros(n, bool)
        for i in range(6):  # six signs of 9 bits, nothing beyond an end
            c = np.where(stop, 0, wide[i : i + n])
            key = key << U64(9) | c.astype(U64)
            stop |= c == 0
        values = np.unique(key, return_inverse=True)[1].astype(np.int64)
        step, kept = 6, {6: values}
        # An end sorts by its text's number, so that no two suffixes are equal.
        own = np.full(n, 0, np.int64)
        own[ends] = np.arange(1, len(ends) + 1)
        last = np.searchsorted(ends, np.arange(n))
        near_end = ends[last] - np.arange(n)
        unique = near_end < step
        values = values * np.int64(len(ends) + 1) + np.where(unique, last + 1, 0)
        values = np.unique(values, return_inverse=True)[1].astype(np.int64)
        kept[6] = values
        while step <= longest:
            nxt = np.where(near_end >= step, values[np.minimum(np.arange(n) + step, n - 1)] + 1, 0)
            key = values * np.int64(n + 2) + nxt
            values = np.unique(key, return_inverse=True)[1].astype(np.int64)
            step *= 2
            kept[step] = values
        return values, kept

    def equal(self, a: np.ndarray, b: np.ndarray, length: int) -> np.ndarray:
        """Do the suffixes at a and b agree on `length` bytes?"""
        if length < min(self.depth_ranks):
            at = [np.minimum(x[:, None] + np.arange(length), self.n - 1) for x in (a, b)]
            same = self.text[at[0]] == self.text[at[1]]
            return (same & (self.text[at[0]] > 0)).all(1)
        depth = max(d for d in self.depth_ranks if d <= length)
        r = self.depth_ranks[depth]
        ok = np.ones(len(a), bool)
        for at in [*range(0, length - depth, depth), length - depth]:
            x, y = np.minimum(a + at, self.n - 1), np.minimum(b + at, self.n - 1)
            ok &= r[x] == r[y]
        return ok

    def classes(self, length: int, order: np.ndarray) -> np.ndarray:
        """For rows of the index: the smallest `order` (by text position) of the suffixes that agree on `length` bytes."""
        sa = self._sa
        new = np.r_[True, ~self.equal(sa[1:], sa[:-1], length)] if self.n > 1 else np.ones(self.n, bool)
        starts = np.nonzero(new)[0]
        low = np.minimum.reduceat(order[sa], starts) if self.n else order
        self.class_start, self.class_low = starts, low
        self._sa = self.depth_ranks = None  # from here on only runs and samples are held
        return low

    def matching_statistics(self, patterns: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Length and index row of the longest match that starts at each byte of the patterns, and their offsets.

        All patterns are extended to the left in step. Where a row is not preceded by the wanted byte, the nearest
        runs of that byte above and below are tried, from their sampled ends, and the longer match goes on.
        """
        size = np.array([len(p) for p in patterns], np.int64)
        off = np.r_[0, np.cumsum(size)]
        data = np.frombuffer(b"".join(patterns), np.uint8).astype(np.int64) + 1
        order = np.argsort(-size, kind="stable")
        row, pos, long = np.zeros(len(patterns), np.int64), np.full(len(patterns), -1, np.int64), np.zeros(len(patterns), np.int64)
        lengths, rows = np.zeros(len(data), np.int64), np.zeros(len(data), np.int64)
        live_sizes = size[order]
        for t in range(int(size.max(initial=0))):
            lanes = order[: int(np.searchsorted(-live_sizes, -t, side="left"))]
            c = data[off[lanes + 1] - 1 - t]
            q, m, p = row[lanes], long[lanes], pos[lanes]
            key = c * np.int64(self.n + 1) + q
            at = np.searchsorted(self.sorted_key, key, side="right") - 1  # the run of c that starts at q or before
            lo, hi = self.char_start[c], self.char_start[c + 1]
            has_up = at >= lo
            run = self.by_char[np.maximum(at, 0)]
            inside = has_up & (q <= self.tail[run]) & (p >= 0)
            down = np.minimum(at + 1, len(self.by_char) - 1)
            has_down = at + 1 < hi
            run_down = self.by_char[down]
            up_at, down_at = self.tail_at[run], self.head_at[run_down]
            jump = ~inside
            up_long, down_long = np.zeros(len(q), np.int64), np.zeros(len(q), np.int64)
            j = np.nonzero(jump)[0]
            if len(j):
                tail = off[lanes[j] + 1] - t
                up_long[j] = np.where(has_up[j], self._agree(up_at[j], data, tail, m[j]), -1)
                down_long[j] = np.where(has_down[j], self._agree(down_at[j], data, tail, m[j]), -1)
            use_down = jump & (down_long > up_long)
            none = jump & ~has_up & ~has_down
            chosen = np.where(use_down, down, np.maximum(at, 0))
            chosen_run = self.by_char[chosen]
            source = np.where(inside, q, np.where(use_down, self.head[chosen_run], self.tail[chosen_run]))
            new_row = self.first[c] + self.before[chosen] + source - self.head[chosen_run]
            new_pos = np.where(inside, p, np.where(use_down, down_at, up_at)) - 1
            new_long = np.where(inside, m, np.maximum(up_long, down_long)) + 1
            row[lanes] = np.where(none, 0, new_row)
            pos[lanes] = np.where(none, -1, new_pos)
            long[lanes] = np.where(none, 0, new_long)
            where = off[lanes + 1] - 1 - t
            lengths[where], rows[where] = long[lanes], row[lanes]
        return lengths, rows, off

    def _agree(self, at: np.ndarray, data: np.ndarray, tail: np.ndarray, most: np.ndarray) -> np.ndarray:
        """Signs on which the text at `at` agrees with the pattern from `tail`, up to `most`."""
        out, wide = np.zeros(len(at), np.int64), int(most.max(initial=0))
        if not wide:
            return out
        step = np.arange(wide)
        for s in range(0, len(at), max(1, 1_000_000 // wide)):
            e = s + max(1, 1_000_000 // wide)
            differs = self.text[np.minimum(at[s:e, None] + step, self.n - 1)] != data[np.minimum(tail[s:e, None] + step, len(data) - 1)]
            differs |= step >= most[s:e, None]
            out[s:e] = np.where(differs.any(1), differs.argmax(1), wide)
        return out


def mark_block(rows: list[tuple[int, int, bytes]], length: int) -> list[tuple[int, int, int]]:
    """(doc, start, end) of the bytes in contexts (doc, start of context, bytes) that occur earlier in the block."""
    by_text: dict[bytes, tuple[int, int]] = {}
    for doc, start, text in rows:
        by_text[text] = min(by_text.get(text, (doc, start)), (doc, start))
    texts = sorted(by_text)
    # Places of the block in order: a rank for (doc, byte).
    index = RunLengthIndex(texts)
    doc = np.repeat([by_text[t][0] for t in texts], [len(t) + 1 for t in texts])
    byte = np.concatenate([np.arange(by_text[t][1], by_text[t][1] + len(t) + 1) for t in texts])
    order = np.empty(len(doc), np.int64)
    by = np.lexsort((byte, doc))
    step = np.r_[False, (np.diff(doc[by]) != 0) | (np.diff(byte[by]) != 0)]
    order[by] = np.cumsum(step)
    index.classes(length, order)
    lengths, found, off = index.matching_statistics(texts)
    low = index.class_low[np.searchsorted(index.class_start, found, side="right") - 1]
    own = np.concatenate([order[b : b + len(t)] for b, t in zip(index.bounds[:-1], texts, strict=True)])
    marked = (lengths >= length) & (low < own)
    # A later row with the text of an earlier one is covered throughout.
    out = [(doc, start, start + len(text)) for doc, start, text in rows if len(text) >= length and (doc, start) > by_text[text]]
    for t, s, e in zip(texts, off[:-1], off[1:], strict=True):
        hit = np.nonzero(marked[s:e])[0]
        if len(hit):
            d, base = by_text[t]
            cut = np.r_[0, np.nonzero(np.diff(hit) > 1)[0] + 1, len(hit)]
            out += [(d, base + int(hit[a]), base + int(hit[b - 1]) + length) for a, b in zip(cut[:-1], cut[1:], strict=True)]
    return out


NO_ID = -(1 << 63)


def _frame(**columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict({k: v if isinstance(v, pa.Array) else pa.array(np.ascontiguousarray(v)) for k, v in columns.items()})


def _parse(length: int):
    """Texts to anchor rows (h, c, doc, span): span holds the context's start, then in 20 bits the anchor's place in it
    and the size of the context.

    Of equal contexts in a slice only the first goes on as an anchor; the others, being settled, go on with c null.
    """

    def run(batches):
        for b in slices(batches, "text", 4_000_000):
            data, off = flat(b.column("text"))
            ids = b.column("d").to_numpy()
            d, lo, hi, place, h, c = anchors(data, off, length)
            doc, span = ids[d], lo << 20 | place << 10 | hi - lo
            order = np.lexsort((span, doc, c, h))
            doc, span, h, c = doc[order], span[order], h[order], c[order]
            new = np.r_[True, (h[1:] != h[:-1]) | (c[1:] != c[:-1])] if len(h) else np.zeros(0, bool)
            first = np.maximum.accumulate(np.where(new, np.arange(len(new)), 0))
            later = (doc != doc[first]) | (span != span[first])
            keep = new | (later & (span & 1023 >= length))
            h = np.where(later, doc.astype(U64) * U64(0x9E3779B97F4A7C15), h)
            yield _frame(h=h[keep].view(np.int64), c=pa.array(c[keep].view(np.int64), mask=later[keep]), doc=doc[keep], span=span[keep])

    return run


def _settle(length: int):
    """All anchor rows of some hashes: marks for later rows of a context (n = 0), and the first row of each context of
    an anchor that has n > 1 of them."""

    def run(batches):
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        rows = pa.Table.from_batches(held).combine_chunks()
        mark = np.asarray(rows["c"].is_null())
        h, c, doc, span = (rows[x].fill_null(0).to_numpy() for x in ("h", "c", "doc", "span"))
        if mark.any():
            yield _frame(h=h[mark], n=np.zeros(mark.sum(), np.int64), doc=doc[mark], span=span[mark])
        h, c, doc, span = h[~mark], c[~mark], doc[~mark], span[~mark]
        if not len(h):
            return
        order = np.lexsort((span, doc, c, h))
        h, c, doc, span = h[order], c[order], doc[order], span[order]
        anchor = np.r_[True, h[1:] != h[:-1]]
        new = anchor | np.r_[True, c[1:] != c[:-1]]
        first = np.maximum.accumulate(np.where(new, np.arange(len(new)), 0))
        later = ((doc != doc[first]) | (span != span[first])) & (span & 1023 >= length)
        yield _frame(h=h[later], n=np.zeros(later.sum(), np.int64), doc=doc[later], span=span[later])
        of = np.cumsum(anchor) - 1
        n = np.bincount(of[new], minlength=of[-1] + 1)[of]
        need = new & (n > 1)
        yield _frame(h=h[need], n=n[need].astype(np.int64), doc=doc[need], span=span[need])

    return run


def _contexts(batches):
    for b in batches:
        for doc, text, wanted in zip(b.column("doc").to_pylist(), b.column("raw").to_pylist(), b.column("wanted").to_pylist(), strict=True):
            cut = [(w["h"], w["n"], doc, at := w["span"] >> 20, w["span"] >> 10 & 1023, text[at : at + (w["span"] & 1023)]) for w in wanted]
            h, n, d, lo, place, ctx = zip(*cut, strict=True)
            yield pa.RecordBatch.from_arrays([*(pa.array(x, pa.int64()) for x in (h, n, d, lo, place)), pa.array(ctx, pa.binary())], ["h", "n", "doc", "lo", "place", "ctx"])


def _shared(side: list[bytes], group: np.ndarray, width: int) -> np.ndarray:
    """For each string the longest prefix that it has in common with another one of its group."""
    n = len(side)
    flat_side = np.frombuffer(b"".join(x.ljust(width, b"\0") for x in side), np.uint8).reshape(n, width)
    keyed = np.empty((n, width + 4), np.uint8)
    keyed[:, :4] = group.astype(">u4").view(np.uint8).reshape(n, 4)
    keyed[:, 4:] = flat_side
    order = np.argsort(keyed.view(f"S{width + 4}").ravel(), kind="stable")
    size = np.array([len(x) for x in side], np.int64)[order]
    same = flat_side[order[1:]] != flat_side[order[:-1]]
    common = np.where(same.any(1), same.argmax(1), width)
    common = np.minimum(common, np.minimum(size[1:], size[:-1]))
    common[group[order[1:]] != group[order[:-1]]] = -1
    out = np.full(n, -1, np.int64)
    np.maximum.at(out, order[1:], common)
    np.maximum.at(out, order[:-1], common)
    return out


def trim(rows: list[tuple[int, int, int, int, bytes]], length: int, k: int = ANCHOR) -> list[tuple[int, int, bytes]]:
    """(h, doc, lo, place, context) rows to (doc, lo, context), each cut to what it shares with others of its anchor.

    Contexts that share less than `length` bytes around the anchor go. Rows with zero bytes are left whole, since
    those serve as filling here.
    """
    if any(b"\0" in r[4] for r in rows) or length - k < 1:
        return [(doc, lo, ctx) for _, doc, lo, _, ctx in rows]
    group = np.unique([r[0] for r in rows], return_inverse=True)[1]
    right = _shared([c[p + k :] for *_, p, c in rows], group, length - k).tolist()
    left = _shared([c[:p][::-1] for *_, p, c in rows], group, length - k).tolist()
    return [(doc, lo + p - x, c[p - x : p + k + y]) for (_, doc, lo, p, c), x, y in zip(rows, left, right, strict=True) if x >= 0 and x + k + y >= length]


def _indexed(length: int):
    """Contexts sorted by anchor to marks, an index block at a time; an anchor's contexts stay in one block."""

    def flush(rows):
        rows = trim(rows, length)
        out = mark_block(rows, length) if rows else []
        return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (zip(*out, strict=True) if out else ([], [], []))], ["doc", "start", "end"])

    def run(batches):
        held, size, last = [], 0, None
        for b in batches:
            for row in zip(*(b.column(x).to_pylist() for x in ("h", "doc", "lo", "place", "ctx")), strict=True):
                if size >= BLOCK_BYTES and row[0] != last:
                    yield flush(held)
                    held, size = [], 0
                held.append(row)
                size += len(row[4])
                last = row[0]
        if held:
            yield flush(held)

    return run


def _windows(length: int):
    """Contexts of a crowded anchor to all their strings of `length` bytes."""

    def run(batches):
        for b in slices(batches, "ctx", 100_000):
            data, off = flat(b.column("ctx"))
            row = np.repeat(np.arange(b.num_rows), np.maximum(np.diff(off) - length + 1, 0))
            if not len(row):
                continue
            at = off[row] + np.arange(len(row)) - np.searchsorted(row, row)
            held = np.lib.stride_tricks.sliding_window_view(data, length)[at].tobytes()
            bounds = pa.py_buffer((np.arange(len(row) + 1, dtype=np.int32) * length).tobytes())
            strings = pa.Array.from_buffers(pa.binary(), len(row), [None, bounds, pa.py_buffer(held)])
            start = at - off[row] + b.column("lo").to_numpy()[row]
            yield _frame(string=strings, doc=b.column("doc").to_numpy()[row], start=start)

    return run


def _remove(batches):
    for b in batches:
        out = []
        for doc, text, marks in zip(b.column("doc_id").to_pylist(), b.column("raw").to_pylist(), b.column("marks").to_pylist(), strict=True):
            kept, spans = remove_spans(text, [(m["start"], m["end"]) for m in marks or ()])
            out.append((doc, len(text), len(text) - len(kept), len(spans), hashlib.sha256(kept).hexdigest(), kept))
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out, strict=True), (pa.int64(),) * 4 + (pa.string(), pa.binary()), strict=True)], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])


def remove_spans(text: bytes, spans: list[tuple[int, int]]) -> tuple[bytes, list[tuple[int, int]]]:
    """The text without the spans, and the spans merged where they overlap or touch."""
    merged: list[list[int]] = []
    for s, e in sorted((s, min(e, len(text))) for s, e in spans):
        if s >= e:
            continue
        if merged and s <= merged[-1][1]:
            merged[-1][1] = max(merged[-1][1], e)
        else:
            merged.append([s, e])
    kept, at = [], 0
    for s, e in merged:
        kept.append(text[at:s])
        at = e
    return b"".join([*kept, text[at:]]), [tuple(m) for m in merged]


def repeated_spans(docs: DataFrame, length: int = LENGTH, group: int = GROUP) -> DataFrame:
    """(doc, start, end): bytes of docs (d, text) covered by a string of `length` bytes that also starts earlier."""
    settled = stage(docs.mapInArrow(_parse(length), "h long, c long, doc long, span long").repartition("h").mapInArrow(_settle(length), "h long, n long, doc long, span long"))
    whole = settled.where("n = 0").select("doc", F.shiftright("span", 20).alias("start"), (F.shiftright("span", 20) + F.col("span").bitwiseAND(1023)).alias("end"))
    wanted = settled.where("n > 0").groupBy("doc").agg(F.collect_list(F.struct("h", "n", "span")).alias("wanted"))
    texts = docs.select(F.col("d").alias("doc"), F.col("text").cast("binary").alias("raw"))
    contexts = stage(wanted.join(texts, "doc").mapInArrow(_contexts, "h long, n long, doc long, lo long, place long, ctx binary"))
    near = contexts.where(F.col("n") <= group).select("h", "doc", "lo", "place", "ctx").repartition("h").sortWithinPartitions("h").mapInArrow(_indexed(length), "doc long, start long, end long")
    windows = contexts.where(F.col("n") > group).select("doc", "lo", "ctx").mapInArrow(_windows(length), "string binary, doc long, start long")
    first = windows.groupBy("string").agg(F.min(F.struct("doc", "start")).alias("first"))
    crowded = windows.join(first, "string").where(F.struct("doc", "start") > F.col("first")).select("doc", "start", (F.col("start") + length).alias("end"))
    return whole.union(near).union(crowded)


def remove_repeats(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept): each text without what an earlier text or place holds.

    Order is by doc_id, then start; a null doc_id comes first of all. Null texts count as empty. Texts shorter than
    `length` bytes stay as they are; very long ones are one row like any other. Rows that repeat a doc_id and a text
    count as one place, and each gets the same result; rows that repeat a doc_id with other texts are documents of
    their own, in the order of a hash of their texts. An empty table gives an empty result; other columns are ignored.
    """
    keyed = docs.select("doc_id", F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("d"), F.coalesce("text", F.lit("")).alias("text"))
    hashed = keyed.select("d", F.xxhash64("text").alias("h"))
    if not hashed.groupBy("d").agg(F.min("h").alias("lo"), F.max("h").alias("hi")).where("lo <> hi").isEmpty():
        # Ids are shared: a number that rises with (d, h) takes the place of d.
        places = hashed.distinct().repartitionByRange("d", "h").sortWithinPartitions("d", "h").withColumn("place", F.monotonically_increasing_id())
        keyed = keyed.withColumn("h", F.xxhash64("text")).join(stage(places), ["d", "h"]).select("doc_id", F.col("place").alias("d"), "text")
    marks = repeated_spans(keyed.select("d", "text"), length).groupBy(F.col("doc").alias("d")).agg(F.collect_list(F.struct("start", "end")).alias("marks"))
    rows = keyed.select("doc_id", "d", F.col("text").cast("binary").alias("raw")).join(marks, "d", "left").select("doc_id", "raw", "marks")
    return rows.mapInArrow(_remove, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")
