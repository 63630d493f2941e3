"""Benchmark decontamination: a broadcast hash set of test n-grams, scanned with rolling hashes and verified."""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubgraph.llm.common import BYTE_VALUES, LOWER, U64, Rolling, flat, in_arrow, mix, slices, stage

WINDOW = 10
#: Characters of benchmark text that may be broadcast; a larger benchmark is scanned in blocks of this size.
BLOCK_CHARS = 32_000_000
#: Bytes of text that are scanned at once.
SLICE = 1_000_000
WORD_BYTE = np.zeros(256, bool)
WORD_BYTE[0x30:0x3A] = WORD_BYTE[0x61:0x7B] = WORD_BYTE[0x80:] = True
_BYTES, _WORDS = Rolling(0x5851F42D4C957F2D), Rolling(0x14057B7EF767814F)


class Words:
    """All words of a block of texts: where each starts and ends, its document and its hash."""

    def __init__(self, data: np.ndarray, off: np.ndarray):
        self.low = LOWER[data]
        inside = WORD_BYTE[self.low]
        edge = np.zeros(len(inside) + 1, bool)
        edge[off] = True
        before, after = np.r_[False, inside[:-1]], np.r_[inside[1:], False]
        self.start = np.nonzero(inside & (~before | edge[:-1]))[0]
        self.end = np.nonzero(inside & (~after | edge[1:]))[0] + 1
        self.first = np.searchsorted(self.start, off)  # the first word of each document, and the total
        self.hash = _BYTES.spans(_BYTES.prefix(BYTE_VALUES[self.low]), self.start, self.end)
        self.prefix = _WORDS.prefix(self.hash)

    def windows(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Word position and hash of each run of n words of one document."""
        left = np.repeat(self.first[1:], np.diff(self.first)) - np.arange(len(self.start))
        at = np.nonzero(left >= n)[0]
        return at, mix(_WORDS.spans(self.prefix, at, at + n) + U64(n))

    def text(self, at: int, n: int) -> bytes:
        return b" ".join(self.low[self.start[i] : self.end[i]].tobytes() for i in range(at, at + n))


class BenchmarkIndex:
    """Window hashes of the items by window length, with their texts and items for the exact check."""

    def __init__(self, items: list[tuple[str, str]], window: int = WINDOW):
        texts = [t for _, t in items]
        words = Words(*flat(pa.array(texts, pa.string())))
        size = np.diff(words.first)
        self.found: dict[bytes, set[str]] = {}
        hashes: dict[int, list[np.ndarray]] = {}
        doc = np.repeat(np.arange(len(items)), size)
        for n in sorted({window, *size[(size > 0) & (size < window)].tolist()}):
            at, h = words.windows(n)
            if n < window:
                keep = size[doc[at]] == n
                at, h = at[keep], h[keep]
            for i in at.tolist():
                self.found.setdefault(words.text(i, n), set()).add(items[doc[i]][0])
            hashes[n] = np.unique(h)
        self.hashes = {n: h for n, h in hashes.items() if len(h)}
        self.bits = {n: np.zeros(1 << 20, bool) for n in self.hashes}
        for n, h in self.hashes.items():
            self.bits[n][(h & U64((1 << 20) - 1)).astype(np.int64)] = True

    def scan(self, words: Words) -> list[tuple[int, int, bytes]]:
        """(word position, window length, text) of every verified occurrence."""
        out = []
        for n, known in self.hashes.items():
            at, h = words.windows(n)
            maybe = np.nonzero(self.bits[n][(h & U64((1 << 20) - 1)).astype(np.int64)])[0]
            maybe = maybe[known[np.minimum(np.searchsorted(known, h[maybe]), len(known) - 1)] == h[maybe]]
            for i in at[maybe].tolist():
                if (text := words.text(i, n)) in self.found:
                    out.append((i, n, text))
        return out


@lru_cache(4)
def _index(key: str, items: tuple, window: int) -> BenchmarkIndex:
    return BenchmarkIndex(list(items), window)


def _scanner(items: list[tuple[str, str]], window: int, clean: bool):
    key = hashlib.sha256(repr(items).encode()).hexdigest()
    items = tuple(items)

    def run(batches):
        index = _index(key, items, window)
        for b in slices(batches, "text", SLICE):
            data, off = flat(b.column("text"))
            words = Words(data, off)
            n = b.num_rows
            hit, found = np.zeros(len(words.start) + 1, np.int32), [set() for _ in range(n)]
            for at, size, text in index.scan(words):
                hit[at] += 1
                hit[at + size] -= 1
                found[int(np.searchsorted(words.first, at, side="right")) - 1] |= index.found[text]
            hit = np.cumsum(hit)[:-1] > 0
            count = np.r_[0, np.cumsum(hit)]
            names = [sorted(x) for x in found]
            columns = {"doc_id": b.column("doc_id"), "n_words": pa.array(np.diff(words.first), pa.int64()), "items": pa.array(names, pa.list_(pa.string())), "hits": pa.array([np.nonzero(hit[s:e])[0].tolist() if count[e] > count[s] else [] for s, e in zip(words.first[:-1], words.first[1:], strict=True)], pa.list_(pa.int32()))}
            if clean:
                columns["text"] = pa.array([_without(b.column("text")[i].as_py(), data[off[i] : off[i + 1]], words, hit, i, off[i]) for i in range(n)], pa.string())
            yield pa.RecordBatch.from_pydict(columns)

    return run


def _without(text, raw, words, hit, i, base):
    """The text without its hit words and what stands between two of them."""
    s, e = words.first[i], words.first[i + 1]
    if text is None or not hit[s:e].any():
        return text
    keep = np.ones(len(raw), bool)
    for w in np.nonzero(hit[s:e])[0] + s:
        until = words.start[w + 1] if w + 1 < e and hit[w + 1] else words.end[w]
        keep[words.start[w] - base : until - base] = False
    return raw[keep].tobytes().decode("utf-8", "ignore")


def _cleaner():
    """Texts without the words at `hits`, positions of all blocks united."""

    def run(batches):
        for b in slices(batches, "text", SLICE):
            data, off = flat(b.column("text"))
            words = Words(data, off)
            hit = np.zeros(len(words.start), bool)
            at = b.column("hits")
            many = np.diff(at.offsets.to_numpy())
            hit[np.repeat(words.first[:-1], many) + at.flatten().to_numpy()] = True
            text = [_without(b.column("text")[i].as_py(), data[off[i] : off[i + 1]], words, hit, i, off[i]) for i in range(b.num_rows)]
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("doc_id", "n_words", "items", "hits")), pa.array(text, pa.string())], ["doc_id", "n_words", "items", "hits", "text"])

    return run


def _items(benchmark: DataFrame) -> tuple[DataFrame, int]:
    """(id, text) of the items, and the characters of all texts."""
    items = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("null")).alias("id"), F.coalesce("text", F.lit("")).alias("text"))
    return items, items.agg(F.coalesce(F.sum(F.length("text")), F.lit(0)).alias("n")).first().n


def _blocks(items: DataFrame, total: int, block_chars: int):
    """The items in lists of about block_chars characters at most, one at a time; a single list where all fit."""
    if total <= block_chars:
        yield [tuple(r) for r in items.orderBy("id", "text").collect()]
        return
    blocks = 1 + total // block_chars * 2
    placed = stage(items.withColumn("block", F.pmod(F.xxhash64("id", "text"), F.lit(blocks))))
    for k in range(blocks):
        yield [(r.id, r.text) for r in placed.where(F.col("block") == k).orderBy("id", "text").toLocalIterator()]


def decontaminate(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, *, clean: bool = False, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """(doc_id, n_words, n_hit, items) of each row of docs; with clean=True also the text without hit words.

    Words are runs of digits, ASCII letters (lower-cased) and characters beyond ASCII. A window is `window` words of
    an item in a row, or all words of a shorter item. Null or wordless texts have no words and no hits; items without
    words are passed over; a null item_id is listed as "null"; repeated items count once. Repeated documents each
    get their row. The items are broadcast up to block_chars characters; beyond that the items, cut into blocks of
    that size on the executors, each make a scan, and the hits of a row are united by a key written with it before.
    Very long texts are scanned whole; empty tables give no rows or no hits; other columns are ignored.
    """
    docs = docs.select("doc_id", "text")
    items, total = _items(benchmark)
    schema = "doc_id long, n_words long, items array<string>, hits array<int>"
    if total <= block_chars:
        found = docs.transform(in_arrow, _scanner(next(_blocks(items, total, block_chars)), window, clean), schema + ", text string" * clean)
    else:
        keyed = stage(docs.withColumn("row", F.monotonically_increasing_id()))
        parts = None
        for held in _blocks(items, total, block_chars):
            part = keyed.select(F.col("row").alias("doc_id"), "text").transform(in_arrow, _scanner(held, window, False), schema).withColumnRenamed("doc_id", "row")
            parts = part if parts is None else parts.unionByName(part)
        found = parts.groupBy("row").agg(F.max("n_words").alias("n_words"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("hits")))).alias("hits"))
        found = found.join(keyed if clean else keyed.drop("text"), "row").select("doc_id", "n_words", "items", "hits", *["text"] * clean)
        if clean:
            found = found.transform(in_arrow, _cleaner(), schema + ", text string")
    return found.withColumn("n_hit", F.size("hits").cast("long"))


def _sieve(items: list[tuple[str, str]], window: int):
    scan = _scanner(items, window, False)

    def run(batches):
        for b in slices(batches, "text", SLICE):
            (found,) = scan([b])
            yield b.filter(pc.equal(pc.list_value_length(found.column("hits")), 0))

    return run


def uncontaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, *, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """The rows of docs without a hit, with all their columns. Each row is judged by itself, whatever its doc_id; a
    benchmark of several blocks sieves what the block before has left."""
    items, total = _items(benchmark)
    out = docs
    for k, held in enumerate(_blocks(items, total, block_chars)):
        out = (stage(out) if k else out).transform(in_arrow, _sieve(held, window), docs.schema)
    return out


def contamination_report(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The digest of query op6."""
    return decontaminate(docs, benchmark).select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))
