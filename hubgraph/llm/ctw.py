"""Language-model scoring by context-tree weighting over bytes, beside a unigram baseline.

Each byte is eight binary decisions. For every decision each depth of context (the last 0 to DEPTH bytes) holds counts
of zeros and ones over all training text; Krichevsky-Trofimov estimates of all depths are mixed with the weights that
the context tree gives them. A text is read with DEPTH zero bytes before it and ends with byte 255, which UTF-8 never
holds, so its score is the log10 probability of the whole text, whatever stands before or after it in the table.

The tree is never in one place. Codes (context and byte) of all texts are counted on the executors and dealt by the
last OWNED bytes of their contexts; whoever owns a context builds the tree below it and mixes the deeper depths for each
of its codes. What is above, at most 256 ** (OWNED - 1) contexts, is summed up on the driver and mixed in last.

The baseline needs the count of every token of the corpus. Tokens go by a 64-bit hash, packed per slice of documents
and range of hashes: the owner of a range adds up the counts and sends back the sums for each document of the slice.
"""

from __future__ import annotations

import math
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubgraph.llm.common import BYTE_VALUES, LOWER, U64, Rolling, flat, id_crc, in_arrow, packed, slice_names, slices, stage, unpacked

DEPTH, OWNED, END = 5, 2, 255
#: Codes whose values may be broadcast (16 bytes each); with more, texts and the values that they need meet by bucket.
ENTRIES = 1 << 21
#: Bytes of text of a bucket, about; codes that are made into trees at once.
BUCKET_BYTES, FOREST = 8 << 20, 400_000
_BYTES = Rolling(0xC2B2AE3D27D4EB4F)
BLANK = np.zeros(256, bool)
BLANK[[0x20, *range(0x09, 0x0E)]] = True


def tokens(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash and document of each word of lower-cased texts laid end to end."""
    inside = ~BLANK[data]
    edge = np.zeros(len(data) + 1, bool)
    edge[off] = True
    start = np.nonzero(inside & (~np.r_[False, inside[:-1]] | edge[:-1]))[0]
    end = np.nonzero(inside & (~np.r_[inside[1:], False] | edge[1:]))[0] + 1
    return _BYTES.spans(_BYTES.prefix(BYTE_VALUES[data]), start, end), np.searchsorted(off, start, side="right") - 1


def _ask(ranges: int):
    """Documents to (range, slice, payload): the token counts of a slice by range of hashes."""
    shift = U64(64 - ranges.bit_length() + 1)

    def run(batches):
        names = slice_names()
        for b in slices(batches, "text", 4_000_000):
            data, off = flat(b.column("text"))
            h, doc = tokens(LOWER[data], off)
            order = np.argsort(h, kind="stable")
            h, doc = h[order], doc[order]
            token = np.r_[True, h[1:] != h[:-1]] if len(h) else np.zeros(0, bool)
            pair = np.nonzero(token | np.r_[True, doc[1:] != doc[:-1]] if len(h) else token)[0]
            n = np.diff(np.r_[pair, len(h)]).astype(np.uint32)
            new, doc, h = token[pair], doc[pair].astype(np.uint32), h[pair]
            ids, texts = b.column("d").to_numpy(), b.column("th").to_numpy()
            train = b.column("train").to_numpy(zero_copy_only=False).astype(np.uint8)
            words = np.bincount(doc, n, b.num_rows).astype(np.int64)
            name = next(names)
            rows = [(-1, name, packed(ids, texts, train, words))]
            cut = np.searchsorted(h, np.arange(1, ranges, dtype=np.uint64) << shift)
            for p, (s, e) in enumerate(zip([0, *cut.tolist()], [*cut.tolist(), len(h)], strict=True)):
                if s < e:
                    first = np.nonzero(new[s:e])[0].astype(np.uint32)
                    rows.append((p, name, packed(h[s:e][first], first, doc[s:e], n[s:e], train[doc[s:e]])))
            p, name, blob = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(p, pa.int32()), pa.array(name), pa.array(blob, pa.binary())], ["p", "slice", "blob"])

    return run


def _own(batches):
    """All payloads of some ranges of hashes, sorted by range: sums for each document of each slice, and the number of
    distinct training tokens. The document lists (range -1) pass through."""

    def settle(held):
        parts = [(name, unpacked(blob)) for name, blob in held]
        token = np.concatenate([p[0] for _, p in parts])
        of = []
        gained = []
        for _, (_, first, doc, n, train) in parts:
            t = np.repeat(np.arange(len(first)), np.diff(np.r_[first, len(doc)]))
            of.append(t)
            gained.append(np.bincount(t, n * train.astype(np.int64), len(first)))
        _, which = np.unique(token, return_inverse=True)
        count = np.bincount(which, np.concatenate(gained))
        value, known, at, out = np.log10(count + 0.1), count > 0, 0, []
        for (name, (_, first, doc, n, _)), t in zip(parts, of, strict=True):
            k = which[at + t]
            at += len(first)
            docs = np.unique(doc)
            s = np.bincount(doc, n * value[k], docs[-1] + 1)[docs]
            m = np.bincount(doc, n * known[k], docs[-1] + 1)[docs].astype(np.int64)
            out.append((name, packed(docs, s, m), 0))
        return [*out, (None, b"", int(known.sum()))]

    def batch(out):
        name, blob, distinct = zip(*out, strict=True)
        return pa.RecordBatch.from_arrays([pa.array(name, pa.string()), pa.array(blob, pa.binary()), pa.array(distinct, pa.int64())], ["slice", "blob", "distinct"])

    held, last = [], None
    for b in batches:
        for p, name, blob in zip(b.column("p").to_pylist(), b.column("slice").to_pylist(), b.column("blob").to_pylist(), strict=True):
            if p == -1:
                yield batch([(name, b"\0" + blob, 0)])
                continue
            if p != last and held:
                yield batch(settle(held))
                held = []
            last = p
            held.append((name, blob))
    if held:
        yield batch(settle(held))


def _gather(batches):
    """The answers to a slice, sorted by slice, to one row a document."""

    def row(held):
        lists = [unpacked(x[1:]) for x in held if x[:1] == b"\0"]
        ids, texts, train, words = lists[0]
        s, m = np.zeros(len(ids)), np.zeros(len(ids), np.int64)
        for x in held:
            if x[:1] != b"\0":
                docs, a, k = unpacked(x)
                s[docs] += a
                m[docs] += k
        return pa.RecordBatch.from_pydict({"d": pa.array(ids), "th": pa.array(texts), "train": pa.array(train.astype(bool)), "words": pa.array(words), "s": pa.array(s), "known": pa.array(m)})

    held, last = [], None
    for b in batches:
        for name, blob in zip(b.column("slice").to_pylist(), b.column("blob").to_pylist(), strict=True):
            if name != last and held:
                yield row(held)
                held = []
            last = name
            held.append(blob)
    if held:
        yield row(held)


def laid_out(data: np.ndarray, off: np.ndarray, depth: int = DEPTH) -> tuple[np.ndarray, np.ndarray]:
    """Codes (the context bytes, then the byte) of each byte and end of the texts, and offsets by text."""
    docs, n = len(off) - 1, len(data)
    doc = np.repeat(np.arange(docs), np.diff(off))
    wide = np.zeros(n + (depth + 1) * docs, U64)
    wide[np.arange(n) + (depth + 1) * doc + depth] = data
    wide[off[1:] + (depth + 1) * np.arange(docs) + depth] = END
    code = wide[depth:].copy()
    for k in range(1, depth + 1):
        code |= wide[depth - k : len(wide) - k] << U64(8 * k)
    keep = np.ones(len(code), bool)  # not the next text's padding
    at = off[1:-1] + (depth + 1) * np.arange(1, docs) - depth
    for i in range(depth):
        keep[at + i] = False
    return code[keep], off + np.arange(docs + 1)


def _count(batches):
    """Codes of all texts with their counts in training, merged over the slices of a partition until they are many."""
    code, n = np.zeros(0, U64), np.zeros(0, np.int64)

    def batch():
        return pa.RecordBatch.from_arrays([pa.array(code.astype(np.int64)), pa.array(n)], ["code", "n"])

    for b in slices(batches, "text", 2_000_000):
        data, off = flat(b.column("text"))
        own, at = laid_out(LOWER[data], off)
        train = np.repeat(b.column("train").to_numpy(zero_copy_only=False), np.diff(at))
        new, of = np.unique(own, return_inverse=True)
        more = np.bincount(of, train, len(new)).astype(np.int64)
        code, of = np.unique(np.r_[code, new], return_inverse=True)
        n = np.bincount(of, np.r_[n, more], len(code)).astype(np.int64)
        if len(code) > 1_000_000:
            yield batch()
            code, n = code[:0], n[:0]
    if len(code):
        yield batch()


class Lookup:
    """Places of known uint64 keys by open addressing, for many keys at once."""

    FREE = U64(0xFFFFFFFFFFFFFFFF)

    def __init__(self, keys: np.ndarray):
        bits = max(4, (2 * len(keys)).bit_length())
        self.shift, self.mask = U64(64 - bits), (1 << bits) - 1
        self.key, self.place = np.full(1 << bits, self.FREE), np.full(1 << bits, -1, np.int32)
        todo, slot = np.arange(len(keys), dtype=np.int32), self._slot(keys)
        while len(todo):
            free = self.place[slot] < 0
            self.place[slot[free]] = todo[free]
            won = self.place[slot] == todo
            self.key[slot[won]] = keys[todo[won]]
            todo, slot = todo[~won], slot[~won] + 1 & self.mask

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return (keys * U64(0x9E3779B97F4A7C15) >> self.shift).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        slot = self._slot(keys)
        got = self.key[slot]
        out = np.where(got == keys, self.place[slot], np.int32(-1))
        todo = np.nonzero((got != keys) & (got != self.FREE))[0]
        slot = slot[todo]
        while len(todo):
            slot = slot + 1 & self.mask
            got = self.key[slot]
            hit = got == keys[todo]
            out[todo[hit]] = self.place[slot[hit]]
            go = ~hit & (got != self.FREE)
            todo, slot = todo[go], slot[go]
        return out


def _log_gamma(x: np.ndarray) -> np.ndarray:
    shift = np.zeros_like(x)
    for _ in range(8):  # Stirling's series holds from 8 on
        low = x < 8
        shift = np.where(low, shift - np.log(np.where(low, x, 1)), shift)
        x = np.where(low, x + 1, x)
    return shift + (x - 0.5) * np.log(x) - x + 0.5 * math.log(2 * math.pi) + 1 / (12 * x) - 1 / (360 * x**3) + 1 / (1260 * x**5)


class ContextTree:
    """The depths low to depth of weighted context trees of the 255 binary decisions of a byte.

    A node's key is its context, then in 8 bits the higher bits of the byte behind a one. `below` is the log of the
    weighted probability of what lies under each node of the greatest depth, None where that depth has the leaves.
    """

    def __init__(self, code: np.ndarray, n: np.ndarray, depth: int = DEPTH, low: int = 0):
        """From counts of (context, byte) codes; those that count nothing are passed over."""
        code, n = code.astype(np.int64)[n > 0], n.astype(np.float64)[n > 0]
        key, of = np.unique(np.concatenate([self.node(code, depth, i) for i in range(8)]), return_inverse=True)
        bit, every = np.concatenate([code >> i & 1 for i in range(8)]), np.tile(n, 8)
        self._weigh(key, *(np.bincount(of, every * (bit == v), len(key)) for v in (0, 1)), depth, low)

    @classmethod
    def above(cls, key: np.ndarray, zeros: np.ndarray, ones: np.ndarray, below: np.ndarray, depth: int) -> ContextTree:
        """The depths from `depth` up, from its nodes and what hangs under them."""
        tree = cls.__new__(cls)
        tree._weigh(key, zeros, ones, depth, 0, below)
        return tree

    def _weigh(self, key, zeros, ones, depth: int, low: int, below=None):
        self.depth, self.low, self.levels = depth, low, {}
        for d in range(depth, low - 1, -1):
            if d < depth:
                key, zeros, ones, below = self._folded(key, zeros, ones, log_pw, d)
            log_pe = _log_gamma(zeros + 0.5) + _log_gamma(ones + 0.5) - math.log(math.pi) - _log_gamma(zeros + ones + 1)
            log_pw = log_pe if below is None else np.logaddexp(log_pe, below) - math.log(2)
            self.levels[d] = key, zeros, ones, np.ones(len(key)) if below is None else np.exp(log_pe - math.log(2) - log_pw)
        self.log_pw = log_pw

    @staticmethod
    def node(code: np.ndarray, d: int, bit: int) -> np.ndarray:
        context = code >> 8 & (1 << 8 * d) - 1
        return context << 8 | (1 << 7 - bit) | (code & 255) >> bit + 1

    @staticmethod
    def _folded(key, zeros, ones, log_pw, d: int):
        key, of = np.unique((key >> 8 & (1 << 8 * d) - 1) << 8 | key & 255, return_inverse=True)
        return key, *(np.bincount(of, x, len(key)) for x in (zeros, ones, log_pw))

    def folded(self):
        """Keys, zeros, ones and log probabilities of all that hangs under each node of the depth above the lowest."""
        key, zeros, ones, _ = self.levels[self.low]
        return self._folded(key, zeros, ones, self.log_pw, self.low - 1)

    def mixture(self, code: np.ndarray, p: np.ndarray | None = None) -> np.ndarray:
        """Probabilities of the eight bits of each code's byte, mixed over the depths; p is what deeper ones give."""
        code = code.astype(np.int64)
        p = np.full((len(code), 8), 0.5) if p is None else p.copy()
        for i in range(8):
            one = (code >> i & 1).astype(bool)
            for d in range(self.depth, self.low - 1, -1):
                keys, zeros, ones, weight = self.levels[d]
                if not len(keys):
                    continue
                want = self.node(code, d, i)
                at = np.minimum(np.searchsorted(keys, want), len(keys) - 1)
                a0, a1, w = zeros[at], ones[at], weight[at]
                kt = (np.where(one, a1, a0) + 0.5) / (a0 + a1 + 1)
                p[:, i] = np.where(keys[at] == want, w * kt + (1 - w) * p[:, i], p[:, i])
        return p

    def log10(self, code: np.ndarray) -> np.ndarray:
        """log10 probability of each code's byte in its context."""
        return np.log10(self.mixture(code)).sum(1)


def _grow(batches):
    """Codes sorted by the contexts that a task owns: for each code the bits as the depths from OWNED on mix them (p),
    and for each node above (code null) what hangs under it."""

    def settle(code, n):
        tree = ContextTree(code, n, DEPTH, OWNED)
        p, (key, zeros, ones, below) = tree.mixture(code), tree.folded()
        yield _batch([code, None, None, None, None, [x.tobytes() for x in p]])
        yield _batch([None, key, zeros, ones, below, None])

    def _batch(columns):
        size = max(len(x) for x in columns if x is not None)
        types = (pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64(), pa.binary())
        return pa.RecordBatch.from_arrays([pa.nulls(size, t) if x is None else pa.array(x, t) for x, t in zip(columns, types, strict=True)], ["code", "key", "zeros", "ones", "below", "p"])

    code, n = np.zeros(0, np.int64), np.zeros(0, np.int64)
    for b in batches:
        code, n = np.r_[code, b.column("code").to_numpy()], np.r_[n, b.column("n").to_numpy()]
        if len(code) > FOREST:
            owner = code >> 8 & (1 << 8 * OWNED) - 1
            cut = int(np.nonzero(owner != owner[-1])[0][-1] + 1) if owner[0] != owner[-1] else 0
            if cut:
                yield from settle(code[:cut], n[:cut])
                code, n = code[cut:], n[cut:]
    if len(code):
        yield from settle(code, n)


def code_values(docs: DataFrame) -> DataFrame:
    """(code, value): the log10 probability of each code that docs (text, train) hold, learned from the rows to train."""
    counts = docs.select("text", "train").transform(in_arrow, _count, "code long, n long").groupBy("code").agg(F.sum("n").alias("n"))
    owner = F.shiftright("code", 8).bitwiseAND((1 << 8 * OWNED) - 1)
    grown = counts.repartition(owner).sortWithinPartitions(owner, "code")
    grown = stage(grown.transform(in_arrow, _grow, "code long, key long, zeros double, ones double, below double, p binary"))
    above = grown.where("code is null").groupBy("key").agg(*(F.sum(c).alias(c) for c in ("zeros", "ones", "below"))).orderBy("key").toArrow()
    key, zeros, ones, below = (above[c].to_numpy() for c in ("key", "zeros", "ones", "below"))
    top = ContextTree.above(key, zeros, ones, below, OWNED - 1)

    def finish(batches):
        for b in batches:
            code, p = b.column("code").to_numpy(), np.frombuffer(b"".join(b.column("p").to_pylist())).reshape(-1, 8)
            yield pa.RecordBatch.from_arrays([b.column("code"), pa.array(np.log10(top.mixture(code, p)).sum(1))], ["code", "value"])

    return stage(grown.where("code is not null").select("code", "p").transform(in_arrow, finish, "code long, value double"))


class Values:
    """The values of codes, in an order that makes look-ups quick."""

    def __init__(self, code: np.ndarray, value: np.ndarray):
        self.known, self.value = Lookup(code.astype(U64)), value

    def score(self, data: np.ndarray, off: np.ndarray) -> np.ndarray:
        """log10 probability of each text; all its codes have values."""
        code, at = laid_out(data, off)
        return np.add.reduceat(self.value[self.known.find(code)], at[:-1]) if len(off) > 1 else np.zeros(0)


_MADE: dict[str, Values] = {}  # a worker's own, for the tasks that it runs


def _scored(b, values: Values):
    data, off = flat(b.column("text"))
    score = values.score(LOWER[data], off)
    return pa.RecordBatch.from_arrays([*(b.column(c) for c in ("doc_id", "d", "th", "train")), pa.array(score), pa.array(np.diff(off))], ["doc_id", "d", "th", "train", "score", "bytes"])


SCORED = "doc_id long, d long, th long, train boolean, score double, bytes long"


def _asked_codes(batches):
    """Texts sorted by bucket to the distinct codes of each bucket."""
    held, code = None, np.zeros(0, U64)

    def batch():
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(code), held)), pa.array(code.astype(np.int64))], ["bucket", "code"])

    for b in slices(batches, "text", 2_000_000):
        bucket = b.column("bucket").to_numpy()
        cut = [0, *(np.nonzero(np.diff(bucket))[0] + 1).tolist(), len(bucket)]
        for s, e in zip(cut[:-1], cut[1:], strict=True):
            if bucket[s] != held and len(code):
                yield batch()
                code = code[:0]
            held = bucket[s]
            data, off = flat(b.column("text").slice(s, e - s))
            code = np.union1d(code, laid_out(LOWER[data], off)[0])
    if len(code):
        yield batch()


def _score_buckets(batches):
    """Rows sorted by bucket, in each the values first and then the texts."""
    held, code, value, values = None, [], [], None
    for b in slices(batches, "text", 2_000_000):
        bucket = b.column("bucket").to_numpy()
        cut = [0, *(np.nonzero(np.diff(bucket))[0] + 1).tolist(), len(bucket)]
        for s, e in zip(cut[:-1], cut[1:], strict=True):
            if bucket[s] != held:
                held, code, value, values = bucket[s], [], [], None
            part = b.slice(s, e - s)
            given = np.asarray(part.column("code").is_valid())
            code.append(part.column("code").filter(pa.array(given)).to_numpy())
            value.append(part.column("value").filter(pa.array(given)).to_numpy())
            texts = part.filter(pa.array(~given))
            if texts.num_rows:
                values = values or Values(np.concatenate(code), np.concatenate(value))
                yield _scored(texts, values)


def score_by_tree(docs: DataFrame, entries: int = ENTRIES) -> DataFrame:
    """docs (doc_id, d, th, text, train) with the score of each text. Up to `entries` values are broadcast; beyond that
    texts are dealt into buckets, and each bucket is sent the values of its codes. Both ways give the same scores."""
    spark, values = docs.sparkSession, code_values(docs)
    if values.count() <= entries:
        held = values.toArrow()
        shared = spark.sparkContext.broadcast((held["code"].to_numpy(), held["value"].to_numpy()))
        name = uuid.uuid4().hex

        def run(batches):
            for b in slices(batches, "text", 2_000_000):
                if name not in _MADE:
                    _MADE.clear()
                    _MADE[name] = Values(*shared.value)
                yield _scored(b, _MADE[name])

        return docs.select("doc_id", "d", "th", "text", "train").transform(in_arrow, run, SCORED)
    size = docs.agg(F.sum(F.length("text"))).first()[0]
    dealt = docs.withColumn("bucket", F.pmod(F.xxhash64("th", "d"), F.lit(size // BUCKET_BYTES + 1)))
    dealt = stage(dealt.repartition("bucket").sortWithinPartitions("bucket"))
    asked = dealt.repartition("bucket").sortWithinPartitions("bucket").select("bucket", "text").transform(in_arrow, _asked_codes, "bucket long, code long")
    told = asked.join(values, "code").select("bucket", "code", "value")
    empty = lambda t, n: F.lit(None).cast(t).alias(n)
    both = told.select("bucket", "code", "value", empty("long", "doc_id"), empty("long", "d"), empty("long", "th"), empty("string", "text"), empty("boolean", "train"))
    both = both.unionByName(dealt.select("bucket", empty("long", "code"), empty("double", "value"), "doc_id", "d", "th", "text", "train"))
    return both.repartition("bucket").sortWithinPartitions("bucket", F.col("code").isNull()).transform(in_arrow, _score_buckets, SCORED)


def score_texts(docs: DataFrame, train, entries: int = ENTRIES) -> DataFrame:
    """(doc_id, train, n_tokens, n_known, train_tokens, base_score, score, bits_per_byte) of docs (doc_id, text, ...).

    `train` is a condition on docs: all rows that meet it are learned from. Null texts count as empty: one token, the
    end. A word or byte that was never seen in training has its smoothed share. Repeated rows each get their row and
    count each in training; with no training row every token has the same share. An empty table gives an empty result.
    Very long texts are rows like any other and are read whole; other columns of docs are ignored.
    """
    spark = docs.sparkSession
    docs = docs.select("doc_id", F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("d"), F.coalesce("text", F.lit("")).alias("text"), F.coalesce(train, F.lit(False)).alias("train"))
    docs = docs.withColumn("th", F.xxhash64("text"))
    ranges = 1 << (4 * int(spark.conf.get("spark.sql.shuffle.partitions"))).bit_length()
    asked = docs.select("d", "th", "text", "train").transform(in_arrow, _ask(ranges), "p int, slice string, blob binary")
    answers = stage(asked.repartition("p", F.when(F.col("p") < 0, F.col("slice"))).sortWithinPartitions("p").transform(in_arrow, _own, "slice string, blob binary, distinct long"))
    counted = stage(answers.where("slice is not null").select("slice", "blob").repartition("slice").sortWithinPartitions("slice").transform(in_arrow, _gather, "d long, th long, train boolean, words long, s double, known long"))
    totals = counted.where("train").agg(F.coalesce(F.sum(F.col("words") + 1), F.lit(0)).alias("n"), F.count("*").alias("ends")).first()
    distinct = answers.agg(F.coalesce(F.sum("distinct"), F.lit(0)).alias("v")).first().v + (totals.ends > 0)
    # Rows that repeat both id and text answer once each: their sums are shared out again.
    base = counted.groupBy("d", "th").agg(*(F.expr(f"sum({c}) / count(*)").alias(c) for c in ("words", "s", "known")))
    scored = score_by_tree(docs, entries)
    n_tokens = (F.round("words") + 1).cast("long")
    scale = math.log10(totals.n + 0.1 * (distinct + 1))
    end = math.log10(totals.ends + 0.1)
    return scored.join(base, ["d", "th"]).select("doc_id", "train", n_tokens.alias("n_tokens"), (F.round("known") + int(totals.ends > 0)).cast("long").alias("n_known"), F.lit(totals.n).cast("long").alias("train_tokens"), (F.col("s") + end - n_tokens * F.lit(scale)).alias("base_score"), "score", (-F.col("score") / math.log10(2) / (F.col("bytes") + 1)).alias("bits_per_byte"))


def scoring_report(docs: DataFrame) -> DataFrame:
    """The digest of query op9: nine folds of ten are learned from, all documents are scored."""
    held_out = id_crc("doc_id") % 10 == 0
    out = score_texts(docs, ~held_out)
    return out.select("doc_id", held_out.alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")
