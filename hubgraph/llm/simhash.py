"""SimHash near-duplicates found through fuzzy keys of the binary Golay code.

A 64-bit fingerprint is cut into segments of 23, 23 and 18 bits (the last one padded to 23). Two fingerprints at
distance 2 or less always have an ordered pair of neighbouring segments (0-1, 1-2 or 2-0) with no error in the first
and at most one in the second. The first segment is used as it is. The second is decoded with the perfect (23,12)
code: every word lies within 3 of one codeword, so two words at distance 1 share a codeword within radius 4 of both.
Listing the codewords within radius 4 gives each fingerprint about five keys a pair. Rows that share a key are
verified by their exact distance; inside a key only a spanning forest of the true links is passed on.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubgraph.llm.common import LOWER, Rolling, flat, in_arrow, mix, packed, slice_names, slices, stage, unpacked
from hubgraph.llm.components import connected_components
from hubgraph.llm.ctw import tokens

GENERATOR = 0b101011100011  # generator polynomial of the (23,12) Golay code
SHARE, SALTS = 512, 64
WIDTH, SEGMENTS = 23, ((0, 23), (23, 23), (46, 18))


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """64-bit SimHash over word shingles; null, empty or blank text gives 0."""
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    joined, digest = b" ".join(words), xxhash.xxh64_intdigest
    if len(words) <= shingle:
        h = [digest(joined, 42)]
    else:
        ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
        starts = [0, *(ends[:-1] + 1).tolist()]
        view = memoryview(joined)
        h = [digest(view[a:b], 42) for a, b in zip(starts, ends[shingle - 1 :].tolist(), strict=False)]
    bits = np.unpackbits(np.array(h, "<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    on = 2 * bits.sum(0, dtype=np.int64) > len(h)
    return int(np.packbits(on, bitorder="little").view("<u8")[0])


@lru_cache(1)
def _syndromes() -> tuple[np.ndarray, np.ndarray]:
    """For each 11-bit syndrome the error of weight 3 or less that causes it; patterns of weight 1 to 4 of 23 bits."""
    words = np.arange(1 << WIDTH, dtype=np.uint32)
    light = words[np.bitwise_count(words) <= 4]
    error = np.zeros(1 << 11, np.uint32)
    few = light[np.bitwise_count(light) <= 3]
    error[_remainder(few)] = few
    return error, light


def _remainder(words: np.ndarray) -> np.ndarray:
    r = words.astype(np.uint32)
    for at in range(WIDTH - 1, 10, -1):
        r = np.where(r >> np.uint32(at) & np.uint32(1), r ^ np.uint32(GENERATOR << (at - 11)), r)
    return r


@lru_cache(1)
def _near() -> tuple[np.ndarray, np.ndarray]:
    """Errors of weight 4 or less in order of syndrome, and where each syndrome starts: word ^ error is a codeword."""
    _, light = _syndromes()
    syndrome = _remainder(light)
    order = np.argsort(syndrome, kind="stable")
    return light[order], np.searchsorted(syndrome[order], np.arange((1 << 11) + 1))


def decode(words: np.ndarray) -> np.ndarray:
    """Index (12 bits) of the nearest codeword of each 23-bit word."""
    error, _ = _syndromes()
    return (words.astype(np.uint32) ^ error[_remainder(words)]) >> np.uint32(11)


def codeword_keys(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, codeword index) of every codeword within radius 4 of each word."""
    errors, start = _near()
    s = _remainder(words)
    n = start[s + 1] - start[s]
    row = np.repeat(np.arange(len(words)), n)
    at = np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(start[s], n)
    return row, (words.astype(np.uint32)[row] ^ errors[at]) >> np.uint32(11)


def fuzzy_keys(prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, 64-bit key) for uint64 fingerprints: which pair, one exact segment, one codeword of the other."""
    rows, keys = [], []
    part = [(prints >> np.uint64(a) & np.uint64((1 << n) - 1)) for a, n in SEGMENTS]
    for k in range(3):
        row, word = codeword_keys(part[(k + 1) % 3])
        rows.append(row)
        keys.append(np.uint64(k) << np.uint64(40) | part[k][row] << np.uint64(12) | word.astype(np.uint64))
    return np.concatenate(rows), np.concatenate(keys)


def forest(prints: np.ndarray, radius: int = 2, block: int = 1024) -> tuple[np.ndarray, np.ndarray]:
    """Links that span the components of distinct fingerprints under Hamming distance <= radius.

    Up to 4 blocks all distances are taken; more rows look their neighbours up by flipping bits, which is linear.
    """
    n, parent, out = len(prints), list(range(len(prints))), []

    def root(i):
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    def link(pairs):
        for i, j in pairs:
            a, b = root(i), root(j)
            if a != b:
                parent[max(a, b)] = min(a, b)
                out.append((i, j))

    if n <= 4 * block:
        for at in range(0, n, block):
            near = np.bitwise_count(prints[at : at + block, None] ^ prints[None, :]) <= radius
            i, j = np.nonzero(np.triu(near, 1 + at))
            link(zip((i + at).tolist(), j.tolist(), strict=True))
    else:
        order = np.argsort(prints)
        ranked, one = prints[order], [1 << b for b in range(64)]
        masks = [0] if radius < 1 else one if radius < 2 else one + [one[a] | one[b] for a in range(64) for b in range(a)]
        for m in masks:
            other = ranked ^ np.uint64(m)
            at = np.minimum(np.searchsorted(ranked, other), n - 1)
            hit = np.nonzero((ranked[at] == other) & (ranked < other))[0]
            link(zip(order[hit].tolist(), order[at[hit]].tolist(), strict=True))
    i, j = np.array(out, np.int64).reshape(-1, 2).T
    return i, j


def _prints(batches):
    for b in batches:
        fp = np.array([fingerprint(t) for t in b.column("text").to_pylist()], np.uint64).view(np.int64)
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(fp, pa.int64())], ["doc_id", "fp"])


def _keys(batches):
    for b in batches:
        fp = b.column("fp").to_numpy()
        row, key = fuzzy_keys(fp.view(np.uint64))
        yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(fp[row])], ["key", "fp"])


def _links(batches):
    """Rows arrive sorted by key; a key may span batches."""
    held_k, held_f = np.zeros(0, np.int64), np.zeros(0, np.int64)

    def emit(k, f):
        cut = np.r_[0, np.nonzero(np.diff(k))[0] + 1, len(k)]
        start, size = cut[:-1], np.diff(cut)
        two = start[size == 2]
        two = two[np.bitwise_count((f[two] ^ f[two + 1]).view(np.uint64)) <= 2]
        a, b = [f[two]], [f[two + 1]]
        for s, n in zip(start[size > 2].tolist(), size[size > 2].tolist(), strict=True):
            i, j = forest(f[s : s + n].view(np.uint64))
            a.append(f[s : s + n][i])
            b.append(f[s : s + n][j])
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(a)), pa.array(np.concatenate(b))], ["a", "b"])

    for batch in batches:
        k, f = np.r_[held_k, batch.column("key").to_numpy()], np.r_[held_f, batch.column("fp").to_numpy()]
        if not len(k):
            continue
        cut = np.searchsorted(k, k[-1])
        if cut:
            yield emit(k[:cut], f[:cut])
        held_k, held_f = k[cut:], f[cut:]
    if len(held_k):
        yield emit(held_k, held_f)


def salted_join(rows: DataFrame, groups: DataFrame, by: str, spark) -> DataFrame:
    """rows joined with groups, one row for each value of `by` with the number k of rows that hold it.

    Values that more than one row in SHARE holds, of which there are fewer than SHARE, are dealt over SALTS keys.
    """
    total = rows.count()
    hot = spark.createDataFrame([(r[0],) for r in groups.where(F.col("k") > max(1, total // SHARE)).select(by).collect()], groups.select(by).schema).withColumn("hot", F.lit(True))
    salt = F.when(F.col("hot"), F.monotonically_increasing_id() % SALTS).otherwise(0)
    left = rows.join(F.broadcast(hot), by, "left").withColumn("salt", salt).drop("hot")
    salts = F.when(F.col("hot"), F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))).otherwise(F.array(F.lit(0).cast("long")))
    right = groups.join(F.broadcast(hot), by, "left").withColumn("salt", F.explode(salts)).drop("hot", "k")
    return left.join(right, [by, "salt"]).drop("salt")


def simhash_components(docs: DataFrame) -> DataFrame:
    """(doc_id, fp, component_id) of every row of docs (doc_id, text, ...).

    Fingerprints of 2 or fewer differing bits link; component_id is the smallest doc_id that can be reached.
    Null, empty and blank texts have fingerprint 0 and link like any other. A null doc_id is kept and never becomes
    a component_id unless nothing else is there. Repeated rows stay. An empty table gives an empty result; other
    columns are ignored. Copies meet as one fingerprint, so no group of copies is ever expanded.
    """
    spark = docs.sparkSession
    prints = stage(docs.select("doc_id", "text").transform(in_arrow, _prints, "doc_id long, fp long"))
    unique = stage(prints.groupBy("fp").agg(F.min("doc_id").alias("low"), F.count("*").alias("k")))
    keyed = unique.select("fp").transform(in_arrow, _keys, "key long, fp long")
    links = keyed.repartition("key").sortWithinPartitions("key", "fp").transform(in_arrow, _links, "a long, b long")
    labels = connected_components(links)
    owner = unique.join(labels.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "low", "k", F.coalesce("label", "fp").alias("label"))
    lowest = owner.groupBy("label").agg(F.min("low").alias("component_id"))
    of_print = owner.join(lowest, "label").select("fp", "k", "component_id")
    return salted_join(prints, of_print, "fp", spark).select("doc_id", "fp", "component_id")


def near_duplicate_report(docs: DataFrame) -> DataFrame:
    """The digest of query op5."""
    return simhash_components(docs).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


SHINGLE, BINS, PIECE = 5, 256, 200_000
#: Bytes of text whose shingles are counted together, and of a range of hashes; rows of a key compared in one task.
SLICE, RANGE_BYTES, HOT = 2_000_000, 24_000_000, 4096
KEPT_BITS = 40  # of a shingle's hash, where shingles are counted and meet
_GRAMS = Rolling(0xA0761D6478BD642F)


def row_key(doc_id: str = "doc_id", text: str = "text"):
    """64-bit key of a row: rows share it if they are equal in id (null is a value) and text."""
    return F.xxhash64(F.coalesce(F.col(doc_id).cast("string"), F.lit("null")), F.coalesce(F.col(text), F.lit("")))


def _shingles(col):
    """Shingle hashes of a text column in reading order, and where each text's begin; a text of fewer words is one shingle."""
    data, off = flat(col)
    word, doc = tokens(LOWER[data], off)
    first = np.searchsorted(doc, np.arange(len(col) + 1))
    prefix = _GRAMS.prefix(word)
    size = np.diff(first)
    starts = np.maximum(size - SHINGLE + 1, np.minimum(size, 1))
    row = np.repeat(np.arange(len(col)), starts)
    at = first[row] + np.arange(len(row)) - np.repeat(np.cumsum(starts) - starts, starts)
    return _GRAMS.spans(prefix, at, np.minimum(at + SHINGLE, first[row + 1])), np.r_[0, np.cumsum(starts)]


def _prefix_size(n: np.ndarray) -> np.ndarray:
    """Two sets of similarity 0.8 share one of so many first shingles under any one order of all shingles."""
    return np.where(n > 0, n + (-4 * n // 5) + 1, 0)


def _ask(ranges: int):
    """Texts to (range, slice, payload): the distinct shingles of a slice's documents by range of hashes, and in range
    -1 of each document key, id, set size, digest of the set and counts of the set by BINS."""
    rest = KEPT_BITS - (ranges.bit_length() - 1)

    def run(batches):
        names = slice_names()
        for b in slices(batches, "text", SLICE):
            h, bound = _shingles(b.column("text"))
            row = np.repeat(np.arange(b.num_rows), np.diff(bound))
            order = np.lexsort((h, row))
            h, row = h[order], row[order]
            new = np.r_[True, (h[1:] != h[:-1]) | (row[1:] != row[:-1])] if len(h) else np.zeros(0, bool)
            h, row = h[new], row[new]
            n = np.bincount(row, minlength=b.num_rows)
            at = np.r_[0, np.cumsum(n)].tolist()
            counts = np.bincount(row * BINS + (h >> np.uint64(56)).astype(np.int64), minlength=BINS * b.num_rows)
            sign = np.frombuffer(b"".join(xxhash.xxh3_128_digest(h[s:e].tobytes()) for s, e in zip(at[:-1], at[1:], strict=True)), np.uint8)
            given = b.column("doc_id").is_valid().to_numpy(zero_copy_only=False).astype(np.uint8)
            own = (b.column("key").to_numpy(), b.column("doc_id").fill_null(0).to_numpy(), given, n, sign, np.minimum(counts, 255).astype(np.uint8))
            name = next(names)
            rows = [(-1, name, packed(*own))]
            h = h >> np.uint64(64 - KEPT_BITS)
            order = np.argsort(h, kind="stable")
            h, row = h[order], row[order].astype(np.uint16 if b.num_rows < 1 << 16 else np.uint32)
            cut = np.searchsorted(h, np.arange(ranges + 1, dtype=np.uint64) << np.uint64(rest)).tolist()
            for p in range(ranges):
                s, e = cut[p], cut[p + 1]
                if s < e:
                    low = (h[s:e] - np.uint64(p << rest)).astype(np.uint32)
                    rows.append((p, name, packed(np.diff(low, prepend=np.uint32(0)), row[s:e])))
            p, name, blob = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(p, pa.int32()), pa.array(name), pa.array(blob, pa.binary())], ["p", "slice", "blob"])

    return run


def _own(ranges: int):
    """All payloads of some ranges, sorted by range: for each slice its documents' shingles that other documents hold
    too, and how many do. The document lists (range -1) pass through."""
    rest = KEPT_BITS - (ranges.bit_length() - 1)

    def settle(p, held):
        parts = [(name, *unpacked(blob)) for name, blob in held]
        low = [np.cumsum(d, dtype=np.uint32) for _, d, _ in parts]
        _, which, many = np.unique(np.concatenate(low), return_inverse=True, return_counts=True)
        many, at, out = many[which], 0, []
        for (name, _, row), v in zip(parts, low, strict=True):
            df = many[at : at + len(v)]
            at += len(v)
            if (df > 1).any():
                out.append((name, packed(row[df > 1], v[df > 1].astype(np.uint64) + np.uint64(p << rest), df[df > 1].astype(np.uint32))))
        return out

    def batch(out):
        name, blob = zip(*out, strict=True) if out else ([], [])
        return pa.RecordBatch.from_arrays([pa.array(name, pa.string()), pa.array(blob, pa.binary())], ["slice", "blob"])

    def run(batches):
        held, last = [], None
        for b in batches:
            for p, name, blob in zip(*(b.column(c).to_pylist() for c in ("p", "slice", "blob")), strict=True):
                if p == -1:
                    yield batch([(name, b"\0" + blob)])
                    continue
                if p != last and held:
                    yield batch(settle(last, held))
                    held = []
                last = p
                held.append((name, blob))
        if held:
            yield batch(settle(last, held))

    return run


PROFILE = "key long, doc_id long, n int, sign binary, hist binary, h array<long>, pos array<int>, df array<int>"


def _gather(batches):
    """The answers to a slice, sorted by slice, to one row a document: its profile, and those of its prefix's shingles
    that others hold too. The order of shingles is by rising number of documents, then by hash; shingles of one
    document alone come first and can meet nothing, so they only take up places."""

    def rows(held):
        key, doc_id, given, n, sign, hist = unpacked(next(x for x in held if x[:1] == b"\0")[1:])
        parts = [unpacked(x) for x in held if x[:1] != b"\0"]
        row, h, df = (np.concatenate(x) for x in zip(*parts, strict=True)) if parts else (np.zeros(0, np.int64),) * 3
        order = np.lexsort((h, df, row))
        row, h, df = row[order].astype(np.int64), h[order].astype(np.int64), df[order]
        shared = np.bincount(row, minlength=len(key))
        pos = np.arange(len(row)) - np.searchsorted(row, row) + (n - shared)[row]
        use = pos < _prefix_size(n)[row]
        row, h, df, pos = row[use], h[use], df[use], pos[use]
        at = pa.array(np.r_[0, np.cumsum(np.bincount(row, minlength=len(key)))], pa.int32())
        lists = [pa.ListArray.from_arrays(at, pa.array(x, t)) for x, t in ((h, pa.int64()), (pos, pa.int32()), (df, pa.int32()))]
        cut = lambda x, w: pa.array([x[i : i + w].tobytes() for i in range(0, w * len(key), w)], pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(key), pa.array(doc_id, mask=given == 0), pa.array(n, pa.int32()), cut(sign, 16), cut(hist, BINS), *lists], ["key", "doc_id", "n", "sign", "hist", "h", "pos", "df"])

    held, last = [], None
    for b in batches:
        for name, blob in zip(b.column("slice").to_pylist(), b.column("blob").to_pylist(), strict=True):
            if name != last and held:
                yield rows(held)
                held = []
            last = name
            held.append(blob)
    if held:
        yield rows(held)


def _prefix_rows(hot: int):
    """A row of each shingle of a prefix. A hot one is dealt in blocks of documents, one row for each pair of blocks."""

    def run(batches):
        for b in batches:
            lists = [b.column(c) for c in ("h", "pos", "df")]
            values, pos, df = (x.flatten().to_numpy() for x in lists)
            values = values.view(np.uint64)
            row = np.repeat(np.arange(b.num_rows), np.diff(lists[0].offsets.to_numpy()))
            times = -(-df.astype(np.int64) // hot)
            pick = np.repeat(np.arange(len(values)), times)
            other = np.arange(len(pick)) - np.repeat(np.cumsum(times) - times, times)
            k = times[pick]
            own = (mix(b.column("key").to_numpy().view(np.uint64))[row[pick]] % np.maximum(k, 1).astype(np.uint64)).astype(np.int64)
            # A block meets itself in every pair it is part of, so no pair of a block with itself is made.
            use = (k == 1) | (other != own)
            pick, other, k, own = pick[use], other[use], k[use], own[use]
            salt = np.where(k == 1, 0, 1 + np.minimum(own, other) * k + np.maximum(own, other)).astype(np.uint64)
            values, row, pos = np.where(salt == 0, values[pick], mix(values[pick] + mix(salt))), row[pick], pos[pick]
            for s in range(0, max(len(row), 1), 200_000):
                r = pa.array(row[s : s + 200_000])
                yield pa.RecordBatch.from_arrays([pa.array(values[s : s + 200_000].view(np.int64)), *(b.column(c).take(r) for c in ("key", "comp", "n")), pa.array(pos[s : s + 200_000], pa.int32())], ["h", "key", "comp", "n", "pos"])

    return run


def _near_hist(x: np.ndarray, y: np.ndarray, both: np.ndarray) -> np.ndarray:
    """Which rows of counts by BINS differ by no more than those of sets of similarity 0.8 can, `both` sizes added up."""
    return 9 * np.abs(x.astype(np.int16) - y).sum(1, dtype=np.int64) <= both


def _meet(neighbours: int | None, counted: bool = False, rows: bool = False):
    """Pairs of rows of one shingle that may reach 0.8 by their sizes, by what can follow and precede the shingle and,
    if counted, by their counts by BINS; or the rows themselves that are in such a pair.

    Rows arrive sorted by shingle and size; a shingle may span batches. Pairs already in one group are passed over.
    With `neighbours` a row meets only so many rows next to it, and the first one; else it meets all. A counted row
    has its whole prefix with it, so that a pair is written once, at the first shingle that both prefixes hold.
    """
    names = ("h", "key", "comp", "n", "pos")

    def emit(h, key, comp, n, pos, hist, start, prefix):
        a, b, sets = [], [], {}

        def met_first(i, j):
            if j not in sets:
                sets[j] = set(prefix[j])
            return next(x for x in prefix[i] if x in sets[j]) == prefix[i][pos[i] - start[i]]

        def pairs(i, j):
            most = np.minimum(pos[i], pos[j]) + np.minimum(n[i] - pos[i], n[j] - pos[j])
            ok = (comp[i] != comp[j]) & (5 * n[i] >= 4 * n[j]) & (9 * most >= 4 * (n[i] + n[j]))
            i, j = i[ok], j[ok]
            if counted:
                cuts = range(0, len(i), 10_000)
                near = np.concatenate([_near_hist(hist[i[s : s + 10_000]], hist[j[s : s + 10_000]], (n[i] + n[j])[s : s + 10_000]) for s in cuts] or [np.zeros(0, bool)])
                i, j = i[near], j[near]
                once = np.array([met_first(*x) for x in zip(i.tolist(), j.tolist(), strict=True)], bool)
                i, j = i[once], j[once]
            if rows:
                i, j = np.unique(i), np.unique(j)
            a.append(i)
            b.append(j)

        if neighbours:
            pairs(np.searchsorted(h, h), np.arange(len(h)))
        live, lag = np.arange(len(h)), 0
        while len(live) and lag != neighbours:
            lag += 1
            live = live[live + lag < len(h)]
            live = live[(h[live] == h[live + lag]) & (5 * n[live] >= 4 * n[live + lag])]
            pairs(live, live + lag)
        if rows:
            use = np.unique(np.concatenate([*a, *b])).astype(np.int64) if a else np.zeros(0, np.int64)
            return pa.RecordBatch.from_arrays([pa.array(x[use], t) for x, t in zip((h, key, comp, n, pos), (pa.int64(),) * 3 + (pa.int32(),) * 2, strict=True)], list(names))
        x, y = (key[np.concatenate(i)] if i else np.zeros(0, np.int64) for i in (a, b))
        both = np.unique(np.stack([np.maximum(x, y), np.minimum(x, y)], 1), axis=0)
        return pa.RecordBatch.from_arrays([pa.array(both[:, 0]), pa.array(both[:, 1])], ["a", "b"])

    def run(batches):
        held = [np.zeros(0, np.int64)] * 5 + [np.zeros((0, BINS if counted else 0), np.uint8), np.zeros(0, np.int64), np.zeros(0, object)]
        for batch in batches:
            new = [batch.column(c).to_numpy().astype(np.int64) for c in names]
            m, prefix = len(new[0]), np.zeros(len(new[0]), object)
            if counted:
                prefix[:] = batch.column("prefix").to_pylist()
                new += [np.frombuffer(b"".join(batch.column("hist").to_pylist()), np.uint8).reshape(-1, BINS), batch.column("start").to_numpy().astype(np.int64), prefix]
            else:
                new += [np.zeros((m, 0), np.uint8), np.zeros(m, np.int64), prefix]
            every = [np.concatenate([x, y]) for x, y in zip(held, new, strict=True)]
            if not len(every[0]):
                continue
            cut = np.searchsorted(every[0], every[0][-1])
            if cut:
                yield emit(*(x[:cut] for x in every))
            held = [x[cut:] for x in every]
        if len(held[0]):
            yield emit(*held)

    return run


def _near_counts(batches):
    """Pairs that may reach 0.8: the counts by BINS differ by no more than sets of that similarity can differ."""
    for b in batches:
        x, y = (np.frombuffer(b"".join(b.column(c).to_pylist()), np.uint8).reshape(-1, BINS) for c in ("x", "y"))
        n, m = (b.column(c).to_numpy().astype(np.int64) for c in ("n", "m"))
        ok = _near_hist(x, y, n + m) & (5 * np.minimum(n, m) >= 4 * np.maximum(n, m))
        yield pa.RecordBatch.from_arrays([b.column("a"), b.column("b")], ["a", "b"]).filter(pa.array(ok, pa.bool_()))


def _alike(batches):
    """Pairs of texts whose whole shingle sets have a similarity of 0.8 or more."""
    for b in slices(batches, "x", PIECE):
        (h, hb), (g, gb) = _shingles(b.column("x")), _shingles(b.column("y"))
        keep = []
        for i in range(b.num_rows):
            x, y = np.unique(h[hb[i] : hb[i + 1]]), np.unique(g[gb[i] : gb[i + 1]])
            both = len(np.intersect1d(x, y, assume_unique=True))
            keep.append(5 * both >= 4 * (len(x) + len(y) - both))
        yield pa.RecordBatch.from_arrays([b.column("a"), b.column("b")], ["a", "b"]).filter(pa.array(keep, pa.bool_()))


def near_duplicate_rows(docs: DataFrame) -> DataFrame:
    """(key, doc_id, label) of each distinct row key of docs (doc_id, text, ...): rows of one label are one group of
    five-word shingle similarity 0.8 or more.

    The search is exact. Two sets of that similarity share a shingle of their prefixes under any one order of all
    shingles; the order here is by the number of documents that hold a shingle, counted over all documents, so that a
    passage many documents share brings few of them together. Copies, SimHash links and each prefix shingle's nearest
    rows are verified and joined first; then prefixes bring up all pairs of different groups. Every pair, whatever
    brought it up, is verified on the whole sets of both texts. Rows without words are alike. Null and repeated ids,
    empty tables and very long texts are no special cases: rows go by a hash of id and text.
    """
    spark, keyed = docs.sparkSession, docs.select(row_key().alias("key"), "doc_id", "text")
    size = docs.agg(F.coalesce(F.sum(F.length("text")), F.lit(0))).first()[0]
    ranges = 1 << max(8, (size // RANGE_BYTES).bit_length())
    asked = keyed.transform(in_arrow, _ask(ranges), "p int, slice string, blob binary")
    answers = stage(asked.repartition("p", F.when(F.col("p") < 0, F.col("slice"))).sortWithinPartitions("p").transform(in_arrow, _own(ranges), "slice string, blob binary"))
    held = stage(answers.repartition("slice").sortWithinPartitions("slice").transform(in_arrow, _gather, PROFILE))
    again = stage(held.groupBy("key").agg(F.count("*").alias("k")).where("k > 1").select("key"))
    if not again.isEmpty():
        held = stage(held.join(again, "key", "left_anti").unionByName(held.join(again, "key", "left_semi").dropDuplicates(["key"])))
    # Copies meet as one: only the first row of each set looks for others.
    first = held.groupBy("sign").agg(F.min("key").alias("b"), F.count("*").alias("k")).where("k > 1")
    same = stage(salted_join(held.select("sign", F.col("key").alias("a")), first, "sign", spark).where("a <> b").select("a", "b"))
    profile = held.select("key", "n", "hist")
    texts = keyed.select("key", "text")

    def verified(close):
        """Pairs of keys that pass the test on the texts; each document's text is read once a side."""
        asked = close.select(F.col("a").alias("key")).union(close.select("b")).distinct()
        some = texts.join(asked, "key", "left_semi").dropDuplicates(["key"])
        read = lambda k, x: some.select(F.col("key").alias(k), F.col("text").alias(x))
        return stage(close.join(read("b", "y"), "b").join(read("a", "x"), "a").select("a", "b", "x", "y").transform(in_arrow, _alike, "a long, b long"))

    def near(pairs):
        """Pairs of keys that pass the counts."""
        side = lambda k, c, x: profile.select(F.col("key").alias(k), F.col("n").alias(c), F.col("hist").alias(x))
        return stage(pairs.join(side("b", "m", "y"), "b").join(side("a", "n", "x"), "a").select("a", "b", "n", "m", "x", "y").transform(in_arrow, _near_counts, "a long, b long"))

    by_print = simhash_components(keyed.select(F.col("key").alias("doc_id"), "text")).select(F.col("doc_id").alias("a"), F.col("component_id").alias("b"))
    for end in ("a", "b"):
        to = same.select(F.col("a").alias(end), F.col("b").alias("to"))
        by_print = by_print.join(to, end, "left").withColumn(end, F.coalesce("to", end)).drop("to")
    by_print = by_print.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    seek = stage(held.where(F.size("h") > 0).select("key", "n", "h", "pos", "df").join(same.select(F.col("a").alias("key")), "key", "left_anti"))

    posting = "h long, key long, comp long, n int, pos int"

    def spread(grouped):
        return grouped.transform(in_arrow, _prefix_rows(HOT), posting).repartition("h").sortWithinPartitions("h", "n", "key")

    beside = spread(seek.withColumn("comp", F.col("key"))).transform(in_arrow, _meet(2), "a long, b long").distinct()
    early = connected_components(same.union(verified(near(by_print.union(beside).distinct()))))
    known = early.select(F.col("node").alias("key"), F.col("label").alias("comp"))
    # Rows that may be alike across groups meet with their counts, so that only pairs which pass those are written.
    apart = spread(seek.join(known, "key", "left").withColumn("comp", F.coalesce("comp", "key"))).transform(in_arrow, _meet(None, rows=True), posting)
    counted = apart.join(held.select("key", "hist", F.get("pos", F.lit(0)).alias("start"), F.col("h").alias("prefix")), "key").repartition("h").sortWithinPartitions("h", "n", "key")
    late = verified(stage(counted.transform(in_arrow, _meet(None, counted=True), "a long, b long").distinct()))
    # Only pairs across groups are left, so the second search joins labels and not documents.
    for end in ("a", "b"):
        late = late.join(known.select(F.col("key").alias(end), F.col("comp").alias("to")), end, "left").withColumn(end, F.coalesce("to", end)).drop("to")
    merged = connected_components(late.select("a", "b"))
    ends = held.select("key", "doc_id").join(known, "key", "left").withColumn("comp", F.coalesce("comp", "key"))
    return ends.join(merged.select(F.col("node").alias("comp"), F.col("label").alias("to")), "comp", "left").select("key", "doc_id", F.coalesce("to", "comp").alias("label"))


def near_duplicate_groups(docs: DataFrame) -> DataFrame:
    """(doc_id, component_id) of each row of docs (doc_id, text, ...), by the groups of near_duplicate_rows.

    component_id is the smallest doc_id of the group, null if it has none. A null or repeated doc_id links nothing:
    rows group by their texts alone.
    """
    rows = stage(near_duplicate_rows(docs))
    low = rows.groupBy("label").agg(F.min("doc_id").alias("component_id"))
    groups = rows.join(low, "label").select("key", "component_id")
    return docs.select(row_key().alias("key"), "doc_id").join(groups, "key").select("doc_id", "component_id")
