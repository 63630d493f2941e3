"""Best-fit packing by linear grouping over the histogram of piece lengths."""

from __future__ import annotations

import base64
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from hubgraph.llm.common import Rolling, in_arrow, slices, stage

CAPACITY, END_ID = 1024, 2
# Classes of code points for the tokenizer's pre-splitting.
SPACE, BLANK, LETTER, NUMBER, OTHER = range(5)
_CHARS = Rolling(0x2545F4914F6CDD1D)


@lru_cache(1)
def _char_classes() -> tuple[np.ndarray, np.ndarray]:
    import regex

    every = "".join(map(chr, [*range(0xD800), *range(0xE000, 0x110000)]))
    classes = np.full(0x110000, OTHER, np.uint8)
    for kind, pattern in ((LETTER, r"\p{L}"), (NUMBER, r"\p{N}"), (BLANK, r"\s")):
        classes[[ord(c) for c in regex.findall(pattern, every)]] = kind
    classes[32] = SPACE
    return classes, np.random.default_rng(7).integers(1, 1 << 63, 0x110000, dtype=np.uint64)


@lru_cache(2)
def _encoder(path: str):
    """The byte-level BPE; its ranks file lies beside the tokenizer file and holds the same vocabulary."""
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(path, "rb"))}
    from public_tokenizers import PATTERN

    return tiktoken.Encoding("own", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={}), ranks


def split_points(points: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Starts of the pre-tokens of texts laid end to end (contractions apart), by the rules of the public pattern."""
    classes, _ = _char_classes()
    kind = classes[points]
    n = len(points)
    first = np.zeros(n + 1, bool)
    first[off] = True
    blank = kind <= BLANK
    prev = np.r_[np.uint8(255), kind[:-1]]
    prev_blank = np.r_[False, blank[:-1]]
    # A visible run starts where the class changes; a single space before it belongs to it.
    visible = ~blank & (first[:-1] | (kind != prev))
    joins = visible & ~first[:-1] & (prev == SPACE)
    begin = visible & ~joins
    last_blank = blank & ~np.r_[blank[1:], False] & ~first[1:]  # a blank with something visible after it
    begin |= last_blank  # either joins the next token or stands alone
    begin |= blank & (first[:-1] | ~prev_blank)
    return np.nonzero(begin)[0]


_SEEN: dict[int, np.ndarray] = {}


def encode_block(texts: list[str], path: str) -> tuple[np.ndarray, np.ndarray]:
    """Token ids of all texts end to end (without the closing id) and offsets by text."""
    encoding, ranks = _encoder(path)
    slow = [i for i, t in enumerate(texts) if "'" in t]
    fast = texts if not slow else [t if "'" not in t else "" for t in texts]
    off = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(t) for t in fast], out=off[1:])
    joined = "".join(fast)
    points = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
    start = split_points(points, off) if len(points) else np.zeros(0, np.int64)
    end = np.r_[start[1:], len(points)]
    values = _char_classes()[1]
    key = _CHARS.spans(_CHARS.prefix(values[points]), start, end) if len(start) else np.zeros(0, np.uint64)
    unique, where, which = np.unique(key, return_index=True, return_inverse=True)
    if len(_SEEN) > 150_000:
        _SEEN.clear()
    ids = []
    for k, s, e in zip(unique.tolist(), start[where].tolist(), end[where].tolist(), strict=True):
        got = _SEEN.get(k)
        if got is None:
            piece = joined[s:e].encode("utf-8", "replace")
            rank = ranks.get(piece)
            got = _SEEN[k] = [rank] if rank is not None else encoding._core_bpe.encode_single_piece(piece)
        ids.append(got)
    size = np.fromiter(map(len, ids), np.int64, len(ids))
    every = np.fromiter((x for y in ids for x in y), np.uint32, int(size.sum()))
    at = np.cumsum(size) - size
    n = size[which]
    total = np.r_[0, np.cumsum(n)]
    out = every[np.arange(total[-1]) - np.repeat(total[:-1], n) + np.repeat(at[which], n)]
    bounds = total[np.searchsorted(start, off)]
    if not slow:
        return out, bounds
    parts = [out[bounds[i] : bounds[i + 1]] for i in range(len(texts))]
    for i in slow:
        parts[i] = np.array(encoding.encode_ordinary(texts[i]), np.uint32)
    return np.concatenate(parts), np.r_[0, np.cumsum([len(p) for p in parts])]


def _pieces(path: str, capacity: int, with_ids: bool):
    def run(batches):
        for b in slices(batches, "text", 1_000_000):
            ids, off = encode_block([t or "" for t in b.column("text").to_pylist()], path)
            doc, piece, start, length, crc, held = [], [], [], [], [], []
            for row, d in enumerate(b.column("doc_id").to_pylist()):
                own = np.append(ids[off[row] : off[row + 1]], np.uint32(END_ID)).astype("<u4", copy=False)
                cut = [0, *range(len(own) % capacity or min(capacity, len(own)), len(own) + 1, capacity)]
                for k, (s, e) in enumerate(zip(cut[:-1], cut[1:], strict=True)):
                    doc.append(d), piece.append(k), start.append(s), length.append(e - s), crc.append(zlib.crc32(own[s:e]))
                    if with_ids:
                        held.append(own[s:e].astype(np.int32))
            names = {"doc_id": pa.array(doc, pa.int64()), "piece": pa.array(piece, pa.int32()), "start": pa.array(start, pa.int64()), "length": pa.array(length, pa.int64()), "ids_crc32": pa.array(crc, pa.int64())}
            if with_ids:
                names["ids"] = pa.array(held, pa.list_(pa.int32()))
            yield pa.RecordBatch.from_pydict(names)

    return run


def _fullest(sizes: np.ndarray, worth: np.ndarray, capacity: int) -> tuple[float, np.ndarray]:
    """The most worth that repeated sizes can have within the capacity, and how often each is taken."""
    most, chosen = np.zeros(capacity + 1), np.full(capacity + 1, -1)
    for c in range(int(sizes.min()), capacity + 1):
        got = np.where(sizes <= c, worth + most[np.maximum(c - sizes, 0)], -1.0)
        i = int(got.argmax())
        if got[i] > most[c - 1] + 1e-12:
            most[c], chosen[c] = got[i], i
        else:
            most[c] = most[c - 1]
    take, c = np.zeros(len(sizes)), capacity
    while c > 0:
        if chosen[c] < 0:
            c -= 1
        else:
            take[chosen[c]] += 1
            c -= int(sizes[chosen[c]])
    return float(most[capacity]), take


def configurations(sizes: np.ndarray, demand: np.ndarray, capacity: int, tolerance: float = 1e-5) -> list[tuple[np.ndarray, float]]:
    """The linear programme of the fewest bins over all configurations of a few sizes: (counts by size, times).

    Revised simplex; the entering configuration is the fullest one at the present prices of the sizes, found by a
    knapsack, so that no list of configurations is ever made. There are as many configurations used as sizes.
    """
    m = len(sizes)
    alone = np.maximum(1, capacity // sizes).astype(float)
    columns, inverse, times = [alone[i] * np.eye(m)[i] for i in range(m)], np.diag(1 / alone), demand / alone
    for _ in range(60 * m):
        value, column = _fullest(sizes, inverse.sum(0), capacity)
        if value <= 1 + tolerance:
            break
        step = inverse @ column
        ratio = np.where(step > 1e-9, times / np.where(step > 1e-9, step, 1), np.inf)
        out = int(ratio.argmin())
        times = np.maximum(times - ratio[out] * step, 0)
        times[out] = ratio[out]
        columns[out] = column
        row = inverse[out] / step[out]
        inverse -= np.outer(step, row)
        inverse[out] = row
    return [(c, float(t)) for c, t in zip(columns, times, strict=True) if t > 0]


def plan_bins(histogram: dict[int, int], capacity: int = CAPACITY, small: int = 128, groups: int = 96) -> list[tuple[int, list[int]]]:
    """(number of bins, exact lengths inside) for lengths below capacity.

    Lengths above `small`, in falling order, are dealt into groups of equal cardinality and rounded up to the longest
    of the group. The configurations of these few sizes that need the fewest bins come from a linear programme; the
    whole part of each is used. Actual lengths then take the places of rounded ones: the longest that its group still
    has, and in a configuration's last place the longest of all that fits, which wins back what rounding up cost. Bins
    of equal content are made at once. What is left over and the small lengths go last, longest first, each into the
    fullest bin that still holds it.
    """
    left = {s: n for s, n in histogram.items() if n and s < capacity}
    large = sorted((s for s in left if s > small), reverse=True)
    quota = max(1, -(-sum(left[s] for s in large) // groups))
    rounded, demand, lowest = [], [], []  # by group
    for s in large:
        n = left[s]
        while n:
            if not demand or demand[-1] == quota:
                rounded.append(s), demand.append(0), lowest.append(s)
            take = min(n, quota - demand[-1])
            demand[-1] += take
            lowest[-1] = s
            n -= take
    there = np.zeros(capacity + 1, np.int64)  # lengths above `small` that are left
    there[large] = [left[s] for s in large]
    runs: list[tuple[int, list[int]]] = []
    plan = configurations(np.array(rounded, np.int64), np.array(demand, float), capacity) if large else []
    plan = sorted((np.repeat(np.arange(len(c)), c.astype(int)).tolist(), t) for c, t in plan)
    for places, used in plan:
        times = int(used + 1e-6)
        while times:
            own: list[int] = []
            for g in places[:-1]:
                fit = np.nonzero(there[: rounded[g] + 1])[0]
                if not len(fit) or fit[-1] < lowest[g] - small:
                    break
                own.append(int(fit[-1]))
                there[own[-1]] -= 1
            room, full = capacity - sum(own), len(own) == len(places) - 1
            while full and len(fit := np.nonzero(there[: room + 1])[0]):
                own.append(int(fit[-1]))
                there[own[-1]] -= 1
                room -= own[-1]
            kinds = {s: own.count(s) for s in own}
            for s, k in kinds.items():
                there[s] += k
            if not full or not own:
                break
            can = min(times, *(int(there[s]) // k for s, k in kinds.items()))
            for s, k in kinds.items():
                there[s] -= k * can
            runs.append((can, own))
            times -= can
    last = {s: n for s, n in left.items() if s <= small} | {int(s): int(there[s]) for s in np.nonzero(there)[0]}
    by_room: dict[int, list[tuple[int, list[int]]]] = {}
    for n, own in runs:
        by_room.setdefault(capacity - sum(own), []).append((n, own))
    for s in sorted(last, reverse=True):
        n = last[s]
        while n:
            fits = [r for r in by_room if r >= s]
            if not fits:
                by_room.setdefault(capacity, []).append((-(-n // (capacity // s)), []))
                fits = [capacity]
            r = min(fits)
            m, own = by_room[r].pop()
            if not by_room[r]:
                del by_room[r]
            each = min(r // s, n)
            use = min(m, n // each)
            if m > use:
                by_room.setdefault(r, []).append((m - use, own))
            by_room.setdefault(r - s * each, []).append((use, own + [s] * each))
            n -= use * each
    return [(n, own) for kind in by_room.values() for n, own in kind if own]


def pack(docs: DataFrame, ranks_path: str, capacity: int = CAPACITY, *, with_ids: bool = False) -> DataFrame:
    """Pieces of all docs (doc_id, text, ...) with the sequence and the offset that each is packed at.

    A document is its token ids and the closing id; only one longer than capacity is cut, its first piece holding the
    remainder. Null and empty texts are the closing id alone. Repeated rows are packed each for itself. An empty table
    gives an empty result; very long texts are cut whole; other columns are ignored. Only the histogram of lengths (capacity entries at most) reaches the driver, and the plan
    made from it goes back as rows (length, rank range, first sequence, offset): pieces find their place by length and
    rank. Ranks are taken per length and salt, with as many salts as the number of pieces asks for, so a length that
    holds most pieces is still spread.
    """
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * with_ids
    spark = docs.sparkSession
    pieces = stage(docs.select("doc_id", "text").transform(in_arrow, _pieces(ranks_path, capacity, with_ids), schema))
    histogram = {r.length: r.n for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}
    plan, sequence = [], histogram.get(capacity, 0)
    taken: dict[int, int] = {}
    if sequence:
        plan.append((capacity, 0, sequence, 1, 0, 0, 0))
    for n, own in plan_bins(histogram, capacity):
        at, k = 0, {}
        for s in own:
            k.setdefault(s, []).append(at)
            at += s
        for s, offsets in k.items():
            base = taken.get(s, 0)
            for j, offset in enumerate(offsets):
                plan.append((s, base, base + n * len(offsets), len(offsets), j, sequence, offset))
            taken[s] = base + n * len(offsets)
        sequence += n
    salts = max(8, sum(histogram.values()) // 20_000)
    salted = pieces.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(salts)))
    counts = salted.groupBy("length", "salt").agg(F.count("*").alias("n"))
    base = counts.select("length", "salt", (F.sum("n").over(Window.partitionBy("length").orderBy("salt")) - F.col("n")).alias("base"))
    ranked = salted.withColumn("r", F.row_number().over(Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "ids_crc32")) - 1)
    ranked = ranked.join(base, ["length", "salt"]).withColumn("rank", F.col("r") + F.col("base"))
    # The plan has a few rows for each length; one array a length keeps the join an equality on it.
    slots = spark.createDataFrame(plan, "length long, lo long, hi long, step int, slot int, sequence long, offset long")
    slots = slots.groupBy("length").agg(F.array_sort(F.collect_list(F.struct("lo", "hi", "step", "slot", "sequence", "offset"))).alias("places"))
    mine = F.filter("places", lambda p: (F.col("rank") >= p.lo) & (F.col("rank") < p.hi) & (F.pmod(F.col("rank") - p.lo, p.step) == p.slot))[0]
    placed = ranked.join(F.broadcast(slots), "length").withColumn("place", mine)
    columns = ["doc_id", "piece", "start", "length", "ids_crc32", (F.col("place.sequence") + F.floor((F.col("rank") - F.col("place.lo")) / F.col("place.step"))).cast("long").alias("sequence_id"), F.col("place.offset").alias("offset")]
    return placed.select(*columns, *["ids"] * with_ids)
