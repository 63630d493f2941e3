"""The rounds of an expansion over lists of neighbours, for what only needs counts: nothing is kept for an edge but its two
entries in the lists of its ends, a neighbour and eid modulo parts in four bytes each.

Which edges are free follows from the vertices. All free edges around a taken vertex are claimed in that round, and a free
edge whose ends meet in a live part is claimed as soon as they do; parts that have stopped gain no vertices. So between
rounds an edge is free just when neither end was taken and its ends lie in no common part.
"""

from __future__ import annotations

import json
import math
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubgraph.core.model import PropertyGraph
from hubgraph.partition import expansion
from hubgraph.session import small_batches, stage

MOST_PARTS = 12  # a table of claims has a row for each set of parts
LISTS = "n long, src binary, times binary, dst binary, at binary, turn binary"
FILES = expansion.BLOB_FILES | {"compression": "zstd"}
BLOB = 1 << 16  # edges a row, so that places in its targets fit two bytes
ENDS = 1 << 22  # distinct ends that a packing task holds before it writes them
CLOSED = 1 << 15
VERTICES = 1 << 18  # vertices that are looked at at once
PAIRED = 30_000_000  # beyond so many edges a study's vertex orders share their lists two by two


def _steps(ids):
    """Sorted ids as differences, which compress."""
    import numpy as np

    return np.diff(ids, prepend=ids.dtype.type(0)).astype("<i8").tobytes()


def pack_lists(graph: PropertyGraph, parts: int) -> tuple[DataFrame, int, int]:
    """Edges as blobs, at most BLOB to a row, sorted by source: distinct sources and how often each comes, distinct targets and
    each edge's place in them, eid modulo parts. Rows with n = 0 have distinct ends of many edges, with their degrees as
    sources (times) and as targets (at). Also the number of edges, and of rows with n = 0."""

    def pack(batches):
        import numpy as np
        import pyarrow as pa

        schema = pa.schema([("n", pa.int64()), *((c, pa.binary()) for c in ("src", "times", "dst", "at", "turn"))])
        held, count, ends, size = [], 0, ([], []), 0

        def record(n, *blobs):
            return pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), *(pa.array([x], pa.binary()) for x in blobs)], schema=schema)

        def row(eid, src, dst):
            order = np.argsort(src, kind="stable")
            source, times = np.unique(src, return_counts=True)
            target, at, of_target = np.unique(dst[order], return_inverse=True, return_counts=True)
            ends[0].append((source, times))
            ends[1].append((target, of_target))
            return record(len(src), _steps(source), times.astype("<u4").tobytes(), _steps(target), at.astype("<u2").tobytes(), (eid[order] % parts).astype("u1").tobytes())

        def vertices():
            ids = expansion.distinct([x for side in ends for x, _ in side])
            degrees = [np.zeros(len(ids), "<u4") for _ in ends]
            for side, degree in zip(ends, degrees, strict=True):
                for x, n in side:
                    degree[np.searchsorted(ids, x)] += n.astype("u4")
                side.clear()
            for i in range(0, len(ids), BLOB):
                k = slice(i, i + BLOB)
                yield record(0, _steps(ids[k]), degrees[0][k].tobytes(), None, degrees[1][k].tobytes(), None)

        for b in batches:
            held.append([b.column(c).to_numpy() for c in ("eid", "src", "dst")])
            count += b.num_rows
            while count >= BLOB:
                eid, src, dst = (np.concatenate(x) for x in zip(*held, strict=True))
                yield row(eid[:BLOB], src[:BLOB], dst[:BLOB])
                held, count = [[x[BLOB:].copy() for x in (eid, src, dst)]], count - BLOB
                size += len(ends[0][-1][0]) + len(ends[1][-1][0])
                if size > ENDS:
                    yield from vertices()
                    size = 0
        if count:
            yield row(*(np.concatenate(x) for x in zip(*held, strict=True)))
        if ends[0]:
            yield from vertices()

    small_batches(graph.edges.sparkSession)
    packed = stage(graph.edges.select("eid", "src", "dst").mapInArrow(pack, LISTS), **FILES)
    total, heads = packed.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count_if(F.col("n") == 0)).first()
    return packed, total, heads


def rows_of(packed: DataFrame) -> DataFrame:
    """For one task: ids of vertices, then their degrees, then edges; `step` tells which. A row of step 3 holds nothing."""

    def some(step, where, *kept):
        return packed.where(where).select(F.lit(step).alias("step"), *(c if c in kept else F.lit(None).cast("binary").alias(c) for c in ("src", "times", "dst", "at", "turn")))

    # The executor's heap is given back first: what packing left there would lie beside the lists.
    emptied = packed.sparkSession.range(0, 1, 1, 1).select(F.expr("cast(if(reflect('java.lang.System', 'gc') is null, 3, 3) as int)").alias("step"), *(F.lit(None).cast("binary").alias(c) for c in ("src", "times", "dst", "at", "turn")))
    return emptied.union(some(0, "n = 0", "src")).union(some(1, "n = 0", "src", "times", "at")).union(some(2, "n > 0", "src", "times", "dst", "at", "turn")).coalesce(1)


class Lists:
    """A graph as lists. ids are sorted, and a vertex is its place there; an entry of sides[0] is a source's edge, one of sides[1]
    a target's: the other end's place, shifted, and eid modulo parts. batches are of rows_of, in any order."""

    def __init__(self, batches, parts, total, heads):
        import numpy as np

        self.shift, self.total = (parts - 1).bit_length(), total
        waiting, left, fresh, phase, done = ([], [], []), heads, [], 0, 0
        self.ids = np.zeros(0, "int64")
        kind = "int32" if total < 1 << 31 else "int64"

        def ids_of(blob):
            return np.cumsum(np.frombuffer(blob, "<i8"))

        def starts(n):
            return np.cumsum(n, dtype="int64") - n

        for b in batches:
            for step, *blobs in zip(*(b.column(c) for c in ("step", "src", "times", "dst", "at", "turn")), strict=True):
                if step.as_py() < 3:
                    waiting[step.as_py()].append([x.as_buffer() if x.is_valid else None for x in blobs])
            del blobs
            while phase < 3 and waiting[phase]:
                src, times, dst, at, turn = waiting[phase].pop()
                if phase < 2:
                    left -= 1
                if phase == 0:
                    fresh.append(ids_of(src))
                    if not left or sum(map(len, fresh)) > max(len(self.ids), ENDS):
                        self.ids, fresh = expansion.distinct([self.ids, *fresh]), []
                    if not left:
                        phase, left, places = 1, heads, expansion.Places(self.ids)
                        degrees = [np.zeros(len(self.ids), kind) for _ in range(2)]
                elif phase == 1:
                    v = places.of(ids_of(src))
                    for degree, n in zip(degrees, (times, at), strict=True):
                        degree[v] += np.frombuffer(n, "<u4").astype(kind)
                    if not left:
                        phase = 2
                        code = "uint32" if len(self.ids) << self.shift < 1 << 32 else "uint64"
                        codes, next_ = [np.empty(total, code) for _ in range(2)], [starts(x).astype(kind) for x in degrees]
                        del degrees
                else:
                    s, d, times = places.of(ids_of(src)), places.of(ids_of(dst)), np.frombuffer(times, "<u4").astype("int64")
                    at, turn = np.frombuffer(at, "<u2"), np.frombuffer(turn, "u1")
                    to = np.repeat(next_[0][s] - starts(times), times) + np.arange(len(at))
                    codes[0][to] = (d.astype(code) << self.shift)[at] | turn
                    next_[0][s] += times.astype(kind)
                    order, times_in = np.argsort(at, kind="stable"), np.bincount(at, minlength=len(d))
                    to = np.repeat(next_[1][d] - starts(times_in), times_in) + np.arange(len(at))
                    codes[1][to] = (np.repeat(s.astype(code) << self.shift, times) | turn)[order]
                    next_[1][d] += times_in.astype(kind)
                    done += len(at)
        if done != total or phase < 2:
            raise ValueError(f"{done} edges came, {total} were counted")
        self.sides = [(np.concatenate([np.zeros(1, kind), x]), c) for x, c in zip(next_, codes, strict=True)]  # a list begins where the one before has ended

    @property
    def size(self):
        return len(self.sides[0][0]) - 1

    def deg(self, v=slice(None)):
        """Degrees of vertices, or of all."""
        if isinstance(v, slice):
            return sum(begin[1:] - begin[:-1] for begin, _ in self.sides)
        return sum(begin[v + 1] - begin[v] for begin, _ in self.sides)

    def around(self, side, v):
        """(vertices, lengths of their lists, entries) of distinct vertices v, in chunks."""
        for i in range(0, len(v), expansion.CHUNK):
            yield from self._around(side, v[i : i + expansion.CHUNK])

    def _around(self, side, v):
        import numpy as np

        begin, code = self.sides[side]
        first, count = begin[v], begin[v + 1] - begin[v]
        some = count > 0
        if not some.all():
            v, first, count = v[some], first[some], count[some]
        ends = np.cumsum(count, dtype="int64")
        cuts = [0, *np.searchsorted(ends, np.arange(expansion.CHUNK, ends[-1], expansion.CHUNK)).tolist(), len(v)] if len(v) else [0]
        for a, b in zip(cuts, cuts[1:], strict=False):
            if b == a + 1:
                yield v[a:b], count[a:b], code[int(first[a]) : int(first[a]) + int(count[a])]
            elif b > a:
                n = count[a:b]
                yield v[a:b], n, code[np.repeat(first[a:b] - (ends[a:b] - n - (ends[a] - n[0])), n) + np.arange(int(ends[b - 1] - ends[a] + n[0]))]


class Order:
    """Vertices in the order of a hash, and by degree with ties in that order; rank is a vertex's place in the latter."""

    def __init__(self, g: Lists, salt: str):
        import numpy as np

        self.tied = expansion.order_by_hash(salt, g.ids)
        self.by_rank = self.tied[np.argsort(g.deg()[self.tied], kind="stable")]
        self.rank = np.empty(g.size, "int32")
        self.rank[self.by_rank] = np.arange(g.size, dtype="int32")

    def seeds(self, g: Lists, start: str, parts: int, grid=None):
        """(vertex, part) where parts begin."""
        import numpy as np

        if start == "vertices":
            return [(int(v), p) for p, v in enumerate(self.tied[:parts])]
        row, column = grid
        tie, lowest = np.empty(g.size, "int32"), np.full(parts, g.size, "int32")
        tie[self.tied] = np.arange(g.size, dtype="int32")
        for v, n, code in g.around(0, np.arange(g.size, dtype="int32")):
            to = (code >> g.shift).astype("intp")
            np.minimum.at(lowest, np.repeat(row[v], n) + column[to], np.minimum(np.repeat(tie[v], n), tie[to]))
        return [(int(self.tied[v]), p) for p, v in enumerate(lowest.tolist()) if v < g.size]


def claims(parts, shift, load):
    """The part that takes an edge, at (set of parts that want it, as bits) << shift | turn: the least loaded, ties in an order
    turned by the edge; the turn itself where none wants it."""
    import numpy as np

    level = np.unique(np.array(load), return_inverse=True)[1]
    turn, sets = np.arange(1 << shift), np.arange(1 << parts)
    best, part = np.full((1 << parts, 1 << shift), parts * parts), np.tile(turn, (1 << parts, 1))
    for p in range(parts):
        rank = np.where((sets >> p & 1)[:, None] > 0, level[p] * parts + (turn + p) % parts, parts * parts)
        part[rank < best] = p
        best = np.minimum(best, rank)
    return part.astype("uint8").ravel()


def list_rounds(g: Lists, order: Order, seeds, *, parts, steer, lambda0, alpha, beta, tau, max_rounds, tail, cap):
    """The rounds of expand: (edges of each part, vertices of each part, vertices that lie in one part only, trace)."""
    import numpy as np

    assert 0 < max_rounds and tail < 1 and parts <= MOST_PARTS
    total, size, shift = g.total, g.size, g.shift
    turns, every = g.sides[0][1].dtype.type((1 << shift) - 1), (1 << parts) - 1
    free = g.deg()
    # A vertex's parts, as bits: after the last round in the lower half, now in the upper half. CLOSED: taken.
    state = np.zeros(size, "uint32")
    halves = state.view("uint16").reshape(size, 2)
    old, now = (halves[:, 0], halves[:, 1]) if np.little_endian else (halves[:, 1], halves[:, 0])
    taking, marked = np.zeros(size, "uint16"), np.zeros(size, bool)
    one = free.dtype.type(1)
    nv, ne, speed, trace, left = [1] * parts, [0] * parts, [lambda0] * parts, [], total
    replicas, searched = [0] * parts, 0

    def where(test):
        """The vertices that meet test(slice), a chunk at a time, so that what is passing stays small."""
        return np.concatenate([(np.flatnonzero(test(slice(i, i + VERTICES))) + i).astype("int32") for i in range(0, size, VERTICES)])

    def first_open(most):
        """The first vertices in the order of the hash that have free edges."""
        nonlocal searched
        found, at = [], searched
        while at < size and len(found) < most:
            v = order.tied[at : at + expansion.CHUNK]
            v_open = np.flatnonzero(free[v] > 0)
            if not found:  # closed vertices stay closed
                searched = at + int(v_open[0]) if len(v_open) else at + len(v)
            found += v[v_open[: most - len(found)]].tolist()
            at += len(v)
        return found

    def taken(p, v):
        """The vertices of v that part p takes: as many as its quota, of about cap edge ends."""
        n = min(expansion.quota(speed[p], len(v)), math.ceil(cap) + 1)  # each has an end at least
        r = order.rank[v]
        if n < len(r):
            r = np.partition(r, n - 1)[:n]
        r.sort()
        v = order.by_rank[r]
        if cap > 2 * total:
            return v
        d = g.deg(v).astype("int64")
        return v[np.cumsum(d) - d < cap]

    def add(held, v, part, gained):
        """Puts parts down at vertices v."""
        which = np.flatnonzero(gained).tolist()
        for p in which:
            at = v if len(which) == 1 else v[part == p]
            held[at] |= np.uint16(1 << p)

    for number in range(max_rounds):
        if left <= tail * total:
            break
        vs, es = expansion.share_score(nv), expansion.share_score(ne)
        if steer:
            speed = [expansion.next_lambda(*x, alpha, beta) for x in zip(speed, vs, es, strict=True)]
        live = [p for p in range(parts) if steer or ne[p] <= tau * total / parts]
        live_bits = sum(1 << p for p in live)
        boundary = where(lambda k, some=np.uint16(live_bits): ((old[k] & some) != 0) & (free[k] > 0))
        bits = old[boundary]
        there = int(np.bitwise_or.reduce(bits)) if len(bits) else 0
        begun = list(seeds) if not number else []
        starved = [p for p in live if not there >> p & 1 and p not in {q for _, q in begun}]
        begun += zip(first_open(len(starved)), starved, strict=False) if starved else ()
        begin_at = {p: np.array([v], "int32") for v, p in begun}
        groups = []
        for p in live:
            if p in begin_at or there >> p & 1:
                groups.append(taken(p, begin_at[p] if p in begin_at else boundary[(bits & np.uint16(1 << p)) > 0]))
                taking[groups[-1]] |= np.uint16(1 << p)
        del boundary, bits
        chosen = np.unique(np.concatenate([np.zeros(0, "int32"), *groups]))
        del groups
        # Free edges around taken vertices. Parts begin at vertices that do not hold them yet.
        table, count = claims(parts, shift, ne), np.array(ne)
        for side in (0, 1):
            for v, n, code in g.around(side, chosen):
                to = (code >> shift).astype("intp")
                at = np.flatnonzero((np.repeat(old[v] | np.uint16(CLOSED), n) & old[to]) == 0)
                if side:  # seen from its source before
                    at = at[taking[to[at]] == 0]
                if not len(at):
                    continue
                to, u = to[at], np.repeat(np.arange(len(v)), n)[at]
                want = taking[v][u].astype("int64")
                if not side:
                    want |= taking[to]
                part = table[(want << shift) | (code[at] & turns)]
                gained = np.bincount(part, minlength=parts)
                count += gained
                np.subtract.at(free, to, one)
                add(now, to, part, gained)
                add(now, v[u], part, gained)
        ne = count.tolist()
        free[chosen] = 0
        fresh = where(lambda k: old[k] != now[k])
        gain = now[fresh] ^ old[fresh]
        for p in range(parts):
            replicas[p] += int(np.count_nonzero(gain & np.uint16(1 << p)))
        for v, p in begun:  # a part counts where it began, though it may have got no edge there
            replicas[p] += not int(now[v]) >> p & 1
        taking[chosen] = 0
        old[chosen] |= np.uint16(CLOSED)
        now[chosen] |= np.uint16(CLOSED)
        # Free edges whose ends have come to meet in a live part.
        near = fresh[free[fresh] > 0]
        marked[near] = True
        table = claims(parts, shift, ne)
        for side in (0, 1):
            for v, n, code in g.around(side, near):
                mine = (state[v] & np.uint32(live_bits << 16 | 0xFFFF)) | np.uint32(CLOSED)
                to = (code >> shift).astype("intp")
                both = np.repeat(mine, n) & state[to]
                at = np.flatnonzero(both)
                both = both[at]
                here = both & np.uint32(0xFFFF) == 0
                at, both = at[here], both[here]
                if side and len(at):
                    here = ~marked[to[at]]
                    at, both = at[here], both[here]
                if not len(at):
                    continue
                part = table[(both >> np.uint32(16) << np.uint32(shift)) | (code[at] & turns)]
                count += np.bincount(part, minlength=parts)
                np.subtract.at(free, to[at], one)
                free[v] -= np.bincount(np.repeat(np.arange(len(v)), n)[at], minlength=len(v)).astype(free.dtype)
        marked[near] = False
        old[fresh] = now[fresh]
        ne, nv = count.tolist(), list(replicas)
        left = total - sum(ne)
        trace += [{"round": number, "part": p, "speed": speed[p], "vs": vs[p], "es": es[p], "nv": nv[p], "ne": ne[p], "free": left, "reseeded": p in starved} for p in range(parts)]
    held, table, count = now & np.uint16(every), claims(parts, shift, ne), np.array(ne)
    for v, n, code in g.around(0, where(lambda k: free[k] > 0)):
        to = (code >> shift).astype("intp")
        at = np.flatnonzero((np.repeat(old[v] | np.uint16(CLOSED), n) & old[to]) == 0)
        u, to = np.repeat(v, n)[at], to[at]
        part = table[((old[u] | old[to]).astype("int64") << shift) | (code[at] & turns)]
        gained = np.bincount(part, minlength=parts)
        count += gained
        add(held, u, part, gained)
        add(held, to, part, gained)
    nv = np.array([np.count_nonzero(held & np.uint16(1 << p)) for p in range(parts)])
    return count, nv, int(np.count_nonzero((held & (held - np.uint16(1))) == 0)), trace


def in_lists(rules: dict) -> bool:
    """Whether list_rounds does what these rules ask for."""
    return rules["parts"] <= MOST_PARTS and rules["max_rounds"] > 0 and rules["tail"] < 1


def small_grid(ids, parts):
    """grid_of in a byte each, which MOST_PARTS allows; a chunk at a time."""
    import numpy as np

    pairs = [expansion.grid_of(ids[i : i + expansion.CHUNK], parts) for i in range(0, len(ids), expansion.CHUNK)]
    return [np.concatenate([x[k].astype("uint8") for x in pairs]) for k in (0, 1)]


COUNTS = "part int, ne long, nv long, v long, inside long, trace string"


def counts_in_task(packed: DataFrame, total: int, heads: int, start: str, salt: str, rules: dict) -> DataFrame:
    """COUNTS of one run, written out."""
    parts = rules["parts"]

    def grow(batches):
        import pyarrow as pa

        g = Lists(batches, parts, total, heads)
        order = Order(g, salt)
        seeds = order.seeds(g, start, parts, None if start == "vertices" else small_grid(g.ids, parts))
        g.ids = None
        ne, nv, inside, trace = list_rounds(g, order, seeds, **rules)
        yield pa.RecordBatch.from_pydict({"part": pa.array(range(parts), pa.int32()), "ne": pa.array(ne, pa.int64()), "nv": pa.array(nv, pa.int64()), "v": pa.array([g.size] * parts, pa.int64()), "inside": pa.array([inside] * parts, pa.int64()), "trace": pa.array([json.dumps(trace)] + [None] * (parts - 1), pa.string())})

    return stage(rows_of(packed).mapInArrow(grow, COUNTS))


def study_task(mine, parts, total, heads, starts, shares, rules):
    """A function over rows_of that makes rows of STUDY for the vertex orders `mine`, each in a thread over the same lists."""

    def run(batches):
        import pyarrow as pa

        g = Lists(batches, parts, total, heads)
        grid = small_grid(g.ids, parts) if "grid" in starts else None
        orders = {k: Order(g, f"s{k}") for k in mine}  # one after the other, since each takes room for a while
        g.ids = None
        ratio = lambda x: float(x.max() / x.min()) if x.min() else None

        def of_order(k):
            order, out = orders[k], []
            for start in starts:
                seeds = order.seeds(g, start, parts, grid)
                for share in shares:
                    for steer in (True, False):
                        ne, nv, _, trace = list_rounds(g, order, seeds, parts=parts, steer=steer, cap=expansion.round_cap(total, parts, share), **rules)
                        out.append({"start": start, "steered": steer, "round_share": share, "vertex_order": k, "rf": float(nv.sum() / g.size), "vb": ratio(nv), "eb": ratio(ne), "rounds": len(trace) // parts})
            return out

        kinds = pa.schema([("start", pa.string()), ("steered", pa.bool_()), ("round_share", pa.float64()), ("vertex_order", pa.int32()), ("rf", pa.float64()), ("vb", pa.float64()), ("eb", pa.float64()), ("rounds", pa.int32())])
        with ThreadPoolExecutor(len(mine)) as pool:
            for out in pool.map(of_order, mine):
                yield pa.RecordBatch.from_pylist(out, schema=kinds)

    return run
