"""Vertex-cut by expansion, in rounds: steered by balance, or with a constant speed and a stopping threshold.

Parts start at the first vertices in the order of a hash, or each at a vertex of its own slot of the grid placement.
Every part grows from its replicas that still have free edges. Each round it takes the share lambda of these with the
lowest degrees, claims their free edges, and then free edges whose ends already meet in a part. With steering, lambda
follows how far the part's vertices and edges are from the mean; without, a part stops above tau times its share.
Rounds are distributed: only a row for each part reaches the driver, and all state lies in the shared folder. A graph
of no more than `local_limit` edges runs the same rounds over arrays within one task instead, with the same result.
"""

from __future__ import annotations

import hashlib
import json
import math
import sys
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from hubgraph.core.model import PropertyGraph
from hubgraph.core.portable import bits
from hubgraph.partition import metrics, placement
from hubgraph.session import small_batches, stage

LAMBDA_MIN, LAMBDA_MAX = 1e-6, 1.0
LOCAL_LIMIT = 40_000_000  # edges whose rounds one task holds: some 25 bytes each, and some 50 for each vertex
LISTS_LIMIT = 200_000_000  # edges whose lists one task holds where only counts are asked for: 8 bytes each, and some 100 for each vertex
CHUNK = 1 << 18  # edges that arrays are worked over at once


@dataclass
class PartitionResult:
    edges: DataFrame | None
    trace: list[dict] = field(default_factory=list)
    counts: DataFrame | None = None  # (part, ne, nv, v, inside) in place of edges, where only these were asked for


def share_score(counts: list[int]) -> list[float]:
    """Each part's count over the mean; 1 where nothing is there yet."""
    mean = sum(counts) / len(counts)
    return [c / mean if mean else 1.0 for c in counts]


def next_lambda(speed: float, vs: float, es: float, alpha: float, beta: float) -> float:
    """The speed after a round: above the mean it falls, below it rises; the geometric mean over parts stays."""
    return math.exp(math.log(speed) + alpha * (1 - vs) + beta * (1 - es))


def quota(speed: float, boundary: int) -> int:
    return max(1, min(boundary, math.ceil(min(max(speed, LAMBDA_MIN), LAMBDA_MAX) * boundary)))


def _claims(rows: DataFrame, load: DataFrame, parts: int) -> DataFrame:
    """One part for each claimed edge: the least loaded, ties in an order turned by eid; packed into one long for hash aggregation."""
    packed = (F.col("load") * parts + F.expr(f"pmod(eid + part, {parts}L)")) * 4096 + F.col("part")
    return rows.join(F.broadcast(load), "part").groupBy("eid").agg(F.min(packed).alias("claim")).select("eid", (F.col("claim") % 4096).cast("int").alias("part"))


def start_vertices(every: DataFrame, degree: DataFrame, parts: int, start: str, salt: str) -> list[tuple[int, int]]:
    """(vid, part): where parts begin. "grid": the vertex of least hash of the part's slot of the grid placement;
    "vertices": the vertices of least hash, one each. A part without a slot's vertex begins when it is found starved."""
    if start == "vertices":
        return [(r.vid, k) for k, r in enumerate(degree.orderBy("h", "vid").limit(parts).collect())]
    ends = placement.place(every, parts, "hash2d").select("part", F.explode(F.array("src", "dst")).alias("vid"))
    low = ends.groupBy("part").agg(F.min(F.struct(bits(salt, "vid").alias("h"), "vid")).alias("low"))
    return sorted((r.low.vid, r.part) for r in low.collect())


def expand(graph: PropertyGraph, parts: int, *, steer: bool, lambda0: float = 0.1, alpha: float = 1.0, beta: float = 1.0, tau: float = 1.1, max_rounds: int = 200, tail: float = 0.02, round_share: float | None = 0.02, start: str = "vertices", salt: str = "s", local_limit: int | None = None, counts_only: bool = False) -> PartitionResult:
    """Edges (eid, src, dst, part) and the trace of rounds. Vertices are in the order of a hash with `salt`.

    When no more than the share `tail` of the edges is free, or after max_rounds, each of the rest goes in one pass to
    its ends' least loaded part. In a round a part takes vertices of about round_share of its fair share of edges at
    most, so that steering can act before a part runs away (None: no such bound). A part whose boundary is empty while edges are free starts again at another vertex.
    With counts_only the rounds within a task return counts of parts, and no edges are written out.
    """
    spark = graph.edges.sparkSession
    rules = {"parts": parts, "steer": steer, "lambda0": lambda0, "alpha": alpha, "beta": beta, "tau": tau, "max_rounds": max_rounds, "tail": tail}
    if counts_only and lists.in_lists(rules):
        packed, total, heads = lists.pack_lists(graph, parts)
        if not total:
            return PartitionResult(spark.createDataFrame([], "eid long, src long, dst long, part int"))
        if total <= (LISTS_LIMIT if local_limit is None else local_limit):
            counts = lists.counts_in_task(packed, total, heads, start, salt, rules | {"cap": round_cap(total, parts, round_share)})
            return PartitionResult(None, json.loads(counts.where("trace is not null").first().trace), counts.drop("trace"))
    packed, total = pack_edges(graph, parts)
    if not total:
        return PartitionResult(unpacked(packed).withColumn("part", F.lit(0)))
    cap = round_cap(total, parts, round_share)
    if total <= (LOCAL_LIMIT if local_limit is None else local_limit):
        return _expand_in_task(packed, start, salt, rules | {"cap": cap}, total, counts_only)
    every = stage(unpacked(packed))
    degree = stage(every.select(F.explode(F.array("src", "dst")).alias("vid")).groupBy("vid").agg(F.count("*").alias("d")).withColumn("h", bits(salt, "vid")))
    free, placed = every, []
    replicas = stage(spark.createDataFrame(start_vertices(every, degree, parts, start, salt), "vid long, part int"))
    nv, ne, speed, trace, left = [1] * parts, [0] * parts, [lambda0] * parts, [], total
    for number in range(max_rounds):
        if left <= tail * total:
            break
        vs, es = share_score(nv), share_score(ne)
        if steer:
            speed = [next_lambda(*x, alpha, beta) for x in zip(speed, vs, es, strict=True)]
        live = [p for p in range(parts) if steer or ne[p] <= tau * total / parts]
        ends = free.select(F.explode(F.array("src", "dst")).alias("vid")).distinct()
        boundary = stage(replicas.where(F.col("part").isin(live)).join(ends, "vid", "left_semi").join(degree, "vid"))
        counts = {r.part: r.n for r in boundary.groupBy("part").agg(F.count("*").alias("n")).collect()}
        starved = [p for p in live if p not in counts]
        if starved:
            fresh = ends.join(degree, "vid").orderBy("h", "vid").limit(len(starved)).collect()
            extra = spark.createDataFrame([(r.vid, p) for r, p in zip(fresh, starved, strict=False)], "vid long, part int")
            replicas = stage(replicas.union(extra).distinct())
            boundary = stage(boundary.unionByName(extra.join(degree, "vid")))
            counts |= {p: 1 for p, _ in zip(starved, fresh, strict=False)}
        want = spark.createDataFrame([(p, quota(speed[p], n)) for p, n in counts.items()], "part int, quota int")
        # Degree histogram of each part, cut where the quota is met; only the cut degree itself is ranked.
        histogram = boundary.groupBy("part", "d").agg(F.count("*").alias("n"))
        below = F.sum("n").over(Window.partitionBy("part").orderBy("d")) - F.col("n")
        ends_below = F.sum(F.col("n") * F.col("d")).over(Window.partitionBy("part").orderBy("d")) - F.col("n") * F.col("d")
        room = F.least(F.col("quota") - F.col("below"), F.greatest(F.lit(1), F.ceil((F.lit(cap) - F.col("ends_below")) / F.col("d"))))
        cuts = histogram.withColumn("below", below).withColumn("ends_below", ends_below).join(F.broadcast(want), "part").where((F.col("below") < F.col("quota")) & (F.col("ends_below") < cap)).select("part", "d", room.alias("room"), "n")
        chosen = boundary.join(cuts, ["part", "d"])
        whole = chosen.where("n <= room").select("vid", "part")
        rank = F.row_number().over(Window.partitionBy("part", "d").orderBy("h", "vid"))
        partly = chosen.where("n > room").withColumn("r", rank).where("r <= room").select("vid", "part")
        selected = stage(whole.union(partly))
        load = spark.createDataFrame([(p, ne[p]) for p in range(parts)], "part int, load long")
        at_ends = free.join(selected.withColumnRenamed("vid", "src"), "src").select("eid", "part").union(free.join(selected.withColumnRenamed("vid", "dst"), "dst").select("eid", "part"))
        one = stage(free.join(_claims(at_ends, load, parts), "eid"))
        joined = one.select("part", F.explode(F.array("src", "dst")).alias("vid")).distinct()
        grown = stage(replicas.unionByName(joined.select("vid", "part")).distinct())
        new = grown.join(replicas, ["vid", "part"], "left_anti")
        rest = stage(free.join(one, "eid", "left_anti"))
        gained = {r.part: r.n for r in one.groupBy("part").agg(F.count("*").alias("n")).collect()}
        load = spark.createDataFrame([(p, ne[p] + gained.get(p, 0)) for p in range(parts)], "part int, load long")
        touched = rest.join(new.select(F.col("vid").alias("src")).distinct(), "src", "left_semi").unionByName(rest.join(new.select(F.col("vid").alias("dst")).distinct(), "dst", "left_semi").select("eid", "src", "dst")).distinct()
        shared = touched.join(grown.withColumnRenamed("vid", "src"), "src").join(grown.select(F.col("vid").alias("dst"), F.col("part").alias("other")), "dst").where("part = other").select("eid", "part")
        shared = shared.where(F.col("part").isin(live))
        two = stage(rest.join(_claims(shared, load, parts), "eid"))
        free, replicas = stage(rest.join(two, "eid", "left_anti")), grown
        placed += [one.select("eid", "src", "dst", "part"), two.select("eid", "src", "dst", "part")]
        for r in two.groupBy("part").agg(F.count("*").alias("n")).collect():
            gained[r.part] = gained.get(r.part, 0) + r.n
        sizes = {r.part: r.n for r in replicas.groupBy("part").agg(F.count("*").alias("n")).collect()}
        nv, ne = [sizes.get(p, 0) for p in range(parts)], [ne[p] + gained.get(p, 0) for p in range(parts)]
        left = total - sum(ne)
        trace += [{"round": number, "part": p, "speed": speed[p], "vs": vs[p], "es": es[p], "nv": nv[p], "ne": ne[p], "free": left, "reseeded": p in starved} for p in range(parts)]
    if left:
        load = spark.createDataFrame([(p, ne[p]) for p in range(parts)], "part int, load long")
        near = free.join(replicas.withColumnRenamed("vid", "src"), "src").select("eid", "part").union(free.join(replicas.withColumnRenamed("vid", "dst"), "dst").select("eid", "part"))
        last = free.join(_claims(near, load, parts), "eid", "left").withColumn("part", F.coalesce("part", F.expr(f"cast(pmod(eid, {parts}L) as int)")))
        placed.append(last.select("eid", "src", "dst", "part"))
    out = placed[0] if placed else every.withColumn("part", F.lit(0))
    for p in placed[1:]:
        out = out.unionByName(p)
    return PartitionResult(stage(out), trace)


def round_cap(total: int, parts: int, round_share: float | None) -> float:
    """Edge ends that a part may take in a round; more than there are where no bound is wanted."""
    return 2.0 * total + 1 if round_share is None else max(1.0, round_share * total / parts)


class EdgeArrays:
    """A graph as arrays. s and d are places in vid, which is sorted; order has the places in the order that breaks ties;
    turn is eid modulo parts. Vertices are numbered in the order that rounds take them in, by degree and then by `order`;
    edges lie by their source's number, `edge` has their places in what was given (where kept). The lists given are emptied."""

    def __init__(self, columns, deg, order, keep=True):
        import numpy as np

        turn, s, d = columns
        columns.clear()
        by_degree = order[np.argsort(deg[order], kind="stable")]
        self.deg, self.number_of = deg[by_degree], np.empty(len(deg), "int32")
        self.number_of[by_degree] = np.arange(len(deg))
        self.tied = self.number_of[order]

        def sort(ends):
            """Places of edges by their ends, and counts of the ends; an end and a place make one number, which sorts fast."""
            count = np.zeros(len(deg), "int32")
            key = np.empty(len(ends), "int64")
            for i in range(0, len(ends), CHUNK):
                x = ends[i : i + CHUNK]
                key[i : i + CHUNK] = (x.astype("int64") << 32) + np.arange(i, i + len(x))
                count += np.bincount(x, minlength=len(deg)).astype("int32")
            key.sort()
            if sys.byteorder != "little":
                return (key & 0xFFFFFFFF).astype("int32"), count
            low = key.view("int32")
            n = len(key)
            for i in range(0, n, CHUNK):  # in place, and what is left over is given back
                j = min(n, i + CHUNK)
                low[i:j] = low[2 * i : 2 * j : 2]
            del low
            key.resize(-(-n // 2), refcheck=False)
            return key.view("int32")[:n], count

        def each(kind, some):
            """some(slice) of all edges; indices of a chunk alone are widened."""
            out = np.empty(len(turn), kind)
            for i in range(0, len(out), CHUNK):
                at = slice(i, i + CHUNK)
                out[at] = some(at)
            return out

        s = each("int32", lambda at: self.number_of[s[at]])
        self.edge, sources = sort(s)
        s = None
        self.s = np.repeat(np.arange(len(deg), dtype="int32"), sources)
        self.d = each("int32", lambda at: self.number_of[d[self.edge[at]]])
        d = None
        self.turn = each(turn.dtype, lambda at: turn[self.edge[at]])
        turn = None
        if not keep:
            self.edge = None
        self.to, targets = sort(self.d)  # edges by their target
        self.sides = [(count, np.cumsum(count, dtype="int64") - count) for count in (sources, targets)]

    def around(self, vertices, part):
        """The free edges around distinct vertices, each once, in chunks."""
        import numpy as np

        found, inside = [], None
        for side, (count, begin) in enumerate(self.sides):
            v = vertices[count[vertices] > 0]
            if side and len(v) and found:
                inside = np.zeros(len(self.deg), bool)
                inside[vertices] = True
            ends = np.cumsum(count[v], dtype="int64")
            cuts = [0, *np.searchsorted(ends, np.arange(CHUNK, ends[-1], CHUNK)).tolist(), len(v)] if len(v) else [0]
            for a, b in zip(cuts, cuts[1:], strict=False):  # a chunk at a time, so that what is passing stays small
                n = count[v[a:b]]
                at = np.repeat(begin[v[a:b]] - (np.cumsum(n) - n), n) + np.arange(n.sum())
                if side:
                    at = self.to[at]
                at = at[part[at] < 0].astype("int32", copy=False)
                found.append(at if inside is None else at[~inside[self.s[at]]])
        return found


def array_rounds(g: EdgeArrays, seeds, *, parts, steer, lambda0, alpha, beta, tau, max_rounds, tail, cap):
    """The rounds of expand over arrays: (part of each edge of g, trace). seeds are (place, part).

    A round looks at the edges around the vertices that it takes and around new replicas, not at all free edges: a vertex
    is taken once and is new once a part, so all rounds together come to the order of edges times parts at most."""
    import numpy as np

    si, di, turn_of, deg = g.s, g.d, g.turn, g.deg
    total, size = len(si), len(deg)
    free_ends = deg.astype("int64" if total >= 1 << 30 else "int32")
    # Below zero an edge is free: -1, or, while parts claim it, the least of their ranks above `low`.
    low = next(np.iinfo(k) for k in ("int8", "int16", "int32", "int64") if parts * parts < np.iinfo(k).max)
    part, low = np.full(total, -1, low.dtype), low.min
    kind = next(k for k in ("uint8", "uint16", "uint32", "uint64") if parts <= 8 * np.dtype(k).itemsize or k == "uint64")
    width = 8 * np.dtype(kind).itemsize
    words = np.zeros((-(-parts // width), size), kind)  # the parts that hold a vertex, as bits
    bit = [(p // width, np.dtype(kind).type(1 << p % width)) for p in range(parts)]
    for v, p in seeds:
        words[bit[p][0], g.number_of[v]] |= bit[p][1]
    nv, ne, speed, trace, left = [1] * parts, [0] * parts, [lambda0] * parts, [], total

    def holds(p, at=slice(None)):
        return (words[bit[p][0]][at] & bit[p][1]) > 0

    replicas = [int(holds(p).sum()) for p in range(parts)]
    one, in_level = free_ends.dtype.type(1), (np.arange(parts * parts) % parts).astype(part.dtype)

    def claim(wants, load, join=False):
        """Gives each edge the least loaded of the parts that want it; edges of wants (part, edges) are free and come once a
        part, and wants is emptied. With join their ends become replicas. The new load."""
        level, given, count = np.unique(np.array(load), return_inverse=True)[1], [], np.array(load)
        while wants:  # the turn tells the part, so level and turn make an order of all parts
            p, at = wants.pop()
            at = at.astype("intp")
            ranks = (low + level[p] * parts + (np.arange(parts) + p) % parts).astype(part.dtype)
            before, mine = part[at], ranks[turn_of[at]]
            new = before == -1
            given.append((at if new.all() else at[new]).astype("int32"))
            part[at] = np.minimum(before, mine)
        while given:
            whole = given.pop()
            for i in range(0, len(whole), CHUNK):
                at = whole[i : i + CHUNK].astype("intp")
                to = in_level[part[at] - low] - turn_of[at]
                to[to < 0] += parts
                part[at] = to
                gained = np.bincount(to, minlength=parts)
                count += gained
                groups = [(p, to == p) for p in np.flatnonzero(gained).tolist()] if join else []
                for side in (si, di):
                    ends = side[at].astype("intp")
                    np.subtract.at(free_ends, ends, one)
                    for p, mine in groups:
                        word, flag = words[bit[p][0]], bit[p][1]
                        v = ends if len(groups) == 1 else ends[mine]
                        word[v] |= flag
        return count.tolist()

    def taken(p, mask):
        """The vertices of mask that part p takes: as many as its quota, of about cap edge ends."""
        n = quota(speed[p], int(np.count_nonzero(mask)))
        found, have, ends = [], 0, 0
        for i in range(0, size, CHUNK):
            v = np.flatnonzero(mask[i : i + CHUNK]) + i
            v = v[: n - have]
            below = np.cumsum(deg[v]) - deg[v] + ends
            found.append(v[below < cap])
            have += len(v)
            if have == n or len(found[-1]) < len(v):
                break
            ends += int(deg[v].sum())
        return np.concatenate(found)

    for number in range(max_rounds):
        if left <= tail * total:
            break
        vs, es = share_score(nv), share_score(ne)
        if steer:
            speed = [next_lambda(*x, alpha, beta) for x in zip(speed, vs, es, strict=True)]
        live = [p for p in range(parts) if steer or ne[p] <= tau * total / parts]
        open_ = free_ends > 0
        edge_of = {p: holds(p) & open_ for p in live}
        starved = [p for p in live if not edge_of[p].any()]
        if starved:
            for p, v in zip(starved, g.tied[np.flatnonzero(open_[g.tied])[: len(starved)]], strict=False):
                edge_of[p][v] = True
                words[bit[p][0], v] |= bit[p][1]
                replicas[p] += 1
        wants = []
        for p in live:
            if edge_of[p].any():
                wants += [(p, at) for at in g.around(taken(p, edge_of[p]), part)]
        del edge_of
        old = words.copy()
        ne = claim(wants, ne, join=True)
        old ^= words
        fresh = np.flatnonzero(old[0] != 0 if len(old) == 1 else old.any(axis=0))
        for p in range(parts):
            replicas[p] += int(np.count_nonzero(old[bit[p][0], fresh] & bit[p][1]))
        del old
        wants, near = [], g.around(fresh[free_ends[fresh] > 0], part)
        while near:
            at = near.pop()
            s, d = si[at], di[at]
            for w, word in enumerate(words):
                common = word[s]
                common &= word[d]
                some = np.flatnonzero(common != 0)
                here, common = at[some], common[some]
                for p in live:
                    if bit[p][0] == w and len(mine := here[(common & bit[p][1]) > 0]):
                        wants.append((p, mine))
        ne = claim(wants, ne)
        nv, left = list(replicas), total - sum(ne)
        trace += [{"round": number, "part": p, "speed": speed[p], "vs": vs[p], "es": es[p], "nv": nv[p], "ne": ne[p], "free": left, "reseeded": p in starved} for p in range(parts)]
    at = np.flatnonzero(part < 0).astype("int32")
    claim([(p, at[holds(p, si[at]) | holds(p, di[at])]) for p in range(parts)], ne)
    at = np.flatnonzero(part < 0)
    part[at] = turn_of[at]
    return part, trace


PACKED = "n long, turn binary, eid binary, src binary, dst binary, vid binary"
#: Row groups stay small, so that neither a writer nor a reader of columns holds many blobs at once.
BLOB_FILES = {"parquet.block.size": str(8 << 20), "parquet.block.size.row.check.min": "1", "parquet.page.size.row.check.min": "1", "parquet.enable.dictionary": "false"}
BLOB = 1 << 15  # edges a row


def pack_edges(graph: PropertyGraph, parts: int) -> tuple[DataFrame, int]:
    """Edges as blobs of columns, BLOB to a row, and the distinct ends of each partition, in rows of their own (n is 0);
    the number of edges. All tasks pack, so that one task can take in a graph at a small part of what rows cost."""
    kind = "int8" if parts < 128 else "int16"

    def pack(batches):
        import numpy as np
        import pyarrow as pa

        schema = pa.schema([("n", pa.int64()), *((c, pa.binary()) for c in ("turn", "eid", "src", "dst", "vid"))])
        held, count, ends, fresh = [], 0, np.zeros(0, "int64"), []

        def row(eid, src, dst):
            blobs = [x.tobytes() for x in ((eid % parts).astype(kind), eid, src, dst)]
            return pa.RecordBatch.from_arrays([pa.array([len(eid)], pa.int64()), *(pa.array([x], pa.binary()) for x in blobs), pa.nulls(1, pa.binary())], schema=schema)

        def merged():
            return distinct([ends, *fresh])

        for b in batches:
            held.append([b.column(c).to_numpy() for c in ("eid", "src", "dst")])
            count += b.num_rows
            while count >= BLOB:
                eid, src, dst = (np.concatenate(x) for x in zip(*held, strict=True))
                yield row(eid[:BLOB], src[:BLOB], dst[:BLOB])
                fresh.append(distinct([src[:BLOB], dst[:BLOB]]))
                held, count = [[x[BLOB:].copy() for x in (eid, src, dst)]], count - BLOB
                if sum(map(len, fresh)) > max(len(ends), 8 * BLOB):
                    ends, fresh = merged(), []
        if count:
            eid, src, dst = (np.concatenate(x) for x in zip(*held, strict=True))
            yield row(eid, src, dst)
            fresh.append(np.concatenate([src, dst]))
        ends = merged()
        for i in range(0, len(ends), BLOB):
            none = [pa.nulls(1, pa.binary())] * 4
            yield pa.RecordBatch.from_arrays([pa.array([0], pa.int64()), *none, pa.array([ends[i : i + BLOB].tobytes()], pa.binary())], schema=schema)

    small_batches(graph.edges.sparkSession)  # else a batch holds many blobs
    packed = stage(graph.edges.select("eid", "src", "dst").mapInArrow(pack, PACKED), **BLOB_FILES)
    return packed, packed.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]


def unpacked(packed: DataFrame) -> DataFrame:
    """(eid, src, dst), a row an edge."""

    def rows(batches):
        import numpy as np
        import pyarrow as pa

        for b in batches:
            for blobs in zip(*(b.column(c) for c in ("eid", "src", "dst")), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(x.as_buffer(), "int64")) for x in blobs], ["eid", "src", "dst"])

    return packed.where("n > 0").select("eid", "src", "dst").mapInArrow(rows, "eid long, src long, dst long")


def _rows(packed: DataFrame, keep: bool) -> DataFrame:
    """Blobs of vertices, then of edges, for one task; with eid where it is to be kept."""
    none = F.lit(None).cast("binary")
    vertices = packed.where("n = 0").select("vid", *(none.alias(c) for c in ("turn", "eid", "src", "dst")))
    return vertices.union(packed.where("n > 0").select(none.alias("vid"), "turn", "eid" if keep else none.alias("eid"), "src", "dst")).coalesce(1)


def _md5_heads(texts):
    """The first eight hex digits of the md5 of each row of bytes, at most 55 to a row, as numbers; over arrays, which costs
    a tenth of a call for each row."""
    import numpy as np

    size = texts.shape[1]
    block = np.zeros((len(texts), 64), "uint8")
    block[:, :size], block[:, size] = texts, 0x80
    block[:, 56:58] = 8 * size & 255, 8 * size >> 8
    words = np.ascontiguousarray(block.view("<u4").T)
    used = [i == 14 or 4 * i <= size for i in range(16)]
    one = np.uint32
    first = a = np.full(len(texts), 0x67452301, "uint32")
    b, c, d = (np.full(len(texts), x, "uint32") for x in (0xEFCDAB89, 0x98BADCFE, 0x10325476))
    for i in range(64):
        if i < 16:
            mix, k = d ^ (b & (c ^ d)), i
        elif i < 32:
            mix, k = c ^ (d & (b ^ c)), (5 * i + 1) % 16
        elif i < 48:
            mix, k = b ^ c ^ d, (3 * i + 5) % 16
        else:
            mix, k = c ^ (b | ~d), 7 * i % 16
        mix += a
        mix += one(int(abs(math.sin(i + 1)) * 2**32))
        if used[k]:
            mix += words[k]
        turn = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))[i // 16][i % 4]
        a, d, c, b = d, c, b, b + ((mix << one(turn)) | (mix >> one(32 - turn)))
    return (first + a).byteswap()


def hashes(salt: str, vid):
    """What bits(salt, vid) is, for an array of ids."""
    import numpy as np

    out, head = np.empty(len(vid), "int64"), f"{salt}:".encode()
    powers = 10 ** np.arange(1, 19, dtype="int64")
    for i in range(0, len(vid), 1 << 14):  # so few that what is passing stays in the processor's cache
        x = vid[i : i + (1 << 14)]
        digits = np.where(x < 0, 0, np.searchsorted(powers, x, side="right") + 1)
        for n in np.unique(digits).tolist():
            at = np.flatnonzero(digits == n)
            if not n or len(head) + n > 55:
                out[i + at] = [int(hashlib.md5(b"%b%d" % (head, v)).hexdigest()[:8], 16) for v in x[at].tolist()]
                continue
            texts, left = np.empty((len(at), len(head) + n), "uint8"), x[at]
            texts[:, : len(head)] = np.frombuffer(head, "uint8")
            for k in range(len(head) + n - 1, len(head) - 1, -1):
                rest = left // 10
                texts[:, k], left = 48 + (left - 10 * rest), rest
            out[i + at] = _md5_heads(texts)
    return out


def distinct(arrays):
    """The distinct values of int64 arrays, sorted; numpy's own way hashes them first."""
    import numpy as np

    x = np.concatenate(arrays)
    x.sort()
    return x[np.append(True, x[1:] != x[:-1])] if len(x) else x


def order_by_hash(salt: str, vid):
    """Places of the sorted ids vid by their hash, ties by id; an id's hash and place make one number, which sorts fast."""
    import numpy as np

    key = (hashes(salt, vid) << 31) + np.arange(len(vid))
    key.sort()
    return (key & ((1 << 31) - 1)).astype("int32")


def first_in_slots(vid, s, d, order, grid, parts):
    """(place, part) of the first vertex of `order` in each part's slot of the grid placement; grid: a vertex's row and column."""
    import numpy as np

    tie, lowest, (row, column) = np.empty(len(vid), "int32"), np.full(parts, len(vid), "int32"), grid
    tie[order] = np.arange(len(vid), dtype="int32")
    for i in range(0, len(s), CHUNK):
        x, y = s[i : i + CHUNK], d[i : i + CHUNK]
        np.minimum.at(lowest, row[x] + column[y], np.minimum(tie[x], tie[y]))
    return [(int(order[v]), p) for p, v in enumerate(lowest.tolist()) if v < len(vid)]


def grid_of(vid, parts):
    """What a vertex adds to the number of an edge's slot in the grid placement, as a source and as a target."""
    rows, across = placement.grid_shape(parts)
    return (hashes("pr", vid) % rows * across).astype("int32"), (hashes("pc", vid) % across).astype("int32")


class Places:
    """Places of ids in a sorted array of distinct ids, by a hash table with linear probing."""

    def __init__(self, ids):
        import numpy as np

        self.ids, self.bits = ids, max(4, int(2 * len(ids)).bit_length())
        self.slots = np.full(1 << self.bits, -1, "int32")
        left = np.arange(len(ids), dtype="int32")
        at = self._hash(ids)
        while len(left):
            free = self.slots[at] < 0
            self.slots[at[free]] = left[free]
            lost = self.slots[at] != left
            left, at = left[lost], (at[lost] + 1) & (len(self.slots) - 1)

    def _hash(self, x):
        import numpy as np

        return ((x.astype("uint64") * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype("intp")

    def of(self, x):
        """The places of x; -1 where an id is not there."""
        import numpy as np

        if not len(self.ids):
            return np.full(len(x), -1, "int32")
        at = self._hash(x)
        out = self.slots[at]
        left = np.flatnonzero((out >= 0) & (self.ids[out] != x))
        while len(left):
            at[left] = (at[left] + 1) & (len(self.slots) - 1)
            out[left] = found = self.slots[at[left]]
            left = left[(found >= 0) & (self.ids[found] != x[left])]
        return out


def _arrays(batches, parts, total, keep=False):
    """(vid, deg, turn, s, d, eid) of _rows with total edges: vid is sorted, s and d are places in it; eid is kept where asked for."""
    import numpy as np

    kind = "int8" if parts < 128 else "int16"
    turn, s, d = np.empty(total, kind), np.empty(total, "int32"), np.empty(total, "int32")
    eids = np.empty(total, "int64") if keep else None
    fresh, late, places, done = [], [], Places(np.zeros(0, "int64")), 0

    def merged():
        return distinct([places.ids, *fresh])

    def add(turns, eid, src, dst):
        nonlocal done
        at = slice(done, done + len(turns))
        turn[at], s[at], d[at] = turns, src, dst
        if keep:
            eids[at] = eid
        done += len(turns)

    for b in batches:
        for vid, *blobs in zip(*(b.column(c) for c in ("vid", "turn", "eid", "src", "dst")), strict=True):
            if vid.is_valid:
                fresh.append(np.frombuffer(vid.as_buffer(), "int64").copy())
                continue
            if fresh and not done:
                places, fresh = Places(merged()), []
            turns, eid, src, dst = (np.frombuffer(x.as_buffer(), k) if x.is_valid else None for x, k in zip(blobs, (kind, "int64", "int64", "int64"), strict=True))
            if not fresh and len(places.ids):
                x, y = places.of(src), places.of(dst)
                if min(x.min(), y.min()) >= 0:
                    add(turns, eid, x, y)
                    continue
            late.append([None if x is None else x.copy() for x in (turns, eid, src, dst)])
    if late or fresh:  # edges that came before vertices
        vid_old, places = places.ids, Places(merged())
        for x in (s, d) if done else ():
            x[:done] = places.of(vid_old[x[:done]])
        for turns, eid, src, dst in late:
            add(turns, eid, places.of(src), places.of(dst))
    if done != total:
        raise ValueError(f"{done} edges came, {total} were counted")
    deg = np.zeros(len(places.ids), "int64")
    for i in range(0, total, CHUNK):
        for x in (s, d):
            deg += np.bincount(x[i : i + CHUNK], minlength=len(deg))
    return places.ids, deg, turn, s, d, eids


def held_counts(g: EdgeArrays, part, parts):
    """(edges, vertices) of each part, and the vertices that lie in one part only."""
    import numpy as np

    ne, nv, times = np.bincount(part, minlength=parts), np.zeros(parts, "int64"), np.zeros(len(g.deg), "int16")
    for p in range(parts):
        of_part = np.zeros(len(g.deg), bool)
        for i in range(0, len(part), CHUNK):
            at = np.flatnonzero(part[i : i + CHUNK] == p) + i
            of_part[g.s[at]] = of_part[g.d[at]] = True
        nv[p] = of_part.sum()
        times += of_part
    return ne, nv, int((times == 1).sum())


def _expand_in_task(packed, start, salt, rules, total, counts_only=False) -> PartitionResult:
    """The rounds of expand over arrays in one task; the caller has checked the number of edges."""
    parts = rules["parts"]

    def grow(batches):
        import numpy as np
        import pyarrow as pa

        vid, deg, turn, s, d, eid = _arrays(batches, parts, total, keep=not counts_only)
        order, columns = order_by_hash(salt, vid), [turn, s, d]
        begin = [(int(v), p) for p, v in enumerate(order[:parts])] if start == "vertices" else first_in_slots(vid, s, d, order, grid_of(vid, parts), parts)
        if counts_only:
            del turn, s, d
        g = EdgeArrays(columns, deg, order, keep=not counts_only)
        made, trace = array_rounds(g, begin, **rules)
        if counts_only:
            ne, nv, inside = held_counts(g, made, parts)
            yield pa.RecordBatch.from_pydict({"part": pa.array(range(parts), pa.int32()), "ne": pa.array(ne, pa.int64()), "nv": pa.array(nv, pa.int64()), "v": pa.array([len(vid)] * parts, pa.int64()), "inside": pa.array([inside] * parts, pa.int64()), "trace": pa.array([json.dumps(trace)] + [None] * (parts - 1), pa.string())})
            return
        part = np.empty(total, "int32")
        part[g.edge] = made
        for i in range(0, total, 1 << 16):
            k = slice(i, i + (1 << 16))
            yield pa.RecordBatch.from_pydict({"eid": eid[k], "src": vid[s[k]], "dst": vid[d[k]], "part": part[k], "trace": pa.nulls(len(eid[k]), pa.string())})
        yield pa.RecordBatch.from_pydict({"eid": pa.nulls(1, pa.int64()), "src": pa.nulls(1, pa.int64()), "dst": pa.nulls(1, pa.int64()), "part": pa.nulls(1, pa.int32()), "trace": [json.dumps(trace)]})

    kinds = "part int, ne long, nv long, v long, inside long, trace string" if counts_only else "eid long, src long, dst long, part int, trace string"
    done = stage(_rows(packed, keep=not counts_only).mapInArrow(grow, kinds))
    trace = json.loads(done.where("trace is not null").first().trace)
    if counts_only:
        return PartitionResult(None, trace, done.drop("trace"))
    return PartitionResult(done.where("trace is null").select("eid", "src", "dst", "part"), trace)


def quality(partition, graph: PropertyGraph, parts: int, **options) -> DataFrame:
    """The report of what bse_partition or tse_partition makes, from counts alone where the rounds run over arrays."""
    made = partition(graph, parts, counts_only=True, **options)
    return metrics.partition_report(made.edges, parts) if made.counts is None else metrics.counted_report(made.counts)


STUDY = "start string, steered boolean, round_share double, vertex_order int, rf double, vb double, eb double, rounds int"


def balance_study(graph: PropertyGraph, parts: int, *, orders: int = 5, shares=(0.02, None), starts=("grid", "vertices"), local_limit: int | None = None) -> DataFrame:
    """A row (STUDY) for each run: steered and constant speed, from each start and with each bound of a round, in several
    vertex orders.

    Up to local_limit edges the runs of a vertex order are one task's, or those of two over the same lists where edges are many
    (over arrays beyond lists.MOST_PARTS parts); larger graphs' runs follow each other."""
    spark = graph.edges.sparkSession
    no_rows = [F.lit(None).cast(kind).alias(name) for name, kind in (x.split() for x in STUDY.split(", "))]
    fixed = {"lambda0": 0.1, "alpha": 1.0, "beta": 1.0, "tau": 1.1, "max_rounds": 200, "tail": 0.02}
    if lists.in_lists(fixed | {"parts": parts}):
        packed, total, heads = lists.pack_lists(graph, parts)
        if total <= (LISTS_LIMIT if local_limit is None else local_limit):
            # Spark puts a union of children with one partition each into one task; no rows in two partitions keep it from that.
            out = spark.range(0, 2, 1, 2).where("id < 0").select(*no_rows)
            side_by_side = 2 if total > lists.PAIRED else 1
            for first in range(0, orders if total else 0, side_by_side):
                mine = range(first, min(orders, first + side_by_side))
                out = out.union(lists.rows_of(packed).mapInArrow(lists.study_task(mine, parts, total, heads, starts, shares, fixed), STUDY))
            return out
    packed, total = pack_edges(graph, parts)
    if not total:
        return spark.createDataFrame([], STUDY)
    runs = [(start, steer, share, f"s{k}", k) for k in range(orders) for start in starts for share in shares for steer in (True, False)]
    if total > (LOCAL_LIMIT if local_limit is None else local_limit):
        out = None
        for start, steer, share, salt, k in runs:
            r = expand(graph, parts, steer=steer, round_share=share, start=start, salt=salt, local_limit=local_limit)
            row = metrics.partition_report(r.edges, parts).select(F.lit(start).alias("start"), F.lit(steer).alias("steered"), F.lit(share).cast("double").alias("round_share"), F.lit(k).alias("vertex_order"), "rf", "vb", "eb", F.lit(len(r.trace) // parts).alias("rounds"))
            out = row if out is None else out.union(row)
        return out

    def task(order):
        def run(batches):
            import numpy as np
            import pyarrow as pa

            vid, deg, turn, s, d, _ = _arrays(batches, parts, total)
            by_hash = order_by_hash(f"s{order}", vid)
            lowest = first_in_slots(vid, s, d, by_hash, grid_of(vid, parts), parts) if "grid" in starts else []
            columns = [turn, s, d]
            del turn, s, d
            g = EdgeArrays(columns, deg, by_hash, keep=False)
            out = []
            for start, steer, share, _, k in runs:
                if k != order:
                    continue
                seeds = [(int(v), p) for p, v in enumerate(by_hash[:parts])] if start == "vertices" else lowest
                part, trace = array_rounds(g, seeds, parts=parts, steer=steer, lambda0=0.1, alpha=1.0, beta=1.0, tau=1.1, max_rounds=200, tail=0.02, cap=round_cap(total, parts, share))
                ne, nv, _ = held_counts(g, part, parts)
                ratio = lambda x: float(x.max() / x.min()) if x.min() else None
                out.append({"start": start, "steered": steer, "round_share": share, "vertex_order": k, "rf": float(nv.sum() / len(vid)), "vb": ratio(nv), "eb": ratio(ne), "rounds": len(trace) // parts})
            kinds = pa.schema([("start", pa.string()), ("steered", pa.bool_()), ("round_share", pa.float64()), ("vertex_order", pa.int32()), ("rf", pa.float64()), ("vb", pa.float64()), ("eb", pa.float64()), ("rounds", pa.int32())])
            yield pa.RecordBatch.from_pylist(out, schema=kinds)

        return run

    # A task for each order, in one stage; each reads the edges itself, so that none are shuffled.
    out = spark.range(0, 2, 1, 2).where("id < 0").select(*no_rows)
    for order in range(orders):
        out = out.union(_rows(packed, keep=False).mapInArrow(task(order), STUDY))
    return out


def balance_claim(study: DataFrame) -> DataFrame:
    """(start, round_share, measure, steered, constant, lower_in, orders): medians over vertex orders, and in how many of them
    steering gave the lower figure."""
    out = None
    for m in ("rf", "vb", "eb"):
        pair = study.groupBy("start", "round_share", "vertex_order").agg(F.max(F.when(F.col("steered"), F.col(m))).alias("a"), F.max(F.when(~F.col("steered"), F.col(m))).alias("b"))
        row = pair.groupBy("start", "round_share").agg(F.lit(m).alias("measure"), F.round(F.median("a"), 4).alias("steered"), F.round(F.median("b"), 4).alias("constant"), F.count_if(F.col("a") < F.col("b")).alias("lower_in"), F.count("*").alias("orders"))
        out = row if out is None else out.union(row)
    return out


def bse_partition(graph: PropertyGraph, parts: int, **options) -> PartitionResult:
    """Balance-steered expansion."""
    return expand(graph, parts, steer=True, **options)


def tse_partition(graph: PropertyGraph, parts: int, **options) -> PartitionResult:
    """Threshold-stopped expansion: constant speed."""
    return expand(graph, parts, steer=False, **options)


from hubgraph.partition import lists  # noqa: E402 (it takes the rounds' rules from here)
