"""Exact top-k by inner product through a pivot-distance index.

Inner product becomes distance by one more coordinate: with M the largest squared norm, x gets sqrt(M - |x|^2) and a
query 0, so |q - x|^2 = |q|^2 + M - 2 q.x. Every vector is keyed by its nearest pivot and the distance to it, and
sorted annuli of a pivot make blocks. Queries of one home pivot go together. They first search the annulus they fall
into, which bounds the k-th score of each; then they expand to the other annuli of each pivot, and a query passes an
annulus over where the triangle inequality says that nothing in it can reach the query's own bound.

Vectors are moved once, to their annulus; queries are sent to the annuli that they must search.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubgraph.llm.common import in_arrow, stage

SCALE = 64
#: Vectors of an annulus, queries that go together, and the bounds of the number of pivots, which grows with the data.
BLOCK, TOGETHER, PIVOTS = 4096, 512, (8, 512)
SAMPLE = 64  # sampled vectors for each pivot
SLACK = 1e-6  # of the largest distance: bounds are loosened by more than rounding can move them
LEAST, MOST = np.iinfo(np.int64).min, np.iinfo(np.int64).max


def quantise(vectors: pa.Array) -> tuple[list[np.ndarray], np.ndarray]:
    """floor(64 x) of each vector, as doubles, which hold it exactly, and which rows take part."""
    if isinstance(vectors, pa.ChunkedArray):
        vectors = vectors.combine_chunks()
    off = vectors.offsets.to_numpy()
    flat = vectors.values.slice(off[0], off[-1] - off[0])
    x = flat.to_numpy(zero_copy_only=False).astype(float)
    bad = np.r_[0, np.cumsum(~np.isfinite(x) | ~np.isfinite(SCALE * x))]
    off = off - off[0]
    ok = (bad[off[1:]] == bad[off[:-1]]) & np.asarray(vectors.is_valid())
    with np.errstate(all="ignore"):
        whole = np.floor(SCALE * x)
    return [whole[s:e] for s, e in zip(off[:-1], off[1:], strict=True)], ok


def _ready(batches):
    for b in batches:
        rows, ok = quantise(b.column("embedding"))
        keep = np.nonzero(ok & np.asarray(b.column("vec_id").is_valid()))[0]
        with np.errstate(over="ignore"):
            norm = [float(rows[i] @ rows[i]) for i in keep]
        yield pa.RecordBatch.from_arrays([b.column("vec_id").take(pa.array(keep)), b.column("rid").take(pa.array(keep)), pa.array([rows[i].tobytes() for i in keep], pa.binary()), pa.array(norm, pa.float64())], ["vec_id", "rid", "v", "norm"])


def _matrix(rows: list[bytes], width: int) -> np.ndarray:
    out = np.zeros((len(rows), width))
    for i, r in enumerate(rows):
        out[i, : len(r) // 8] = np.frombuffer(r)
    return out


def fit_pivots(m: np.ndarray, k: int, rounds: int = 6) -> np.ndarray:
    """Centres of a bounded sample by Lloyd's rounds, from evenly spread rows."""
    centre = m[np.linspace(0, len(m) - 1, min(k, len(m))).astype(int)].copy()
    for _ in range(rounds):
        near = _distance(m, centre).argmin(1)
        for c in range(len(centre)):
            if (near == c).any():
                centre[c] = m[near == c].mean(0)
    return centre


def _distance(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    with np.errstate(all="ignore"):
        d = (a**2).sum(1)[:, None] + (b**2).sum(1)[None, :] - 2 * a @ b.T
        return np.nan_to_num(np.sqrt(np.maximum(d, 0)), nan=0.0, posinf=0.0)


def scores(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Inner products of whole-numbered rows: floating point where that is exact, else integers of any size, held
    within a long at last."""
    with np.errstate(over="ignore"):
        small = max(np.abs(q).max(initial=0), 1) * max(np.abs(x).max(initial=0), 1) * max(q.shape[1], 1) < 2**52
    if small:
        return (q @ x.T).astype(np.int64)
    whole = lambda m: np.array([[int(v) for v in r] for r in m], object).reshape(m.shape)
    exact = whole(q) @ whole(x).T
    return np.array([[min(max(v, LEAST + 1), MOST) for v in r] for r in exact], np.int64).reshape(len(q), len(x))


def best(score: np.ndarray, ids: np.ndarray, ok: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, column) of each row's k best among those that are ok, ties to the smaller id."""
    if score.shape[1] > k:
        kth = np.partition(np.where(ok, score, LEAST), score.shape[1] - k, axis=1)[:, score.shape[1] - k]
        ok = ok & (score >= kth[:, None])
    i, j = np.nonzero(ok)
    order = np.lexsort((ids[j], -score[i, j], i))
    i, j = i[order], j[order]
    keep = np.arange(len(i)) - np.searchsorted(i, i) < k
    return i[keep], j[keep]


FOUND = "rid long, query_id long, vec_id long, score long, products long"
ANNULUS = "block string, pivot int, lo double, hi double, x_ids array<long>, x_rids array<long>, x_vs array<binary>"
QUERY = "qb string, home int, q_ids array<long>, q_rids array<long>, q_vs array<binary>, q_norms array<double>, bound_s array<long>, bound_id array<long>"


def _search(k: int, width: int, pivots: np.ndarray, most: float):
    """Rows sorted by block, in each the annulus and then the query groups that search it: each query's best rows in
    it that beat its bound. A row without a query counts the products that were taken."""
    slack = SLACK * (np.sqrt(most) + 1)

    def run(batches):
        block = x = None
        for b in batches:
            for r in b.to_pylist():
                if r["x_ids"] is not None:
                    block, x = r, _matrix(r["x_vs"], width)
                    xid, xrid = np.array(r["x_ids"], np.int64), np.array(r["x_rids"], np.int64)
                    continue
                if block is None or r["block"] != block["block"]:
                    continue
                q, norm = _matrix(r["q_vs"], width), np.array(r["q_norms"])
                qid, qrid, bs, bi = (np.array(r[c], np.int64) for c in ("q_ids", "q_rids", "bound_s", "bound_id"))
                d = _distance(np.c_[q, np.zeros(len(q))], pivots[block["pivot"] : block["pivot"] + 1])[:, 0]
                reach = _reach(norm, bs, most) + slack
                use = np.nonzero((d + reach >= block["lo"]) & (d - reach <= block["hi"]))[0]
                if not len(use):
                    continue
                q, qid, qrid, bs, bi = q[use], qid[use], qrid[use], bs[use], bi[use]
                score = scores(q, x)
                ok = (score > bs[:, None]) | ((score == bs[:, None]) & (xid[None, :] < bi[:, None]))
                ok &= qrid[:, None] != xrid[None, :]
                i, j = best(score, xid, ok, k)
                yield _found(qrid[i], qid[i], xid[j], score[i, j], score.size)

    return run


def _found(rid, qid, xid, score, products):
    none = pa.array([None], pa.int64())
    parts = [pa.concat_arrays([pa.array(c, pa.int64()), none]) for c in (rid, qid, xid, score)]
    return pa.RecordBatch.from_arrays([*parts, pa.concat_arrays([pa.nulls(len(rid), pa.int64()), pa.array([products], pa.int64())])], ["rid", "query_id", "vec_id", "score", "products"])


def _reach(norm: np.ndarray, bound: np.ndarray, most: float) -> np.ndarray:
    """The distance within which a row may still reach the bound; without end where nothing bounds it."""
    if not np.isfinite(most):
        return np.full(len(norm), np.inf)
    return np.where(bound == LEAST, np.inf, np.sqrt(np.maximum(norm + most - 2 * bound.astype(float), 0)))


def _blocks(size: int):
    """Rows sorted by pivot and distance, by bucket, to annuli of `size` rows of one bucket at most."""

    def run(batches):
        held, number = [], 0

        def flush():
            ids, rids, vs, ds = zip(*((r[0], r[1], r[2], r[5]) for r in held), strict=True)
            return pa.RecordBatch.from_pydict({"block": pa.array([f"{held[0][3]}-{held[0][4]}-{number}"]), "pivot": pa.array([held[0][3]], pa.int32()), "lo": pa.array([ds[0]]), "hi": pa.array([ds[-1]]), "x_ids": pa.array([ids], pa.list_(pa.int64())), "x_rids": pa.array([rids], pa.list_(pa.int64())), "x_vs": pa.array([vs], pa.list_(pa.binary()))})

        for b in batches:
            for r in zip(*(b.column(c).to_pylist() for c in ("vec_id", "rid", "v", "pivot", "bucket", "dist")), strict=True):
                new = held and held[0][3:5] != r[3:5]
                if held and (new or len(held) == size):
                    yield flush()
                    held, number = [], 0 if new else number + 1
                held.append(r)
        if held:
            yield flush()

    return run


def _groups(batches):
    """Queries sorted by home pivot and salt, in groups of TOGETHER at most; nothing bounds them yet."""
    held, number = [], 0

    def flush():
        ids, rids, vs, norms = zip(*(r[:4] for r in held), strict=True)
        lists = {"q_ids": (ids, pa.int64()), "q_rids": (rids, pa.int64()), "q_vs": (vs, pa.binary()), "q_norms": (norms, pa.float64()), "bound_s": ([LEAST] * len(ids), pa.int64()), "bound_id": ([LEAST] * len(ids), pa.int64())}
        return pa.RecordBatch.from_pydict({"qb": pa.array([f"{held[0][4]}-{held[0][5]}-{number}"]), "home": pa.array([held[0][4]], pa.int32())} | {n: pa.array([v], pa.list_(t)) for n, (v, t) in lists.items()})

    for b in batches:
        for r in zip(*(b.column(c).to_pylist() for c in ("vec_id", "rid", "v", "norm", "home", "salt")), strict=True):
            new = held and held[0][4:6] != r[4:6]
            if held and (new or len(held) == TOGETHER):
                yield flush()
                held, number = [], 0 if new else number + 1
            held.append(r)
    if held:
        yield flush()


def _merge(k: int):
    """Rows sorted by query, falling score and id: the first k of each query with their ranks."""

    def run(batches):
        last, n = None, 0
        for b in batches:
            q = b.column("rid").to_numpy()
            if not len(q):
                continue
            new = np.r_[q[0] != last, q[1:] != q[:-1]]
            start = np.maximum.accumulate(np.where(new, np.arange(len(q)), -1))
            rank = np.where(start < 0, n + 1 + np.arange(len(q)), np.arange(len(q)) - start + 1)
            last, n = q[-1], int(rank[-1])
            yield pa.RecordBatch.from_arrays([b.column("query_id"), pa.array(rank.astype(np.int32)), b.column("vec_id"), b.column("score")], ["query_id", "rank", "vec_id", "score"]).filter(pa.array(rank <= k))

    return run


def search_all(vectors: DataFrame, *, k: int = 20, every: int = 20, block: int = BLOCK, pivots: int | None = None) -> tuple[DataFrame, int, int]:
    """Best rows of all queries (rid, query_id, vec_id, score, products) before the last merge, with the number of queries and of rows."""
    spark, block = vectors.sparkSession, max(block, 2 * k)  # the first annulus must hold k rows to bound anything
    ready = vectors.select("vec_id", "embedding").withColumn("vec_id", F.col("vec_id").cast("long")).withColumn("rid", F.monotonically_increasing_id())
    ready = stage(ready.transform(in_arrow, _ready, "vec_id long, rid long, v binary, norm double"))
    asked = F.col("vec_id") % every == 0
    top = ready.agg(F.max("norm").alias("m"), F.coalesce(F.max(F.length("v")), F.lit(0)).alias("w"), F.count("*").alias("n"), F.count_if(asked).alias("q")).first()
    if not top.q:
        return spark.createDataFrame([], FOUND), 0, top.n
    width, most = top.w // 8, top.m
    k_pivots = pivots or min(max(PIVOTS[0], top.n // block), PIVOTS[1])
    sample = ready.orderBy(F.xxhash64("v"), "v").limit(SAMPLE * k_pivots).toArrow()

    def lifted(rows, norms):
        with np.errstate(all="ignore"):
            return np.c_[_matrix(rows, width), np.nan_to_num(np.sqrt(np.maximum(most - norms, 0)), nan=0.0, posinf=0.0)]

    centres = fit_pivots(lifted(sample["v"].to_pylist(), sample["norm"].to_numpy()), k_pivots)

    def keyed(batches):
        for b in batches:
            d = _distance(lifted(b.column("v").to_pylist(), b.column("norm").to_numpy()), centres)
            near = d.argmin(1)
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("vec_id", "rid", "v")), pa.array(near.astype(np.int32)), pa.array(d[np.arange(len(d)), near])], ["vec_id", "rid", "v", "pivot", "dist"])

    def homed(batches):
        for b in batches:
            d = _distance(np.c_[_matrix(b.column("v").to_pylist(), width), np.zeros(b.num_rows)], centres)
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("vec_id", "rid", "v", "norm")), pa.array(d.argmin(1).astype(np.int32))], ["vec_id", "rid", "v", "norm", "home"])

    index = stage(ready.transform(in_arrow, keyed, "vec_id long, rid long, v binary, pivot int, dist double"))
    # Sorted annuli: each pivot's distances are cut at quantiles, so that a bucket has about a block of rows.
    cuts = index.groupBy("pivot").agg(F.count("*").alias("n"), F.percentile_approx("dist", [i / 1024 for i in range(1, 1024)], 4096).alias("at"))
    edges = {r.pivot: np.array(r.at)[[round(1024 * i / m) - 1 for i in range(1, m)]] if (m := min(-(-r.n // block), 1024)) > 1 else np.zeros(0) for r in cuts.collect()}

    def bucketed(batches):
        for b in batches:
            pivot, dist = b.column("pivot").to_numpy(), b.column("dist").to_numpy()
            bucket = np.zeros(len(pivot), np.int32)
            for p in np.unique(pivot):
                bucket[pivot == p] = np.searchsorted(edges[int(p)], dist[pivot == p], side="right")
            yield b.append_column("bucket", pa.array(bucket))

    cut = index.transform(in_arrow, bucketed, "vec_id long, rid long, v binary, pivot int, dist double, bucket int")
    annuli = stage(cut.repartition("pivot", "bucket").sortWithinPartitions("pivot", "bucket", "dist", "vec_id").transform(in_arrow, _blocks(block), ANNULUS))
    directory = annuli.select("block", "pivot", "lo", "hi")
    salts = 1 + top.q // (TOGETHER * k_pivots)
    queries = ready.where(asked).transform(in_arrow, homed, "vec_id long, rid long, v binary, norm double, home int").withColumn("salt", F.pmod(F.xxhash64("rid"), F.lit(salts)).cast("int"))
    queries = stage(queries.repartition("home", "salt").sortWithinPartitions("home", "salt", "rid").transform(in_arrow, _groups, QUERY))

    def distances(batches):
        """For each query group and pivot the nearest and farthest place at which a row may reach the bounds, and the middle."""
        slack = SLACK * (np.sqrt(most) + 1)
        for b in batches:
            for r in b.to_pylist():
                d = _distance(np.c_[_matrix(r["q_vs"], width), np.zeros(len(r["q_vs"]))], centres)
                reach = (_reach(np.array(r["q_norms"]), np.array(r["bound_s"], np.int64), most) + slack)[:, None]
                n = len(centres)
                yield pa.RecordBatch.from_arrays([pa.array([r["qb"]] * n), pa.array([r["home"]] * n, pa.int32()), pa.array(np.arange(n, dtype=np.int32)), pa.array((d - reach).min(0)), pa.array((d + reach).max(0)), pa.array((d.min(0) + d.max(0)) / 2)], ["qb", "home", "pivot", "near", "far", "middle"])

    ranges = "qb string, home int, pivot int, near double, far double, middle double"
    home = queries.transform(in_arrow, distances, ranges).where("home = pivot").join(directory, "pivot")
    gap = F.greatest(F.col("lo") - F.col("middle"), F.col("middle") - F.col("hi"), F.lit(0.0))
    first = stage(home.groupBy("qb").agg(F.min_by("block", F.struct(gap, "block")).alias("block")))

    def searched(pairs, groups):
        none = lambda d, other: d.select(*(F.col(c) if c in d.columns else F.lit(None).cast(t).alias(c) for c, t in other))
        columns = [tuple(c.rsplit(" ", 1)) for c in (ANNULUS + ", " + QUERY).split(", ")]
        rows = none(annuli.join(pairs.select("block").distinct(), "block", "left_semi"), columns).unionByName(none(pairs.join(groups, "qb"), columns))
        return rows.repartition("block").sortWithinPartitions("block", F.col("qb")).transform(in_arrow, _search(k, width, centres, most), FOUND)

    begun = stage(searched(first, queries))
    worst = F.max(F.struct((-F.col("score")).alias("s"), "vec_id"))
    bounds = begun.where("rid is not null").groupBy("rid").agg(F.count("*").alias("n"), worst.alias("w")).where(F.col("n") >= k).select("rid", (-F.col("w.s")).alias("s"), F.col("w.vec_id").alias("i"))
    members = queries.select("qb", F.posexplode("q_rids").alias("pos", "rid")).join(bounds, "rid", "left")
    held = F.array_sort(F.collect_list(F.struct("pos", F.coalesce("s", F.lit(LEAST)).alias("s"), F.coalesce("i", F.lit(LEAST)).alias("i"))))
    bounded = members.groupBy("qb").agg(held.alias("b")).select("qb", F.col("b.s").alias("bound_s"), F.col("b.i").alias("bound_id"))
    queries = stage(queries.drop("bound_s", "bound_id").join(bounded, "qb"))
    # Out from there: of each pivot the annuli that lie within reach of some query of the group.
    pairs = queries.transform(in_arrow, distances, ranges).join(directory, "pivot").where("hi >= near and lo <= far").select("qb", "block")
    rest = searched(stage(pairs.join(first, ["qb", "block"], "left_anti")), queries)
    return begun.unionByName(rest), top.q, top.n


def top_k(vectors: DataFrame, *, k: int = 20, every: int = 20, block: int = BLOCK, pivots: int | None = None) -> DataFrame:
    """(query_id, rank, vec_id, score): the k best rows by inner product of each row whose vec_id is divisible by `every`.

    Vectors that are null, or hold null or non-finite components, take no part, nor do rows with a null vec_id; short
    vectors, empty ones too, count as padded with zeros. Components are whole doubles of any size; a score beyond a
    long is held at its ends. Ties go to the smaller vec_id. Rows that repeat a vec_id take part each for itself, as
    candidates and as queries, and only the query's own row is no candidate of it. With fewer candidates than k all
    are returned; an empty table gives an empty result; other columns are ignored. The pivots come from a sample of
    SAMPLE vectors a pivot at most; all rows are indexed and the result is exact.
    """
    found, _, _ = search_all(vectors, k=k, every=every, block=block, pivots=pivots)
    ranked = found.where("rid is not null").repartition("rid").sortWithinPartitions("rid", F.desc("score"), "vec_id")
    return ranked.transform(in_arrow, _merge(k), "query_id long, rank int, vec_id long, score long")


def share_pruned(vectors: DataFrame, **how) -> float:
    """The share of the products of all queries and rows that the index did not take."""
    found, q, n = search_all(vectors, **how)
    return 1 - (found.agg(F.sum("products")).first()[0] or 0) / max(1, q * n)
