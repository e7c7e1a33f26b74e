"""Exact top-k inner-product search with dual cover trees.

Rows are dealt to the nearest of a bounded sample of centres (`most_centres`; every row is indexed), and the rows of a
centre, in parts of bounded expected size, become one cover tree each (nested centres whose children lie within a shrinking
radius). Queries meet the trees' means and radii in blocks of both: first each query visits the few trees whose means promise
most, which gives it a k-th score; then it goes to every tree whose best possible product reaches that score, and to no
other. At a tree its askers form a tree too, and a pair of nodes is dropped when even its best possible product, from
centres and covering radii, stays below the worst k-th score of the query node. Scores are exact integers; ties go to
the smaller id.

Edge cases: null vectors and vectors with null or non-finite components take no part, empty vectors neither; vectors meet
only vectors of their length; repeated rows count as the SQL counts them: each is a candidate of its own, and each row
of a repeated query id asks for itself, their answers being ranked together; equal vectors share a tree node, which keeps
k rows of an id at most and the 2k smallest of those, all that a top-k can need once the query's own rows are left out;
rows with the query's own id are no candidates; scores saturate at 64 bits; rows with a null id take no part; an empty
table gives an empty result.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import materialise

#: Rows expected at a centre; most rows expected in a tree; askers and trees compared at once; askers at a tree; first visits.
GROUP, BLOCK, QUERY_BLOCK, ASKERS, SEEDS = 512, 4096, 1024, 4096, 2
LIMIT = 2**63 - 1


def exact_products(q: np.ndarray, p: np.ndarray) -> np.ndarray:
    """Integer inner products of all rows of q with all rows of p."""
    top = float(np.abs(q).max(initial=0)) * float(np.abs(p).max(initial=0)) * max(q.shape[1], 1)
    if top < 2**53:
        return (q @ p.T).astype(np.int64)
    whole = np.vectorize(int, otypes=[object])
    return np.clip(whole(q) @ whole(p).T, -LIMIT, LIMIT).astype(np.int64)


@dataclass
class CoverTree:
    points: np.ndarray  # distinct vectors, float64 holding integers
    ids: np.ndarray  # ids of all members, ascending inside a point
    member_start: np.ndarray  # per point, into ids; one more at the end
    node_point: np.ndarray
    radius: np.ndarray
    child_start: np.ndarray  # per node, into child; one more at the end
    child: np.ndarray
    fresh: np.ndarray  # nodes whose point no ancestor shares


def build(points: np.ndarray, ids: np.ndarray, keep: int, base: float = 1.6, leaf: int = 1) -> CoverTree:
    """A cover tree over the rows of points; of each distinct point `keep` rows of an id stay, and the 2 * keep smallest of those."""
    order = np.lexsort((ids, *points.T[::-1]))
    points, ids = points[order], ids[order]
    new = np.append(True, (points[1:] != points[:-1]).any(1))
    which = np.cumsum(new) - 1
    run = np.flatnonzero(new | np.append(True, ids[1:] != ids[:-1]))
    few = np.arange(len(ids)) - np.repeat(run, np.diff(np.append(run, len(ids)))) < keep
    before = np.cumsum(few) - few
    held = few & (before - before[np.flatnonzero(new)][which] < 2 * keep)
    starts = np.append(0, np.cumsum(np.bincount(which[held], minlength=int(which[-1]) + 1)))
    distinct = points[new]
    node_point: list[int] = []
    radius: list[float] = []
    fresh: list[bool] = []
    children: list[list[int]] = []

    def node(point: int, r: float, is_new: bool) -> int:
        node_point.append(point)
        radius.append(r)
        fresh.append(is_new)
        children.append([])
        return len(node_point) - 1

    centre = int(np.argmin(((distinct - distinct.mean(0)) ** 2).sum(1)))
    rest = np.delete(np.arange(len(distinct)), centre)
    far = np.sqrt(((distinct[rest] - distinct[centre]) ** 2).sum(1))
    stack = [(node(centre, float(far.max(initial=0)), True), rest, far)]
    while stack:
        at_node, idx, dist = stack.pop()
        if not len(idx):
            continue
        cover = radius[at_node] / base
        point, own, is_new = node_point[at_node], dist <= cover, False
        groups = [(point, idx[own], dist[own], is_new)] if own.any() else []
        idx = idx[~own]
        while len(idx):
            head, tail = int(idx[0]), idx[1:]
            d = np.sqrt(((distinct[tail] - distinct[head]) ** 2).sum(1))
            near = d <= cover
            groups.append((head, tail[near], d[near], True))
            idx = tail[~near]
        for head, members, d, is_new in groups:
            c = node(head, float(d.max(initial=0)), is_new)
            children[at_node].append(c)
            stack.append((c, members, d))
    n_child = np.array([len(c) for c in children])
    return CoverTree(
        distinct,
        ids[held],
        starts,
        np.array(node_point),
        np.array(radius) * (1 + 1e-9),
        np.append(0, np.cumsum(n_child)),
        np.array([c for cs in children for c in cs], np.int64),
        np.array(fresh),
    )


def query_tree(ids: np.ndarray, points: np.ndarray) -> tuple[CoverTree, np.ndarray]:
    """(tree, row of each member): a tree that keeps every row."""
    tree = build(points, np.arange(len(ids)), len(ids))
    return replace(tree, ids=ids[tree.ids]), tree.ids


class Best:
    """The k best (score, id) of each query so far."""

    def __init__(self, query_ids: np.ndarray, floor: np.ndarray, k: int):
        self.query_ids, self.floor, self.k = query_ids, floor.copy(), k
        self.scores = [np.zeros(0, np.int64) for _ in query_ids]
        self.ids = [np.zeros(0, np.int64) for _ in query_ids]

    def offer(self, rows: np.ndarray, scores: np.ndarray, tree: CoverTree, points: np.ndarray) -> None:
        """scores: of the queries `rows` (axis 0) with the tree's points (axis 1)."""
        hit_r, hit_c = np.nonzero(scores >= self.floor[rows][:, None])
        cuts = np.searchsorted(hit_r, np.arange(len(rows) + 1))
        for i in np.flatnonzero(np.diff(cuts)):
            r, cols = rows[i], hit_c[cuts[i] : cuts[i + 1]]
            p = points[cols]
            n = tree.member_start[p + 1] - tree.member_start[p]
            ids = tree.ids[np.repeat(tree.member_start[p], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)]
            s = np.repeat(scores[i, cols], n)
            other = ids != self.query_ids[r]
            s, ids = np.append(self.scores[r], s[other]), np.append(self.ids[r], ids[other])
            top = np.lexsort((ids, -s))[: self.k]
            self.scores[r], self.ids[r] = s[top], ids[top]
            if len(top) == self.k:
                self.floor[r] = max(self.floor[r], s[top[-1]])


def search(queries: CoverTree, data: CoverTree, floor: np.ndarray, k: int) -> Best:
    """Dual-tree descent. queries.ids are one per asking row, in the order of `floor`."""
    point_of = np.repeat(np.arange(len(queries.points)), np.diff(queries.member_start))
    best = Best(queries.ids, floor, k)
    q_norm = np.sqrt((queries.points**2).sum(1))
    p_norm = np.sqrt((data.points**2).sum(1))
    below: dict[int, np.ndarray] = {}
    for n in range(len(queries.node_point) - 1, -1, -1):
        kids = queries.child[queries.child_start[n] : queries.child_start[n + 1]]
        own = np.flatnonzero(point_of == queries.node_point[n]) if queries.fresh[n] else np.zeros(0, np.int64)
        below[n] = np.concatenate([own, *[below[int(c)] for c in kids]])
    # A query node's own point is scored with it when the node is split.
    work: list[tuple[int, np.ndarray, np.ndarray]] = [(0, below[0], np.zeros(1, np.int64))]
    while work:
        n, rows, frontier = work.pop()
        if not len(rows) or not len(frontier):
            continue
        c, rq = queries.points[queries.node_point[n]], queries.radius[n]
        pts = data.node_point[frontier]
        bound = data.points[pts] @ c + data.radius[frontier] * q_norm[queries.node_point[n]] + rq * p_norm[pts] + rq * data.radius[frontier]
        frontier = frontier[bound * (1 + 1e-9) + 1 >= best.floor[rows].min()]
        if not len(frontier):
            continue
        kids = queries.child[queries.child_start[n] : queries.child_start[n + 1]]
        # Rows left over at a split share the node's own point: they are not split again.
        if len(rows) > 64 and len(rows) == len(below[n]) and len(kids) > 1 and len(kids) <= 64 and rq > data.radius[frontier].max():
            left = np.setdiff1d(rows, np.concatenate([below[int(x)] for x in kids]), assume_unique=True)
            work += [(int(x), below[int(x)], frontier) for x in kids]
            if len(left):
                work.append((n, left, frontier))
            continue
        for new in (frontier[data.fresh[frontier]],):
            if len(new):
                pts = data.node_point[new]
                best.offer(rows, exact_products(queries.points[point_of[rows]], data.points[pts]), data, pts)
        spans = data.child_start[frontier + 1] - data.child_start[frontier]
        nxt = data.child[np.repeat(data.child_start[frontier], spans) + np.arange(spans.sum()) - np.repeat(np.cumsum(spans) - spans, spans)]
        work.append((n, rows, nxt))
    return best


def _vectors(batch: pa.RecordBatch, scale: float) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(rows, ids, floor(scale * x)) of the usable rows, by vector length."""
    col, ids = batch.column("embedding"), batch.column("vec_id")
    n = pc.list_value_length(col).fill_null(0).to_numpy(zero_copy_only=False)
    flat = col.flatten().cast(pa.float64())
    bad = ~np.isfinite(flat.fill_null(float("nan")).to_numpy(zero_copy_only=False))
    flat = flat.fill_null(0.0).to_numpy(zero_copy_only=False)
    first = np.cumsum(n) - n
    broken = np.add.reduceat(np.append(bad, False), np.minimum(first, len(bad)))[: len(n)] if len(bad) else np.zeros(len(n))
    good = (n > 0) & (broken == 0) & np.array(ids.is_valid())
    keys = ids.fill_null(0).to_numpy(zero_copy_only=False)
    for d in np.unique(n[good]):
        rows = np.flatnonzero(good & (n == d))
        yield rows, keys[rows], np.floor(scale * flat[first[rows][:, None] + np.arange(d)]) + 0.0


def _centres(table: DataFrame, scale: float, most: int) -> dict[int, np.ndarray]:
    """By vector length, distinct vectors of a sample of rows: one row in GROUP, at most `most` rows, by hash of the id."""
    n = table.count()
    few = table.orderBy(F.xxhash64("vec_id"), "vec_id").limit(min(most, -(-n // GROUP))).toArrow().combine_chunks()
    out: dict[int, list[np.ndarray]] = {}
    for batch in few.to_batches():
        for _, _, x in _vectors(batch, scale):
            out.setdefault(x.shape[1], []).append(x)
    return {d: np.unique(np.concatenate(xs), axis=0) for d, xs in out.items()}


def _assign(table: DataFrame, centres: dict[int, np.ndarray], every: int, scale: float) -> DataFrame:
    """The usable rows with their nearest centre, a number of their own, and their integer vector where they ask."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        next_row = TaskContext.get().partitionId() << 36
        for batch in batches:
            for rows, ids, x in _vectors(batch, scale):
                at = np.zeros(len(rows), np.int64)
                c = centres.get(x.shape[1])
                for i in range(0, len(rows) if c is not None else 0, 1024):
                    at[i : i + 1024] = np.argmin((c * c).sum(1) - 2 * (x[i : i + 1024] @ c.T), 1)
                body = [v.tobytes() if asks else None for v, asks in zip(x, ids % every == 0, strict=True)]
                number = np.arange(next_row, next_row + len(rows))
                next_row += len(rows)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(ids), batch.column("embedding").take(pa.array(rows)), pa.array(np.full(len(rows), x.shape[1], np.int32)), pa.array(at), pa.array(number), pa.array(body, pa.binary())],
                    ["vec_id", "embedding", "dim", "centre", "row", "body"],
                )

    kind = table.schema["embedding"].dataType.simpleString()
    return table.mapInArrow(run, f"vec_id long, embedding {kind}, dim int, centre long, row long, body binary")


def _plant(assigned: DataFrame, k: int, scale: float) -> DataFrame:
    """One row per data tree: (dim, tree, mean, radius, body). A centre of more than BLOCK rows gets several trees."""
    sizes = assigned.groupBy("dim", "centre").agg(F.ceil(F.count(F.lit(1)) / BLOCK).alias("parts"))
    dealt = assigned.join(sizes, ["dim", "centre"]).select("vec_id", "embedding", "dim", (F.col("centre") * (1 << 32) + F.pmod(F.xxhash64("row"), "parts")).alias("tree"))

    def run(rows: pa.Table) -> pa.Table:
        ((_, ids, x),) = _vectors(rows.combine_chunks().to_batches()[0], scale)
        mean = x.mean(0)
        far = float(np.sqrt(((x - mean) ** 2).sum(1)).max()) * (1 + 1e-9)
        cells = (rows.column("dim")[0], rows.column("tree")[0], mean.tobytes(), far, pickle.dumps(build(x, ids, k), 5))
        return pa.Table.from_arrays([pa.array([v.as_py() if isinstance(v, pa.Scalar) else v], t) for v, t in zip(cells, (pa.int32(), pa.int64(), pa.binary(), pa.float64(), pa.binary()), strict=True)], ["dim", "tree", "mean", "radius", "body"])

    return dealt.groupBy("dim", "tree").applyInArrow(run, "dim int, tree long, mean binary, radius double, body binary")


def _matrix(column: pa.ChunkedArray, dim: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.float64).reshape(-1, dim)


def _candidates(asked: DataFrame, trees: DataFrame, seeds: int | None) -> DataFrame:
    """(dim, qid, tree, best): pairs of askers and trees, read from the trees' means and radii in blocks of both.

    With `seeds`, each asker's trees of largest product with the mean, so many of each block; without, all trees whose best
    possible product reaches the asker's floor.
    """
    n_q, n_t = asked.count(), trees.count()
    parts_q, parts_t = max(1, -(-n_q // QUERY_BLOCK)), max(1, -(-n_t // QUERY_BLOCK))
    every = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")))
    left = asked.select("dim", "qid", "floor", F.col("body").alias("vector"), F.pmod(F.xxhash64("qid"), F.lit(parts_q)).alias("pq")).withColumn("pt", every(parts_t))
    right = trees.select("dim", "tree", "mean", "radius", F.pmod(F.xxhash64("tree"), F.lit(parts_t)).alias("pt")).withColumn("pq", every(parts_q))

    def run(qs: pa.Table, ts: pa.Table) -> pa.Table:
        if qs.num_rows and ts.num_rows:
            dim = qs.column("dim")[0].as_py()
            q, mean = _matrix(qs.column("vector"), dim), _matrix(ts.column("mean"), dim)
            best = q @ mean.T
            if seeds:
                keep = np.argsort(-best, 1, kind="stable")[:, :seeds]
                at, to = np.repeat(np.arange(len(q)), keep.shape[1]), keep.ravel()
            else:
                best = best + np.sqrt((q**2).sum(1))[:, None] * ts.column("radius").to_numpy()
                at, to = np.nonzero(best + 1e-9 * np.abs(best) + 1 >= qs.column("floor").to_numpy()[:, None])
            cells = [np.full(len(at), dim, np.int32), qs.column("qid").to_numpy()[at], ts.column("tree").to_numpy()[to], best[at, to]]
        else:
            cells = [np.zeros(0, t) for t in (np.int32, np.int64, np.int64, np.float64)]
        return pa.Table.from_arrays([pa.array(c) for c in cells], ["dim", "qid", "tree", "best"])

    keys = ["dim", "pq", "pt"]
    return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(run, "dim int, qid long, tree long, best double")


def _visit(pairs: DataFrame, asked: DataFrame, trees: DataFrame, k: int) -> DataFrame:
    """(qid, query_id, vec_id, score, times): what each tree has for the askers paired with it, at most ASKERS at a time."""
    parts = pairs.groupBy("dim", "tree").agg(F.ceil(F.count(F.lit(1)) / ASKERS).alias("parts"))
    keys = ["dim", "tree", "part"]
    left = pairs.select("dim", "qid", "tree").join(asked.drop("dim"), "qid").join(parts, ["dim", "tree"]).withColumn("part", F.pmod(F.xxhash64("qid"), "parts"))
    right = trees.select("dim", "tree", F.col("body").alias("data")).join(parts, ["dim", "tree"]).withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)))
    names = ["qid", "query_id", "vec_id", "score", "times"]

    def run(qs: pa.Table, ts: pa.Table) -> pa.Table:
        if not qs.num_rows or not ts.num_rows:
            return pa.Table.from_arrays([pa.array([], pa.int64())] * len(names), names)
        group, order = query_tree(qs.column("query").to_numpy(), _matrix(qs.column("body"), qs.column("dim")[0].as_py()))
        best = search(group, pickle.loads(ts.column("data")[0].as_py()), qs.column("floor").to_numpy()[order], k)
        n = [len(s) for s in best.scores]
        askers = (np.repeat(v, n) for v in (qs.column("qid").to_numpy()[order], group.ids))
        times = np.repeat(np.minimum(qs.column("copies").to_numpy()[order], k), n)
        return pa.Table.from_arrays([pa.array(v) for v in (*askers, np.concatenate(best.ids), np.concatenate(best.scores), times)], names)

    return left.select(*keys, "qid", "query", "copies", "floor", "body").groupBy(*keys).cogroup(right.select(*keys, "data").groupBy(*keys)).applyInArrow(run, ", ".join(f"{c} long" for c in names))


def _pairs(spark: SparkSession, table: DataFrame, k: int, every: int, scale: float, most_centres: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(pairs that no bound rules out, askers with floors, trees)."""
    table = table.select(F.col("vec_id").cast("long"), "embedding")
    assigned = materialise(_assign(table, _centres(table, scale, most_centres), every, scale), spark)
    trees = materialise(_plant(assigned, k, scale), spark)
    asked = assigned.where(F.col("body").isNotNull()).groupBy("dim", F.col("vec_id").alias("query"), "body").agg(F.count(F.lit(1)).alias("copies"))
    asked = materialise(asked.withColumn("qid", F.monotonically_increasing_id()).withColumn("floor", F.lit(-LIMIT)), spark)

    nearest = F.row_number().over(W.partitionBy("qid").orderBy(F.col("best").desc(), "tree"))
    first = materialise(_candidates(asked, trees, SEEDS).withColumn("n", nearest).where(F.col("n") <= SEEDS).drop("n"), spark)
    place = F.row_number().over(W.partitionBy("qid").orderBy(F.col("score").desc()))
    floors = _visit(first, asked, trees, k).withColumn("n", place).where(F.col("n") <= k).where(F.col("n") == k).select("qid", F.col("score").alias("known"))
    asked = materialise(asked.join(floors, "qid", "left").withColumn("floor", F.coalesce("known", "floor")).drop("known"), spark)
    return materialise(_candidates(asked, trees, None), spark), asked, trees


def top_k(spark: SparkSession, table: DataFrame, k: int = 10, every: int = 100, scale: float = 1024.0, most_centres: int = 4096) -> DataFrame:
    """(query_id, rank, vec_id, score) for the rows whose id is divisible by `every`."""
    found = _visit(*_pairs(spark, table, k, every, scale, most_centres), k)
    # Every copy of a query row brings the same answers; k of them fill its ranks.
    found = found.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("times"))))
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id"))
    return found.withColumn("rank", rank.cast("int")).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


ORACLE = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)::BIGINT) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_sum(list_transform(list_zip(q.e, c.e), lambda p: p[1] * p[2]))::BIGINT AS score
  FROM v q JOIN v c ON q.vec_id % 100 = 0 AND q.vec_id <> c.vec_id AND len(q.e) = len(c.e)),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM r WHERE rank <= 10
"""
