"""Exact top-k by inner product with a ball tree in every shard.

Vectors are dealt to shards of bounded size, and each
shard turns them into integers and builds a ball tree. An inner product with any point of a ball is at most
the product with its centre plus the query's norm times the radius. Queries come
in blocks; with a block goes each query's k-th score among a few candidates, so
that every shard prunes from its first node on. Within a shard a query takes its
leaves in the order of that bound and stops when the bound falls below its
current k-th score. Shards return k rows a query; a window merges them.
"""

from __future__ import annotations

import math
import operator
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from modelsort.plans.durable import materialize

SCALE = 256
TOP = 5
QUERY_EVERY = 50
#: Vectors of a shard at most on average, queries of a block, and candidates that give the first k-th scores.
SHARD_ROWS = 65_536
BLOCK_QUERIES = 16_384
SEEDS = 4_096
LEAF = 256
NONE = np.iinfo(np.int64).min + 1  # its negative must exist
#: Scores are held between these; a product outside counts as the nearer end.
LOWEST, HIGHEST = NONE + 1, np.iinfo(np.int64).max


def taking_part(embedding: Column) -> Column:
    """The vector as doubles; null for vectors that are null or hold null or non-finite components."""
    ok = embedding.isNotNull() & F.forall(embedding, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x.cast("double")) < float("inf")))
    return F.when(ok, F.transform(embedding, lambda x: x.cast("double")))


def quantised(vectors: np.ndarray) -> np.ndarray:
    """floor(SCALE * x) of doubles: doubles again, which hold these integers exactly, or Python integers where they overflow."""
    with np.errstate(over="ignore"):
        out = np.floor(vectors * float(SCALE))
    if np.isfinite(out).all():
        return out
    return np.array([[int(x) * SCALE if abs(x) > 2.0**60 else math.floor(x * SCALE) for x in row] for row in vectors.tolist()], dtype=object).reshape(vectors.shape)


@dataclass
class Ball:
    """Leaves of a tree: point ranges, with centres and radii of all nodes above them."""

    order: np.ndarray
    centres: np.ndarray
    radii: np.ndarray
    children: np.ndarray  # two nodes, or -1 and -1
    ranges: np.ndarray


def build(points: np.ndarray, leaf: int = LEAF) -> Ball:
    """Split at the middle of the direction between two far points until leaves are small."""
    order = np.arange(len(points))
    nodes: list[tuple] = []
    todo = [(0, len(points), -1, 0)]
    while todo:
        a, b, parent, side = todo.pop()
        own = points[order[a:b]]
        with np.errstate(all="ignore"):  # vectors near the largest double give infinite radii, whose nodes are always visited
            centre = own.mean(axis=0)
            distance = np.sqrt(((own - centre) ** 2).sum(axis=1))
            distance = np.where(np.isnan(distance), np.inf, distance)
        me = len(nodes)
        nodes.append([centre, float(distance.max()), [-1, -1], (a, b)])
        if parent >= 0:
            nodes[parent][2][side] = me
        if b - a > leaf and distance.max() > 0:
            with np.errstate(all="ignore"):
                far = own[distance.argmax()]
                other = own[((own - far) ** 2).sum(axis=1).argmax()]
                along = np.nan_to_num(own @ (other - far))
            middle = (b - a) // 2
            order[a:b] = order[a:b][np.argpartition(along, middle)]
            todo += [(a, a + middle, me, 0), (a + middle, b, me, 1)]
    return Ball(order, np.array([n[0] for n in nodes]), np.array([n[1] for n in nodes]), np.array([n[2] for n in nodes]), np.array([n[3] for n in nodes]))


def _real(x: np.ndarray) -> np.ndarray:
    """Integers as doubles; infinite where no double is large enough."""
    if x.dtype != object:
        return x.astype(np.float64)
    top = 2**1023
    return np.array([[float(v) if -top < v < top else math.inf if v > 0 else -math.inf for v in row] for row in x.tolist()], float).reshape(x.shape)


def _largest(x: np.ndarray) -> np.ndarray:
    """Largest component of each row in size, as a double."""
    return np.abs(_real(x)).max(axis=1, initial=0) if x.shape[1] else np.zeros(len(x))


def _products(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Exact integer inner products, held between ``LOWEST`` and ``HIGHEST``.

    Doubles do where no sum can pass 2**52, 64-bit integers where none can pass
    2**62, Python integers for the rows that are left.
    """
    size = max(1, q.shape[1])
    a, b = _largest(q), _largest(x)
    with np.errstate(over="ignore"):
        most = a.max(initial=0) * b.max(initial=0) * size
    if most < 2.0**52:
        return (q.astype(np.float64) @ x.astype(np.float64).T).astype(np.int64)
    if most < 2.0**62 and max(a.max(initial=0), b.max(initial=0)) < 2.0**62:
        return q.astype(np.int64) @ x.astype(np.int64).T
    if len(x) > 1:
        # Rows of ordinary size are kept apart from the few that need wide integers.
        out, by = np.empty((len(q), len(x)), np.int64), np.argsort(b, kind="stable")
        with np.errstate(over="ignore"):
            fits = int(np.searchsorted(b[by] * a.max(initial=0) * size, 2.0**62)) if a.max(initial=0) < 2.0**62 else 0
        if 0 < fits < len(x):
            out[:, by[:fits]], out[:, by[fits:]] = _products(q, x[by[:fits]]), _products(q, x[by[fits:]])
            return out
    wide = lambda m: [[int(v) for v in row] for row in m.tolist()]
    rows, columns = wide(q), wide(x)
    return np.array([[min(HIGHEST, max(LOWEST, sum(map(operator.mul, r, c)))) for c in columns] for r in rows], np.int64).reshape(len(q), len(x))


class Best:
    """The k best scores so far of each query, ties to the smaller id."""

    def __init__(self, queries: int, k: int, floor: np.ndarray):
        self.k, self.floor = k, floor
        self.scores = np.full((queries, k), NONE)
        self.ids = np.full((queries, k), np.iinfo(np.int64).max)

    def kth(self) -> np.ndarray:
        return np.maximum(self.scores[:, -1], self.floor)

    def offer(self, rows: np.ndarray, ids: np.ndarray, scores: np.ndarray, own: np.ndarray) -> None:
        """``scores[i, j]`` of query ``rows[i]`` and candidate ``ids[j]``; a query's own id is left out."""
        r, c = np.nonzero((scores >= self.kth()[rows][:, None]) & (ids[None, :] != own[rows][:, None]))
        if not len(r):
            return
        touched = np.unique(r)
        q = np.concatenate([rows[r], np.repeat(rows[touched], self.k)])
        s = np.concatenate([scores[r, c], self.scores[rows[touched]].ravel()])
        i = np.concatenate([ids[c], self.ids[rows[touched]].ravel()])
        by = np.lexsort((i, -s, q))
        q, s, i = q[by], s[by], i[by]
        first = np.flatnonzero(np.append(True, q[1:] != q[:-1]))
        take = (first[:, None] + np.arange(self.k)).ravel()
        self.scores[q[first]], self.ids[q[first]] = s[take].reshape(-1, self.k), i[take].reshape(-1, self.k)


def search(tree: Ball, points: np.ndarray, ids: np.ndarray, queries: np.ndarray, own: np.ndarray, best: Best) -> int:
    """Improve ``best`` with the points of one tree; returns how many leaf visits it took."""
    real = _real(queries)
    with np.errstate(all="ignore"):
        norms = np.sqrt((real**2).sum(axis=1))
        # Rounding is relative to the terms of the bound, not to their sum, which may cancel.
        slack = 1e-9 * (np.sqrt((tree.centres**2).sum(axis=1)) + tree.radii)
    leaf_q, leaf_n, leaf_u = [], [], []
    q, node = np.arange(len(queries)), np.zeros(len(queries), np.int64)
    while len(q):
        upper = np.empty(len(q))
        with np.errstate(all="ignore"):
            for a in range(0, len(q), 65_536):
                part = slice(a, a + 65_536)
                upper[part] = (real[q[part]] * tree.centres[node[part]]).sum(axis=1) + norms[q[part]] * (tree.radii[node[part]] + slack[node[part]])
        upper = np.where(np.isnan(upper), np.inf, upper + 1)
        keep = upper >= best.kth()[q]
        q, node, upper = q[keep], node[keep], upper[keep]
        low = tree.children[node, 0] < 0
        leaf_q.append(q[low])
        leaf_n.append(node[low])
        leaf_u.append(upper[low])
        q, node = np.repeat(q[~low], 2), tree.children[node[~low]].ravel()
    q, node, upper = np.concatenate(leaf_q), np.concatenate(leaf_n), np.concatenate(leaf_u)
    by = np.lexsort((-upper, q))
    q, node, upper = q[by], node[by], upper[by]
    turn = np.arange(len(q)) - np.searchsorted(q, q)
    visits = 0
    for r in range(int(turn.max(initial=-1)) + 1):
        now = np.flatnonzero(turn == r)
        now = now[upper[now] >= best.kth()[q[now]]]
        for n in np.unique(node[now]).tolist():
            rows = q[now[node[now] == n]]
            a, b = tree.ranges[n]
            at = tree.order[a:b]
            best.offer(rows, ids[at], _products(queries[rows], points[at]), own)
            visits += len(rows)
    return visits


def _kth_of_seeds(queries: np.ndarray, own: np.ndarray, seeds: np.ndarray, seed_ids: np.ndarray, k: int) -> np.ndarray:
    best = Best(len(queries), k, np.full(len(queries), NONE))
    for a in range(0, len(queries), 1024):
        rows = np.arange(a, min(a + 1024, len(queries)))
        best.offer(rows, seed_ids, _products(queries[rows], seeds), own)
    return best.scores[:, -1]


def _matrix(column: pa.Array | pa.ChunkedArray, dim: int) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return quantised(column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), dim))


OUT = pa.schema([("query", pa.int64()), ("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])


def _search_shard(batches: Iterator[pa.RecordBatch], blocks: list[dict], k: int) -> Iterator[pa.RecordBatch]:
    parts = list(batches)
    if not parts:
        return
    shard = pa.Table.from_batches(parts)
    for block in blocks:
        dim = block["queries"].shape[1]
        same = shard.filter(pc.equal(shard.column("dim"), dim))
        if not len(same):
            continue
        points, ids = _matrix(same.column("v"), dim), same.column("vec_id").to_numpy()
        best = Best(len(block["own"]), k, block["kth"])
        search(build(_real(points)), points, ids, block["queries"], block["own"], best)
        r, c = np.nonzero(best.scores != NONE)
        yield pa.RecordBatch.from_arrays([pa.array(block["number"][r]), pa.array(block["own"][r]), pa.array(best.ids[r, c]), pa.array(best.scores[r, c])], schema=OUT)


def top_inner_products(vectors: DataFrame, is_query: Column, k: int = TOP, id_col: str = "vec_id", vector_col: str = "embedding", shard_rows: int = SHARD_ROWS, block_queries: int = BLOCK_QUERIES) -> DataFrame:
    """Columns ``query_id, rank, vec_id, score``: the k best candidates of every row for which ``is_query``.

    Candidates are all rows but those with the query's own id, of the query's
    length. Rows without id, and vectors that are null or hold null or non-finite
    components, take no part. Rows that repeat id and vector count once; one id
    with several vectors gives several queries. Scores are exact; one that no long
    can hold counts as the largest or least. An empty table gives no rows.
    """
    spark = vectors.sparkSession
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), taking_part(F.col(vector_col)).alias("v"), F.coalesce(is_query, F.lit(False)).alias("is_query"))
    rows = rows.where("vec_id is not null and v is not null").dropDuplicates(["vec_id", "v"]).withColumn("dim", F.size("v"))
    rows = materialize(rows, "vectors")
    total, asked = rows.agg(F.count("*"), F.count(F.when(F.col("is_query"), 1))).first()
    shards = max(-(-total // shard_rows), min(spark.sparkContext.defaultParallelism, -(-total // 2048)), 1)
    dealt = rows.select("vec_id", "v", "dim").repartition(shards, "vec_id", "v")
    passes = max(1, -(-asked // block_queries))
    if passes > 1:
        dealt = materialize(dealt, "shards")
    seeds = rows.select("vec_id", "v", "dim").orderBy(F.xxhash64("vec_id", "v"), "vec_id").limit(SEEDS).toArrow()
    found = []
    for number in range(passes):
        mine = rows.where("is_query").where(F.pmod(F.xxhash64("vec_id", "v"), F.lit(passes)) == number).select("vec_id", "v", "dim").toArrow()  # about block_queries rows
        blocks = []
        for dim in sorted(set(mine.column("dim").to_pylist())):
            own = mine.filter(pc.equal(mine.column("dim"), dim))
            near = seeds.filter(pc.equal(seeds.column("dim"), dim))
            queries, ids = _matrix(own.column("v"), dim), own.column("vec_id").to_numpy()
            kth = _kth_of_seeds(queries, ids, _matrix(near.column("v"), dim), near.column("vec_id").to_numpy(), k)
            start = sum(len(b["own"]) for b in blocks) + (number << 32)
            blocks.append({"queries": queries, "own": ids, "kth": kth, "number": np.arange(len(ids)) + start})
        shared = spark.sparkContext.broadcast(blocks)
        found.append(dealt.mapInArrow(lambda batches, shared=shared: _search_shard(batches, shared.value, k), "query long, query_id long, vec_id long, score long"))
    every = found[0]
    for more in found[1:]:
        every = every.unionByName(more)
    order = Window.partitionBy("query").orderBy(F.desc("score"), "vec_id")
    return every.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
