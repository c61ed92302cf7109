"""Approximate nearest neighbours: stable projections, kd-tree leaves, chi-square stopping test."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spanfold.llm.common import ship

DIMS = 8  # of the projection; even, so that the chi-square distribution has a closed form
LEAF = 64
BLOCK_ROWS = 16_384
BLOCK_QUERIES = 4_096


def chi_square_cdf(x: np.ndarray, dims: int) -> np.ndarray:
    half = np.asarray(x, dtype=np.float64) / 2
    term, total = np.ones_like(half), np.ones_like(half)
    for i in range(1, dims // 2):
        term = term * half / i
        total = total + term
    return 1 - np.exp(-half) * total


def chi_square_quantile(p: float, dims: int) -> float:
    lo, hi = 0.0, 50.0 * dims
    for _ in range(80):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if chi_square_cdf(mid, dims) < p else (lo, mid)
    return hi


class KdTree:
    """Leaves of at most `leaf` projected points, split at the median of the widest axis."""

    def __init__(self, points: np.ndarray, leaf: int = LEAF):
        self.leaves: list[np.ndarray] = []
        stack = [np.arange(len(points))]
        while stack:
            rows = stack.pop()
            if len(rows) <= leaf:
                self.leaves.append(rows)
                continue
            axis = int(np.ptp(points[rows], axis=0).argmax())
            half = len(rows) // 2
            cut = np.argpartition(points[rows, axis], half)
            stack += [rows[cut[half:]], rows[cut[:half]]]
        self.low = np.stack([points[r].min(axis=0) for r in self.leaves])
        self.high = np.stack([points[r].max(axis=0) for r in self.leaves])

    def bounds(self, q: np.ndarray) -> np.ndarray:
        """Squared projected distance from each query to each leaf's box, at least."""
        out = np.zeros((len(q), len(self.leaves)))
        for j in range(q.shape[1]):
            gap = np.maximum(np.maximum(self.low[:, j] - q[:, j, None], q[:, j, None] - self.high[:, j]), 0)
            out += gap * gap
        return out


def search(q_ids, queries, ids, vectors, k: int, reach: float, confidence: float, seed: int = 11):
    """(query, vector id, inner product) of verified neighbours of each query in one block; `ids`
    ascend. Equal vectors are one point, given back with their smallest ids, k of them at most;
    among equal products the point of the smaller id is kept.

    Largest inner product is nearest distance once each vector is lengthened to `reach`. Leaves are
    taken in order of projected distance, twice as many each round; a query stops when a point as
    near as its k-th would, with the given confidence, have come up already.
    """
    vectors, members, starts = _distinct(vectors)
    size = vectors.shape[1]
    spare = int(np.unique(ids, return_counts=True)[1].max())  # rows that share a query's id fall away below
    rng = np.random.default_rng(seed)
    lines = rng.standard_normal((size + 1, DIMS))
    norms = np.einsum("ij,ij->i", vectors, vectors)
    points = vectors @ lines[:-1] + np.sqrt(np.maximum(reach * reach - norms, 0))[:, None] * lines[-1]
    tree = KdTree(points)
    bounds = tree.bounds(queries @ lines[:-1])
    order = np.argsort(bounds, axis=1)
    bounds = np.take_along_axis(bounds, order, axis=1)
    far = np.einsum("ij,ij->i", queries, queries) + reach * reach
    limit = chi_square_quantile(confidence, DIMS)
    keep = k + spare
    slack = 1e-9 * reach * reach  # of products and bounds that differ by rounding only
    best = np.full((len(queries), keep), -np.inf)
    which = np.zeros((len(queries), keep), dtype=np.int64)
    active = np.arange(len(queries))
    done, step = 0, 4
    while len(active) and done < len(tree.leaves):
        turn = order[active, done : done + step]
        flat = turn.ravel()
        by_leaf = np.argsort(flat, kind="stable")
        edges = np.searchsorted(flat[by_leaf], np.arange(len(tree.leaves) + 1))
        for leaf in np.flatnonzero(np.diff(edges)):
            who = active[by_leaf[edges[leaf] : edges[leaf + 1]] // turn.shape[1]]
            rows = tree.leaves[leaf]
            s = queries[who] @ vectors[rows].T
            near = s >= best[who, -1:] - slack
            hit = np.flatnonzero(near.any(axis=1))
            if len(hit):
                w = who[hit]
                x, y = np.nonzero(near[hit])
                s = np.full((len(hit), len(rows)), -np.inf)
                s[x, y] = (queries[w[x]] * vectors[rows[y]]).sum(axis=1)  # equal vectors, equal products
                both = np.hstack([best[w], s])
                point = np.hstack([which[w], np.broadcast_to(rows, (len(w), len(rows)))])
                at = np.lexsort((point, -both), axis=1)[:, :keep]
                which[w] = np.take_along_axis(point, at, axis=1)
                best[w] = np.take_along_axis(both, at, axis=1)
        done += step
        step *= 2
        if done >= len(tree.leaves):
            break
        kth = np.maximum(far[active] - 2 * best[active, -1], 0)  # squared distance of the last kept
        active = active[~(bounds[active, done] > limit * kth + slack)]
    qi, slot = np.nonzero(np.isfinite(best))
    rows, score = which[qi, slot], best[qi, slot]
    held = np.minimum(starts[rows + 1] - starts[rows], keep)
    each = np.repeat(np.arange(len(qi)), held)
    row = members[starts[rows[each]] + np.arange(len(each)) - np.repeat(np.cumsum(held) - held, held)]
    other = ids[row] != q_ids[qi[each]]
    return q_ids[qi[each]][other], ids[row][other], score[each][other]


def _distinct(vectors: np.ndarray):
    """The distinct vectors by first row, all rows by vector, and where each vector's rows begin."""
    _, first, inverse = np.unique(vectors + 0.0, axis=0, return_index=True, return_inverse=True)
    order = np.argsort(first)
    place = np.empty(len(order), dtype=np.int64)
    place[order] = np.arange(len(order))
    owner = place[inverse.ravel()]
    return vectors[first[order]], np.argsort(owner, kind="stable"), np.concatenate(([0], np.cumsum(np.bincount(owner))))


def _matrix(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    ids = table.column("id").combine_chunks().to_numpy(zero_copy_only=False)
    flat = table.column("v").combine_chunks().flatten().to_numpy(zero_copy_only=False)
    return ids, flat.reshape(len(ids), -1) if len(ids) else flat.reshape(0, 1)


def nearest(vectors: DataFrame, query_rows, k: int = 20, id_col: str = "vec_id", vector_col: str = "embedding", confidence: float = 0.97) -> DataFrame:
    """query_id, rank, vec_id, score: the k largest inner products found for each query row.

    `query_rows` is a condition on the input's columns. Vectors that are null, zero, of another
    length than most, or hold null or non-finite components take no part, nor do rows without an
    id. Of rows that share an id with a query, the query is one of them and none is its candidate;
    other repeated rows are candidates each. Ties go to the smaller id. An empty table gives none.

    Plan: rows are dealt to blocks by a hash of the id, queries in groups to every block; each
    pair of blocks is searched in one task of bounded size and the groups' best are ranked.
    """
    x = F.col(vector_col).cast("array<double>")
    clean = vectors.select(F.col(id_col).cast("long").alias("id"), x.alias("v"), F.coalesce(query_rows, F.lit(False)).alias("asks")).where("id is not null and v is not null")
    clean = clean.where("not exists(v, e -> e is null or isnan(e) or abs(e) = double('Infinity')) and exists(v, e -> e <> 0)")
    facts = clean.agg(F.mode(F.size("v")).alias("size"), F.max(F.aggregate("v", F.lit(0.0), lambda a, e: a + e * e)).alias("reach"), F.count("*").alias("n"), F.count_if("asks").alias("m")).first()
    blocks = max(1, math.ceil(facts.n / BLOCK_ROWS))
    groups = max(1, math.ceil(facts.m / BLOCK_QUERIES))
    reach = math.sqrt(facts.reach or 0.0)
    clean = clean.where(F.size("v") == (facts.size or 0))
    h = F.xxhash64("id")
    data = clean.select("id", "v", F.pmod(h, F.lit(blocks).cast("long")).alias("b"), F.explode(F.sequence(F.lit(0), F.lit(groups - 1))).alias("g"))
    asks = clean.where("asks").dropDuplicates(["id"]).select("id", "v", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("b"), F.pmod(F.shiftright(h, 20), F.lit(groups)).cast("int").alias("g"))

    def pair(key, left: pa.Table, right: pa.Table) -> pa.Table:
        names = ["query_id", "vec_id", "score"]
        if not left.num_rows or not right.num_rows:
            return pa.table([pa.array([], pa.int64()), pa.array([], pa.int64()), pa.array([], pa.float64())], names=names)
        q_ids, q = _matrix(left)
        ids, v = _matrix(right)
        order = np.argsort(ids, kind="stable")
        return pa.table(list(search(q_ids, q, ids[order], v[order], k, reach, confidence)), names=names)

    found = asks.groupBy("b", "g").cogroup(data.groupBy("b", "g")).applyInArrow(pair, "query_id long, vec_id long, score double")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


ship(__name__)
