"""Operator 3 - exact top-k by an impact-ordered, score-at-a-time index.

Rows are dealt into tiles of bounded size.  A tile keeps its non-zero components
as postings in segments, one for each quantised impact and dimension, in
descending order of impact.  A block of queries adds segment after segment to its
accumulators.  Before each impact of many postings the norm of what a row's unread postings hold
bounds its final score from both sides; a query stops only when that proves which
rows can still be among its best and rescoring these is less work than reading on.
Its unread segments are never touched, and the rows left are rescored exactly.

Queries are tiled as well, so a task holds ``ROWS`` rows and ``QUERIES``
queries at any input size; each tile returns its own k best and a window merges them.

Edge cases: vectors that are null, empty or hold null or non-finite components
take no part; shorter vectors count as padded with zeros; rows that share the
query's id are its own, and rows that repeat a query's id are one query, with the
least of their vectors; components of any size are quantised and scored exactly
(a tile whose scores could leave 53 bits uses whole numbers of any length
throughout), and a score that a long can't hold is given as the nearest long; an
empty table gives no rows.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import vectors

ROWS, QUERIES, LEVELS, BLOCK, LOOK, SCALE = 8192, 2048, 16, 128, 0.08, 256
SCHEMA = "query_id long, vec_id long, score long"
LEAST, MOST = -(1 << 63), (1 << 63) - 1


class ImpactIndex:
    """Postings of one tile by descending quantised impact (a component's magnitude in ``LEVELS`` steps), then dimension."""

    def __init__(self, x: np.ndarray):
        self.x = x  # whole numbers, exact in double precision
        self.n, dims = x.shape
        size = np.abs(x)
        level = np.minimum((size * (LEVELS / max(1.0, size.max(initial=0)))).astype(np.int64), LEVELS - 1)
        segment = ((LEVELS - 1 - level) * dims + np.arange(dims)).ravel()
        order = np.argsort(segment, kind="stable")
        order = order[x.ravel()[order] != 0]
        self.rows, self.values = order // max(dims, 1), x.ravel()[order]
        self.bounds = np.searchsorted(segment[order], np.arange(LEVELS * dims + 1)).reshape(-1) if dims else np.zeros(1, int)
        left, self.rest = (x**2).sum(axis=1), []
        for at in range(LEVELS):
            a, b = self.bounds[at * dims], self.bounds[(at + 1) * dims]
            left = left - np.bincount(self.rows[a:b], self.values[a:b] ** 2, self.n)
            self.rest.append(np.sqrt(np.maximum(left, 0)))
        unread = len(order) - self.bounds[dims::dims] if dims else np.zeros(LEVELS, int)
        ahead = unread - np.append(unread[1:], 0)  # postings of the next impact: a look is worth its while before many
        self.read, self.unread, self.looks = 0, unread, {*np.flatnonzero(ahead >= LOOK * len(order)).tolist(), LEVELS - 1}

    def search(self, q: np.ndarray, k: int, own: list[np.ndarray]) -> list[tuple[np.ndarray, np.ndarray]]:
        """For each query of the block: rows and exact scores of its k best rows outside ``own``; ties by row order (ids ascend)."""
        dims = self.x.shape[1]
        norm = np.sqrt((q**2).sum(axis=1))
        out: list = [None] * len(q)
        still, weight, scores = np.arange(len(q)), np.ascontiguousarray(q.T), np.zeros((self.n, len(q)))
        for level in range(LEVELS):
            for d in range(dims):
                a, b = self.bounds[level * dims + d : level * dims + d + 2]
                if a < b:
                    self.read += int(b - a) * len(still)
                    scores[self.rows[a:b]] += self.values[a:b, None] * weight[d]
            if level not in self.looks:
                continue
            open_ = []
            for column, i in enumerate(still):
                keep = min(k, self.n - len(own[i]))
                slack = norm[i] * self.rest[level] * (1 + 1e-9) + 1e-6
                low = scores[:, column] - slack
                low[own[i]] = -np.inf
                floor = np.partition(low, self.n - keep)[self.n - keep] if keep else np.inf
                could = np.flatnonzero(scores[:, column] + slack >= floor)
                could = np.setdiff1d(could, own[i], assume_unique=True)
                if self.unread[level] and len(could) * dims > self.unread[level]:
                    open_.append(column)
                    continue
                exact = self.x[could] @ q[i]
                best = np.lexsort((could, -exact))[:keep]
                out[i] = could[best], exact[best].astype(np.int64)
            if not open_:
                break
            still, weight, scores = still[open_], np.ascontiguousarray(weight[:, open_]), np.ascontiguousarray(scores[:, open_])
        return out


def whole(x: np.ndarray, scale: int) -> np.ndarray | None:
    """floor(scale * x) of a matrix in double precision, which is exact; None where a product overflows."""
    with np.errstate(over="ignore"):
        z = np.floor(x * scale)
    return z if np.isfinite(z).all() else None


def _any_length(x: np.ndarray, scale: int) -> np.ndarray:
    """floor(scale * x) as Python integers; a double beyond 2**53 is whole itself."""
    one = lambda c: int(c) * scale if abs(c) >= 1 << 53 else math.floor(c * scale)
    return np.array([[one(float(c)) for c in row] for row in x], dtype=object).reshape(x.shape)


def _long_search(x: np.ndarray, q: np.ndarray, k: int, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The k best rows of one query by integers of any length, given as the nearest longs."""
    score = np.array([min(max(int(s), LEAST), MOST) for s in x.dot(q)], dtype=np.int64)
    rest = np.setdiff1d(np.arange(len(x)), own)
    best = rest[np.lexsort((rest, ~score[rest]))][:k]  # ~s falls as s rises and doesn't overflow
    return best, score[best]


def _tile(k: int, scale: int):
    def run(_key, rows: pa.Table, queries: pa.Table) -> pa.Table:
        out_q, out_v, out_s = [], [], []
        if rows.num_rows and queries.num_rows:
            ids = np.asarray(rows["vec_id"])
            order = np.argsort(ids, kind="stable")
            x, q = vectors.matrix(rows["v"])[order], vectors.matrix(queries["v"])
            ids, width = ids[order], max(x.shape[1], q.shape[1])
            x, q, qids = vectors.widen(x, width), vectors.widen(q, width), np.asarray(queries["vec_id"])
            zx, zq = whole(x, scale), whole(q, scale)
            own = [np.arange(*np.searchsorted(ids, [i, i + 1])) for i in qids]
            small = zx is not None and zq is not None and width * max(np.abs(zx).max(initial=1), 1) * max(np.abs(zq).max(initial=1), np.abs(zx).max(initial=1)) < float(1 << 53)
            if small:
                index = ImpactIndex(zx)
                found = [f for at in range(0, len(q), BLOCK) for f in index.search(zq[at : at + BLOCK], k, own[at : at + BLOCK])]
            else:
                lx = _any_length(x, scale)
                found = [_long_search(lx, z, k, o) for z, o in zip(_any_length(q, scale), own, strict=True)]
            for qid, (rows_at, score) in zip(qids, found, strict=True):
                out_q.append(np.full(len(rows_at), qid))
                out_v.append(ids[rows_at])
                out_s.append(score)
        cat = lambda parts: pa.array(np.concatenate(parts) if parts else np.zeros(0, np.int64), pa.int64())
        return pa.table({"query_id": cat(out_q), "vec_id": cat(out_v), "score": cat(out_s)})

    return run


def exact_topk(rows: DataFrame, queries: DataFrame, k: int = 5, scale: int = SCALE, tile_rows: int = ROWS, tile_queries: int = QUERIES) -> DataFrame:
    """For each query ``(vec_id, v array<double>)`` its k best of ``rows`` by the inner product of floor(scale * component), exactly."""
    n, m = rows.count(), queries.count()
    row_tiles, query_tiles = max(1, -(-n // tile_rows)), max(1, -(-m // tile_queries))
    number = lambda salt, tiles: F.pmod(F.xxhash64(F.lit(salt), "vec_id", "v"), F.lit(tiles))
    every = lambda tiles: F.explode(F.sequence(F.lit(0), F.lit(tiles - 1)))
    left = rows.withColumn("rt", number(1, row_tiles).cast("int")).withColumn("qt", every(query_tiles))
    right = queries.withColumn("qt", number(2, query_tiles).cast("int")).withColumn("rt", every(row_tiles))
    found = left.groupBy("rt", "qt").cogroup(right.groupBy("rt", "qt")).applyInArrow(_tile(k, scale), SCHEMA)
    return vectors.merge_top(found, k)
