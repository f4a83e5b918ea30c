"""Operator 5 - approximate nearest neighbours in a hierarchical k-means tree.

The tree is fitted on a bounded sample and then *every* row is routed to its
leaf.  A query walks the tree best-bin-first: a priority queue holds branches
by the inner product with their centre, and leaves come out best first.  How
many leaves to visit is calibrated: on the sample, the visits widen until the
mean recall against brute force reaches ``RECALL``.

Rows of neighbouring leaves share a tile of bounded size and a large leaf (many
copies of one vector) is spread over several tiles; a query goes to the tiles
that hold leaves it visits and scores exactly these leaves' rows.

Bounds: ``SAMPLE`` rows for fitting and calibration, at most ``LEAVES`` leaves
(the tree and the leaf counts are all that the driver holds).

Edge cases: null, empty, zero or non-finite vectors take no part; rows sharing
the query's id are its own, and rows that repeat a query's id are one query, with the
least of their vectors; a query visits leaves until they hold more than k rows,
so it gets k where there are as many (of ids that don't repeat); an empty table
gives no rows; ties go to the smaller id.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import vectors
from .common import cut

SAMPLE, LEAVES, LEAF_ROWS, BRANCH, RECALL, TILE_ROWS, TILE_QUERIES, CALIBRATE = 16384, 4096, 256, 8, 0.97, 8192, 4096, 400
FOUND = "query_id long, vec_id long, score double"


class KMeansTree:
    """Nodes: ``(centre, children)`` by number, or ``(centre, leaf number)``."""

    def __init__(self, x: np.ndarray, leaf_rows: float, seed: int = 7):
        self.rng = np.random.default_rng(seed)
        self.centres: list[np.ndarray] = []
        self.children: list[list[int]] = []
        self.leaf_of: dict[int, int] = {}
        self.leaf_rows, self.leaves = max(1.0, leaf_rows), 0
        self.root = self._grow(x)

    def _grow(self, x: np.ndarray) -> int:
        at = len(self.centres)
        self.centres.append(x.mean(axis=0))
        self.children.append([])
        parts = self._split(x) if len(x) > self.leaf_rows else []
        if len(parts) < 2:
            self.leaf_of[at] = self.leaves
            self.leaves += 1
        else:
            self.children[at] = [self._grow(p) for p in parts]
        return at

    def _split(self, x: np.ndarray) -> list[np.ndarray]:
        distinct = np.unique(x, axis=0)
        if len(distinct) < 2:
            return []
        k = min(BRANCH, len(distinct), int(np.ceil(len(x) / self.leaf_rows)) if len(x) / self.leaf_rows >= 2 else 2)
        centres = distinct[self.rng.choice(len(distinct), k, replace=False)]
        for _ in range(12):
            label = nearest(x, centres)
            centres = np.stack([x[label == j].mean(axis=0) if (label == j).any() else centres[j] for j in range(k)])
        label = nearest(x, centres)
        return [x[label == j] for j in range(k) if (label == j).any()]

    def route(self, x: np.ndarray) -> np.ndarray:
        """Leaf of each row: down the nearest centre at every branch."""
        out = np.zeros(len(x), np.int32)

        def down(node: int, rows: np.ndarray) -> None:
            kids = self.children[node]
            if not kids:
                out[rows] = self.leaf_of[node]
                return
            label = nearest(x[rows], np.stack([self.centres[c] for c in kids]))
            for j, c in enumerate(kids):
                if (label == j).any():
                    down(c, rows[label == j])

        down(self.root, np.arange(len(x)))
        return out

    def visit(self, q: np.ndarray, most: int, affinity: np.ndarray | None = None, rows: dict[int, int] | None = None, need: int = 0) -> list[int]:
        """The first ``most`` leaves of a best-bin-first walk, and more of them until they hold ``need`` of the counted ``rows``."""
        near = self.table @ q if affinity is None else affinity
        queue, out, held = [(0.0, self.root)], [], 0
        while queue and (len(out) < most or held < need):
            _, node = heapq.heappop(queue)
            if self.children[node]:
                for c in self.children[node]:
                    heapq.heappush(queue, (-near[c], c))
            else:
                out.append(self.leaf_of[node])
                held += rows.get(out[-1], 0) if rows else 0
        return out

    @property
    def table(self) -> np.ndarray:
        return np.stack(self.centres)


def nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return np.argmin((centres**2).sum(axis=1) - 2 * (x @ centres.T), axis=1)


def calibrate(tree: KMeansTree, x: np.ndarray, k: int, goal: float = RECALL) -> tuple[int, float]:
    """Leaf visits at which mean recall on the sample reaches ``goal``, and the recall there."""
    pick = np.random.default_rng(3).choice(len(x), min(CALIBRATE, len(x)), replace=False)
    leaf, near = tree.route(x), x[pick] @ x.T
    k = min(k, len(x) - 1)
    if k < 1:
        return tree.leaves, 1.0
    near[np.arange(len(pick)), pick] = -np.inf
    best = np.argpartition(-near, k - 1, axis=1)[:, :k]
    hits = np.zeros(tree.leaves)
    for row, i in enumerate(pick):
        place = np.empty(tree.leaves, int)
        place[tree.visit(x[i], tree.leaves)] = np.arange(tree.leaves)
        hits += np.bincount(place[leaf[best[row]]], minlength=tree.leaves)
    recall = np.cumsum(hits) / (len(pick) * k)
    visits = int(np.searchsorted(recall, goal)) + 1
    return min(visits, tree.leaves), float(recall[min(visits, tree.leaves) - 1])


def build(rows: DataFrame, n: int, k: int) -> tuple[KMeansTree, int, float] | None:
    """Fit and calibrate on at most ``SAMPLE`` rows with the smallest hashes of id and vector."""
    share = F.lit(min(1.0, 1.25 * SAMPLE / max(n, 1)))
    unit = F.shiftrightunsigned(F.xxhash64(F.lit(5), "vec_id", "v"), 11) / F.lit(float(1 << 53))
    picked = rows.where(unit < share).orderBy(F.xxhash64(F.lit(5), "vec_id", "v"), "vec_id").limit(SAMPLE).select("v").toArrow()
    if not picked.num_rows:
        return None
    x = vectors.matrix(picked["v"])
    leaves = min(LEAVES, max(1, n // LEAF_ROWS))
    tree = KMeansTree(x, len(x) / leaves)
    return tree, *calibrate(tree, x, k)


def _tile(k: int):
    def run(_key, rows: pa.Table, queries: pa.Table) -> pa.Table:
        out = []
        if rows.num_rows and queries.num_rows:
            ids, leaf, x = np.asarray(rows["vec_id"]), np.asarray(rows["leaf"]), vectors.matrix(rows["v"])
            qids, q = np.asarray(queries["vec_id"]), vectors.matrix(queries["v"])
            width = max(x.shape[1], q.shape[1])
            x, q = vectors.widen(x, width), vectors.widen(q, width)
            wanted = queries["leaves"].combine_chunks()
            owner = np.repeat(np.arange(len(qids)), np.asarray(wanted.value_lengths()))
            asked = np.asarray(wanted.flatten())
            parts = []
            for one in np.unique(leaf):
                at, who = np.flatnonzero(leaf == one), owner[asked == one]
                if not len(who):
                    continue
                near = q[who] @ x[at].T
                near[qids[who][:, None] == ids[at][None, :]] = -np.inf
                if len(at) > k:
                    floor = np.partition(near, len(at) - k, axis=1)[:, len(at) - k]
                    a, b = np.nonzero(near >= (floor - 1e-9 * np.maximum(1, np.abs(floor)))[:, None])
                else:
                    a, b = np.nonzero(near > -np.inf)
                good = near[a, b] > -np.inf
                parts.append((who[a[good]], at[b[good]]))
            if parts:
                who, at = (np.concatenate(p) for p in zip(*parts, strict=True))
                exact = np.concatenate([(q[who[i : i + 65536]] * x[at[i : i + 65536]]).sum(axis=1) for i in range(0, len(who), 65536)])
                order = np.lexsort((ids[at], -exact, who))
                who, at, exact = who[order], at[order], exact[order]
                first = np.searchsorted(who, who)
                keep = np.arange(len(who)) - first < k
                out = [qids[who[keep]], ids[at[keep]], exact[keep]]
        cols = out or [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]
        return pa.table({"query_id": pa.array(cols[0], pa.int64()), "vec_id": pa.array(cols[1], pa.int64()), "score": pa.array(cols[2], pa.float64())})

    return run


def nearest_neighbours(rows: DataFrame, queries: DataFrame, k: int = 20) -> DataFrame:
    """For each query its k nearest rows found, by inner product of the original vectors."""
    spark, n = rows.sparkSession, rows.count()
    built = build(rows, n, k)
    if built is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    tree, visits, _ = built
    held = spark.sparkContext.broadcast((tree, visits))  # at most LEAVES leaves and their branches

    def route(batches):
        own, _ = held.value
        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(own.route(vectors.widen(vectors.matrix(b["v"]), own.centres[0].shape[0])[:, : own.centres[0].shape[0]]), pa.int32())], names=["vec_id", "v", "leaf"])

    placed = cut(rows.select("vec_id", "v").mapInArrow(route, "vec_id long, v array<double>, leaf int"))  # routed once, read twice
    counts = {r["leaf"]: r["count"] for r in placed.groupBy("leaf").count().collect()}
    tile_of, spread, tile, room = {}, {}, -1, 0
    for leaf in sorted(counts):  # neighbouring leaves share a tile; a large leaf gets tiles of its own
        if counts[leaf] > TILE_ROWS:
            spread[leaf] = -(-counts[leaf] // TILE_ROWS)
            tile_of[leaf], tile, room = tile + 1, tile + spread[leaf], 0
        else:
            if counts[leaf] > room:
                tile, room = tile + 1, TILE_ROWS
            tile_of[leaf], room = tile, room - counts[leaf]
    query_tiles = max(1, -(-queries.count() // TILE_QUERIES))
    plan = spark.sparkContext.broadcast((tile_of, spread, counts))  # a few numbers a leaf

    def probe(batches):
        own, most = held.value
        tiles, wide, held_rows = plan.value
        dims = own.centres[0].shape[0]
        table = own.table
        for b in batches:
            near = vectors.widen(vectors.matrix(b["v"]), dims)[:, :dims] @ table.T
            at, goes, leaves = [], [], []
            for i in range(b.num_rows):
                to: dict[int, list[int]] = {}
                for leaf in own.visit(None, most, near[i], held_rows, k + 1):
                    for t in range(wide.get(leaf, 1)) if leaf in tiles else ():
                        to.setdefault(tiles[leaf] + t, []).append(leaf)
                for t, these in to.items():
                    at.append(i)
                    goes.append(t)
                    leaves.append(these)
            got = b.take(pa.array(at, pa.int64()))
            yield pa.RecordBatch.from_arrays([got["vec_id"], got["v"], pa.array(goes, pa.int32()), pa.array(leaves, pa.list_(pa.int32()))], names=["vec_id", "v", "rt", "leaves"])

    first = F.create_map(*[F.lit(x) for pair in tile_of.items() for x in pair])
    wide = F.coalesce(F.create_map(*[F.lit(x) for pair in spread.items() for x in pair])[F.col("leaf")], F.lit(1)) if spread else F.lit(1)
    tiles = placed.withColumn("rt", (first[F.col("leaf")] + F.pmod(F.xxhash64("vec_id", "v"), wide)).cast("int")).withColumn("qt", F.explode(F.sequence(F.lit(0), F.lit(query_tiles - 1))))
    asks = queries.select("vec_id", "v").mapInArrow(probe, "vec_id long, v array<double>, rt int, leaves array<int>").withColumn("qt", F.pmod(F.xxhash64("vec_id"), F.lit(query_tiles)).cast("int"))
    found = tiles.groupBy("rt", "qt").cogroup(asks.groupBy("rt", "qt")).applyInArrow(_tile(k), FOUND)
    return vectors.merge_top(found, k)
