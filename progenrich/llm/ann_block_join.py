"""Nearest neighbours by a block matrix join on int8 product tiles.

Candidates are packed into tiles and queries into blocks, a row each; both are tables, and a grid key joins
them: every tile meets every block in exactly one cell of the grid, and a task holds one cell at a time. Tiles
and blocks are quantised to int8 with a scale for each vector and the exact norm of its rounding error. A tile of int8 dot products (exact in float arithmetic)
gives each distance up to a bound from those norms. A query keeps the candidates whose lower bound does
not exceed the k-th least upper bound seen; those alone are recomputed in double precision from the
original vectors and go through a heap of k entries. Heaps of tasks are merged by query.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import bound_batches, salts

TILE = 2048
#: Most bytes of the vectors of a tile or block.
TILE_BYTES = 4 << 20
#: Queries of one cell of the grid.
CELL_QUERIES = 65_536
PACKED = "dim int, ids binary, xs binary"
FOUND = "query_id long, vec_id long, score double"


def usable(vectors: DataFrame, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """``vec_id, v`` of vectors that are neither null nor zero and hold finite components only."""
    v = F.col(vector).cast("array<double>")
    fine = F.col("v").isNotNull() & F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists("v", lambda x: x != 0)
    return vectors.select(F.col(key).cast("long").alias("vec_id"), v.alias("v")).where("vec_id is not null").where(fine)


def quantise(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """int8 rows, their scales, and the norm of what rounding leaves."""
    scale = np.abs(x).max(1) / 127
    scale = np.where(scale > 0, scale, 1.0)
    q = np.rint(x / scale[:, None]).astype(np.int8)
    return q, scale, np.sqrt(((x - q * scale[:, None]) ** 2).sum(1))


class QueryBlock:
    """Queries (or candidates) of one dimension, quantised once."""

    def __init__(self, ids: np.ndarray, x: np.ndarray):
        self.ids, self.x = ids, x
        self.q, self.scale, self.error = quantise(x)
        self.norm = np.sqrt((x * x).sum(1))


def search_tile(block: QueryBlock, tile: QueryBlock, k: int, limit: np.ndarray):
    """Survivors of a tile as (query number, candidate number); ``limit`` holds squared k-th upper bounds and is lowered."""
    ids, x, q, scale, error, norm = tile.ids, tile.x, tile.q, tile.scale, tile.error, tile.norm
    # 127 * 127 * dimension stays exact in float32 below 2**24, in float64 far beyond
    kind = np.float32 if x.shape[1] * 16129 < 1 << 24 else np.float64
    dot = (block.q.astype(kind) @ q.T.astype(kind)).astype(np.float64) * block.scale[:, None] * scale
    slack = block.error[:, None] * norm + (block.norm + block.error)[:, None] * error
    base = (block.norm**2)[:, None] + norm**2 - 2 * dot
    room = 2 * slack + 1e-9 * ((block.norm**2)[:, None] + norm**2)
    own = block.ids[:, None] == ids
    upper = np.where(own, np.inf, base + room)
    order = np.argsort(ids, kind="stable")
    starts = np.flatnonzero(np.r_[True, np.diff(ids[order]) != 0])
    if len(starts) < len(ids):  # k distinct ids make the bound: a repeated id counts once, by its nearest row
        upper = np.minimum.reduceat(upper[:, order], starts, axis=1)
    if len(starts) >= k:
        np.minimum(limit, np.partition(upper, k - 1, axis=1)[:, k - 1], out=limit)
    return np.nonzero(~own & (base - room <= limit[:, None]))


def distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Euclidean distances of rows, summed component by component, so that a value depends on its rows alone."""
    total = np.zeros(len(x))
    for j in range(x.shape[1]):
        d = x[:, j] - y[:, j]
        total += d * d
    return np.sqrt(total)


def _packed(rows: DataFrame) -> DataFrame:
    """Rows ``dim, ids, xs``: vectors of one dimension, a tile of them in each row."""

    def run(batches):
        held: dict[int, list] = {}

        def rows_of(d: int, all_: bool):
            most = max(1, min(TILE, TILE_BYTES // (8 * d)))
            ids, xs = (np.concatenate(c) for c in zip(*held.pop(d)))
            full = len(ids) if all_ else len(ids) // most * most
            if full < len(ids):
                held[d] = [(ids[full:], xs[full:])]
            cuts = range(0, full, most)
            if full:
                yield pa.RecordBatch.from_arrays(
                    [pa.array([d] * len(cuts), pa.int32()), pa.array([ids[i : min(i + most, full)].tobytes() for i in cuts], pa.binary()), pa.array([xs[i : min(i + most, full)].tobytes() for i in cuts], pa.binary())],
                    names=["dim", "ids", "xs"],
                )

        for batch in batches:
            sizes, ids = np.asarray(batch["v"].value_lengths()), batch["vec_id"].to_numpy()
            for d in np.unique(sizes).tolist():
                at = np.flatnonzero(sizes == d)
                flat = batch["v"].take(pa.array(at)).flatten().to_numpy(zero_copy_only=False)
                held.setdefault(d, []).append((ids[at], flat.reshape(len(at), d)))
                yield from rows_of(d, False)
        for d in list(held):
            yield from rows_of(d, True)

    return rows.mapInArrow(run, PACKED)


class _Cell:
    """The blocks of one cell with their bounds, and a heap of the k nearest distinct ids for each query."""

    def __init__(self, k: int):
        self.k, self.blocks, self.heaps = k, {}, {}

    def block(self, d: int, ids: bytes, xs: bytes) -> tuple[QueryBlock, np.ndarray]:
        key = (ids, hash(xs))
        if key not in self.blocks:
            made = QueryBlock(np.frombuffer(ids, np.int64), np.frombuffer(xs, np.float64).reshape(-1, d))
            self.blocks[key] = made, np.full(len(made.ids), np.inf), len(self.blocks)
        return self.blocks[key]

    def meet(self, tile: QueryBlock, found) -> None:
        block, limit, name = found
        qi, ci = search_tile(block, tile, self.k, limit)
        for s in range(0, len(qi), 65_536):
            a, c = qi[s : s + 65_536], ci[s : s + 65_536]
            dist = distances(block.x[a], tile.x[c])
            for i, j, e in zip(a.tolist(), tile.ids[c].tolist(), dist.tolist()):
                heap, held = self.heaps.setdefault((name, i), ([], {}))
                item = (-e, -j)
                if j in held:
                    if e >= held[j]:
                        continue
                    heap.remove((-held[j], -j))
                    heap.append(item)
                    heapq.heapify(heap)
                elif len(heap) < self.k:
                    heapq.heappush(heap, item)
                elif item > heap[0]:
                    del held[-heapq.heapreplace(heap, item)[1]]
                else:
                    continue
                held[j] = e

    def rows(self) -> pa.RecordBatch:
        ids = {name: block.ids for block, _, name in self.blocks.values()}
        rows = [(int(ids[name][i]), -j, -e) for (name, i), (heap, _) in self.heaps.items() for e, j in heap]
        cols = list(zip(*rows)) or [(), (), ()]
        return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.float64())], names=["query_id", "vec_id", "score"])


def _search(batches, k: int):
    """Cells come one after the other, as the join sorts by its key; within a cell each tile meets all blocks."""
    at, cell, held, tile = None, _Cell(k), None, None
    for batch in batches:
        for r in batch.to_pylist():
            if (r["dim"], r["g"], r["h"]) != at:
                yield cell.rows()
                at, cell, held = (r["dim"], r["g"], r["h"]), _Cell(k), None
            if held != (r["ids"], r["xs"]):
                held = (r["ids"], r["xs"])
                tile = QueryBlock(np.frombuffer(r["ids"], np.int64), np.frombuffer(r["xs"], np.float64).reshape(-1, r["dim"]))
            cell.meet(tile, cell.block(r["dim"], r["q_ids"], r["q_xs"]))
    yield cell.rows()


def nearest(spark: SparkSession, vectors: DataFrame, queries: DataFrame, k: int = 10, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """``query_id, rank, vec_id, score``: the k nearest of all ``vectors`` but the query's own row.

    Exact Euclidean distances, ties to the smaller id. Null, zero and non-finite vectors take no part,
    nor do null ids; vectors are compared within their dimension. Repeated ids of candidates are distinct
    rows but appear once for a query (the nearest). Fewer than k candidates give fewer rows; an empty
    table gives none. Neither side is collected or broadcast: a task holds the queries of one cell
    (``CELL_QUERIES``) and one tile.
    """
    bound_batches(spark)
    asked = usable(queries, key, vector)
    groups, parts = salts(spark), max(1, -(-asked.count() // CELL_QUERIES))
    tiles = _packed(usable(vectors, key, vector)).withColumn("g", F.pmod(F.xxhash64("ids"), F.lit(groups)).cast("int"))
    tiles = tiles.withColumn("h", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    blocks = _packed(asked).select("dim", F.col("ids").alias("q_ids"), F.col("xs").alias("q_xs"), F.pmod(F.xxhash64("ids"), F.lit(parts)).cast("int").alias("h"))
    blocks = blocks.withColumn("g", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))))
    met = tiles.hint("merge").join(blocks, ["dim", "g", "h"])
    found = met.mapInArrow(lambda batches: _search(batches, k), FOUND)
    once = found.groupBy("query_id", "vec_id").agg(F.min("score").alias("score"))
    rank = F.row_number().over(W.partitionBy("query_id").orderBy("score", "vec_id")).cast("int")
    return once.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
