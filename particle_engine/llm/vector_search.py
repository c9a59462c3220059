"""Exact top-k inner-product search by a vector-approximation file.

* The file: every vector is stored as one byte per dimension, its cell on a uniform
  grid between that dimension's smallest and largest value in the table.  It is
  written once as a table of its own, an eighth of the vectors or less.
* First scan: the cells alone bound each score from above and below.  Each task keeps
  the ``k`` highest lower bounds of a query; over all tasks the k-th is a score that k vectors surely reach.
* Second scan: vectors whose upper bound reaches that score are read exactly, and nothing else
  is; their exact scores decide.

Queries go in blocks that are counted to fit a broadcast, one pass of both scans over the file for each
block, so no vector is copied for each query and only ids and bounds are shuffled.

Defined results: vectors that are null, or hold null or non-finite components,
take no part, nor do null ids; vectors score only against others of the same
length; equal scores go to the smaller vec_id; repeated rows of one vec_id each
count; a query never meets rows of its own id; a repeated query row is asked
once, and a query id with several vectors asks with each of them for one list.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from particle_engine.llm.common import BROADCAST_BYTES, small_batches, stage_table

SCALE = 1024
CELLS = 256
#: Scores held at once in a scan.
SCORES = 1 << 21

#: By length of the vectors: lowest corner and cell width in each dimension.
Grid = dict[int, tuple[np.ndarray, np.ndarray]]


def scaled(vectors: DataFrame) -> DataFrame:
    """(vec_id, dims, v): floor(1024 x) of the vectors that take part."""
    x = F.col("embedding").cast("array<double>")
    whole = F.forall(x, lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < F.lit(float("inf"))))
    ints = F.transform(x, lambda e: F.floor(e * SCALE).cast("long"))
    return vectors.where(F.col("vec_id").isNotNull() & x.isNotNull() & whole).select(F.col("vec_id").cast("long").alias("vec_id"), F.size(x).alias("dims"), ints.alias("v"))


def _matrices(batch: pa.RecordBatch) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(dims, places, matrix) of a batch's vectors, by length."""
    dims, lists = batch.column("dims").to_numpy(), batch.column("v")
    for d in np.unique(dims).tolist():
        at = np.flatnonzero(dims == d)
        yield d, at, lists.take(pa.array(at)).flatten().to_numpy().reshape(len(at), d)


def grid_of(rows: DataFrame) -> Grid:
    """The grid of each length; a task reports its corners once per batch and length, and these meet by dimension."""

    def corners(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [(d, m.min(0), m.max(0)) for d, _, m in _matrices(batch)]
            yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in found], pa.int32()), *(pa.array([x[i].tolist() for x in found], pa.list_(pa.int64())) for i in (1, 2))], ["dims", "low", "high"])

    local = rows.select("dims", "v").mapInArrow(corners, "dims int, low array<long>, high array<long>")
    cells = local.select("dims", F.posexplode(F.arrays_zip("low", "high")).alias("i", "c"))
    met = cells.groupBy("dims", "i").agg(F.min("c.low").alias("low"), F.max("c.high").alias("high")).orderBy("dims", "i").collect()  # a row a dimension
    grid: Grid = {r["dims"]: (np.empty(0), np.empty(0)) for r in rows.select("dims").distinct().collect()}
    for d in {r["dims"] for r in met}:
        low, high = (np.array([r[c] for r in met if r["dims"] == d], float) for c in ("low", "high"))
        grid[d] = (low, np.maximum((high - low) / CELLS, 1e-9))
    return grid


def approximate(matrix: np.ndarray, low: np.ndarray, width: np.ndarray) -> np.ndarray:
    """Cell of each component, a byte."""
    return np.clip((matrix - low) // width, 0, CELLS - 1).astype(np.uint8)


def _file(rows: DataFrame, grid: Grid) -> DataFrame:
    """The approximation file: (vec_id, dims, cells)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cells: list[bytes] = [b""] * batch.num_rows
            for d, at, matrix in _matrices(batch):
                data = approximate(matrix, *grid[d]).tobytes()
                for i, place in enumerate(at.tolist()):
                    cells[place] = data[i * d : (i + 1) * d]
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), batch.column("dims"), pa.array(cells, pa.binary())], ["vec_id", "dims", "cells"])

    return stage_table(rows.mapInArrow(run, "vec_id long, dims int, cells binary"), "cells")


class Bounds:
    """A block of queries of one length, ready to bound scores against cells."""

    def __init__(self, ids: np.ndarray, queries: np.ndarray, low: np.ndarray, width: np.ndarray):
        q = queries.astype(np.float64)
        self.ids, self.weights, self.base = ids, (q * width).T, q @ (low + width / 2)
        # half a cell in every dimension, and what rounding of the sums may add
        self.slack = np.abs(q) @ (width / 2) + 1e-6 * (1 + np.abs(q) @ (np.abs(low) + CELLS * width))

    def middles(self, cells: np.ndarray) -> np.ndarray:
        """Score of each row's cell centres with each query."""
        return cells.astype(np.float64) @ self.weights + self.base


def _scan(batches: Iterator[pa.RecordBatch], blocks: dict[int, Bounds]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(dims, vec_ids, scores of cell centres) in pieces of bounded size."""
    for batch in batches:
        ids, dims = batch.column(0).to_numpy(), batch.column(1).to_numpy()
        for d in np.unique(dims).tolist():
            if d in blocks:
                at = np.flatnonzero(dims == d)
                cells = np.frombuffer(b"".join(batch.column(2).take(pa.array(at)).to_pylist()), np.uint8).reshape(len(at), d)
                step = max(1, SCORES // len(blocks[d].ids))
                for i in range(0, len(at), step):
                    yield d, ids[at[i : i + step]], blocks[d].middles(cells[i : i + step])


def _ask(rows: DataFrame, file: DataFrame, grid: Grid, asked: list, k: int) -> DataFrame:
    """(query_id, vec_id): the pairs of one block of queries that can be among the k best."""
    blocks = {}
    for d in {r["dims"] for r in asked} & set(grid):
        own = [r for r in asked if r["dims"] == d]
        blocks[d] = Bounds(np.array([r["vec_id"] for r in own]), np.array([r["v"] for r in own], np.int64).reshape(len(own), d), *grid[d])
    shared = file.sparkSession.sparkContext.broadcast(blocks)

    def lowest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = {d: np.full((k, len(b.ids)), -np.inf) for d, b in shared.value.items()}
        for d, ids, middle in _scan(batches, shared.value):
            b = shared.value[d]
            lower = np.where(ids[:, None] == b.ids[None, :], -np.inf, middle - b.slack)
            lower = np.concatenate((best[d], lower))
            best[d] = -np.partition(-lower, k - 1, axis=0)[:k]
        for d, found in best.items():
            row, query = np.nonzero(found > -np.inf)
            yield pa.RecordBatch.from_arrays([pa.array(shared.value[d].ids[query], pa.int64()), pa.array(np.full(len(query), d), pa.int32()), pa.array(query, pa.int32()), pa.array(found[row, query], pa.float64())], ["query_id", "dims", "query", "lower"])

    local = file.mapInArrow(lowest, "query_id long, dims int, query int, lower double")
    rank = F.row_number().over(Window.partitionBy("dims", "query").orderBy(F.desc("lower")))
    kth = local.withColumn("rank", rank).where(F.col("rank") == k).select("dims", "query", "lower").collect()  # a row a query of the block
    least = {d: np.full(len(b.ids), -np.inf) for d, b in blocks.items()}
    for r in kth:
        least[r["dims"]][r["query"]] = r["lower"]
    floors = file.sparkSession.sparkContext.broadcast(least)

    def reach(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for d, ids, middle in _scan(batches, shared.value):
            b = shared.value[d]
            row, query = np.nonzero((middle + b.slack >= floors.value[d]) & (ids[:, None] != b.ids[None, :]))
            yield pa.RecordBatch.from_arrays([pa.array(b.ids[query], pa.int64()), pa.array(ids[row], pa.int64())], ["query_id", "vec_id"])

    return file.mapInArrow(reach, "query_id long, vec_id long").distinct()


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """(query_id, rank, vec_id, score) of the k highest inner products of each query row against ``vectors``."""
    rows = small_batches(stage_table(scaled(vectors), "vectors"))
    asked = stage_table(scaled(queries).dropDuplicates(["vec_id", "v"]), "queries")
    size = asked.agg(F.coalesce(F.sum(8 * F.col("dims") + 64), F.lit(0)).alias("n")).first()["n"]
    grid = grid_of(rows)
    file = _file(rows, grid)
    # as many blocks as keep each under half a broadcast on average; a hash deals them evenly
    n_blocks = -(-2 * size // BROADCAST_BYTES)
    found = None
    for block in range(n_blocks):
        part = asked.where(F.pmod(F.xxhash64("vec_id", F.lit(7)), F.lit(n_blocks)) == block).collect()
        pairs = stage_table(_ask(rows, file, grid, part, k), "reached") if part else None
        found = pairs if found is None else found if pairs is None else found.unionByName(pairs)
    if found is None:
        found = rows.sparkSession.createDataFrame([], "query_id long, vec_id long")
    query = asked.select(F.col("vec_id").alias("query_id"), F.col("dims").alias("q_dims"), F.col("v").alias("q"))
    both = found.join(rows, "vec_id").join(query, "query_id").where("dims = q_dims")
    score = F.aggregate(F.zip_with("v", "q", lambda a, b: a * b), F.lit(0).cast("long"), lambda s, x: s + x)
    scored = both.select("query_id", "vec_id", score.alias("score"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return scored.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
