"""Exact top-k search: a Voronoi kNN join for the largest inner products.

Vectors are grouped by their nearest pivot.  Queries are stretched to the
largest length and vectors get one more coordinate that brings them to it, so
the largest inner product is the smallest distance.  From summaries of the
groups (radii, and the k nearest distances to each pivot) every query gets an
upper bound of its k-th distance; a block of queries is replicated only to
groups that the triangle inequality cannot exclude.  Blocks are solved locally
with integer scores and the local answers are merged.

A group with many vectors is split into salted parts, and queries go to each
of them.  Defined cases: null vectors, vectors with null or non-finite
components and null ids take no part; shorter vectors count as ending in zeros,
empty ones as zeros alone; repeated ids count as one with its best score and never answer themselves;
ties go to the smaller id; a zero query reaches every group; fewer vectors than k give all; an empty table gives
no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import shared
from .batches import fields, spark_schema

PIVOTS = 32
#: Vectors that one part of a group may hold, and queries of a block.
PART_ROWS, BLOCK_ROWS = 50_000, 512
SLACK = 1e-9
#: Distances to the pivot that a chunk's summary holds; k must stay below.
NEAREST = 64

CHUNKS = fields(cell=pa.int32(), salt=pa.int64(), n=pa.int64(), far=pa.float64(), near=pa.float64(), nearest=pa.list_(pa.struct([("d", pa.float64()), ("id", pa.int64())])), ids=pa.binary(), vectors=pa.binary())
BLOCKS = fields(cells=pa.list_(pa.int32()), query_ids=pa.binary(), queries=pa.binary())
HITS = fields(query_id=pa.int64(), vec_id=pa.int64(), score=pa.int64())


def scaled(vectors: DataFrame, scale: int = 256) -> DataFrame:
    """vec_id and integer components floor(scale * x) of the vectors that take part."""
    x = F.transform("embedding", lambda v: v.cast("double"))
    fine = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    own = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), x.alias("x")).where(F.col("vec_id").isNotNull() & F.col("x").isNotNull() & fine)
    return own.select("vec_id", F.transform("x", lambda v: F.floor(scale * v).cast("long")).alias("x"))


def _matrix(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    ids = batch.column("vec_id").to_numpy(zero_copy_only=False)
    return ids, np.stack(batch.column("x").to_numpy(zero_copy_only=False)) if len(ids) else np.zeros((0, 0), np.int64)


def _packed(x: np.ndarray) -> bytes:
    small = not len(x) or np.abs(x).max() < 2**31 - 1
    return np.ascontiguousarray(x, "<i4" if small else "<i8").tobytes()


class Space:
    """Pivots and the sphere on which stretched queries and lifted vectors lie."""

    def __init__(self, pivots: np.ndarray, square: int):
        self.square = float(max(square, 1))
        self.pivots = self.lift(pivots)
        self.between = self.distances(self.pivots)

    def lift(self, x: np.ndarray) -> np.ndarray:
        """Vectors with the coordinate that makes them as long as the longest."""
        x = x.astype(float)
        return np.concatenate([x, np.sqrt(np.maximum(self.square - (x * x).sum(1), 0))[:, None]], 1)

    def stretch(self, q: np.ndarray) -> np.ndarray:
        """Queries as long as the longest vector; the last coordinate is 0.  A zero query stays at the pole."""
        q = q.astype(float)
        length = np.sqrt((q * q).sum(1))
        out = np.concatenate([q * (np.sqrt(self.square) / np.maximum(length, 1e-12))[:, None], np.zeros((len(q), 1))], 1)
        out[length == 0] = 0
        out[length == 0, -1] = np.sqrt(self.square)
        return out

    def distances(self, points: np.ndarray) -> np.ndarray:
        return np.sqrt(np.maximum(2 * self.square - 2 * points @ self.pivots.T, 0))


def _chunker(space: Space):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, x = _matrix(batch)
            if not len(ids):
                continue
            d = space.distances(space.lift(x))
            cell = d.argmin(1)
            rows = []
            for c in np.unique(cell):
                own = np.flatnonzero(cell == c)
                order = np.argsort(d[own, c], kind="stable")
                near = d[own, c][order]
                closest = [{"d": float(x), "id": int(i)} for x, i in zip(near[:NEAREST], ids[own][order[:NEAREST]], strict=True)]
                raw = _packed(x[own])
                wide = len(raw) > 4 * x.shape[1] * len(own)
                rows.append((int(c), int(ids[own[0]]), len(own), float(near[-1]), float(near[0]), closest, ids[own].astype("<i8").tobytes(), bytes([wide]) + raw))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), CHUNKS.types, strict=True)], schema=CHUNKS)

    return run


def _planner(space: Space, far: np.ndarray, near: np.ndarray, nearest: list[list[float]], there: np.ndarray, k: int):
    """Blocks of queries with the groups that may hold one of their k nearest."""
    all_near = np.concatenate([np.asarray(x) for x in nearest]) if nearest else np.zeros(0)
    owner = np.repeat(np.arange(len(nearest)), [len(x) for x in nearest])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, q = _matrix(batch)
            if not len(ids):
                continue
            d = space.distances(space.stretch(q))
            upper = d[:, owner] + all_near
            # One more than k: a query is among the vectors itself.
            bound = np.partition(upper, k, 1)[:, k] if upper.shape[1] > k else np.full(len(ids), np.inf)
            # All vectors score 0 with a zero query, so its distances tell nothing and the ids decide.
            bound = np.where(q.any(1), bound, np.inf)
            reach = np.maximum(d - far, near - d) <= bound[:, None] * (1 + SLACK) + 1e-6
            reach &= there
            order = np.argsort(d.argmin(1), kind="stable")
            rows = []
            for a in range(0, len(order), BLOCK_ROWS):
                own = order[a : a + BLOCK_ROWS]
                raw = _packed(q[own])
                wide = len(raw) > 4 * q.shape[1] * len(own)
                rows.append((np.flatnonzero(reach[own].any(0)).tolist(), ids[own].astype("<i8").tobytes(), bytes([wide]) + raw))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), BLOCKS.types, strict=True)], schema=BLOCKS)

    return run


def best_k(scores: np.ndarray, ids: np.ndarray, query_id: int, k: int) -> list[tuple[int, int]]:
    """(id, score) of the k best other ids, ties to the smaller id, the best score of a repeated id."""
    take = min(len(ids), k + 1)
    while True:
        floor = np.partition(scores, len(scores) - take)[len(scores) - take]
        own = np.flatnonzero(scores >= floor)
        own = own[ids[own] != query_id]
        own = own[np.lexsort((ids[own], -scores[own]))]
        _, first = np.unique(ids[own], return_index=True)
        if len(first) >= k or take == len(ids):
            own = own[np.sort(first)][:k]
            return [(int(ids[i]), int(scores[i])) for i in own]
        take = min(len(ids), 2 * take)


def _load(raw: bytes, rows: int) -> np.ndarray:
    return np.frombuffer(raw, "<i8" if raw[0] else "<i4", offset=1).reshape(rows, -1) if rows else np.zeros((0, 0), np.int64)


def _solver(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                ids, query_ids = np.frombuffer(row["ids"], "<i8"), np.frombuffer(row["query_ids"], "<i8")
                x, q = _load(row["vectors"], len(ids)), _load(row["queries"], len(query_ids))
                most = max(float(np.abs(x).max(initial=0)) * float(np.abs(q).max(initial=0)) * x.shape[1], 1.0)
                exact = most < 2.0**52  # then every partial sum is an integer that a double holds
                out: tuple[list, list, list] = ([], [], [])
                for a in range(0, len(query_ids), 64):
                    part = q[a : a + 64]
                    scores = (part.astype(float) @ x.T.astype(float)).astype(np.int64) if exact else part.astype(np.int64) @ x.T.astype(np.int64)
                    for query_id, own in zip(query_ids[a : a + 64].tolist(), scores, strict=True):
                        for vec_id, score in best_k(own, ids, query_id, k):
                            for column, value in zip(out, (query_id, vec_id, score), strict=True):
                                column.append(value)
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in out], schema=HITS)

    return run


def knn_join(vectors: DataFrame, is_query: Column, k: int = 5, pivots: int = PIVOTS, scale: int = 256, part_rows: int = PART_ROWS) -> DataFrame:
    """query_id, rank, vec_id, score: the k largest inner products of each query among all other vectors."""
    if not 0 < k < NEAREST:
        raise ValueError(f"k must lie between 1 and {NEAREST - 1}")
    spark = vectors.sparkSession
    own = scaled(vectors, scale)
    sizes = own.groupBy(F.size("x").alias("dim")).agg(F.count("*").alias("n"), F.max(F.aggregate("x", F.lit(0).cast("long"), lambda a, v: a + v * v)).alias("square"))
    whole = sizes.agg(F.max("dim").alias("dim"), F.max("square").alias("square")).first()
    if whole["dim"] is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    dim = max(whole["dim"], 1)
    own = own.select("vec_id", F.when(F.size("x") < dim, F.concat("x", F.array_repeat(F.lit(0).cast("long"), dim - F.size("x")))).otherwise(F.col("x")).alias("x"))
    picked = own.orderBy(F.xxhash64("vec_id"), "vec_id").limit(pivots).collect()
    space = Space(np.array([r["x"] for r in picked], np.int64), whole["square"])
    chunks = shared.written(own.mapInArrow(_chunker(space), spark_schema(CHUNKS)), "knn-chunks")
    groups = {r["cell"]: r for r in chunks.groupBy("cell").agg(F.sum("n").alias("n"), F.max("far").alias("far"), F.min("near").alias("near")).collect()}
    # At most k + 1 distances for each pivot are gathered, and none counts for two rows of one id.
    close = chunks.select("cell", F.explode("nearest").alias("x")).groupBy("cell", F.col("x.id").alias("id")).agg(F.min("x.d").alias("d"))
    ranked = close.withColumn("i", F.row_number().over(Window.partitionBy("cell").orderBy("d", "id")))
    nearest: list[list[float]] = [[] for _ in picked]
    seen: set[int] = set()
    for r in sorted(ranked.where(F.col("i") <= k + 1).collect(), key=lambda r: (r["d"], r["id"])):
        if r["id"] not in seen:
            seen.add(r["id"])
            nearest[r["cell"]].append(r["d"])
    far = np.array([groups[c]["far"] if c in groups else 0.0 for c in range(len(picked))])
    near = np.array([groups[c]["near"] if c in groups else 0.0 for c in range(len(picked))])
    there = np.array([c in groups for c in range(len(picked))])
    blocks = own.where(is_query).mapInArrow(_planner(space, far, near, nearest, there, k), spark_schema(BLOCKS))
    parts = F.lit(1)
    for c, r in groups.items():
        if r["n"] > part_rows:
            parts = F.when(F.col("cell") == c, -(-r["n"] // part_rows)).otherwise(parts)
    spread = blocks.select(F.explode("cells").alias("cell"), "query_ids", "queries")
    spread = spread.withColumn("part", F.explode(F.sequence(F.lit(0), parts - 1)))
    salted = chunks.select("cell", F.pmod(F.xxhash64("salt"), parts).cast("int").alias("part"), "ids", "vectors")
    hits = spread.join(salted, ["cell", "part"]).select("ids", "vectors", "query_ids", "queries").mapInArrow(_solver(k), spark_schema(HITS))
    best = hits.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return best.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
