"""Baselines: exact sizes, min-rank propagation, and distinct counts over the joined rows."""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import md5

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from .estimate import Spec, finish, hits_by_join, hashed, k_smallest
from .relations import Rel, work


#: Rows of a right side that go to every executor; the driver gathers them first.
BROADCAST_ROWS = 2_000_000


def join_project(rel: Rel, hint: str | None = None) -> DataFrame:
    """The exact result: distinct (lk, rk).  A right side above ``BROADCAST_ROWS`` is dealt by the join value, not broadcast."""
    if hint == "broadcast" and rel.right.limit(BROADCAST_ROWS + 1).count() > BROADCAST_ROWS:
        hint = "shuffle_hash"
    right = rel.right.hint(hint) if hint else rel.right
    return rel.left.join(right, "jk").select("lk", "rk").distinct()


def exact_size(rel: Rel, hint: str | None = None) -> DataFrame:
    """One row z; ``hint`` fixes the physical join (broadcast, shuffle_hash, merge)."""
    return join_project(rel, hint).agg(F.count("*").alias("z"))


def exact_by_left(rel: Rel) -> DataFrame:
    """One row z, summing each left value's distinct partners."""
    per = rel.left.join(rel.right, "jk").groupBy("lk").agg(F.count_distinct("rk").alias("n"))
    return per.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("z"))


def exponential_rank(value: Column, round_: Column) -> Column:
    """A unit exponential variate of a value in a round, the same in any engine that has md5."""
    text = F.concat(F.lit("rank"), round_.cast("string"), F.lit(":"), F.coalesce(value.cast("string"), F.lit("\\N")))
    unit = (F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long").cast("double") + 0.5) / float(2**52)
    return -F.log(unit)


#: Vectors of ranks that a task holds of ends, and of first values: 64 rounds are 512 bytes each.
VECTORS = 1 << 16
#: First values of a chain up to which its leading factors are multiplied out: every task then reduces to that many vectors.
FEW_FIRSTS = 256


def _ranks_of(ends: list, rounds: int) -> np.ndarray:
    """``exponential_rank`` of each end in each round."""
    digits = [[int(md5(f"rank{i}:{e}".encode()).hexdigest()[:13], 16) for i in range(1, rounds + 1)] for e in ends]
    return -np.log((np.array(digits, np.int64).reshape(-1, rounds).astype(np.float64) + 0.5) / float(2**52))


class _Vectors:
    """Vectors by value, ``VECTORS`` of them at most; the caller empties it when it is full."""

    def __init__(self, rounds: int):
        self.rounds, self.at, self.rows = rounds, {}, np.zeros((256, rounds))

    def places(self, values: list, fresh) -> np.ndarray:
        new = [v for v in values if v not in self.at]
        if new:
            n = len(self.at)
            while len(self.rows) < n + len(new):
                self.rows = np.concatenate([self.rows, np.zeros_like(self.rows)])
            self.rows[n : n + len(new)] = fresh(new)
            self.at.update(zip(new, range(n, n + len(new)), strict=True))
        return np.array([self.at[v] for v in values], np.int64)


def _lowest(rows: np.ndarray, group: np.ndarray) -> np.ndarray:
    """The minima of rows by rising group numbers."""
    return np.minimum.reduceat(rows, np.flatnonzero(np.diff(group, prepend=-1)), axis=0)


def _min_ranks(rounds: int, schema: pa.DataType):
    """From (key, side, end, first), sorted by key and side: the minima of each first value over the ends that share a key with it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ends, firsts = _Vectors(rounds), _Vectors(rounds)
        open_key, open_low = None, np.full(rounds, np.inf)

        def give() -> Iterator[pa.RecordBatch]:
            names, n = list(firsts.at), len(firsts.at)
            for i in range(0, n, 4096):
                part = firsts.rows[i : min(i + 4096, n)]
                ranks = pa.ListArray.from_arrays(pa.array(np.arange(len(part) + 1) * rounds, pa.int32()), pa.array(part.ravel()))
                yield pa.RecordBatch.from_arrays([pa.array(names[i : i + 4096], schema), ranks], names=["a", "ranks"])

        for batch in batches:
            if not batch.num_rows:
                continue
            key, side = batch.column("key"), batch.column("side").to_numpy()
            change = np.zeros(batch.num_rows, bool)
            change[1:] = np.asarray(pc.not_equal(key[1:], key[:-1]))
            group, is_end = np.cumsum(change), side == 0
            low = np.full((group[-1] + 1, rounds), np.inf)
            if key[0].as_py() == open_key:
                low[0] = open_low
            if is_end.any():
                coded = batch.column("end").filter(pa.array(is_end)).dictionary_encode()
                if len(ends.at) + len(coded.dictionary) > VECTORS:
                    ends = _Vectors(rounds)
                at = ends.places(coded.dictionary.to_pylist(), lambda new: _ranks_of(new, rounds))[coded.indices.to_numpy()]
                of = group[is_end]
                mine = np.unique(of)
                low[mine] = np.minimum(low[mine], _lowest(ends.rows[at], of))
            open_key, open_low = key[len(key) - 1].as_py(), low[-1].copy()
            # Keys without an end give nothing.
            takes = ~is_end & np.isfinite(low[:, 0])[group]
            if takes.any():
                coded = batch.column("first").filter(pa.array(takes)).dictionary_encode(null_encoding="encode")
                if len(firsts.at) + len(coded.dictionary) > VECTORS:
                    yield from give()
                    firsts = _Vectors(rounds)
                at = firsts.places(coded.dictionary.to_pylist(), lambda new: np.inf)[coded.indices.to_numpy()]
                order = np.argsort(at, kind="stable")
                mine = np.unique(at)
                firsts.rows[mine] = np.minimum(firsts.rows[mine], _lowest(low[group[takes][order]], at[order]))
        yield from give()

    return run


def _reached(chain: list[DataFrame]) -> DataFrame:
    """(a, b) of the product of the factors, as rows."""
    out = chain[0]
    for table in chain[1:]:
        out = out.withColumnRenamed("b", "__on").join(table.withColumnRenamed("a", "__on"), "__on").select("a", "b").distinct()
    return out


def min_rank_sizes(chain: list[DataFrame], rounds: int = 64) -> DataFrame:
    """(first, size): the estimated number of ends each first value reaches along a chain of (a, b) edge tables.

    Every end value draws exponential ranks; minima travel back along the
    chain, and (rounds - 1) over the sum of minima estimates how many took part.
    The last two factors meet by ranges of their shared value: edges travel as
    they are, a task draws the ranks of the ends it sees, and only minima of
    first values leave it.  Where there are few first values, the factors
    before the last are multiplied out, so that this is the only step.
    """
    if len(chain) > 2 and chain[0].select("a").distinct().limit(FEW_FIRSTS + 1).count() <= FEW_FIRSTS:
        chain = [_reached(chain[:-1]), chain[-1]]
    last = chain[-1]
    before = chain[-2] if len(chain) > 1 else last.select("a", F.col("a").alias("b")).distinct()
    whole = isinstance(last.schema["b"].dataType, T.IntegralType)
    end = F.col("b") if whole else F.col("b").cast("string")
    first = before.schema["a"].dataType
    e = last.where("b is not null and a is not null").select(F.col("a").alias("key"), F.lit(0).alias("side"), end.alias("end"), F.lit(None).cast(first).alias("first"))
    f = before.where("b is not null").select(F.col("b").alias("key"), F.lit(1).alias("side"), F.lit(None).cast("long" if whole else "string").alias("end"), F.col("a").alias("first"))
    rows = e.unionByName(f).repartitionByRange("key").sortWithinPartitions("key", "side")
    low = rows.mapInArrow(_min_ranks(rounds, to_arrow_type(first)), T.StructType([T.StructField("a", first), T.StructField("ranks", T.ArrayType(T.DoubleType()))]))
    least = [F.min(F.col("ranks")[i]).alias(f"m{i}") for i in range(rounds)]
    low = low.groupBy("a").agg(*least)
    for table in reversed(chain[:-2]):
        low = table.join(low.withColumnRenamed("a", "b"), "b").groupBy("a").agg(*[F.min(f"m{i}").alias(f"m{i}") for i in range(rounds)])
    total = F.aggregate(F.array(*[F.col(f"m{i}") for i in range(rounds)]), F.lit(0.0), lambda x, y: x + y)
    return low.select(F.col("a").alias("first"), ((rounds - 1) / total).alias("size"))


def min_rank_size(rel: Rel, rounds: int = 64) -> DataFrame:
    """One row z_hat of the earlier estimator, which works on n * rounds rows."""
    chain = [rel.left.select(F.col("lk").alias("a"), F.col("jk").alias("b")), rel.right.select(F.col("jk").alias("a"), F.col("rk").alias("b"))]
    return min_rank_sizes(chain, rounds).agg(F.sum("size").alias("z_hat"))


def min_rank_chain(chain: list[DataFrame], rounds: int = 64) -> DataFrame:
    """One row z_hat for a chain of any number of relations (a, b)."""
    return min_rank_sizes(chain, rounds).agg(F.sum("size").alias("z_hat"))


def explicit_bottomk(rel: Rel, spec: Spec) -> DataFrame:
    """A bottom-k sketch fed with every joined pair."""
    left, right = hashed(rel, spec, spec.seed)
    return finish(k_smallest(hits_by_join(left, right, spec, 1.0), spec.k), spec, 1.0)


def builtin_hll(rel: Rel) -> DataFrame:
    """Spark's own approximate distinct counts over the joined rows."""
    pair = F.xxhash64("lk", "rk")
    return rel.left.join(rel.right, "jk").agg(
        F.approx_count_distinct(pair, 0.02).alias("hll_plus"), F.hll_sketch_estimate(F.hll_sketch_agg(pair, F.lit(12))).alias("hll")
    )


def builtin_theta(rel: Rel) -> DataFrame:
    """A theta sketch over the joined rows."""
    return rel.left.join(rel.right, "jk").agg(F.theta_sketch_estimate(F.theta_sketch_agg(F.xxhash64("lk", "rk"), F.lit(12))).alias("theta"))


def tuple_sample_size(rel: Rel, p: float, seed: int = 5) -> DataFrame:
    """Uniform tuples instead of values: the biased control."""
    left, right = rel.left.sample(p, seed), rel.right.sample(p, seed + 1)
    return join_project(Rel(left, right)).agg((F.count("*") / (p * p)).alias("z_hat"))


def catalyst_size(rel: Rel) -> DataFrame:
    """The optimizer's own guess for the joined rows, bytes from plan statistics and rows where it has them, beside the rows that there are."""
    stats = rel.left.join(rel.right, "jk")._jdf.queryExecution().optimizedPlan().stats()
    rows = stats.rowCount()
    guess = int(str(rows.get())) if rows.isDefined() else None
    return work(rel).select(F.lit(float(str(stats.sizeInBytes()))).alias("size_bytes"), F.lit(guess).cast("long").alias("rows"), "joined")
