"""Bottom-k size estimation over implicit pairs.

Pairs hash to a difference on a circle, so within one join value the pairs
below a threshold are a cyclic range.  ``hits`` lists them without expanding
the join, ``k_smallest`` keeps the least, ``finish`` turns them to a row.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass, replace
from math import ceil, floor, log2

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.bounds import eps_for, k_for
from ..functions.hashing import FAMILIES
from .relations import Rel, work
from .scan import BLOCK_PAIRS, BottomK, before, scan_hits

POLICIES = ("printed", "doubled", "inverse_k", "one", "fixed")
STRATEGIES = ("cells", "sweep", "grouped", "full")
ESTIMATE = "run int, k int, policy string, p double, threshold long, filled boolean, kept long, kth_hash long, z_hat double, lo double, hi double, status string"


#: Parts into which the grouped strategy splits a join value.
GROUP_CELLS = 4
#: Rows of whole groups that the grouped strategy walks at once.
GROUP_ROWS = 1 << 17


@dataclass(frozen=True)
class Spec:
    """How to estimate.  ``eps`` sets k; ``on_short`` says what an unfilled set gives."""

    k: int = 1024
    eps: float | None = None
    policy: str = "doubled"
    p: float | None = None
    strategy: str = "cells"
    family: str = "mix63"
    seed: int = 1
    runs: int = 1
    on_short: str = "bound"
    tighten: str = "local"
    estimator: str = "ratio"

    def __post_init__(self):
        if self.eps is not None:
            object.__setattr__(self, "k", k_for(self.eps))
        if self.k < 1 or self.policy not in POLICIES or self.strategy not in STRATEGIES or self.family not in FAMILIES:
            raise ValueError(f"unknown setting in {self}")
        if self.on_short not in ("bound", "count", "scaled", "widen") or self.tighten not in ("none", "local", "pilot") or self.estimator not in ("ratio", "unbiased"):
            raise ValueError(f"unknown setting in {self}")
        if self.policy == "fixed" and not (self.p and 0 < self.p <= 1):
            raise ValueError("the fixed policy needs p in (0, 1]")

    @property
    def below_guarantee(self) -> bool:
        """k under 144 means an error of 1/4 or more, outside the theorem."""
        return self.k < 144

    def seeds(self, run: int) -> tuple[str, str]:
        return f"L{run}:", f"R{run}:"

    def all_runs(self) -> range:
        return range(self.seed, self.seed + self.runs)


def threshold_p(k: int, policy: str, maxprod: int | None = None, p: float | None = None) -> float:
    """The share of the circle below which pairs are listed."""
    if policy == "one":
        return 1.0
    if policy == "fixed":
        return float(p)
    if policy == "inverse_k":
        return min(1.0, 2.0 / k)
    if not maxprod:
        return 1.0
    return min(1.0 / k, 1.0 * k / maxprod) if policy == "printed" else min(1.0, 2.0 / k, 2.0 * k / maxprod)


def choose_threshold(rel: Rel, spec: Spec) -> float:
    """p for the spec; the statistics are one row."""
    if spec.policy in ("one", "fixed", "inverse_k"):
        return threshold_p(spec.k, spec.policy, p=spec.p)
    return threshold_p(spec.k, spec.policy, int(work(rel).first()["maxprod"]))


def as_threshold(p: float, domain: int) -> int:
    """Hits have a pair hash below this; at p = 1 the filter goes."""
    return min(domain, ceil(p * float(domain)))


def hashed(rel: Rel, spec: Spec, run: int) -> tuple[DataFrame, DataFrame]:
    """(jk, x_h) and (jk, y_h): all that travels."""
    family = FAMILIES[spec.family]
    left_seed, right_seed = spec.seeds(run)
    return (
        rel.left.select("jk", family.hash(F.col("lk"), left_seed).alias("x_h")),
        rel.right.select("jk", family.hash(F.col("rk"), right_seed).alias("y_h")),
    )


def _residual(df: DataFrame, spec: Spec, t: int) -> DataFrame:
    family = FAMILIES[spec.family]
    df = df.withColumn("pair_h", family.pair(F.col("x_h"), F.col("y_h")))
    if t < family.domain:
        df = df.where(F.col("pair_h") < t)
    return df.select("x_h", "y_h", "pair_h")


def cells_for(p: float, domain: int) -> tuple[int, int]:
    """Number of equal cells, each at least the threshold wide, and the cell width."""
    cells = 1 if p >= 1 else 2 ** max(0, min(40, floor(log2(1 / p) + 1e-12)))
    while cells > 1 and domain // cells < as_threshold(p, domain):
        cells //= 2
    return cells, -(-domain // cells)


def hits_by_cell(left: DataFrame, right: DataFrame, spec: Spec, p: float) -> DataFrame:
    """The cyclic range as an equi-join on (join value, cell).

    A right row looks into its own cell and the next; heavy join values spread
    over the cells.
    """
    domain = FAMILIES[spec.family].domain
    t = as_threshold(p, domain)
    if cells_for(p, domain)[0] == 1:
        return _residual(left.join(right, "jk"), spec, t)
    l2, r2 = in_cells(left, right, domain, p)
    return _residual(l2.join(r2, ["jk", "cell"]), spec, t)


def in_cells(left: DataFrame, right: DataFrame, domain: int, p: float) -> tuple[DataFrame, DataFrame]:
    """Both sides with the cells in which they meet; right rows stand in their own and the next."""
    cells, width = cells_for(p, domain)
    if cells == 1:
        return left.withColumn("cell", F.lit(0)), right.withColumn("cell", F.lit(0))
    power = not domain & (domain - 1)
    cell = lambda c: F.shiftright(c, width.bit_length() - 1) if power else F.expr(f"{c} div {width}")
    both = F.array(F.col("own"), F.pmod(F.col("own") + 1, F.lit(cells)))
    return left.withColumn("cell", cell("x_h")), right.withColumn("own", cell("y_h")).select("jk", "y_h", F.explode(both).alias("cell"))


def probes(left: DataFrame, right: DataFrame, spec: Spec, p: float) -> DataFrame:
    """(jk, x_h, y_h) that the cells make the engine look at: the join without its residual filter."""
    l2, r2 = in_cells(left, right, FAMILIES[spec.family].domain, p)
    return l2.join(r2, ["jk", "cell"]).select("jk", "x_h", "y_h")


def hits_by_sweep(left: DataFrame, right: DataFrame, spec: Spec, p: float, keep: int | None = None, how: str = "hash") -> DataFrame:
    """One sort by (join value, cell, hash), then one forward scan in batches; with ``keep`` the threshold falls on the way."""
    domain = FAMILIES[spec.family].domain
    return scan_hits(left, right, spec.family, as_threshold(p, domain), *cells_for(p, domain), keep, how)


def walk_group(x: np.ndarray, y: np.ndarray, t: int, domain: int) -> tuple[np.ndarray, np.ndarray, int, int]:
    """Pairs of one group below the threshold, by a cyclic run in the sorted left hashes.

    Also the moves of the start cursor, which only goes forward from the first
    left row, and the pairs visited.  A run visits a left row once at most.
    """
    x, y = np.unique(x), np.unique(y)
    if not len(x) or not len(y):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), 0, 0
    low = np.searchsorted(x, y, "left")
    if t >= domain:
        return np.tile(x, len(y)), np.repeat(y, len(x)), int(low[-1]), len(x) * len(y)
    end = y + t
    high = np.where(end < domain, np.searchsorted(x, np.minimum(end, domain - 1), "left"), len(x) + np.searchsorted(x, end - domain, "left"))
    count = np.maximum(high - low, 0)
    at = np.repeat(low, count) + np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
    return x[at % len(x)], np.repeat(y, count), int(low[-1]), int(count.sum())


def walk_groups(x_run: np.ndarray, x: np.ndarray, y_run: np.ndarray, y: np.ndarray, t: int, domain: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """What ``walk_group`` gives, for many groups at once: their numbers rise, hashes rise within a group, none comes twice.

    For each right row: the first left row of its cyclic run, its length, and the group's first and number of left rows.
    """
    start = np.searchsorted(x_run, y_run)
    size = np.searchsorted(x_run, y_run, "right") - start
    low = before(x_run, x, y_run, y)
    if t >= domain:
        return low, size, np.stack([start, size])
    end = y + t
    high = before(x_run, x, y_run, np.where(end < domain, end, end - domain)) + np.where(end < domain, 0, size)
    return low, np.maximum(high - low, 0), np.stack([start, size])


def _grouped(t: int, domain: int, keep: int | None):
    """Whole groups of (jk, cell) from sorted rows, as many at once as ``GROUP_ROWS`` holds."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = BottomK(keep) if keep else None

        def groups(rows: pa.Table) -> Iterator[pa.RecordBatch]:
            rows = rows.combine_chunks()
            jk, (cell, side, h) = rows.column("jk").combine_chunks(), (rows.column(c).to_numpy() for c in ("cell", "side", "h"))
            new = np.ones(len(h), bool)
            new[1:] = np.asarray(pc.not_equal(jk[1:], jk[:-1])) | (cell[1:] != cell[:-1])
            again = ~new
            again[1:] &= (side[1:] == side[:-1]) & (h[1:] == h[:-1])
            group, once = np.cumsum(new), ~again
            left, right = once & (side == 0), once & (side == 1)
            x, y = h[left], h[right]
            low, count, (start, size) = walk_groups(group[left], x, group[right], y, min(t, kept.limit + 1) if kept else t, domain)
            total, at = np.cumsum(count), 0
            while at < len(y):
                stop = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + BLOCK_PAIRS, "right")))
                n = count[at:stop]
                where = np.repeat(low[at:stop] - start[at:stop] - np.cumsum(n) + n, n) + np.arange(n.sum())
                px, py = x[np.repeat(start[at:stop], n) + where % np.repeat(size[at:stop], n)], np.repeat(y[at:stop], n)
                if kept:
                    kept.add_batch((px - py) % domain, px, py)
                elif len(px):
                    yield pa.RecordBatch.from_arrays([pa.array(px), pa.array(py)], names=["x_h", "y_h"])
                at = stop

        held, n = [], 0
        for batch in batches:
            held.append(batch)
            n += batch.num_rows
            if n < GROUP_ROWS:
                continue
            rows = pa.Table.from_batches(held)
            jk, cell = rows.column("jk"), rows.column("cell")
            # The last group may go on in the next batch.
            last = np.asarray(pc.fill_null(pc.and_(pc.equal(jk, jk[n - 1]), pc.equal(cell, cell[n - 1])), False))
            cut = int(np.argmax(last))
            if cut:
                yield from groups(rows.slice(0, cut))
            held = rows.slice(cut).combine_chunks().to_batches()
            n -= cut
        if n:
            yield from groups(pa.Table.from_batches(held))
        if kept:
            yield pa.RecordBatch.from_arrays([pa.array(kept.rows[:, i]) for i in (1, 2)], names=["x_h", "y_h"])

    return run


def hits_by_group(left: DataFrame, right: DataFrame, spec: Spec, p: float, keep: int | None = None) -> DataFrame:
    """Whole groups of (join value, cell) with sorted arrays, for groups that fit a worker; light groups are walked together.

    With ``keep`` a task holds its kept set over all its groups, looks only at
    pairs below its k-th, and gives no others.
    """
    domain = FAMILIES[spec.family].domain
    t = as_threshold(p, domain)
    if domain > 2**62:
        raise ValueError("the grouped strategy needs a domain of at most 2^62")
    # Few wide cells: a heavy join value is split, a light one isn't many groups.
    l2, r2 = in_cells(left, right, domain, max(p, 1 / GROUP_CELLS))
    row = lambda df, side, h: df.select("jk", F.col("cell").cast("long").alias("cell"), F.lit(side).alias("side"), F.col(h).alias("h"))
    rows = row(l2, 0, "x_h").unionByName(row(r2, 1, "y_h"))
    if isinstance(rows.schema["jk"].dataType, (T.StructType, T.ArrayType)):
        rows = rows.withColumn("jk", F.to_json(F.struct("jk")))
    rows = rows.repartition("jk", "cell").sortWithinPartitions("jk", "cell", "side", "h")
    return _residual(rows.mapInArrow(_grouped(t, domain, keep), "x_h long, y_h long"), spec, t)


def hits_by_join(left: DataFrame, right: DataFrame, spec: Spec, p: float) -> DataFrame:
    """Every joined pair, then the filter: what the other strategies avoid."""
    return _residual(left.join(right, "jk"), spec, as_threshold(p, FAMILIES[spec.family].domain))


_BY = {"cells": hits_by_cell, "sweep": hits_by_sweep, "grouped": hits_by_group, "full": hits_by_join}


def hits(rel: Rel, spec: Spec, p: float | None = None, run: int | None = None) -> DataFrame:
    """(x_h, y_h, pair_h) of every joined pair below the threshold; repeats of a pair may show."""
    p = choose_threshold(rel, spec) if p is None else p
    return _BY[spec.strategy](*hashed(rel, spec, spec.seed if run is None else run), spec, p)


def _pruner(k: int, method: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept, heap, seen = BottomK(k), [], set()
        for batch in batches:
            x, y, h = (batch.column(c).to_numpy() for c in ("x_h", "y_h", "pair_h"))
            if method == "buffer":
                kept.add_batch(h, x, y)
                continue
            for row in zip((-h).tolist(), (-x).tolist(), (-y).tolist(), strict=True):
                if row in seen or len(heap) == k and row <= heap[0]:
                    continue
                seen.add(row)
                if len(heap) < k:
                    heapq.heappush(heap, row)
                else:
                    seen.discard(heapq.heappushpop(heap, row))
        rows = kept.rows if method == "buffer" else -np.array(sorted(heap, reverse=True), np.int64).reshape(-1, 3)
        yield pa.RecordBatch.from_arrays([pa.array(rows[:, i]) for i in (1, 2, 0)], names=["x_h", "y_h", "pair_h"])

    return run


def local_prune(found: DataFrame, k: int, method: str = "buffer") -> DataFrame:
    """At most k distinct rows from each task: a falling threshold of its own."""
    return found.select("x_h", "y_h", "pair_h").mapInArrow(_pruner(k, method), "x_h long, y_h long, pair_h long")


def k_smallest(found: DataFrame, k: int, method: str = "native") -> DataFrame:
    """The k smallest distinct pairs.  ``native`` stays in the JVM; ``buffer`` and ``heap`` prune in Arrow batches first; ``rank`` is SQL ranking."""
    if method in ("buffer", "heap"):
        found = local_prune(found, k, method)
    distinct = found.select("x_h", "y_h", "pair_h").distinct()
    if method == "rank":
        rank = F.row_number().over(Window.orderBy("pair_h", "x_h", "y_h"))
        return distinct.withColumn("i", rank).where(F.col("i") <= k).drop("i")
    return distinct.orderBy("pair_h", "x_h", "y_h").limit(k)


def merge(a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    """The kept set of a union from the kept sets of its parts."""
    return k_smallest(a.unionByName(b), k)


def finish(kept: DataFrame, spec: Spec, p: float, run: int | None = None, scale: float = 1.0, rates: tuple[float, float] | None = None) -> DataFrame:
    """One ESTIMATE row from a kept set.

    ``scale`` is one over the product of a sample's ``rates``: estimates,
    counts and bounds of the sample become those of the relation.
    """
    domain, k = FAMILIES[spec.family].domain, spec.k
    one = kept.agg(F.count("*").alias("kept"), F.max("pair_h").alias("kth_hash"))
    filled = F.col("kept") >= k
    top = float(k if spec.estimator == "ratio" else k - 1) * float(domain)
    eps = eps_for(k)
    guess = F.lit(top) / F.greatest(F.col("kth_hash"), F.lit(1)).cast("double") * scale
    exact, sampled = F.lit(p >= 1.0), scale != 1.0
    if spec.on_short == "bound":
        short, name = F.lit(float(k) * k * scale), "upper_bound"
    elif spec.on_short == "scaled":
        short, name = F.col("kept") / float((rates or (1.0, 1.0))[0] * (rates or (1.0, 1.0))[1]), "scaled_count"
    else:
        short, name = F.col("kept") / float(p) * scale, "scaled_count"
    status = F.when(F.col("kept") == 0, "empty").when(filled, "estimate").when(exact, "scaled_count" if sampled else "exact").otherwise(name)
    z_hat = F.when(F.col("kept") == 0, F.lit(None).cast("double") if rates else F.lit(0.0)).when(filled, guess).when(exact, F.col("kept") * float(scale)).otherwise(short)
    lo = F.when(filled, guess / (1 + eps)).otherwise(0.0)
    hi = F.when(filled, guess / (1 - eps) if eps < 1 else F.lit(None).cast("double")).otherwise((1 + eps) * k * k * scale)
    return one.select(
        F.lit(spec.seed if run is None else run).cast("int").alias("run"),
        F.lit(k).cast("int").alias("k"),
        F.lit(spec.policy).alias("policy"),
        F.lit(float(p)).alias("p"),
        F.lit(min(as_threshold(p, domain), 2**63 - 1)).cast("long").alias("threshold"),
        filled.alias("filled"),
        F.least("kept", F.lit(k)).cast("long").alias("kept"),
        F.when(filled, F.col("kth_hash")).alias("kth_hash"),
        z_hat.alias("z_hat"),
        lo.alias("lo"),
        hi.alias("hi"),
        status.alias("status"),
    )


def pilot_threshold(rel: Rel, spec: Spec, p: float, share: int = 8, run: int | None = None) -> int | None:
    """An upper bound of the k-th hash from one in ``share`` join values, or None if they hold too few pairs."""
    run = spec.seed if run is None else run
    some = lambda df: df.where(F.pmod(F.xxhash64("jk"), F.lit(share)) == 0)
    left, right = hashed(Rel(some(rel.left), some(rel.right)), spec, run)
    last = k_smallest(_BY[spec.strategy](left, right, spec, p), spec.k).agg(F.count("*").alias("n"), F.max("pair_h").alias("v")).first()
    return int(last["v"]) + 1 if last["n"] >= spec.k else None


def kept_set(rel: Rel, spec: Spec, p: float, run: int | None = None) -> DataFrame:
    """The kept set under the spec's way of tightening; each gives the same rows."""
    if spec.tighten == "pilot" and (t := pilot_threshold(rel, spec, p, run=run)):
        p = min(p, t / FAMILIES[spec.family].domain * (1 + 1e-12))
    sides = hashed(rel, spec, spec.seed if run is None else run)
    if spec.tighten == "local" and (spec.strategy == "sweep" or spec.strategy == "cells" and cells_for(p, FAMILIES[spec.family].domain)[0] == 1):
        # With a single cell the equi-join would list every joined pair; the scan lowers its threshold on the way.
        return k_smallest(hits_by_sweep(*sides, spec, p, spec.k), spec.k)
    if spec.tighten == "local" and spec.strategy == "grouped":
        return k_smallest(hits_by_group(*sides, spec, p, spec.k), spec.k)
    found = _BY[spec.strategy](*sides, spec, p)
    return k_smallest(found, spec.k, "buffer" if spec.tighten == "local" else "native")


def estimate_size(rel: Rel, spec: Spec = Spec()) -> DataFrame:
    """An ESTIMATE row for each run."""
    p = choose_threshold(rel, spec)
    out = None
    for run in spec.all_runs():
        own = p
        kept = kept_set(rel, spec, own, run)
        while spec.on_short == "widen" and own < 1 and kept.count() < spec.k:
            own = min(1.0, 4 * own)
            kept = kept_set(rel, spec, own, run)
        row = finish(kept, spec, own, run)
        out = row if out is None else out.unionByName(row)
    return out


def run_hits(rel: Rel, spec: Spec, p: float, runs: range) -> DataFrame:
    """Hits of several runs in one plan: values are hashed for every run, tuples multiply by a join on the value.

    (run, x_h, y_h, pair_h); only families whose seed may be a column: md5_60.
    """
    domain = FAMILIES["md5_60"].domain
    cells, width = cells_for(p, domain)
    shift = width.bit_length() - 1
    each = F.explode(F.sequence(F.lit(runs.start), F.lit(runs.stop - 1))).alias("run")
    digest = lambda side, c: F.conv(F.substring(F.md5(F.concat(F.lit(side), F.col("run"), F.lit(":"), F.coalesce(F.col(c).cast("string"), F.lit("\\N")))), 1, 15), 16, 10).cast("long")

    def hashed_by_run(df: DataFrame, role: str, side: str, out: str) -> DataFrame:
        """Values are hashed once for each run; their tuples follow by a join."""
        values = df.select(F.col(role).alias("__value")).distinct().select("__value", each).select("__value", "run", digest(side, "__value").alias(out))
        return df.join(values, F.col(role).eqNullSafe(F.col("__value"))).select("run", "jk", out)

    left, right = hashed_by_run(rel.left, "lk", "L", "x_h"), hashed_by_run(rel.right, "rk", "R", "y_h")
    keys = ["run", "jk"]
    if cells > 1:
        own = F.shiftright("y_h", shift)
        left = left.withColumn("cell", F.shiftright("x_h", shift))
        right = right.select("run", "jk", "y_h", F.explode(F.array(own, F.pmod(own + 1, F.lit(cells)))).alias("cell"))
        keys.append("cell")
    both = left.join(right, keys).withColumn("pair_h", (F.col("x_h") - F.col("y_h")).bitwiseAND(F.lit(domain - 1)))
    t = as_threshold(p, domain)
    return (both.where(F.col("pair_h") < t) if t < domain else both).select("run", "x_h", "y_h", "pair_h")


def _run_pruner(k: int):
    """At most k pairs of each run from a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: dict[int, BottomK] = {}
        for batch in batches:
            which, x, y, h = (batch.column(c).to_numpy() for c in ("run", "x_h", "y_h", "pair_h"))
            order = np.argsort(which, kind="stable")
            cuts = np.flatnonzero(np.diff(which[order], prepend=-1))
            for a, b in zip(cuts, np.append(cuts[1:], len(order)), strict=True):
                own = order[a:b]
                kept.setdefault(int(which[own[0]]), BottomK(k)).feed(h[own], x[own], y[own])
        for number, state in kept.items():
            state.flush()
            columns = [pa.array(np.full(len(state.rows), number, np.int32)), *(pa.array(state.rows[:, i]) for i in (1, 2, 0))]
            yield pa.RecordBatch.from_arrays(columns, names=["run", "x_h", "y_h", "pair_h"])

    return run


def run_estimates(rel: Rel, spec: Spec, runs: range, p: float | None = None) -> DataFrame:
    """(run, kept, kth_hash, z_hat) of several runs; unfilled runs count and divide by p."""
    p = choose_threshold(rel, spec) if p is None else p
    few = run_hits(rel, spec, p, runs).mapInArrow(_run_pruner(spec.k), "run int, x_h long, y_h long, pair_h long")
    distinct = few.distinct()
    rank = F.row_number().over(Window.partitionBy("run").orderBy("pair_h", "x_h", "y_h"))
    kept = distinct.withColumn("i", rank).where(F.col("i") <= spec.k)
    one = kept.groupBy("run").agg(F.count("*").alias("kept"), F.max("pair_h").alias("kth_hash"))
    guess = F.lit(float(spec.k) * float(FAMILIES["md5_60"].domain)) / F.greatest("kth_hash", F.lit(1)).cast("double")
    return one.select(F.col("run").cast("int").alias("run"), "kept", "kth_hash", F.when(F.col("kept") >= spec.k, guess).otherwise(F.col("kept") / float(p)).alias("z_hat"))


def median_of_runs(rel: Rel, spec: Spec, runs: int) -> DataFrame:
    """The median over runs: failure falls exponentially with their number."""
    found = run_estimates(rel, replace(spec, family="md5_60"), range(spec.seed, spec.seed + runs))
    return found.agg(F.count("*").alias("runs"), F.median("z_hat").alias("z_hat"))


def sqrt_n_k(n: int) -> int:
    """k of the high-confidence mode."""
    return max(1, ceil(n**0.5 - 1e-9))
