"""The kept sets of many runs in one pass: tuples travel once, whatever the number of runs.

Both sides are dealt by ranges of the join value.  A task dictionary-encodes
the values of some whole groups, hashes each of them once a run, and looks at
all runs of a group together: small groups as blocks of differences, heavy ones
by a sorted cyclic walk.  A task holds a kept set for each run and lowers the
run's threshold by it, so at most k pairs a run leave the task.

Where much of the product of both sides' values is joined, the order is turned
round: a task lists all pairs of values below a run's threshold, joined or not,
and those few meet the values' lists of join values, which tell the joined ones.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import md5
from math import ceil

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.hashing import MD5_60
from ..sources.sketches import released, stored
from . import exact
from .relations import Rel
from .scan import BottomK

DOMAIN = MD5_60.domain

#: Rows of whole groups that are walked together, hashes held for them, and differences looked at together.
CHUNK_ROWS, HELD_HASHES, BLOCK = 1 << 19, 1 << 22, 1 << 18
#: Hits that wait for the kept sets.
WAITING = 1 << 18
#: A group is walked by sorting if its pairs are so many times its rows.
HEAVY = 128
FOUND = "run int, x_h long, y_h long, pair_h long"
#: Pairs of values are listed first if so many times k are expected in all, by so many values and bytes of their lists at most; a first pass expects so many pairs for a kept one.
MANY, MOST_VALUES, LIST_BYTES, FIRST_PASS = 64, 4_000_000, 400 << 20, 1.25

_TURNS = np.array([7, 12, 17, 22] * 4 + [5, 9, 14, 20] * 4 + [4, 11, 16, 23] * 4 + [6, 10, 15, 21] * 4, np.uint32)
_SINES = np.floor(np.abs(np.sin(np.arange(1, 65, dtype=np.float64))) * 2.0**32).astype(np.uint64).astype(np.uint32)
_TILE = 8_192


def _md5_blocks(words: np.ndarray) -> np.ndarray:
    """The first eight bytes, big end first, of the md5 of one-block messages; ``words`` is (16, n) uint32."""
    first = [np.uint32(x) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]
    a, b, c, d = (np.full(words.shape[1], x, np.uint32) for x in first)
    for i in range(64):
        if i < 16:
            f, g = d ^ (b & (c ^ d)), i
        elif i < 32:
            f, g = c ^ (d & (b ^ c)), (5 * i + 1) % 16
        elif i < 48:
            f, g = b ^ c ^ d, (3 * i + 5) % 16
        else:
            f, g = c ^ (b | ~d), (7 * i) % 16
        f += a
        f += words[g]
        f += _SINES[i]
        a, d, c = d, c, b
        b = b + ((f << _TURNS[i]) | (f >> (np.uint32(32) - _TURNS[i])))
    a, b = a + first[0], b + first[1]
    return (a.byteswap().astype(np.uint64) << np.uint64(32)) | b.byteswap().astype(np.uint64)


class Texts:
    """Values as texts, to be hashed under many seeds: what ``md5_60`` gives, four bits to the left."""

    def __init__(self, values: pa.Array):
        self.raw = [x.encode() for x in values.to_pylist()]
        self.size = np.array([len(x) for x in self.raw], np.int64)
        width = int(min(55, self.size.max(initial=0)))
        joined = np.frombuffer(b"".join(x[:width].ljust(width, b"\0") for x in self.raw), np.uint8)
        self.bytes = joined.reshape(len(self.raw), width)

    def __len__(self) -> int:
        return len(self.raw)

    def hashes(self, seed: str, own: np.ndarray | None = None) -> np.ndarray:
        """The hashes of all values, or of the given places, under a seed."""
        own = np.arange(len(self)) if own is None else own
        head = np.frombuffer(seed.encode(), np.uint8)
        out = np.empty(len(own), np.uint64)
        fits = self.size[own] + len(head) <= 55
        short = np.flatnonzero(fits)
        for a in range(0, len(short), _TILE):
            at = short[a : a + _TILE]
            rows, size = own[at], self.size[own[at]] + len(head)
            block = np.zeros((len(at), 64), np.uint8)
            block[:, : len(head)] = head
            wide = min(self.bytes.shape[1], 55 - len(head))
            block[:, len(head) : len(head) + wide] = self.bytes[rows, :wide]
            block[np.arange(len(at)), size] = 0x80
            words = np.ascontiguousarray(block.view("<u4").T)
            words[14] = size * 8
            out[at] = _md5_blocks(words)
        for at in np.flatnonzero(~fits):
            out[at] = int.from_bytes(md5(seed.encode() + self.raw[own[at]]).digest()[:8], "big")
        return out & ~np.uint64(15)


class Kept:
    """The kept set of each run and the largest difference that may still enter it."""

    def __init__(self, k: int, runs: range, t: int):
        self.runs, self.sets = runs, [BottomK(k) for _ in runs]
        self.most = np.full(len(runs), ((t - 1) << 4) | 15, np.uint64)
        self.held: list[tuple[np.ndarray, ...]] = []
        self.waiting = 0

    def add(self, run: np.ndarray, x: np.ndarray, y: np.ndarray) -> None:
        if len(run):
            self.held.append((run, x, y))
            self.waiting += len(run)
            if self.waiting >= WAITING:
                self.settle()

    def settle(self) -> None:
        """Waiting pairs enter the kept sets, and thresholds fall."""
        if not self.waiting:
            return
        run, x, y = (np.concatenate(c) for c in zip(*self.held, strict=True))
        self.held, self.waiting = [], 0
        order = np.argsort(run, kind="stable")
        cuts = np.searchsorted(run[order], np.arange(len(self.sets) + 1))
        for r in np.flatnonzero(np.diff(cuts)):
            own = order[cuts[r] : cuts[r + 1]]
            h = ((x[own] - y[own]) >> np.uint64(4)).astype(np.int64)
            kept = self.sets[r]
            kept.add_batch(h, (x[own] >> np.uint64(4)).astype(np.int64), (y[own] >> np.uint64(4)).astype(np.int64))
            if len(kept.rows) == kept.k:
                self.most[r] = min(int(self.most[r]), (kept.limit << 4) | 15)

    def batches(self) -> Iterator[pa.RecordBatch]:
        self.settle()
        for number, kept in zip(self.runs, self.sets, strict=True):
            if len(kept.rows):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(kept.rows), number, np.int32)), *(pa.array(kept.rows[:, i]) for i in (1, 2, 0))], names=["run", "x_h", "y_h", "pair_h"])


def walk(x: np.ndarray, y: np.ndarray, run: int, kept: Kept) -> None:
    """Pairs of a heavy group in one run, by the cyclic run of sorted left hashes that each right hash begins."""
    x, y = np.sort(x), np.sort(y)
    n, at = len(x), 0
    low = np.searchsorted(x, y)
    while at < len(y):
        most = kept.most[run]
        end = y[at:] + most
        high = np.searchsorted(x, end, "right") + np.where(end < y[at:], n, 0)
        count = high - low[at:]
        some = max(1, int(np.searchsorted(np.cumsum(count), WAITING, "right")))
        count = count[:some]
        if count.any():
            where = np.repeat(low[at : at + some] - np.cumsum(count) + count, count) + np.arange(count.sum())
            kept.add(np.full(len(where), run), x[where % n], np.repeat(y[at : at + some], count))
        at += some


class Chunk:
    """Whole groups: the places of their values, left rows and right rows side by side."""

    def __init__(self, rows: pa.Table, mirrored: bool):
        rows = rows.combine_chunks()
        jk, side, v = (rows.column(c).combine_chunks() for c in ("jk", "side", "v"))
        new = np.ones(len(jk), bool)
        new[1:] = np.asarray(pc.not_equal(jk[1:], jk[:-1]))
        group = np.cumsum(new) - 1
        self.groups = int(group[-1]) + 1
        sides = [np.ones(len(jk), bool)] * 2 if mirrored else [np.asarray(side) == i for i in (0, 1)]
        self.texts, self.codes, self.group, self.start, self.size = [], [], [], [], []
        for i, own in enumerate(sides):
            if i and mirrored:
                for held in (self.texts, self.codes, self.group, self.start, self.size):
                    held.append(held[0])
                break
            coded = v.filter(pa.array(own)).dictionary_encode()
            self.texts.append(Texts(coded.dictionary))
            self.codes.append(np.asarray(coded.indices))
            self.group.append(group[own])
            size = np.bincount(group[own], minlength=self.groups)
            self.size.append(size)
            self.start.append(np.cumsum(size) - size)

    def whole(self, kept: Kept) -> None:
        """Every run over every pair of the chunk."""
        (l, r), (a, b) = self.size, self.start
        values, runs = max(1, *map(len, self.texts)), kept.runs
        step = max(1, min(len(runs), HELD_HASHES // values))
        heavy = l * r > HEAVY * (l + r)
        light = np.flatnonzero(~heavy & (l * r > 0))
        light = light[np.lexsort((r[light], l[light]))]
        # Blocks of groups of equal sizes: where each begins, and the end of the last.
        cuts = np.flatnonzero(np.r_[True, (np.diff(l[light]) != 0) | (np.diff(r[light]) != 0), True]) if len(light) else np.zeros(0, int)
        for first in range(0, len(runs), step):
            some = runs[first : first + step]
            x, y = (np.stack([t.hashes(f"{s}{run}:") for run in some], 1) for t, s in zip(self.texts, "LR", strict=True))
            for i, j in zip(cuts[:-1], cuts[1:], strict=True):
                m, n = int(l[light[i]]), int(r[light[i]])
                many = max(1, BLOCK // (m * n * len(some)))
                for at in range(i, j, many):
                    own = light[at : min(j, at + many)]
                    px = x[self.codes[0][a[own][:, None] + np.arange(m)]]
                    py = y[self.codes[1][b[own][:, None] + np.arange(n)]]
                    hit = np.flatnonzero((px[:, :, None] - py[:, None]) <= kept.most[first : first + len(some)])
                    if len(hit):
                        pair, which = np.divmod(hit, len(some))
                        g, pair = np.divmod(pair, m * n)
                        kept.add(which + first, px[g, pair // n, which], py[g, pair % n, which])
            for g in np.flatnonzero(heavy):
                left, right = (self.codes[i][self.start[i][g] : self.start[i][g] + self.size[i][g]] for i in (0, 1))
                for which in range(len(some)):
                    walk(x[left, which], y[right, which], first + which, kept)

    def sampled(self, kept: Kept, below: tuple[int, int]) -> None:
        """Every run over the pairs of its own samples."""
        for which, run in enumerate(kept.runs):
            h, place, size, start = [], [], [], []
            for i, side in enumerate("LR"):
                own = np.flatnonzero(self.texts[i].hashes(f"S{side}{run}:") < np.uint64(below[i] << 4))
                table = np.zeros(len(self.texts[i]), np.uint64)
                table[own] = self.texts[i].hashes(f"{side}{run}:", own)
                chosen = np.zeros(len(table), bool)
                chosen[own] = True
                rows = np.flatnonzero(chosen[self.codes[i]])
                h.append(table[self.codes[i][rows]])
                n = np.bincount(self.group[i][rows], minlength=self.groups)
                place.append(self.group[i][rows])
                size.append(n)
                start.append(np.cumsum(n) - n)
            (l, r), (x, y) = size, h
            heavy = l * r > HEAVY * (l + r)
            for g in np.flatnonzero(heavy):
                walk(x[start[0][g] : start[0][g] + l[g]], y[start[1][g] : start[1][g] + r[g]], which, kept)
            rows = np.flatnonzero(~heavy[place[1]] & (l[place[1]] > 0))
            total = np.cumsum(l[place[1][rows]])
            at = 0
            while at < len(rows):
                stop = max(at + 1, int(np.searchsorted(total, (total[at - 1] if at else 0) + BLOCK, "right")))
                g = place[1][rows[at:stop]]
                n = l[g]
                px = x[np.repeat(start[0][g] - np.cumsum(n) + n, n) + np.arange(n.sum())]
                py = np.repeat(y[rows[at:stop]], n)
                hit = np.flatnonzero(px - py <= kept.most[which])
                kept.add(np.full(len(hit), which), px[hit], py[hit])
                at = stop


def _walker(k: int, runs: range, t: int, below: tuple[int, int] | None, mirrored: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = Kept(k, runs, t)

        def groups(rows: pa.Table) -> None:
            chunk = Chunk(rows, mirrored)
            chunk.sampled(kept, below) if below else chunk.whole(kept)

        held, n = [], 0
        for batch in batches:
            held.append(batch)
            n += batch.num_rows
            if n < CHUNK_ROWS:
                continue
            rows = pa.Table.from_batches(held)
            # The last group may go on in the next batch.
            cut = int(np.argmax(np.asarray(pc.equal(rows.column("jk"), rows.column("jk")[n - 1]))))
            if cut:
                groups(rows.slice(0, cut))
            held = rows.slice(cut).combine_chunks().to_batches()
            n -= cut
        if n:
            groups(pa.Table.from_batches(held))
        yield from kept.batches()

    return run


def kept_of_runs(rel: Rel, k: int, runs: range, t: int, below: tuple[int, int] | None = None) -> DataFrame:
    """(run, x_h, y_h, pair_h, i): the k smallest distinct pairs of each run below ``t``, numbered; the hashes are ``md5_60``.

    With ``below`` a run sees the samples alone: values whose sampling hash lies below the side's bound.
    """
    spark = rel.left.sparkSession
    row = lambda df, side, v: df.select("jk", F.lit(side).alias("side"), F.col(v).alias("v"))
    rows = row(rel.left, 0, "lk")
    text = lambda df: df.select("jk", "side", F.coalesce(F.col("v").cast("string"), F.lit("\\N")).alias("v"))
    if not rel.mirrored:
        right = row(rel.right, 1, "rk")
        if rows.schema["v"].dataType != right.schema["v"].dataType:
            rows, right = text(rows), text(right)
        rows = rows.unionByName(right)
    if isinstance(rows.schema["jk"].dataType, (T.StructType, T.ArrayType)):
        rows = rows.withColumn("jk", F.to_json(F.struct("jk")))
    # Work is many times the bytes, so tasks must not be joined by their bytes.
    tasks = max(4 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    rows = text(rows.where(F.col("jk").isNotNull()).repartitionByRange(tasks, "jk").sortWithinPartitions("jk", "side"))
    found = rows.mapInArrow(_walker(k, runs, t, below, rel.mirrored), FOUND).distinct()
    rank = F.row_number().over(Window.partitionBy("run").orderBy("pair_h", "x_h", "y_h"))
    return found.withColumn("i", rank).where(F.col("i") <= k)


def _below(x: np.ndarray, y: np.ndarray, t: int) -> tuple[np.ndarray, np.ndarray]:
    """The places of pairs whose difference lies below ``t``."""
    order = np.argsort(x)
    x, n = x[order], len(x)
    end = y + np.uint64(((t - 1) << 4) | 15)
    low = np.searchsorted(x, y)
    count = np.searchsorted(x, end, "right") + np.where(end < y, n, 0) - low
    where = np.repeat(low - np.cumsum(count) + count, count) + np.arange(count.sum())
    return order[where % max(1, n)], np.repeat(np.arange(len(y)), count)


def _lister(runs: range, groups: int, t: int, below: tuple[int, int] | None, mirrored: bool):
    """The pairs of values of some runs below ``t``, joined or not."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        rows = pa.Table.from_batches(held)
        group, values = rows.column("group")[0].as_py(), []
        for side in (0,) if mirrored else (0, 1):
            values.append(rows.filter(pc.equal(rows.column("side"), side)).column("v").combine_chunks())
        texts = [Texts(v.cast(pa.string())) for v in values]
        values, texts = (values * 2)[:2], (texts * 2)[:2]
        for number in runs[group::groups]:
            own = [np.arange(len(v)) for v in values]
            if below:
                own = [np.flatnonzero(text.hashes(f"S{side}{number}:") < np.uint64(b << 4)) for text, side, b in zip(texts, "LR", below, strict=True)]
            x, y = (text.hashes(f"{side}{number}:", o) for text, side, o in zip(texts, "LR", own, strict=True))
            i, j = _below(x, y, t)
            x, y = x[i], y[j]
            columns = [np.full(len(i), number, np.int32), *((h >> np.uint64(4)).astype(np.int64) for h in (x, y, x - y))]
            ends = [v.take(pa.array(o[at])) for v, o, at in zip(values, own, (i, j), strict=True)]
            yield pa.RecordBatch.from_arrays([*map(pa.array, columns), *ends], names=["run", "x_h", "y_h", "pair_h", "a", "c"])

    return run


def _share_a_key(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs whose lists of join values meet."""
    for batch in batches:
        (left, a), (right, b) = (exact.flat_lists(batch.column(c)) for c in ("left_keys", "right_keys"))
        # A list's keys lie in a range of their own.
        one, two = ((np.repeat(np.arange(len(e), dtype=np.uint64), np.diff(e, prepend=0)) << np.uint64(32)) | f for f, e in ((left, a), (right, b)))
        meets = np.zeros(batch.num_rows, bool)
        if len(one) and len(two):
            at = np.minimum(np.searchsorted(two, one), len(two) - 1)
            meets[(one[two[at] == one] >> np.uint64(32)).astype(np.int64)] = True
        yield batch.select(["run", "x_h", "y_h", "pair_h"]).filter(pa.array(meets))


def listed_pairs(rel: Rel, k: int, runs: range, t: int, below: tuple[int, int] | None, held: tuple[DataFrame, ...]) -> DataFrame:
    """What ``kept_of_runs`` gives, from ``held``, the stored lists of both sides (``exact.lists``; one of a mirrored relation)."""
    spark = rel.left.sparkSession
    groups = min(len(runs), 2 * spark.sparkContext.defaultParallelism)
    rows = None
    for side, df in enumerate(held):
        one = df.select("v", F.lit(side).alias("side"))
        rows = one if rows is None else rows.unionByName(one)
    dealt = rows.withColumn("group", F.explode(F.sequence(F.lit(0), F.lit(groups - 1)))).repartitionById(groups, F.col("group"))
    pairs = stored(dealt.mapInArrow(_lister(runs, groups, t, below, rel.mirrored), FOUND + ", a long, c long"), "pairs")
    pairs = pairs.join(held[0].select(F.col("v").alias("a"), F.col("keys").alias("left_keys")), "a").join(held[-1].select(F.col("v").alias("c"), F.col("keys").alias("right_keys")), "c")
    found = pairs.select("run", "x_h", "y_h", "pair_h", "left_keys", "right_keys").mapInArrow(_share_a_key, FOUND).distinct()
    rank = F.row_number().over(Window.partitionBy("run").orderBy("pair_h", "x_h", "y_h"))
    return found.withColumn("i", rank).where(F.col("i") <= k)


def _estimates(kept: DataFrame, k: int, scale: float = 1.0) -> DataFrame:
    """(run, kept, kth_hash, z_hat) from numbered kept sets; an unfilled set counts its pairs."""
    one = kept.where(F.col("i") <= k).groupBy("run").agg(F.count("*").alias("kept"), F.max("pair_h").alias("kth_hash"))
    guess = F.lit(float(k) * float(DOMAIN)) / F.greatest("kth_hash", F.lit(1)).cast("double")
    size = F.when(F.col("kept") >= k, guess).otherwise(F.col("kept"))
    return one.select(F.col("run").cast("int").alias("run"), "kept", "kth_hash", (size / scale).alias("z_hat"))


def listed(rel: Rel, k: int, runs: range, z: float, expected: float) -> tuple[DataFrame, ...] | None:
    """The stored lists of the sides, if pairs of values are to be listed first: of whole numbers, and so dense that the lists of few pairs are looked at."""
    if expected < MANY * k:
        return None
    sides = [(rel.left, "lk")] + ([] if rel.mirrored else [(rel.right, "rk")])
    with released(rel.left.sparkSession):
        n = [df.select(c).distinct().count() for df, c in sides]
        pairs = FIRST_PASS * k * len(runs) * n[0] * n[-1] / z
        if sum(n) > MOST_VALUES or pairs * 8 * sum(df.count() / v for (df, _), v in zip(sides, n, strict=True)) / len(sides) > LIST_BYTES or not all(exact.listable(*side) for side in sides):
            return None
    return tuple(exact.lists_of(rel, i) for i in range(len(sides)))


def _settled(rel: Rel, k: int, runs: range, expected: float, below: tuple[int, int] | None = None, held: tuple[DataFrame, ...] | None = None) -> DataFrame:
    """The kept sets as from p = 1, stored: the first pass lists 4k expected pairs, or a few more than k where pairs are listed first; runs it leaves unfilled are walked again, at last without a threshold."""
    def walked(some: range, p: float) -> DataFrame:
        t = min(DOMAIN, ceil(p * float(DOMAIN)))
        return stored(listed_pairs(rel, k, some, t, below, held) if held and p < 1 else kept_of_runs(rel, k, some, t, below), "runs")

    out, short = None, list(runs)
    for times in ((FIRST_PASS, 4.0) if held else (4.0,)) + (float("inf"),):
        p = min(1.0, times * k / max(expected, 1.0))
        again = walked(range(short[0], short[-1] + 1), p)
        out = again if out is None else out.where(~F.col("run").isin(short)).unionByName(again.where(F.col("run").isin(short)))
        if p == 1:
            break
        with released(rel.left.sparkSession):
            full = {row["run"] for row in out.groupBy("run").agg(F.max("i").alias("n")).where(F.col("n") >= k).collect()}
        if not (short := [r for r in runs if r not in full]):
            break
    return out


def runs_from_one(rel: Rel, ks: tuple[int, ...], runs: range, z: float) -> dict[int, DataFrame]:
    """(run, kept, kth_hash, z_hat) for each k, all from one pass for the largest; ``z`` only sets where the first pass begins."""
    kept = _settled(rel, max(ks), runs, z, held=listed(rel, max(ks), runs, z, z))
    return {k: _estimates(kept, k) for k in ks}


def sample_sketches(rel: Rel, p1: float, p2: float, runs: range, k: int, z: float) -> DataFrame:
    """(run, kept, z_hat): the k smallest pairs of each run's samples; runs without a pair have kept 0 and a null."""
    below = tuple(int(round(p * float(DOMAIN))) for p in (p1, p2))
    found = _estimates(_settled(rel, k, runs, z * p1 * p2, below, listed(rel, k, runs, z, z * p1 * p2)), k, p1 * p2)
    every = rel.left.sparkSession.range(runs.start, runs.stop).select(F.col("id").cast("int").alias("run"))
    return every.join(found, "run", "left").select("run", F.coalesce("kept", F.lit(0)).alias("kept"), "z_hat")
