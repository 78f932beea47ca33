"""The exact size of relations whose pairs are dense, by bits instead of joined rows.

Where many join values repeat the same pairs, listing them costs far more than
a bit for each left and right value.  Right values get places in blocks, a join
value is a posting list of places, and a left value's partners are the union of
its join values' postings: long ones are held as bitmaps, short ones as lists.
Nothing is estimated or left out: every left value meets every block.

A dense relation joined with itself is counted by ranks: values are dealt into
blocks by their number of join values, and a value meets the blocks of those
that have as many or more, so each pair is looked for from its shorter side.

Many joined rows that aren't dense are counted from packed tuples: a pass takes
the right values of one block, a task some of the left values, and the pairs of
a left value are listed, sorted and counted where they are found.  Tuples are
shuffled, joined rows never are.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.hashing import MD5_60
from ..sources.sketches import batches_of, released, stored
from . import baselines, sampling
from .relations import Rel, work

#: Joined rows up to which the join is as good, and places times tuples for a joined row up to which bits are.
FEW_JOINED, WORTH = 20_000_000, 2_000
#: Places of a block, fewer than two bytes hold so that uneven shares still fit, and bytes of bitmaps in a task.
PLACES, FILLED, BITMAP_BYTES = 1 << 16, 60_000, 48 << 20
#: Postings of a bitmap at least.
LONG = 64
#: Right tuples of a pass and left tuples of a task, about; tuples packed or looked up together, and joined rows sorted together.
BLOCK_TUPLES, PART_TUPLES, TOGETHER, LISTED = 8_000_000, 4_000_000, 1 << 18, 1 << 21
#: By ranks: values and tuples of a block, bytes of its bitmaps, rows united before a look at what is missing, tuples of missing values for a row left.
RANK_VALUES, RANK_TUPLES, RANK_BITMAP_BYTES, FIRST_ROWS, MISSING = 60_000, 8_000_000, 72 << 20, 24, 100
#: Rows that a task gathers together.
GATHERED = 2_000_000
_LOW = np.uint64(2**32 - 1)


def _tuples(jk: pa.Array, sizes: np.ndarray | None, lk: pa.Array) -> tuple[pa.Array, pa.Array, np.ndarray]:
    """Join values, kept values, and each tuple once: the place of its join value above 32 bits, that of its kept value below."""
    j, v = (x.dictionary_encode(null_encoding="encode").combine_chunks() for x in (jk, lk))
    j, v = (x.chunk(0) if isinstance(x, pa.ChunkedArray) else x for x in (j, v))
    at = np.asarray(j.indices)
    rows = ((at if sizes is None else np.repeat(at, sizes)).astype(np.uint64) << np.uint64(32)) | np.asarray(v.indices).astype(np.uint64)
    rows.sort()
    return j.dictionary, v.dictionary, rows[np.r_[True, rows[1:] != rows[:-1]][: len(rows)]]


def _gatherer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The kept values of each join value, of many rows at a time."""
    def gathered(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = pa.Table.from_batches(held)
        jk, lk = rows.column("jk"), rows.column("lk")
        if pa.types.is_list(jk.type):
            lk, jk = lk.take(pc.list_parent_indices(jk.combine_chunks())), pc.list_flatten(jk)
        jk, lk, found = _tuples(jk, None, lk)
        ends = np.searchsorted(found >> np.uint64(32), np.arange(len(jk) + 1).astype(np.uint64))
        values = lk.take(pa.array((found & _LOW).astype(np.int64)))
        for a in range(0, len(jk), 1 << 14):
            own = ends[a : a + (1 << 14) + 1]
            some = pa.ListArray.from_arrays(pa.array((own - own[0]).astype(np.int32)), values[own[0] : own[-1]])
            yield pa.RecordBatch.from_arrays([jk[a : a + len(some)], some], names=["jk", "lks"])

    held, n = [], 0
    for batch in batches:
        for a in range(0, batch.num_rows, 1024):
            held.append(batch.slice(a, 1024))
            jk = held[-1].column("jk")
            n += pc.sum(pc.list_value_length(jk)).as_py() or 0 if pa.types.is_list(jk.type) else len(jk)
            if n >= GATHERED:
                yield from gathered(held)
                held, n = [], 0
    if n:
        yield from gathered(held)


def _namer(tasks: int):
    """The kept values of a task's join values, which get numbers, frequent ones first; another task's differ."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [b for b in batches if b.num_rows]
        if not rows:
            return
        rows = pa.Table.from_batches(rows)
        sizes = np.asarray(pc.list_value_length(rows.column("lks")))
        jk, lk, found = _tuples(rows.column("jk"), sizes, pc.list_flatten(rows.column("lks")))
        del rows
        ends = np.searchsorted(found >> np.uint64(32), np.arange(len(jk) + 1).astype(np.uint64))
        name = np.empty(len(jk), np.int64)
        name[np.argsort(-np.diff(ends), kind="stable")] = np.arange(len(jk)) * tasks + TaskContext.get().partitionId()
        for a in range(0, len(jk), 1 << 14):
            own = ends[a : a + (1 << 14) + 1]
            values = lk.take(pa.array((found[own[0] : own[-1]] & _LOW).astype(np.int64)))
            yield pa.RecordBatch.from_arrays([pa.array(name[a : a + len(own) - 1]), pa.ListArray.from_arrays(pa.array((own - own[0]).astype(np.int32)), values)], names=["jk", "lks"])

    return run


def named(rows: DataFrame) -> DataFrame:
    """(jk, lks): a number for each join value, and its distinct kept values; what a task gathers of a join value is dealt as one row."""
    spark = rows.sparkSession
    tasks = max(2 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    jk, lk = (rows.schema[c].dataType for c in ("jk", "lk"))
    jk = jk.elementType if isinstance(jk, T.ArrayType) else jk
    kept = lambda name, kind: T.StructType([T.StructField(name, kind), T.StructField("lks", T.ArrayType(lk))])
    gathered = rows.where(F.col("jk").isNotNull()).select("lk", "jk").mapInArrow(_gatherer, kept("jk", jk))
    return gathered.repartition(tasks, "jk").mapInArrow(_namer(tasks), kept("jk", T.LongType()))


def stored_rel(rel: Rel) -> Rel:
    """The relation written once, where several passes read it; join values of a mirrored one that are texts are numbered, which changes no pair."""
    if rel.mirrored and rel.distinct and isinstance(rel.left.schema["jk"].dataType, T.StringType):
        postings = stored(named(rel.left if rel.rows is None else rel.rows), "postings")
        left, held = postings.select(F.explode("lks").alias("lk"), "jk"), {"postings": postings}
    else:
        left, held = stored(rel.left, "left"), {}
    right = left.select("jk", F.col("lk").alias("rk")) if rel.mirrored else stored(rel.right, "right")
    return Rel(left, right, rel.distinct, rel.mirrored, held=held)


def matched(rel: Rel) -> DataFrame:
    """One row n_a, n_c: values that are in some pair."""
    count = lambda df, role: df.select(role).distinct().agg(F.count("*").alias(f"n_{'a' if role == 'lk' else 'c'}"))
    if rel.mirrored:
        one = count(rel.left, "lk")
        return one.select("n_a", F.col("n_a").alias("n_c"))
    return count(rel.left.join(rel.right.select("jk"), "jk", "left_semi"), "lk").crossJoin(count(rel.right.join(rel.left.select("jk"), "jk", "left_semi"), "rk"))


def _dense(rel: Rel) -> tuple[int, int | None]:
    """Joined rows, and the number of right values if bits are cheaper."""
    with released(rel.left.sparkSession):
        joined = int(work(rel).first()["joined"])
        if joined <= FEW_JOINED:
            return joined, None
        n_c = rel.right.select("rk").distinct().count()
    return joined, n_c if rel.left.count() * n_c < WORTH * joined else None


def size(rel: Rel) -> DataFrame:
    """One row z: by bits where they are cheaper, by lists where joined rows are many."""
    joined, n_c = _dense(rel)
    if n_c and rel.mirrored and listable(rel.left, "lk"):
        return by_ranks(rel, n_c)
    if n_c:
        return by_bits(rel, n_c).where("run = 0").select(F.col("kept").alias("z"))
    return by_lists(rel) if joined > FEW_JOINED else baselines.exact_size(rel)


def samples(rel: Rel, p1: float, p2: float, runs: range) -> DataFrame:
    """(run, kept, z): pairs of each run's samples beside all pairs."""
    if n_c := _dense(rel)[1]:
        found = by_bits(rel, n_c, (p1, p2), runs)
        return found.where("run > 0").crossJoin(found.where("run = 0").select(F.col("kept").alias("z")))
    return sampling.sample_runs(rel, p1, p2, runs).select("run", "kept").crossJoin(baselines.exact_size(rel))


def _member(col: Column, side: str, p: float, runs: range) -> Column:
    """A bit for each run whose sample has the value."""
    out = F.lit(0).cast("long")
    for i, run in enumerate(runs):
        out = out.bitwiseOR(F.when(MD5_60.hash(col, f"S{side}{run}:") < sampling.sample_threshold(p, "md5_60"), F.lit(1 << i).cast("long")).otherwise(F.lit(0).cast("long")))
    return out


class Block:
    """Postings of one block of right values."""

    def __init__(self, keys: list[np.ndarray], sizes: list[np.ndarray], places: list[np.ndarray]):
        self.keys, n, flat = (np.concatenate([np.zeros(0, np.int64), *x]).astype(np.int64) for x in (keys, sizes, places))
        order = np.argsort(self.keys, kind="stable")
        start = (np.cumsum(n) - n)[order]
        self.keys, n = self.keys[order], n[order]
        self.width = -(-(int(flat.max(initial=0)) + 1) // 64)
        self.row = np.full(len(n), -1)
        largest = np.argsort(-n, kind="stable")[: max(1, BITMAP_BYTES // (8 * self.width))]
        largest = largest[n[largest] >= LONG]
        self.row[largest] = np.arange(len(largest))
        self.maps = np.stack([self.bits(flat[start[i] : start[i] + n[i]]) for i in largest]) if len(largest) else np.zeros((0, self.width), np.uint64)
        self.start, self.flat = start, flat
        self.size = np.where(self.row < 0, n, 0)

    def bits(self, places: np.ndarray) -> np.ndarray:
        flags = np.zeros(self.width * 64, np.uint8)
        flags[places[places < len(flags)]] = 1
        return np.packbits(flags, bitorder="little").view(np.uint64)

    def union(self, keys: np.ndarray) -> np.ndarray:
        """The partners in this block of a left value with these join values."""
        out = np.zeros(self.width, np.uint64)
        if not len(self.keys):
            return out
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        at = at[self.keys[at] == keys]
        for row in self.row[at]:
            if row >= 0:
                np.bitwise_or(out, self.maps[row], out=out)
        at = at[self.size[at] > 0]
        if len(at):
            n = self.size[at]
            places = self.flat[np.repeat(self.start[at] - np.cumsum(n) + n, n) + np.arange(n.sum())]
            places = places[(out[places >> 6] >> (places & 63).astype(np.uint64)) & np.uint64(1) == 0]
            np.bitwise_or.at(out, places >> 6, np.uint64(1) << (places & 63).astype(np.uint64))
        return out


def _counter(runs: range | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros(1 + len(runs or ()), np.int64)
        cell = block = None
        for batch in batches:
            if not batch.num_rows:
                continue
            cells, sides = batch.column("cell").to_numpy(), batch.column("side").to_numpy()
            cuts = np.flatnonzero(np.r_[True, (np.diff(cells) != 0) | (np.diff(sides) != 0)])
            for a, b in zip(cuts, np.append(cuts[1:], len(cells)), strict=True):
                if cells[a] != cell:
                    cell, block, masks = cells[a], None, []
                    keys, sizes, postings, places, members = [], [], [], [], []
                some = batch.slice(a, b - a)
                key, member = some.column("key").to_numpy(), some.column("member").to_numpy()
                if sides[a] == 0:
                    places.append(key)
                    members.append(member)
                elif sides[a] == 1:
                    keys.append(key)
                    sizes.append(np.asarray(pc.list_value_length(some.column("places"))))
                    postings.append(some.column("places").flatten().to_numpy().astype(np.int64) + PLACES // 2)
                else:
                    if block is None:
                        block = Block(keys, sizes, postings)
                        held = np.concatenate([np.zeros(0, np.int64), *members])
                        at = np.concatenate([np.zeros(0, np.int64), *places])
                        masks = [block.bits(at[(held >> r) & 1 == 1]) for r in range(len(runs or ()))]
                    ids = some.column("ids")
                    flat, ends = ids.flatten().to_numpy(), np.cumsum(np.asarray(pc.list_value_length(ids)))
                    for i, end in enumerate(ends):
                        out = block.union(flat[ends[i - 1] if i else 0 : end])
                        counts[0] += int(np.bitwise_count(out).sum())
                        for r, mask in enumerate(masks):
                            if member[i] >> r & 1:
                                counts[1 + r] += int(np.bitwise_count(out & mask).sum())
        # Every task gives every run, so that none is missing.
        yield pa.RecordBatch.from_arrays([pa.array([0, *(runs or ())], pa.int32()), pa.array(counts)], names=["run", "kept"])

    return run


def by_bits(rel: Rel, n_c: int, rates: tuple[float, float] | None = None, runs: range | None = None) -> DataFrame:
    """(run, kept): run 0 counts all pairs, the others those of their samples at the given rates; at most 63 runs, from 1."""
    spark = rel.left.sparkSession
    if rates and (len(runs) > 63 or runs.start < 1):
        raise ValueError("a value's samples are 63 bits, and runs begin at 1")

    none = F.lit(0).cast("long")
    member = lambda c, side, p: _member(F.col(c), side, p, runs) if rates else none
    left, right = rel.left.select(F.col("jk").alias("key"), "lk"), rel.right.select(F.col("jk").alias("key"), "rk")
    alone = None
    if rel.mirrored:
        # A join value of one value alone pairs it with itself, which any other join value does too.
        n = F.count("*") if rel.distinct else F.count_distinct(F.coalesce(F.col("lk").cast("string"), F.lit("\\N")))
        often = left.groupBy("key").agg(n.alias("n")).where("n > 1").select("key")
        often = stored(often.select("key", F.monotonically_increasing_id().alias("id")), "keys")
        met = stored(left.join(often, "key").select(F.col("id").alias("key"), "lk"), "met")
        own = left.select("lk").distinct()
        alone = own.join(met.select(F.col("lk").alias("__met")).distinct(), F.col("lk").eqNullSafe(F.col("__met")), "left_anti")
        alone = alone.select(member("lk", "L", rates and rates[0]).bitwiseAND(member("lk", "R", rates and rates[1])).alias("member"))
        left, right = met, met.select("key", F.col("lk").alias("rk"))
    elif not isinstance(left.schema["key"].dataType, (T.LongType, T.IntegerType)) or not isinstance(right.schema["key"].dataType, (T.LongType, T.IntegerType)):
        both = left.select("key").distinct().join(right.select("key").distinct(), "key")
        named = stored(both.select("key", F.monotonically_increasing_id().alias("id")), "keys")
        left, right = (df.join(named, "key").drop("key").withColumnRenamed("id", "key") for df in (left, right))
    number = F.monotonically_increasing_id()
    values = right.select("rk").distinct().repartition(-(-n_c // FILLED), "rk").select(F.col("rk").alias("value"), number.alias("n"))
    values = values.select("value", (F.shiftright("n", 33) * 2**17 + F.shiftright(F.col("n").bitwiseAND(F.lit(2**33 - 1)), 16)).alias("block"), F.col("n").bitwiseAND(F.lit(PLACES - 1)).alias("place"))
    values = stored(values.withColumn("member", member("value", "R", rates and rates[1])), "places")
    blocks = sorted(row["block"] for row in values.select("block").distinct().collect())
    # Each block is dealt to so many tasks, by the left values.
    parts = -(-spark.sparkContext.defaultParallelism // max(1, len(blocks)))
    ordinal = F.element_at(F.create_map(*[F.lit(x) for pair in ((b, i) for i, b in enumerate(blocks)) for x in pair]), F.col("block")) if blocks else F.lit(0)
    cell = lambda part: (ordinal * parts + part).cast("int").alias("cell")
    every = F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part")
    no_places, no_ids = F.lit(None).cast("array<smallint>").alias("places"), F.lit(None).cast("array<bigint>").alias("ids")
    # Lists are written, so that the shuffle files behind them are gone when they are dealt.
    lists = right.join(values, F.col("rk").eqNullSafe(F.col("value"))).groupBy("block", "key").agg(F.collect_list((F.col("place") - PLACES // 2).cast("smallint")).alias("places"))
    lists = stored(lists, "lists")
    rows = lists.select("block", F.col("key").cast("long").alias("key"), "places", every).select(cell(F.col("part")), F.lit(1).alias("side"), "key", "places", no_ids, none.alias("member"))
    if rates:
        held = values.select("block", "place", "member", every)
        rows = rows.unionByName(held.select(cell(F.col("part")), F.lit(0).alias("side"), F.col("place").alias("key"), no_places, no_ids, "member"))
    own = stored(left.groupBy("lk").agg(F.collect_list(F.col("key").cast("long")).alias("ids")), "own").withColumn("member", member("lk", "L", rates and rates[0]))
    own = own.select(F.pmod(F.xxhash64("lk"), F.lit(parts)).alias("part"), "ids", "member", F.explode(F.array(*[F.lit(b) for b in blocks]) if blocks else F.array().cast("array<bigint>")).alias("block"))
    rows = rows.unionByName(own.select(cell(F.col("part")), F.lit(2).alias("side"), none.alias("key"), no_places, "ids", "member"))
    dealt = rows.repartitionById(max(1, len(blocks) * parts), F.col("cell")).sortWithinPartitions("cell", "side")
    found = dealt.mapInArrow(_counter(runs if rates else None), "run int, kept long")
    if alone is not None:
        each = F.explode(F.array(*[F.lit(x) for x in (0, *(runs if rates else ()))])).alias("run")
        of_run = F.when(F.col("run") == 0, 1).otherwise(F.expr(f"shiftright(member, greatest(0, run - {runs.start if rates else 1})) & 1"))
        found = found.unionByName(alone.select("member", each).select("run", of_run.cast("long").alias("kept")))
    return found.groupBy("run").agg(F.sum("kept").alias("kept"))


def _numbered(df: DataFrame, other: DataFrame) -> DataFrame:
    """(value, id): distinct values of two single columns, numbered from 0 without gaps."""
    number, low = F.monotonically_increasing_id(), F.lit(2**33 - 1)
    held = stored(df.toDF("value").unionByName(other.toDF("value")).distinct().select("value", number.alias("n")), "numbers")
    counts = held.groupBy(F.shiftright("n", 33).cast("int").alias("part")).count().collect()
    before = [0] * (1 + max((r["part"] for r in counts), default=0))
    for r in counts:
        before[r["part"]] = r["count"]
    if sum(before) >= 2**32:
        raise ValueError("more than 2^32 distinct values")
    before = [0, *np.cumsum(before)[:-1].tolist()]
    offset = F.element_at(F.array(*[F.lit(x).cast("long") for x in before]), F.shiftright("n", 33).cast("int") + 1)
    return held.select("value", (offset + F.col("n").bitwiseAND(low)).alias("id"))


def _as_ints(rel: Rel) -> tuple[DataFrame, DataFrame]:
    """(v, k) of both sides as numbers of 32 bits: the values themselves where they are such, else a number of each."""
    sides = [(rel.left, "lk"), (rel.right, "rk")][: 1 if rel.mirrored else 2]
    small = True
    for df, c in sides:
        if small := small and all(isinstance(df.schema[x].dataType, (T.LongType, T.IntegerType)) for x in (c, "jk")):
            seen = df.agg(F.min(F.least(c, "jk")).alias("least"), F.max(F.greatest(c, "jk")).alias("most"), F.count_if(F.col(c).isNull()).alias("nulls")).first()
            small = not seen["nulls"] and (seen["least"] is None or (0 <= seen["least"] and seen["most"] < 2**32))
    if small:
        out = [df.select(F.col(c).cast("long").alias("v"), F.col("jk").cast("long").alias("k")) for df, c in sides]
    else:
        keys = _numbered(rel.left.select("jk"), rel.right.select("jk")).select(F.col("value").alias("jk"), F.col("id").alias("k"))
        out = []
        for df, c in sides:
            values = _numbered(df.select(c), df.select(c).limit(0)).select("value", F.col("id").alias("v"))
            out.append(stored(df.join(keys, "jk").join(values, F.col(c).eqNullSafe(F.col("value"))).select("v", "k"), "ints"))
    return out[0], out[-1]


def _share(values: np.ndarray, n: int) -> np.ndarray:
    return ((values * np.uint64(0x9E3779B1) & _LOW) >> np.uint64(4)) % np.uint64(n)


def _dealer(right: bool, parts: int, block: int, blocks: int):
    """Packed tuples for each part: left ones by their value, right ones of the block for all parts."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def packed(held: list[pa.RecordBatch]) -> pa.RecordBatch:
            v, k = (np.concatenate([b.column(i).to_numpy() for b in held]).astype(np.uint64) for i in (0, 1))
            if right:
                own = _share(v, blocks) == block
                one = np.sort((k[own] << np.uint64(32)) | v[own]).tobytes()
                out = [one] * parts
            else:
                part = _share(v, parts)
                pairs = (v << np.uint64(32)) | k
                out = [np.sort(pairs[part == i]).tobytes() for i in range(parts)]
            return pa.RecordBatch.from_arrays([pa.array(range(parts), pa.int32()), pa.array([right] * parts), pa.array(out, pa.binary())], names=["cell", "right", "packed"])

        held, n = [], 0
        for batch in batches:
            held.append(batch)
            n += batch.num_rows
            if n >= TOGETHER:
                yield packed(held)
                held, n = [], 0
        if n:
            yield packed(held)

    return run


class Lists:
    """Right values of one block by their join value."""

    def __init__(self, pairs: np.ndarray):
        pairs = np.sort(pairs)
        keys, self.values = (pairs >> np.uint64(32)).astype(np.uint32), pairs.astype(np.uint32)
        self.start = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]][: len(keys)])
        self.keys, self.size = keys[self.start], np.diff(np.append(self.start, len(keys)))

    def count(self, own: np.ndarray, keys: np.ndarray) -> int:
        """Distinct pairs of left values, sorted, and the right values of their join values."""
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        hit = self.keys[at] == keys
        own, at = own[hit], at[hit]
        if not len(at):
            return 0
        new = np.r_[True, own[1:] != own[:-1]]
        number, ends = np.cumsum(new) - 1, np.append(np.flatnonzero(new)[1:], len(own))
        total = np.cumsum(self.size[at])
        found = a = i = 0
        while i < len(ends):
            # Whole left values, as many as are listed together.
            j = max(i + 1, int(np.searchsorted(total[ends - 1], (total[a - 1] if a else 0) + LISTED, "right")))
            held, b = np.zeros(0, np.uint64), int(ends[j - 1])
            while a < b:
                stop = min(b, max(a + 1, int(np.searchsorted(total, (total[a - 1] if a else 0) + LISTED, "right"))))
                n = self.size[at[a:stop]]
                listed = self.values[np.repeat(self.start[at[a:stop]] - np.cumsum(n) + n, n) + np.arange(n.sum())]
                listed = np.concatenate([held, (np.repeat(number[a:stop] - number[a], n).astype(np.uint64) << np.uint64(32)) | listed])
                listed.sort()
                # More than one turn is taken for a single left value alone.
                held = listed[np.r_[True, listed[1:] != listed[:-1]]] if stop < b else held
                a = stop
            found += 1 + int(np.count_nonzero(listed[1:] != listed[:-1]))
            i = j
        return found


def _list_counter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    sides, found = ([], []), 0
    for batch in batches:
        for right, packed in zip(batch.column("right").to_pylist(), batch.column("packed"), strict=True):
            sides[right].append(np.frombuffer(packed.as_py(), np.uint64))
    left, right = (np.concatenate([np.zeros(0, np.uint64), *x]) for x in sides)
    for held in sides:
        held.clear()
    if len(left) and len(right):
        lists = Lists(right)
        del right
        left.sort()
        a = 0
        while a < len(left):
            # Whole left values.
            b = min(len(left), a + TOGETHER)
            b = int(np.searchsorted(left, left[b - 1] | _LOW, "right"))
            found += lists.count((left[a:b] >> np.uint64(32)).astype(np.uint32), left[a:b].astype(np.uint32))
            a = b
    yield pa.RecordBatch.from_arrays([pa.array([found], pa.int64())], names=["z"])


def by_lists(rel: Rel) -> DataFrame:
    """One row z: each pass counts the pairs with the right values of one block; its shuffle files go before the next."""
    spark = rel.left.sparkSession
    left, right = _as_ints(rel)
    parts = max(spark.sparkContext.defaultParallelism, -(-left.count() // PART_TUPLES))
    blocks = max(1, -(-right.count() // BLOCK_TUPLES))
    deal = lambda df, *how: df.mapInArrow(_dealer(*how), "cell int, right boolean, packed binary")
    z = 0
    for block in range(blocks):
        rows = deal(left, False, parts, block, blocks).unionByName(deal(right, True, parts, block, blocks))
        with released(spark):
            z += rows.repartitionById(parts, F.col("cell")).mapInArrow(_list_counter, "z long").agg(F.sum("z").alias("z")).first()["z"] or 0
    return spark.range(1).select(F.lit(z).cast("long").alias("z"))


def listable(df: DataFrame, c: str) -> bool:
    """Whether ``lists`` takes the side: whole numbers without nulls, join values of 32 bits."""
    if not all(isinstance(df.schema[x].dataType, (T.LongType, T.IntegerType)) for x in (c, "jk")):
        return False
    seen = df.agg(F.min("jk").alias("least"), F.max("jk").alias("most"), F.count_if(F.col(c).isNull() | F.col("jk").isNull()).alias("nulls")).first()
    return not seen["nulls"] and (seen["least"] is None or (0 <= seen["least"] and seen["most"] < 2**32))


def _packer(parts: int):
    """Tuples packed for each part, by their value; values may be side by side in arrays."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def packed(held: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
            v, k = (np.concatenate(x) for x in zip(*held, strict=True))
            part = _share(v.astype(np.uint64) & _LOW, parts)
            order = np.argsort(part.astype(np.uint16) if parts < 2**16 else part, kind="stable")
            v, k = v[order], k[order].astype(np.uint32)
            ends = np.searchsorted(part[order], np.arange(parts + 1))
            cut = lambda a: pa.array([a[i:j].tobytes() for i, j in zip(ends, ends[1:])], pa.binary())  # noqa: B905, E731
            return pa.RecordBatch.from_arrays([pa.array(range(parts), pa.int32()), cut(v), cut(k)], names=["cell", "v", "k"])

        held, n = [], 0
        for batch in batches:
            v, k = batch.column(0), batch.column(1).to_numpy()
            if pa.types.is_list(v.type):
                v, k = v.flatten(), np.repeat(k, np.asarray(pc.list_value_length(v)))
            held.append((v.to_numpy(), k))
            n += len(k)
            if n >= 1 << 20:
                yield packed(held)
                held, n = [], 0
        if n:
            yield packed(held)

    return run


def _grouper(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each value of a part with its join values, in order."""
    held = ([], [])
    for batch in batches:
        for i, kind in enumerate((np.int64, np.uint32)):
            held[i].extend(np.frombuffer(x.as_py(), kind) for x in batch.column(1 + i))
    if not held[0]:
        return
    coded = pa.array(np.concatenate(held[0])).dictionary_encode()
    held[0].clear()
    rows = (np.asarray(coded.indices).astype(np.uint64) << np.uint64(32)) | np.concatenate(held[1])
    held[1].clear()
    rows.sort()
    rows = rows[np.r_[True, rows[1:] != rows[:-1]][: len(rows)]]
    keys, ends = rows.astype(np.uint32), np.searchsorted(rows >> np.uint64(32), np.arange(len(coded.dictionary) + 1))
    for a in range(0, len(coded.dictionary), 1024):
        own = ends[a : a + 1025]
        offsets, data = ((own - own[0]) * 4).astype(np.int32), keys[own[0] : own[-1]].copy()
        lists = pa.Array.from_buffers(pa.binary(), len(own) - 1, [None, pa.py_buffer(offsets), pa.py_buffer(data)])
        yield pa.RecordBatch.from_arrays([coded.dictionary[a : a + len(own) - 1], pa.array(np.diff(own)), lists], names=["v", "n", "keys"])


def lists_of(rel: Rel, side: int) -> DataFrame:
    """``lists`` of a side, written once."""
    c = ("lk", "rk")[side and not rel.mirrored]
    if c not in rel.held:
        df = rel.held.get("postings", rel.right if c == "rk" else rel.left)
        rel.held[c] = stored(lists(df, "lks" if "postings" in rel.held else c), "lists")
    return rel.held[c]


def lists(df: DataFrame, c: str) -> DataFrame:
    """(v, n, keys): each value with its n join values, as packed 32-bit numbers in order; a row has a value or an array of them."""
    spark = df.sparkSession
    parts = max(4 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    kind = "array<bigint>" if isinstance(df.schema[c].dataType, T.ArrayType) else "long"
    packed = df.select(F.col(c).cast(kind).alias("v"), F.col("jk").cast("long").alias("k")).mapInArrow(_packer(parts), "cell int, v binary, k binary")
    return packed.repartitionById(parts, F.col("cell")).mapInArrow(_grouper, "v long, n long, keys binary")


def flat_lists(keys: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Packed lists side by side, and where each ends."""
    offsets = np.frombuffer(keys.buffers()[1], np.int32)[keys.offset : keys.offset + len(keys) + 1].astype(np.int64) // 4
    data = keys.buffers()[2]
    flat = np.frombuffer(data, np.uint8)[offsets[0] * 4 : offsets[-1] * 4].view(np.uint32) if data is not None else np.zeros(0, np.uint32)
    return flat, offsets[1:] - offsets[0]


def _rank_blocks(sizes: list[tuple[int, int]]) -> np.ndarray:
    """Where blocks end in the order of (n, values that have n)."""
    cuts, at, values, tuples = [], 0, 0, 0
    for n, count in sizes:
        while count:
            some = min(count, RANK_VALUES - values, max(0, RANK_TUPLES - tuples) // n)
            if some <= 0 and values:
                cuts.append(at)
                values = tuples = 0
                continue
            some = max(1, some)
            at, values, tuples, count = at + some, values + some, tuples + some * n, count - some
    return np.array([*cuts, at], np.int64)


def _rank_dealer(block: int, cuts: np.ndarray, sizes: list[tuple[int, int]], parts: int):
    """Values of the block for all parts, those of it and of the blocks before for one part each."""
    ns, counts = (np.array(x, np.int64) for x in zip(*sizes, strict=True))
    first = np.cumsum(counts) - counts

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            v, n = batch.column("v").to_numpy(), batch.column("n").to_numpy()
            mixed = (v.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(32)
            i = np.searchsorted(ns, n)
            place = first[i] + ((mixed * counts[i].astype(np.uint64)) >> np.uint64(32)).astype(np.int64)
            of = np.searchsorted(cuts, place, "right")
            part = ((mixed * np.uint64(0x85EBCA6B) & _LOW) >> np.uint64(3)) % np.uint64(parts)
            for side, own, cells in ((0, of == block, range(parts)), (1, of <= block, [None])):
                at = np.flatnonzero(own)
                keys = batch.column("keys").take(pa.array(at))
                for cell in cells if len(at) else ():
                    to = part[at].astype(np.int32) if cell is None else np.full(len(at), cell, np.int32)
                    yield pa.RecordBatch.from_arrays([pa.array(to), pa.array(np.full(len(at), side, np.int32)), pa.array(np.where(of[at] == block, 1, 2)), keys], names=["cell", "side", "times", "keys"])

    return run


class RankBlock:
    """The values of one block: bitmaps of frequent join values, lists of places of the others."""

    def __init__(self, held: list[pa.Array]):
        each = [flat_lists(x) for x in held]
        self.end = np.cumsum(np.concatenate([np.diff(e, prepend=0) for _, e in each]))
        self.values, at, place = len(self.end), 0, 0
        rows = np.empty(int(self.end[-1]), np.uint64)
        for flat, ends in each:
            own = rows[at : at + len(flat)]
            own[:] = flat
            own <<= np.uint64(32)
            own |= np.repeat(np.arange(place, place + len(ends), dtype=np.uint32), np.diff(ends, prepend=0))
            at, place = at + len(flat), place + len(ends)
        rows.sort()
        keys = rows.view(np.uint32)[1::2]
        self.places = rows.view(np.uint32)[::2].astype(np.uint16 if self.values <= 1 << 16 else np.uint32)
        self.start = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
        self.size = np.diff(np.append(self.start, len(keys)))
        self.keys = keys[self.start]
        del rows, keys
        self.width = -(-self.values // 64)
        long = max(LONG, self.values // 1024)
        largest = np.argsort(-self.size, kind="stable")[: max(1, RANK_BITMAP_BYTES // (8 * self.width))]
        largest = largest[self.size[largest] >= long]
        self.row = np.full(len(self.keys), -1)
        self.row[largest] = np.arange(len(largest))
        self.maps = [self.bits(self.places[self.start[i] : self.start[i] + self.size[i]]) for i in largest]
        self.full = np.bitwise_count(self.bits(np.arange(self.values))).sum()
        # The places of keys, looked up by the key where that is cheap.
        self.table = None
        if len(self.keys) and int(self.keys[-1]) < max(1 << 22, 16 * len(self.keys)):
            self.table = np.full(int(self.keys[-1]) + 1, -1, np.int32)
            self.table[self.keys] = np.arange(len(self.keys))
        self.seen = np.zeros(len(self.keys), bool)
        # What the values of the block hold, by the places of keys.
        self.held = np.concatenate([self.find(flat) for flat, _ in each])

    def bits(self, places: np.ndarray) -> np.ndarray:
        flags = np.zeros(self.width * 64, np.uint8)
        flags[places] = 1
        return np.packbits(flags, bitorder="little").view(np.uint64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The places of keys among the block's, -1 for others."""
        if self.table is not None:
            return np.where(keys < len(self.table), self.table[np.minimum(keys, len(self.table) - 1)], -1)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return np.where(self.keys[at] == keys, at, -1).astype(np.int32)

    def missing(self, out: np.ndarray) -> np.ndarray:
        flags = np.unpackbits(out.view(np.uint8), bitorder="little")[: self.values]
        return np.flatnonzero(flags == 0)

    def counts(self, keys: pa.Array) -> np.ndarray:
        """How many values of the block share a join value with each of these lists."""
        flat, ends = flat_lists(keys)
        at = self.find(flat)
        hit = np.r_[0, np.cumsum(at >= 0)]
        at = at[at >= 0]
        ends = hit[ends]
        rows = self.row[at]
        long, short = np.r_[0, np.cumsum(rows >= 0)], at[rows < 0]
        rows = rows[rows >= 0].tolist()
        found, a = np.zeros(len(ends), np.int64), 0
        out, unite, maps = np.zeros(self.width, np.uint64), np.bitwise_or, self.maps
        for i, b in enumerate(ends.tolist()):
            i0, i1 = int(long[a]), int(long[b])
            out[:] = 0
            for r in rows[i0 : min(i1, i0 + FIRST_ROWS)]:
                unite(out, maps[r], out)
            left = i1 - i0 - FIRST_ROWS
            if left > 0:
                n = int(np.bitwise_count(out).sum())
                if n < self.full:
                    gone = self.missing(out) if (self.full - n) * 16 < MISSING * left else None
                    if gone is not None and int((size := self.end[gone] - np.r_[0, self.end][gone]).sum()) < MISSING * left:
                        self.seen[at[a:b]] = True
                        ahead = np.cumsum(size) - size
                        shared = self.seen[self.held[np.repeat(self.end[gone] - size - ahead, size) + np.arange(size.sum())]]
                        n += int(np.count_nonzero(np.logical_or.reduceat(shared, ahead)))
                        self.seen[at[a:b]] = False
                        found[i], a = n, b
                        continue
                    for r in rows[i0 + FIRST_ROWS : i1]:
                        unite(out, maps[r], out)
                else:
                    found[i], a = n, b
                    continue
            some = short[a - i0 : b - i1]
            n = int(np.bitwise_count(out).sum())
            if len(some):
                size = self.size[some]
                places = self.places[np.repeat(self.start[some] - np.cumsum(size) + size, size) + np.arange(size.sum())]
                places = places[(out[places >> 6] >> (places & np.uint32(63)).astype(np.uint64)) & np.uint64(1) == 0]
                n += len(np.unique(places))
            found[i], a = n, b
        return found


def _rank_counter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    # Memory that earlier tasks of this worker gave back to the pool.
    pa.default_memory_pool().release_unused()
    held, block, z = [], None, 0
    for batch in batches:
        side = batch.column("side").to_numpy()
        cut = int(np.searchsorted(side, 1))
        if cut:
            held.append(batch.column("keys").slice(0, cut))
        # The places of a block may all be free.
        if cut < len(side) and (block or held):
            block = block or RankBlock(held)
            held.clear()
            for a in range(cut, len(side), TOGETHER >> 8):
                z += int((block.counts(batch.column("keys").slice(a, TOGETHER >> 8)) * batch.column("times").to_numpy()[a : a + (TOGETHER >> 8)]).sum())
    yield pa.RecordBatch.from_arrays([pa.array([z], pa.int64())], names=["z"])


def by_ranks(rel: Rel, n_c: int) -> DataFrame:
    """One row z of a mirrored relation of ``n_c`` values: a pass for each block, whose shuffle files go before the next."""
    spark = rel.left.sparkSession
    held = lists_of(rel, 0)
    sizes = sorted((r["n"], r["count"]) for r in held.groupBy("n").count().collect())
    parts, z = spark.sparkContext.defaultParallelism, 0
    cuts = _rank_blocks(sizes)
    for block in range(len(cuts)) if sizes else ():
        rows = held.mapInArrow(_rank_dealer(block, cuts, sizes, parts), "cell int, side int, times long, keys binary")
        with released(spark), batches_of(spark, 1_000):
            z += rows.repartitionById(parts, F.col("cell")).sortWithinPartitions("side").mapInArrow(_rank_counter, "z long").agg(F.sum("z").alias("z")).first()["z"] or 0
    return spark.range(1).select(F.lit(z).cast("long").alias("z"))
