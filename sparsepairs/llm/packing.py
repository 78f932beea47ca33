"""Packing: cutting-stock column generation over the histogram of piece lengths.

Documents longer than a sequence give whole sequences and a remainder.  The
histogram of piece lengths has at most one entry for each length, whatever the
size of the corpus.  A linear program over patterns (how many pieces of each
length share a sequence) is solved by the simplex method; a knapsack dynamic
programme over the dual prices finds the next columns.  Patterns are rounded
down and what is left is filled greedily.  Pieces are then ranked within their
length and the ranks are dealt to the patterns' places.

Ranks come from salted groups: each length has as many groups as its share of
all pieces needs, and group offsets are a table, so no task holds a whole
length.

Defined cases: null and empty texts are the end token alone; very long texts
are packed whole; repeated rows and ids are pieces of their own; an empty
table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import shared
from .batches import fields, sliced, spark_schema
from .tokens import END, encoder

SEQUENCE = 1024
#: Rows that one ranking task may hold, and groups into which smaller tables are dealt.
GROUP_ROWS, GROUPS = 200_000, 4_096
#: Relative tolerance of the linear program to its bound, and what so many rounds of pricing must save to go on.
TOLERANCE, LEAST_SAVING, ROUNDS = 5e-5, 2e-5, 48
#: Columns of one round of pricing.
OFFERED = 96

PIECES = fields(doc_id=pa.int64(), start=pa.int64(), length=pa.int64(), ids_crc32=pa.int64(), doc_tokens=pa.int64())


@dataclass(frozen=True)
class Pattern:
    """Counts by length of the pieces in one sequence, and how many sequences are like it."""

    items: tuple[tuple[int, int], ...]
    copies: int


def pieces(docs: DataFrame, sequence: int = SEQUENCE, tokenizer_folder: str | None = None) -> DataFrame:
    """The pieces of every document: whole sequences, then what remains."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(tokenizer_folder).ids
        for batch in sliced(batches, "text"):
            out: tuple[list, ...] = ([], [], [], [], [])
            for doc_id, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                ids = encode(text or "")
                raw = memoryview(np.append(ids, np.uint32(END)).astype("<u4").tobytes())
                total = len(ids) + 1
                for start in range(0, total, sequence):
                    length = min(sequence, total - start)
                    for column, value in zip(out, (doc_id, start, length, zlib.crc32(raw[4 * start : 4 * (start + length)]), total), strict=True):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in out], schema=PIECES)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, spark_schema(PIECES))


def greedy(demand: dict[int, int], sequence: int = SEQUENCE, whole: bool = True) -> list[Pattern]:
    """The longest piece left, then always the longest that still fits; each pattern as often as demand allows.

    With ``whole`` false the copies may be fractions, and every pattern then
    uses up a length: such patterns are a basis of the linear program.
    """
    left = np.zeros(sequence + 1)
    for length, n in demand.items():
        left[length] = n
    out: list[Pattern] = []
    lengths = np.flatnonzero(left)
    while len(lengths):
        room, items = sequence, []
        k = len(lengths)
        while k and room >= lengths[0]:
            k = int(np.searchsorted(lengths[:k], room, "right"))
            if not k:
                break
            length = int(lengths[k - 1])
            count = room // length
            if whole:
                count = min(count, int(left[length]))
            items.append((length, count))
            room -= length * count
            k -= 1
        ratios = [left[length] / count for length, count in items]
        copies = int(min(ratios)) if whole else min(ratios)
        out.append(Pattern(tuple(items), copies))
        for (length, count), ratio in zip(items, ratios, strict=True):
            left[length] = 0 if ratio == copies else left[length] - count * copies
        lengths = np.flatnonzero(left)
    return out


class Knapsack:
    """Unbounded knapsacks of all sizes up to a sequence, by dynamic programming over the prices of lengths."""

    def __init__(self, prices: np.ndarray, lengths: np.ndarray, sequence: int = SEQUENCE):
        self.lengths, self.sequence, low = lengths, sequence, int(lengths[0])
        dense = np.full(sequence + 1, -np.inf)
        dense[lengths[prices > 0]] = prices[prices > 0]
        self.value, last = np.zeros(sequence + 1), np.zeros(sequence + 1, np.int64)
        for room in range(low, sequence + 1):
            got = dense[low : room + 1] + self.value[room - low :: -1]
            k = int(got.argmax())
            self.value[room] = self.value[room - 1]
            if got[k] > self.value[room - 1] + 1e-12:
                self.value[room], last[room] = got[k], k + low
        # The longest filled part of each room, and the last piece in it.
        self.filled = np.maximum.accumulate(np.where(last > 0, np.arange(sequence + 1), 0))
        self.last = last
        self.with_first = prices + self.value[sequence - lengths]

    def columns(self, first: np.ndarray) -> np.ndarray:
        """The best column that holds each of the given lengths (by place): a row of counts for each."""
        place = np.zeros(self.sequence + 1, np.int64)
        place[self.lengths] = np.arange(len(self.lengths))
        out = np.zeros((len(first), len(self.lengths)))
        out[np.arange(len(first)), first] = 1
        room, rows = self.sequence - self.lengths[first], np.arange(len(first))
        while len(rows):
            room = self.filled[room]
            rows, room = rows[room > 0], room[room > 0]
            piece = self.last[room]
            out[rows, place[piece]] += 1
            room = room - piece
        return out


@dataclass(frozen=True)
class Plan:
    """Patterns that use every piece once; the linear program's value and lower bound, and the columns that were priced in."""

    patterns: list[Pattern]
    lp_value: float
    bound: float
    columns: int

    @property
    def sequences(self) -> int:
        return sum(p.copies for p in self.patterns)


def _basis(demand: dict[int, int], lengths: np.ndarray, sequence: int) -> np.ndarray:
    """Columns of the fractional greedy filling: each uses up a length that no later one has."""
    place = {int(x): i for i, x in enumerate(lengths)}
    columns, held = np.eye(len(lengths)), {}
    for pattern in greedy(demand, sequence, whole=False):
        for length, count in pattern.items:
            held[length] = held.get(length, 0.0) + count * pattern.copies
        for length, _ in pattern.items:
            i = place[length]
            if held[length] >= demand[length] * (1 - 1e-12):
                columns[:, i] = 0
                for other, n in pattern.items:
                    columns[place[other], i] = n
                break
    return columns


def relax(demand: dict[int, int], sequence: int = SEQUENCE) -> tuple[np.ndarray, np.ndarray, float, int]:
    """(basis, level of each column, lower bound, columns priced in) of the linear program.

    Each round the knapsack prices the best column for every length; of those
    that save, the best of all and an even spread enter in turn, the one
    that saves most first.  It ends where no column saves, where the bound shows that
    no whole sequence is left to save, within ``TOLERANCE`` of the bound, or
    where ``ROUNDS`` rounds (more with fewer lengths) save less than ``LEAST_SAVING`` of all: near the end
    most steps are small, and the bound of unsettled prices is weak.
    """
    lengths = np.array(sorted(demand))
    need = np.array([demand[int(x)] for x in lengths], float)
    basis = _basis(demand, lengths, sequence)
    rng = np.random.default_rng(3)
    # Demands that differ a little keep steps from being empty.
    moved = need * (1 + 1e-6 * rng.random(len(need)))
    inverse = np.linalg.inv(basis)
    level, bound, entered, totals = inverse @ moved, float(lengths @ need) / sequence, 0, []
    # Few lengths take cheap rounds, but as many of them.
    rounds = ROUNDS * sequence // len(lengths)
    while True:
        prices = inverse.sum(0)
        packed = Knapsack(prices, lengths, sequence)
        bound = max(bound, float(prices @ need) / max(packed.value[sequence], 1.0))
        total = float(prices @ need)
        totals.append(total)
        stuck = len(totals) > rounds and totals[-1 - rounds] - total < LEAST_SAVING * total
        saving = np.flatnonzero(packed.with_first > 1 + 1e-9)
        if stuck or not len(saving) or np.ceil(total - 1e-6) <= np.ceil(bound - 1e-6) or total <= (1 + TOLERANCE) * bound:
            break
        if len(saving) > OFFERED:
            top = saving[np.argsort(-packed.with_first[saving], kind="stable")[:8]]
            saving = np.concatenate([top, rng.choice(saving, OFFERED - 8, replace=False)])
        offered = np.unique(packed.columns(saving), axis=0)
        moves = inverse @ offered.T
        before = entered
        while True:
            saved = moves.sum(0) - 1
            with np.errstate(divide="ignore", invalid="ignore"):
                ratios = np.where(moves > 1e-7, np.maximum(level, 0)[:, None] / moves, np.inf)
            outs = ratios.argmin(0)
            steps = ratios[outs, np.arange(len(offered))]
            able = (saved > 1e-9) & np.isfinite(steps)
            if not able.any():
                break
            k = int(np.where(able, np.where(able, saved, 0) * np.where(able, steps, 0), -1).argmax())
            move, out = moves[:, k].copy(), int(outs[k])
            basis[:, out] = offered[k]
            level -= steps[k] * move
            level[out] = steps[k]
            touched = np.flatnonzero(np.abs(move) > 1e-12)
            for table in (inverse, moves):
                row = table[out] / move[out]
                table[touched] -= move[touched, None] * row
                table[out] = row
            entered += 1
            if entered % 500 == 0:
                inverse = np.linalg.inv(basis)
                level, moves = inverse @ moved, inverse @ offered.T
        if entered == before:
            break
    return basis, np.linalg.solve(basis, need), bound, entered


def solve(demand: dict[int, int], sequence: int = SEQUENCE) -> Plan:
    """Patterns that use every piece once: column generation, levels rounded down, the rest filled greedily.

    Levels of at most one column for each length are rounded, so at most so
    many sequences come on top of the linear program; the plain greedy filling
    is taken where it needs fewer.
    """
    demand = {k: int(v) for k, v in demand.items() if v > 0}
    if not demand:
        return Plan([], 0.0, 0.0, 0)
    lengths = np.array(sorted(demand))
    basis, level, bound, entered = relax(demand, sequence)
    rest = dict(demand)
    rounded = []
    for j in np.argsort(-level):
        items = [(int(lengths[i]), int(basis[i, j])) for i in np.flatnonzero(basis[:, j] > 0.5)[::-1]]
        copies = min([int(np.floor(level[j] + 1e-6)), *(rest[a] // b for a, b in items)])
        if copies > 0:
            rounded.append(Pattern(tuple(items), copies))
            for a, b in items:
                rest[a] -= b * copies
    both = rounded + greedy({a: n for a, n in rest.items() if n}, sequence)
    best = min(both, greedy(demand, sequence), key=lambda own: sum(p.copies for p in own))
    return Plan(best, float(level.sum()), bound, entered)


def places(patterns: list[Pattern]) -> list[tuple[int, int, int, int, int, int]]:
    """(length, first rank, past rank, first sequence, pieces in a sequence, offset): where ranks of a length go."""
    out, used, sequence_id = [], {}, 0
    for pattern in patterns:
        at = 0
        for length, count in pattern.items:
            first = used.get(length, 0)
            used[length] = first + count * pattern.copies
            out.append((length, first, used[length], sequence_id, count, at))
            at += length * count
        sequence_id += pattern.copies
    return out


def pack(found: DataFrame, sequence: int = SEQUENCE, group_rows: int = GROUP_ROWS) -> DataFrame:
    """``found`` pieces with ``sequence_id`` and ``offset``; ``found`` should be a written table, it is read three times."""
    spark = found.sparkSession
    histogram = {r["length"]: r["n"] for r in found.groupBy("length").agg(F.count("*").alias("n")).collect()}
    plan = places(solve(histogram, sequence).patterns)
    group = max(1, min(group_rows, sum(histogram.values()) // GROUPS))
    groups = F.get(F.lit([-(-histogram.get(x, 1) // group) for x in range(sequence + 1)]), F.col("length").cast("int"))
    salted = found.withColumn("__salt", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), groups))
    sizes = salted.groupBy("length", "__salt").agg(F.count("*").alias("__n"))
    before = Window.partitionBy("length").orderBy("__salt").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select("length", "__salt", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__before"))
    own = Window.partitionBy("length", "__salt").orderBy("doc_id", "start", "ids_crc32")
    ranked = salted.withColumn("__own", F.row_number().over(own) - 1).join(offsets, ["length", "__salt"])
    ranked = ranked.withColumn("__rank", F.col("__before") + F.col("__own"))
    # At most two patterns for each length and a few places in each: bounded by the sequence's length.
    table = spark.createDataFrame(plan, "__length long, __first long, __past long, __sequence long, __count long, __at long")
    hit = (F.col("length") == F.col("__length")) & (F.col("__rank") >= F.col("__first")) & (F.col("__rank") < F.col("__past"))
    step = F.col("__rank") - F.col("__first")
    return ranked.join(F.broadcast(table), hit).select(
        *PIECES.names,
        (F.col("__sequence") + F.floor(step / F.col("__count"))).cast("long").alias("sequence_id"),
        (F.col("__at") + F.pmod(step, F.col("__count")) * F.col("length")).cast("long").alias("offset"),
    )


def pack_documents(docs: DataFrame, sequence: int = SEQUENCE, tokenizer_folder: str | None = None) -> DataFrame:
    """Pieces of all documents with their sequences."""
    return pack(shared.written(pieces(docs, sequence, tokenizer_folder), "pieces"), sequence)
