"""One sort, then one forward scan: hits from sorted runs in Arrow batches.

Left rows and right rows are sorted by (join value, cell, side, hash).  A right
row stands in its own cell and in the next one, so a hit never leaves its run
and a heavy join value is as many runs as there are cells.  Within a run three
cursors only go forward: the right row, and the first and the last left row of
its interval; in a batch they are running counts.  What is held over from one
batch to the next is the left rows of the open run.

With ``keep`` the kept set lives inside the scan: every full buffer lowers the
threshold for the rows that follow, and a task emits its k smallest pairs.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.hashing import FAMILIES

#: Pairs that are looked at together.
BLOCK_PAIRS = 1 << 20
HITS = "x_h long, y_h long, pair_h long"
COUNTERS = "left_rows long, right_rows long, moves long, visited long, inserts long, selections long, first_t double, last_t double"


class BottomK:
    """The k smallest distinct pairs by a buffer of k and linear selection.

    States merge: the union of two sets' states is the state of the union.
    """

    def __init__(self, k: int):
        self.k, self.rows = k, np.zeros((0, 3), np.int64)
        self.held: list[np.ndarray] = []
        self.waiting = self.selections = self.inserts = 0

    @property
    def limit(self) -> int:
        """Pairs above this hash need not be looked at."""
        return int(self.rows[-1, 0]) if len(self.rows) == self.k else 2**63 - 1

    def _combine(self, new: np.ndarray) -> None:
        self.selections += 1
        self.rows = np.unique(np.concatenate([self.rows, new]), axis=0)[: self.k]

    def add_batch(self, pair_h: np.ndarray, x_h: np.ndarray, y_h: np.ndarray) -> None:
        """Adds pairs at once, with one selection."""
        low = pair_h <= self.limit
        new = np.stack([pair_h[low], x_h[low], y_h[low]], 1)
        if not len(new):
            return
        self.inserts += len(new)
        if len(new) > 4 * self.k:
            cut = np.partition(new[:, 0], 4 * self.k - 1)[4 * self.k - 1]
            if len(np.unique(new[new[:, 0] <= cut], axis=0)) >= self.k:
                new = new[new[:, 0] <= cut]
        self._combine(new)

    def feed(self, pair_h: np.ndarray, x_h: np.ndarray, y_h: np.ndarray) -> None:
        """Adds pairs one after the other: a selection whenever the buffer holds k, and pairs above the new limit stay out."""
        new = np.stack([pair_h, x_h, y_h], 1)
        while True:
            new = new[new[:, 0] <= self.limit]
            some, new = new[: self.k - self.waiting], new[self.k - self.waiting :]
            self.inserts += len(some)
            self.waiting += len(some)
            if len(some):
                self.held.append(some)
            if self.waiting < self.k:
                return
            self.flush()

    def flush(self) -> None:
        if self.waiting:
            self._combine(np.concatenate(self.held))
            self.held, self.waiting = [], 0

    def merge(self, other: BottomK) -> BottomK:
        out = BottomK(self.k)
        out.rows = np.unique(np.concatenate([self.rows, other.rows]), axis=0)[: self.k]
        return out


def sorted_runs(left: DataFrame, right: DataFrame, cells: int, cell, how: str = "hash", partitions: int | None = None) -> DataFrame:
    """(jk, cell, side, h): both sides in one table, arranged by run and sorted; ``how`` is hash or range.

    Side 0 is a left row, 1 a right row in its own cell, 2 one in the next
    cell, 3 one whose next cell lies behind the wrap.
    """
    if how not in ("hash", "range"):
        raise ValueError("how is 'hash' or 'range'")
    own = cell("y_h")
    side = F.when(own + 1 >= cells, 3).otherwise(2)
    both = F.explode(F.array(F.struct(own.cast("long").alias("cell"), F.lit(1).alias("side")), F.struct(F.pmod(own + 1, F.lit(cells)).cast("long").alias("cell"), side.alias("side"))))
    r = right.select("jk", F.col("y_h").alias("h"), both.alias("at")).select("jk", "at.cell", F.col("at.side").cast("int").alias("side"), "h")
    rows = left.select("jk", cell("x_h").cast("long").alias("cell"), F.lit(0).alias("side"), F.col("x_h").alias("h")).unionByName(r)
    if isinstance(rows.schema["jk"].dataType, (T.StructType, T.ArrayType)):
        rows = rows.withColumn("jk", F.to_json(F.struct("jk")))
    keys = ([partitions] if partitions else []) + ["jk", "cell"]
    dealt = rows.repartition(*keys) if how == "hash" else rows.repartitionByRange(*keys)
    return dealt.sortWithinPartitions("jk", "cell", F.least("side", F.lit(1)), "h")


@dataclass
class Scan:
    """The forward scan of one task."""

    domain: int
    t: int
    keep: int | None = None
    kept: BottomK | None = None
    counts: dict = field(default_factory=lambda: dict.fromkeys(("left_rows", "right_rows", "moves", "visited"), 0))

    def __post_init__(self):
        self.first_t, self.open, self.open_key, self.open_low = self.t, np.zeros(0, np.uint64), None, 0
        self.block = BLOCK_PAIRS
        if self.keep is not None:
            self.kept, self.block = BottomK(self.keep), 4 * self.keep

    def batch(self, rows: pa.RecordBatch) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """The hits of a batch, in blocks."""
        n = rows.num_rows
        jk, cell = rows.column("jk"), rows.column("cell")
        side, h = rows.column("side").to_numpy(), rows.column("h").to_numpy().view(np.uint64)
        change = np.ones(n, bool)
        change[1:] = np.asarray(pc.not_equal(jk[1:], jk[:-1])) | (cell.to_numpy()[1:] != cell.to_numpy()[:-1])
        goes_on = self.open_key == (jk[0].as_py(), cell[0].as_py())
        run = np.cumsum(change) - 1
        if not goes_on:
            self.open, self.open_low = np.zeros(0, np.uint64), 0
        is_left = side == 0
        x = np.concatenate([self.open, h[is_left]])
        x_run = np.concatenate([np.zeros(len(self.open), np.int64), run[is_left]])
        y, y_run, kind = h[~is_left], run[~is_left], side[~is_left]
        base = np.searchsorted(x_run, np.arange(run[-1] + 1))
        # The first left row of the interval: the start of the run where the interval began in the cell before.
        low = base[y_run]
        own = kind == 1
        low[own] = before(x_run, x, y_run[own], y[own])
        self._count(is_left, own, low, base, y_run)
        at = 0
        while at < len(y):
            high = self._ends(x_run, x, y_run[at:], y[at:], kind[at:])
            size = np.maximum(high - low[at:], 0)
            total = np.cumsum(size)
            some = max(1, int(np.searchsorted(total, self.block, "right")))
            size = size[:some]
            where = np.repeat(low[at : at + some] - np.cumsum(size) + size, size) + np.arange(size.sum())
            px, py = x[where], np.repeat(y[at : at + some], size)
            ph = np.where(px >= py, px - py, px + (np.uint64(self.domain) - py))
            self.counts["visited"] += len(px)
            hit = tuple(v.view(np.int64) for v in (px, py, ph))
            if self.kept is None:
                yield hit
            else:
                self.kept.feed(hit[2], hit[0], hit[1])
                self.t = min(self.t, self.kept.limit + 1)
                # Short blocks at first, since the threshold falls fastest then.
                self.block = min(2 * self.block, BLOCK_PAIRS)
            at += some
        last = x_run == run[-1]
        self.open, self.open_key = x[last], (jk[n - 1].as_py(), cell[n - 1].as_py())

    def _ends(self, x_run, x, y_run, y, kind) -> np.ndarray:
        """Left rows before the end of each interval under the threshold of now."""
        t, domain = np.uint64(self.t), np.uint64(self.domain)
        end = y + t
        none = (kind == 3) & (end <= domain)
        end = np.where(kind == 3, np.where(none, np.uint64(0), end - domain), np.minimum(end, domain))
        return before(x_run, x, y_run, end)

    def _count(self, is_left, own, low, base, y_run) -> None:
        self.counts["left_rows"] += int(is_left.sum())
        self.counts["right_rows"] += int(own.sum())
        if not own.any():
            # The cursor stays where it was, if the run does.
            self.open_low = self.open_low if len(base) == 1 else 0
            return
        # Where the start cursor stands at the last right row of each run; it came from where the run's scan stood.
        runs, last = y_run[own], low[own] - base[y_run[own]]
        ends = np.flatnonzero(np.append(runs[1:] != runs[:-1], True))
        moved = last[ends].copy()
        if runs[ends[0]] == 0:
            moved[0] -= self.open_low
        self.counts["moves"] += int(moved.sum())
        self.open_low = int(last[ends[-1]]) if runs[ends[-1]] == len(base) - 1 else 0

    def finish(self) -> np.ndarray:
        self.kept.flush()
        self.t = min(self.t, self.kept.limit + 1)
        return self.kept.rows


def before(x_run: np.ndarray, x: np.ndarray, run: np.ndarray, value: np.ndarray) -> np.ndarray:
    """For each (run, value), the left rows of earlier runs and those of its run below the value."""
    n = len(x)
    order = np.lexsort((np.concatenate([np.ones(n, np.int8), np.zeros(len(value), np.int8)]), np.concatenate([x, value]), np.concatenate([x_run, run])))
    seen = np.cumsum(order < n)
    out = np.empty(n + len(value), np.int64)
    out[order] = seen
    return out[n:]


def _runner(domain: int, t: int, keep: int | None, counters: bool):
    names = [x.split()[0] for x in (COUNTERS if counters else HITS).split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scan = Scan(domain, t, keep)
        for rows in batches:
            if rows.num_rows:
                for hit in scan.batch(rows):
                    if not counters:
                        yield pa.RecordBatch.from_arrays([pa.array(v) for v in hit], names=names)
        if keep is None:
            return
        kept = scan.finish()
        if counters:
            row = {**scan.counts, "inserts": scan.kept.inserts, "selections": scan.kept.selections, "first_t": scan.first_t / domain, "last_t": scan.t / domain}
            yield pa.RecordBatch.from_pydict({n: [row[n]] for n in names})
        else:
            yield pa.RecordBatch.from_arrays([pa.array(kept[:, i]) for i in (1, 2, 0)], names=names)

    return run


def scan_hits(left: DataFrame, right: DataFrame, family: str, t: int, cells: int, width: int, keep: int | None = None, how: str = "hash", counters: bool = False, partitions: int | None = None) -> DataFrame:
    """(x_h, y_h, pair_h) below ``t``, or with ``keep`` at most so many of each task; ``counters`` gives what each task did."""
    domain = FAMILIES[family].domain
    power = not domain & (domain - 1)
    if cells == 1:
        cell = lambda c: F.lit(0)
    else:
        cell = lambda c: F.shiftright(c, width.bit_length() - 1) if power else F.expr(f"{c} div {width}")
    rows = sorted_runs(left, right, cells, cell, how, partitions)
    return rows.mapInArrow(_runner(domain, t, keep, counters), COUNTERS if counters else HITS)
