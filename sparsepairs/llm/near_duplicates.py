"""N-gram Jaccard join: chosen paths over word shingles, then exact similarity.

A document is the set of its five-word shingles; a shorter one has a single
shingle of all its words.  Documents of equal sets are one class from the
start.  Among the distinct sets a chosen-path join looks for candidates: sets
are split on tokens of their min-wise samples, a node's hash chooses the
coordinates, each with probability 1 / (similarity * coordinates), and sets
that share the token there meet in a child.  Small buckets are compared by
their samples without more splitting.  Runs are added until the target recall
is expected at the lowest similarity.  Candidates, gathered to components, are
then compared by their whole sets, block against block, and counted.

No pair is written as a row: a bucket gives a star per component and, after
the exact comparison, the links of each member.  A set is named by a 64-bit
hash (about n^2 / 2^65 expected clashes among n sets).

Defined cases: null and empty texts and texts without words have no set; each
is a class of its own without links; very long texts count whole; repeated
rows and ids give a row each, also where one id has several texts; rows without
an id are compared like others, their class takes its smallest known id (null
if it has none); extra columns are ignored; empty tables give no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shared
from .batches import fields, mix, row_of, sliced, spark_schema, text_bytes, word_hashes, word_spans
from .components import components

WORDS = 5
#: 32-bit words of the bitmap that spares most texts a shuffle: at most 2 MB.
FILTER_WORDS = 1 << 17
SIMILARITY = 0.8
COORDINATES = 128
RECALL = 0.99999
#: Sets of a bucket that is compared without more splitting, and levels of splitting.
BUCKET, LEVELS = 256, 4
#: Sets of one side of a comparison of samples.
COMPARED = 2_048
#: Shingles and sets of one side of an exact comparison.
BLOCK_SHINGLES, BLOCK_SETS = 400_000, 1_024
#: Share of the misses that the recall allows which the comparison of samples may cause.
FILTER_SHARE = 0.1

_RNG = np.random.default_rng(20_240_601)
_ODD = _RNG.integers(0, 2**32, COORDINATES, dtype=np.uint32) | np.uint32(1)
_XOR = _RNG.integers(0, 2**32, COORDINATES, dtype=np.uint32)
_CHAIN = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0x85EBCA77C2B2AE63], np.uint64)

SETS = fields(doc_id=pa.int64(), text_key=pa.int64(), name=pa.int64(), n=pa.int64(), sample=pa.binary())
NODES = fields(node=pa.int64(), name=pa.int64())
CHILDREN = fields(parent=pa.int64(), node=pa.int64(), name=pa.int64())
EDGES = fields(a=pa.int64(), b=pa.int64())
WHOLE = fields(component=pa.int64(), name=pa.int64(), copies=pa.int64(), shingles=pa.binary())
LINKED = fields(name=pa.int64(), root=pa.int64(), links=pa.int64())


def shingle_sets(raw: np.ndarray, off: np.ndarray) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each row."""
    starts, ends, before = word_spans(raw, off)
    h, rows = word_hashes(raw, starts, ends), row_of(before)
    n = len(h) - WORDS + 1
    out = [np.zeros(0, np.uint64)] * (len(off) - 1)
    if n > 0:
        s = np.zeros(n, np.uint64)
        for j in range(WORDS):
            s = (s + h[j : j + n]) * _CHAIN[j]
            s ^= s >> np.uint64(31)
        s = mix(s)
    for r, (a, b) in enumerate(zip(before[:-1].tolist(), before[1:].tolist(), strict=True)):
        if b - a >= WORDS:
            out[r] = np.unique(s[a : b - WORDS + 1])
        elif b > a:
            short = np.uint64(b - a)
            for x in h[a:b]:
                short = mix(np.array([(int(short) * 31 + int(x)) & (2**64 - 1)], np.uint64))[0]
            out[r] = np.array([short], np.uint64)
    return out


def set_name(s: np.ndarray) -> int:
    """A signed 64-bit hash of a set."""
    with np.errstate(over="ignore"):
        both = mix(s ^ _CHAIN[1]).sum(dtype=np.uint64) ^ (np.uint64(len(s)) << np.uint64(48))
    return int(mix(np.array([both], np.uint64)).view(np.int64)[0])


def sample_of(s: np.ndarray) -> np.ndarray:
    """The min-wise sample: for each coordinate, the smallest value of its own hash."""
    x = (s >> np.uint64(32)).astype(np.uint32)
    best = np.full(COORDINATES, 2**32 - 1, np.uint32)
    for a in range(0, len(x), 1024):
        np.minimum(best, (((x[None, a : a + 1024] ^ _XOR[:, None]) * _ODD[:, None])).min(1), out=best)
    return best


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in sliced(batches, "text"):
        found = shingle_sets(*text_bytes(batch.column("text")))
        yield pa.RecordBatch.from_arrays(
            [
                batch.column("doc_id").cast(pa.int64()),
                batch.column("text_key"),
                pa.array([set_name(s) if len(s) else None for s in found], pa.int64()),
                pa.array([len(s) for s in found], pa.int64()),
                pa.array([sample_of(s).astype("<u4").tobytes() if len(s) else None for s in found], pa.binary()),
            ],
            schema=SETS,
        )


def runs_for(similarity: float = SIMILARITY, recall: float = RECALL) -> list[int]:
    """Coordinates that the root nodes of the runs choose, until a pair of that similarity meets with the target recall.

    A pair meets at a coordinate with a probability of its similarity.
    """
    chosen: list[int] = []
    run = 0
    while 1 - (1 - similarity) ** len(chosen) < recall:
        root = mix(np.arange(COORDINATES, dtype=np.uint64) + np.uint64(1_000_003 * (run + 1)))
        picked = np.flatnonzero(root.astype(float) / 2.0**64 < 1 / (similarity * COORDINATES))
        chosen += [int(i) for i in picked if i not in chosen]
        run += 1
    return chosen


def _first_level(chosen: list[int]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sample = np.frombuffer(b"".join(batch.column("sample").to_pylist()), "<u4").reshape(-1, COORDINATES)
            for i in chosen:
                node = mix(sample[:, i].astype(np.uint64) + (np.uint64(i + 1) << np.uint64(40)))
                yield pa.RecordBatch.from_arrays([pa.array(node.view(np.int64)), batch.column("name")], schema=NODES)

    return run


def fan_out(similarity: float, recall: float) -> int:
    """Coordinates that a large bucket tries, so that a pair which is parted in one bucket meets in another.

    A pair misses if in each root bucket it is apart from the start or on one
    of the levels below.
    """
    many, roots = 1, len(runs_for(similarity, recall))
    while (1 - similarity * (1 - (1 - similarity) ** many) ** LEVELS) ** roots > 1 - recall:
        many += 1
    return many


def _next_level(similarity: float, level: int, recall: float = RECALL):
    """Children of large buckets; a node's own hash picks its coordinates."""
    many = fan_out(similarity, recall)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            parent = batch.column("node").to_numpy(zero_copy_only=False).view(np.uint64)
            sample = np.frombuffer(b"".join(batch.column("sample").to_pylist()), "<u4").reshape(-1, COORDINATES)
            # An odd step visits all coordinates before one comes again.
            start, step = mix(parent + np.uint64(7_919 + level)), mix(parent + np.uint64(2 * 7_919 + level)) | np.uint64(1)
            for t in range(min(many, COORDINATES)):
                i = ((start + np.uint64(t) * step) % np.uint64(COORDINATES)).astype(np.int64)
                node = mix(parent ^ mix(sample[np.arange(len(i)), i].astype(np.uint64) + ((i + 1).astype(np.uint64) << np.uint64(40))))
                yield pa.RecordBatch.from_arrays([batch.column("node"), pa.array(node.view(np.int64)), batch.column("name")], schema=CHILDREN)

    return run


def stars(n: int, first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """The root (smallest place) of each of ``n`` places under the given links."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[first], root[second])
        new = root.copy()
        np.minimum.at(new, first, low)
        np.minimum.at(new, second, low)
        np.minimum.at(new, root[first], low)
        np.minimum.at(new, root[second], low)
        new = new[new]
        if (new == root).all():
            return root
        root = new


def grouped(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """The runs of equal keys in sorted batches, whole even where batches end."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [batch.column(k).to_numpy(zero_copy_only=False) for k in keys]
        change = np.zeros(batch.num_rows, bool)
        for c in columns:
            change[1:] |= c[1:] != c[:-1]
        cuts = np.concatenate([[0], np.flatnonzero(change), [batch.num_rows]])
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            key = tuple(c[a] for c in columns)
            if held and key != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
            last = key
    if held:
        yield pa.Table.from_batches(held)


def least_agreement(similarity: float, recall: float) -> int:
    """The most coordinates below which a pair of that similarity agrees in at most its share of the misses."""
    below = 0.0
    for agreed in range(COORDINATES + 1):
        below += math.comb(COORDINATES, agreed) * similarity**agreed * (1 - similarity) ** (COORDINATES - agreed)
        if below > FILTER_SHARE * (1 - recall):
            return agreed
    return COORDINATES


def _compare(similarity: float, recall: float = RECALL):
    """Stars of sets in a bucket whose samples agree nearly as much as the similarity asks."""
    least = least_agreement(similarity, recall)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b, size = [], [], 0
        for group in grouped(batches, ["node", "low", "high"]):
            names = group.column("name").to_numpy()
            side = group.column("side").to_numpy()
            s = unpacked(b"".join(group.column("bytes").to_pylist()))
            cross = group.column("low")[0] != group.column("high")[0]
            left = np.flatnonzero(side == group.column("low")[0].as_py()) if cross else np.arange(len(names))
            right = np.flatnonzero(side != group.column("low")[0].as_py()) if cross else left
            first, second = [], []
            for k, i in enumerate(left):
                rest = right if cross else left[k + 1 :]
                hit = rest[(s[rest] == s[i]).sum(1) >= least]
                first.append(np.full(len(hit), i))
                second.append(hit)
            if first and sum(map(len, second)):
                root = stars(len(names), np.concatenate(first), np.concatenate(second))
                own = np.flatnonzero(root != np.arange(len(names)))
                a.append(names[own])
                b.append(names[root[own]])
                size += len(own)
            if size > 100_000:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(a)), pa.array(np.concatenate(b))], schema=EDGES)
                a, b, size = [], [], 0
        if size:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(a)), pa.array(np.concatenate(b))], schema=EDGES)

    return run


def _sized(nodes: DataFrame, keys: list[str]) -> DataFrame:
    """Buckets of two or more with their size; of buckets with the same members one is kept."""
    # Sums of 32-bit halves: rows that come twice don't cancel, and no sum overflows below 2^31 members.
    first, second = F.xxhash64("name"), F.xxhash64("name", F.lit(1))
    halves = [h for x in (first, second) for h in (x.bitwiseAND(F.lit(2**32 - 1)), F.shiftrightunsigned(x, 32))]
    members = [F.sum(h).alias(f"s{i}") for i, h in enumerate(halves)]
    sizes = nodes.groupBy(*keys).agg(F.count("*").alias("size"), *members).where("size > 1")
    return sizes.groupBy("size", *[f"s{i}" for i in range(len(halves))]).agg(F.min(F.struct(*keys)).alias("k")).select("k.*", "size")


def candidates(sets: DataFrame, similarity: float = SIMILARITY, recall: float = RECALL) -> DataFrame:
    """(a, b): stars of sets that the chosen-path join brings together; ``sets`` has name and sample, names differ.

    A bucket whose largest child still has half of its sets holds near copies
    of each other: splitting won't part them, so it is compared as it is.
    The misses that the recall allows are shared by the paths and the
    comparison of samples.
    """
    meeting = 1 - (1 - FILTER_SHARE) * (1 - recall)
    samples = sets.select("name", "sample")
    nodes = shared.written(samples.mapInArrow(_first_level(runs_for(similarity, meeting)), spark_schema(NODES)), "nodes")
    member = nodes.join(_sized(nodes, ["node"]), "node").select("node", "name", "size")
    done = member.where(F.col("size") <= BUCKET)
    large = shared.written(member.where(F.col("size") > BUCKET), "large")
    for level in range(1, LEVELS + 1):
        if not large.limit(1).collect():
            break
        if level == LEVELS:
            done = done.unionByName(large)
            break
        children = large.join(samples, "name").select("node", "name", "sample").mapInArrow(_next_level(similarity, level, meeting), spark_schema(CHILDREN))
        children = shared.written(children, "children")
        own = children.groupBy("parent", "node").agg(F.count("*").alias("n")).groupBy("parent").agg(F.max("n").alias("top"))
        judged = large.groupBy("node").agg(F.max("size").alias("whole")).join(own.withColumnRenamed("parent", "node"), "node")
        stuck = judged.where(2 * F.col("top") >= F.col("whole")).select("node")
        done = done.unionByName(large.join(stuck, "node", "left_semi").select("node", "name", "size"))
        moving = children.join(stuck.withColumnRenamed("node", "parent"), "parent", "left_anti").select("node", "name")
        member = moving.join(_sized(moving, ["node"]), "node").select("node", "name", "size")
        done = done.unionByName(member.where(F.col("size") <= BUCKET))
        large = shared.written(member.where(F.col("size") > BUCKET), "large")
    # The buckets are stored before they are dealt, so that only one of both lies on disk as shuffles.
    done = shared.written(done, "done")
    blocks = F.ceil(F.col("size") / COMPARED).cast("int")
    placed = done.select("node", "name", F.pmod(F.xxhash64("name", F.lit(2)), blocks).cast("int").alias("side"), F.explode(F.sequence(F.lit(0), blocks - 1)).alias("other"))
    placed = placed.select("node", "name", "side", F.least("side", "other").alias("low"), F.greatest("side", "other").alias("high"))
    # Two bits of each coordinate: equal ones stay equal, and a quarter of the others agree by chance.
    thin = samples.mapInArrow(_low_bits, spark_schema(BYTES))
    joined = placed.join(thin, "name")
    dealt = joined.repartition("node", "low", "high").sortWithinPartitions("node", "low", "high", "name")
    return dealt.mapInArrow(_compare(similarity, recall), spark_schema(EDGES))


BYTES = fields(name=pa.int64(), bytes=pa.binary())


def packed(sample: np.ndarray) -> np.ndarray:
    """The two low bits of each coordinate, four to a byte."""
    low = (sample & 3).astype(np.uint8).reshape(len(sample), -1, 4)
    return low[:, :, 0] | low[:, :, 1] << 2 | low[:, :, 2] << 4 | low[:, :, 3] << 6


def unpacked(raw: bytes) -> np.ndarray:
    """Rows of coordinates from their packed bits."""
    both = np.frombuffer(raw, np.uint8).reshape(-1, COORDINATES // 4)
    return np.stack([both >> shift & 3 for shift in (0, 2, 4, 6)], 2).reshape(-1, COORDINATES)


def _low_bits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sample = np.frombuffer(b"".join(batch.column("sample").to_pylist()), "<u4").reshape(-1, COORDINATES)
        yield pa.RecordBatch.from_arrays([batch.column("name"), pa.array([x.tobytes() for x in packed(sample)], pa.binary())], schema=BYTES)


def _whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The whole sets of candidates; a row of the same id but another text falls out by its name."""
    for batch in sliced(batches, "text"):
        found = shingle_sets(*text_bytes(batch.column("text")))
        names = batch.column("name").to_numpy()
        own = [r for r, s in enumerate(found) if len(s) and set_name(s) == names[r]]
        take = batch.take(pa.array(own, pa.int64()))
        parts = pa.array([found[r].astype("<u8").tobytes() for r in own], pa.binary())
        yield pa.RecordBatch.from_arrays([take.column("component"), take.column("name"), take.column("copies"), parts], schema=WHOLE)


def shared_counts(sets: list[np.ndarray], columns: int = 2048) -> np.ndarray:
    """Sizes of all pairwise intersections, by blocks of the incidence matrix."""
    sizes = [len(s) for s in sets]
    if len(sets) == 2:
        both = len(np.intersect1d(sets[0], sets[1], assume_unique=True))
        return np.array([[sizes[0], both], [both, sizes[1]]])
    _, place, seen = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    rows = np.repeat(np.arange(len(sets)), sizes)
    often = seen[place] > 1
    place, rows = place[often], rows[often]
    # Shingles of one set only meet none; those of all meet all.
    rank = np.cumsum(seen > 1) - 1
    place = rank[place]
    out = np.zeros((len(sets), len(sets)), np.float32)
    order = np.argsort(place, kind="stable")
    place, rows = place[order], rows[order]
    top = int(place[-1]) + 1 if len(place) else 0
    for a in range(0, top, columns):
        low, high = np.searchsorted(place, [a, a + columns])
        x = np.zeros((len(sets), min(columns, top - a)), np.float32)
        x[rows[low:high], place[low:high] - a] = 1
        out += x @ x.T
    got = np.rint(out).astype(np.int64)
    np.fill_diagonal(got, sizes)
    return got


def _exact(numerator: int, denominator: int):
    """Links of each member of a block pair, weighted by copies, and its star."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in grouped(batches, ["component", "low", "high"]):
            names, first = np.unique(group.column("name").to_numpy(), return_index=True)
            raw = group.column("shingles")
            sets = [np.frombuffer(raw[int(i)].as_buffer(), "<u8") for i in first]
            copies = group.column("copies").to_numpy()[first]
            side = group.column("side").to_numpy()[first]
            if len(names) < 2:
                continue
            both = shared_counts(sets)
            size = np.diag(both)
            near = denominator * both >= numerator * (size[:, None] + size[None] - both)
            np.fill_diagonal(near, False)
            if group.column("low")[0] != group.column("high")[0]:
                near &= side[:, None] != side[None]
            links = near @ copies
            i, j = np.nonzero(np.triu(near))
            if len(i):
                root = stars(len(names), i, j)
                own = np.flatnonzero(links > 0)
                yield pa.RecordBatch.from_arrays([pa.array(names[own]), pa.array(names[root[own]]), pa.array(links[own].astype(np.int64))], schema=LINKED)

    return run


def _marked(rows: DataFrame, held: DataFrame, key: str, held_key: str) -> DataFrame:
    """Rows with ``__held``: whether their key's bit is set in a bitmap of the held keys, as all held keys' bits are.

    The bitmap has ``FILTER_WORDS`` words whatever the data's size; in a full one all bits are set.
    """
    at = lambda c: F.pmod(F.xxhash64(F.lit("filter"), F.col(c)), F.lit(FILTER_WORDS * 32))
    word, bit = (lambda c: F.shiftright(at(c), 5)), (lambda c: F.pow(F.lit(2.0), F.pmod(at(c), F.lit(32))).cast("long"))
    bitmap = held.groupBy(word(held_key).alias("__word")).agg(F.bit_or(bit(held_key)).alias("__bits"))
    out = rows.withColumn("__word", word(key)).withColumn("__bit", bit(key)).join(F.broadcast(bitmap), "__word", "left")
    return out.select(*rows.columns, (F.coalesce("__bits", F.lit(0)).bitwiseAND(F.col("__bit")) != 0).alias("__held"))


def _likely(rows: DataFrame, held: DataFrame, key: str) -> DataFrame:
    """Rows whose key's bit is set: most others needn't be shuffled, and the join that follows decides."""
    return _marked(rows, held, key, key).where("__held").drop("__held")


def _parted(rows: DataFrame, held: DataFrame, key: str, held_key: str) -> tuple[DataFrame, DataFrame]:
    """Rows whose key is surely not held, and the others."""
    marked = _marked(rows, held, key, held_key)
    return marked.where("not __held").drop("__held"), marked.where("__held").drop("__held")


def keyed(docs: DataFrame) -> DataFrame:
    """doc_id, a hash of the text that tells the texts of one id apart, and the text."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("text_key"), "text")


def members(docs: DataFrame, similarity: tuple[int, int] = (4, 5), recall: float = RECALL) -> DataFrame:
    """doc_id, text_key, component, class_id, n_links of every row; the component is null without a set.

    ``similarity`` is a fraction; a link joins documents of at least that
    Jaccard similarity, copies included.
    """
    numerator, denominator = similarity
    share = numerator / denominator
    sets = shared.written(keyed(docs).mapInArrow(_sets, spark_schema(SETS)), "sets")
    known = sets.where(F.col("name").isNotNull()).groupBy("name")
    example = F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "text_key")).alias("example")
    distinct = known.agg(F.min("doc_id").alias("first"), example, F.count("*").alias("copies"), F.first("n").alias("n"), F.first("sample").alias("sample"))
    distinct = shared.written(distinct.select("name", "first", F.col("example.doc_id").alias("example"), F.col("example.text_key").alias("text_key"), "copies", "n", "sample"), "distinct")
    loose = components(candidates(distinct, share, recall))
    held = loose.join(distinct.select(F.col("name").alias("id"), "example", "text_key", "copies", "n"), "id")
    held = shared.written(held.select(F.col("id").alias("name"), "component", "example", "text_key", "copies", "n"), "held")
    weights = held.groupBy("component").agg(F.sum("n").alias("weight"), F.count("*").alias("size"))
    parts = F.greatest(F.ceil(F.col("weight") / BLOCK_SHINGLES), F.ceil(F.col("size") / BLOCK_SETS)).cast("int")
    # One text for each set: rows that share id and text meet in one.
    wanted = held.select("example", F.col("text_key").alias("__key"), "component", "name", "copies")
    texts = _likely(keyed(docs), held, "text_key").join(wanted, (F.col("text_key") == F.col("__key")) & F.col("doc_id").eqNullSafe(F.col("example")))
    texts = texts.select("component", "name", "copies", "text")
    whole = texts.mapInArrow(_whole, spark_schema(WHOLE)).join(weights.select("component", parts.alias("parts")), "component")
    side = F.pmod(F.xxhash64("name", F.lit(3)), F.col("parts")).cast("int")
    placed = whole.withColumn("side", side).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    placed = placed.select("component", "name", "copies", "shingles", "side", F.least("side", "other").alias("low"), F.greatest("side", "other").alias("high"))
    dealt = placed.repartition("component", "low", "high").sortWithinPartitions("component", "low", "high", "name")
    linked = shared.written(dealt.mapInArrow(_exact(numerator, denominator), spark_schema(LINKED)), "linked")
    tight = components(linked.select(F.col("name").alias("a"), F.col("root").alias("b")))
    links = linked.groupBy("name").agg(F.sum("links").alias("links"))
    named = distinct.select("name", "first", "copies").join(tight.withColumnRenamed("id", "name"), "name", "left").join(links, "name", "left")
    named = named.withColumn("component", F.coalesce("component", "name"))
    heads = named.groupBy("component").agg(F.min("first").alias("class_id"))
    named = named.join(heads, "component").select("name", "component", "class_id", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    named = shared.written(named, "named")
    out = sets.select("doc_id", "text_key", "name").join(named, "name", "left")
    class_id = F.when(F.col("component").isNull(), F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id")
    return out.select("doc_id", "text_key", "component", class_id, F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))


def classes(docs: DataFrame, similarity: tuple[int, int] = (4, 5), recall: float = RECALL) -> DataFrame:
    """doc_id, class_id (smallest id of the class) and n_links of every document."""
    return members(docs, similarity, recall).select("doc_id", "class_id", "n_links")


def without_copies(docs: DataFrame, similarity: tuple[int, int] = (4, 5), recall: float = RECALL) -> DataFrame:
    """One row of each class, of the smallest id (then text hash), and all rows without a set; a repeated id and text stays once.

    Removal is by id and text: another text of the same id stays.
    """
    found = members(docs, similarity, recall).where(F.col("component").isNotNull())
    mine = F.struct(F.col("doc_id").isNull(), "doc_id", "text_key")
    heads = shared.written(found.groupBy("component").agg(F.min(mine).alias("head")).select(F.col("head.doc_id").alias("__id"), F.col("head.text_key").alias("__key")), "heads")
    gone = found.select(F.col("doc_id").alias("__id"), F.col("text_key").alias("__key")).distinct()
    gone = shared.written(gone.join(heads.withColumnsRenamed({"__id": "__i", "__key": "__k"}), F.col("__id").eqNullSafe(F.col("__i")) & (F.col("__key") == F.col("__k")), "left_anti"), "gone")
    keyed_docs = docs.withColumn("__text", F.xxhash64("text"))
    again = keyed_docs.groupBy("doc_id", "__text").count().where("count > 1").select(F.col("__text").alias("__key"))
    # Texts that are neither dropped nor repeated stay where they are; only the others are dealt.
    clear, suspect = _parted(keyed_docs, gone.select("__key").unionByName(again), "__text", "__key")
    kept = suspect.join(gone, F.col("doc_id").eqNullSafe(F.col("__id")) & (F.col("__text") == F.col("__key")), "left_anti")
    return clear.select(*docs.columns).unionByName(kept.select(*docs.columns).dropDuplicates(["doc_id", "text"]))
