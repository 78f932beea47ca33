"""SentencePiece encoding and decoding: Gumbel top-k samples without replacement.

A text's segmentations form a lattice that falls apart between letters that
stand side by side in no piece (before spaces, mostly, and at marks), so the
lattices of distinct units are built once for many batches: pieces
are found by walking a trie from all places at the same time, and a backward
pass gives each place the log sum of all ways to the word's end.  With that, the
chance of the next piece is exact.

The sampler is a perturbed A-star search.  A node of the search is a set of
segmentations that share a prefix, and its key is the largest Gumbel-perturbed
log probability in the set, drawn top down: the whole set's key is a Gumbel
variate, a set's best member follows by sampling pieces, and the sets that
branch off its path get Gumbel variates below the parent's key.  The best key
is taken next, so the k best come out in order and never twice.  The key after
the k-th gives inclusion probabilities.  All variates are hashes of the row's
key, hence the same for any partitioning.

The vocabulary is a byte-fallback BPE model, whose scores are only ranks;
piece log probabilities follow Zipf's law over the ranks, divided by a
temperature.  Characters outside the vocabulary are encoded as bytes.

Defined cases: null and empty texts have one segmentation, the empty one; a
text with fewer than k segmentations gives all of them, with inclusion 1; very
long texts are sampled whole; repeated ids draw alike, and a null id draws like
0; extra columns are ignored.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .batches import _MIX_A, _MIX_B, fields, mix, sliced, spark_schema

MODEL = "piece_bpe_32k.model"
SAMPLES = 3
#: The space mark of pieces, and bits of a code point.
MARK, BITS = 0x2581, 21
_ALL = 2**64 - 1
#: Sizes of the tables of transitions and of letters that stand side by side in a piece.
SLOT_BITS, PAIR_BITS = 18, 22
#: Text bytes that are sampled together, and places of lattices that a worker holds.
SLICE, MOST_PLACES = 400_000, 1_600_000

SAMPLED = fields(
    doc_id=pa.int64(), rank=pa.int32(), ids=pa.list_(pa.int32()), n_pieces=pa.int64(), ids_crc32=pa.int64(),
    log_prob=pa.float64(), perturbed=pa.float64(), inclusion=pa.float64(), decodes=pa.bool_(),
)


def _slot(keys: np.ndarray) -> np.ndarray:
    return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - SLOT_BITS)).astype(np.int64)


def _pair(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The bit of two letters side by side; two pairs may share one."""
    return ((a.astype(np.uint32) * np.uint32(0x9E3779B1) + b.astype(np.uint32)) * np.uint32(0x85EBCA77)) >> np.uint32(32 - PAIR_BITS)


def one_uniform(x: int) -> float:
    """``uniform`` of a single number."""
    x &= _ALL
    x = ((x ^ (x >> 32)) * int(_MIX_B)) & _ALL
    x = ((x ^ (x >> 29)) * int(_MIX_A)) & _ALL
    return (((x ^ (x >> 32)) >> 12) + 0.5) / 2.0**52


class Vocabulary:
    """The pieces of a model as a trie of sorted transitions."""

    def __init__(self, path: str | None = None, temperature: float = 1.0):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path or public_tokenizers.path(MODEL))
        n = model.get_piece_size()
        self.pieces = [model.id_to_piece(i) for i in range(n)]
        self.bytes = {int(self.pieces[i][1:-1], 16): i for i in range(n) if model.is_byte(i)}
        self.byte_ids = np.array([self.bytes[b] for b in range(256)])
        normal = [i for i in range(n) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i))]
        harmonic = float((1 / np.arange(1, len(normal) + 1)).sum())
        self.log_prob = np.full(n, -np.inf)
        self.log_prob[normal] = (-np.log(np.arange(1, len(normal) + 1)) - np.log(harmonic)) / temperature
        self.byte_log_prob = float(self.log_prob[normal].min()) - 1 / temperature
        nodes: dict[tuple[int, int], int] = {}
        ends = [-1]
        for i in normal:
            at = 0
            for c in map(ord, self.pieces[i]):
                nxt = nodes.get((at, c))
                if nxt is None:
                    nxt = nodes[(at, c)] = len(ends)
                    ends.append(-1)
                at = nxt
            ends[at] = i
        self.root = np.full(1 << BITS, -1, np.int32)
        for (a, c), node in nodes.items():
            if a == 0:
                self.root[c] = node
        self.ends = np.array(ends, np.int32)
        self._hold(np.array([(a << BITS) | c for a, c in nodes], np.int64), np.array(list(nodes.values()), np.int32))
        self.joined = np.zeros(1 << PAIR_BITS, bool)
        for i in normal:
            letters = np.array(list(map(ord, self.pieces[i])))
            self.joined[_pair(letters[:-1], letters[1:])] = True
        raw = [bytes([int(p[1:-1], 16)]) if model.is_byte(i) else p.replace(chr(MARK), " ").encode() for i, p in enumerate(self.pieces)]
        self.letters = np.frombuffer(b"".join(raw), np.uint8)
        self.sizes = np.array([len(x) for x in raw])
        self.starts = np.cumsum(self.sizes) - self.sizes
        self.lattices: Lattices | None = None

    def _hold(self, keys: np.ndarray, children: np.ndarray) -> None:
        """Transitions in an open hash table: a key lies at its place or behind it."""
        self.slots, self.child = np.full(1 << SLOT_BITS, -1), np.zeros(1 << SLOT_BITS, np.int32)
        at = _slot(keys)
        while len(keys):
            free = np.flatnonzero(self.slots[at] < 0)
            _, first = np.unique(at[free], return_index=True)
            own = free[first]
            self.slots[at[own]], self.child[at[own]] = keys[own], children[own]
            rest = np.ones(len(keys), bool)
            rest[own] = False
            keys, children, at = keys[rest], children[rest], (at[rest] + 1) & (len(self.slots) - 1)

    def steps(self, node: np.ndarray, letter: np.ndarray) -> np.ndarray:
        """The node behind each transition, or -1."""
        key = (node.astype(np.int64) << BITS) | letter
        at = _slot(key)
        held = self.slots[at]
        out = np.where(held == key, self.child[at], -1)
        more = np.flatnonzero((held != key) & (held >= 0))
        while len(more):
            at[more] = (at[more] + 1) & (len(self.slots) - 1)
            held = self.slots[at[more]]
            hit = held == key[more]
            out[more[hit]] = self.child[at[more[hit]]]
            more = more[~hit & (held >= 0)]
        return out

    def spelt(self, ids: np.ndarray) -> bytes:
        """The bytes of piece ids, a space for each mark."""
        sizes = self.sizes[ids]
        stops = np.cumsum(sizes)
        return self.letters[np.repeat(self.starts[ids] - stops + sizes, sizes) + np.arange(stops[-1] if len(stops) else 0)].tobytes()

    def decode(self, ids) -> str:
        """The text of piece ids; the leading space mark is dropped and marks become spaces."""
        text = self.spelt(np.asarray(ids, np.int64)).decode("utf-8", "replace")
        return text[1:] if text[:1] == " " else text


_HELD: dict[tuple, Vocabulary] = {}


def vocabulary(path: str | None = None, temperature: float = 1.0) -> Vocabulary:
    """One vocabulary for each worker process."""
    key = (path, temperature)
    if key not in _HELD:
        _HELD[key] = Vocabulary(path, temperature)
    return _HELD[key]


def uniform(x: np.ndarray) -> np.ndarray:
    """Numbers strictly between 0 and 1 from 64-bit hashes."""
    return ((mix(x) >> np.uint64(12)).astype(float) + 0.5) / 2.0**52


#: Places whose sets are weighed first.
NEAR = 64
#: Bounds of Gumbel variates that ``uniform`` can give.
LEAST, MOST = -3.61, 36.75


def gumbel(u: np.ndarray) -> np.ndarray:
    return -np.log(-np.log(u))


def truncated(key: float, limit: float) -> float:
    """A Gumbel variate cut off at the limit; an empty set stays at minus infinity."""
    low, high = min(key, limit), max(key, limit)
    return -math.inf if low == -math.inf else low - math.log1p(math.exp(low - high))


class Lattices:
    """The lattices of distinct units (words with their space marks), laid end to end.

    Units are added as they come and found again by a 64-bit hash, so a word's
    lattice is built once for many batches.  Every number of a unit depends on
    the unit alone, not on where it lies.
    """

    def __init__(self, vocab: Vocabulary):
        self.vocab, self.places, self.edges = vocab, 0, 0
        self.hashes, self.bases = np.zeros(0, np.uint64), np.zeros(0, np.int32)
        self.points, self.is_end, self.edges_of = np.zeros(0, np.int32), np.zeros(0, bool), np.zeros(1, np.int32)
        self.first, self.past, self.piece = (np.zeros(0, np.int32) for _ in range(3))
        self.log_p, self.log_rest, self.ladder = (np.zeros(0) for _ in range(3))

    def find(self, hashes: np.ndarray, points: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """The first place of each of the distinct units, which are added where they are new; ``hashes`` are sorted."""
        at = np.minimum(np.searchsorted(self.hashes, hashes), max(len(self.hashes) - 1, 0))
        new = np.flatnonzero(self.hashes[at] != hashes) if len(self.hashes) else np.arange(len(hashes))
        out = np.empty(len(hashes), np.int32)
        if len(self.hashes):
            out[:] = self.bases[at]
        if len(new):
            out[new] = self._add(points, starts[new], lengths[new])
            where = np.searchsorted(self.hashes, hashes[new])
            self.hashes, self.bases = np.insert(self.hashes, where, hashes[new]), np.insert(self.bases, where, out[new])
        return out

    def _add(self, points: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        base = np.concatenate([[0], np.cumsum(lengths + 1)])[:-1]
        total = int((lengths + 1).sum())
        inside = np.arange(int(lengths.sum())) - np.repeat(np.cumsum(lengths) - lengths, lengths)
        own = np.zeros(total, np.int32)
        own[np.repeat(base, lengths) + inside] = points[np.repeat(starts, lengths) + inside]
        stop = base + lengths
        is_end = np.zeros(total, bool)
        is_end[stop] = True
        first, past, piece, score = self._find_pieces(own, is_end)
        left = np.repeat(stop, lengths + 1) - np.arange(total)
        past, piece, log_p, edges_of = _weighed(first, past, piece, score, left)
        with np.errstate(divide="ignore"):
            p = np.exp(log_p)
            log_rest = np.where(p < 1 - 1e-12, np.log1p(-np.minimum(p, 1 - 1e-16)), -np.inf)
        places, edges = self.places, self.edges
        self._append("places", points=own, is_end=is_end)
        self.edges_of = _room(self.edges_of, places + 1 + total)
        self.edges_of[places + 1 : places + 1 + total] = edges_of[1:] + edges
        self._append("edges", first=first + places, past=past + places, piece=piece, log_p=log_p, log_rest=log_rest, ladder=_ladder(p, edges_of))
        return (base + places).astype(np.int32)

    def _append(self, count: str, **arrays: np.ndarray) -> None:
        used = getattr(self, count)
        for name, new in arrays.items():
            held = _room(getattr(self, name), used + len(new))
            held[used : used + len(new)] = new
            setattr(self, name, held)
        setattr(self, count, used + len(new))

    def _find_pieces(self, points: np.ndarray, is_end: np.ndarray) -> tuple[np.ndarray, ...]:
        """(first, past, piece, score) of the edges, by place and length."""
        vocab, places = self.vocab, np.flatnonzero(~is_end)
        at, node, first, past, piece = places, np.zeros(len(places), np.int64), [], [], []
        alone = np.zeros(len(points), bool)
        step = 0
        while len(at):
            if step == 0:
                node = vocab.root[points[at]]
                ok = node >= 0
            else:
                node = vocab.steps(node, points[at + step])
                ok = (node >= 0) & ~is_end[at + step]
            at, node = at[ok], node[ok]
            step += 1
            whole = vocab.ends[node] >= 0
            first.append(at[whole])
            past.append(at[whole] + step)
            piece.append(vocab.ends[node[whole]])
            if step == 1:
                alone[at[whole]] = True
        rest = places[~alone[places]]
        first.append(rest)
        past.append(rest + 1)
        piece.append(np.full(len(rest), -1))
        first, past, piece = np.concatenate(first), np.concatenate(past), np.concatenate(piece)
        order = np.argsort(first * 32 + (past - first), kind="stable")
        first, past, piece = first[order], past[order], piece[order]
        score = np.where(piece >= 0, vocab.log_prob[piece], 0.0)
        bare = np.flatnonzero(piece < 0)
        letters = points[first[bare]]
        score[bare] = vocab.byte_log_prob * (1 + (letters > 0x7F) + (letters > 0x7FF) + (letters > 0xFFFF))
        # A character of one byte has its byte's id; longer ones are spelt out where ids are listed.
        piece[bare] = np.where(letters < 0x80, vocab.byte_ids[np.minimum(letters, 0xFF)], -1)
        return first, past, piece, score

    def choose(self, place: np.ndarray, u: np.ndarray) -> np.ndarray:
        """An edge from each place by its chance."""
        edge = self.edges_of[place]
        more = np.flatnonzero(u >= self.ladder[edge])
        while len(more):
            edge[more] += 1
            more = more[u[more] >= self.ladder[edge[more]]]
        return edge

    def walk(self, place: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(edges before each walker and in all, edge) of walks from each place to its unit's end, in order."""
        who, step, whos, edges = np.flatnonzero(~self.is_end[place]), 0, [], []
        counts = np.zeros(len(place), np.int64)
        at, own = place[who], key[who]
        while len(who):
            edge = self.choose(at, uniform(own + np.uint64(0x9E3779B9 * (step + 1))))
            whos.append(who)
            edges.append(edge)
            counts[who] += 1
            at = self.past[edge]
            going = ~self.is_end[at]
            who, at, own, step = who[going], at[going], own[going], step + 1
        before = np.concatenate([[0], np.cumsum(counts)])
        out = np.empty(int(before[-1]), np.int32)
        for i, (w, e) in enumerate(zip(whos, edges, strict=True)):
            out[before[w] + i] = e
        return before, out


def _room(held: np.ndarray, need: int) -> np.ndarray:
    """``held``, in a longer array where it is too short; what is behind its used part has no meaning."""
    if need <= len(held):
        return held
    out = np.zeros(max(need, len(held) + len(held) // 2), held.dtype)
    out[: len(held)] = held
    return out


def _weighed(first: np.ndarray, past: np.ndarray, piece: np.ndarray, score: np.ndarray, left: np.ndarray) -> tuple[np.ndarray, ...]:
    """(past, piece, log chance, edges before each place): the likeliest edge of a place comes first, so a draw rarely looks further."""
    total = np.zeros(len(left))
    far = left[first]
    order = np.argsort(far.astype(np.int16) if far.max(initial=0) < 2**15 else far, kind="stable")
    cuts = np.searchsorted(far[order], np.unique(far))
    # Log sums from each place to its unit's end, the nearest places first.
    for a, b in zip(cuts, np.append(cuts[1:], len(order)), strict=False):
        own = order[a:b]
        start = first[own]
        heads = np.flatnonzero(np.concatenate([[True], start[1:] != start[:-1]]))
        total[start[heads]] = np.logaddexp.reduceat(score[own] + total[past[own]], heads)
    log_p = np.minimum(score + total[past] - total[first], 0.0)
    counts = np.bincount(first, minlength=len(left))
    edges_of = np.concatenate([[0], np.cumsum(counts)])
    heads = edges_of[:-1][counts > 0]
    if len(heads):
        own = np.repeat(np.arange(len(heads)), counts[counts > 0])
        best = np.flatnonzero(log_p == np.maximum.reduceat(log_p, heads)[own])[::-1]
        likeliest = np.empty(len(heads), np.int64)
        likeliest[own[best]] = best
        for values in (past, piece, log_p):
            values[heads], values[likeliest] = values[likeliest], values[heads]
    return past, piece, log_p, edges_of


def _ladder(p: np.ndarray, edges_of: np.ndarray) -> np.ndarray:
    """Running sums of each place's chances, which end at 1."""
    out, counts = p.copy(), np.diff(edges_of)
    heads, counts = edges_of[:-1][counts > 0], counts[counts > 0]
    for rank in range(1, int(counts.max(initial=1))):
        at = heads[counts > rank] + rank
        out[at] += out[at - 1]
    last = heads + counts - 1
    out /= np.repeat(out[last], counts)
    out[last] = 1.0
    return out


def units(points: np.ndarray, off: np.ndarray, vocab: Vocabulary) -> tuple[np.ndarray, np.ndarray]:
    """Starts of units in texts laid end to end, and the units before each text.

    A unit starts at a text and between two letters that stand side by side in
    no piece: no piece reaches over such a place.
    """
    first = np.zeros(len(points), bool)
    if len(points):
        first[0] = True
        np.logical_not(vocab.joined[_pair(points[:-1], points[1:])], out=first[1:])
    own = off[:-1]
    first[own[own < len(points)]] = True
    starts = np.flatnonzero(first)
    return starts, np.searchsorted(starts, off)


class Path:
    """A segmentation that was emitted, and the sets that branch off it.

    Gumbel variates from 53-bit numbers lie between ``LEAST`` and ``MOST``, so
    a set whose log share is behind those of ``k`` others by more than their
    difference never comes before them: such sets get no variate.
    """

    def __init__(self, edges: np.ndarray, lattices: Lattices, key: float, branch: int, seed: np.uint64, k: int):
        self.edges, self.key, self.limit, self.seed = edges, key, key, seed
        self.before = np.zeros(len(edges) + 1)
        np.cumsum(lattices.log_p[edges], out=self.before[1:])
        self.banned: dict[int, list[int]] = {}
        # No set's share is above that of its prefix, and shares of prefixes fall: far ones need no look.
        past, first = len(edges), edges[branch : branch + NEAR]
        near = self.before[branch : branch + len(first)] + lattices.log_rest[first]
        if len(near) > k:
            past = int(np.searchsorted(-self.before[:-1], MOST - LEAST - np.partition(near, len(near) - k)[len(near) - k], "right"))
        mass = self.before[branch:past] + lattices.log_rest[edges[branch:past]]
        if len(mass) > k:
            self.places = branch + np.flatnonzero(mass >= np.partition(mass, len(mass) - k)[len(mass) - k] - (MOST - LEAST))
            mass = mass[self.places - branch]
        else:
            self.places = np.arange(branch, branch + len(mass))
        # Untruncated keys; the truncation at the limit keeps their order.
        self.gumbels = mass + gumbel(uniform(seed ^ mix(self.places.astype(np.uint64) * np.uint64(64) + np.uint64(1))))
        # Sets that lost an edge have limits of their own.
        self.redrawn: dict[int, float] = {}

    @property
    def log_prob(self) -> float:
        return float(self.before[-1])

    def best(self) -> tuple[float, int]:
        """The largest key of the sets and its place; minus infinity where none is left."""
        found = max(((key, place) for place, key in self.redrawn.items()), default=(-np.inf, -1))
        if len(self.gumbels):
            i = int(self.gumbels.argmax())
            if self.gumbels[i] > -np.inf:
                found = max(found, (truncated(float(self.gumbels[i]), self.limit), int(self.places[i])))
        return found

    def ban(self, place: int, lattices: Lattices, edge: int, limit: float) -> None:
        """Takes ``edge`` out of the set at ``place`` and draws the rest's key."""
        out = self.banned.setdefault(place, [int(self.edges[place])])
        out.append(edge)
        gone = sum(math.exp(lattices.log_p[x]) for x in out)
        start = lattices.first[edge]
        left = lattices.edges_of[start + 1] - lattices.edges_of[start]
        rest = -math.inf if left == len(out) or gone >= 1 - 1e-12 else math.log1p(-gone)
        u = one_uniform(int(self.seed) ^ int(mix(np.array([place * 64 + 2 * len(out) + 1], np.uint64))[0]))
        own = float(self.before[place]) + rest - math.log(-math.log(u))
        self.redrawn[place] = truncated(own, limit)
        self.gumbels[self.places == place] = -np.inf


def held_lattices(vocab: Vocabulary) -> Lattices:
    """The worker's lattices of that vocabulary; begun anew where they hold too many places."""
    if vocab.lattices is None or vocab.lattices.places > MOST_PLACES:
        vocab.lattices = Lattices(vocab)
    return vocab.lattices


def _roots(points: np.ndarray, starts: np.ndarray, lattices: Lattices) -> np.ndarray:
    """The first place of each unit's lattice."""
    if not len(starts):
        return np.zeros(0, np.int32)
    lengths = np.diff(np.concatenate([starts, [len(points)]]))
    inside = np.arange(len(points)) - np.repeat(starts, lengths)
    letters = (points.astype(np.uint64) | (inside.astype(np.uint64) << np.uint64(BITS))) * np.uint64(0x9E3779B97F4A7C15)
    letters ^= letters >> np.uint64(29)
    letters *= np.uint64(0xD6E8FEB86659FD93)
    hashes, example, kind = np.unique(np.add.reduceat(letters ^ (letters >> np.uint64(32)), starts), return_index=True, return_inverse=True)
    return lattices.find(hashes, points, starts[example], lengths[example])[kind]


def sample_batch(texts: list[str], row_keys: np.ndarray, vocab: Vocabulary, k: int) -> list[tuple[list[Path], float, Lattices]]:
    """For each text its k best perturbed paths in order, the next key, and the lattices their edges refer to."""
    marked = [chr(MARK) + t.replace(" ", chr(MARK)) if t else "" for t in texts]
    raw = [np.frombuffer(t.encode("utf-32-le", "surrogatepass"), "<u4") for t in marked]
    off = np.concatenate([[0], np.cumsum([len(r) for r in raw])]).astype(np.int64)
    points = np.concatenate(raw).astype(np.int32) if raw else np.zeros(0, np.int32)
    starts, before = units(points, off, vocab)
    lattices = held_lattices(vocab)
    root = _roots(points, starts, lattices)
    unit_row = np.repeat(np.arange(len(texts)), np.diff(before))
    unit_no = (np.arange(len(starts)) - before[unit_row]).astype(np.uint64)
    unit_no = mix(unit_no + np.uint64(1))

    def seed(turn: int) -> np.ndarray:
        return mix(row_keys + np.uint64(0x51ED270B * (turn + 1)))

    rows, seeds = range(len(texts)), seed(0)
    cuts, edge = lattices.walk(root, seeds[unit_row] ^ unit_no)
    top = gumbel(uniform(seeds ^ np.uint64(0xABCDEF)))
    found: list[list[Path]] = [[Path(edge[cuts[before[r]] : cuts[before[r + 1]]], lattices, float(top[r]), 0, seeds[r], k)] for r in rows]
    # Edges of a path before each of its units.
    owner: list[list[np.ndarray]] = [[cuts[before[r] : before[r + 1]] - cuts[before[r]]] for r in rows]
    for turn in range(1, k):
        seeds = seed(turn)
        jobs = []
        for r in rows:
            (limit, place), i = max((p.best(), i) for i, p in enumerate(found[r]))
            if limit == -np.inf:
                continue
            parent = found[r][i]
            start = lattices.first[parent.edges[place]]
            low, high = int(lattices.edges_of[start]), int(lattices.edges_of[start + 1])
            chance = np.exp(lattices.log_p[low:high])
            chance[np.array(parent.banned.get(place, [int(parent.edges[place])])) - low] = 0
            ladder = np.cumsum(chance)
            u = one_uniform(int(seeds[r]) ^ 0x1234567)
            pick = min(int(np.searchsorted(ladder, u * ladder[-1], "right")), high - low - 1)
            pick = low + (pick if chance[pick] else int(chance.argmax()))
            parent.ban(place, lattices, pick, limit)
            unit = int(np.searchsorted(owner[r][i], place, "right")) - 1
            jobs.append((r, i, place, pick, limit, unit))
        if not jobs:
            break
        later = [np.arange(before[r] + unit, before[r + 1]) for r, _, _, _, _, unit in jobs]
        heads = np.concatenate([[0], np.cumsum([len(x) for x in later])])
        walkers = np.concatenate(later)
        at = root[walkers]
        at[heads[:-1]] = lattices.past[[pick for _, _, _, pick, _, _ in jobs]]
        cuts, edge = lattices.walk(at, seeds[unit_row[walkers]] ^ unit_no[walkers])
        for (r, i, place, pick, limit, unit), a, b in zip(jobs, heads[:-1], heads[1:], strict=True):
            parent = found[r][i]
            edges = np.concatenate([parent.edges[:place], np.array([pick], np.int32), edge[cuts[a] : cuts[b]]])
            own = cuts[a:b] - cuts[a] + place + 1
            own[0] = owner[r][i][unit]
            owner[r].append(np.concatenate([owner[r][i][:unit], own]))
            found[r].append(Path(edges, lattices, limit, place + 1, seeds[r], k))
    return [(own, max(p.best()[0] for p in own), lattices) for own in found]


def piece_ids(path: Path, lattices: Lattices, vocab: Vocabulary) -> np.ndarray:
    """The ids of a path; characters outside the vocabulary are their bytes."""
    ids = lattices.piece[path.edges]
    if len(ids) and ids.min() < 0:
        parts = []
        for edge, i in zip(path.edges.tolist(), ids.tolist(), strict=True):
            parts += [i] if i >= 0 else [vocab.bytes[b] for b in chr(lattices.points[lattices.first[edge]]).encode("utf-8", "surrogatepass")]
        ids = np.array(parts)
    return ids.astype("<u4")


def _sampler(k: int, seed: int, path: str | None, temperature: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocab = vocabulary(path, temperature)
        for batch in sliced(batches, "text", SLICE):
            texts = [t or "" for t in batch.column("text").to_pylist()]
            ids = batch.column("doc_id").to_pylist()
            keys = mix(np.array([(i or 0) & (2**64 - 1) for i in ids], np.uint64) ^ mix(np.array([seed], np.uint64))[0])
            out: list[list] = [[] for _ in SAMPLED.names]
            for doc_id, text, (paths, after, lattices) in zip(ids, texts, sample_batch(texts, keys, vocab, k), strict=True):
                plain = b" " + text.encode("utf-8", "surrogatepass") if text else b""
                for rank, p in enumerate(paths, 1):
                    pieces = piece_ids(p, lattices, vocab)
                    inclusion = 1.0 if after == -np.inf else float(-np.expm1(-np.exp(min(p.log_prob - after, 50.0))))
                    row = (doc_id, rank, pieces, len(pieces), zlib.crc32(pieces), p.log_prob, p.key, inclusion, vocab.spelt(pieces) == plain)
                    for column, value in zip(out, row, strict=True):
                        column.append(value)
            at = SAMPLED.get_field_index("ids")
            cuts = np.concatenate([[0], np.cumsum(out[at + 1])]).astype(np.int32)
            flat = np.concatenate(out[at]).astype(np.int32)
            arrays = [pa.array(c, t) if i != at else pa.ListArray.from_arrays(pa.array(cuts), pa.array(flat)) for i, (c, t) in enumerate(zip(out, SAMPLED.types, strict=True))]
            yield pa.RecordBatch.from_arrays(arrays, schema=SAMPLED)

    return run


def sample_encodings(docs: DataFrame, k: int = SAMPLES, seed: int = 17, model: str | None = None, temperature: float = 1.0) -> DataFrame:
    """Up to k distinct segmentations of each text by falling perturbed log probability.

    ``inclusion`` is the chance that a segmentation is among the k, given the
    next key.  ``decodes`` tells that the ids decode to the text.
    """
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_sampler(k, seed, model, temperature), spark_schema(SAMPLED))


def decode_ids(rows: DataFrame, model: str | None = None) -> DataFrame:
    """``doc_id``, ``rank`` and the text of each row's ``ids``."""
    schema = fields(doc_id=pa.int64(), rank=pa.int32(), text=pa.string())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocab = vocabulary(model)
        for batch in batches:
            texts = [vocab.decode(x or []) for x in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("rank"), pa.array(texts, pa.string())], schema=schema)

    return rows.select("doc_id", "rank", "ids").mapInArrow(run, spark_schema(schema))
