"""License scans: phrase places, and a fuzzy search for short notices.

Fuzzy search: a notice of length m with at most e edits is cut into e + 1
parts.  One of them must stand in the text unchanged (pigeonhole), so an
Aho-Corasick pass over those exact seeds finds every candidate.  Each word
start from which the seed can be reached is then verified against every word
end within reach by the bounded-error matching of the ``regex`` library, whose
best match of that whole span gives its edits.

Defined cases: null and empty texts give no places, null first and last word,
empty labels and score 0; very long texts are scanned whole; repeated rows and
repeated ids each give a row; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .batches import fields, row_of, sliced, spark_schema, text_bytes, word_hashes, word_spans

#: Phrases of words and the label that each stands for.
PHRASES = {
    "gnu general public license": "gpl",
    "apache license": "apache",
    "cc by": "cc-by",
    "mit license": "mit",
}

#: Short notices of the fuzzy search, with their labels.
NOTICES = {
    "licensed under the gnu general public license": "gpl",
    "gnu lesser general public license": "lgpl",
    "licensed under the apache license version 2 0": "apache",
    "released under the mit license": "mit",
    "permission is hereby granted free of charge": "mit",
    "redistribution and use in source and binary forms": "bsd",
    "licensed under cc by": "cc-by",
    "licensed under cc by nc": "cc-by-nc",
    "creative commons attribution": "cc-by",
    "mozilla public license": "mpl",
    "eclipse public license": "epl",
    "dedicated to the public domain": "public-domain",
    "all rights reserved": "all-rights-reserved",
}

#: Letters of a notice for each edit that is allowed.
LETTERS_PER_EDIT = 10

_WORD = np.zeros(256, bool)
_WORD[0x30:0x3A] = _WORD[0x41:0x5B] = _WORD[0x61:0x7B] = True
_WORD[0x80:] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[0x41:0x5B] += 0x20

SCHEMA = fields(
    doc_id=pa.int64(),
    n_words=pa.int64(),
    n_base=pa.int64(),
    first_word=pa.int64(),
    last_word=pa.int64(),
    base_labels=pa.list_(pa.string()),
    notices=pa.list_(pa.struct([("label", pa.string()), ("start", pa.int64()), ("stop", pa.int64()), ("edits", pa.int32()), ("score", pa.float64())])),
)


@dataclass(frozen=True)
class Notice:
    """A notice, its label, its bound of edits and its exact seeds with their places."""

    text: str
    label: str
    edits: int

    @property
    def seeds(self) -> list[tuple[str, int]]:
        cuts = np.linspace(0, len(self.text), self.edits + 2).astype(int)
        return [(self.text[a:b], int(a)) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]


def compile_notices(notices: dict[str, str], letters_per_edit: int = LETTERS_PER_EDIT):
    """The automaton of all seeds, and each notice with the pattern of its best match within its bound."""
    import ahocorasick
    import regex

    machine, held, checks = ahocorasick.Automaton(), {}, []
    for text, label in notices.items():
        notice = Notice(text, label, max(1, len(text) // letters_per_edit))
        checks.append((notice, regex.compile(f"(?b)(?:{regex.escape(text)}){{e<={notice.edits}}}")))
        for seed, at in notice.seeds:
            held.setdefault(seed, []).append((len(checks) - 1, at))
    for seed, owners in held.items():
        machine.add_word(seed, (len(seed), owners))
    machine.make_automaton()
    return machine, checks


def word_stops(plain: str, start: int, notice: Notice, pattern) -> list[tuple[int, int]]:
    """Each word end up to which the text from ``start`` is the notice within its bound, and the least edits."""
    shortest, longest = (start + len(notice.text) + x for x in (-notice.edits, notice.edits))
    out = []
    for stop in range(max(start + 1, shortest), min(len(plain), longest) + 1):
        if plain[stop - 1] != " " and (stop == len(plain) or plain[stop] == " "):
            match = pattern.fullmatch(plain, start, stop)
            if match:
                out.append((stop, sum(match.fuzzy_counts)))
    return out


def apart(spans: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """(start, stop, edits) that don't overlap: fewest edits first, then the leftmost, then the longest."""
    taken: list[tuple[int, int, int]] = []
    for span in sorted(spans, key=lambda x: (x[2], x[0], -x[1])):
        at = bisect_left(taken, span)
        if (at == 0 or taken[at - 1][1] <= span[0]) and (at == len(taken) or span[1] <= taken[at][0]):
            taken.insert(at, span)
    return taken


def fuzzy_places(plain: str, machine, checks) -> list[tuple[Notice, int, int, int]]:
    """Verified (notice, start, stop, edits) in a plain text: lower case, one space between words.

    Every whole-word span within a notice's bound is among them or overlaps one
    of the same notice with no more edits.
    """
    starts: dict[int, set[int]] = {}
    for last, (size, owners) in machine.iter(plain):
        for which, at in owners:
            middle, edits = last - size + 1 - at, checks[which][0].edits
            near = range(max(0, middle - edits), min(len(plain), middle + edits + 1))
            starts.setdefault(which, set()).update(x for x in near if plain[x] != " " and (x == 0 or plain[x - 1] == " "))
    found = []
    for which, own in starts.items():
        spans = [(x, stop, edits) for x in own for stop, edits in word_stops(plain, x, *checks[which])]
        found += [(checks[which][0], *span) for span in apart(spans)]
    return sorted(found, key=lambda x: (x[1], x[2], x[0].label))


def _scanner(phrases: dict[str, str], notices: dict[str, str]):
    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine, checks = compile_notices(notices)
        wanted = []
        for phrase, label in phrases.items():
            raw = np.frombuffer(phrase.encode(), np.uint8)
            starts, ends, _ = word_spans(raw, np.array([0, len(raw)]), ~_WORD)
            wanted.append((word_hashes(raw, starts, ends), label))
        for batch in sliced(batches, "text"):
            raw, off = text_bytes(batch.column("text"))
            raw = _LOWER[raw]
            starts, ends, before = word_spans(raw, off, ~_WORD)
            hashes, rows = word_hashes(raw, starts, ends), row_of(before)
            n = batch.num_rows
            n_base, labels = np.zeros(n, np.int64), [set() for _ in range(n)]
            first, last = np.full(n, np.iinfo(np.int64).max), np.full(n, -1)
            for want, label in wanted:
                m = len(hashes) - len(want) + 1
                if m <= 0:
                    continue
                hit = rows[:m] == rows[len(want) - 1 :]
                for j, w in enumerate(want):
                    hit &= hashes[j : j + m] == w
                at = np.flatnonzero(hit)
                own = rows[at]
                np.add.at(n_base, own, 1)
                np.minimum.at(first, own, at - before[own])
                np.maximum.at(last, own, at - before[own])
                for r in np.unique(own):
                    labels[r].add(label)
            # One space for every run of other bytes; letters are code points.
            keep = _WORD[raw]
            gap = np.zeros(len(raw), bool)
            gap[ends[:-1][rows[1:] == rows[:-1]]] = True
            held = np.flatnonzero(keep | gap)
            plain_bytes = np.where(keep[held], raw[held], np.uint8(0x20))
            cuts = np.searchsorted(held, off)
            notes = []
            for r in range(n):
                places = []
                if cuts[r + 1] > cuts[r]:
                    own = plain_bytes[cuts[r] : cuts[r + 1]]
                    letters = np.append(np.flatnonzero((own & 0xC0) != 0x80), len(own))
                    for notice, a, b, edits in fuzzy_places(own.tobytes().decode("utf-8", "replace"), machine, checks):
                        span = held[cuts[r] + letters[a]], held[cuts[r] + letters[b] - 1] + 1
                        begin, stop = (int(np.count_nonzero((raw[off[r] : x] & 0xC0) != 0x80)) for x in span)
                        places.append({"label": notice.label, "start": begin, "stop": stop, "edits": edits, "score": max(0.0, 1 - edits / len(notice.text))})
                notes.append(places)
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id").cast(pa.int64()),
                    pa.array(np.diff(before)),
                    pa.array(n_base),
                    pa.array(first, mask=n_base == 0),
                    pa.array(last, mask=n_base == 0),
                    pa.array([sorted(x) for x in labels], pa.list_(pa.string())),
                    pa.array(notes, SCHEMA.field("notices").type),
                ],
                schema=SCHEMA,
            )

    return scan


def scan_licenses(docs: DataFrame, phrases: dict[str, str] = PHRASES, notices: dict[str, str] = NOTICES) -> DataFrame:
    """A row per document: words, phrase places, and the spans of fuzzy notices (code points)."""
    return docs.select("doc_id", "text").mapInArrow(_scanner(phrases, notices), spark_schema(SCHEMA))
