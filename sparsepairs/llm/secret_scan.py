"""Secret scans: three base patterns, and windows of high Shannon entropy.

Entropy: candidate strings are maximal runs of at least ``WINDOW`` letters,
digits and ``+/_=-``.  A window slides over the candidate; counts of its
characters change by one in and one out, and the entropy follows from them.
Each class of characters (hexadecimal, letters with digits) has its own
threshold.  Windows above it are merged to a span.  An allow list suppresses
placeholders, and spans that a base pattern already covers are not repeated.

Defined cases: null and empty texts have no spans; very long texts are
scanned whole; repeated rows each give a row; extra columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from math import log2

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .batches import fields, sliced, spark_schema, text_bytes, word_spans

#: The base patterns, in the order of their kinds.
ASSIGN = re.compile(rb"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(rb"AKIA[A-Z0-9]+")
ASSIGN_LEAST, ACCESS_LEAST, HEX_LEAST = 6, 20, 24
KINDS = ("assign", "access", "hex", "entropy")

#: Window length, and bits of entropy that a window of each class must reach.
WINDOW = 20
THRESHOLDS = {"hex": 3.0, "mixed": 3.6}

#: Placeholders; a candidate that holds one of them is no secret.
ALLOWED = ("0123456789", "abcdefghij", "1234567890", "xxxxxx", "example", "placeholder", "deadbeef", "changeme")

_HEX = np.zeros(256, bool)
_HEX[np.frombuffer(b"0123456789abcdef", np.uint8)] = True
_CANDIDATE = np.zeros(256, bool)
_CANDIDATE[np.frombuffer(b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-", np.uint8)] = True

SCHEMA = fields(
    doc_id=pa.int64(),
    n_assign=pa.int64(),
    n_access=pa.int64(),
    n_hex=pa.int64(),
    spans=pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("stop", pa.int64()), ("bits", pa.float64())])),
)


def long_runs(raw: np.ndarray, off: np.ndarray, member: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts and stops of maximal runs of ``member`` bytes that are ``least`` long; runs end at rows' ends."""
    starts, stops, _ = word_spans(raw, off, ~member)
    long = stops - starts >= least
    return starts[long], stops[long]


def char_class(word: bytes) -> str | None:
    """``hex``, ``mixed`` (letters with digits) or None: words and numbers carry no secret."""
    digits = sum(48 <= c < 58 for c in word)
    letters = sum(65 <= c < 91 or 97 <= c < 123 for c in word)
    if digits < 3 or letters < 3:
        return None
    return "hex" if re.fullmatch(rb"[0-9a-f]+|[0-9A-F]+", word) else "mixed"


def entropy_spans(word: bytes, window: int = WINDOW, thresholds: dict[str, float] = THRESHOLDS) -> list[tuple[int, int, float]]:
    """(start, stop, bits) of merged windows above their class's threshold, by incremental counts."""
    low = word.lower()
    kind = char_class(word)
    if kind is None or len(word) < window or any(x.encode() in low for x in ALLOWED):
        return []
    need, counts = thresholds[kind], [0] * 256
    terms = [0.0] + [c * log2(c) for c in range(1, window + 1)]
    total, found = 0.0, []
    for i, c in enumerate(word):
        total += terms[counts[c] + 1] - terms[counts[c]]
        counts[c] += 1
        if i >= window:
            out = word[i - window]
            total += terms[counts[out] - 1] - terms[counts[out]]
            counts[out] -= 1
        if i >= window - 1:
            bits = log2(window) - total / window
            if bits >= need - 1e-9:
                start = i - window + 1
                if found and start <= found[-1][1]:
                    found[-1] = (found[-1][0], i + 1, max(bits, found[-1][2]))
                else:
                    found.append((start, i + 1, bits))
    return found


def _runs_by_row(raw: np.ndarray, off: np.ndarray, member: np.ndarray, least: int) -> dict[int, list[tuple[int, int]]]:
    starts, stops = long_runs(raw, off, member, least)
    rows = np.searchsorted(off, starts, "right") - 1
    out: dict[int, list[tuple[int, int]]] = {}
    for r, a, b in zip(rows.tolist(), starts.tolist(), stops.tolist(), strict=True):
        out.setdefault(r, []).append((a - int(off[r]), b - int(off[r])))
    return out


def scan_batch(raw: np.ndarray, off: np.ndarray) -> list[list[tuple[str, int, int, float | None]]]:
    """The spans of each row, by start and then kind, in code points."""
    whole, result = raw.tobytes(), []
    hexes, words = _runs_by_row(raw, off, _HEX, HEX_LEAST), _runs_by_row(raw, off, _CANDIDATE, WINDOW)
    for r in range(len(off) - 1):
        text = whole[off[r] : off[r + 1]]
        found: list[tuple[str, int, int, float | None]] = []
        if b"=" in text or b":" in text:
            found += [("assign", *m.span(), None) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= ASSIGN_LEAST]
        if b"AKIA" in text:
            found += [("access", *m.span(), None) for m in ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_LEAST]
        found += [("hex", a, b, None) for a, b in hexes.get(r, ())]
        base = list(found)
        for a, b in words.get(r, ()):
            for s, e, bits in entropy_spans(text[a:b]):
                if not any(x <= a + s and a + e <= y for _, x, y, _ in base):
                    found.append(("entropy", a + s, a + e, bits))
        if found:
            points = np.cumsum((raw[off[r] : off[r + 1]] & 0xC0) != 0x80)
            place = lambda x: int(points[x - 1]) if x else 0
            found = [(k, place(a), place(b), bits) for k, a, b, bits in found]
            found.sort(key=lambda x: (x[1], KINDS.index(x[0]), x[2]))
        result.append(found)
    return result


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in sliced(batches, "text"):
        spans = scan_batch(*text_bytes(batch.column("text")))
        counts = [pa.array([sum(x[0] == k for x in row) for row in spans], pa.int64()) for k in KINDS[:3]]
        rows = [[{"kind": k, "start": a, "stop": b, "bits": bits} for k, a, b, bits in row] for row in spans]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), *counts, pa.array(rows, SCHEMA.field("spans").type)], schema=SCHEMA)


def scan_secrets(docs: DataFrame) -> DataFrame:
    """A row per document: counts of the base kinds and all spans (code points, end exclusive)."""
    return docs.select("doc_id", "text").mapInArrow(_scan, spark_schema(SCHEMA))


def _mask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in sliced(batches, "text"):
        col, out = batch.column("text"), []
        for text, spans in zip(col.to_pylist(), scan_batch(*text_bytes(col)), strict=True):
            if spans:
                parts, at = [], 0
                for kind, a, b, _ in spans:
                    if b <= at:
                        continue
                    parts += [text[at : max(a, at)], f"<{kind}>" if a >= at else ""]
                    at = b
                text = "".join(parts) + text[at:]
            out.append(text)
        yield batch.set_column(batch.schema.get_field_index("text"), "text", pa.array(out, col.type))


def mask_secrets(docs: DataFrame) -> DataFrame:
    """The documents with every span replaced by its kind in angle brackets; other columns stay."""
    return docs.mapInArrow(_mask, docs.schema)

