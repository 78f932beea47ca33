"""Toxicity: a convolutional text classifier, trained and applied with numpy.

A word's vector is the sum of the hashed embedding rows of the word and of its
prefixes, so inflected forms share what is learned.  Filters of several widths slide
over the words of a whole text, the largest answer of each filter is kept and
a logistic layer gives the score.  Training runs on the driver over a bounded
labelled sample; scoring maps over batches with the filters folded into lookup
tables.  Thresholds are calibrated by language after the score, on labelled rows
that were kept out of training; the score itself sees nothing but the text.

Defined cases: null and empty texts get the score of a text without words;
very long texts are scored whole; without labels of both classes the score is
0.5 less a little for all; repeated rows get equal scores; extra columns stay.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import text_stats
from .batches import fields, mix, sliced, spark_schema, text_bytes, word_hashes, word_spans

BUCKETS = 1 << 18
#: Bytes of the prefixes that have embedding rows beside the word's own.
PREFIXES = (4, 5, 6, 7)
DIMS = 8
WIDTHS = (1, 2, 3)
FILTERS = 8
#: Bound of the labelled rows of the training sample.
MOST_LABELLED = 6_000
EPOCHS = 10
#: One labelled row in so many is kept out of training, for the thresholds.
CALIBRATED = 5
BATCH_WORDS = 30_000
#: Rows of prior evidence when a word's share of toxic texts is estimated.
PRIOR = 15.0
LEAST_POSITIVES = 20

_WORD = np.zeros(256, bool)
_WORD[0x30:0x3A] = _WORD[0x41:0x5B] = _WORD[0x61:0x7B] = True
_WORD[0x80:] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[0x41:0x5B] += 0x20
PAD = BUCKETS


def word_keys(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Embedding rows of the distinct lower-cased words, each word's place among them, and the words before each row."""
    raw = _LOWER[raw]
    starts, ends, before = word_spans(raw, off, ~_WORD)
    _, first, inverse = np.unique(word_hashes(raw, starts, ends), return_index=True, return_inverse=True)
    starts, ends = starts[first], ends[first]
    keys = np.empty((len(first), 1 + len(PREFIXES)), np.int32)
    keys[:, 0] = word_hashes(raw, starts, ends) >> np.uint64(46)
    for j, k in enumerate(PREFIXES, 1):
        own = word_hashes(raw, starts, np.minimum(ends, starts + k)) ^ np.uint64(k)
        keys[:, j] = np.where(ends - starts >= k, mix(own) >> np.uint64(46), PAD)
    return keys, inverse.astype(np.int32), before


@dataclass
class Model:
    """Embedding with a zero row for padding, filters by width, and the logistic layer."""

    embedding: np.ndarray
    filters: dict[int, np.ndarray]
    bias: np.ndarray
    out: np.ndarray
    out_bias: float
    thresholds: dict[str, float] = field(default_factory=dict)
    threshold: float = 0.5

    def tables(self, keys: np.ndarray) -> dict[int, list[np.ndarray]]:
        """For each width, each place's answer to each word; the last row is padding."""
        vectors = np.zeros((len(keys) + 1, DIMS))
        for k in range(keys.shape[1]):
            vectors[:-1] += self.embedding[keys[:, k]]
        return {w: [vectors @ f[j] for j in range(w)] for w, f in self.filters.items()}


def pooled(ids: np.ndarray, before: np.ndarray, tables: dict[int, list[np.ndarray]], step: int = 60_000) -> np.ndarray:
    """The largest answer of every filter for each row; windows reach into zero padding, never into another row."""
    rows, gap = len(before) - 1, max(tables)
    total = len(ids) + gap * rows
    seq = np.full(total + gap, len(tables[gap][0]) - 1, np.int32)
    heads = before[:-1] + gap * np.arange(rows)
    stops = np.append(heads[1:], total)
    if len(ids):
        seq[np.arange(len(ids)) + np.repeat(gap * np.arange(rows), np.diff(before))] = ids
    out = []
    for w, places in tables.items():
        best = np.full((rows, places[0].shape[1]), -np.inf)
        r = 0
        while r < rows:
            # Rows up to about ``step`` words; a longer row is walked in parts.
            stop = max(r + 1, int(np.searchsorted(heads, heads[r] + step, "right")) - 1) if r + 1 < rows else rows
            stop = min(stop, rows)
            low, high = int(heads[r]), int(heads[stop]) if stop < rows else total
            for a in range(low, high, 4 * step):
                b = min(high, a + 4 * step)
                answer = places[0][seq[a:b]]
                for j in range(1, w):
                    answer += places[j][seq[a + j : b + j]]
                    # Windows that start on a row's last places would see the next row.
                    over = stops[r:stop] - j
                    answer[over[(over >= a) & (over < b)] - a] = -np.inf
                if stop == r + 1:
                    np.maximum(best[r], answer.max(0), out=best[r])
                else:
                    best[r:stop] = np.maximum.reduceat(answer, heads[r:stop] - low, axis=0)
            r = stop
        out.append(best)
    return np.concatenate(out, 1)


def scores(model: Model, keys: np.ndarray, ids: np.ndarray, before: np.ndarray) -> np.ndarray:
    """The score of each row of words; ``ids`` are places in ``keys``."""
    hidden = np.maximum(pooled(ids, before, model.tables(keys)) + model.bias, 0)
    return 1 / (1 + np.exp(-np.clip(hidden.astype(np.float64) @ model.out + model.out_bias, -30, 30)))


def _evidence(docs: list[np.ndarray], y: np.ndarray) -> np.ndarray:
    """Shrunk log odds of each bucket by the documents that hold it."""
    share = y.mean()
    bad, seen = np.zeros(BUCKETS), np.zeros(BUCKETS)
    for keys, label in zip(docs, y, strict=True):
        own = np.unique(keys)
        own = own[own < BUCKETS]
        seen[own] += 1
        bad[own] += label
    rate = (bad + PRIOR * share) / (seen + PRIOR)
    return np.log(rate / (1 - rate)) - np.log(share / (1 - share))


def train(docs: list[np.ndarray], labels: np.ndarray, seed: int = 11, epochs: int = EPOCHS) -> Model:
    """Adagrad on the logistic loss; a document is its words' embedding rows, in order.

     Gradients reach only the windows that max pooling kept.

    The first dimension starts from the log odds of words in one half of the
    rows, so the filters, which learn on both halves, can't trust it blindly.
    """
    y = np.asarray(labels, float)
    rng = np.random.default_rng(seed)
    emb = np.zeros((BUCKETS + 1, DIMS), np.float32)
    emb[:BUCKETS, 1:] = rng.normal(0, 0.05, (BUCKETS, DIMS - 1))
    filters = {w: rng.normal(0, 0.15, (w, DIMS, FILTERS)).astype(np.float32) for w in WIDTHS}
    for f in filters.values():
        f[:, 0, : FILTERS // 2] = np.abs(f[:, 0, : FILTERS // 2]) + 0.4 / len(f)
    n_hidden = FILTERS * len(WIDTHS)
    bias, out, out_bias = np.zeros(n_hidden, np.float32), np.full(n_hidden, 0.1), 0.0
    model = Model(emb, filters, bias, out, out_bias)
    if not 0 < y.sum() < len(y):
        model.out[:], model.out_bias = 0, -0.01
        return model
    half = np.arange(len(y)) % 2 == 0
    if not 0 < y[half].sum() < half.sum():
        half[:] = True
    emb[:BUCKETS, 0] = _evidence([d for d, h in zip(docs, half, strict=True) if h], y[half])
    model.out_bias = float(np.log(y.mean() / (1 - y.mean())))
    order = np.argsort([len(d) for d in docs], kind="stable")
    batches, own, longest = [], [], 0
    for i in order:
        longest = max(longest, len(docs[i]))
        if own and (longest * (len(own) + 1) > BATCH_WORDS or len(own) == 64):
            batches.append(own)
            own, longest = [], len(docs[i])
        own.append(i)
    batches.append(own)
    g_emb = np.full(BUCKETS + 1, 1e-2)
    g_f = {w: np.full_like(f, 1e-2) for w, f in filters.items()}
    g_bias, g_out, g_ob = np.full(n_hidden, 1e-2), np.full(n_hidden, 1e-2), 1e-2
    for epoch in range(epochs):
        rate = 0.06 / (1 + 0.4 * epoch)
        for k in rng.permutation(len(batches)):
            rows = batches[k]
            longest = max(WIDTHS) + max(len(docs[i]) for i in rows)
            seq = np.full((len(rows), longest, 1 + len(PREFIXES)), PAD, np.int32)
            for r, i in enumerate(rows):
                seq[r, : len(docs[i])] = docs[i]
            words, best, answers = emb[seq].sum(2), {}, []
            for w, f in filters.items():
                m = longest - w + 1
                a = words[:, :m] @ f[0]
                for j in range(1, w):
                    a += words[:, j : j + m] @ f[j]
                best[w] = a.argmax(1)
                answers.append(np.take_along_axis(a, best[w][:, None, :], 1)[:, 0])
            hidden = np.maximum(np.concatenate(answers, 1) + bias, 0)
            p = 1 / (1 + np.exp(-np.clip(hidden @ model.out + model.out_bias, -30, 30)))
            err = (p - y[rows]) / len(rows)
            d_hidden = err[:, None] * model.out * (hidden > 0)
            d_out = hidden.T @ err + 1e-4 * model.out
            g_out += d_out**2
            model.out -= rate * d_out / np.sqrt(g_out)
            g_ob += err.sum() ** 2
            model.out_bias -= rate * err.sum() / np.sqrt(g_ob)
            d_bias = d_hidden.sum(0)
            g_bias += d_bias**2
            bias -= (rate * d_bias / np.sqrt(g_bias)).astype(np.float32)
            at_rows, at_grads = [], []
            for n, (w, f) in enumerate(filters.items()):
                d = d_hidden[:, n * FILTERS : (n + 1) * FILTERS]
                d_f = np.zeros_like(f)
                for j in range(w):
                    here = seq[np.arange(len(rows))[:, None], best[w] + j]
                    d_f[j] = np.einsum("bfkd,bf->df", emb[here], d)
                    at_rows.append(here.ravel())
                    at_grads.append(np.repeat((d[:, :, None] * f[j].T[None]).reshape(-1, DIMS), here.shape[2], 0))
                g_f[w] += d_f**2
                f -= (rate * d_f / np.sqrt(g_f[w])).astype(np.float32)
            touched, inverse = np.unique(np.concatenate(at_rows), return_inverse=True)
            grad = np.zeros((len(touched), DIMS))
            np.add.at(grad, inverse, np.concatenate(at_grads))
            g_emb[touched] += (grad**2).mean(1)
            emb[touched] -= (0.3 * rate * grad / np.sqrt(g_emb[touched])[:, None]).astype(np.float32)
            emb[PAD] = 0
    return model


def calibrate(model: Model, docs: list[np.ndarray], labels: np.ndarray, langs: list[str | None] | None = None) -> None:
    """Thresholds of fewest errors on rows that the model hasn't learned from, in general and by language.

    Of equal ones the threshold next to 0.5 is taken; with fewer than
    ``LEAST_POSITIVES`` rows of a class it stays as it is.
    """
    y, s = np.asarray(labels, float), np.zeros(len(docs))
    langs = langs or [None] * len(docs)
    for a in range(0, len(docs), 64):
        some = docs[a : a + 64]
        before = np.concatenate([[0], np.cumsum([len(d) for d in some])]).astype(np.int64)
        s[a : a + 64] = scores(model, np.concatenate(some), np.arange(before[-1], dtype=np.int32), before)

    def best(own: np.ndarray) -> float | None:
        if not LEAST_POSITIVES <= y[own].sum() <= own.sum() - LEAST_POSITIVES:
            return None
        grid = np.linspace(0.2, 0.8, 25)
        errors = [((s[own] >= t) != (y[own] == 1)).sum() for t in grid]
        good = grid[np.array(errors) == min(errors)]
        return float(good[np.argmin(np.abs(good - 0.5))])

    model.threshold = best(np.ones(len(y), bool)) or model.threshold
    for lang in sorted({x for x in langs if x is not None}):
        if found := best(np.array([x == lang for x in langs])):
            model.thresholds[lang] = found


def _ids(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in sliced(batches, "text"):
        keys, ids, before = word_keys(*text_bytes(batch.column("text")))
        parts = [keys[ids[a:b]].tobytes() for a, b in zip(before[:-1], before[1:], strict=True)]
        yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), batch.column(1), batch.column(2).cast(pa.int32()), pa.array(parts, pa.binary())], schema=IDS)


IDS = fields(doc_id=pa.int64(), lang=pa.string(), label=pa.int32(), ids=pa.binary())


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", most: int = MOST_LABELLED) -> Model:
    """A model from at most ``most`` labelled documents outside fold 0; one in ``CALIBRATED`` sets thresholds and isn't learned from."""
    lang = F.col("lang").cast("string") if "lang" in docs.columns else F.lit(None).cast("string")
    known = text_stats.labelled(docs.select("doc_id", "text", lang.alias("lang")), labels, label, most, ["text", "lang"])
    rows = known.select("doc_id", "lang", F.col(label).alias("label"), "text").mapInArrow(_ids, spark_schema(IDS)).collect()
    rows.sort(key=lambda r: (r["doc_id"], bytes(r["ids"])))
    keys = [np.frombuffer(r["ids"], np.int32).reshape(-1, 1 + len(PREFIXES)) for r in rows]
    y, langs = np.array([r["label"] for r in rows], float), [r["lang"] for r in rows]
    kept = [np.flatnonzero((np.arange(len(rows)) % CALIBRATED == CALIBRATED - 1) == held) for held in (False, True)]
    model = train([keys[i] for i in kept[0]], y[kept[0]])
    calibrate(model, [keys[i] for i in kept[1]], y[kept[1]], [langs[i] for i in kept[1]])
    return model


def score(docs: DataFrame, model: Model, out: str = "score") -> DataFrame:
    """``docs`` with the score of each whole text in ``out``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = shared.value
        for batch in sliced(batches, "text"):
            got = scores(held, *word_keys(*text_bytes(batch.column("text"))))
            at = batch.schema.get_field_index(out)
            kept = batch if at < 0 else batch.remove_column(at)
            yield kept.append_column(out, pa.array(got))

    from pyspark.sql.types import DoubleType, StructField, StructType

    schema = StructType([f for f in docs.schema.fields if f.name != out] + [StructField(out, DoubleType())])
    return docs.mapInArrow(run, schema)


def threshold(model: Model, lang: str = "lang") -> Column:
    """The calibrated threshold of a row's language, or the general one."""
    out = F.lit(model.threshold)
    for name, value in model.thresholds.items():
        out = F.when(F.col(lang) == name, value).otherwise(out)
    return out
