"""Quality classifier: Bradley-Terry scores from preference pairs.

Every labelled good document is preferred to every labelled bad one.  The
weights minimise the logistic loss of the feature differences over pairs, in
which every labelled row meets ``OPPONENTS`` of the other class, with a ridge.  A score quantile of the training rows is the threshold;
the published score is a logistic curve that takes ``CUT`` there.

Defined cases: no pair (one class only) gives the score 0.5 to all; null and
empty texts have zero statistics and get a score like any other; repeated rows
get equal scores; extra columns stay out of the score.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import text_stats

#: Bound of the labelled rows that are collected, and the rows of the other class that each one meets.
MOST_LABELLED = 20_000
OPPONENTS = 4
#: The published score at the threshold.
CUT = 0.3
KNOT_QUANTILES = (0.5, 0.8, 0.9, 0.95)


@dataclass(frozen=True)
class Scorer:
    """Weights of hinges (feature, knot or None for the feature itself), threshold and steepness."""

    hinges: tuple[tuple[str, float | None], ...]
    weights: tuple[float, ...]
    threshold: float
    steepness: float

    def raw(self) -> Column:
        total = F.lit(0.0)
        for (name, knot), w in zip(self.hinges, self.weights, strict=True):
            x = F.col(name) if knot is None else F.greatest(F.col(name) - knot, F.lit(0.0))
            total = total + w * x
        return total

    def score(self) -> Column:
        if not self.hinges:
            return F.lit(0.5)
        at = self.steepness * (self.raw() - self.threshold) + float(np.log(CUT / (1 - CUT)))
        at = F.greatest(F.lit(-30.0), F.least(F.lit(30.0), at))
        return 1 / (1 + F.exp(-at))


def _expand(rows: np.ndarray, names: list[str]) -> tuple[np.ndarray, list[tuple[str, float | None]]]:
    cols, hinges = [], []
    for j, name in enumerate(names):
        cols.append(rows[:, j])
        hinges.append((name, None))
        for knot in np.unique(np.round(np.quantile(rows[:, j], KNOT_QUANTILES), 6)):
            cols.append(np.maximum(rows[:, j] - knot, 0))
            hinges.append((name, float(knot)))
    return np.stack(cols, 1), hinges


def train(rows: np.ndarray, good: np.ndarray, names: list[str], seed: int = 7, ridge: float = 1e-3, steps: int = 25) -> Scorer:
    """Newton steps on the pairwise logistic loss, then threshold and steepness."""
    good = np.asarray(good, bool)
    win, lose = np.flatnonzero(good), np.flatnonzero(~good)
    if not len(win) or not len(lose):
        return Scorer((), (), 0.0, 1.0)
    x, hinges = _expand(np.asarray(rows, float), names)
    scale = x.std(0)
    scale[scale < 1e-9] = 1.0
    z = (x - x.mean(0)) / scale
    rng = np.random.default_rng(seed)
    pairs = OPPONENTS * len(z)
    better = np.concatenate([np.repeat(win, OPPONENTS), rng.choice(win, OPPONENTS * len(lose))])
    worse = np.concatenate([rng.choice(lose, OPPONENTS * len(win)), np.repeat(lose, OPPONENTS)])
    d = z[better] - z[worse]
    w = np.zeros(z.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(np.clip(d @ w, -30, 30)))
        grad = -(d.T @ p) / pairs + ridge * w
        curve = (d.T * (p * (1 - p))) @ d / pairs + (ridge + 1e-6) * np.eye(len(w))
        step = np.linalg.solve(curve, grad)
        w -= step * min(1.0, 5.0 / (np.abs(step).max() + 1e-12))
        if np.abs(step).max() < 1e-6:
            break
    s = z @ w
    # The quantile with fewest errors; of equal ones the lowest, which rejects least.
    order = np.argsort(s, kind="stable")
    right = np.concatenate([[0], np.cumsum(np.where(good[order], -1, 1))])
    k = int(np.argmax(right))
    t = s[order][0] - 1.0 if k == 0 else (s[order][k - 1] + s[order][min(k, len(s) - 1)]) / 2
    spread = max(float(np.std(s)), 1e-9)
    raw_w = w / scale
    return Scorer(tuple(hinges), tuple(map(float, raw_w)), float(t + x.mean(0) @ raw_w), 2.0 / spread)


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", most: int = MOST_LABELLED) -> Scorer:
    """A scorer from at most ``most`` labelled documents outside fold 0."""
    names = list(text_stats.FEATURES)
    known = text_stats.labelled(docs, labels, label, most, ["text"])
    got = text_stats.with_stats(known).select("doc_id", label, *[c.alias(k) for k, c in text_stats.features().items()]).collect()
    got.sort(key=lambda r: r["doc_id"])
    return train(np.array([[r[n] for n in names] for r in got], float).reshape(-1, len(names)), np.array([r[label] == 1 for r in got], bool), names)


def score(docs: DataFrame, scorer: Scorer, out: str = "score") -> DataFrame:
    """``docs`` with the score of each whole text in ``out``; its other columns stay as they are."""
    own = docs.columns
    kept = docs.select(F.struct(*[F.col(f"`{c}`") for c in own]).alias("__row"), F.col("text"))
    named = {f"__f_{k}": c for k, c in text_stats.features().items()}
    moved = Scorer(tuple((f"__f_{n}", k) for n, k in scorer.hinges), scorer.weights, scorer.threshold, scorer.steepness)
    scored = text_stats.with_stats(kept).withColumns(named).select("__row", moved.score().alias(out))
    return scored.select(*[F.col("__row")[c].alias(c) for c in own if c != out], out)
