"""Quality rules: ordered threshold conjunctions, learned by sequential covering.

A rule rejects.  It grows on two thirds of the labelled rows, condition by
condition, by information gain; conditions are then dropped from its end while
that helps on the other third.  Rows that the rule covers are removed and the
next rule is learned, until a rule is right too seldom.  The list becomes one
Spark conditional expression; applying it needs DataFrame functions only.

Defined cases: no labelled rows, or rows of one class, give an empty list,
which keeps everything; null and empty texts have zero statistics; ties take
the first condition in the order of features and thresholds.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import text_stats

#: Bound of labelled rows that the learner collects.
MOST_LABELLED = 20_000
MOST_RULES = 16
MOST_CONDITIONS = 4
THRESHOLDS = 48
LEAST_PRECISION = 0.6
LEAST_COVERED = 3


@dataclass(frozen=True)
class Condition:
    feature: str
    above: bool
    value: float

    def column(self) -> Column:
        return F.col(self.feature) > self.value if self.above else F.col(self.feature) <= self.value

    def mask(self, rows: np.ndarray, names: list[str]) -> np.ndarray:
        x = rows[:, names.index(self.feature)]
        return x > self.value if self.above else x <= self.value

    def __str__(self) -> str:
        return f"{self.feature} {'>' if self.above else '<='} {self.value:.6g}"


@dataclass(frozen=True)
class Rule:
    conditions: tuple[Condition, ...]
    precision: float

    def column(self) -> Column:
        return reduce(lambda a, b: a & b, (c.column() for c in self.conditions))

    def __str__(self) -> str:
        return " and ".join(map(str, self.conditions))


def _covered(conditions, rows: np.ndarray, names: list[str]) -> np.ndarray:
    held = np.ones(len(rows), bool)
    for c in conditions:
        held &= c.mask(rows, names)
    return held


def _best_condition(rows: np.ndarray, bad: np.ndarray, names: list[str]) -> tuple[float, Condition] | None:
    """The condition of highest gain: bad rows kept times the rise of log precision."""
    p0, n0 = int(bad.sum()), int((~bad).sum())
    if not p0 or not n0:
        return None
    before, best = np.log2(p0 / (p0 + n0)), None
    for j, name in enumerate(names):
        x = rows[:, j]
        cuts = np.unique(np.quantile(x, np.linspace(0, 1, THRESHOLDS + 1)[:-1], method="lower"))
        order = np.argsort(x, kind="stable")
        at = np.searchsorted(x[order], cuts, "right")
        low_bad = np.concatenate([[0], np.cumsum(bad[order])])[at]
        for above in (True, False):
            p = p0 - low_bad if above else low_bad
            n = (len(x) - at) - p if above else at - low_bad
            with np.errstate(divide="ignore", invalid="ignore"):
                gain = np.where(p > 0, p * (np.log2(p / (p + n)) - before), -np.inf)
            k = int(np.argmax(gain))
            if gain[k] > 1e-9 and (best is None or gain[k] > best[0] + 1e-9):
                best = float(gain[k]), Condition(name, above, float(cuts[k]))
    return best


def learn(rows: np.ndarray, bad: np.ndarray, names: list[str]) -> list[Rule]:
    """Ordered rules that reject; ``rows`` are features, ``bad`` marks the class to reject."""
    rows, bad = np.asarray(rows, float).reshape(len(bad), len(names)), np.asarray(bad, bool)
    grow = np.arange(len(bad)) % 3 != 2
    left, rules = np.ones(len(bad), bool), []
    while len(rules) < MOST_RULES and bad[left].any():
        conditions: list[Condition] = []
        held = left & grow
        while len(conditions) < MOST_CONDITIONS and (found := _best_condition(rows[held], bad[held], names)):
            conditions.append(found[1])
            held &= found[1].mask(rows, names)
        check = left & ~grow
        worth = []
        for k in range(1, len(conditions) + 1):
            got = bad[check & _covered(conditions[:k], rows, names)]
            worth.append((2 * got.sum() - len(got)) / len(got) if len(got) else -1.0)
        if not worth:
            break
        conditions = conditions[: int(np.argmax(worth)) + 1]
        covers = left & _covered(conditions, rows, names)
        precision = bad[covers].mean() if covers.any() else 0.0
        if covers.sum() < LEAST_COVERED or precision < LEAST_PRECISION:
            break
        rules.append(Rule(tuple(conditions), float(precision)))
        left &= ~covers
    return rules


def verdict(rules: list[Rule]) -> Column:
    """True where no rule rejects: the rules in order, as one conditional expression."""
    out = None
    for rule in rules:
        out = F.when(rule.column(), False) if out is None else out.when(rule.column(), False)
    return F.lit(True) if out is None else out.otherwise(True)


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", most: int = MOST_LABELLED) -> list[Rule]:
    """Rules from at most ``most`` labelled documents outside fold 0; label 0 is rejected."""
    names = list(text_stats.FEATURES)
    known = text_stats.labelled(docs, labels, label, most, ["text"])
    got = text_stats.with_stats(known).select("doc_id", label, *[c.alias(k) for k, c in text_stats.features().items()]).collect()
    got.sort(key=lambda r: r["doc_id"])
    return learn(np.array([[r[n] for n in names] for r in got], float), np.array([r[label] == 0 for r in got], bool), names)


def apply(docs: DataFrame, rules: list[Rule]) -> DataFrame:
    """doc_id, the statistics, ``base_failed`` and ``kept`` of each document; other columns are ignored."""
    named = {f"__f_{k}": c for k, c in text_stats.features().items()}
    moved = [Rule(tuple(Condition(f"__f_{c.feature}", c.above, c.value) for c in r.conditions), r.precision) for r in rules]
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    out = text_stats.with_stats(docs.select("doc_id", "text")).withColumns(named)
    return out.withColumn("base_failed", failed).withColumn("kept", ~F.col("base_failed") & verdict(moved)).drop("text", *named)
