"""Uses of the estimate: allocation, orders of products, supports, join advice."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .estimate import Spec, estimate_size
from .relations import Rel, self_rel


def size_of(rel: Rel, spec: Spec) -> float:
    """The point estimate; an unfilled set counts and divides by p."""
    row = estimate_size(rel, spec).first()
    return float(row["z_hat"] or 0.0)


def allocate(rel: Rel, bytes_per_pair: int, spec: Spec) -> DataFrame:
    """z_hat and the bytes to set aside: the upper end of the interval."""
    row = estimate_size(rel, spec)
    return row.select("z_hat", "status", F.ceil(F.coalesce("hi", "z_hat") * bytes_per_pair).cast("long").alias("bytes"))


def order_chain(names: list[str], sizes: dict[tuple[int, int], float]) -> tuple[str, float]:
    """The cheapest bracketing of a chain of products; ``sizes[i, j]`` is the size of the product of i..j.

    Sizes of two factors may come from the estimator.  Longer products are open
    for it: give sizes from the chain baseline or from a stepwise result.
    """
    n = len(names)
    best: dict[tuple[int, int], tuple[float, str]] = {(i, i): (0.0, names[i]) for i in range(n)}
    for width in range(2, n + 1):
        for i in range(n - width + 1):
            j = i + width - 1
            options = []
            for m in range(i, j):
                cost = best[i, m][0] + best[m + 1, j][0] + (sizes[i, m] if m > i else 0.0) + (sizes[m + 1, j] if j > m + 1 else 0.0)
                options.append((cost, f"({best[i, m][1]}{best[m + 1, j][1]})"))
            best[i, j] = min(options)
    cost, text = best[0, n - 1]
    return text, cost


def choose_support(baskets: DataFrame, item: str, basket: str, supports: list[int], budget: float, spec: Spec) -> tuple[int | None, list[tuple[int, float]]]:
    """The smallest support whose frequent items make at most ``budget`` pairs, and the estimates seen."""
    rows = baskets.select(item, basket).distinct()
    counts = rows.groupBy(item).agg(F.count("*").alias("support"))
    seen = []
    for s in sorted(supports):
        frequent = rows.join(counts.where(F.col("support") >= s).select(item), item, "left_semi")
        z = size_of(self_rel(frequent, item, basket, dedup=False), spec)
        seen.append((s, z))
        if z <= budget:
            return s, seen
    return None, seen


@dataclass(frozen=True)
class Advice:
    strategy: str
    partitions: int
    z_hat: float


def advise_join(z_hat: float, joined: float, bytes_per_pair: int = 16, broadcast_bytes: int = 10_000_000, partition_bytes: int = 128_000_000) -> Advice:
    """Broadcast a small result, project early where joined rows far exceed it, else shuffle; partitions by bytes."""
    size = z_hat * bytes_per_pair
    partitions = max(1, -(-int(size) // partition_bytes))
    if size <= broadcast_bytes:
        return Advice("broadcast", partitions, z_hat)
    return Advice("early_distinct" if joined > 2 * z_hat else "shuffle", partitions, z_hat)
