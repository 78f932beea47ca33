"""Accuracy and cost measures over runs, results and relations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import FAMILIES
from .estimate import Spec, as_threshold, cells_for, hashed, probes, run_hits
from .relations import Rel, work
from .scan import scan_hits


def with_ratio(runs: DataFrame, z: float) -> DataFrame:
    """Runs with ``ratio`` of estimate to exact size."""
    return runs.withColumn("ratio", F.col("z_hat") / F.lit(float(z)))


def ratio_cdf(runs: DataFrame) -> DataFrame:
    """(ratio, cdf): the empirical distribution."""
    return runs.where(F.col("ratio").isNotNull()).select("ratio", F.cume_dist().over(Window.orderBy("ratio")).alias("cdf"))


def two_thirds_error(runs: DataFrame) -> DataFrame:
    """The smallest error that holds in two of three runs that gave an estimate."""
    ranked = runs.where(F.col("ratio").isNotNull()).select(F.abs(F.col("ratio") - 1).alias("error"))
    ranked = ranked.select("error", F.row_number().over(Window.orderBy("error")).alias("i"), F.count("*").over(Window.partitionBy()).alias("n"))
    return ranked.where(F.col("i") * 3 >= 2 * F.col("n")).agg(F.min("error").alias("error"))


def success_share(runs: DataFrame, eps: float) -> DataFrame:
    return runs.agg(F.avg((F.abs(F.coalesce("ratio", F.lit(0.0)) - 1) <= eps).cast("int")).alias("share"))


def empty_share(runs: DataFrame) -> DataFrame:
    return runs.agg(F.avg((F.col("kept") == 0).cast("int")).alias("share"))


def mean_ratio(runs: DataFrame) -> DataFrame:
    """Mean of ratios with empty runs as 0: the bias of a sample estimator shows here."""
    return runs.agg(F.avg(F.coalesce("ratio", F.lit(0.0))).alias("mean_ratio"))


def failure_split(runs: DataFrame, eps: float, k: int) -> DataFrame:
    """Shares of runs over, under, and unfilled."""
    full = F.col("kept") >= k
    part = lambda c: F.avg(c.cast("int"))
    return runs.agg(part(full & (F.col("ratio") > 1 + eps)).alias("over"), part(full & (F.col("ratio") < 1 - eps)).alias("under"), part(~full).alias("unfilled"))


def degree_squares(pairs: DataFrame) -> DataFrame:
    """One row: z, n_a, n_c, and sums of squared row and column degrees of distinct (lk, rk)."""
    rows = pairs.groupBy("lk").agg(F.count("*").alias("d")).agg(F.sum(F.col("d") * F.col("d")).alias("row_squares"), F.count("*").alias("n_a"), F.sum("d").alias("z"))
    cols = pairs.groupBy("rk").agg(F.count("*").alias("d")).agg(F.sum(F.col("d") * F.col("d")).alias("col_squares"), F.count("*").alias("n_c"))
    return rows.crossJoin(cols).select("z", "n_a", "n_c", "row_squares", "col_squares")


def work_profile(rel: Rel, spec: Spec, p: float) -> DataFrame:
    """One row: n, joined, hits and probes of the cell join at ``p``."""
    left, right = hashed(rel, spec, spec.seed)
    found = probes(left, right, spec, p)
    family = FAMILIES[spec.family]
    hit = family.pair(F.col("x_h"), F.col("y_h")) < F.lit(min(as_threshold(p, family.domain), 2**63 - 1))
    seen = found.agg(F.count("*").alias("probes"), F.coalesce(F.sum(hit.cast("long")), F.lit(0)).alias("hits"))
    sizes = rel.left.agg(F.count("*").alias("n1")).crossJoin(rel.right.agg(F.count("*").alias("n2")))
    return seen.crossJoin(sizes).crossJoin(work(rel).select("joined"))


def scan_counters(rel: Rel, spec: Spec, p: float, partitions: int = 1) -> DataFrame:
    """Per task of the forward scan: rows, moves of the start cursor, visited pairs, buffer inserts and selections, first and last threshold."""
    domain = FAMILIES[spec.family].domain
    return scan_hits(*hashed(rel, spec, spec.seed), spec.family, as_threshold(p, domain), *cells_for(p, domain), spec.k, counters=True, partitions=partitions)


def thresholds(runs: DataFrame, k: int, domain: int, first: float = 1.0) -> DataFrame:
    """(run, first_p, last_p): where each run began and where its kept set ended; unfilled runs end as they began."""
    last = F.when(F.col("kept") >= k, F.col("kth_hash").cast("double") / float(domain)).otherwise(F.lit(first))
    return runs.select("run", F.lit(first).alias("first_p"), last.alias("last_p"))


def io_profile(spark, action) -> dict[str, int]:
    """Bytes read, and shuffled both ways, by all executors while ``action()`` runs."""
    def totals() -> list[int]:
        found = spark.sparkContext._jsc.sc().statusStore().executorList(False)
        each = [found.apply(i) for i in range(found.size())]
        return [sum(getattr(e, name)() for e in each) for name in ("totalInputBytes", "totalShuffleRead", "totalShuffleWrite")]

    start = totals()
    action()
    return dict(zip(("input", "shuffle_read", "shuffle_write"), (b - a for a, b in zip(start, totals(), strict=True)), strict=True))


def hits_per_run(rel: Rel, p: float, runs: range) -> DataFrame:
    """(run, hits, distinct): repeats of a pair counted, and not."""
    found = run_hits(rel, Spec(family="md5_60"), p, runs)
    return found.groupBy("run").agg(F.count("*").alias("hits"), F.count_distinct("x_h", "y_h").alias("distinct"))
