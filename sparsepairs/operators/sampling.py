"""Independent samples of two relations as sketches of the result size.

A side keeps the tuples whose kept value hashes below its rate.  Sides use
seeds of their own, and none is a seed of the pair hash: values of a sample
have small sampling hashes, which would crowd the pair hash.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import FAMILIES, drawn_table
from ..sources.sketches import scratch
from .estimate import ESTIMATE, Spec, choose_threshold, finish, kept_set
from .relations import Rel, drop_dangling


def sample_threshold(p: float, family: str) -> int:
    return int(round(p * float(FAMILIES[family].domain)))


def sample_side(df: DataFrame, role: str, p: float, seed: str, family: str = "mix63", mode: str = "hash") -> DataFrame:
    """Tuples of one side whose kept value is in the sample.

    With ``table`` values are chosen by random bits that are drawn once,
    stored in the shared folder and joined, whatever task reads them.
    """
    if not 0 < p <= 1:
        raise ValueError("a rate lies in (0, 1]")
    if mode == "table":
        drawn = drawn_table(df, role, seed, scratch(df.sparkSession, "drawn"))
        return table_sample(df, role, p, drawn)
    if p >= 1:
        return df
    return df.where(FAMILIES[family].hash(F.col(role), seed) < sample_threshold(p, family))


def table_sample(df: DataFrame, role: str, p: float, drawn: DataFrame) -> DataFrame:
    """Tuples whose kept value has stored bits below the rate; a null value is a value."""
    chosen = drawn.where(F.col("bits") < sample_threshold(p, "md5_60")).select(F.col(role).alias("__value"))
    return df.join(chosen, F.col(role).eqNullSafe(F.col("__value")), "left_semi")


def sampled(rel: Rel, p1: float, p2: float, run: int = 1, family: str = "mix63", mode: str = "hash") -> Rel:
    """Both sides' samples under the run's sampling seeds."""
    return Rel(sample_side(rel.left, "lk", p1, f"SL{run}:", family, mode), sample_side(rel.right, "rk", p2, f"SR{run}:", family, mode))


def rates_for(s: float, n1: float, n2: float) -> tuple[float, float]:
    """Rates that keep about ``s`` tuples of each side."""
    return min(1.0, s / n1), min(1.0, s / n2)


def sample_estimate(rel: Rel, p1: float, p2: float, inner: str = "exact", spec: Spec = Spec(), run: int = 1, mode: str = "hash") -> DataFrame:
    """An ESTIMATE row: the samples' result size over both rates; status ``empty`` and a null where no pair is left."""
    rel = sampled(rel, p1, p2, run, spec.family, mode)
    if inner == "bottomk":
        rel = drop_dangling(rel)
        p = choose_threshold(rel, spec)
        return finish(kept_set(rel, spec, p, run), spec, p, run, 1 / (p1 * p2), (p1, p2))
    pairs = rel.left.join(rel.right, "jk").select("lk", "rk").distinct().agg(F.count("*").alias("kept"))
    empty = F.col("kept") == 0
    row = pairs.select(
        F.lit(run).cast("int").alias("run"), F.lit(None).cast("int").alias("k"), F.lit("exact").alias("policy"), F.lit(1.0).alias("p"),
        F.lit(None).cast("long").alias("threshold"), F.lit(False).alias("filled"), "kept", F.lit(None).cast("long").alias("kth_hash"),
        F.when(~empty, F.col("kept") / (p1 * p2)).alias("z_hat"), F.lit(None).cast("double").alias("lo"), F.lit(None).cast("double").alias("hi"),
        F.when(empty, "empty").otherwise("estimate").alias("status"),
    )
    return row.select(*[x.split()[0] for x in ESTIMATE.split(", ")])


@dataclass
class SketchStore:
    """Samples kept as Parquet under (relation, role, seed, p), each with the size of what it came from."""

    spark: SparkSession
    path: str

    def put(self, relation: str, role: str, df: DataFrame, p: float, seed: str, family: str = "mix63") -> None:
        own = sample_side(df, role, p, seed, family)
        tagged = own.withColumns({"relation": F.lit(relation), "role": F.lit(role), "seed": F.lit(seed), "p": F.lit(str(p))})
        tagged.write.mode("append").partitionBy("relation", "role", "seed", "p").parquet(self.path)

    def get(self, relation: str, role: str, seed: str, p: float) -> DataFrame:
        names = ("lk", "jk") if role == "lk" else ("jk", "rk")
        found = self.spark.read.option("mergeSchema", "true").parquet(self.path).where((F.col("relation") == relation) & (F.col("role") == role) & (F.col("seed") == seed) & (F.col("p").cast("double") == p))
        return found.select(*names)

    def list(self) -> DataFrame:
        """relation, role, seed, p and the tuples kept."""
        return self.spark.read.option("mergeSchema", "true").parquet(self.path).groupBy("relation", "role", F.col("seed").cast("string").alias("seed"), F.col("p").cast("double").alias("p")).agg(F.count("*").alias("n_kept"))


def thin(sketch: DataFrame, role: str, p_new: float, seed: str, family: str = "mix63") -> DataFrame:
    """A smaller sample from a stored one: the same hash, a lower threshold, no new scan."""
    return sample_side(sketch, role, p_new, seed, family)


def maintain(sketch: DataFrame, role: str, p: float, seed: str, inserts: DataFrame | None = None, deletes: DataFrame | None = None, family: str = "mix63") -> DataFrame:
    """The sample after inserts and deletes of distinct tuples; only the changes are hashed."""
    out = sketch
    if inserts is not None:
        out = out.unionByName(sample_side(inserts, role, p, seed, family)).distinct()
    if deletes is not None:
        gone = sample_side(deletes, role, p, seed, family)
        out = out.join(gone, [out[c].eqNullSafe(gone[c]) for c in out.columns], "left_anti")
    return out


def fingerprint_sketch(rel: Rel) -> DataFrame:
    """The trivial sketch: fingerprints of all tuples of both sides."""
    return rel.left.select(F.lit("left").alias("side"), F.xxhash64("lk", "jk").alias("fingerprint")).unionByName(
        rel.right.select(F.lit("right").alias("side"), F.xxhash64("jk", "rk").alias("fingerprint"))
    )


def median_of_samples(rel: Rel, p1: float, p2: float, runs: int, spec: Spec = Spec()) -> DataFrame:
    """The median of repeated exact sample estimates; runs without a pair count as 0."""
    found = sample_runs(rel, p1, p2, range(1, runs + 1), spec.family)
    return found.agg(F.count("*").alias("runs"), F.median(F.coalesce("z_hat", F.lit(0.0))).alias("z_hat"))


def sample_runs(rel: Rel, p1: float, p2: float, runs: range, family: str = "md5_60", k: int | None = None) -> DataFrame:
    """(run, kept, z_hat) of sample estimates of many runs in one plan; runs without a pair have kept 0 and a null.

    Pairs of the samples are counted, or with ``k`` sketched by their k smallest hashes.
    """
    if family != "md5_60":
        raise ValueError("runs as a column need md5_60")
    spark = rel.left.sparkSession
    each = F.explode(F.sequence(F.lit(runs.start), F.lit(runs.stop - 1))).alias("run")
    digest = lambda side, c: F.conv(F.substring(F.md5(F.concat(F.lit(side), F.col("run"), F.lit(":"), F.coalesce(F.col(c).cast("string"), F.lit("\\N")))), 1, 15), 16, 10).cast("long")
    # Values are sampled once for each run, tuples follow by a join on the value.
    chosen = lambda df, c, side, p: df.select(c).distinct().select(c, each).where(digest(side, c) < sample_threshold(p, family))
    left = rel.left.join(chosen(rel.left, "lk", "SL", p1), "lk")
    right = rel.right.join(chosen(rel.right, "rk", "SR", p2), "rk")
    pairs = left.join(right, ["run", "jk"]).select("run", "lk", "rk").distinct()
    if k is None:
        found = pairs.groupBy("run").agg(F.count("*").alias("kept"))
        size = F.col("kept")
    else:
        domain = FAMILIES[family].domain
        hashed = pairs.select("run", digest("L", "lk").alias("x_h"), digest("R", "rk").alias("y_h"))
        hashed = hashed.select("run", "x_h", "y_h", (F.col("x_h") - F.col("y_h")).bitwiseAND(F.lit(domain - 1)).alias("pair_h"))
        rank = F.row_number().over(Window.partitionBy("run").orderBy("pair_h", "x_h", "y_h"))
        kept = hashed.withColumn("i", rank).where(F.col("i") <= k)
        found = kept.groupBy("run").agg(F.count("*").alias("kept"), F.max("pair_h").alias("kth_hash"))
        size = F.when(F.col("kept") >= k, F.lit(float(k) * float(domain)) / F.greatest("kth_hash", F.lit(1)).cast("double")).otherwise(F.col("kept"))
    every = spark.range(runs.start, runs.stop).select(F.col("id").cast("int").alias("run"))
    return every.join(found, "run", "left").select("run", F.coalesce("kept", F.lit(0)).alias("kept"), (size / (p1 * p2)).alias("z_hat"))
