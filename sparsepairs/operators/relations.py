"""Two binary relations that share an attribute: normal form, pruning, statistics."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


@dataclass(frozen=True)
class Rel:
    """``left(lk, jk)`` and ``right(jk, rk)``; lazy.  ``distinct`` says that no row comes twice, ``mirrored`` that the sides are one table.

    ``rows`` are a mirrored relation's rows before repeats went, the join values of a row in an array;
    ``held`` is what was written of a stored relation.
    """

    left: DataFrame
    right: DataFrame
    distinct: bool = False
    mirrored: bool = False
    rows: DataFrame | None = field(default=None, compare=False)
    held: dict[str, DataFrame] = field(default_factory=dict, compare=False)


def _key(df: DataFrame, columns: str | list[str]) -> Column:
    """One column as it is; several, or a type that hashes badly, as a struct or a cleaned value."""
    names = [columns] if isinstance(columns, str) else list(columns)
    out = []
    for name in names:
        kind = df.schema[name].dataType
        if isinstance(kind, T.MapType):
            raise TypeError(f"{name}: maps can't be keys")
        col = F.col(name)
        if isinstance(kind, (T.DoubleType, T.FloatType)):
            col = F.when(col == 0, F.lit(0).cast(kind)).otherwise(col)
        out.append(col.alias(name))
    return out[0] if len(out) == 1 else F.struct(*out)


def normalize(
    left: DataFrame,
    right: DataFrame,
    left_keep: str | list[str],
    right_keep: str | list[str],
    on: str | list[str] | tuple[str, str],
    dedup: bool = True,
    fingerprint: bool = False,
) -> Rel:
    """The two relations as (lk, jk) and (jk, rk).

    ``on`` names the join column(s), or a pair of names where the sides differ.
    Null join keys are dropped; a null kept value is a value.  With
    ``fingerprint`` every role becomes a 64-bit integer.
    """
    left_on, right_on = on if isinstance(on, tuple) else (on, on)
    sides = []
    for df, keep, by, roles in ((left, left_keep, left_on, ("lk", "jk")), (right, right_keep, right_on, ("rk", "jk"))):
        kept, joined = _key(df, keep), _key(df, by)
        if fingerprint:
            kept, joined = F.xxhash64(kept), F.when(joined.isNotNull(), F.xxhash64(joined))
        names = [by] if isinstance(by, str) else list(by)
        rows = df.dropna(subset=names).select(kept.alias(roles[0]), joined.alias(roles[1]))
        rows = rows.select("lk", "jk") if roles[0] == "lk" else rows.select("jk", "rk")
        sides.append(rows.distinct() if dedup else rows)
    return Rel(*sides, distinct=dedup)


def self_rel(df: DataFrame, keep: str | list[str], on: str | list[str], dedup: bool = True) -> Rel:
    """A relation joined with itself; pairs of a value with itself count."""
    left = normalize(df, df, keep, keep, on, dedup).left
    # The mirror reads the same rows, so their exchange is made once.
    return Rel(left, left.select("jk", F.col("lk").alias("rk")), distinct=dedup, mirrored=True)


def drop_dangling(rel: Rel) -> Rel:
    """Without tuples that find no partner: a semi join each way."""
    return Rel(rel.left.join(rel.right.select("jk"), "jk", "left_semi").select("lk", "jk"), rel.right.join(rel.left.select("jk"), "jk", "left_semi").select("jk", "rk"))


def cluster(rel: Rel, how: str = "hash", partitions: int | None = None) -> Rel:
    """Both sides arranged by join value: by hash, or by range and sorted."""
    if how not in ("hash", "sort"):
        raise ValueError("how is 'hash' or 'sort'")
    args = ([partitions] if partitions else []) + ["jk"]
    if how == "hash":
        return Rel(rel.left.repartition(*args), rel.right.repartition(*args))
    return Rel(rel.left.repartitionByRange(*args).sortWithinPartitions("jk", "lk"), rel.right.repartitionByRange(*args).sortWithinPartitions("jk", "rk"))


def group_sizes(rel: Rel) -> DataFrame:
    """jk, l, r: distinct kept values of each join value that has both."""
    def sizes(df: DataFrame, role: str, name: str) -> DataFrame:
        n = F.count("*") if rel.distinct else F.count_distinct(F.coalesce(F.xxhash64(role), F.lit(0)))
        return df.groupBy("jk").agg(n.alias(name))

    left = sizes(rel.left, "lk", "l")
    return left.withColumn("r", F.col("l")) if rel.mirrored else left.join(sizes(rel.right, "rk", "r"), "jk")


def work(rel: Rel) -> DataFrame:
    """One row: maxprod (largest group product) and joined (their sum)."""
    product = (F.col("l") * F.col("r")).cast("long")
    return group_sizes(rel).agg(F.coalesce(F.max(product), F.lit(0)).alias("maxprod"), F.coalesce(F.sum(product), F.lit(0)).alias("joined"))


def profile(rel: Rel) -> DataFrame:
    """One row: n1, n2, n_a, n_c, joined, maxprod."""
    left = rel.left.agg(F.count("*").alias("n1"), F.count_distinct("lk").alias("n_a"))
    right = rel.right.agg(F.count("*").alias("n2"), F.count_distinct("rk").alias("n_c"))
    return left.crossJoin(right).crossJoin(work(rel)).select("n1", "n2", "n_a", "n_c", "joined", "maxprod")
