"""Functions for SQL users: hashes, sketches of columns, hits of a group, and a size by view names."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.estimate import Spec, estimate_size, walk_group
from ..operators.relations import normalize
from .hashing import affine61_udf


def bottom_k_udaf(k: int):
    """The k smallest distinct values of a column, ascending."""

    @F.pandas_udf("array<long>")
    def sp_bottom_k(v: pd.Series) -> list:
        return np.unique(v.dropna().to_numpy(np.int64))[:k].tolist()

    return sp_bottom_k


@F.udtf(returnType="x_h long, y_h long")
class GroupHits:
    """Pairs of two hash arrays below a threshold on the 60-bit circle."""

    def eval(self, xs: list, ys: list, t: int):
        x, y, _, _ = walk_group(np.array(xs or [], np.int64), np.array(ys or [], np.int64), t, 2**60)
        yield from zip(x.tolist(), y.tolist(), strict=True)


def register_functions(spark: SparkSession) -> None:
    """sp_attr_hash, sp_pair_hash (SQL expressions), sp_affine61, sp_hits."""
    spark.sql("create or replace temporary function sp_attr_hash(v string, seed string) returns bigint return cast(conv(substring(md5(concat(seed, v)), 1, 15), 16, 10) as bigint)")
    spark.sql(f"create or replace temporary function sp_pair_hash(x bigint, y bigint) returns bigint return (x - y) & {2**60 - 1}")
    spark.udf.register("sp_affine61", affine61_udf("L1:"))
    spark.udtf.register("sp_hits", GroupHits)


def sp_size(spark: SparkSession, left: str, right: str, left_keep: str, right_keep: str, on: str | tuple[str, str], spec: Spec = Spec(), view: str = "sp_size_result") -> DataFrame:
    """The ESTIMATE of two views or SQL texts, also registered as a view."""
    frame = lambda text: spark.sql(text) if " " in text.strip() else spark.table(text)
    out = estimate_size(normalize(frame(left), frame(right), left_keep, right_keep, on), spec)
    out.createOrReplaceTempView(view)
    return out
