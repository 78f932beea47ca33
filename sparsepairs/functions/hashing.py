"""One-attribute hashes and the pair hash that is their difference on a circle."""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed value: the Mersenne prime 2^61 - 1 of the pairwise independent family.
PRIME = 2**61 - 1


@dataclass(frozen=True)
class Family:
    """A family of one-attribute hashes with values in [0, domain)."""

    name: str
    domain: int

    def hash(self, col: Column, seed: str) -> Column:
        raise NotImplementedError

    def pair(self, x: Column, y: Column) -> Column:
        """(x - y) modulo the domain, which is a power of two."""
        return (x - y).bitwiseAND(F.lit(self.domain - 1))


class Mix63(Family):
    """xxhash64 with a seed column, sign bit dropped: code-generated and fast."""

    def hash(self, col: Column, seed: str) -> Column:
        return F.shiftrightunsigned(F.xxhash64(F.lit(seed), col), 1)


class Md5x60(Family):
    """The first 60 bits of md5 over seed and value: any SQL engine can compute it."""

    def hash(self, col: Column, seed: str) -> Column:
        text = F.concat(F.lit(seed), F.coalesce(col.cast("string"), F.lit("\\N")))
        return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


class Affine61(Family):
    """(alpha * value + beta) modulo 2^61 - 1: provably pairwise independent; integral keys."""

    def coefficients(self, seed: str) -> tuple[int, int]:
        import hashlib

        raw = hashlib.md5(seed.encode()).digest()
        return int.from_bytes(raw[:8], "big") % (PRIME - 1) + 1, int.from_bytes(raw[8:], "big") % PRIME

    def hash(self, col: Column, seed: str) -> Column:
        alpha, beta = self.coefficients(seed)
        value = F.pmod(col.cast("long"), F.lit(PRIME)).cast("decimal(19,0)")
        return F.pmod(F.lit(alpha).cast("decimal(19,0)") * value + F.lit(beta), F.lit(PRIME).cast("decimal(38,0)")).cast("long")

    def pair(self, x: Column, y: Column) -> Column:
        return F.pmod(x - y, F.lit(self.domain))


MIX63 = Mix63("mix63", 2**63)
MD5_60 = Md5x60("md5_60", 2**60)
AFFINE61 = Affine61("affine61", PRIME)
FAMILIES = {f.name: f for f in (MIX63, MD5_60, AFFINE61)}


def attr_hash(col: Column, seed: str, family: str = "mix63") -> Column:
    """The hash of one attribute under a seed."""
    return FAMILIES[family].hash(col, seed)


def pair_hash(x: Column, y: Column, family: str = "mix63") -> Column:
    """The hash of a pair from its parts' hashes."""
    return FAMILIES[family].pair(x, y)


def lookup_table(values: DataFrame, column: str, seed: str) -> DataFrame:
    """Each distinct value with 60 bits that any engine can compute, to be written once and joined."""
    return values.select(column).distinct().withColumn("bits", MD5_60.hash(F.col(column), seed))


def drawn_table(values: DataFrame, column: str, seed: str, path: str) -> DataFrame:
    """Each distinct value with 60 random bits, drawn once and stored under ``path``: all readers see the same draw."""
    number = zlib.crc32(seed.encode())
    bits = lambda n: F.floor(F.rand(n) * float(2**30)).cast("long")
    rows = values.select(column).distinct()
    rows.select(column, (bits(number) * 2**30 + bits(number ^ 0x5BD1E995)).alias("bits")).write.parquet(path)
    return values.sparkSession.read.parquet(path)


def _affine_arrays(value: np.ndarray, alpha: int, beta: int) -> np.ndarray:
    """alpha * value + beta modulo 2^61 - 1 by 32-bit limbs; values lie in [0, 2^61 - 1)."""
    p = np.uint64(PRIME)

    def fold(x: np.ndarray) -> np.ndarray:
        x = (x & p) + (x >> np.uint64(61))
        return np.where(x >= p, x - p, x)

    v = value.astype(np.uint64)
    low, high = v & np.uint64(0xFFFFFFFF), v >> np.uint64(32)
    a_low, a_high = np.uint64(alpha & 0xFFFFFFFF), np.uint64(alpha >> 32)
    cross = fold(fold(low * a_high) + fold(high * a_low))
    # cross * 2^32: its upper 29 bits wrap round, since 2^61 = 1.
    shifted = fold((cross >> np.uint64(29)) + ((cross & np.uint64(2**29 - 1)) << np.uint64(32)))
    # high * a_high * 2^64 = high * a_high * 8.
    top = fold(high * a_high)
    top = fold((top >> np.uint64(58)) + ((top & np.uint64(2**58 - 1)) << np.uint64(3)))
    out = fold(fold(low * a_low) + shifted)
    return fold(fold(out + top) + np.uint64(beta)).astype(np.int64)


def affine61_udf(seed: str):
    """The affine family as an Arrow UDF over integers, without decimals."""
    alpha, beta = AFFINE61.coefficients(seed)

    @F.pandas_udf("long")
    def run(value: pd.Series) -> pd.Series:
        v = value.to_numpy(dtype=np.int64) % np.int64(PRIME)
        return pd.Series(_affine_arrays(v, alpha, beta))

    return run


def rounding_risk(k: int, n: int, domain: int) -> float:
    """Chance, up to a constant, that rounding hashes to the domain changes a decision."""
    return k * n / domain
