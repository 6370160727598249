"""Seeded coins: pure functions of their keys, so a retried task draws the same."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def coin(seed: int, purpose: str, *keys: Column | str, portable: bool = False) -> Column:
    """A number in [0, 1).  ``portable``: 32 bits of an md5, which other SQL engines can repeat."""
    columns = [F.col(k) if isinstance(k, str) else k for k in keys]
    if portable:
        text = F.concat_ws("|", F.lit(str(seed)), F.lit(purpose), *(c.cast("string") for c in columns))
        return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") / F.lit(float(1 << 32))
    return F.pmod(F.xxhash64(F.lit(seed), F.lit(purpose), *columns), F.lit(1 << 52)).cast("double") / F.lit(float(1 << 52))


def coin_filter(df, p: float, seed: int, purpose: str, *keys, portable: bool = False):
    """The rows whose coin is below p."""
    return df.where(coin(seed, purpose, *keys, portable=portable) < p)


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser for arrays (public-domain splitmix64 constants)."""
    with np.errstate(over="ignore"):
        x = x + np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def priority(label: Column, seed: int, step: int) -> Column:
    return F.xxhash64(F.lit(seed), F.lit(step), label)


def trailing_zeros(h: Column, most: int) -> Column:
    """Zeros at the end of a hash, at most ``most``."""
    safe = h.bitwiseAND(F.lit((1 << 62) - 1)).bitwiseOR(F.lit(1 << most))
    return F.bit_count(F.bitwise_not(safe).bitwiseAND(safe - 1)).cast("int")


def cosine_distance(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return 1 - dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def register_functions(spark: SparkSession) -> None:
    """SQL names: coin(seed, purpose, key) and cosine_distance(a, b)."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION coin(seed INT, purpose STRING, k BIGINT) RETURNS DOUBLE RETURN cast(pmod(xxhash64(seed, purpose, k), 4503599627370496) AS DOUBLE) / 4503599627370496D")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cosine_distance(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN 1 - aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v) / sqrt(aggregate(transform(a, x -> x * x), 0D, (s, v) -> s + v) * aggregate(transform(b, x -> x * x), 0D, (s, v) -> s + v))")
