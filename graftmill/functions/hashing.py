"""Deterministic pseudo-random numbers from md5, the same in any partitioning and in other SQL engines."""

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _c(x) -> Column:
    return F.col(x) if isinstance(x, str) else x


def hash32(*parts, seed: int | str = 7) -> Column:
    """First 8 hex digits of md5('seed:part:part...') as bigint."""
    text = F.concat_ws(":", F.lit(str(seed)), *[_c(p).cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def hash_uniform(*parts, seed: int | str = 7) -> Column:
    return hash32(*parts, seed=seed) / F.lit(float(2**32))


def bucket(text, n: int = 384) -> Column:
    return F.conv(F.substring(F.md5(_c(text)), 1, 8), 16, 10).cast("long") % n


def hash_sample(df: DataFrame, fraction: float, key: str, *, seed: int = 7) -> DataFrame:
    return df.filter(hash_uniform(key, seed=seed) < fraction)


def nested_sample(df: DataFrame, levels: tuple[float, ...], *keys: str, seed: int = 7) -> DataFrame:
    """The rows of every level, with the level as a column; smaller levels are subsets of larger ones."""
    u = hash_uniform(*keys, seed=seed)
    return df.withColumn("keep", F.explode(F.array(*[F.lit(x) for x in levels]))).filter(u < F.col("keep"))
