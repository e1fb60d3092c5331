"""Samples by digests of a key: the same rows under retries, other partitionings and other engines; no shuffle."""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import rng


def bernoulli(df: DataFrame, key: str, share: float, seed: int = 0) -> DataFrame:
    """Each row with probability ``share``; rows that share a key stay or go together."""
    return df.where(rng.uniform(str(seed), "sample", F.col(key).cast("string")) < share)


def stratified(df: DataFrame, by: str, key: str, shares: Mapping[object, float], seed: int = 0) -> DataFrame:
    """A share of its own for each stratum; strata without one give no rows."""
    share = F.lit(0.0)
    for name, v in shares.items():
        share = F.when(F.col(by).eqNullSafe(F.lit(name)), F.lit(float(v))).otherwise(share)
    return df.where(rng.uniform(str(seed), "sample", F.col(key).cast("string")) < share)
