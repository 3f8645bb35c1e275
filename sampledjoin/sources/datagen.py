"""Inputs whose rows by key follow a Poisson distribution, with a dial for how many keys they share."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.keys import text_hash
from ..model import JoinInput


def poisson_counts(u, lam: float):
    """A Poisson count from a uniform column, by the inverse distribution function."""
    out, p, total = F.lit(0), math.exp(-lam), 0.0
    for k in range(int(lam + 8 * math.sqrt(lam) + 8)):
        total += p
        out = out + F.when(u > total, 1).otherwise(0)
        p *= lam / (k + 1)
    return out


def poisson_inputs(spark: SparkSession, n: int = 2, lam: float = 10.0, keys: int = 1000, overlap: float = 0.1, seed: int = 42, family: str = "xx", ids: DataFrame | None = None) -> list[JoinInput]:
    """n inputs (k, v) of ``keys`` keys; the share ``overlap`` of the keys is common, the rest is each input's own. Rows come from hashes, so they are the same at any partitioning.

    ids: a table's keys (id, not negative, each once) take the place of made ones; of each thousand, the lowest ``overlap`` are common."""
    shared = round(keys * overlap)
    out = []
    for i in range(n):
        if ids is None:
            source, k = spark.range(keys), F.when(F.col("id") < shared, F.col("id")).otherwise(F.col("id") + (i + 1) * keys)
        else:
            source, k = ids, F.col("id") * (n + 1) + F.when(F.col("id") % 1000 < round(1000 * overlap), F.lit(0)).otherwise(i + 1)
        h = text_hash(F.col("id"), i, seed) if family == "portable" else F.xxhash64("id", F.lit(i), F.lit(seed))
        u = (F.pmod(h, F.lit(1 << 52)) + F.lit(0.5)) / float(1 << 52)
        rows = source.select(k.alias("k"), F.explode(F.sequence(F.lit(0), poisson_counts(u, lam))).alias("r")).where("r > 0")
        v = F.round(F.pmod(F.xxhash64("k", "r", F.lit(i), F.lit(seed)), F.lit(1_000_000)) / 100, 2).cast("decimal(18,2)")
        out.append(JoinInput(rows.select("k", v.alias(f"v{i + 1}")), ["k"], [f"v{i + 1}"], f"poisson{i + 1}"))
    return out


def dial(df: DataFrame, key: str, i: int, n: int, p: int) -> DataFrame:
    """Input i of n: keys k with k % 100 < p are kept by all, others by the input with k % n = i."""
    return df.where((F.pmod(F.col(key), F.lit(100)) < p) | (F.pmod(F.col(key), F.lit(n)) == i))
