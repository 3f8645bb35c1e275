"""Strata of a join: rows of each side and edges by key."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def count_strata(keyed: list[DataFrame]) -> DataFrame:
    """(jk, n_1..n_n, edges): keys that all sides have; edges as decimal(38,0), since products outgrow bigint. One exchange: a tagged union with partial counts."""
    rows = reduce(DataFrame.unionAll, (k.select("jk", F.lit(i).alias("side")) for i, k in enumerate(keyed, 1)))
    counts = [F.count(F.when(F.col("side") == i, 1)).alias(f"n_{i}") for i in range(1, len(keyed) + 1)]
    every = rows.groupBy("jk").agg(*counts)
    there = reduce(lambda a, b: a & b, (F.col(f"n_{i}") > 0 for i in range(1, len(keyed) + 1)))
    return every.where(there).withColumn("edges", product([F.col(f"n_{i}") for i in range(1, len(keyed) + 1)]))


def product(counts: list[Column]) -> Column:
    return reduce(lambda a, b: (a * b).cast("decimal(38,0)"), (c.cast("decimal(19,0)") for c in counts[1:]), counts[0].cast("decimal(38,0)"))


def total_edges(strata: DataFrame) -> DataFrame:
    """(strata, edges, sampled): the counts, and the sum of sample sizes if they are there."""
    sampled = F.sum("b").cast("bigint") if "b" in strata.columns else F.lit(None).cast("bigint")
    return strata.agg(F.count("*").alias("strata"), F.coalesce(F.sum("edges"), F.lit(0)).cast("decimal(38,0)").alias("edges"), sampled.alias("sampled"))


def heaviest(strata: DataFrame, k: int = 10) -> DataFrame:
    """The k strata of most edges, for a report on skew."""
    return strata.orderBy(F.desc("edges"), "jk").limit(k)
