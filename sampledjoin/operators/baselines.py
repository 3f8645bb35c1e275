"""The joins and samplings that the operator is compared with."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.keys import text_hash
from .strata import count_strata

UNIT = float(1 << 60)


def native_join(keyed: list[DataFrame]) -> DataFrame:
    """The engine's own join by key, chained for several inputs."""
    return reduce(lambda a, b: a.join(b.hint("merge"), "jk"), keyed)


def repartition_join(keyed: list[DataFrame]) -> DataFrame:
    """Every input dealt by key once, then joined where it lies."""
    return reduce(lambda a, b: a.join(b.hint("shuffle_hash"), "jk"), (k.repartition("jk") for k in keyed))


def union_join(keyed: list[DataFrame]) -> DataFrame:
    """All inputs through one exchange as a tagged union, packed by key; a key's rows are held by one task."""
    cols = [[c for c in k.columns if c != "jk"] for k in keyed]
    rows = reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), (k.select("jk", F.struct(*c).alias(f"side_{i}")) for i, (k, c) in enumerate(zip(keyed, cols, strict=True))))
    packed = rows.groupBy("jk").agg(*(F.collect_list(f"side_{i}").alias(f"side_{i}") for i in range(len(keyed))))
    for i in range(len(keyed)):
        packed = packed.withColumn(f"side_{i}", F.explode(f"side_{i}"))
    return packed.select("jk", *(F.col(f"side_{i}.{c}").alias(c) for i, cs in enumerate(cols) for c in cs))


def broadcast_join(keyed: list[DataFrame], most_bytes: int = 1 << 28) -> DataFrame:
    """All inputs but the first go to every node, if each has at most ``most_bytes`` by its rows and 24 bytes a column; else the engine chooses."""
    width = lambda b: 16 + 24 * len(b.columns)
    fits = lambda b, most: b.limit(most + 1).count() <= most
    return reduce(lambda a, b: a.join(F.broadcast(b) if fits(b, most_bytes // width(b)) else b, "jk"), keyed[1:], keyed[0])


def unit_hash(*parts: Column | str | int) -> Column:
    """In [0, 1), by a hash that other engines can repeat."""
    return text_hash(*parts) / F.lit(UNIT)


def postjoin_sample(joined: DataFrame, fraction: float, value: Column, seed: int = 42, identity: list[str] | None = None) -> DataFrame:
    """(jk, n, edges, s1, s2): a baseline, which sorts a key's rows in one task: a stratified sample of the finished join: of each key the share ``fraction`` of its rows, at least 2, those of smallest hash."""
    cols = identity or [c for c in joined.columns if c != "jk"]
    order = text_hash(*(F.col(c) for c in cols), seed)
    by_key = Window.partitionBy("jk")
    ranked = joined.withColumn("r", F.row_number().over(by_key.orderBy(order, *cols))).withColumn("edges", F.count("*").over(by_key))
    b = F.least(F.greatest(F.ceil(F.lit(fraction) * F.col("edges") - F.lit(1e-9)), F.lit(2)), F.col("edges"))
    return ranked.where(F.col("r") <= b).groupBy("jk").agg(F.count("*").alias("n"), F.first("edges").alias("edges"), F.sum(value).cast("double").alias("s1"), F.sum(value * value).cast("double").alias("s2"))


def postjoin_sum(joined: DataFrame, fraction: float, value: Column, seed: int = 42, identity: list[str] | None = None) -> DataFrame:
    """(estimate, sampled_edges, total_edges) by post-join sampling."""
    rows = postjoin_sample(joined, fraction, value, seed, identity)
    return rows.agg(F.sum(F.col("edges") / F.col("n") * F.col("s1")).alias("estimate"), F.sum("n").cast("bigint").alias("sampled_edges"), F.sum("edges").cast("bigint").alias("total_edges"))


def prejoin_sum(keyed: list[DataFrame], fraction: float, value: Column, ids: list[list[str]], seed: int = 42, per_input: bool = False) -> DataFrame:
    """(estimate, sampled_edges): inputs are sampled by hash before the join, the joined samples scaled up. The fraction is of the edges, so each input keeps its n-th root; with ``per_input`` it is each input's own."""
    n = len(keyed)
    share = fraction if per_input else fraction ** (1 / n)
    kept = [k.where(unit_hash(*(F.col(c) for c in cols), i, seed) < share) for i, (k, cols) in enumerate(zip(keyed, ids, strict=True), 1)]
    joined = reduce(lambda a, b: a.join(b, "jk"), kept)
    return joined.agg((F.coalesce(F.sum(value).cast("double"), F.lit(0.0)) / F.lit(share**n)).alias("estimate"), F.count("*").alias("sampled_edges"))


def prejoin_stratified(keyed: list[DataFrame], fraction: float, value: Column, seed: int = 42, family: str = "xx") -> DataFrame:
    """As ``prejoin_sum``, but each input keeps the share of every key's rows, at least one; a key is scaled by its own shares."""
    n = len(keyed)
    share = fraction ** (1 / n)
    strata, kept = count_strata(keyed), []
    for i, k in enumerate(keyed, 1):
        cols = [c for c in k.columns if c != "jk"]
        w = Window.partitionBy("jk")
        ranked = k.withColumn("r", F.row_number().over(w.orderBy(text_hash(*map(F.col, cols), seed + i) if family == "portable" else F.xxhash64(*cols, F.lit(seed + i)), *cols))).withColumn("c", F.count("*").over(w))
        kept.append(ranked.withColumn(f"w_{i}", F.col("c") / F.greatest(F.lit(1.0), F.ceil(share * F.col("c")))).where(F.col("r") <= F.greatest(F.lit(1), F.ceil(share * F.col("c")))).drop("r", "c"))
    joined = reduce(lambda a, b: a.join(b, "jk"), kept).join(strata.select("jk"), "jk", "left_semi")
    weight = reduce(lambda a, b: a * b, (F.col(f"w_{i}") for i in range(1, n + 1)))
    return joined.agg(F.sum(value.cast("double") * weight).alias("estimate"), F.count("*").alias("sampled_edges"))


def hybrid_postjoin(keyed: list[DataFrame], fraction: float, value: Column, ids: list[str], seed: int = 42) -> DataFrame:
    """(estimate, sampled_edges): the engine joins as it likes, a uniform sample of the output is summed and scaled."""
    joined = reduce(lambda a, b: a.join(b, "jk"), keyed).where(unit_hash(*(F.col(c) for c in ids), seed) < fraction)
    return joined.agg((F.sum(value).cast("double") / F.lit(fraction)).alias("estimate"), F.count("*").alias("sampled_edges"))
