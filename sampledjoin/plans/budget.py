"""From a budget to sample sizes: what a latency allows, what an error needs, and how they trade."""

from __future__ import annotations

import time

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.keys import text_hash
from ..functions.quantiles import z_quantile
from ..model import InfeasibleError, LatencyModel
from ..sources.io import stored


def remaining(desired_s: float, filter_s: float) -> float:
    """What the filtering stage leaves of the desired latency."""
    return desired_s - filter_s


def check(edges: float, rest_s: float, model: LatencyModel, least_edges: float = 0.0, filter_s: float = 0.0) -> str:
    """exact if all edges fit the rest of the time, sampled if at least ``least_edges`` do; else InfeasibleError with the least latency that would do."""
    if model.predict(edges) <= rest_s:
        return "exact"
    if rest_s <= model.epsilon or model.predict(least_edges) > rest_s:
        raise InfeasibleError(f"{rest_s:.3g} s remain; the smallest sample needs {model.predict(least_edges):.3g} s", filter_s + model.predict(least_edges))
    return "sampled"


def fraction_for_latency(desired_s: float, filter_s: float, edges: float, model: LatencyModel) -> float:
    """The fraction of the edges that the remaining time allows, at most 1."""
    return max(0.0, min(1.0, (desired_s - filter_s - model.epsilon) / model.beta / edges)) if edges else 1.0


def allocate(strata: DataFrame, fraction: float | Column, min_b: int = 2) -> DataFrame:
    """``strata`` with b, the floor of fraction · edges but at least ``min_b`` and at most all edges, and full."""
    s = F.lit(float(fraction)) if isinstance(fraction, int | float) else fraction
    return clamp(strata, F.floor(s * F.col("edges").cast("double") + F.lit(1e-9)), min_b)


def allocate_within(strata: DataFrame, edges: float, min_b: int = 2) -> DataFrame:
    """``allocate`` of a number of edges over all keys. Where keeping every key lifts the sum over it (``overdrawn``), each key gets its least first and a share of the rest, so that the sum stays within."""
    least = F.least(F.lit(min_b).cast("decimal(38,0)"), F.col("edges"))
    whole = strata.agg(F.sum("edges").cast("double").alias("all"), F.sum(least).cast("double").alias("least")).first()
    if not whole["all"]:
        return allocate(strata, 1.0, min_b)
    share = min(1.0, edges / whole["all"])
    if (allocate(strata, share, min_b).agg(F.sum("b")).first()[0] or 0) <= edges or share == 1.0:
        return allocate(strata, share, min_b)
    rest = max(0.0, edges - whole["least"]) / max(1.0, whole["all"] - whole["least"])
    return clamp(strata, least + F.floor(F.lit(rest) * (F.col("edges") - least).cast("double")), min_b)


def clamp(strata: DataFrame, b: Column, min_b: int = 2) -> DataFrame:
    sized = F.least(F.greatest(b.cast("decimal(38,0)"), F.lit(min_b).cast("decimal(38,0)")), F.col("edges")).cast("bigint")
    return strata.withColumn("b", sized).withColumn("full", F.col("b") >= F.col("edges"))


def overdrawn(strata: DataFrame, fraction: float, min_b: int = 2) -> DataFrame:
    """(least, wanted, overdrawn): whether keeping every key alone takes more edges than the fraction allows."""
    return strata.agg(F.sum(F.least(F.lit(min_b).cast("decimal(38,0)"), F.col("edges"))).cast("double").alias("least"), (F.sum("edges").cast("double") * fraction).alias("wanted")).withColumn("overdrawn", F.col("least") > F.col("wanted"))


def error_size(sigma: Column, error: float, confidence: float = 0.95) -> Column:
    """Draws for a stratum mean to be within ``error``: (z σ / error)², rounded up."""
    z = z_quantile(confidence)
    return F.ceil(F.pow(F.lit(z) * sigma / F.lit(error), F.lit(2.0)) - F.lit(1e-9))


def mean_error(sigma: Column, b: Column, confidence: float = 0.95) -> Column:
    return F.lit(z_quantile(confidence)) * sigma / F.sqrt(b)


def size_for_error(strata: DataFrame, sigma: DataFrame, error: float, confidence: float = 0.95, kind: str = "stratum_mean", min_b: int = 2, total: float | None = None) -> DataFrame:
    """``strata`` with b from stored standard deviations (jk, n, sigma); a key without one takes the pooled one.

    kind stratum_mean: each key's mean is within ``error``. total_abs: the total is, with the fewest draws (they go with edges · sigma). relative: the total is within error · ``total``."""
    pool = sigma.agg(F.sqrt(F.try_divide(F.sum((F.col("n") - 1) * F.col("sigma") ** 2), F.sum(F.greatest(F.col("n") - 1, F.lit(1))).cast("double"))).alias("pooled"))
    known = strata.join(sigma.select("jk", "sigma"), "jk", "left").crossJoin(F.broadcast(pool)).withColumn("sigma", F.coalesce("sigma", "pooled", F.lit(0.0))).drop("pooled")
    if kind == "stratum_mean":
        return clamp(known, error_size(F.col("sigma"), error, confidence), min_b)
    target = error if kind == "total_abs" else error * abs(total or 0.0)
    spread = F.col("edges").cast("double") * F.col("sigma")
    whole = known.agg(F.sum(spread).alias("spread"))
    need = F.ceil(F.lit((z_quantile(confidence) / target) ** 2) * spread * F.col("spread"))
    return clamp(known.crossJoin(F.broadcast(whole)), need, min_b).drop("spread")


def latency_for_error(strata: DataFrame, error: float, filter_s: float, model: LatencyModel, confidence: float = 0.95) -> DataFrame:
    """(jk, latency): the latency at which each key (edges, sigma) would be within the error, as one fraction for all keys."""
    z2 = z_quantile(confidence) ** 2
    whole = strata.agg(F.sum("edges").cast("double").alias("all_edges"))
    return strata.crossJoin(F.broadcast(whole)).select("jk", (F.lit(z2) * F.pow(F.col("sigma") / error, F.lit(2.0)) * model.beta / F.col("edges").cast("double") * F.col("all_edges") + F.lit(filter_s + model.epsilon)).alias("latency"))


def error_for_latency(strata: DataFrame, desired_s: float, filter_s: float, model: LatencyModel, confidence: float = 0.95) -> DataFrame:
    """(jk, error): the error of each key's mean at the fraction that the latency allows."""
    whole = strata.agg(F.sum("edges").cast("double").alias("all_edges"))
    share = F.least(F.lit(1.0), F.lit((desired_s - filter_s - model.epsilon) / model.beta) / F.col("all_edges"))
    return strata.crossJoin(F.broadcast(whole)).select("jk", mean_error(F.col("sigma"), F.greatest(F.lit(1.0), share * F.col("edges").cast("double")), confidence).alias("error"))


def bootstrap_sigma(edges: DataFrame, value: Column, reps: int = 30, seed: int = 42, family: str = "xx") -> DataFrame:
    """(jk, n, sigma) from resamples of a pilot: every draw gets a Poisson(1) weight by hash in each replicate."""
    h = text_hash(F.col("jk"), F.col("draw"), F.col("rep"), seed) if family == "portable" else F.xxhash64("jk", "draw", "rep", F.lit(seed))
    u = (F.pmod(h, F.lit(1 << 52)) + F.lit(0.5)) / F.lit(float(1 << 52))
    weight = F.lit(0)
    cumulative, p = 0.0, 2.718281828459045**-1
    for k in range(1, 9):  # inverse distribution function; beyond 8 has weight under 1e-6
        cumulative += p
        weight = weight + F.when(u > cumulative, 1).otherwise(0)
        p /= k
    v = value.cast("double")
    rows = edges.select("jk", "draw", v.alias("v")).withColumn("rep", F.explode(F.sequence(F.lit(1), F.lit(reps)))).withColumn("w", weight)
    each = rows.groupBy("jk", "rep").agg(F.sum("w").alias("w"), F.sum(F.col("w") * F.col("v")).alias("s"), F.sum(F.col("w") * F.col("v") * F.col("v")).alias("q")).where("w > 1")
    return each.groupBy("jk").agg(F.max("w").cast("bigint").alias("n"), F.sqrt(F.avg(F.greatest(F.lit(0.0), (F.col("q") - F.col("s") ** 2 / F.col("w")) / (F.col("w") - 1)))).alias("sigma"))


def calibrate(spark: SparkSession, sizes: tuple[int, ...] = (1000, 2000, 3000, 4000), repeats: int = 2, rows: DataFrame | None = None) -> LatencyModel:
    """Times cross products of several sizes and fits a line: seconds against edges. rows: (id, v) of a table, of which each size takes the rows of the smallest ids; without it, numbers are made."""
    kept = spark.range(max(sizes)).select("id", F.col("id").alias("v")) if rows is None else stored(rows.orderBy("id").limit(max(sizes)), "calibration")

    def timed(n: int) -> tuple[float, float]:
        t = time.perf_counter()
        side = kept.orderBy("id").limit(n)
        edges = side.select("v").crossJoin(side.select(F.col("v").alias("other"))).agg(F.count("*").alias("n"), F.sum(F.col("v") + F.col("other"))).first().n
        return float(edges), time.perf_counter() - t

    for n in sizes[:2]:  # what starts once is not an edge's cost
        timed(n)
    points = [timed(n) for n in sizes for _ in range(repeats)]
    slope, intercept, r2 = spark.createDataFrame(points, "x double, y double").agg(F.regr_slope("y", "x"), F.regr_intercept("y", "x"), F.regr_r2("y", "x")).first()
    return LatencyModel(max(slope, 1e-12), max(0.0, intercept), r2)
