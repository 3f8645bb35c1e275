"""Estimates from a stratified sample of edges, with bounds: by the central limit theorem, and by inclusion probabilities.

A row of the input is a stratum (or what a stratum holds of a group): the stratum's edges and draws, and sums of powers of the value over the sampled edges.
A null value counts for none of the aggregates, as in SQL. With groups, an edge of another group is a zero of this one, so that every stratum's draws count.
SUM and COUNT are weighted totals, AVG is their ratio, and STDEV a function of three totals; the bounds of the last two come from their linear form.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.quantiles import t_column

#: Sums of the value's powers from 0 (edges with a value) to 4.
POWERS = ("m", "s1", "s2", "s3", "s4")
AGGREGATES = ("sum", "avg", "count", "stdev")


def _sums(value: Column, powers: int) -> list[Column]:
    sums, power = [F.count(value).alias("m")], value
    for name in POWERS[1 : powers + 1]:
        sums.append(F.sum(power).cast("double").alias(name))
        power = power.cast("double") * value.cast("double") if name != "s1" else value * value
    return sums


def partials(edges: DataFrame, value: Column, group_by: list[str] | None = None, powers: int = 2) -> DataFrame:
    """(jk, groups, n, m, s1, ...) of the sampled edges: partial sums on the workers, a row for each key (and group) into the merge."""
    return edges.groupBy("jk", *(group_by or [])).agg(F.count("*").alias("n"), *_sums(value, powers))


def stratum_rows(edges: DataFrame, value: Column, group_by: list[str] | None = None, powers: int = 2) -> DataFrame:
    """``partials`` beside their stratum's numbers, which the edges carry (``sampler.sample_edges(carry=True)``): no join with the strata."""
    numbers = [F.first("st_edges").cast("double").alias("edges"), F.first("st_b").cast("double").alias("b"), F.first("st_full").alias("full")]
    return edges.groupBy("jk", *(group_by or [])).agg(F.count("*").alias("n"), *_sums(value, powers), *numbers)


def with_strata(parts: DataFrame, strata: DataFrame) -> DataFrame:
    """Partials beside their stratum's numbers, as doubles where estimates need them."""
    return parts.join(strata.select("jk", F.col("edges").cast("double").alias("edges"), F.col("b").cast("double").alias("b"), "full"), "jk")


def _zero(c: Column | str) -> Column:
    return F.coalesce(F.col(c) if isinstance(c, str) else c, F.lit(0.0))


def _moment(k: int) -> Column:
    return _zero(F.col(POWERS[k]).cast("double"))


def _covariance(i: int, j: int, n: Column) -> Column:
    """Of the i-th and j-th power of the value, over a stratum's n draws; null for one draw."""
    c = (_moment(i + j) - _moment(i) * _moment(j) / n) / (n - 1)
    return F.when(n > 1, F.greatest(F.lit(0.0), c) if i == j else c)


def stratum_factor(kind: str) -> Column:
    """What a stratum's sample variance is multiplied by for the variance of its total. published and without_replacement have the finite-population factor; with_replacement has none, as fits draws that may repeat. A full stratum has no variance."""
    B, b = F.col("edges"), F.col("b")
    return F.when(F.col("full"), F.lit(0.0)).otherwise((B * B if kind == "with_replacement" else B * (B - b)) / b)


def _summed(pairs: list[tuple[int, int]], n: Column, factor: Column, pool: bool) -> list[Column]:
    """Sums (v_ij) of factor times covariance over the strata; with ``pool``, also what the pooled covariance of strata of one draw needs."""
    out = []
    for i, j in pairs:
        c = _covariance(i, j, n)
        out.append(F.sum(F.coalesce(factor * c, F.lit(0.0))).alias(f"v_{i}{j}"))
        if pool:
            out.append(F.sum((n - 1) * c).alias(f"p_{i}{j}"))
    return [*out, F.sum(F.when(n > 1, n - 1)).alias("p_n"), F.sum(F.when(n <= 1, factor)).alias("p_f")] if pool else out


def _variance(i: int, j: int, pool: bool) -> Column:
    own = F.col(f"v_{i}{j}")
    return own + _zero(F.try_divide(F.col(f"p_{i}{j}"), F.col("p_n"))) * _zero("p_f") if pool else own


def finish(total: Column, variance: Column, dof: Column, edges: Column, n: Column, confidence: float, mode: str, divide: Column | None = None) -> list[Column]:
    by = divide if divide is not None else F.lit(1.0)
    bound = F.try_divide(t_column(confidence, dof) * F.sqrt(F.greatest(variance, F.lit(0.0))), by)
    est = F.try_divide(total, by)
    return [
        est.alias("estimate"), bound.alias("error_bound"), (est - bound).alias("lower"), (est + bound).alias("upper"), F.lit(confidence).alias("confidence"),
        dof.cast("bigint").alias("dof"), n.cast("bigint").alias("sampled_edges"), edges.cast("decimal(38,0)").alias("total_edges"), F.try_divide(n.cast("double"), edges.cast("double")).alias("fraction"), F.lit(mode).alias("mode"),
    ]


def _estimate(rows: DataFrame, agg: str, weight: Column, n: Column, factor: Column, dof: Column, confidence: float, mode: str, group_by: list[str], pool: bool) -> DataFrame:
    """weight: of a sampled edge; n: the stratum's draws (or different edges); factor: as of ``stratum_factor``; dof: over a group's rows."""
    if agg not in AGGREGATES:
        raise ValueError(f"no estimate for {agg}")
    pairs = {"sum": [(1, 1)], "count": [(0, 0)]}.get(agg, [(0, 0), (0, 1), (1, 1)])
    totals = [F.sum(weight * _moment(k)).alias(f"t_{k}") for k in range(3 if agg == "stdev" else 2)]
    sums = [*totals, dof.alias("dof"), F.sum("edges").alias("all_edges"), F.sum("n").alias("all_n")]
    end = lambda whole, total, variance, divide=None: whole.select(*group_by, *finish(total, variance, _zero("dof"), _zero("all_edges"), _zero(F.col("all_n").cast("double")), confidence, mode, divide))
    if agg != "stdev":
        whole = rows.groupBy(*group_by).agg(*sums, *_summed(pairs, n, factor, pool))
        if agg == "sum":
            return end(whole, _zero("t_1"), _zero(_variance(1, 1, pool)))
        if agg == "count":
            return end(whole, _zero("t_0"), _zero(_variance(0, 0, pool)))
        mean = F.try_divide(F.col("t_1"), F.col("t_0"))
        return end(whole, _zero("t_1"), _variance(1, 1, pool) - 2 * mean * _variance(0, 1, pool) + mean * mean * _variance(0, 0, pool), F.when(F.col("t_0") > 0, F.col("t_0")))
    # u = (v - mean)² - deviation², by the centred powers; its total over the count is the variance's error, and half of that over the deviation the deviation's
    mean = F.try_divide(F.col("t_1"), F.col("t_0"))
    center = rows.groupBy(*group_by).agg(*sums).withColumn("mu", mean).withColumn("sd", F.sqrt(F.greatest(F.try_divide(F.col("t_2"), F.col("t_0")) - F.col("mu") ** 2, F.lit(0.0))))
    center = center.select(*(F.col(g).alias(f"g_{i}") for i, g in enumerate(group_by)), "mu", "sd")
    here = [F.col(g).eqNullSafe(F.col(f"g_{i}")) for i, g in enumerate(group_by)]
    # without groups, center is one row
    rows = rows.join(center, here) if here else rows.crossJoin(F.broadcast(center))
    m = [_moment(k) for k in range(5)]
    mu, s = F.col("mu"), F.col("sd") * F.col("sd")
    q2 = m[2] - 2 * mu * m[1] + mu**2 * m[0]
    q4 = m[4] - 4 * mu * m[3] + 6 * mu**2 * m[2] - 4 * mu**3 * m[1] + mu**4 * m[0]
    u1, u2 = q2 - s * m[0], q4 - 2 * s * q2 + s * s * m[0]
    u_variance = F.when(n > 1, F.greatest(F.lit(0.0), (u2 - u1 * u1 / n) / (n - 1)))
    whole = rows.groupBy(*group_by).agg(*sums, F.first("sd").alias("sd"), F.sum(F.coalesce(factor * u_variance, F.lit(0.0))).alias("var_u"))
    bound = F.try_divide(F.sqrt("var_u"), F.col("t_0") * 2 * F.col("sd"))
    return end(whole, F.col("sd"), F.coalesce(bound * bound, F.lit(0.0)))


def clt(rows: DataFrame, agg: str = "sum", confidence: float = 0.95, variance: str = "with_replacement", group_by: list[str] | None = None) -> DataFrame:
    """The estimate of SUM, AVG, COUNT or STDEV over the join from ``with_strata`` rows. With ``group_by``: of each group, its edges being a domain of every stratum."""
    b = F.col("b")
    dof = F.sum(F.when(~F.col("full"), b - 1).otherwise(0.0))
    return _estimate(rows, agg, F.col("edges") / b, b, stratum_factor(variance), dof, confidence, f"clt_{variance}", group_by or [], True)


def horvitz_thompson(rows: DataFrame, level: str = "item", confidence: float = 0.95, agg: str = "sum", draws: bool = False, pi_joint: DataFrame | None = None, group_by: list[str] | None = None) -> DataFrame:
    """Totals weighted by 1/π. π is b / B for samples without duplicates; with ``draws``, 1 - (1 - 1/B)^b for the different edges of b draws.

    level item: edges are the units, its variance B (B - n) r² / n in closed form; level stratum: a key's sample sum is one unit (the literal form, SUM and COUNT only),
    whose cross terms vanish as keys are drawn independently; ``pi_joint`` (jk_k, jk_l, pi) gives other joint probabilities, and the cross terms of SUM are then summed."""
    group_by = group_by or []
    B, b = F.col("edges"), F.col("b")
    pi = F.when(F.col("full"), F.lit(1.0)).otherwise(1 - F.pow(1 - 1 / B, b)) if draws else b / B
    rows = rows.withColumn("pi", pi)
    # a stratum's different edges, over all groups
    whole_n = F.sum("n").over(Window.partitionBy("jk")) if group_by else F.col("n")
    rows = rows.withColumn("drawn", whole_n.cast("double"))
    n, dof = F.col("drawn"), F.greatest(F.sum("drawn") - 1, F.lit(0.0))
    if level == "item":
        if pi_joint is not None:
            raise ValueError("joint probabilities are of strata")
        factor = F.when(F.col("full"), F.lit(0.0)).otherwise(B * (B - n) / n)
        return _estimate(rows, agg, 1 / F.col("pi"), n, factor, dof, confidence, "ht_item", group_by, False)
    if agg not in ("sum", "count") or pi_joint is not None and (group_by or agg != "sum"):
        raise ValueError(f"no estimate for {agg} with whole strata as units")
    y = _moment(1 if agg == "sum" else 0)
    var = (1 - F.col("pi")) / (F.col("pi") * F.col("pi")) * y * y
    whole = rows.groupBy(*group_by).agg(F.sum(y / F.col("pi")).alias("total"), F.sum(var).alias("var"), dof.alias("dof"), F.sum("n").cast("double").alias("all_n"), F.sum("edges").alias("all_edges"))
    if pi_joint is not None:
        k, l = (rows.select(F.col("jk").alias(f"jk_{s}"), F.col("pi").alias(f"pi_{s}"), y.alias(f"y_{s}")) for s in "kl")
        product = F.col("pi_k") * F.col("pi_l")
        cross = k.join(pi_joint, "jk_k").join(l, "jk_l").where("jk_k <> jk_l").agg(F.coalesce(F.sum((F.col("pi") - product) / product * F.col("y_k") * F.col("y_l") / F.col("pi")), F.lit(0.0)).alias("cross"))
        whole = whole.crossJoin(cross).withColumn("var", F.col("var") + F.col("cross"))
    return whole.select(*group_by, *finish(_zero("total"), _zero("var"), _zero("dof"), _zero("all_edges"), _zero("all_n"), confidence, "ht_stratum"))


def stratum_sigma(rows: DataFrame) -> DataFrame:
    """(jk, n, sigma): standard deviations to be kept for later runs; strata of one draw take the pooled one."""
    b = F.col("b")
    rows = rows.withColumn("r2", _covariance(1, 1, b))
    pool = rows.agg(F.try_divide(F.sum((b - 1) * F.col("r2")), F.sum(F.when(b > 1, b - 1))).alias("pooled"))
    return rows.crossJoin(F.broadcast(pool)).select("jk", b.cast("bigint").alias("n"), F.sqrt(F.coalesce("r2", "pooled", F.lit(0.0))).alias("sigma"))
