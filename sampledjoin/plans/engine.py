"""The operator: filter the inputs, choose sample sizes by the budget, sample while joining, estimate with a bound."""

from __future__ import annotations

import re
import time
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import Budget, InfeasibleError, JoinInput, LatencyModel
from ..operators import estimators as E
from ..operators import sampler
from ..operators.filtering import prefilter
from ..operators.strata import count_strata
from ..sources.io import stored
from . import budget as P
from .feedback import FeedbackStore, fingerprint

PILOT = 0.01


def exact_join(keyed: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.join(b, "jk"), keyed)


def exact(keyed: list[DataFrame], value: Column, agg: str = "sum", group_by: list[str] | None = None, confidence: float = 0.95) -> DataFrame:
    """The exact answer in the shape of an estimate, its bound 0. COUNT counts values that are not null, as in SQL."""
    v = value
    f = {"sum": F.coalesce(F.sum(v).cast("double"), F.lit(0.0)), "avg": F.avg(v.cast("double")), "count": F.count(v).cast("double"), "stdev": F.stddev_pop(v.cast("double"))}[agg]
    rows = exact_join(keyed).groupBy(*(group_by or [])).agg(f.alias("estimate"), F.count("*").alias("n"))
    return rows.select(
        *(group_by or []), "estimate", F.lit(0.0).alias("error_bound"), F.col("estimate").alias("lower"), F.col("estimate").alias("upper"), F.lit(confidence).alias("confidence"), F.lit(0).cast("bigint").alias("dof"),
        F.col("n").alias("sampled_edges"), F.col("n").cast("decimal(38,0)").alias("total_edges"), F.lit(1.0).alias("fraction"), F.lit("exact").alias("mode"),
    )


def sampled_rows(keyed: list[DataFrame], strata: DataFrame, value: Column, agg: str = "sum", dedupe: bool | str = False, seed: int = 42, group_by: list[str] | None = None, strategy: str = "position", family: str = "xx", salts: int = 1) -> DataFrame:
    """Sample and sum by stratum (and group): strata have b and full."""
    edges = sampler.sample_edges(keyed, strata, seed, dedupe, strategy, family, salts, carry=True)
    return E.stratum_rows(edges, value, group_by, powers=4 if agg == "stdev" else 2)


def conclude(rows: DataFrame, agg: str = "sum", dedupe: bool | str = False, estimator: str = "clt", variance: str | None = None, level: str = "item", confidence: float = 0.95, group_by: list[str] | None = None) -> DataFrame:
    """The estimate from ``sampled_rows``."""
    if estimator == "ht":
        return E.horvitz_thompson(rows, level, confidence, agg, draws=dedupe == "distinct", group_by=group_by)
    if dedupe == "distinct":
        raise ValueError("draws without their duplicates need the estimator ht, which weighs by inclusion")
    return E.clt(rows, agg, confidence, variance or ("without_replacement" if dedupe == "resample" else "with_replacement"), group_by)


SAMPLING, CONCLUDING = ("seed", "strategy", "family", "salts"), ("estimator", "variance", "level", "confidence")


def estimate(keyed: list[DataFrame], strata: DataFrame, value: Column, agg: str = "sum", dedupe: bool | str = False, group_by: list[str] | None = None, **options) -> DataFrame:
    """Sample and estimate: strata have b and full. options: of ``sampled_rows`` and ``conclude``."""
    if unknown := options.keys() - {*SAMPLING, *CONCLUDING}:
        raise TypeError(f"unknown options: {sorted(unknown)}")
    rows = sampled_rows(keyed, strata, value, agg, dedupe, group_by=group_by, **{k: v for k, v in options.items() if k in SAMPLING})
    return conclude(rows, agg, dedupe, group_by=group_by, **{k: v for k, v in options.items() if k in CONCLUDING})


def choose_mode(edges: float, strata: int, budget: Budget, model: LatencyModel, filter_s: float = 0.0, exact_edges: float = 1e6, min_b: int = 2) -> str:
    """exact, sampled or infeasible. Without a latency, a join of at most ``exact_edges`` is done exactly."""
    if budget.latency_s is None:
        return "exact" if edges <= exact_edges else "sampled"
    try:
        return P.check(edges, P.remaining(budget.latency_s, filter_s), model, min(edges, strata * min_b), filter_s)
    except InfeasibleError:
        return "infeasible"


def plan_text(df: DataFrame) -> str:
    """The analysed plan without the numbers of its columns: tells tables' filters apart, and is the same in the next session."""
    return re.sub(r"#\d+L?", "", df._jdf.queryExecution().analyzed().toString())


def budgeted_join(inputs: list[JoinInput], value: Column, agg: str = "sum", budget: Budget | None = None, fraction: float | None = None, filter: bool = True, sample: bool = True, store: FeedbackStore | None = None, model: LatencyModel | None = None, min_b: int = 2, params=None, name: str = "", **options) -> DataFrame:
    """An aggregate over the join of ``inputs`` on their keys, as an estimate row (or one for each group).

    With ``fraction`` nothing but the filter's sizing runs before the result is asked for. A budget needs the filtering stage's time and the strata first: a latency gives the fraction, an error the sizes,
    by standard deviations that the store has of an earlier run or else that a pilot finds; with both, the error's sizes are taken if they fit the latency. sample=False: filter only."""
    began = time.perf_counter()
    confidence = budget.confidence if budget else options.pop("confidence", 0.95)
    keyed = prefilter(inputs, params).dfs if filter else [i.keyed() for i in inputs]
    if not sample or fraction is not None and fraction >= 1:
        return exact(keyed, value, agg, options.get("group_by"), confidence)
    if budget is None:
        strata = P.allocate(count_strata(keyed), 0.1 if fraction is None else fraction, min_b)
        return estimate(keyed, strata, value, agg, confidence=confidence, **options)

    # filtering and strata are done once, and timed from the first job on; the answer reads what they left
    model = model or LatencyModel()
    keyed = [stored(k, "kept") for k in keyed]
    counted = stored(count_strata(keyed), "strata")
    whole = counted.agg(F.coalesce(F.sum("edges"), F.lit(0)).cast("double").alias("edges"), F.count("*").alias("m"), F.coalesce(F.sum(F.least(F.col("edges"), F.lit(min_b).cast("decimal(38,0)"))), F.lit(0)).cast("double").alias("least")).first()
    filter_s = time.perf_counter() - began
    options.setdefault("salts", sampler.salts_for(counted))
    if (mode := choose_mode(whole.edges, whole.m, budget, model, filter_s, min_b=min_b)) == "exact":
        return exact(keyed, value, agg, options.get("group_by"), confidence)
    if mode == "infeasible":
        raise InfeasibleError(f"the budget of {budget.latency_s} s can't be met", filter_s + model.predict(whole.least))
    if budget.error is None:
        allowed = (P.remaining(budget.latency_s, filter_s) - model.epsilon) / model.beta
        return estimate(keyed, P.allocate_within(counted, allowed, min_b), value, agg, confidence=confidence, **options)

    key = fingerprint(name, [i.name for i in inputs], [list(i.keys) for i in inputs], [plan_text(i.df) for i in inputs], value, agg)
    sigma = store.load(key) if store else None
    total = None
    if sigma is None or budget.error_kind == "relative":
        rows = sampled_rows(keyed, P.allocate(counted, PILOT, min_b), value, seed=options.get("seed", 42) + 1)
        sigma = E.stratum_sigma(rows) if sigma is None else sigma
        total = E.clt(rows).first()["estimate"]
    sized = stored(P.size_for_error(counted, sigma, budget.error, confidence, budget.error_kind, min_b, total), "sized")
    if budget.latency_s is not None:
        wanted = sized.agg(F.sum("b")).first()[0] or 0
        if filter_s + model.predict(wanted) > budget.latency_s:
            raise InfeasibleError(f"an error of {budget.error} needs {wanted} edges", filter_s + model.predict(wanted))
    group_by, dedupe = options.pop("group_by", None), options.pop("dedupe", False)
    rows = sampled_rows(keyed, sized, value, agg, dedupe, group_by=group_by, **{k: v for k, v in options.items() if k in SAMPLING})
    if store and not group_by and not dedupe:  # the deviations are of whole strata
        rows = stored(rows, "sampled")
        store.save(key, E.stratum_sigma(rows))
    return conclude(rows, agg, dedupe, confidence=confidence, group_by=group_by, **{k: v for k, v in options.items() if k in CONCLUDING})


def refine(inputs: list[JoinInput], value: Column, target: float, deadline_s: float | None = None, first: float = PILOT, max_rounds: int = 5, seed: int = 42, params=None, family: str = "xx") -> list[dict]:
    """Rounds of sampling until the bound is at most ``target``: each run's deviations size the next. Draws are numbered and their sums add up, so a round makes only the draws that
    are not there yet (of a stratum that became full, all its edges, once). Returns a row for each round, with the edges that it drew."""
    began = time.perf_counter()
    keyed = [stored(k, "kept") for k in prefilter(inputs, params).dfs]
    counted = stored(count_strata(keyed), "strata")
    strata = stored(P.allocate(counted, first).withColumn("done", F.lit(0).cast("bigint")), "sized")
    sums, out = None, []
    for k in range(max_rounds):
        fresh = E.partials(sampler.sample_edges(keyed, strata, seed, family=family, after="done"), value)
        if sums is not None:  # of strata that are full now, the earlier draws are left out
            fresh = sums.join(strata.where("not full or done >= b").select("jk"), "jk", "left_semi").unionByName(fresh).groupBy("jk").agg(*(F.sum(c).alias(c) for c in ("n", "m", "s1", "s2")))
        sums = stored(fresh, "partials")
        rows = E.with_strata(sums, strata)
        drawn = strata.agg(F.sum(F.when(F.col("full") & (F.col("done") < F.col("b")), F.col("b")).otherwise(F.col("b") - F.col("done"))).cast("bigint")).first()[0] or 0
        row = E.clt(rows).first().asDict() | {"round": k + 1, "drawn": drawn}
        out.append(row)
        if row["error_bound"] <= target or deadline_s is not None and time.perf_counter() - began > deadline_s:
            break
        sized = P.size_for_error(counted, E.stratum_sigma(rows), target, kind="total_abs").join(strata.select("jk", F.col("b").alias("done")), "jk")
        # no stratum loses draws that it has; full ones stay full
        b = F.greatest("b", "done")
        strata = stored(sized.withColumn("b", b).withColumn("full", F.col("b") >= F.col("edges")).drop("sigma"), "sized")
    return out


def cascade(first: JoinInput, hub: DataFrame, hub_keys: tuple[str, str], second: JoinInput, value: Column, hub_columns: list[str], fraction: float, seed: int = 42, family: str = "xx", params=None) -> DataFrame:
    """A chain first ⋈ hub ⋈ second over two attributes: the hub is filtered on both, the first input is looked up (one row for each of its keys) as the hub's payload, and the edge of many rows, hub ⋈ second, is sampled."""
    hub_first = JoinInput(hub, [hub_keys[0]], [hub_keys[1], *hub_columns])
    kept = prefilter([first, hub_first], params)
    side = kept.dfs[1].join(kept.dfs[0], "jk").drop("jk")
    middle = JoinInput(side, [hub_keys[1]], [*hub_columns, *first.columns])
    keyed = prefilter([middle, second], params).dfs
    return estimate(keyed, P.allocate(count_strata(keyed), fraction), value, seed=seed, family=family)


def explain(inputs: list[JoinInput], value: Column, budget: Budget | None = None, fraction: float | None = None, model: LatencyModel | None = None, params=None) -> dict:
    """What would be done: mode, fraction, filter, predicted latency and the plan's text."""
    model = model or LatencyModel()
    kept = prefilter(inputs, params)
    whole = count_strata(kept.dfs).agg(F.coalesce(F.sum("edges"), F.lit(0)).cast("double").alias("edges"), F.count("*").alias("m")).first()
    mode = "sampled" if budget is None else choose_mode(whole.edges, whole.m, budget, model)
    share = fraction if fraction is not None else P.fraction_for_latency(budget.latency_s, 0.0, whole.edges, model) if budget and budget.latency_s else 1.0
    plan = budgeted_join(inputs, value, fraction=min(share, 0.999), params=kept.params)
    return {"mode": mode, "fraction": share, "filter_bits": kept.params.m_bits, "hashes": kept.params.h, "strata": whole.m, "edges": whole.edges, "predicted_s": model.predict(share * whole.edges), "plan": plan._jdf.queryExecution().toString() if hasattr(plan, "_jdf") else ""}
