"""Worked examples, measures and invariants of the sampled join."""

from __future__ import annotations

import math
from decimal import Decimal

import duckdb
import pytest
from pyspark.sql import functions as F

from sampledjoin import registry
from sampledjoin import workloads as W
from sampledjoin.functions.quantiles import t_quantile, z_quantile
from sampledjoin.model import Budget, FilterParams, InfeasibleError, JoinInput, LatencyModel
from sampledjoin.operators import estimators as E
from sampledjoin.operators import filters, sampler
from sampledjoin.operators.filtering import chained_prefilter, overlap_fraction, prefilter
from sampledjoin.operators.strata import count_strata
from sampledjoin.plans import budget as P
from sampledjoin.plans import engine, sqlfront
from sampledjoin.plans.feedback import FeedbackStore
from sampledjoin.plans.measures import coverage, shuffle_measured
from sampledjoin.sources.datagen import poisson_inputs
from sampledjoin.sources.io import read_grouped_text
from sampledjoin.streaming import streams

PARAMS = FilterParams(1 << 14, 4)


def two(spark, left, right):
    a = spark.createDataFrame(left, "k bigint, v1 double")
    b = spark.createDataFrame(right, "k int, v2 double")
    return [JoinInput(a, ["k"], ["v1"], "a"), JoinInput(b, ["k"], ["v2"], "b")]


@pytest.fixture(scope="module")
def one_key(spark):
    return two(spark, [(1, float(i)) for i in range(3)], [(1, float(10 * i)) for i in range(4)])


def test_filter_keeps_common_keys_and_counts_overlap(spark):
    inputs = two(spark, [(k, 1.0) for k in (0, 1, 2, 3)] + [(None, 1.0)], [(k, 1.0) for k in (0, 1, 8, 9)] + [(None, 2.0)])
    for df in prefilter(inputs, PARAMS).dfs:
        assert {0, 1} <= {r.jk for r in df.collect()}
    row = overlap_fraction(inputs).first()
    assert (row.total_rows, row.joining_rows, row.overlap) == (8, 4, 0.5)
    assert overlap_fraction(inputs, "filter", PARAMS).first().joining_rows >= 4


@pytest.mark.parametrize("layout", ["word", "classic", "counting"])
def test_filter_layouts_lose_nothing(spark, layout):
    p = FilterParams(1 << 13, 4, layout=layout)
    inputs = two(spark, [(k, 1.0) for k in range(0, 300)], [(k, 1.0) for k in range(250, 600)])
    for df in prefilter(inputs, p).dfs:
        kept = {r.jk for r in df.collect()}
        assert set(range(250, 300)) <= kept and len(kept) < 80


def test_filter_merges_agree_and_union_is_or(spark):
    a, b = (spark.range(lo, hi).withColumnRenamed("id", "jk") for lo, hi in ((0, 200), (150, 400)))
    want = sorted(filters.build_filter(a, PARAMS).collect())
    assert sorted(filters.build_filter(a, PARAMS, "tree", 3).collect()) == want == sorted(filters.build_filter(a, PARAMS, "driver").collect())
    both = filters.unite([filters.build_filter(a, PARAMS), filters.build_filter(b, PARAMS)])
    assert sorted(both.collect()) == sorted(filters.build_filter(a.union(b), PARAMS).collect())
    assert sorted(filters.intersect([filters.build_filter(a, PARAMS), filters.build_filter(b, PARAMS)]).collect()) == sorted(filters.intersect([filters.build_filter(b, PARAMS), filters.build_filter(a, PARAMS)]).collect())
    est = filters.estimate_cardinality(filters.build_filter(a, FilterParams(1 << 14, 4, layout="classic")), PARAMS).first()
    assert abs(est["keys"] - 200) < 20
    assert filters.bitmap_filter(a, PARAMS).count() >= 1


def test_counting_filter_forgets_and_scalable_grows(spark):
    p = FilterParams(1 << 13, 3, layout="counting")
    a, b = spark.range(100).withColumnRenamed("id", "jk"), spark.range(50).withColumnRenamed("id", "jk")
    left = filters.remove_from_counting(filters.build_filter(a, p), b, p)
    kept = {r.jk for r in filters.apply_filter(a, left, p).collect()}
    assert set(range(50, 100)) <= kept and len(kept) < 60
    s = filters.ScalableFilter(100, 0.01)
    s.add(a)
    s.add(spark.range(1000, 1200).withColumnRenamed("id", "jk"))
    got = {r.jk for r in s.apply(spark.range(3000).withColumnRenamed("id", "jk")).collect()}
    assert set(range(100)) | set(range(1000, 1200)) <= got and len(got) < 420


def test_chained_filter_keeps_what_joins(spark):
    inputs = two(spark, [(k, 1.0) for k in range(100)], [(k, 1.0) for k in range(90, 200)])
    for df in chained_prefilter(inputs, PARAMS):
        assert set(range(90, 100)) <= {r.jk for r in df.collect()}


def test_draws_stay_among_the_edges_and_reach_all(spark, one_key):
    keyed = [i.keyed() for i in one_key]
    strata = P.clamp(count_strata(keyed), F.lit(11))
    rows = sampler.sample_edges(keyed, strata).collect()
    assert len(rows) == 11 and {(r.v1, r.v2) for r in rows} <= {(float(i), 10.0 * j) for i in range(3) for j in range(4)}
    seen = set()
    for seed in range(12):
        seen |= {(r.pos_1, r.pos_2) for r in sampler.draw_edges(strata, 2, seed).collect()}
    assert len(seen) == 12
    full = sampler.sample_edges(keyed, P.clamp(count_strata(keyed), F.lit(99))).collect()
    assert len({(r.v1, r.v2) for r in full}) == len(full) == 12


def test_dedupe_gives_different_edges(spark, one_key):
    keyed = [i.keyed() for i in one_key]
    for b in (3, 8):
        strata = P.clamp(count_strata(keyed), F.lit(b))
        rows = sampler.sample_edges(keyed, strata, dedupe="resample").collect()
        assert len({(r.v1, r.v2) for r in rows}) == len(rows) == b
    assert len(sampler.sample_edges(keyed, P.clamp(count_strata(keyed), F.lit(8)), dedupe="distinct").collect()) <= 8


def test_sizes_from_budgets():
    model = LatencyModel(4.16e-9)
    assert P.remaining(120, 42) == 78
    assert math.isclose(P.fraction_for_latency(120, 42, 1e11, model), 0.1875)
    assert P.check(1e10, 78, model) == "exact" and P.check(1e11, 78, model) == "sampled"
    with pytest.raises(InfeasibleError):
        P.check(1e11, P.remaining(40, 42), model)
    assert math.isclose(z_quantile(0.95) ** 2, 3.84, abs_tol=0.002)
    assert math.isclose(t_quantile(0.975, 5), 2.5706, abs_tol=1e-4) and math.isclose(t_quantile(0.975, 6), 2.4469, abs_tol=1e-4)


def test_error_sizes_round_trip(spark):
    df = spark.createDataFrame([(10.0,), (0.0,)], "sigma double")
    b = [r[0] for r in df.select(P.error_size(F.col("sigma"), 1.0)).collect()]
    assert b == [385, 0]
    assert df.where("sigma > 0").select(P.mean_error(F.col("sigma"), F.lit(385.0))).first()[0] <= 1.0
    strata = spark.createDataFrame([(1, Decimal(100)), (2, Decimal(3))], "jk bigint, edges decimal(38,0)")
    got = {r.jk: (r.b, r.full) for r in P.allocate(strata, 0.1875, 1).collect()}
    assert got == {1: (18, False), 2: (1, False)}


@pytest.fixture(scope="module")
def two_strata(spark):
    rows = [(1, v) for v in (5.0, 7.0, 9.0, 7.0)] + [(2, v) for v in (10.0, 12.0, 14.0)]
    edges = spark.createDataFrame(rows, "jk bigint, v double")
    strata = spark.createDataFrame([(1, Decimal(12), 4, False), (2, Decimal(6), 3, False)], "jk bigint, edges decimal(38,0), b bigint, full boolean")
    return E.with_strata(E.partials(edges, F.col("v")), strata)


def test_estimates_of_two_strata(two_strata):
    for variance, bound in (("published", 88), ("with_replacement", 144), ("without_replacement", 88)):
        r = E.clt(two_strata, variance=variance).first()
        assert math.isclose(r.estimate, 156) and r.dof == 5
        assert math.isclose(r.error_bound, 2.5706 * math.sqrt(bound), rel_tol=0.01)
    assert math.isclose(E.clt(two_strata, "avg").first().estimate, 156 / 18)
    assert E.clt(two_strata, "count").first().estimate == 18
    for level, var in (("stratum", 7296), ("item", 88)):
        r = E.horvitz_thompson(two_strata, level).first()
        assert math.isclose(r.estimate, 156) and r.dof == 6 and math.isclose(r.error_bound, 2.4469 * math.sqrt(var), rel_tol=0.01)


def test_cross_terms_vanish_for_independent_keys(spark, two_strata):
    pi = spark.createDataFrame([(1, 2, 1 / 6), (2, 1, 1 / 6)], "jk_k bigint, jk_l bigint, pi double")
    a, b = E.horvitz_thompson(two_strata, "stratum").first(), E.horvitz_thompson(two_strata, "stratum", pi_joint=pi).first()
    assert math.isclose(a.error_bound, b.error_bound, rel_tol=1e-9)


def test_item_variance_equals_the_double_sum(two_strata):
    ys, B = [5.0, 7.0, 9.0, 7.0], 12
    b = len(ys)
    pi, pij = b / B, b * (b - 1) / (B * (B - 1))
    total = sum((1 - pi) / pi**2 * y * y for y in ys) + sum((pij - pi * pi) / (pi * pi) * x * y / pij for i, x in enumerate(ys) for j, y in enumerate(ys) if i != j)
    mean = sum(ys) / b
    assert math.isclose(total, B * (B - b) * sum((y - mean) ** 2 for y in ys) / (b - 1) / b)


def test_coverage_and_order_of_variances(spark, sf):
    inputs, value = W.customer_orders(spark, sf)
    keyed = [i.keyed() for i in inputs]
    for k in keyed:
        k.cache()
    strata = P.allocate(count_strata(keyed), 0.6).cache()
    exact = engine.exact(keyed, value).first().estimate
    runs = {"with_replacement": [], "published": []}
    for seed in range(12):
        edges = E.with_strata(E.partials(sampler.sample_edges(keyed, strata, seed), value), strata)
        for kind, out in runs.items():
            r = E.clt(edges, variance=kind).first()
            out.append((r.lower, r.upper))
    widths = {k: sum(hi - lo for lo, hi in v) for k, v in runs.items()}
    assert coverage(runs["with_replacement"], exact) >= 0.8 and widths["published"] < widths["with_replacement"]


def test_full_fraction_is_exact_and_filter_only_too(spark, sf):
    inputs, value = W.customer_orders(spark, sf)
    exact = engine.exact([i.keyed() for i in inputs], value).first()
    for r in (engine.budgeted_join(inputs, value, fraction=1.0, params=PARAMS).first(), engine.budgeted_join(inputs, value, sample=False, params=PARAMS).first()):
        assert math.isclose(r.estimate, exact.estimate) and r.error_bound == 0


def test_budgets_end_to_end(spark, sf, tmp_path):
    inputs, value = W.flows(spark, sf)
    exact = engine.budgeted_join(inputs, value, sample=False, params=PARAMS).first().estimate
    store = FeedbackStore(spark, f"file://{tmp_path}/sigma")
    kw = {"params": PARAMS, "store": store, "model": LatencyModel(1e-3), "name": "flows"}
    r = engine.budgeted_join(inputs, value, budget=Budget(latency_s=600, error=0.05, error_kind="relative"), **kw)
    assert r.first().mode in ("exact", "clt_with_replacement") and abs(r.first().estimate - exact) / exact < 0.2
    slow = LatencyModel(1.0)
    assert engine.budgeted_join(inputs, value, budget=Budget(latency_s=2000.0), params=PARAMS, model=slow).first().sampled_edges < 2001
    with pytest.raises(InfeasibleError):
        engine.budgeted_join(inputs, value, budget=Budget(latency_s=1.0), params=PARAMS, model=slow)
    assert "predicted_s" in engine.explain(inputs, value, fraction=0.1, params=PARAMS)
    rounds = engine.refine(inputs, value, target=0.05 * exact, params=PARAMS)
    assert rounds[-1]["error_bound"] <= 0.1 * exact


def test_store_keeps_latest(spark, tmp_path):
    store = FeedbackStore(spark, f"file://{tmp_path}/s")
    assert store.load("q") is None
    for x in (1.0, 2.0):
        store.save("q", spark.createDataFrame([(1, 5, x), (2, 1, 0.0)], "jk bigint, n bigint, sigma double"))
    assert [tuple(r) for r in store.load("q").collect()] == [(1, 5, 2.0)]


def test_clause_parser(spark, sf):
    text, b = sqlfront.split_clause("SELECT SUM(x) FROM a, b WHERE a.k = b.k WITHIN 120 SECONDS OR ERROR 0.01 CONFIDENCE 95%")
    assert text.endswith("a.k = b.k") and (b.latency_s, b.error, b.confidence) == (120.0, 0.01, 0.95)
    assert sqlfront.split_clause("SELECT 1")[1] is None


def test_edge_cases(spark):
    apart = two(spark, [(1, 1.0)], [(2, 1.0)])
    r = engine.budgeted_join(apart, F.col("v1") + F.col("v2"), fraction=0.5, params=PARAMS).first()
    assert (r.estimate, r.error_bound) == (0.0, 0.0)
    same = two(spark, [(1, 3.0)] * 20, [(1, -3.0)] * 20)
    r = engine.budgeted_join(same, F.col("v1") + F.col("v2"), fraction=0.1, params=PARAMS).first()
    assert r.estimate == 0 and r.error_bound == 0


def test_same_seed_same_sample_at_any_partitioning(spark, sf):
    inputs, value = W.customer_orders(spark, sf)
    a = engine.budgeted_join(inputs, value, fraction=0.3, params=PARAMS).first().estimate
    dealt = [JoinInput(i.df.repartition(7), i.keys, i.columns) for i in inputs]
    assert math.isclose(a, engine.budgeted_join(dealt, value, fraction=0.3, params=PARAMS).first().estimate)


def test_prejoin_sampling_loses_more(spark, sf):
    inputs, value = W.flows(spark, sf)
    exact = W.run(inputs, value, "native").first().estimate
    loss = lambda m: sum(abs(W.run(inputs, value, m, 0.1, s, params=PARAMS).first().estimate - exact) for s in range(3))
    assert loss("during") < loss("prejoin")


def test_measured_shuffle_and_poisson(spark):
    inputs = poisson_inputs(spark, 2, 5.0, 200, 0.1)
    assert shuffle_measured(W.run(inputs, F.col("v1") + F.col("v2"), "native")) > 0
    assert W.overlap_row(inputs).first().strata >= 18
    m = P.calibrate(spark, (200, 400), 1)
    assert m.beta > 0


def test_grouped_text(spark, tmp_path):
    (tmp_path / "m1.txt").write_text("7:\n10,3,2005-01-01\n11,5,2005-02-01\n")
    got = sorted(tuple(r)[:3] for r in read_grouped_text(spark, f"file://{tmp_path}").collect())
    assert got == [(7, 10, 3.0), (7, 11, 5.0)]


def test_streams(spark, sf, tmp_path):
    schema = spark.read.parquet(f"{sf}/events.parquet").schema
    spark.read.parquet(f"{sf}/events.parquet").repartition(3).write.parquet(f"{tmp_path}/events")
    stream = lambda: streams.events_stream(spark, f"{tmp_path}/events", schema)
    out = streams.replay(spark, streams.windowed(stream(), "tumbling", late="40 days"), "w1", f"{tmp_path}/c1", "update")
    assert out.count() > 0
    keyed = stream().withColumn("jk", F.col("user_id"))
    streams.incremental_partials(keyed, f"{tmp_path}/parts", f"{tmp_path}/c2").awaitTermination()
    assert streams.merged_partials(spark, f"{tmp_path}/parts").agg(F.sum("n")).first()[0] == 1000
    table = filters.build_filter(spark.range(5).withColumnRenamed("id", "jk"), PARAMS)
    kept = streams.replay(spark, streams.filter_stream(keyed, table, PARAMS), "w2", f"{tmp_path}/c3")
    assert {r.jk for r in kept.select("jk").distinct().collect()} >= {0, 1, 2, 3, 4}
    once = streams.replay(spark, streams.dedupe_stream(stream(), ["event_id"], "40 days"), "w3", f"{tmp_path}/c4")
    assert once.count() == 1000


@pytest.mark.parametrize("name", ["co_clt_sum", "co_ht_item", "net3_clt_sum", "co_dedupe_edges", "filter_bits_replay", "part_overlap_sweep", "join_asof", "tradeoff_curve"])
def test_queries_agree_with_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("customer", "orders", "lineitem", "events", "nation"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    got = registry.QUERIES[name](spark, sf).toPandas()
    want = con.sql(registry.SQL[name]).df()[list(got.columns)]
    text = lambda d: sorted(map(str, d.itertuples(index=False, name=None)))
    assert text(got) == text(want)
