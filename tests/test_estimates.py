"""Estimates by group and over nulls, budgets, SQL forms, sources and streams that the worked examples do not reach."""

from __future__ import annotations

import math

import duckdb
import pytest
from pyspark.sql import functions as F

from sampledjoin import experiments, registry
from sampledjoin import workloads as W
from sampledjoin.model import Budget, FilterParams, JoinInput, LatencyModel
from sampledjoin.operators import estimators as E
from sampledjoin.operators import filters, sampler
from sampledjoin.operators.filtering import key_estimate, prefilter
from sampledjoin.operators.strata import count_strata
from sampledjoin.plans import budget as P
from sampledjoin.plans import engine, measures, sqlfront
from sampledjoin.plans.feedback import FeedbackStore
from sampledjoin.sources import io
from sampledjoin.streaming import streams

def value():
    return F.col("v1") + F.col("v2")


@pytest.fixture(scope="module")
def grouped(spark):
    """Two groups whose values lie apart, ten keys; every third value is null."""
    a = [(k, float(10 * g + i % 7), g) for k in range(10) for g in (0, 1) for i in range(20)]
    b = [(k, float(i) if i % 3 else None) for k in range(10) for i in range(15)]
    left = spark.createDataFrame(a, "k bigint, v1 double, g int").withColumn("r1", F.monotonically_increasing_id()).cache()
    right = spark.createDataFrame(b, "k bigint, v2 double").withColumn("r2", F.monotonically_increasing_id()).cache()
    return [JoinInput(left, ["k"], ["v1", "g", "r1"], "left"), JoinInput(right, ["k"], ["v2", "r2"], "right")]


@pytest.mark.parametrize(("agg", "options"), [*((a, o) for a in E.AGGREGATES for o in ({}, {"estimator": "ht", "dedupe": "distinct"})), ("avg", {"dedupe": "resample"})])
def test_intervals_of_groups_hold_the_truth(grouped, agg, options):
    exact = {r.g: r.estimate for r in engine.budgeted_join(grouped, value(), agg, sample=False, group_by=["g"]).collect()}
    whole = engine.budgeted_join(grouped, value(), agg, sample=False).first().estimate
    rows = engine.budgeted_join(grouped, value(), agg, fraction=0.4, group_by=["g"], confidence=0.9999, **options).collect()
    assert len(rows) == 2 and len(exact) == 2
    for r in rows:
        assert r.lower <= exact[r.g] <= r.upper and r.error_bound > 0 and abs(r.estimate - exact[r.g]) < 0.2 * abs(exact[r.g])
    one = engine.budgeted_join(grouped, value(), agg, fraction=0.4, confidence=0.9999, **options).first()
    assert one.lower <= whole <= one.upper


def test_group_intervals_cover_as_often_as_they_say(grouped):
    keyed = [i.keyed() for i in grouped]
    strata = P.allocate(count_strata(keyed), 0.1)
    truth = {r.g: r.estimate for r in engine.exact(keyed, value(), "avg", ["g"]).collect()}
    runs = []
    for seed in range(8):
        runs += [r.lower <= truth[r.g] <= r.upper for r in engine.estimate(keyed, strata, value(), "avg", seed=seed, group_by=["g"]).collect()]
    assert sum(runs) >= 13  # of 16, at 95 %


def test_a_full_sample_is_exact_for_every_aggregate(grouped):
    keyed = [i.keyed() for i in grouped]
    strata = P.allocate(count_strata(keyed), 1.0)
    for agg in E.AGGREGATES:
        exact = {r.g: r.estimate for r in engine.exact(keyed, value(), agg, ["g"]).collect()}
        for options in ({}, {"estimator": "ht"}):
            for r in engine.estimate(keyed, strata, value(), agg, group_by=["g"], **options).collect():
                assert math.isclose(r.estimate, exact[r.g], rel_tol=1e-9) and r.error_bound < 1e-6 * abs(r.estimate)


def test_what_has_no_estimate_is_refused(grouped):
    for options in ({"agg": "max"}, {"agg": "avg", "estimator": "ht", "level": "stratum"}, {"agg": "sum", "dedupe": "distinct"}):
        with pytest.raises(ValueError):
            engine.budgeted_join(grouped, value(), fraction=0.3, **options).collect()
    with pytest.raises(TypeError):
        engine.budgeted_join(grouped, value(), fraction=0.3, no_such_option=1)


def test_samples_for_a_latency_stay_within_it(grouped):
    keyed = [i.keyed() for i in grouped]
    counted = count_strata(keyed)
    for edges in (20.0, 35.0, 600.0, 3000.0):
        got = P.allocate_within(counted, edges).agg(F.sum("b")).first()[0]
        assert got <= max(edges, 20) and got >= min(edges, 6000) * 0.8 - 20
    rows = P.overdrawn(counted, 0.001).first()
    assert rows.overdrawn and rows.least == 20


def test_refinement_adds_draws_to_those_it_has(grouped):
    whole = F.coalesce("v2", F.lit(0.0)) + F.col("v1")
    rounds = engine.refine(grouped, whole, target=1.0, first=0.05, max_rounds=3)
    assert len(rounds) >= 2 and rounds[0]["drawn"] == rounds[0]["sampled_edges"] and rounds[-1]["error_bound"] <= rounds[0]["error_bound"]
    keyed = [i.keyed() for i in grouped]
    strata = P.allocate(count_strata(keyed), 0.5).withColumn("done", F.floor(F.col("b") / 2)).cache()
    first = sampler.sample_edges(keyed, strata.withColumn("b", F.col("done")).withColumn("full", F.lit(False)))
    rest = sampler.sample_edges(keyed, strata, after="done")
    every = sampler.sample_edges(keyed, strata)
    key = lambda df: sorted(tuple(r) for r in df.select("jk", "draw", "r1", "r2").collect())
    assert key(first.unionByName(rest)) == key(every)


def test_feedback_of_another_filter_is_not_used(spark, grouped, tmp_path):
    store = FeedbackStore(spark, f"file://{tmp_path}/sigma")
    cut = [JoinInput(grouped[0].df.where("g = 1"), ["k"], ["v1", "g", "r1"], "left"), grouped[1]]
    names = [engine.plan_text(i[0].df) for i in (grouped, cut)]
    assert names[0] != names[1]
    whole, budget = F.coalesce("v2", F.lit(0.0)) + F.col("v1"), Budget(error=0.05, error_kind="relative")
    for inputs in (grouped, cut):
        r = engine.budgeted_join(inputs, whole, budget=budget, store=store, model=LatencyModel(1e-3)).first()
        assert r.mode == "exact"  # few edges
    sized = engine.choose_mode(1e9, 10, budget, LatencyModel())
    assert sized == "sampled"


def test_deviations_are_stored_from_the_sample_that_answers(spark, grouped, tmp_path, monkeypatch):
    store = FeedbackStore(spark, f"file://{tmp_path}/sigma")
    monkeypatch.setattr(engine, "choose_mode", lambda *a, **k: "sampled")
    whole = F.coalesce("v2", F.lit(0.0)) + F.col("v1")
    runs = [engine.budgeted_join(grouped, whole, budget=Budget(error=3000.0, error_kind="total_abs"), store=store).first() for _ in range(2)]
    exact = engine.budgeted_join(grouped, whole, sample=False).first().estimate
    assert all(abs(r.estimate - exact) < 9000 and r.sampled_edges < 6000 for r in runs)
    assert spark.read.parquet(f"file://{tmp_path}/sigma").select("run").distinct().count() == 2


def test_sql_forms(spark):
    spark.createDataFrame([(1, 1, 2.0), (1, 2, 3.0), (2, 1, 5.0)], "a1 int, a2 int, x double").createOrReplaceTempView("ta")
    spark.createDataFrame([(1, 1, 10.0), (2, 2, 20.0), (2, 1, 30.0)], "b1 int, b2 int, y double").createOrReplaceTempView("tb")
    spark.createDataFrame([(1, 7), (2, 8)], "b1 int, c2 int").createOrReplaceTempView("tc")
    one = lambda q: sqlfront.sql(spark, q).first().estimate
    assert one("SELECT SUM(x + y) FROM ta, tb WHERE a1 = tb.b1 AND a2 = b2") == 2 + 10 + 5 + 30
    assert one("SELECT COUNT(*) FROM ta, tb WHERE a1 = tb.b1 AND y BETWEEN 15 AND 25") == 1
    assert one("SELECT SUM(x) FROM ta, tb, tc WHERE a1 = tb.b1 AND tb.b1 = tc.b1 AND (c2 = 7 OR c2 = 9)") == 5
    for bad in (
        "SELECT SUM(x) FROM ta, tb, tc WHERE a1 = tb.b1 AND b2 = c2",  # a chain over two attributes
        "SELECT SUM(x) FROM ta, tb WHERE a1 = b2 OR a2 = b2",
        "SELECT SUM(x) FROM ta, tb, tc WHERE a1 = b1 AND b1 = c2",  # whose b1
        "SELECT SUM(x) FROM ta, tb WHERE x > 1",
    ):
        with pytest.raises(ValueError):
            one(bad)
    assert sqlfront.conjuncts("a = 'x AND y' AND b BETWEEN 1 AND 2 AND (c = 1 AND d = 2)") == ["a = 'x AND y'", "b BETWEEN 1 AND 2", "(c = 1 AND d = 2)"]


def test_filters_are_sized_for_all_inputs_and_keep_their_rate(spark):
    big, small = spark.range(60_000).withColumnRenamed("id", "jk"), spark.range(59_000, 61_000).withColumnRenamed("id", "jk")
    assert abs(key_estimate([big, small]) - 60_000) < 6000
    p = filters.size_filter(60_000, 0.01)
    assert p.words > filters.BLOCK_WORDS / 2 and filters.word_rate(60_000, p.m_bits, p.h) <= 0.01
    kept = prefilter([JoinInput(big, ["jk"]), JoinInput(small, ["jk"])]).dfs
    assert 1000 <= kept[0].count() <= 1000 + 59_000 * 0.015 and 1000 <= kept[1].count() <= 1000 + 40
    assert filters.size_filter(10**12, 0.01).m_bits == 8 * filters.MAX_BYTES
    quality = measures.filter_quality(big, kept[0], [small]).first()
    assert quality.false_negatives == 0 and quality.rate <= 0.012


@pytest.mark.parametrize("rows", [0, 1 << 10])
def test_packed_filters_probe_like_words(spark, monkeypatch, rows):
    monkeypatch.setattr(filters, "BLOCK_WORDS", 8)
    monkeypatch.setattr(filters, "ROW_WORDS", rows)
    p = FilterParams(1 << 12, 3)
    keys = spark.range(300).withColumnRenamed("id", "jk")
    table = filters.build_filter(keys.where("jk % 3 = 0"), p)
    words = {r.slot: r.mask for r in table.collect()}
    probes = keys.select("jk", filters._slot(F.col("jk"), p).alias("s"), filters._mask(filters._bits(F.col("jk"), p)).alias("m")).collect()
    assert {r.jk for r in filters.apply_filter(keys, table, p).collect()} == {r.jk for r in probes if words.get(r.s, 0) & r.m == r.m}
    assert filters.pack(table, p).count() == p.words // 8
    both = filters.join_filter([keys, keys.where("jk < 100")], p)
    assert {0, 50, 99} <= {r.jk for r in filters.apply_filter(keys, both, p, dense=True).collect()} and filters.apply_filter(keys, both, p, dense=True).count() < 130


def test_baselines_move_all_rows_of_dialled_tables(spark, sf):
    inputs, prices = W.by_flag(spark, sf, "RA", p=1, tables=True)
    ours, theirs = (measures.shuffle_measured(W.run(inputs, prices, m)) for m in ("filter_only", "repartition"))
    again = W.by_flag(spark, sf, "RA", p=1, tables=True)[0]
    assert theirs > 0 and ours > 0 and [i.df.inputFiles() for i in again] == [i.df.inputFiles() for i in inputs]


def test_either_stage_can_be_left_out(grouped):
    exact = engine.budgeted_join(grouped, value(), sample=False).first()
    plain = engine.budgeted_join(grouped, value(), filter=False, sample=False).first()
    assert math.isclose(exact.estimate, plain.estimate) and exact.mode == plain.mode == "exact"
    a, b = (engine.budgeted_join(grouped, value(), fraction=0.3, filter=f).first() for f in (True, False))
    assert math.isclose(a.estimate, b.estimate) and a.sampled_edges == b.sampled_edges
    ordered = prefilter(grouped, ordered=True).dfs
    assert [k.count() for k in ordered] == [k.count() for k in prefilter(grouped).dfs]


def test_measures():
    assert measures.ratio(4.0, 2.0) == 2.0 and measures.ratio(1.0, 0.0) == float("inf")
    assert measures.budget_error(5.0, 7.5) == 2.5 and measures.coverage([(0, 2), (2, 3)], 1.0) == 0.5


def test_breakdown_times_each_stage(spark):
    took = measures.breakdown({"a": lambda: spark.range(10), "b": lambda: spark.range(10).groupBy("id").count()})
    assert list(took) == ["a", "b"] and min(took.values()) > 0


def test_sources_and_sinks(spark, tmp_path):
    rows = spark.createDataFrame([(1, "a", 0.5), (2, "b", 1.5)], "k int, s string, x double")
    for fmt in ("csv", "json", "parquet"):
        io.save(rows, f"file://{tmp_path}/t.{fmt}", fmt)
        assert sorted(io.load(spark, f"file://{tmp_path}", "t", fmt, "k int, s string, x double").collect()) == sorted(rows.collect())
    io.save(rows, f"file://{tmp_path}/p", partition_by=["s"])
    assert spark.read.parquet(f"file://{tmp_path}/p").where("s = 'a'").count() == 1
    io.save(rows, table="bucketed_rows", bucket_by=(2, ["k"]), mode="overwrite")
    t = io.catalog_table(spark, "bucketed_rows")
    plan = t.join(t.withColumnRenamed("x", "x2").hint("merge"), "k")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and io.load(spark, "", "bucketed_rows", "catalog").count() == 2
    io.save(rows, fmt="noop")
    (tmp_path / "q.txt").write_text("1:\n10,2005-01-01\n11\n22:\n10\n")
    assert sorted(tuple(r) for r in io.read_query_list(spark, f"file://{tmp_path}/q.txt").collect()) == [(1, 10), (1, 11), (22, 10)]


def test_windows_and_state_of_streams(spark, sf, tmp_path):
    schema = spark.read.parquet(f"{sf}/events.parquet").schema
    spark.read.parquet(f"{sf}/events.parquet").repartition(2).write.parquet(f"{tmp_path}/events")
    stream = lambda: streams.events_stream(spark, f"{tmp_path}/events", schema)
    e = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    last = lambda df: df.groupBy("start", "end", "event_type").agg(F.max("n").alias("n"))  # noqa: E731  the newest state of each window
    sliding = last(streams.replay(spark, streams.windowed(stream(), "sliding", late="40 days"), "e1", f"{tmp_path}/c1", "update"))
    assert sliding.agg(F.sum("n")).first()[0] == 2 * e.count()
    session = streams.replay(spark, streams.windowed(stream(), "session", late="40 days"), "e2", f"{tmp_path}/c2", "complete")
    assert session.agg(F.sum("n")).first()[0] == e.count()
    pairs = streams.replay(spark, streams.interval_join(stream().where("event_type = 'click'"), stream().where("event_type = 'error'"), late="40 days"), "e3", f"{tmp_path}/c3")
    a, b = (e.where(f"event_type = '{t}'").select(F.col("user_id").alias(f"u{t[0]}"), F.col("ts").alias(f"t{t[0]}")) for t in ("click", "error"))
    assert pairs.count() == a.join(b, F.expr("uc = ue AND te >= tc AND te <= tc + INTERVAL 1 HOUR")).count()
    moments = streams.replay(spark, streams.running_moments(stream()), "e4", f"{tmp_path}/c4", "update")
    newest = {r.user_id: r.n for r in moments.groupBy("user_id").agg(F.max("n").alias("n")).collect()}
    assert newest == {r.user_id: r.n for r in e.groupBy("user_id").agg(F.count("*").alias("n")).collect()}


QUICK = [n for n in experiments.QUERIES if n.startswith(("group_by_", "sql_")) or "_nulls" in n] + ["latency_sweep", "feedback_second_run", "bootstrap_sigma", "both_budgets", "flow_losses", "ratings_methods", "poisson_rows", "overlap_moved_rows"]


@pytest.mark.parametrize("name", [*QUICK, "co_resample", "co_array", "co_salted", "co_clt_stdev", "filter_counting", "filter_no_false_neg", "sample_aggregate", "udtf_draws"])
def test_queries_agree_with_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("customer", "orders", "lineitem", "events", "nation"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    got = (registry.QUERIES | experiments.QUERIES)[name](spark, sf).toPandas()
    want = con.sql((registry.SQL | experiments.SQL)[name]).df()[list(got.columns)]
    text = lambda d: sorted(map(str, d.itertuples(index=False, name=None)))
    assert text(got) == text(want)
