"""What only larger or heavier tables show, at a size of seconds."""

from __future__ import annotations

import pytest
from pyspark.errors import AnalysisException
from pyspark.sql import functions as F

from sampledjoin import experiments, registry
from sampledjoin.operators import relational, sampler
from sampledjoin.operators.strata import count_strata
from sampledjoin.plans import budget as P


def test_grouped_sampling_draws_for_all_keys_in_one_pass(spark):
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        keyed = [spark.range(9000).select((F.col("id") % 3000).alias("jk"), F.col("id").alias("x")), spark.range(12000).select((F.col("id") % 4000).alias("jk"), F.when(F.col("id") % 5 > 0, F.col("id")).alias("y"))]
        strata = P.allocate(count_strata(keyed), 0.4)
        edges = sampler.sample_edges(keyed, strata, strategy="grouped")
        assert "CoGroups" not in edges._jdf.queryExecution().toString()
        got = edges.groupBy("jk").agg(F.count("*").alias("n"), F.max(F.col("x") % 3000).alias("x"), F.max(F.col("y") % 4000).alias("y")).join(strata, "jk")
        assert got.count() == 3000 and got.where("n <> b or x <> jk or y <> jk").isEmpty()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)


def test_self_join_meets_no_pairs_of_two_buckets(spark, tmp_path):
    rows = [(k, n) for k in (*range(-30, 9000, 3), 5, 6, 6, None) for n in (0, 1, None)]
    spark.createDataFrame(rows, "c_custkey bigint, c_nationkey int").write.parquet(f"{tmp_path}/customer.parquet")
    df = registry.QUERIES["join_self"](spark, str(tmp_path))
    keys = [k for k, n in rows if n == 0 and k is not None]
    want = 2 * sum(a < b for a in keys for b in keys)
    assert df.first().n == want and "bucket" in df._jdf.queryExecution().toString()


def test_cardinality_of_more_keys_than_the_least_filter_holds(spark, tmp_path):
    spark.range(900_000).select(F.col("id").alias("o_custkey"), F.col("id").alias("o_orderkey"), F.lit(1.0).alias("o_totalprice")).write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame([(1, 1.0)], "c_custkey bigint, c_acctbal double").write.parquet(f"{tmp_path}/customer.parquet")
    assert tuple(registry.QUERIES["filter_cardinality"](spark, str(tmp_path)).first()) == (900_000, True)


def test_draws_of_one_heavy_stratum_are_made_in_several_tasks(spark):
    strata = spark.createDataFrame([(1, 3000, 3000, 900_000)], "jk bigint, n_1 bigint, n_2 bigint, b bigint").select("*", F.lit(9_000_000).cast("decimal(38,0)").alias("edges"), F.lit(False).alias("full"))
    drawn = sampler.draw_edges(strata, 2)
    tasks = drawn.groupBy(F.spark_partition_id()).count().collect()
    assert len(tasks) > 1 and sum(r["count"] for r in tasks) == 900_000
    side = spark.range(3000).select(F.lit(1).cast("bigint").alias("jk"), F.col("id").alias("x"), (F.col("id") + 1).alias("pos"))
    assert "BuildLeft" not in sampler.attach(drawn, [side])._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", ["calibration", "poisson_inputs", "poisson_rows", "udtf_draws"])
def test_queries_read_the_given_tables(spark, name):
    with pytest.raises(AnalysisException):
        {**registry.QUERIES, **experiments.QUERIES}[name](spark, "/no/such/folder").collect()
