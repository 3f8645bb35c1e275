"""Times the headline queries, method by method, and prints one line of JSON.

queries: seconds by workload and method. shuffle_bytes and broadcast_bytes: what the stages of one run wrote to shuffles, and what was sent to every node. loss: |estimate - exact| / exact.
latency_budgets: seconds asked for and taken, and the bound relative to the estimate. coverage: the share of seeds whose 95 % interval holds the exact value. ratios: baseline over ours: seconds and, for the joins without sampling, shuffled bytes, and these with what is broadcast to NODES nodes.
``python bench.py --cores`` runs the two-way join on 2, 4 and 8 threads instead, each in a session of its own.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from sampledjoin import workloads as W
from sampledjoin.model import Budget, LatencyModel
from sampledjoin.operators.strata import count_strata
from sampledjoin.plans import budget as P
from sampledjoin.plans import engine
from sampledjoin.plans.measures import coverage, moved_bytes, ratio, timed

#: workload: (inputs and value, share of the edges or None, the operator, its baselines)
WORKLOADS = {
    "two_way_p1": (lambda s, d: W.by_flag(s, d, "RA", p=1, tables=True), None, "filter_only", ("repartition", "native")),
    "two_way_p10": (lambda s, d: W.by_flag(s, d, "RA", p=10, tables=True), None, "filter_only", ("repartition", "native")),
    "three_way_p1": (lambda s, d: W.by_flag(s, d, "RAN", p=1, tables=True), None, "filter_only", ("repartition", "native")),
    "four_way_p1": (lambda s, d: W.by_line(s, d, 4, 1, tables=True), None, "filter_only", ("repartition", "native")),
    "parts_s10": (lambda s, d: W.by_flag(s, d, "RA"), 0.1, "during", ("postjoin",)),
    "suppliers_s10": (lambda s, d: W.by_flag(s, d, "RA", "l_suppkey"), 0.1, "during", ("postjoin", "native")),
    "suppliers_s1": (lambda s, d: W.by_flag(s, d, "RA", "l_suppkey"), 0.01, "during", ()),
    "flows_s10": (lambda s, d: W.flows(s, d), 0.1, "during", ("postjoin", "prejoin", "prejoin_stratified", "native")),
    "orders_s60": (lambda s, d: W.customer_orders(s, d), 0.6, "during", ("hybrid",)),
}


#: Nodes that a broadcast is counted for.
NODES = 10


def session(cpus: str) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def main() -> None:
    cpus, sf_dir = os.environ.get("BENCH_CPUS", "8"), os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = session(cpus)
    took, moved, sent, loss, ratios = {}, {}, {}, {}, {}
    for name, (make, share, ours, baselines) in WORKLOADS.items():
        inputs, value = make(spark, sf_dir)
        keyed = [i.keyed() for i in inputs]
        exact = engine.exact(keyed, value).first()["estimate"] if share else None  # also reads the files once
        for method in (ours, *baselines):
            run = lambda: W.run(inputs, value, method, share or 0.1)  # noqa: B023,E731
            timed(run())  # compiles
            t = time.perf_counter()
            timed(run())
            key = f"{name}_{method}"
            took[key] = round(time.perf_counter() - t, 3)
            moved[key], sent[key] = moved_bytes(run())
            if share and method != "native":
                loss[key] = round(abs(run().first()["estimate"] - exact) / abs(exact), 6)
        every = lambda m: moved[f"{name}_{m}"] + NODES * sent[f"{name}_{m}"]  # noqa: B023,E731
        ratios |= {f"{name}_{ours}_vs_{b}": [round(ratio(took[f"{name}_{b}"], took[f"{name}_{ours}"]), 2), *([] if share else [round(ratio(moved[f"{name}_{b}"], moved[f"{name}_{ours}"]), 2), round(ratio(every(b), every(ours)), 2)])] for b in baselines}
    # a latency budget: the cost of an edge from the two supplier samples, then what is asked for against what it took
    inputs, value = WORKLOADS["suppliers_s10"][0](spark, sf_dir)
    edges = count_strata([i.keyed() for i in inputs]).agg(F.sum("edges").cast("double")).first()[0]
    model = LatencyModel(max(1e-9, (took["suppliers_s10_during"] - took["suppliers_s1_during"]) / (0.09 * edges)), 0.5)
    budgets = {}
    for desired in (4.0, 6.0, 8.0):
        t = time.perf_counter()
        row = engine.budgeted_join(inputs, value, budget=Budget(latency_s=desired), model=model).first()
        budgets[desired] = {"took": round(time.perf_counter() - t, 2), "mode": row["mode"], "sampled_edges": row["sampled_edges"], "relative_bound": round(row["error_bound"] / abs(row["estimate"]), 6)}
    inputs, value = W.customer_orders(spark, sf_dir)
    keyed = [i.keyed() for i in inputs]
    strata, exact = P.allocate(count_strata(keyed), 0.1), engine.exact(keyed, value).first()["estimate"]
    runs = [tuple(engine.estimate(keyed, strata, value, seed=s).select("lower", "upper").first()) for s in range(10)]
    print(json.dumps({"metric": "sum of headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "shuffle_bytes": moved, "broadcast_bytes": sent, "loss": loss, "ratios": ratios, "latency_budgets": budgets, "coverage": coverage(runs, exact), "sf": sf_dir.rstrip("/").rpartition("sf")[2]}))
    spark.stop()


def one_size(cpus: str) -> None:
    """Seconds of the two-way join at an overlap dial of 1, by method."""
    spark = session(cpus)
    inputs, value = W.by_flag(spark, os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), "RA", p=1, tables=True)
    took = {}
    for method in ("filter_only", "repartition", "native"):
        timed(W.run(inputs, value, method))
        took[method] = round(timed(W.run(inputs, value, method)), 3)
    print(json.dumps({"cpus": int(cpus), "seconds": took}))
    spark.stop()


if __name__ == "__main__":
    if "--cores" in sys.argv:
        for n in ("2", "4", "8"):
            subprocess.run([sys.executable, __file__, "--one", n], check=True)
    elif "--one" in sys.argv:
        one_size(sys.argv[sys.argv.index("--one") + 1])
    else:
        main()
