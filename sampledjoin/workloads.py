"""The experiment workloads on the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .model import FilterParams, JoinInput
from .operators import baselines as BL
from .operators.filtering import participating, prefilter
from .operators.strata import count_strata
from .plans import budget as P
from .plans.engine import estimate, exact, exact_join
from .plans.measures import shuffle_model
from .sources.datagen import dial
from .sources.io import load, stored

MONEY = "decimal(18,2)"


def money(c: str) -> Column:
    return F.col(c).cast(MONEY)


def customer_orders(spark: SparkSession, sf_dir: str) -> tuple[list[JoinInput], Column]:
    """Order price plus customer balance."""
    c = load(spark, sf_dir, "customer").select("c_custkey", money("c_acctbal").alias("c_acctbal"))
    o = load(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", money("o_totalprice").alias("o_totalprice"))
    return [JoinInput(c, ["c_custkey"], ["c_acctbal"], "customer"), JoinInput(o, ["o_custkey"], ["o_orderkey", "o_totalprice"], "orders")], F.col("o_totalprice") + F.col("c_acctbal")


#: The low-overlap cut of each kind of event, by shares of the number u of users.
CUTS = {"click": "user_id * 10 < u * 4", "purchase": "user_id * 3 >= u AND user_id * 30 <= u * 22", "error": "user_id * 30 >= u * 11"}


def flows(spark: SparkSession, sf_dir: str, low: bool = False) -> tuple[list[JoinInput], Column]:
    """Users in all three kinds of event; ``low``: the low-overlap cut of W3."""
    e = load(spark, sf_dir, "events")
    if low:
        e = e.crossJoin(F.broadcast(e.agg((F.max("user_id") + 1).alias("u"))))  # one row
    out = []
    for i, (kind, cut) in enumerate(CUTS.items(), 1):
        own = e.where((F.col("event_type") == kind) & (F.expr(cut) if low else F.lit(True)))
        out.append(JoinInput(own.select("user_id", F.col("event_id").alias(f"e{i}"), F.col("value").cast("decimal(18,4)").alias(f"v{i}")), ["user_id"], [f"e{i}", f"v{i}"], kind))
    return out, F.col("v1") + F.col("v2") + F.col("v3")


_TABLES: dict[tuple, DataFrame] = {}


def as_table(df: DataFrame, *name: object) -> DataFrame:
    """``df`` written once for each application. The dial is a condition on the join key: as a plan, the optimizer would infer each input's dial for the others, and the baselines would filter too."""
    key = (df.sparkSession.sparkContext.applicationId, *name)
    if key not in _TABLES:
        _TABLES[key] = stored(df, "dialled")
    return _TABLES[key]


def by_flag(spark: SparkSession, sf_dir: str, flags: str = "RA", key: str = "l_partkey", p: int = 100, tables: bool = False) -> tuple[list[JoinInput], Column]:
    """Lineitem split by return flag, its overlap dialled by p; ``tables``: the dialled inputs as tables, for comparing methods."""
    li = load(spark, sf_dir, "lineitem")
    out = []
    for i, f in enumerate(flags):
        own = dial(li.where(F.col("l_returnflag") == f), key, i, len(flags), p)
        own = as_table(own, sf_dir, flags, key, p, i) if tables else own
        out.append(JoinInput(own.select(key, F.col("l_orderkey").alias(f"o{i + 1}"), F.col("l_linenumber").alias(f"l{i + 1}"), money("l_extendedprice").alias(f"v{i + 1}")), [key], [f"v{i + 1}", f"o{i + 1}", f"l{i + 1}"], f"lineitem_{f}"))
    return out, sum((F.col(f"v{i + 1}") for i in range(1, len(flags))), F.col("v1"))


def by_line(spark: SparkSession, sf_dir: str, n: int = 4, p: int = 100, tables: bool = False) -> tuple[list[JoinInput], Column]:
    """Lineitem split by line number; ``tables`` as of ``by_flag``."""
    li = load(spark, sf_dir, "lineitem")
    out = []
    for i in range(n):
        own = dial(li.where(F.col("l_linenumber") == i + 1), "l_partkey", i, n, p)
        own = as_table(own, sf_dir, "line", n, p, i) if tables else own
        out.append(JoinInput(own.select("l_partkey", F.col("l_orderkey").alias(f"o{i + 1}"), money("l_extendedprice").alias(f"v{i + 1}")), ["l_partkey"], [f"v{i + 1}", f"o{i + 1}"], f"line{i + 1}"))
    return out, sum((F.col(f"v{i + 1}") for i in range(1, n)), F.col("v1"))


def ratings(spark: SparkSession, sf_dir: str, pair: bool = False) -> list[JoinInput]:
    """Lines up to the sixth as ratings, seventh lines as the qualifying list; by part, or by part and supplier."""
    li = load(spark, sf_dir, "lineitem")
    keys = ["l_partkey", "l_suppkey"] if pair else ["l_partkey"]
    train = JoinInput(li.where("l_linenumber <= 6"), keys, ["l_quantity"], "train")
    listed = li.where("l_linenumber = 7").select(*keys)
    return [train, JoinInput(listed.distinct() if pair else listed, keys, [], "qualifying")]


def nations(spark: SparkSession, sf_dir: str) -> tuple[list[JoinInput], Column]:
    """Few heavy strata."""
    c = load(spark, sf_dir, "customer").select("c_nationkey", "c_custkey", money("c_acctbal").alias("c_acctbal"))
    s = load(spark, sf_dir, "supplier").select("s_nationkey", "s_suppkey", money("s_acctbal").alias("s_acctbal"))
    return [JoinInput(c, ["c_nationkey"], ["c_acctbal", "c_custkey"], "customer"), JoinInput(s, ["s_nationkey"], ["s_acctbal", "s_suppkey"], "supplier")], F.col("c_acctbal") + F.col("s_acctbal")


def tpch(spark: SparkSession, sf_dir: str, which: str) -> DataFrame:
    """The joins of three decision-support queries."""
    c, o, li, n = (load(spark, sf_dir, t) for t in ("customer", "orders", "lineitem", "nation"))
    lines = li.select("l_orderkey", money("l_extendedprice").alias("price"))
    if which == "q4":
        j = o.select("o_orderkey").join(lines, F.col("o_orderkey") == F.col("l_orderkey"))
        return j.agg(F.count("*").alias("n_rows"), F.countDistinct("o_orderkey").alias("n_orders"))
    j = c.select("c_custkey", "c_nationkey").join(o.select("o_custkey", "o_orderkey"), F.col("c_custkey") == F.col("o_custkey")).join(lines, F.col("o_orderkey") == F.col("l_orderkey"))
    if which == "q10":
        j = j.join(F.broadcast(n.select("n_nationkey", "n_name")), F.col("c_nationkey") == F.col("n_nationkey"))
    return j.agg(F.count("*").alias("n_rows"), F.round(F.sum("price").cast("double"), 2).alias("price"))


def tpch_filtered(spark: SparkSession, sf_dir: str, which: str) -> DataFrame:
    """W10 to W12 with the filtering stage: orders pass the customers' and the lines' filters, lines the orders' that are left. The answers are those of ``tpch``."""
    c, o, li, n = (load(spark, sf_dir, t) for t in ("customer", "orders", "lineitem", "nation"))
    lines = JoinInput(li.select("l_orderkey", money("l_extendedprice").alias("price")), ["l_orderkey"], ["price"], "lineitem")
    if which != "q4":
        both = prefilter([JoinInput(c, ["c_custkey"], ["c_nationkey"], "customer"), JoinInput(o, ["o_custkey"], ["o_orderkey"], "orders")]).dfs
        o = exact_join([both[1], both[0]]).drop("jk")
    orders = JoinInput(o, ["o_orderkey"], ["c_nationkey"] if which != "q4" else [], "orders")
    joined = exact_join(prefilter([orders, lines]).dfs)
    if which == "q4":
        return joined.agg(F.count("*").alias("n_rows"), F.countDistinct("jk").alias("n_orders"))
    if which == "q10":
        joined = joined.join(F.broadcast(n.select("n_nationkey", "n_name")), F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.agg(F.count("*").alias("n_rows"), F.round(F.sum("price").cast("double"), 2).alias("price"))


def run(inputs: list[JoinInput], value: Column, method: str, fraction: float = 0.1, seed: int = 42, ids: list[list[str]] | None = None, params: FilterParams | None = None, confidence: float = 0.95, family: str = "xx") -> DataFrame:
    """(estimate, sampled_edges) of a workload by a method: during, filter_only, native, repartition, broadcast, postjoin, prejoin, prejoin_stratified, hybrid."""
    keyed = [i.keyed() for i in inputs]
    flat = [c for k in keyed for c in k.columns if c != "jk"]
    if method == "during":
        kept = prefilter(inputs, params).dfs
        return estimate(kept, P.allocate(count_strata(kept), fraction), value, seed=seed, confidence=confidence, family=family)
    if method == "filter_only":
        return exact(prefilter(inputs, params).dfs, value)
    if method in ("native", "repartition", "broadcast", "union"):
        joined = {"native": BL.native_join, "repartition": BL.repartition_join, "broadcast": BL.broadcast_join, "union": BL.union_join}[method](keyed)
        return joined.agg(F.sum(value).cast("double").alias("estimate"), F.count("*").alias("sampled_edges"))
    if method == "postjoin":
        return BL.postjoin_sum(BL.repartition_join(keyed), fraction, value, seed, flat)
    if method == "prejoin":
        return BL.prejoin_sum(keyed, fraction, value, ids or [[c for c in k.columns if c != "jk"] for k in keyed], seed)
    if method == "prejoin_stratified":
        return BL.prejoin_stratified(keyed, fraction, value, seed, family)
    if method == "hybrid":
        return BL.hybrid_postjoin(keyed, fraction, value, flat, seed)
    raise ValueError(method)


def overlap_row(inputs: list[JoinInput], value: Column | None = None) -> DataFrame:
    """(total_rows, joining_rows, strata, edges) of a workload."""
    keyed = [i.keyed() for i in inputs]
    kept = participating(inputs)
    rows = None
    for a, b in zip(keyed, kept, strict=True):
        r = a.agg(F.count("*").alias("t")).crossJoin(b.agg(F.count("*").alias("j")))
        rows = r if rows is None else rows.unionAll(r)
    both = rows.agg(F.sum("t").cast("bigint").alias("total_rows"), F.sum("j").cast("bigint").alias("joining_rows"))
    s = count_strata(keyed).agg(F.count("*").alias("strata"), F.coalesce(F.sum("edges"), F.lit(0)).cast("bigint").alias("edges"))
    return both.crossJoin(s)


def shuffle_simulation(spark: SparkSession, sf_dir: str, workers: int = 10, m_bits: int = 1 << 16) -> DataFrame:
    """Modelled bytes of three joins against the number of inputs at 1 % and against the overlap of three inputs."""
    out = None
    for n, p in [(2, 1), (3, 1), (4, 1), (3, 2), (3, 4), (3, 6), (3, 8), (3, 10), (3, 40)]:
        inputs, _ = by_line(spark, sf_dir, n, p)
        counts = None
        for i, (a, b) in enumerate(zip([x.keyed() for x in inputs], participating(inputs), strict=True), 1):
            c = a.agg(F.count("*").alias(f"t{i}")).crossJoin(b.agg(F.count("*").alias(f"j{i}")))
            counts = c if counts is None else counts.crossJoin(c)
        rows, kept, width = [F.col(f"t{i + 1}") for i in range(n)], [F.col(f"j{i + 1}") for i in range(n)], [24.0] * n
        row = counts.select(
            F.lit(n).alias("n_inputs"), F.lit(p).alias("p"), F.round(shuffle_model("repartition", rows, width, workers), 1).alias("repartition_bytes"),
            F.round(shuffle_model("broadcast", rows, width, workers), 1).alias("broadcast_bytes"), F.round(shuffle_model("filtered", rows, width, workers, m_bits, kept), 1).alias("filtered_bytes"),
        )
        out = row if out is None else out.unionAll(row)
    return out


def exact_value(inputs: list[JoinInput], value: Column) -> DataFrame:
    return exact_join([i.keyed() for i in inputs]).agg(F.count("*").alias("n_rows"), F.round(F.sum(value).cast("double"), 2).alias("total"))
