"""Relational operators around the method, each as ``f(spark, sf_dir)``, with SQL that answers the same."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.io import load

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def text(sql: str):
    """A query given as SQL text that Spark and other engines read alike."""

    def q(spark: SparkSession, sf_dir: str) -> DataFrame:
        named = {t: load(spark, sf_dir, t) for t in TABLES if re.search(rf"\b{t}\b", sql)}
        return spark.sql(_named(sql, named), **named)

    return q


def _named(sql: str, named: dict) -> str:
    """Table names after FROM and JOIN become parameters, so that no view is left behind."""
    return re.sub(rf"\b(FROM|JOIN)\s+({'|'.join(named)})\b", r"\1 {\2}", sql)


def join_inner(hint: str):
    def q(spark, sf_dir):
        o, li = load(spark, sf_dir, "orders"), load(spark, sf_dir, "lineitem")
        right = F.broadcast(o.select("o_orderkey", "o_orderpriority")) if hint == "broadcast" and o.limit(2_000_001).count() <= 2_000_000 else o.select("o_orderkey", "o_orderpriority").hint("merge" if hint == "broadcast" else hint)
        return li.join(right, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("decimal(18,2)")).cast("double").alias("quantity"))

    return q


_JOIN = "SELECT o_orderpriority, CAST(count(*) AS BIGINT) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority"


def join_outer(how: str):
    def q(spark, sf_dir):
        o, li = load(spark, sf_dir, "orders").select("o_orderkey"), load(spark, sf_dir, "lineitem").where("l_quantity > 25").groupBy("l_orderkey").agg(F.count("*").alias("n"))
        return o.join(li, F.col("o_orderkey") == F.col("l_orderkey"), how).agg(F.count("*").alias("n_rows"), F.count("l_orderkey").alias("matched"), F.count("o_orderkey").alias("with_order"))

    return q


def _outer(how: str) -> str:
    return f"SELECT CAST(count(*) AS BIGINT) AS n_rows, CAST(count(l_orderkey) AS BIGINT) AS matched, CAST(count(o_orderkey) AS BIGINT) AS with_order FROM (SELECT o_orderkey FROM orders) o {how} JOIN (SELECT l_orderkey, count(*) AS n FROM lineitem WHERE l_quantity > 25 GROUP BY l_orderkey) l ON o_orderkey = l_orderkey"


def join_semi(kind: str):
    def q(spark, sf_dir):
        o, li = load(spark, sf_dir, "orders"), load(spark, sf_dir, "lineitem").select("l_orderkey")
        return o.join(li, F.col("o_orderkey") == F.col("l_orderkey"), kind).groupBy("o_orderstatus").agg(F.count("*").alias("n"))

    return q


def join_range(spark, sf_dir, width: float = 0.05):
    """Pairs of a click and a purchase of a user whose values differ by at most ``width``: values fall into bands of that width, and each click meets three bands."""
    e = load(spark, sf_dir, "events")
    band = F.floor(F.col("value") / width).cast("bigint")
    a = e.where("event_type = 'click'").select("user_id", F.col("value").alias("a"), F.explode(F.array(band - 1, band, band + 1)).alias("band"))
    b = e.where("event_type = 'purchase'").select("user_id", F.col("value").alias("b"), band.alias("band"))
    return a.join(b, ["user_id", "band"]).where(F.abs(F.col("a") - F.col("b")) <= width).groupBy("user_id").agg(F.count("*").alias("n"))


def join_interval(spark, sf_dir):
    """Purchases within an hour after a click of the same user: time falls into hours, and each click meets two."""
    e = load(spark, sf_dir, "events").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    hour = 3_600_000_000
    a = e.where("event_type = 'click'").select("user_id", F.col("s").alias("a"), F.explode(F.array(F.expr(f"s div {hour}"), F.expr(f"s div {hour} + 1"))).alias("h"))
    b = e.where("event_type = 'purchase'").select("user_id", F.col("s").alias("b"), F.expr(f"s div {hour}").alias("h"))
    return a.join(b, ["user_id", "h"]).where((F.col("b") >= F.col("a")) & (F.col("b") <= F.col("a") + hour)).groupBy("user_id").agg(F.count("*").alias("n"))


def join_asof(spark, sf_dir):
    """The last click before each purchase, by user: both in one sorted window, without a join."""
    e = load(spark, sf_dir, "events").where("event_type in ('click', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "click", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "click", F.struct("ts", "event_id")), ignorenulls=True).over(w)
    return e.withColumn("click", last).where("event_type = 'purchase'").select("event_id", F.coalesce("click.event_id", F.lit(-1)).cast("bigint").alias("click_id"))


_ASOF = "SELECT p.event_id, coalesce((SELECT c.event_id FROM events c WHERE c.event_type = 'click' AND c.user_id = p.user_id AND c.ts <= p.ts ORDER BY c.ts DESC, c.event_id DESC LIMIT 1), -1) AS click_id FROM events p WHERE p.event_type = 'purchase'"


def join_salted(spark, sf_dir, salts: int = 8):
    """A join whose one side is hot: it is dealt over ``salts`` parts and the other side repeated for each."""
    e = load(spark, sf_dir, "events")
    a = e.where("event_type = 'click'").select("user_id", F.pmod(F.xxhash64("event_id"), F.lit(salts)).alias("salt"))
    b = e.where("event_type = 'error'").select("user_id", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(salts - 1).cast("bigint"))).alias("salt"))
    return a.join(b, ["user_id", "salt"]).groupBy("user_id").agg(F.count("*").alias("n"))


def join_composite(spark, sf_dir):
    li = load(spark, sf_dir, "lineitem")
    a = li.where("l_returnflag = 'R'").select("l_partkey", "l_suppkey")
    b = li.where("l_returnflag = 'A'").select("l_partkey", "l_suppkey")
    return a.join(b, ["l_partkey", "l_suppkey"]).agg(F.count("*").alias("n_rows"), F.countDistinct("l_partkey", "l_suppkey").alias("n_keys"))


#: Keys of a bucket of the self-join.
BUCKET = 4096


def join_self(spark, sf_dir):
    """Pairs of customers of a nation, the first of the smaller key: a self-join of each bucket of keys, and one of the buckets' counts for pairs of two buckets."""
    k = F.col("c_custkey")
    rows = load(spark, sf_dir, "customer").select("c_nationkey", k, (k - F.pmod(k, F.lit(BUCKET))).alias("bucket")).where("c_nationkey is not null and c_custkey is not null").groupBy("c_nationkey", "bucket", "c_custkey").agg(F.count("*").cast("decimal(19,0)").alias("n"))
    counts = rows.groupBy("c_nationkey", "bucket").agg(F.sum("n").cast("decimal(19,0)").alias("n"))
    pairs = lambda df, on, less: df.alias("a").join(df.alias("b"), [F.col(f"a.{c}") == F.col(f"b.{c}") for c in on] + [F.col(f"a.{less}") < F.col(f"b.{less}")]).agg(F.sum(F.col("a.n") * F.col("b.n")).alias("n"))
    both = pairs(rows, ["c_nationkey", "bucket"], "c_custkey").unionAll(pairs(counts, ["c_nationkey"], "bucket"))
    return both.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("n"))


def join_theta(spark, sf_dir):
    """Suppliers beside the nations of a smaller number, by no equality: a nested loop over the nations, which are 25 at every scale."""
    s, n = load(spark, sf_dir, "supplier").select("s_nationkey"), load(spark, sf_dir, "nation").select("n_nationkey")
    return s.join(F.broadcast(n), F.col("s_nationkey") > F.col("n_nationkey")).groupBy("n_nationkey").agg(F.count("*").alias("n"))


def sample_bernoulli(spark, sf_dir):
    from .baselines import unit_hash

    li = load(spark, sf_dir, "lineitem").where(unit_hash(F.col("l_orderkey"), F.col("l_linenumber"), 42) < 0.1)
    return li.groupBy("l_returnflag").agg(F.count("*").alias("n"))


def sample_strat(spark, sf_dir):
    from .baselines import unit_hash

    share = F.when(F.col("event_type") == "click", 0.5).when(F.col("event_type") == "error", 0.2).otherwise(0.05)
    return load(spark, sf_dir, "events").where(unit_hash(F.col("event_id"), 42) < share).groupBy("event_type").agg(F.count("*").alias("n"))


_UNIT = "CAST(('0x' || substr(md5(concat_ws('|', {})), 1, 15)) AS BIGINT) / 1152921504606846976.0"


def sample_aggregate(spark, sf_dir):
    """A stratified sum over one table with its bound: the method with a single input."""
    from ..model import JoinInput
    from ..plans.budget import allocate
    from ..plans.engine import estimate
    from .strata import count_strata

    li = load(spark, sf_dir, "lineitem").select("l_partkey", "l_orderkey", "l_linenumber", F.col("l_extendedprice").cast("decimal(18,2)").alias("price"))
    keyed = [JoinInput(li, ["l_partkey"], ["price", "l_orderkey", "l_linenumber"]).keyed()]
    est = estimate(keyed, allocate(count_strata(keyed), 0.3), F.col("price"), family="portable")
    return est.select(F.round("estimate", 2).alias("estimate"), "sampled_edges", F.col("total_edges").cast("bigint").alias("total_edges"))


def cube(kind: str):
    def q(spark, sf_dir):
        li = load(spark, sf_dir, "lineitem")
        g = li.cube("l_returnflag", "l_linestatus") if kind == "cube" else li.rollup("l_returnflag", "l_linestatus")
        return g.agg(F.count("*").alias("n"), F.grouping_id().cast("int").alias("level"))

    return q


def pivot(spark, sf_dir):
    e = load(spark, sf_dir, "events")
    return e.groupBy(F.dayofmonth("ts").alias("day")).pivot("event_type", ["click", "error", "purchase"]).agg(F.count(F.lit(1))).fillna(0)


def collect(spark, sf_dir):
    """Order keys of each customer, in order; a group is a customer's orders."""
    o = load(spark, sf_dir, "orders")
    return o.groupBy("o_custkey").agg(F.array_join(F.transform(F.array_sort(F.collect_list("o_orderkey")), lambda x: x.cast("string")), ",").alias("keys"))


def win_rank(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    o = load(spark, sf_dir, "orders")
    return o.select("o_orderkey", F.row_number().over(w).alias("rn"), F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("rk"), F.dense_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("dr"))


def win_lag_lead(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = load(spark, sf_dir, "events")
    return e.select("event_id", F.lag("event_id", 1, -1).over(w).alias("before"), F.lead("event_id", 2, -1).over(w).alias("after"), F.first("event_id").over(w).alias("first_id"), F.last("event_id").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("last_id"))


def win_frames(spark, sf_dir):
    o = load(spark, sf_dir, "orders").withColumn("price", F.col("o_totalprice").cast("decimal(18,2)")).withColumn("day", F.datediff(F.col("o_orderdate"), F.lit("1995-01-01").cast("date")))
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    r = Window.partitionBy("o_custkey").orderBy("day").rangeBetween(-90, 0)
    return o.select("o_orderkey", F.sum("price").over(w.rowsBetween(-2, 0)).cast("double").alias("last_three"), F.sum("price").over(w.rowsBetween(Window.unboundedPreceding, 0)).cast("double").alias("running"), F.sum("price").over(r).cast("double").alias("ninety_days"))


def topk_per_group(spark, sf_dir):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return load(spark, sf_dir, "customer").withColumn("r", F.row_number().over(w)).where("r <= 3").select("c_nationkey", "c_custkey", "r")


def set_op(kind: str):
    def q(spark, sf_dir):
        a = load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("k"))
        b = load(spark, sf_dir, "orders").select(F.col("o_custkey").alias("k"))
        return {"union_all": a.unionAll(b), "union": a.union(b).distinct(), "intersect": a.intersect(b), "except": a.subtract(b), "except_all": b.exceptAll(a), "intersect_all": b.intersectAll(a)}[kind].agg(F.count("*").alias("n"), F.coalesce(F.sum("k"), F.lit(0)).cast("bigint").alias("s"))

    return q


def _set(op: str, a: str = "SELECT c_custkey AS k FROM customer", b: str = "SELECT o_custkey AS k FROM orders") -> str:
    return f"SELECT CAST(count(*) AS BIGINT) AS n, CAST(coalesce(sum(k), 0) AS BIGINT) AS s FROM ({a} {op} {b})"


def fn_vector(spark, sf_dir):
    """Norm and product with the neighbour in the array functions."""
    e = load(spark, sf_dir, "embeddings").withColumn("v", F.transform("embedding", lambda x: x.cast("double")))
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda x, y: x + y)
    return e.select("vec_id", F.round(F.sqrt(total(F.transform("v", lambda x: x * x))), 6).alias("norm"), F.round(total(F.zip_with("v", F.reverse("v"), lambda x, y: x * y)), 6).alias("mirror"), F.size("v").alias("dim"))


def fn_map(spark, sf_dir):
    n = load(spark, sf_dir, "nation")
    m = n.groupBy("n_regionkey").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("n_nationkey", "n_name")))).alias("m"))
    return m.select("n_regionkey", F.size("m").alias("n"), F.array_join(F.transform(F.map_keys("m"), lambda x: x.cast("string")), ",").alias("keys"))


def fn_text(spark, sf_dir):
    words = load(spark, sf_dir, "benchmark").select("item_id", F.explode(F.split("text", " ")).alias("w"))
    return words.groupBy("item_id").agg(F.count("*").alias("n_words"), F.countDistinct("w").alias("n_distinct"))


def fn_pages(spark, sf_dir):
    p = load(spark, sf_dir, "pages")
    return p.groupBy(F.parse_url("url", F.lit("PROTOCOL")).alias("scheme")).agg(F.count("*").alias("n"), F.sum(F.char_length("html")).alias("chars"))


def agg_approx(spark, sf_dir):
    e = load(spark, sf_dir, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.countDistinct("user_id").alias("n_users"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("h"))
    return e.select("n_users", ((F.abs(F.col("a") - F.col("n_users")) <= 0.1 * F.col("n_users")) & (F.abs(F.col("h") - F.col("n_users")) <= 0.1 * F.col("n_users"))).alias("close"))


def agg_quantile(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 6).alias("median"), F.round(F.percentile("value", 0.9), 6).alias("p90"))


def stratified_udtf(spark, sf_dir):
    """Draw positions from a table function, beside a lateral join: for each number of orders that a customer has, as draws depend on the sizes only."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="pos_1 bigint, pos_2 bigint")
    class Draws:
        def eval(self, n_1: int, n_2: int, b: int, seed: int):
            import hashlib

            for d in range(b):
                h = int(hashlib.md5(f"{n_1}|{n_2}|{d}|{seed}".encode()).hexdigest()[:15], 16)
                yield 1 + h % n_1, 1 + (h // n_1) % n_2

    spark.udtf.register("draws", Draws)
    sizes = "SELECT DISTINCT CAST(count(*) AS INT) AS k FROM {orders} WHERE o_custkey IS NOT NULL GROUP BY o_custkey"
    return spark.sql(f"SELECT k, pos_1, pos_2 FROM ({sizes}) t, LATERAL draws(k, 7, 10, 42)", orders=load(spark, sf_dir, "orders"))


def stratum_udaf(spark, sf_dir):
    """A deviation by a vectorised aggregate function, beside the built-in one that the engine uses."""
    @F.pandas_udf("double")
    def spread(v: pd.Series) -> float:
        return float(v.std(ddof=1)) if len(v) > 1 else 0.0

    return load(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.round(spread("o_totalprice"), 2).alias("spread"))


_SAMPLE = f"""WITH r AS (SELECT l_partkey AS jk, CAST(l_extendedprice AS DECIMAL(18,2)) AS price, row_number() OVER (PARTITION BY l_partkey ORDER BY CAST(l_extendedprice AS DECIMAL(18,2)), l_orderkey, l_linenumber) AS pos, count(*) OVER (PARTITION BY l_partkey) AS n FROM lineitem),
st AS (SELECT DISTINCT jk, n, least(greatest(floor(0.3 * n + 1e-9), 2), n) AS b FROM r),
d AS (SELECT jk, n, b, unnest(range(1, CAST(b AS BIGINT) + 1)) AS draw FROM st),
e AS (SELECT jk, n, b, CASE WHEN b >= n THEN draw ELSE 1 + {'CAST((' + "'0x' || substr(md5(concat_ws('|', jk, draw, 1, 42)), 1, 15)" + ') AS BIGINT)'} % n END AS pos FROM d)
SELECT round(sum(s), 2) AS estimate, CAST(sum(m) AS BIGINT) AS sampled_edges, (SELECT CAST(count(*) AS BIGINT) FROM lineitem) AS total_edges
FROM (SELECT CAST(e.n AS DOUBLE) / e.b * CAST(sum(price) AS DOUBLE) AS s, count(*) AS m FROM e JOIN r ON r.jk = e.jk AND r.pos = e.pos GROUP BY e.jk, e.n, e.b)"""
_BASIC = "SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS quantity, round(CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2)) * CAST(1 - l_discount AS DECIMAL(18,2))) AS DOUBLE), 2) AS revenue, CAST(CAST(min(l_shipdate) AS DATE) AS STRING) AS first_day, CAST(CAST(max(l_shipdate) AS DATE) AS STRING) AS last_day FROM lineitem GROUP BY l_returnflag, l_linestatus"
_MOMENTS = "SELECT event_type, CAST(count(*) AS BIGINT) AS n, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS sd, round(var_pop(value), 4) AS var, min(value) AS least, max(value) AS most FROM events GROUP BY event_type"
_PROJECT = "SELECT l_orderkey, l_linenumber, CAST(CAST(l_extendedprice AS DECIMAL(18,2)) * CAST(1 - l_discount AS DECIMAL(18,2)) AS DOUBLE) AS net, CASE WHEN l_quantity < 10 THEN 'small' WHEN l_quantity < 30 THEN 'medium' ELSE 'large' END AS class FROM lineitem"
_FILTER = "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 100000 AND 200000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderstatus LIKE 'F%' AND o_orderdate IS NOT NULL"
_DISTINCT = "SELECT event_type, CAST(count(DISTINCT user_id) AS BIGINT) AS n_users FROM events GROUP BY event_type"
_FILTERED = "SELECT o_orderpriority, CAST(count(*) FILTER (WHERE o_orderstatus = 'F') AS BIGINT) AS filled, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY o_orderpriority HAVING count(*) > 10"
_SETS = "SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())"
_SORT = "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5"
_STRING = "SELECT c_custkey, upper(substr(c_name, 1, 4)) AS a, CAST(length(c_name) AS BIGINT) AS n, concat(c_mktsegment, '-', c_custkey) AS b, trim(concat('  ', c_name, ' ')) AS c, md5(c_name) AS d, replace(c_name, '#', '_') AS e, regexp_replace(c_name, '[0-9]+', 'N') AS f FROM customer"
_MATH = "SELECT l_orderkey, l_linenumber, CAST(floor(l_extendedprice / 100) AS BIGINT) AS f, round(pow(l_discount, 2), 6) AS p, round(sqrt(l_quantity), 6) AS s, round(ln(l_quantity + 1), 6) AS l, abs(l_orderkey - l_partkey) AS a FROM lineitem"
_Q4 = "SELECT o_orderpriority, CAST(count(*) AS BIGINT) AS n FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 45) GROUP BY o_orderpriority"
_IN = "SELECT CAST(count(*) AS BIGINT) AS n FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 300000) AND c_nationkey NOT IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 0)"
_SCALAR = "SELECT CAST(count(*) AS BIGINT) AS n FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer)"
_CORRELATED = "SELECT CAST(count(*) AS BIGINT) AS n FROM customer c WHERE c.c_acctbal > (SELECT avg(d.c_acctbal) FROM customer d WHERE d.c_nationkey = c.c_nationkey)"
_CTE = "WITH t AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), u AS (SELECT n, count(*) AS customers FROM t GROUP BY n) SELECT CAST(n AS BIGINT) AS n, CAST(customers AS BIGINT) AS customers FROM u"
_LATERAL = "SELECT n_nationkey, x.c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2) x"
_SELF = "SELECT CAST(count(*) AS BIGINT) AS n FROM customer a JOIN customer b ON a.c_nationkey = b.c_nationkey AND a.c_custkey < b.c_custkey"


def _both(sql: str) -> tuple:
    return text(sql), sql


OPERATORS: dict[str, tuple] = {
    "project_exprs": _both(_PROJECT),
    "filter_predicates": _both(_FILTER),
    "filter_null_safe": (lambda s, d: load(s, d, "nation").where(F.col("n_regionkey").eqNullSafe(F.lit(2)) & F.col("n_name").rlike("[A-Z0-9]")).select("n_nationkey"), "SELECT n_nationkey FROM nation WHERE n_regionkey IS NOT DISTINCT FROM 2 AND regexp_matches(n_name, '[A-Z0-9]')"),
    "join_broadcast": (join_inner("broadcast"), _JOIN),
    "join_shuffle_hash": (join_inner("shuffle_hash"), _JOIN),
    "join_sort_merge": (join_inner("merge"), _JOIN),
    "join_left": (join_outer("left"), _outer("LEFT")),
    "join_right": (join_outer("right"), _outer("RIGHT")),
    "join_full": (join_outer("full"), _outer("FULL")),
    "join_semi": (join_semi("left_semi"), "SELECT o_orderstatus, CAST(count(*) AS BIGINT) AS n FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem) GROUP BY o_orderstatus"),
    "join_anti": (join_semi("left_anti"), "SELECT o_orderstatus, CAST(count(*) AS BIGINT) AS n FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem) GROUP BY o_orderstatus"),
    "join_cross": (lambda s, d: load(s, d, "nation").crossJoin(F.broadcast(load(s, d, "region"))).agg(F.count("*").alias("n")), "SELECT CAST(count(*) AS BIGINT) AS n FROM nation CROSS JOIN region"),
    "join_self": (join_self, _SELF),
    "join_theta": (join_theta, "SELECT n_nationkey, CAST(count(*) AS BIGINT) AS n FROM supplier JOIN nation ON s_nationkey > n_nationkey GROUP BY n_nationkey"),
    "join_range": (join_range, "SELECT a.user_id, CAST(count(*) AS BIGINT) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND abs(a.value - b.value) <= 0.05 GROUP BY a.user_id"),
    "join_interval": (join_interval, "SELECT a.user_id, CAST(count(*) AS BIGINT) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY a.user_id"),
    "join_asof": (join_asof, _ASOF),
    "join_salted": (join_salted, "SELECT a.user_id, CAST(count(*) AS BIGINT) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'error' GROUP BY a.user_id"),
    "join_composite": (join_composite, "SELECT CAST(count(*) AS BIGINT) AS n_rows, CAST(count(DISTINCT (a.l_partkey, a.l_suppkey)) AS BIGINT) AS n_keys FROM lineitem a JOIN lineitem b ON a.l_partkey = b.l_partkey AND a.l_suppkey = b.l_suppkey AND a.l_returnflag = 'R' AND b.l_returnflag = 'A'"),
    "agg_basic": _both(_BASIC),
    "agg_moments": _both(_MOMENTS),
    "agg_distinct": _both(_DISTINCT),
    "agg_approx_distinct": (agg_approx, "SELECT CAST(count(DISTINCT user_id) AS BIGINT) AS n_users, TRUE AS close FROM events"),
    "agg_quantile": (agg_quantile, "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY event_type"),
    "agg_filtered": _both(_FILTERED),
    "agg_grouping_sets": _both(_SETS),
    "agg_cube": (cube("cube"), "SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n, CAST(grouping_id(l_returnflag, l_linestatus) AS INT) AS level FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"),
    "agg_rollup": (cube("rollup"), "SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n, CAST(grouping_id(l_returnflag, l_linestatus) AS INT) AS level FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)"),
    "agg_pivot": (pivot, "SELECT CAST(day(ts) AS INT) AS day, CAST(count(*) FILTER (WHERE event_type = 'click') AS BIGINT) AS click, CAST(count(*) FILTER (WHERE event_type = 'error') AS BIGINT) AS error, CAST(count(*) FILTER (WHERE event_type = 'purchase') AS BIGINT) AS purchase FROM events GROUP BY 1"),
    "agg_unpivot": (lambda s, d: load(s, d, "supplier").unpivot("s_suppkey", [F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance")], "name", "amount"), "SELECT s_suppkey, 'nation' AS name, CAST(s_nationkey AS DOUBLE) AS amount FROM supplier UNION ALL SELECT s_suppkey, 'balance', s_acctbal FROM supplier"),
    "agg_collect": (collect, "SELECT o_custkey, string_agg(CAST(o_orderkey AS VARCHAR), ',' ORDER BY o_orderkey) AS keys FROM orders GROUP BY o_custkey"),
    "sample_aggregate": (sample_aggregate, _SAMPLE),
    "win_rank": (win_rank, "SELECT o_orderkey, CAST(row_number() OVER w AS INT) AS rn, CAST(ntile(4) OVER w AS INT) AS quarter, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, CAST(rank() OVER v AS INT) AS rk, CAST(dense_rank() OVER v AS INT) AS dr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)"),
    "win_lag_lead": (win_lag_lead, "SELECT event_id, lag(event_id, 1, -1) OVER w AS before, lead(event_id, 2, -1) OVER w AS after, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"),
    "win_frames": (win_frames, "WITH o AS (SELECT *, CAST(o_totalprice AS DECIMAL(18,2)) AS price, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS day FROM orders) SELECT o_orderkey, CAST(sum(price) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS DOUBLE) AS last_three, CAST(sum(price) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS DOUBLE) AS running, CAST(sum(price) OVER (PARTITION BY o_custkey ORDER BY day RANGE BETWEEN 90 PRECEDING AND CURRENT ROW) AS DOUBLE) AS ninety_days FROM o"),
    "sort_limit": _both(_SORT),
    "topk_global": (lambda s, d: load(s, d, "customer").orderBy(F.desc("c_acctbal"), "c_custkey").limit(10).select("c_custkey", "c_acctbal"), "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 10"),
    "topk_per_group": (topk_per_group, "SELECT c_nationkey, c_custkey, CAST(r AS INT) AS r FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) WHERE r <= 3"),
    "set_union": (set_op("union"), _set("UNION")),
    "set_union_all": (set_op("union_all"), _set("UNION ALL")),
    "set_intersect": (set_op("intersect"), _set("INTERSECT")),
    "set_except": (set_op("except"), _set("EXCEPT")),
    "set_except_all": (set_op("except_all"), _set("EXCEPT ALL", "SELECT o_custkey AS k FROM orders", "SELECT c_custkey AS k FROM customer")),
    "set_intersect_all": (set_op("intersect_all"), _set("INTERSECT ALL", "SELECT o_custkey AS k FROM orders", "SELECT c_custkey AS k FROM customer")),
    "dedupe_rows": (lambda s, d: load(s, d, "lineitem").select("l_orderkey", "l_linenumber").dropDuplicates().agg(F.count("*").alias("n")), "SELECT CAST(count(*) AS BIGINT) AS n FROM (SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem)"),
    "sample_bernoulli": (sample_bernoulli, f"SELECT l_returnflag, CAST(count(*) AS BIGINT) AS n FROM lineitem WHERE {_UNIT.format('l_orderkey, l_linenumber, 42')} < 0.1 GROUP BY l_returnflag"),
    "sample_strat": (sample_strat, f"SELECT event_type, CAST(count(*) AS BIGINT) AS n FROM events WHERE {_UNIT.format('event_id, 42')} < CASE event_type WHEN 'click' THEN 0.5 WHEN 'error' THEN 0.2 ELSE 0.05 END GROUP BY event_type"),
    "sample_builtin": (lambda s, d: load(s, d, "events").sampleBy("event_type", {"click": 0.5, "error": 0.2}, 42).groupBy("event_type").count(), None),
    "fn_string": _both(_STRING),
    "fn_math": _both(_MATH),
    "fn_date": (lambda s, d: load(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), F.date_trunc("month", "o_orderdate").cast("date").cast("string").alias("m"), F.datediff(F.lit("2002-01-01").cast("date"), F.col("o_orderdate")).alias("age")), "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(quarter(o_orderdate) AS INT) AS q, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS STRING) AS m, CAST(date_diff('day', CAST(o_orderdate AS DATE), DATE '2002-01-01') AS INT) AS age FROM orders"),
    "fn_vector": (fn_vector, "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x))), 6) AS norm, round(list_dot_product(CAST(embedding AS DOUBLE[]), CAST(list_reverse(embedding) AS DOUBLE[])), 6) AS mirror, CAST(len(embedding) AS INT) AS dim FROM embeddings"),
    "fn_map": (fn_map, "SELECT n_regionkey, CAST(count(*) AS INT) AS n, string_agg(CAST(n_nationkey AS VARCHAR), ',' ORDER BY n_nationkey) AS keys FROM nation GROUP BY n_regionkey"),
    "fn_json": (lambda s, d: load(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("bigint").alias("k")).agg(F.count("*").alias("n")), "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1"),
    "fn_text": (fn_text, "SELECT item_id, CAST(count(*) AS BIGINT) AS n_words, CAST(count(DISTINCT w) AS BIGINT) AS n_distinct FROM (SELECT item_id, unnest(string_split(text, ' ')) AS w FROM benchmark) GROUP BY item_id"),
    "fn_pages": (fn_pages, "SELECT string_split(url, ':')[1] AS scheme, CAST(count(*) AS BIGINT) AS n, CAST(sum(length(html)) AS BIGINT) AS chars FROM pages GROUP BY 1"),
    "conversation_turns": (lambda s, d: load(s, d, "conversations").groupBy("conv_id").agg(F.count("*").alias("turns"), F.max("turn").alias("last_turn")), "SELECT conv_id, CAST(count(*) AS BIGINT) AS turns, max(turn) AS last_turn FROM conversations GROUP BY conv_id"),
    "sub_exists": _both(_Q4),
    "sub_in": _both(_IN),
    "sub_scalar": _both(_SCALAR),
    "sub_correlated": _both(_CORRELATED),
    "sub_cte": _both(_CTE),
    "sub_lateral": _both(_LATERAL),
    "udtf_draws": (stratified_udtf, "SELECT CAST(k AS INT) AS k, CAST(1 + h % k AS BIGINT) AS pos_1, CAST(1 + (h // k) % 7 AS BIGINT) AS pos_2 FROM (SELECT k, CAST(('0x' || substr(md5(concat_ws('|', k, 7, d, 42)), 1, 15)) AS BIGINT) AS h FROM (SELECT DISTINCT count(*) AS k FROM orders WHERE o_custkey IS NOT NULL GROUP BY o_custkey) t, range(10) r(d))"),
    "udaf_stratum": (stratum_udaf, "SELECT o_orderpriority, round(stddev_samp(o_totalprice), 2) AS spread FROM orders GROUP BY o_orderpriority"),
}

QUERIES = {k: q for k, (q, _) in OPERATORS.items()}
SQL = {k: s for k, (_, s) in OPERATORS.items() if s}
