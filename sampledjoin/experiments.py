"""Named queries of the experiments: methods beside each other over overlaps and fractions, budgets, and the forms that users write; with SQL that replays them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import workloads as W
from .functions.quantiles import z_quantile
from .model import JoinInput, LatencyModel
from .operators import estimators as E
from .operators import sampler
from .operators.filtering import prefilter
from .operators.strata import count_strata
from .plans import budget as P
from .plans import engine, sqlfront
from .registry import _SIGMA_SQL, CO, CO_V, CONF, FLAGS, NET, NET_V, _clt_sql, _dialled, _domain_sql, _exact_sql, _hash, _line_sides, _replay, _rounded, _sampled, poisson_steps
from .sources.datagen import poisson_inputs
from .sources.io import load


def _union(rows: list[DataFrame]) -> DataFrame:
    out = rows[0]
    for r in rows[1:]:
        out = out.unionAll(r)
    return out


# --- groups and nulls ----------------------------------------------------------------------------------------------------------

_C = "SELECT c_custkey AS jk, CAST(c_acctbal AS DECIMAL(18,2)) AS c_acctbal FROM customer"
_O = "SELECT o_custkey AS jk, o_orderkey, CAST(CASE WHEN o_orderkey % 2 = 0 THEN o_totalprice END AS DECIMAL(18,2)) AS o_totalprice, o_orderpriority FROM orders"
SIDES = [(_C, "c_acctbal NULLS FIRST"), (_O, "o_orderkey NULLS FIRST, o_totalprice NULLS FIRST, o_orderpriority NULLS FIRST")]


def _half(spark, sf_dir):
    """Customers and orders, of which every second one has no price."""
    c = load(spark, sf_dir, "customer").select("c_custkey", W.money("c_acctbal").alias("c_acctbal"))
    o = load(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", F.when(F.col("o_orderkey") % 2 == 0, W.money("o_totalprice")).alias("o_totalprice"), "o_orderpriority")
    return [JoinInput(c, ["c_custkey"], ["c_acctbal"], "customer"), JoinInput(o, ["o_custkey"], ["o_orderkey", "o_totalprice", "o_orderpriority"], "orders")]


def _domain(agg: str, group: bool, s: float = 0.4, **options):
    keep = ("o_orderpriority",) if group else ()
    more = {"group_by": list(keep)} if group else {}
    return lambda spark, d: _rounded(_sampled(_half(spark, d), F.col("o_totalprice") + F.col("c_acctbal"), s, agg=agg, **more, **options), 0 if agg == "sum" else 2, keep)


def _domain_pair(agg: str, group: bool, ht: bool = False):
    options = {"estimator": "ht", "dedupe": "distinct"} if ht else {}
    how = {"distinct": True, "ht": "draws"} if ht else {}
    return _domain(agg, group, **options), _domain_sql(SIDES, CO_V, 0.4, agg, "o_orderpriority" if group else "", digits=0 if agg == "sum" else 2, **how)


# --- SQL with a budget clause --------------------------------------------------------------------------------------------------

def _sql_composite(spark, sf_dir):
    """A key of two columns, and one column's name in both tables."""
    for t, flag in (("a", "R"), ("b", "A")):
        rows = load(spark, sf_dir, "lineitem").where(F.col("l_returnflag") == flag)
        rows.select("l_partkey", "l_suppkey", F.col("l_orderkey").alias(f"o_{t}"), F.col("l_extendedprice").cast(W.MONEY).alias(f"v_{t}")).createOrReplaceTempView(t)
    return engine_row(sqlfront.sql(spark, "SELECT SUM(v_a + v_b) FROM a, b WHERE a.l_partkey = b.l_partkey AND a.l_suppkey = b.l_suppkey"))


def engine_row(df: DataFrame) -> DataFrame:
    return df.select(F.round("estimate", 2).alias("estimate"), "error_bound", F.col("sampled_edges").alias("n_rows"), "mode")


def _sql_chain(spark, sf_dir):
    """(refused, estimate): one FROM list over two attributes is refused; the operator for it is the cascade, here with all edges."""
    for t in ("customer", "orders", "lineitem"):
        load(spark, sf_dir, t).createOrReplaceTempView(t)
    try:
        sqlfront.sql(spark, "SELECT SUM(l_extendedprice) FROM customer, orders, lineitem WHERE c_custkey = o_custkey AND o_orderkey = l_orderkey")
        refused = False
    except ValueError:
        refused = True
    first = JoinInput(spark.table("customer"), ["c_custkey"], [])
    second = JoinInput(load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", W.money("l_extendedprice").alias("price")), ["l_orderkey"], ["price", "l_linenumber", "l_partkey"])
    whole = engine.cascade(first, spark.table("orders").select("o_custkey", "o_orderkey"), ("o_custkey", "o_orderkey"), second, F.col("price"), [], 1.0)
    return whole.select(F.lit(refused).alias("refused"), F.round("estimate", 2).alias("estimate"))


def _between(spark, sf_dir):
    for t in ("customer", "orders"):
        load(spark, sf_dir, t).createOrReplaceTempView(t)
    text = "SELECT COUNT(o_orderkey) FROM customer, orders WHERE c_custkey = o_custkey AND o_orderkey BETWEEN 100 AND 9000 AND (o_orderpriority = '1-URGENT' OR o_orderpriority = '2-HIGH AND DRY')"
    return engine_row(sqlfront.sql(spark, text))


# --- methods over overlaps and fractions ---------------------------------------------------------------------------------------

#: (inputs, overlap dial) and the methods that join all of them.
OVERLAPS, METHODS = ((2, 1), (2, 4), (2, 10), (3, 1), (3, 6), (4, 1)), ("filter_only", "repartition", "native")


def _dialled_inputs(spark, sf_dir, n, p):
    return W.by_line(spark, sf_dir, 4, p, tables=True) if n == 4 else W.by_flag(spark, sf_dir, FLAGS[:n], p=p, tables=True)


def _methods(spark, sf_dir):
    return _union([W.run(*_dialled_inputs(spark, sf_dir, n, p), m).select(F.lit(n).alias("n_inputs"), F.lit(p).alias("p"), F.lit(m).alias("method"), F.col("sampled_edges").alias("n_rows"), F.round("estimate", 2).alias("total")) for n, p in OVERLAPS for m in METHODS])


def _line_values(p: int) -> list[tuple[str, str]]:
    return [(sql.replace("AS jk FROM", f"AS jk, CAST(l_extendedprice AS DECIMAL(18,2)) AS v{i} FROM"), "") for i, (sql, _) in enumerate(_line_sides(p), 1)]


def _methods_sql() -> str:
    parts = []
    for n, p in OVERLAPS:
        sides = _line_values(p) if n == 4 else _dialled(n, p, lambda i: f"l_returnflag = '{FLAGS[i]}'")
        x = _exact_sql(sides, " + ".join(f"v{i}" for i in range(1, n + 1)))
        parts += [f"SELECT {n} AS n_inputs, {p} AS p, '{m}' AS method, n_rows, total FROM ({x})" for m in METHODS]
    return " UNION ALL ".join(parts)


def _moved_rows(spark, sf_dir):
    """(n_inputs, p, all_rows, joining_rows, bounded): rows that baselines move and rows that have to be moved; and whether the filter keeps few others."""
    rows = []
    for n, p in OVERLAPS:
        inputs, _ = _dialled_inputs(spark, sf_dir, n, p)
        kept = _union([k.select("jk") for k in prefilter(inputs).dfs]).agg(F.count("*").alias("kept_rows"))
        o = W.overlap_row(inputs).crossJoin(kept)
        rows.append(o.select(F.lit(n).alias("n_inputs"), F.lit(p).alias("p"), F.col("total_rows").alias("all_rows"), "joining_rows", (F.col("kept_rows") - F.col("joining_rows") <= 0.02 * (F.col("total_rows") - F.col("joining_rows"))).alias("bounded")))
    return _union(rows)


def _moved_sql() -> str:
    parts = []
    for n, p in OVERLAPS:
        sides = [s for s, _ in (_line_sides(p) if n == 4 else _dialled(n, p, lambda i: f"l_returnflag = '{FLAGS[i]}'"))]
        inside = " UNION ALL ".join("SELECT jk FROM x{} WHERE {}".format(i, " AND ".join(f"jk IN (SELECT jk FROM x{k})" for k in range(n) if k != i)) for i in range(n))
        parts.append(f"SELECT * FROM (WITH {', '.join(f'x{i} AS ({s})' for i, s in enumerate(sides))} SELECT {n} AS n_inputs, {p} AS p, CAST({' + '.join(f'(SELECT count(*) FROM x{i})' for i in range(n))} AS BIGINT) AS all_rows, CAST(count(*) AS BIGINT) AS joining_rows, TRUE AS bounded FROM ({inside}))")
    return " UNION ALL ".join(parts)


FRACTIONS = (0.1, 0.2, 0.4, 0.6, 0.8, 1.0)


def _fractions(spark, sf_dir):
    """(s, method, estimate, sampled_edges, loss) of sampling during, after and before the join, and of the hybrid."""
    inputs, value = W.customer_orders(spark, sf_dir)
    keyed = [i.keyed() for i in inputs]
    truth = engine.exact_join(keyed).agg(F.sum(value).cast("double").alias("exact"))
    rows = [W.run(inputs, value, m, s, ids=[["c_acctbal"], ["o_orderkey"]], family="portable").select(F.lit(s).alias("s"), F.lit(m).alias("method"), "estimate", "sampled_edges") for s in FRACTIONS for m in ("during", "postjoin", "prejoin", "prejoin_stratified", "hybrid")]
    return _union(rows).crossJoin(truth).select("s", "method", F.round("estimate", 1).alias("estimate"), "sampled_edges", (F.round((F.col("estimate") - F.col("exact")) / F.col("exact"), 8) + 0.0).alias("loss"))


def _prejoin_stratified_sql(sides: list[tuple[str, str]], value: str, s: float, cols: list[list[str]]) -> str:
    n, share = len(sides), s ** (1 / len(sides))
    kept = []
    for i, (sql, _) in enumerate(sides, 1):
        c = cols[i - 1]
        keep = f"greatest(1, ceil({share!r} * c))"
        kept.append(f"k{i} AS (SELECT *, c / greatest(1.0, ceil({share!r} * c)) AS w_{i} FROM (SELECT *, row_number() OVER (PARTITION BY jk ORDER BY {_hash(*c, str(42 + i))}, {', '.join(c)}) AS r, CAST(count(*) OVER (PARTITION BY jk) AS DOUBLE) AS c FROM ({sql}) WHERE jk IS NOT NULL) WHERE r <= {keep})")
    joins = " ".join(f"JOIN k{i} USING (jk)" if i > 1 else f"k{i}" for i in range(1, n + 1))
    return f"WITH {', '.join(kept)} SELECT sum(CAST({value} AS DOUBLE) * {' * '.join(f'w_{i}' for i in range(1, n + 1))}) AS estimate, CAST(count(*) AS BIGINT) AS sampled_edges FROM {joins}"


def _prejoin_uniform_sql(sides, value, s, ids) -> str:
    share = s ** (1 / len(sides))
    kept = [f"(SELECT * FROM ({sql}) WHERE {_hash(*ids[i - 1], str(i), '42')} / {float(1 << 60)!r} < {share!r}) s{i}" for i, (sql, _) in enumerate(sides, 1)]
    return f"SELECT coalesce(CAST(sum({value}) AS DOUBLE), 0.0) / {share ** len(sides)!r} AS estimate, CAST(count(*) AS BIGINT) AS sampled_edges FROM {' '.join(f'JOIN {k} USING (jk)' if i else k for i, k in enumerate(kept))}"


def _fractions_sql() -> str:
    j = f"({CO[0][0]}) s1 JOIN ({CO[1][0]}) s2 USING (jk)"
    flat = ("c_acctbal", "o_orderkey", "o_totalprice")
    parts = []
    for s in FRACTIONS:
        post = f"""WITH j AS (SELECT jk, {', '.join(flat)}, {CO_V} AS v FROM {j}),
r AS (SELECT *, row_number() OVER (PARTITION BY jk ORDER BY {_hash(*flat, '42')}, {', '.join(flat)}) AS r, count(*) OVER (PARTITION BY jk) AS edges FROM j),
p AS (SELECT jk, count(*) AS n, any_value(edges) AS edges, CAST(sum(v) AS DOUBLE) AS s1 FROM r WHERE r <= least(greatest(ceil({s} * edges - 1e-9), 2), edges) GROUP BY jk)
SELECT sum(edges / n * s1) AS estimate, CAST(sum(n) AS BIGINT) AS sampled_edges FROM p"""
        hybrid = f"SELECT CAST(sum({CO_V}) AS DOUBLE) / {s} AS estimate, CAST(count(*) AS BIGINT) AS sampled_edges FROM {j} WHERE {_hash(*flat, '42')} / {float(1 << 60)!r} < {s}"
        during = f"{_replay(CO, CO_V, s)} SELECT sum(ne / b * s1) AS estimate, CAST(sum(b) AS BIGINT) AS sampled_edges FROM p"
        pre = _prejoin_uniform_sql(CO, CO_V, s, [["c_acctbal"], ["o_orderkey"]])
        strat = _prejoin_stratified_sql(CO, CO_V, s, [["c_acctbal"], ["o_orderkey", "o_totalprice"]])
        parts += [f"SELECT CAST({s} AS DOUBLE) AS s, '{m}' AS method, * FROM ({q})" for m, q in (("during", during), ("postjoin", post), ("prejoin", pre), ("prejoin_stratified", strat), ("hybrid", hybrid))]
    return f"SELECT s, method, round(estimate, 1) AS estimate, sampled_edges, round((estimate - x.total) / x.total, 8) + 0.0 AS loss FROM ({' UNION ALL '.join(parts)}), ({_exact_sql(CO, CO_V)}) x"


def _flow_losses(spark, sf_dir):
    """(method, loss) of the three-way event join at a tenth of the edges."""
    inputs, value = W.flows(spark, sf_dir)
    truth = engine.exact_join([i.keyed() for i in inputs]).agg(F.sum(value).cast("double").alias("exact"))
    rows = [W.run(inputs, value, m, 0.1, ids=[["e1"], ["e2"], ["e3"]], family="portable").select(F.lit(m).alias("method"), "estimate") for m in ("during", "prejoin", "prejoin_stratified")]
    return _union(rows).crossJoin(truth).select("method", F.round((F.col("estimate") - F.col("exact")) / F.col("exact"), 8).alias("loss"))


def _flow_losses_sql() -> str:
    cols = [[f"e{i}", f"v{i}"] for i in (1, 2, 3)]
    q = {"during": f"{_replay(NET, NET_V, 0.1)} SELECT sum(ne / b * s1) AS estimate, 0 AS n FROM p", "prejoin": _prejoin_uniform_sql(NET, NET_V, 0.1, [["e1"], ["e2"], ["e3"]]), "prejoin_stratified": _prejoin_stratified_sql(NET, NET_V, 0.1, cols)}
    rows = " UNION ALL ".join(f"SELECT '{m}' AS method, estimate FROM ({s})" for m, s in q.items())
    return f"SELECT method, round((estimate - x.total) / x.total, 8) AS loss FROM ({rows}), ({_exact_sql(NET, NET_V)}) x"


def _ratings_methods(spark, sf_dir):
    inputs = W.ratings(spark, sf_dir)
    return _union([W.run(inputs, F.col("l_quantity").cast("decimal(12,2)"), m).select(F.lit(m).alias("method"), F.col("sampled_edges").alias("n_rows"), F.round("estimate", 2).alias("total")) for m in ("filter_only", "repartition", "native", "broadcast")])


_RATINGS = [("SELECT l_partkey AS jk, l_orderkey, l_linenumber, CAST(l_quantity AS DECIMAL(12,2)) AS q FROM lineitem WHERE l_linenumber <= 6", "l_orderkey NULLS FIRST, l_linenumber NULLS FIRST, q NULLS FIRST"), ("SELECT l_partkey AS jk, l_orderkey AS o7 FROM lineitem WHERE l_linenumber = 7", "o7 NULLS FIRST")]


def _ratings_sample(s: float):
    def q(spark, sf_dir):
        li = load(spark, sf_dir, "lineitem")
        train = li.where("l_linenumber <= 6").select("l_partkey", "l_orderkey", "l_linenumber", F.col("l_quantity").cast("decimal(12,2)").alias("q"))
        inputs = [JoinInput(train, ["l_partkey"], ["l_orderkey", "l_linenumber", "q"]), JoinInput(li.where("l_linenumber = 7").select("l_partkey", F.col("l_orderkey").alias("o7")), ["l_partkey"], ["o7"])]
        return _rounded(_sampled(inputs, F.col("q"), s))

    return q


# --- budgets -------------------------------------------------------------------------------------------------------------------

#: A model and a filtering time that are fixed, so that the sizes can be repeated.
MODEL, FILTER_S, DESIRED = LatencyModel(1e-3, 0.5), 2.0, (4.0, 6.5, 8.5, 12.5)


def _allowed(desired: float) -> float:
    return (P.remaining(desired, FILTER_S) - MODEL.epsilon) / MODEL.beta


def _latency_sweep(spark, sf_dir):
    """(desired, sampled_edges, predicted, miss, estimate, loss): samples that latencies allow; miss is what is predicted beyond the desired latency."""
    inputs, value = W.customer_orders(spark, sf_dir)
    keyed = prefilter(inputs).dfs
    counted = count_strata(keyed)
    truth = engine.exact_join(keyed).agg(F.sum(value).cast("double").alias("exact"))
    rows = _union([engine.estimate(keyed, P.allocate_within(counted, _allowed(d)), value, family="portable").select(F.lit(d).alias("desired"), "estimate", "sampled_edges") for d in DESIRED]).crossJoin(truth)
    predicted = F.lit(FILTER_S + MODEL.epsilon) + F.col("sampled_edges") * MODEL.beta
    return rows.select("desired", "sampled_edges", F.round(predicted, 6).alias("predicted"), F.round(F.greatest(predicted - F.col("desired"), F.lit(0.0)), 6).alias("miss"), F.round("estimate", 1).alias("estimate"), (F.round((F.col("estimate") - F.col("exact")) / F.col("exact"), 8) + 0.0).alias("loss"))


def _latency_sql() -> str:
    parts = []
    for d in DESIRED:
        allowed = _allowed(d)
        std = f"least(greatest(floor(least(1.0, {allowed!r} / CAST(sum(ne) OVER () AS DOUBLE)) * ne + 1e-9), 2), ne)"
        # the share needs the sum first, then its own sum: in nested windows
        sizes = f"(SELECT jk AS jk, std, sum(std) OVER () AS all_std, least_b, sum(least_b) OVER () AS all_least, all_ne FROM (SELECT jk, least(2, ne) AS least_b, {std} AS std, CAST(sum(ne) OVER () AS DOUBLE) AS all_ne FROM (SELECT jk, n1 * n2 AS ne FROM (SELECT jk, count(*) AS n1 FROM ({CO[0][0]}) GROUP BY jk) JOIN (SELECT jk, count(*) AS n2 FROM ({CO[1][0]}) GROUP BY jk) USING (jk))))"
        size = f"CASE WHEN all_std <= {allowed!r} OR {allowed!r} >= all_ne THEN std ELSE least(ne, least_b + floor(greatest(0.0, {allowed!r} - all_least) / greatest(1.0, all_ne - all_least) * (ne - least_b))) END"
        parts.append(f"SELECT CAST({d} AS DOUBLE) AS desired, * FROM ({_replay(CO, CO_V, 1.0, size=size, sizes=sizes)} SELECT sum(ne / b * s1) AS estimate, CAST(sum(b) AS BIGINT) AS sampled_edges FROM p)")
    predicted = f"({FILTER_S + MODEL.epsilon!r} + sampled_edges * {MODEL.beta!r})"
    return f"SELECT desired, sampled_edges, round({predicted}, 6) AS predicted, round(greatest({predicted} - desired, 0.0), 6) AS miss, round(estimate, 1) AS estimate, round((estimate - x.total) / x.total, 8) + 0.0 AS loss FROM ({' UNION ALL '.join(parts)}), ({_exact_sql(CO, CO_V)}) x"


_SECOND_ERROR = 2e7


def _feedback(spark, sf_dir):
    """The estimate of a second run whose sizes come from the deviations that the first run's sample left."""
    inputs, value = W.customer_orders(spark, sf_dir)
    keyed = prefilter(inputs).dfs
    counted = count_strata(keyed)
    first = engine.sampled_rows(keyed, P.allocate(counted, 0.3), value, family="portable")
    sigma = E.stratum_sigma(first).where("n > 1").withColumn("sigma", F.round("sigma", 4))
    sized = P.size_for_error(counted, sigma, _SECOND_ERROR, CONF, "total_abs")
    return _rounded(engine.estimate(keyed, sized, value, family="portable", confidence=CONF))


def _feedback_sql() -> str:
    first = f"{_replay(CO, CO_V, 0.3)}, sg AS (SELECT jk, b AS n, round(sqrt(greatest(0.0, (s2 - s1 * s1 / b) / (b - 1))), 4) AS sigma, ne FROM p WHERE b > 1) "
    known = f"SELECT p.jk, p.ne AS e0, coalesce(sg.sigma, (SELECT sqrt(sum((n - 1) * sigma * sigma) / sum(n - 1)) FROM sg), 0.0) AS sigma FROM p LEFT JOIN sg USING (jk)"
    sizes = f"(SELECT jk, sigma, sum(e0 * sigma) OVER () AS spread FROM ({first} {known}))"
    size = f"least(greatest(ceil({(z_quantile(CONF) / _SECOND_ERROR) ** 2!r} * (ne * sigma) * spread), 2), ne)"
    return _clt_sql(CO, CO_V, 1.0, size=size, sizes=sizes)


_REPS = 3


def _bootstrap(spark, sf_dir):
    inputs, value = W.customer_orders(spark, sf_dir)
    keyed = [i.keyed() for i in inputs]
    pilot = sampler.sample_edges(keyed, P.allocate(count_strata(keyed), 0.5), family="portable")
    return P.bootstrap_sigma(pilot, value, _REPS, family="portable").select("jk", "n", F.round("sigma", 3).alias("sigma"))


def _bootstrap_sql() -> str:
    steps, total, p = [], 0.0, 2.718281828459045**-1
    for k in range(1, 9):
        total += p
        steps.append(f"(CASE WHEN u > {total!r} THEN 1 ELSE 0 END)")
        p /= k
    u = f"(({_hash('jk', 'draw', 'rep', '42')} % {1 << 52}) + 0.5) / {float(1 << 52)!r}"
    return f"""{_replay(CO, CO_V, 0.5)},
w AS (SELECT jk, rep, CAST(v AS DOUBLE) AS v, {' + '.join(steps)} AS w FROM (SELECT j.jk, draw, v, rep, {u} AS u FROM j, range(1, {_REPS + 1}) r(rep))),
g AS (SELECT jk, rep, sum(w) AS w, sum(w * v) AS s, sum(w * v * v) AS q FROM w GROUP BY jk, rep HAVING sum(w) > 1)
SELECT CAST(jk AS BIGINT) AS jk, CAST(max(w) AS BIGINT) AS n, round(sqrt(avg(greatest(0.0, (q - s * s / w) / (w - 1)))), 3) AS sigma FROM g GROUP BY jk"""


def _both_budgets(spark, sf_dir):
    """(error, wanted, predicted, fits): the edges that errors of the total want, and whether a latency of eight seconds holds them."""
    inputs, value = W.customer_orders(spark, sf_dir)
    keyed = [i.keyed() for i in inputs]
    sigma = engine.exact_join(keyed).groupBy("jk").agg(F.count("*").alias("n"), F.round(F.coalesce(F.stddev_samp(value.cast("double")), F.lit(0.0)), 4).alias("sigma")).where("n > 1")
    rows = [P.size_for_error(count_strata(keyed), sigma, e, CONF, "total_abs").agg(F.sum("b").cast("bigint").alias("wanted")).select(F.lit(e).alias("error"), "wanted") for e in (5e6, 1e7, 4e7)]
    predicted = F.lit(FILTER_S + MODEL.epsilon) + F.col("wanted") * MODEL.beta
    return _union(rows).select("error", "wanted", F.round(predicted, 6).alias("predicted"), (predicted <= 8.0).alias("fits"))


def _both_budgets_sql() -> str:
    parts = [f"SELECT * FROM ({_SIGMA_SQL} SELECT CAST({e} AS DOUBLE) AS error, CAST(sum(CAST(least(greatest(ceil({(z_quantile(CONF) / e) ** 2!r} * (edges * sigma) * (SELECT sum(edges * sigma) FROM k)), 2), edges) AS BIGINT)) AS BIGINT) AS wanted FROM k)" for e in (5e6, 1e7, 4e7)]
    predicted = f"({FILTER_S + MODEL.epsilon!r} + wanted * {MODEL.beta!r})"
    return f"SELECT error, wanted, round({predicted}, 6) AS predicted, {predicted} <= 8.0 AS fits FROM ({' UNION ALL '.join(parts)})"


def _refine(spark, sf_dir):
    """(round, estimate, sampled_edges, drawn) of the rounds of refinement; drawn: the edges that the round added."""
    inputs, value = W.customer_orders(spark, sf_dir)
    rounds = engine.refine(inputs, value, 4e7, first=0.2, max_rounds=2, family="portable")
    rows = [(r["round"], round(r["estimate"], 2), r["sampled_edges"], r["drawn"]) for r in rounds]
    return spark.createDataFrame(rows, "round int, estimate double, sampled_edges bigint, drawn bigint")


def _refine_sql() -> str:
    first = _replay(CO, CO_V, 0.2)
    r2 = "CASE WHEN b > 1 THEN greatest(0.0, (s2 - s1 * s1 / b) / (b - 1)) END"
    sigma = f"SELECT jk, ne AS e0, b AS b0, is_full AS full0, sqrt(coalesce({r2}, (SELECT sum((b - 1) * ({r2})) / sum(CASE WHEN b > 1 THEN b - 1 END) FROM p), 0.0)) AS sigma FROM p"
    sizes = f"(SELECT jk, sigma, b0, full0, sum(e0 * sigma) OVER () AS spread FROM ({first} {sigma}))"
    size = f"greatest(least(greatest(ceil({(z_quantile(0.95) / 4e7) ** 2!r} * (ne * sigma) * spread), 2), ne), b0)"
    second = f"{_replay(CO, CO_V, 1.0, size=size, sizes=sizes)} SELECT 2 AS round, round(sum(p.ne / p.b * s1), 2) AS estimate, CAST(sum(p.b) AS BIGINT) AS sampled_edges, CAST(sum(CASE WHEN is_full AND b0 < p.b THEN p.b ELSE p.b - b0 END) AS BIGINT) AS drawn FROM p JOIN st USING (jk)"
    one = f"{first} SELECT 1 AS round, round(sum(ne / b * s1), 2) AS estimate, CAST(sum(b) AS BIGINT) AS sampled_edges, CAST(sum(b) AS BIGINT) AS drawn FROM p"
    return f"SELECT * FROM ({one}) UNION ALL SELECT * FROM ({second})"


# --- generated inputs ----------------------------------------------------------------------------------------------------------

_POISSON = (2, 4.0, 0.1)


def _poisson(spark, sf_dir):
    """(side, n_rows, n_keys, shared) of generated inputs whose rows by key follow a Poisson distribution."""
    n, lam, overlap = _POISSON
    ids = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id")).where("id is not null").distinct()
    return _union([i.df.agg(F.lit(k).alias("side"), F.count("*").alias("n_rows"), F.countDistinct("k").alias("n_keys"), F.countDistinct(F.when(F.col("k") % (n + 1) == 0, F.col("k"))).alias("shared")) for k, i in enumerate(poisson_inputs(spark, n, lam, overlap=overlap, family="portable", ids=ids))])


def _poisson_sql() -> str:
    n, lam, overlap = _POISSON
    steps = poisson_steps(lam)
    return " UNION ALL ".join(f"SELECT {i} AS side, CAST(sum(c) AS BIGINT) AS n_rows, CAST(count(*) FILTER (WHERE c > 0) AS BIGINT) AS n_keys, CAST(count(*) FILTER (WHERE c > 0 AND id % 1000 < {round(1000 * overlap)}) AS BIGINT) AS shared FROM (SELECT id, {' + '.join(steps)} AS c FROM (SELECT id, (({_hash('id', str(i), '42')} % {1 << 52}) + 0.5) / {float(1 << 52)!r} AS u FROM (SELECT DISTINCT o_orderkey AS id FROM orders WHERE o_orderkey IS NOT NULL)))" for i in range(n))


_TPCH = {
    "q3": "SELECT CAST(count(*) AS BIGINT) AS n_rows, round(CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE), 2) AS price FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey",
    "q4": "SELECT CAST(count(*) AS BIGINT) AS n_rows, CAST(count(DISTINCT o_orderkey) AS BIGINT) AS n_orders FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
}
_TPCH["q10"] = _TPCH["q3"] + " JOIN nation ON c_nationkey = n_nationkey"

#: name: (query, SQL)
EXPERIMENTS: dict[str, tuple] = {
    **{f"group_by_{a}": _domain_pair(a, True) for a in ("count", "sum", "avg", "stdev")},
    **{f"group_by_{a}_ht": _domain_pair(a, True, True) for a in ("count", "sum", "avg", "stdev")},
    **{f"{a}_with_nulls": _domain_pair(a, False) for a in ("count", "avg", "stdev")},
    **{f"{a}_with_nulls_ht": _domain_pair(a, False, True) for a in ("count", "avg", "stdev")},
    "sql_composite": (_sql_composite, "SELECT round(CAST(sum(CAST(a.l_extendedprice AS DECIMAL(18,2)) + CAST(b.l_extendedprice AS DECIMAL(18,2))) AS DOUBLE), 2) AS estimate, CAST(0 AS DOUBLE) AS error_bound, CAST(count(*) AS BIGINT) AS n_rows, 'exact' AS mode FROM lineitem a JOIN lineitem b ON a.l_partkey = b.l_partkey AND a.l_suppkey = b.l_suppkey WHERE a.l_returnflag = 'R' AND b.l_returnflag = 'A'"),
    "sql_chain": (_sql_chain, f"SELECT TRUE AS refused, price AS estimate FROM ({_TPCH['q3']})"),
    "sql_between": (_between, "SELECT CAST(count(o_orderkey) AS DOUBLE) AS estimate, CAST(0 AS DOUBLE) AS error_bound, CAST(count(*) AS BIGINT) AS n_rows, 'exact' AS mode FROM customer JOIN orders ON c_custkey = o_custkey WHERE o_orderkey BETWEEN 100 AND 9000 AND o_orderpriority = '1-URGENT'"),
    "overlap_methods": (_methods, _methods_sql()),
    "overlap_moved_rows": (_moved_rows, _moved_sql()),
    "fraction_methods": (_fractions, _fractions_sql()),
    "flow_losses": (_flow_losses, _flow_losses_sql()),
    "ratings_methods": (_ratings_methods, " UNION ALL ".join(f"SELECT '{m}' AS method, CAST(count(*) AS BIGINT) AS n_rows, round(CAST(sum(CAST(l_quantity AS DECIMAL(12,2))) AS DOUBLE), 2) AS total FROM (SELECT l_partkey, l_quantity FROM lineitem WHERE l_linenumber <= 6) a JOIN (SELECT l_partkey FROM lineitem WHERE l_linenumber = 7) b USING (l_partkey)" for m in ("filter_only", "repartition", "native", "broadcast"))),
    "ratings_sample_10": (_ratings_sample(0.1), _clt_sql(_RATINGS, "q", 0.1)),
    "ratings_sample_100": (_ratings_sample(1.0), _clt_sql(_RATINGS, "q", 1.0)),
    **{f"tpch_{q}_filtered": (lambda s, d, q=q: W.tpch_filtered(s, d, q), sql) for q, sql in _TPCH.items()},
    "latency_sweep": (_latency_sweep, _latency_sql()),
    "feedback_second_run": (_feedback, _feedback_sql()),
    "bootstrap_sigma": (_bootstrap, _bootstrap_sql()),
    "both_budgets": (_both_budgets, _both_budgets_sql()),
    "refine_rounds": (_refine, _refine_sql()),
    "poisson_rows": (_poisson, _poisson_sql()),
}

QUERIES = {k: q for k, (q, _) in EXPERIMENTS.items()}
SQL = {k: s for k, (_, s) in EXPERIMENTS.items()}
