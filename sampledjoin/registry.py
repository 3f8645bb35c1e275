"""Named queries of the engine, and SQL that answers the same on another engine."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads as W
from .functions.keys import text_hash
from .functions.quantiles import t_sql, z_quantile
from .model import FilterParams, JoinInput, LatencyModel
from .operators import baselines as BL
from .operators import filters as bloom
from .operators import sampler
from .operators.filtering import key_estimate, overlap_fraction, participating, prefilter
from .operators.relational import QUERIES as RELATIONAL
from .operators.relational import SQL as RELATIONAL_SQL
from .operators.strata import count_strata, heaviest
from .plans import budget as P
from .plans import engine, sqlfront
from .plans.measures import filter_quality
from .sources.datagen import poisson_inputs
from .sources.io import load

CONF = 0.95
COLUMNS = ("estimate", "error_bound", "lower", "upper")


def _rounded(df: DataFrame, digits: int = 2, keep: tuple[str, ...] = ()) -> DataFrame:
    return df.select(*keep, *(F.round(c, digits).alias(c) for c in COLUMNS), "dof", "sampled_edges", F.col("total_edges").cast("bigint").alias("total_edges"), "mode")


def _sampled(inputs, value, s, agg="sum", dedupe=False, **options) -> DataFrame:
    """The sampling stage with draws that other engines can repeat; the filter may not change the result."""
    kept = prefilter(inputs).dfs
    return engine.estimate(kept, P.allocate(count_strata(kept), s), value, agg, dedupe, family="portable", confidence=CONF, **options)


# --- SQL that replays draws -------------------------------------------------------------------------------------------------

def _hash(*parts: str) -> str:
    return f"CAST(('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, 15)) AS BIGINT)"


def _share(s: float) -> str:
    return f"least(greatest(floor({s!r} * ne + 1e-9), 2), ne)"


def _replay(sides: list[tuple[str, str]], value: str, s: float, key: str = "jk", distinct: bool = False, extra: str = "", size: str | None = None, sizes: str = "") -> str:
    """CTEs up to p (jk, n, m, s1..s4, ne, b, is_full). sides: SELECTs with jk, and the columns that order their rows. size: SQL for b instead of the share s, over ne and, with ``sizes``, the columns of that table (jk, ...); distinct: True, or "resample" for b different edges."""
    n = len(sides)
    ctes = [f"s{i} AS (SELECT *, row_number() OVER (PARTITION BY jk ORDER BY {order}) AS pos_{i} FROM ({sql}) WHERE jk IS NOT NULL)" for i, (sql, order) in enumerate(sides, 1)]
    counts = " JOIN ".join(f"(SELECT jk, count(*) AS n_{i} FROM s{i} GROUP BY jk) c{i}" + (" USING (jk)" if i > 1 else "") for i in range(1, n + 1))
    ne = " * ".join(f"n_{i}" for i in range(1, n + 1))
    ctes.append(f"st AS (SELECT *, CAST({size or _share(s)} AS BIGINT) AS b FROM (SELECT *, CAST({ne} AS BIGINT) AS ne FROM {counts}{f' JOIN {sizes} USING (jk)' if sizes else ''}))")
    if distinct == "resample":
        ctes.append("d AS (SELECT *, b * 2 > ne AS is_full, unnest(range(1, CASE WHEN b * 2 > ne THEN ne ELSE 4 * b + 16 END + 1)) AS draw FROM st)")
    else:
        ctes.append("d AS (SELECT *, b >= ne AS is_full, unnest(range(1, b + 1)) AS draw FROM st)")
    pos, below = [], "1"
    for i in range(1, n + 1):
        pos.append(f"1 + CASE WHEN is_full THEN ((draw - 1) // ({below})) % n_{i} ELSE {_hash(key, 'draw', str(i), '42')} % n_{i} END AS pos_{i}")
        below += f" * n_{i}"
    ctes.append(f"e AS (SELECT jk, draw, {', '.join(pos)} FROM d)")
    src = "e"
    if distinct == "resample":
        every = ", ".join(f"pos_{i}" for i in range(1, n + 1))
        ctes.append(f"u0 AS (SELECT jk, min(draw) AS draw, {every} FROM e GROUP BY jk, {every})")
        ctes.append(f"u AS (SELECT * FROM (SELECT u0.*, b, row_number() OVER (PARTITION BY jk ORDER BY CASE WHEN b * 2 > ne THEN {_hash(key, 'draw', '0', '42')} ELSE 0 END, draw) AS r FROM u0 JOIN st USING (jk)) WHERE r <= b)")
        src = "u"
    elif distinct:
        ctes.append(f"u AS (SELECT jk, min(draw) AS draw, {', '.join(f'pos_{i}' for i in range(1, n + 1))} FROM e GROUP BY jk, {', '.join(f'pos_{i}' for i in range(1, n + 1))})")
        src = "u"
    ctes.append(f"j AS (SELECT {src}.jk, {src}.draw, {extra}{value} AS v FROM {src} " + " ".join(f"JOIN s{i} ON s{i}.jk = {src}.jk AND s{i}.pos_{i} = {src}.pos_{i}" for i in range(1, n + 1)) + ")")
    ctes.append("p AS (SELECT q.*, CAST(st.ne AS DOUBLE) AS ne, CAST(st.b AS DOUBLE) AS b, st.b >= st.ne AS is_full FROM (SELECT jk, count(*) AS n, count(v) AS m, CAST(sum(v) AS DOUBLE) AS s1, CAST(sum(v * v) AS DOUBLE) AS s2, sum(pow(CAST(v AS DOUBLE), 3)) AS s3, sum(pow(CAST(v AS DOUBLE), 4)) AS s4 FROM j GROUP BY jk) q JOIN st USING (jk))")
    return "WITH " + ",\n".join(ctes)


_R2 = "CASE WHEN b > 1 THEN greatest(0.0, (s2 - s1 * s1 / b) / (b - 1)) END"
_POOL = f"r AS (SELECT *, coalesce({_R2}, (SELECT sum((b - 1) * ({_R2})) / sum(CASE WHEN b > 1 THEN b - 1 END) FROM p), 0.0) AS r2 FROM p)"


def _final(total: str, bound: str, dof: str, n: str, ne: str, mode: str, digits: int = 2, groups: str = "", src: str = "a") -> str:
    return f"SELECT {groups}round({total}, {digits}) AS estimate, round({bound}, {digits}) AS error_bound, round({total} - {bound}, {digits}) AS lower, round({total} + {bound}, {digits}) AS upper, CAST({dof} AS BIGINT) AS dof, CAST({n} AS BIGINT) AS sampled_edges, CAST({ne} AS BIGINT) AS total_edges, '{mode}' AS mode FROM {src}"


def _clt_sql(sides, value, s, variance="with_replacement", divide=False, digits=2, **how) -> str:
    factor = "ne * ne" if variance == "with_replacement" else "ne * (ne - b)"
    agg = f"a AS (SELECT sum(ne / b * s1) AS total, sum(CASE WHEN is_full THEN 0.0 ELSE {factor} * r2 / b END) AS var, sum(CASE WHEN is_full THEN 0.0 ELSE b - 1 END) AS dof, sum(ne) AS ne, sum(b) AS b FROM r)"
    by = " / ne" if divide else ""
    return f"{_replay(sides, value, s, **how)},\n{_POOL},\n{agg}\n" + _final(f"(total{by})", f"({t_sql(CONF, 'dof')} * sqrt(var){by})", "dof", "b", "ne", f"clt_{variance}", digits)


def _domain_sql(sides, value, s, agg, groups="", ht=False, digits=2, **how) -> str:
    """COUNT, SUM, AVG or STDEV by group over values that may be null, written out from the single draws: residuals are formed draw by draw, zeros included. Strata of one draw, which are full, have no variance."""
    g = f"{groups}, " if groups else ""
    same = f"o.{groups} IS NOT DISTINCT FROM c.{groups}" if groups else "TRUE"
    x = {"sum": "coalesce(CAST(v AS DOUBLE), 0.0)", "count": "CASE WHEN v IS NULL THEN 0.0 ELSE 1.0 END", "avg": "CASE WHEN v IS NULL THEN 0.0 ELSE CAST(v AS DOUBLE) - mu END", "stdev": "CASE WHEN v IS NULL THEN 0.0 ELSE pow(CAST(v AS DOUBLE) - mu, 2) - var0 END"}[agg]
    w = "CASE WHEN st.b >= st.ne THEN 1.0 ELSE 1 / (1 - pow(1 - 1.0 / st.ne, st.b)) END" if ht == "draws" else "CAST(st.ne AS DOUBLE) / st.b"
    src = f"""{_replay(sides, value, s, extra=f"{groups} AS {groups}, " if groups else "", **how)},
o AS (SELECT j.*, CAST(st.ne AS DOUBLE) AS ne, CAST(st.b AS DOUBLE) AS b, st.b >= st.ne AS is_full, {w} AS w FROM j JOIN st USING (jk)),
nn AS (SELECT jk, CAST(count(*) AS DOUBLE) AS nn FROM j GROUP BY jk),
c AS (SELECT {g}sum(CASE WHEN v IS NULL THEN 0 ELSE w END) AS t0, sum(w * coalesce(CAST(v AS DOUBLE), 0.0)) AS t1, t1 / nullif(t0, 0) AS mu, greatest(sum(w * coalesce(pow(CAST(v AS DOUBLE), 2), 0.0)) / nullif(t0, 0) - mu * mu, 0.0) AS var0 FROM o {f'GROUP BY {groups}' if groups else ''}),
x AS (SELECT {f'o.{groups}, ' if groups else ''}o.jk, any_value(o.ne) AS ne, any_value(o.b) AS b, any_value(o.is_full) AS is_full, count(*) AS n, sum({x}) AS x1, sum(pow({x}, 2)) AS x2 FROM o JOIN c ON {same} GROUP BY {f'o.{groups}, ' if groups else ''}o.jk),
a AS (SELECT {g}sum(CASE WHEN is_full OR nn <= 1 THEN 0.0 ELSE {'ne * (ne - nn)' if ht else 'ne * ne'} / nn * greatest(0.0, (x2 - x1 * x1 / nn) / (nn - 1)) END) AS var, sum({'nn' if ht else 'CASE WHEN is_full THEN 0.0 ELSE b - 1 END'}) {'- 1' if ht else ''} AS dof, sum(ne) AS ne, sum(n) AS n FROM x JOIN nn USING (jk) {f'GROUP BY {groups}' if groups else ''}),
o2 AS (SELECT {'a.*' }, c.t0, c.t1, c.mu, sqrt(c.var0) AS sd FROM a JOIN c ON {'a.' + groups + ' IS NOT DISTINCT FROM c.' + groups if groups else 'TRUE'})
"""
    total = {"sum": "t1", "count": "t0", "avg": "mu", "stdev": "sd"}[agg]
    by = {"sum": "", "count": "", "avg": " / t0", "stdev": " / (2 * t0 * sd)"}[agg]
    return src + _final(total, f"({t_sql(CONF, 'dof')} * sqrt(var){by})", "dof", "n", "ne", "ht_item" if ht else "clt_with_replacement", digits, groups=g, src="o2")


def _ht_sql(sides, value, s, level, distinct=False, digits=2) -> str:
    pi = "CASE WHEN is_full THEN 1.0 ELSE 1 - pow(1 - 1 / ne, b) END" if distinct else "b / ne"
    var = "(1 - pi) / (pi * pi) * s1 * s1" if level == "stratum" else "CASE WHEN is_full THEN 0.0 ELSE ne * (ne - n) * (CASE WHEN n > 1 THEN greatest(0.0, (s2 - s1 * s1 / n) / (n - 1)) ELSE 0.0 END) / n END"
    return f"{_replay(sides, value, s, distinct=distinct)},\nh AS (SELECT *, {pi} AS pi FROM p),\na AS (SELECT sum(s1 / pi) AS total, sum({var}) AS var, CAST(sum(n) AS DOUBLE) AS n, sum(ne) AS ne FROM h)\n" + _final("total", f"({t_sql(CONF, '(n - 1)')} * sqrt(var))", "n - 1", "n", "ne", f"ht_{level}", digits)


def _line(cond: str, i: int, key: str = "l_partkey") -> tuple[str, str]:
    return f"SELECT {key} AS jk, CAST(l_extendedprice AS DECIMAL(18,2)) AS v{i}, l_orderkey AS o{i}, l_linenumber AS l{i} FROM lineitem WHERE {cond}", f"v{i} NULLS FIRST, o{i} NULLS FIRST, l{i} NULLS FIRST"


CO = [
    ("SELECT c_custkey AS jk, CAST(c_acctbal AS DECIMAL(18,2)) AS c_acctbal FROM customer", "c_acctbal NULLS FIRST"),
    ("SELECT o_custkey AS jk, o_orderkey, CAST(o_totalprice AS DECIMAL(18,2)) AS o_totalprice FROM orders", "o_orderkey NULLS FIRST, o_totalprice NULLS FIRST"),
]
CO_V = "o_totalprice + c_acctbal"
NET = [(f"SELECT user_id AS jk, event_id AS e{i}, CAST(value AS DECIMAL(18,4)) AS v{i} FROM events WHERE event_type = '{k}'", f"e{i} NULLS FIRST, v{i} NULLS FIRST") for i, k in enumerate(("click", "purchase", "error"), 1)]
NET_V = "v1 + v2 + v3"
PART = [_line("l_returnflag = 'R'", 1), _line("l_returnflag = 'A'", 2)]
LINE = [(f"SELECT l_partkey AS jk, CAST(l_extendedprice AS DECIMAL(18,2)) AS v{i}, l_orderkey AS o{i} FROM lineitem WHERE l_linenumber = {i}", f"v{i} NULLS FIRST, o{i} NULLS FIRST") for i in range(1, 5)]
NAT = [
    ("SELECT c_nationkey AS jk, CAST(c_acctbal AS DECIMAL(18,2)) AS c_acctbal, c_custkey FROM customer", "c_acctbal NULLS FIRST, c_custkey NULLS FIRST"),
    ("SELECT s_nationkey AS jk, CAST(s_acctbal AS DECIMAL(18,2)) AS s_acctbal, s_suppkey FROM supplier", "s_acctbal NULLS FIRST, s_suppkey NULLS FIRST"),
]


def _exact_sql(sides, value, digits=2) -> str:
    joins = " ".join(f"JOIN ({sql}) s{i} USING (jk)" if i > 1 else f"({sql}) s{i}" for i, (sql, _) in enumerate(sides, 1))
    return f"SELECT CAST(count(*) AS BIGINT) AS n_rows, round(CAST(sum({value}) AS DOUBLE), {digits}) AS total FROM {joins}"


def _strata_sql(sides) -> str:
    n = len(sides)
    counts = " JOIN ".join(f"(SELECT jk, count(*) AS n_{i} FROM ({sql}) GROUP BY jk) c{i}" + (" USING (jk)" if i > 1 else "") for i, (sql, _) in enumerate(sides, 1))
    return f"SELECT CAST(jk AS BIGINT) AS jk, {', '.join(f'CAST(n_{i} AS BIGINT) AS n_{i}' for i in range(1, n + 1))}, CAST({' * '.join(f'n_{i}' for i in range(1, n + 1))} AS BIGINT) AS edges FROM {counts}"


def _overlap_sql(sides) -> str:
    exists = lambda i: " AND ".join(f"jk IN (SELECT jk FROM x{k})" for k in range(1, len(sides) + 1) if k != i)
    ctes = ", ".join(f"x{i} AS ({sql})" for i, (sql, _) in enumerate(sides, 1))
    total = " + ".join(f"(SELECT count(*) FROM x{i})" for i in range(1, len(sides) + 1))
    part = " + ".join(f"(SELECT count(*) FROM x{i} WHERE {exists(i)})" for i in range(1, len(sides) + 1))
    return f"WITH {ctes} SELECT CAST({total} AS BIGINT) AS total_rows, CAST({part} AS BIGINT) AS joining_rows, round(CAST({part} AS DOUBLE) / ({total}), 8) AS overlap"


def _dialled(n: int, p: int, cond, key: str = "l_partkey") -> list[tuple[str, str]]:
    return [_line(f"({cond(i)}) AND ({key} % 100 < {p} OR {key} % {n} = {i})", i + 1, key) for i in range(n)]


# --- queries ------------------------------------------------------------------------------------------------------------------

def _co(spark, sf_dir):
    return W.customer_orders(spark, sf_dir)


def _total(df: DataFrame, digits: int = 2) -> DataFrame:
    return df.select(F.col("sampled_edges").alias("n_rows"), F.round("estimate", digits).alias("total"))


def _strata_query(make):
    return lambda s, d: count_strata([i.keyed() for i in make(s, d)[0]]).withColumn("edges", F.col("edges").cast("bigint"))


def _alloc_latency(spark, sf_dir):
    inputs, _ = _co(spark, sf_dir)
    strata = count_strata([i.keyed() for i in inputs])
    whole = strata.agg(F.sum("edges").cast("double").alias("all"))
    # a latency that allows 6e-5 s of edges after a filtering stage of 42 s
    share = F.least(F.lit(1.0), F.lit((42.00003 - 42.0) / 4.16e-9) / F.col("all"))
    out = P.allocate(strata.crossJoin(F.broadcast(whole)), share, min_b=1)
    return out.select("jk", F.col("edges").cast("bigint").alias("edges"), "b", "full")


def _sigma(spark, sf_dir):
    """Exact deviations by key, as a former run could have stored them."""
    inputs, value = _co(spark, sf_dir)
    j = engine.exact_join([i.keyed() for i in inputs])
    return inputs, j.groupBy("jk").agg(F.count("*").alias("n"), F.round(F.coalesce(F.stddev_samp(value.cast("double")), F.lit(0.0)), 4).alias("sigma")).where("n > 1")


def _alloc_error(spark, sf_dir, kind="stratum_mean", error=50_000.0):
    inputs, sigma = _sigma(spark, sf_dir)
    return P.size_for_error(count_strata([i.keyed() for i in inputs]), sigma, error, CONF, kind).select("jk", F.col("edges").cast("bigint").alias("edges"), "b", "full")


_SIGMA_SQL = f"""WITH x AS (SELECT s1.jk, {CO_V} AS v FROM ({CO[0][0]}) s1 JOIN ({CO[1][0]}) s2 USING (jk)),
st AS (SELECT jk, count(*) AS edges FROM x GROUP BY jk),
sg AS (SELECT jk, count(*) AS n, round(coalesce(stddev_samp(CAST(v AS DOUBLE)), 0.0), 4) AS sigma FROM x GROUP BY jk HAVING count(*) > 1),
k AS (SELECT st.jk, edges, coalesce(sigma, (SELECT sqrt(sum((n - 1) * sigma * sigma) / sum(n - 1)) FROM sg), 0.0) AS sigma FROM st LEFT JOIN sg USING (jk))"""
_SIZED_SQL = "SELECT CAST(jk AS BIGINT) AS jk, CAST(edges AS BIGINT) AS edges, CAST(least(greatest(need, 2), edges) AS BIGINT) AS b, least(greatest(need, 2), edges) >= edges AS \"full\" FROM ({})"


def _tradeoff(spark, sf_dir):
    inputs, sigma = _sigma(spark, sf_dir)
    strata = count_strata([i.keyed() for i in inputs]).join(sigma.select("jk", "sigma"), "jk")
    model = LatencyModel(4.16e-9, 0.5)
    a = P.latency_for_error(strata, 10_000.0, 42.0, model, CONF)
    b = P.error_for_latency(strata, 42.50002, 42.0, model, CONF)
    return a.join(b, "jk").select("jk", F.round("latency", 9).alias("latency"), F.round("error", 2).alias("error"))


def _edges_rows(make, s, dedupe=False, n=2):
    def q(spark, sf_dir):
        inputs, _ = make(spark, sf_dir)
        keyed = [i.keyed() for i in inputs]
        strata = P.allocate(count_strata(keyed), s)
        edges = sampler.draw_edges(strata, n, family="portable")
        return sampler.distinct_edges(edges, n) if dedupe else edges

    return q


def _loss_sweep(spark, sf_dir):
    inputs, value = W.by_flag(spark, sf_dir)
    keyed = [i.keyed() for i in inputs]
    strata = count_strata(keyed)
    truth = engine.exact_join(keyed).agg(F.sum(value).cast("double").alias("exact"))
    out = None
    for s in (0.1, 0.2, 0.4):
        row = engine.estimate(keyed, P.allocate(strata, s), value, family="portable").select(F.lit(s).alias("s"), "estimate", "sampled_edges").crossJoin(truth)
        row = row.select("s", F.round("estimate", 1).alias("estimate"), "sampled_edges", F.round("exact", 1).alias("exact"), F.round((F.col("estimate") - F.col("exact")) / F.col("exact"), 8).alias("loss"))
        out = row if out is None else out.unionAll(row)
    return out


def _loss_sql() -> str:
    parts = []
    for s in (0.1, 0.2, 0.4):
        parts.append(f"SELECT {s} AS s, * FROM ({_replay(PART, 'v1 + v2', s)} SELECT sum(ne / b * s1) AS est, CAST(sum(b) AS BIGINT) AS sampled_edges FROM p)")
    exact = _exact_sql(PART, "v1 + v2", 2)
    return f"SELECT CAST(s AS DOUBLE) AS s, round(est, 1) AS estimate, sampled_edges, round(x.total, 1) AS exact, round((est - x.total) / x.total, 8) AS loss FROM ({' UNION ALL '.join(parts)}), ({exact}) x"


def _business(spark, sf_dir):
    """Customers of one segment and their urgent orders: neither side's cut is on the key."""
    c = load(spark, sf_dir, "customer").where("c_mktsegment = 'BUILDING'")
    o = load(spark, sf_dir, "orders").where("o_orderpriority = '1-URGENT'")
    return [JoinInput(c, ["c_custkey"], ["c_acctbal"], "customer"), JoinInput(o, ["o_custkey"], ["o_orderkey"], "orders")]


_KEYS = ("SELECT c_custkey AS jk FROM customer WHERE c_mktsegment = 'BUILDING'", "SELECT o_custkey AS jk FROM orders WHERE o_orderpriority = '1-URGENT'")
_KEPT = FilterParams(1 << 13, 4, family="portable")


def _quality(layout: str, merge: str = "fused"):
    """(side, all rows, rows kept, rows that join and were lost) for a filter whose hashes other engines can repeat."""

    def q(spark, sf_dir):
        inputs = _business(spark, sf_dir)
        keyed = [i.keyed() for i in inputs]
        kept = prefilter(inputs, FilterParams(_KEPT.m_bits, _KEPT.h, layout=layout, family="portable"), merge).dfs
        out = None
        for i, (k, f, t) in enumerate(zip(keyed, kept, participating(inputs), strict=True), 1):
            rows = k.select(F.lit("a").alias("w"), "jk").unionAll(f.select(F.lit("k"), "jk")).unionAll(t.select(F.lit("j"), "jk")).unionAll(f.join(t.select("jk").distinct(), "jk", "left_semi").select(F.lit("f"), "jk"))
            n = lambda w: F.count(F.when(F.col("w") == w, 1))
            row = rows.agg(F.lit(i).alias("side"), n("a").alias("all_rows"), n("k").alias("kept_rows"), (n("j") - n("f")).alias("lost_rows"))
            out = row if out is None else out.unionAll(row)
        return out

    return q


def _quality_sql(layout: str) -> str:
    words, h = _KEPT.words, _KEPT.h
    one = (lambda x: (f"{_hash('jk', '0', '42')} % {words}", f"{_hash('jk', x, '42')} % 64")) if layout == "word" else (lambda x: ("0", f"{_hash('jk', x, '42')} % {words * 64}"))
    bits = [f"k{i} AS (SELECT jk, {one('x')[0]} AS slot, {one('x')[1]} AS bit FROM (SELECT DISTINCT jk FROM ({sql})), range(1, {h + 1}) r(x))" for i, sql in enumerate(_KEYS, 1)]
    both = "f AS (SELECT slot, bit FROM k1 INTERSECT SELECT slot, bit FROM k2)"
    passed = [f"p{i} AS (SELECT jk FROM k{i} LEFT JOIN f USING (slot, bit) GROUP BY jk HAVING bool_and(f.slot IS NOT NULL))".replace("f.slot IS NOT NULL", "f.bit IS NOT NULL") for i in (1, 2)]
    rows = [f"SELECT {i} AS side, CAST(count(*) AS BIGINT) AS all_rows, CAST(count(*) FILTER (WHERE jk IN (SELECT jk FROM p{i})) AS BIGINT) AS kept_rows, CAST(count(*) FILTER (WHERE jk IN ({_KEYS[2 - i]}) AND jk NOT IN (SELECT jk FROM p{i})) AS BIGINT) AS lost_rows FROM ({_KEYS[i - 1]})" for i in (1, 2)]
    return f"WITH {', '.join([*bits, both, *passed])} " + " UNION ALL ".join(rows)


def _false_positives(spark, sf_dir):
    """(other, within): rows of orders beside the segment's customers' that the sized filter lets through, held against 1.2 times the target of 0.01."""
    inputs = _business(spark, sf_dir)
    q = filter_quality(inputs[1].keyed(), prefilter(inputs, fp=0.01).dfs[1], [inputs[0].keyed()])
    return q.select(F.col("non_joining").alias("other"), "false_negatives", (F.col("rate") <= 1.2 * 0.01 + 3 * F.sqrt(F.lit(0.01) / F.col("non_joining"))).alias("within"))


_BITS = FilterParams(1 << 12, 4, family="portable")


def _bits_replay(layout):
    p = FilterParams(_BITS.m_bits, _BITS.h, layout=layout, family="portable")

    def q(spark, sf_dir):
        inputs, _ = W.flows(spark, sf_dir)
        tables = [bloom.build_filter(i.keyed(), p) for i in inputs]
        return bloom.intersect(tables).select("slot", F.bit_count("mask").cast("bigint").alias("bits"))

    return q


def _bits_sql(layout) -> str:
    words, h = _BITS.words, _BITS.h
    sides = []
    for i, k in enumerate(("click", "purchase", "error")):
        keys = f"SELECT DISTINCT user_id AS jk FROM events WHERE event_type = '{k}'"
        if layout == "word":
            sides.append(f"SELECT DISTINCT {i} AS side, {_hash('jk', '0', '42')} % {words} AS slot, {_hash('jk', 'x', '42')} % 64 AS bit FROM ({keys}), range(1, {h + 1}) r(x)")
        else:
            sides.append(f"SELECT DISTINCT {i} AS side, ({_hash('jk', 'x', '42')} % {words * 64}) // 64 AS slot, ({_hash('jk', 'x', '42')} % {words * 64}) % 64 AS bit FROM ({keys}), range(1, {h + 1}) r(x)")
    return f"SELECT CAST(slot AS BIGINT) AS slot, CAST(count(*) AS BIGINT) AS bits FROM (SELECT slot, bit FROM ({' UNION ALL '.join(sides)}) GROUP BY slot, bit HAVING count(*) = 3) GROUP BY slot"


def _cardinality(spark, sf_dir):
    keyed = W.customer_orders(spark, sf_dir)[0][1].keyed()
    p = bloom.size_filter(key_estimate([keyed]), 0.01, layout="classic")
    est = bloom.estimate_cardinality(bloom.build_filter(keyed, p), p)
    return est.crossJoin(keyed.agg(F.countDistinct("jk").alias("n_keys"))).select("n_keys", (F.abs(F.col("keys") - F.col("n_keys")) <= 0.05 * F.col("n_keys")).alias("within_5_percent"))


def _within(make, s=0.1, seeds=(1, 2, 3, 4, 5), **options):
    """(n_runs, covering): how many runs' intervals contain the exact sum; at least all but one should."""

    def q(spark, sf_dir):
        inputs, value = make(spark, sf_dir)
        keyed = [i.keyed() for i in inputs]
        strata = P.allocate(count_strata(keyed), s)
        truth = engine.exact_join(keyed).agg(F.sum(value).cast("double").alias("exact"))
        runs = None
        for seed in seeds:
            r = engine.estimate(keyed, strata, value, seed=seed, confidence=0.999, **options).select("estimate", "error_bound")
            runs = r if runs is None else runs.unionAll(r)
        return runs.crossJoin(truth).agg(F.count("*").alias("n_runs"), F.round(F.first("exact"), 2).alias("exact"), (F.sum(F.when(F.abs(F.col("estimate") - F.col("exact")) <= F.col("error_bound") + 1e-6, 1).otherwise(0)) >= len(seeds) - 1).alias("covered"))

    return q


def _within_sql(n=5) -> str:
    return f"SELECT CAST({n} AS BIGINT) AS n_runs, total AS exact, TRUE AS covered FROM ({_exact_sql(CO, CO_V)})"


def _budget_sql(spark, sf_dir):
    for t in ("customer", "orders"):
        load(spark, sf_dir, t).createOrReplaceTempView(t)
    text = "SELECT SUM(o_totalprice + c_acctbal) FROM customer, orders WHERE customer.c_custkey = orders.o_custkey AND o_orderpriority = '1-URGENT' WITHIN 3600 SECONDS OR ERROR 0.01 CONFIDENCE 95%"
    return sqlfront.sql(spark, text).select(F.round("estimate", 0).alias("estimate"), "error_bound", "mode")


def _prejoin(spark, sf_dir):
    inputs, value = W.flows(spark, sf_dir)
    ids = [["e1"], ["e2"], ["e3"]]
    return BL.prejoin_sum([i.keyed() for i in inputs], 0.3, value, ids).select(F.round("estimate", 2).alias("estimate"), "sampled_edges")


def _prejoin_sql() -> str:
    share = repr(0.3 ** (1 / 3))
    scale = repr((0.3 ** (1 / 3)) ** 3)
    kept = [f"(SELECT * FROM ({sql}) WHERE {_hash(f'e{i}', str(i), '42')} / {float(1 << 60)!r} < {share}) s{i}" for i, (sql, _) in enumerate(NET, 1)]
    return f"SELECT round(coalesce(CAST(sum({NET_V}) AS DOUBLE), 0.0) / {scale}, 2) AS estimate, CAST(count(*) AS BIGINT) AS sampled_edges FROM {kept[0]} JOIN {kept[1]} USING (jk) JOIN {kept[2]} USING (jk)"


def _postjoin(spark, sf_dir):
    inputs, value = W.flows(spark, sf_dir)
    joined = BL.repartition_join([i.keyed() for i in inputs])
    return BL.postjoin_sum(joined, 0.1, value, identity=["e1", "e2", "e3"]).select(F.round("estimate", 2).alias("estimate"), "sampled_edges", "total_edges")


def _postjoin_sql() -> str:
    src = f"({NET[0][0]}) s1 JOIN ({NET[1][0]}) s2 USING (jk) JOIN ({NET[2][0]}) s3 USING (jk)"
    return f"""WITH j AS (SELECT jk, e1, e2, e3, {NET_V} AS v FROM {src}),
r AS (SELECT *, row_number() OVER (PARTITION BY jk ORDER BY {_hash('e1', 'e2', 'e3', '42')}, e1, e2, e3) AS r, count(*) OVER (PARTITION BY jk) AS edges FROM j),
p AS (SELECT jk, count(*) AS n, any_value(edges) AS edges, CAST(sum(v) AS DOUBLE) AS s1 FROM r WHERE r <= least(greatest(ceil(0.1 * edges - 1e-9), 2), edges) GROUP BY jk)
SELECT round(sum(edges / n * s1), 2) AS estimate, CAST(sum(n) AS BIGINT) AS sampled_edges, CAST(sum(edges) AS BIGINT) AS total_edges FROM p"""


def _hybrid(spark, sf_dir):
    inputs, value = _co(spark, sf_dir)
    return BL.hybrid_postjoin([i.keyed() for i in inputs], 0.6, value, ["o_orderkey"]).select(F.round("estimate", 2).alias("estimate"), "sampled_edges")


def _group(spark, sf_dir):
    c = load(spark, sf_dir, "customer").select("c_custkey", W.money("c_acctbal").alias("c_acctbal"))
    o = load(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", W.money("o_totalprice").alias("o_totalprice"), "o_orderpriority")
    inputs = [JoinInput(c, ["c_custkey"], ["c_acctbal"]), JoinInput(o, ["o_custkey"], ["o_orderkey", "o_totalprice", "o_orderpriority"])]
    return _rounded(_sampled(inputs, F.col("o_totalprice") + F.col("c_acctbal"), 0.3, group_by=["o_orderpriority"]).drop("fraction"), 2, ("o_orderpriority",)).drop("dof", "sampled_edges", "total_edges")


def _group_sql() -> str:
    sides = [CO[0], ("SELECT o_custkey AS jk, o_orderkey, CAST(o_totalprice AS DECIMAL(18,2)) AS o_totalprice, o_orderpriority FROM orders", "o_orderkey NULLS FIRST")]
    base = _replay(sides, CO_V, 0.3, extra="o_orderpriority, ")
    r2 = _R2
    return f"""{base},
g AS (SELECT q.*, CAST(st.ne AS DOUBLE) AS ne, CAST(st.b AS DOUBLE) AS b, st.b >= st.ne AS is_full FROM (SELECT jk, o_orderpriority, CAST(sum(v) AS DOUBLE) AS s1, CAST(sum(v * v) AS DOUBLE) AS s2 FROM j GROUP BY jk, o_orderpriority) q JOIN st USING (jk)),
r AS (SELECT *, coalesce({r2}, (SELECT sum((b - 1) * ({r2})) / sum(CASE WHEN b > 1 THEN b - 1 END) FROM g), 0.0) AS r2 FROM g),
a AS (SELECT o_orderpriority, sum(ne / b * s1) AS total, sum(CASE WHEN is_full THEN 0.0 ELSE ne * ne * r2 / b END) AS var, sum(CASE WHEN is_full THEN 0.0 ELSE b - 1 END) AS dof FROM r GROUP BY o_orderpriority)
SELECT o_orderpriority, round(total, 2) AS estimate, round({t_sql(CONF, 'dof')} * sqrt(var), 2) AS error_bound, round(total - {t_sql(CONF, 'dof')} * sqrt(var), 2) AS lower, round(total + {t_sql(CONF, 'dof')} * sqrt(var), 2) AS upper, 'clt_with_replacement' AS mode FROM a"""


def _text_payload(kind):
    def q(spark, sf_dir):
        if kind == "labels":
            d, x = load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")
            return d.select("doc_id", "n_chars").join(x, "doc_id").groupBy("quality", "toxic").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))
        v = load(spark, sf_dir, "embeddings").select("label")
        return count_strata([JoinInput(v, ["label"]).keyed()] * 2).select("jk", "n_1", F.col("edges").cast("bigint").alias("edges"))

    return q


def _poisson(spark, sf_dir):
    """(strata, low_overlap) of inputs over the orders' keys; by a mean of ten rows hardly a common key has none on either side."""
    ids = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id")).where("id is not null").distinct()
    inputs = poisson_inputs(spark, 2, 10.0, overlap=0.1, family="portable", ids=ids)
    return W.overlap_row(inputs).select("strata", (F.col("joining_rows") < 0.2 * F.col("total_rows")).alias("low_overlap"))


def poisson_steps(lam: float) -> list[str]:
    """The terms of ``datagen.poisson_counts`` over a column u."""
    steps, total, p = [], 0.0, math.exp(-lam)
    for k in range(int(lam + 8 * math.sqrt(lam) + 8)):
        total += p
        steps.append(f"(CASE WHEN u > {total!r} THEN 1 ELSE 0 END)")
        p *= lam / (k + 1)
    return steps


def _poisson_sql() -> str:
    u = lambda i: f"(({_hash('id', str(i), '42')} % {1 << 52}) + 0.5) / {float(1 << 52)!r}"
    counts = [f"(SELECT id, {' + '.join(poisson_steps(10.0))} AS c FROM (SELECT id, {u(i)} AS u FROM (SELECT DISTINCT o_orderkey AS id FROM orders WHERE o_orderkey IS NOT NULL)))" for i in range(2)]
    return f"SELECT CAST(count(*) AS BIGINT) AS strata, TRUE AS low_overlap FROM {counts[0]} a JOIN {counts[1]} b USING (id) WHERE id % 1000 < 100 AND a.c > 0 AND b.c > 0"


def _calibration(spark, sf_dir):
    m = P.calibrate(spark, (500, 1000, 1500), 1, load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), F.col("o_totalprice").alias("v")))
    return spark.createDataFrame([(m.beta, m.epsilon, m.r2)], "beta double, epsilon double, r2 double")


def _sweep(make, ps, n):
    def q(spark, sf_dir):
        out = None
        for p in ps:
            row = W.overlap_row(make(spark, sf_dir, p)[0]).select(F.lit(p).alias("p"), "total_rows", "joining_rows", "strata", "edges")
            out = row if out is None else out.unionAll(row)
        return out

    return q


def _sweep_sql(make, ps) -> str:
    parts = [f"SELECT {p} AS p, o.total_rows, o.joining_rows, CAST(count(*) AS BIGINT) AS strata, CAST(coalesce(sum(edges), 0) AS BIGINT) AS edges FROM ({_strata_sql(make(p))}) s RIGHT JOIN ({_overlap_sql(make(p))}) o ON TRUE GROUP BY ALL" for p in ps]
    return " UNION ALL ".join(parts)


def _simulation_sql(workers=10, m_bits=1 << 16) -> str:
    out = []
    for n, p in [(2, 1), (3, 1), (4, 1), (3, 2), (3, 4), (3, 6), (3, 8), (3, 10), (3, 40)]:
        sides = [f"SELECT l_partkey AS jk FROM lineitem WHERE l_linenumber = {i + 1} AND (l_partkey % 100 < {p} OR l_partkey % {n} = {i})" for i in range(n)]
        ctes = ", ".join(f"x{i} AS ({s})" for i, s in enumerate(sides))
        t = [f"(SELECT count(*) FROM x{i})" for i in range(n)]
        j = ["(SELECT count(*) FROM x{} WHERE {})".format(i, " AND ".join(f"jk IN (SELECT jk FROM x{k})" for k in range(n) if k != i)) for i in range(n)]
        weigh = lambda xs: " + ".join(f"CAST({x} AS DOUBLE) * 24.0" for x in xs)
        filters = n * m_bits / 8 * (workers - 1) + m_bits / 8 * workers
        out.append(f"SELECT * FROM (WITH {ctes} SELECT {n} AS n_inputs, {p} AS p, round(({weigh(t)}) * {(workers - 1) / workers!r}, 1) AS repartition_bytes, round(({weigh(t[1:])}) * {workers - 1}, 1) AS broadcast_bytes, round({filters!r} + ({weigh(j)}) * {(workers - 1) / workers!r}, 1) AS filtered_bytes)")
    return " UNION ALL ".join(out)


def _cascade(spark, sf_dir):
    c = load(spark, sf_dir, "customer").select("c_custkey", W.money("c_acctbal").alias("c_acctbal"))
    o = load(spark, sf_dir, "orders").select("o_custkey", F.col("o_orderkey"))
    li = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", W.money("l_extendedprice").alias("price"))
    first = JoinInput(c, ["c_custkey"], ["c_acctbal"])
    second = JoinInput(li, ["l_orderkey"], ["price", "l_linenumber", "l_partkey"])
    return _rounded(engine.cascade(first, o, ("o_custkey", "o_orderkey"), second, F.col("price"), [], 0.3, family="portable"))


CASCADE = [
    ("SELECT o_orderkey AS jk, CAST(c_acctbal AS DECIMAL(18,2)) AS c_acctbal FROM orders JOIN customer ON o_custkey = c_custkey", "c_acctbal NULLS FIRST"),
    ("SELECT l_orderkey AS jk, CAST(l_extendedprice AS DECIMAL(18,2)) AS price, l_linenumber, l_partkey FROM lineitem", "price NULLS FIRST, l_linenumber NULLS FIRST, l_partkey NULLS FIRST"),
]


def _join_total(make, method):
    return lambda s, d: _total(W.run(*make(s, d), method))


def _hash_check(spark, sf_dir):
    return load(spark, sf_dir, "nation").select("n_nationkey", text_hash(F.col("n_nationkey"), 3, 1, 42).alias("h"))


def _ratings(pair):
    def q(spark, sf_dir):
        inputs = W.ratings(spark, sf_dir, pair)
        return engine.exact_join(prefilter(inputs).dfs).agg(F.count("*").alias("n_rows"))

    return q


def _ratings_sql(pair) -> str:
    keys = "l_partkey, l_suppkey" if pair else "l_partkey"
    return f"SELECT CAST(count(*) AS BIGINT) AS n_rows FROM (SELECT {keys} FROM lineitem WHERE l_linenumber <= 6) a JOIN (SELECT {'DISTINCT ' if pair else ''}{keys} FROM lineitem WHERE l_linenumber = 7) b USING ({keys})"


def _two_way(spark, sf_dir, p=100):
    return W.by_flag(spark, sf_dir, "RA", p=p)


def _three_way(spark, sf_dir, p=100):
    return W.by_flag(spark, sf_dir, "RAN", p=p)


def _four_way(spark, sf_dir, p=100):
    return W.by_line(spark, sf_dir, 4, p)


def _line_sides(p):
    return [(f"SELECT l_partkey AS jk FROM lineitem WHERE l_linenumber = {i + 1} AND (l_partkey % 100 < {p} OR l_partkey % 4 = {i})", "") for i in range(4)]


def _prob_sql() -> str:
    return _SIGMA_SQL + " " + _SIZED_SQL.format(f"SELECT jk, edges, ceil({(z_quantile(CONF) / 1e7) ** 2!r} * (edges * sigma) * (SELECT sum(edges * sigma) FROM k)) AS need FROM k")


TWO, THREE, FOUR = (1, 2, 4, 6, 8, 10, 20, 40, 100), (1, 2, 4, 6, 8, 10), (1, 4, 10)
FLAGS = "RAN"

#: name: (query, SQL or None)
ENGINE: dict[str, tuple] = {
    "co_clt_sum": (lambda s, d: _rounded(_sampled(*_co(s, d), 0.3)), _clt_sql(CO, CO_V, 0.3)),
    "co_clt_sum_published": (lambda s, d: _rounded(_sampled(*_co(s, d), 0.6, variance="published")), _clt_sql(CO, CO_V, 0.6, "published")),
    "co_clt_avg": (lambda s, d: _rounded(_sampled(*_co(s, d), 0.3, agg="avg"), 4), _clt_sql(CO, CO_V, 0.3, divide=True, digits=4)),
    "co_clt_stdev": (lambda s, d: _rounded(_sampled(*_co(s, d), 0.5, agg="stdev"), 1), _domain_sql(CO, CO_V, 0.5, "stdev", digits=1)),
    "co_count": (lambda s, d: _sampled(*_co(s, d), 0.3, agg="count").select("estimate", "error_bound"), f"SELECT CAST(n_rows AS DOUBLE) AS estimate, 0.0::DOUBLE AS error_bound FROM ({_exact_sql(CO, CO_V)})"),
    "co_ht_item": (lambda s, d: _rounded(_sampled(*_co(s, d), 0.3, estimator="ht")), _ht_sql(CO, CO_V, 0.3, "item")),
    "co_ht_stratum": (lambda s, d: _rounded(_sampled(*_co(s, d), 0.3, estimator="ht", level="stratum")), _ht_sql(CO, CO_V, 0.3, "stratum")),
    "co_ht_distinct_draws": (lambda s, d: _rounded(_sampled(*_co(s, d), 0.5, dedupe="distinct", estimator="ht")), _ht_sql(CO, CO_V, 0.5, "item", distinct=True)),
    "co_resample": (lambda s, d: _rounded(_sampled(*_co(s, d), 0.4, dedupe="resample")), _clt_sql(CO, CO_V, 0.4, "without_replacement", distinct="resample")),
    "co_array": (lambda s, d: _rounded(_sampled(*_co(s, d), 0.3, strategy="array")), _clt_sql(CO, CO_V, 0.3)),
    "co_salted": (lambda s, d: _rounded(_sampled(*_co(s, d), 0.3, salts=8)), _clt_sql([(sql, f"{_hash(*order.replace(' NULLS FIRST', '').split(', '), '3')} % 8, {order}") for sql, order in CO], CO_V, 0.3)),
    "co_grouped_within": (_within(_co, 0.3, strategy="grouped", seeds=(1, 2)), _within_sql(2)),
    "co_exact_sum": (lambda s, d: W.exact_value(*_co(s, d)), _exact_sql(CO, CO_V)),
    "co_filtered_sum": (_join_total(_co, "filter_only"), _exact_sql(CO, CO_V)),
    "co_native_join": (_join_total(_co, "native"), _exact_sql(CO, CO_V)),
    "co_repartition_join": (_join_total(_co, "repartition"), _exact_sql(CO, CO_V)),
    "co_union_join": (_join_total(_co, "union"), _exact_sql(CO, CO_V)),
    "co_broadcast_join": (_join_total(_co, "broadcast"), _exact_sql(CO, CO_V)),
    "co_full_fraction": (lambda s, d: _total(_sampled(*_co(s, d), 1.0)), _exact_sql(CO, CO_V)),
    "co_overlap": (lambda s, d: overlap_fraction(_co(s, d)[0]), _overlap_sql(CO)),
    "co_strata": (_strata_query(_co), _strata_sql(CO)),
    "co_heaviest_strata": (lambda s, d: heaviest(count_strata([i.keyed() for i in _co(s, d)[0]]), 5).select("jk", F.col("edges").cast("bigint").alias("edges")), f"SELECT jk, edges FROM ({_strata_sql(CO)}) ORDER BY edges DESC, jk LIMIT 5"),
    "co_alloc_latency": (_alloc_latency, f"SELECT jk, edges, CAST(least(greatest(floor(least(1.0, {(42.00003 - 42.0) / 4.16e-9!r} / CAST(sum(edges) OVER () AS DOUBLE)) * edges + 1e-9), 1), edges) AS BIGINT) AS b, least(greatest(floor(least(1.0, {(42.00003 - 42.0) / 4.16e-9!r} / CAST(sum(edges) OVER () AS DOUBLE)) * edges + 1e-9), 1), edges) >= edges AS \"full\" FROM ({_strata_sql(CO)})"),
    "co_alloc_error": (_alloc_error, _SIGMA_SQL + " " + _SIZED_SQL.format(f"SELECT jk, edges, ceil(pow({z_quantile(CONF)!r} * sigma / 50000.0, 2.0) - 1e-9) AS need FROM k")),
    "co_alloc_total_error": (lambda s, d: _alloc_error(s, d, "total_abs", 1e7), _prob_sql()),
    "tradeoff_curve": (_tradeoff, f"{_SIGMA_SQL} SELECT CAST(k.jk AS BIGINT) AS jk, round({z_quantile(CONF) ** 2!r} * pow(k.sigma / 10000.0, 2.0) * 4.16e-9 / k.edges * (SELECT CAST(sum(st.edges) AS DOUBLE) FROM st JOIN sg USING (jk)) + 42.5, 9) AS latency, round({z_quantile(CONF)!r} * k.sigma / sqrt(greatest(1.0, least(1.0, {(42.50002 - 42.0 - 0.5) / 4.16e-9!r} / (SELECT CAST(sum(st.edges) AS DOUBLE) FROM st JOIN sg USING (jk))) * k.edges)), 2) AS error FROM k JOIN sg USING (jk)"),
    "co_sample_edges": (_edges_rows(_co, 0.3), _replay(CO, CO_V, 0.3) + " SELECT CAST(jk AS BIGINT) AS jk, CAST(draw AS BIGINT) AS draw, CAST(pos_1 AS BIGINT) AS pos_1, CAST(pos_2 AS BIGINT) AS pos_2 FROM e"),
    "co_dedupe_edges": (_edges_rows(_co, 0.6, True), _replay(CO, CO_V, 0.6, distinct=True) + " SELECT CAST(jk AS BIGINT) AS jk, CAST(draw AS BIGINT) AS draw, CAST(pos_1 AS BIGINT) AS pos_1, CAST(pos_2 AS BIGINT) AS pos_2 FROM u"),
    "co_hybrid_postjoin": (_hybrid, f"SELECT round(CAST(sum({CO_V}) AS DOUBLE) / 0.6, 2) AS estimate, CAST(count(*) AS BIGINT) AS sampled_edges FROM ({CO[0][0]}) s1 JOIN ({CO[1][0]}) s2 USING (jk) WHERE {_hash('o_orderkey', '42')} / {float(1 << 60)!r} < 0.6"),
    "group_by_priority": (_group, _group_sql()),
    "budget_sql": (_budget_sql, "SELECT round(CAST(sum(CAST(o_totalprice + c_acctbal AS DOUBLE)) AS DOUBLE), 0) AS estimate, CAST(0 AS DOUBLE) AS error_bound, 'exact' AS mode FROM customer JOIN orders ON c_custkey = o_custkey WHERE o_orderpriority = '1-URGENT'"),
    "net3_exact": (lambda s, d: W.exact_value(*W.flows(s, d)), _exact_sql(NET, NET_V)),
    "net3_filtered": (_join_total(W.flows, "filter_only"), _exact_sql(NET, NET_V)),
    "net3_clt_sum": (lambda s, d: _rounded(_sampled(*W.flows(s, d), 0.1)), _clt_sql(NET, NET_V, 0.1)),
    "net3_prejoin_sum": (_prejoin, _prejoin_sql()),
    "net3_postjoin_sum": (_postjoin, _postjoin_sql()),
    "net3_low_overlap": (lambda s, d: overlap_fraction(W.flows(s, d, True)[0]), _overlap_sql([(f"SELECT user_id AS jk FROM events, (SELECT max(user_id) + 1 AS u FROM events) WHERE event_type = '{k}' AND {c}", "") for k, c in W.CUTS.items()])),
    "part_exact": (lambda s, d: W.exact_value(*_two_way(s, d)), _exact_sql(PART, "v1 + v2")),
    "part_clt_sum": (lambda s, d: _rounded(_sampled(*_two_way(s, d), 0.1), 1), _clt_sql(PART, "v1 + v2", 0.1, digits=1)),
    "part_overlap_sweep": (_sweep(_two_way, TWO, 2), _sweep_sql(lambda p: _dialled(2, p, lambda i: f"l_returnflag = '{FLAGS[i]}'"), TWO)),
    "part3_overlap_sweep": (_sweep(_three_way, THREE, 3), _sweep_sql(lambda p: _dialled(3, p, lambda i: f"l_returnflag = '{FLAGS[i]}'"), THREE)),
    "line4_overlap_sweep": (_sweep(_four_way, FOUR, 4), _sweep_sql(_line_sides, FOUR)),
    "line4_exact": (lambda s, d: W.exact_value(*_four_way(s, d)), _exact_sql(LINE, "v1 + v2 + v3 + v4")),
    "line4_clt": (lambda s, d: _rounded(_sampled(*_four_way(s, d), 0.1), 1), _clt_sql(LINE, "v1 + v2 + v3 + v4", 0.1, digits=1)),
    "accuracy_loss_sweep": (_loss_sweep, _loss_sql()),
    "tpch_q3_joins": (lambda s, d: W.tpch(s, d, "q3"), "SELECT CAST(count(*) AS BIGINT) AS n_rows, round(CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE), 2) AS price FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey"),
    "tpch_q4_joins": (lambda s, d: W.tpch(s, d, "q4"), "SELECT CAST(count(*) AS BIGINT) AS n_rows, CAST(count(DISTINCT o_orderkey) AS BIGINT) AS n_orders FROM orders JOIN lineitem ON o_orderkey = l_orderkey"),
    "tpch_q10_joins": (lambda s, d: W.tpch(s, d, "q10"), "SELECT CAST(count(*) AS BIGINT) AS n_rows, round(CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE), 2) AS price FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey JOIN nation ON c_nationkey = n_nationkey"),
    "q3_cascade_sample": (_cascade, _clt_sql(CASCADE, "price", 0.3)),
    "ratings_join": (_ratings(False), _ratings_sql(False)),
    "ratings_pair_join": (_ratings(True), _ratings_sql(True)),
    "nation_join": (lambda s, d: W.exact_value(*W.nations(s, d)), _exact_sql(NAT, "c_acctbal + s_acctbal")),
    "nation_clt_sum": (lambda s, d: _rounded(_sampled(*W.nations(s, d), 0.1)), _clt_sql(NAT, "c_acctbal + s_acctbal", 0.1)),
    "shuffle_model": (W.shuffle_simulation, _simulation_sql()),
    "filter_no_false_neg": (_quality("word"), _quality_sql("word")),
    "filter_sharded_merge": (_quality("word", "sharded"), _quality_sql("word")),
    "filter_classic": (_quality("classic"), _quality_sql("classic")),
    "filter_counting": (_quality("counting"), _quality_sql("classic")),
    "filter_tree_merge": (_quality("word", "tree"), _quality_sql("word")),
    "filter_driver_merge": (_quality("word", "driver"), _quality_sql("word")),
    "filter_false_positives": (_false_positives, f"SELECT CAST(count(*) AS BIGINT) AS other, CAST(0 AS BIGINT) AS false_negatives, TRUE AS within FROM ({_KEYS[1]}) WHERE jk NOT IN ({_KEYS[0]})"),
    "filter_bits_replay": (_bits_replay("word"), _bits_sql("word")),
    "filter_classic_replay": (_bits_replay("classic"), _bits_sql("classic")),
    "filter_cardinality": (_cardinality, "SELECT CAST(count(DISTINCT o_custkey) AS BIGINT) AS n_keys, TRUE AS within_5_percent FROM orders"),
    "hash_replay": (_hash_check, f"SELECT n_nationkey, {_hash('n_nationkey', '3', '1', '42')} AS h FROM nation"),
    "docs_labels_join": (_text_payload("labels"), "SELECT quality, toxic, CAST(count(*) AS BIGINT) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents JOIN labels USING (doc_id) GROUP BY quality, toxic"),
    "embedding_label_join": (_text_payload("labels2"), "SELECT CAST(label AS BIGINT) AS jk, CAST(count(*) AS BIGINT) AS n_1, CAST(count(*) * count(*) AS BIGINT) AS edges FROM embeddings GROUP BY label"),
    "poisson_inputs": (_poisson, _poisson_sql()),
    "calibration": (_calibration, None),
}


QUERIES = {k: q for k, (q, _) in ENGINE.items()} | RELATIONAL
SQL = {k: s for k, (_, s) in ENGINE.items() if s} | RELATIONAL_SQL
FLAGSHIP = "co_clt_sum"
