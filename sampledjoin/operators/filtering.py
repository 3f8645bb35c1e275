"""The filtering stage over several inputs, and how much of them joins."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import FilterParams, JoinInput
from . import filters as B


@dataclass(frozen=True)
class FilteredInputs:
    dfs: list[DataFrame]
    table: DataFrame
    params: FilterParams


def key_estimate(keyed: list[DataFrame]) -> int:
    """Distinct keys of the input that has most of them, approximately, in one job: a filter of that size is useful to all inputs."""
    rows = reduce(DataFrame.unionAll, (k.select("jk", F.lit(i).alias("side")) for i, k in enumerate(keyed)))
    counts = rows.agg(*(F.approx_count_distinct(F.when(F.col("side") == i, F.col("jk"))).alias(f"n_{i}") for i in range(len(keyed)))).first()
    return max(counts)


def prefilter(inputs: list[JoinInput], params: FilterParams | None = None, merge: str = "fused", fp: float = 0.01, ordered: bool = False) -> FilteredInputs:
    """All inputs at once: a filter of each, their intersection, and the rows whose key may be in it. Without ``params`` a job counts the keys first. merge: fused makes the
    intersection by one exchange; the others build a filter of each input by that scheme (``build_filter``) and intersect them. ``ordered``: the first input's filter already thins the
    others before theirs are built, for inputs of which the first is by far the smallest."""
    keyed = [i.keyed() for i in inputs]
    p = params or B.size_filter(key_estimate(keyed), fp)
    fused = merge == "fused" and p.layout == "word" and not ordered
    merge = "sharded" if merge == "fused" else merge
    if ordered:
        first = B.build_filter(keyed[0], p, merge)
        rest = [B.apply_filter(k, first, p) for k in keyed[1:]]
        table = B.intersect([first, *(B.build_filter(k, p, merge) for k in rest)], p.layout)
    else:
        table = B.join_filter(keyed, p) if fused else B.intersect([B.build_filter(k, p, merge) for k in keyed], p.layout)
    return FilteredInputs([B.apply_filter(k, table, p, fused) for k in keyed], table, p)


def chained_prefilter(inputs: list[JoinInput], params: FilterParams) -> list[DataFrame]:
    """The ablation: pairs are filtered one after the other, each round over what the last one kept."""
    keyed = [i.keyed() for i in inputs]
    for i in range(1, len(keyed)):
        both = B.intersect([B.build_filter(keyed[i - 1], params), B.build_filter(keyed[i], params)], params.layout)
        keyed[i - 1], keyed[i] = B.apply_filter(keyed[i - 1], both, params), B.apply_filter(keyed[i], both, params)
    return keyed


def participating(inputs: list[JoinInput]) -> list[DataFrame]:
    """The rows of each input whose key is in all inputs, exactly."""
    keyed = [i.keyed() for i in inputs]
    common = reduce(lambda a, b: a.join(b, "jk", "left_semi"), (k.select("jk").distinct() for k in keyed))
    return [k.join(common, "jk", "left_semi") for k in keyed]


def overlap_fraction(inputs: list[JoinInput], mode: str = "exact", params: FilterParams | None = None) -> DataFrame:
    """(total_rows, joining_rows, overlap): rows that take part over all rows; mode filter counts what survives the filter, an upper bound."""
    keyed = [i.keyed() for i in inputs]
    kept = participating(inputs) if mode == "exact" else prefilter(inputs, params).dfs
    rows = reduce(DataFrame.unionAll, [*(k.select(F.lit(0).alias("joins")) for k in keyed), *(k.select(F.lit(1).alias("joins")) for k in kept)])
    both = rows.agg(F.sum(1 - F.col("joins")).cast("bigint").alias("total_rows"), F.sum("joins").cast("bigint").alias("joining_rows"))
    return both.select("total_rows", F.coalesce("joining_rows", F.lit(0)).alias("joining_rows"), F.round(F.coalesce("joining_rows", F.lit(0)) / F.col("total_rows"), 8).alias("overlap"))
