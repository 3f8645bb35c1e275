"""Cost and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def timed(df: DataFrame) -> float:
    """Seconds to compute all rows, without keeping them."""
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def breakdown(stages: dict[str, Callable[[], DataFrame]]) -> dict[str, float]:
    """Seconds of each named stage."""
    return {name: timed(make()) for name, make in stages.items()}


def shuffle_measured(df: DataFrame) -> int:
    """Bytes that the stages of one run of ``df`` wrote to shuffles, from the plan's own metrics (classic sessions only)."""
    return moved_bytes(df)[0]


def moved_bytes(df: DataFrame) -> tuple[int, int]:
    """(bytes written to shuffles, bytes broadcast) by one run of ``df``, from the plan's own metrics (classic sessions only). What is broadcast goes to every node; a part that the plan uses again counts once."""
    qe = df._jdf.queryExecution()
    qe.toRdd().count()
    total, sent, todo = 0, 0, [qe.executedPlan()]
    while todo:
        node = todo.pop()
        if node.getClass().getSimpleName() == "AdaptiveSparkPlanExec":
            todo.append(node.executedPlan())
            continue
        if node.getClass().getSimpleName().endswith("QueryStageExec"):
            todo.append(node.plan())
            continue
        metric = node.metrics().get("shuffleBytesWritten")
        if metric.isDefined():
            total += metric.get().value()
        if node.getClass().getSimpleName() == "BroadcastExchangeExec":
            sent += node.metrics().apply("dataSize").value()
        kids = node.children()
        todo += [kids.apply(i) for i in range(kids.size())]
    return total, sent


def shuffle_model(kind: str, rows: list[Column], widths: list[float], workers: int, m_bits: int = 0, survivors: list[Column] | None = None) -> Column:
    """Bytes between nodes. repartition: all rows; broadcast: all inputs but the first, to every other node; filtered: filters merged and sent to all nodes, then surviving rows."""
    moved = (workers - 1) / workers
    weigh = lambda counts, ws: sum((c.cast("double") * w for c, w in zip(counts[1:], ws[1:], strict=True)), counts[0].cast("double") * ws[0])
    if kind == "repartition":
        return weigh(rows, widths) * moved
    if kind == "broadcast":
        return weigh(rows[1:], widths[1:]) * (workers - 1)
    filters = (len(rows) * m_bits / 8 * (workers - 1)) + m_bits / 8 * workers
    return F.lit(filters) + weigh(survivors, widths) * moved


def accuracy_loss(approx: Column, exact: Column) -> Column:
    """(approx - exact) / exact, signed."""
    return (approx - exact) / exact


def ratio(baseline: float, ours: float) -> float:
    """Speed-up or reduction."""
    return baseline / ours if ours else float("inf")


def budget_error(actual_s: float, desired_s: float) -> float:
    return abs(actual_s - desired_s)


def coverage(runs: list[tuple[float, float]], exact: float) -> float:
    """The share of (lower, upper) that contain the exact value."""
    return sum(lo <= exact <= hi for lo, hi in runs) / len(runs)


def filter_quality(keyed: DataFrame, kept: DataFrame, others: list[DataFrame]) -> DataFrame:
    """(false_positives, non_joining, rate, false_negatives) of a filtered input against the keys that all others have."""
    common = others[0].select("jk").distinct()
    for o in others[1:]:
        common = common.join(o.select("jk"), "jk", "left_semi")
    rest = keyed.join(common, "jk", "left_anti").agg(F.count("*").alias("non_joining"))
    fp = kept.join(common, "jk", "left_anti").agg(F.count("*").alias("false_positives"))
    lost = keyed.join(common, "jk", "left_semi").agg(F.count("*").alias("joining")).crossJoin(kept.join(common, "jk", "left_semi").agg(F.count("*").alias("kept_joining")))
    return rest.crossJoin(fp).crossJoin(lost).select("false_positives", "non_joining", (F.col("false_positives") / F.col("non_joining")).alias("rate"), (F.col("joining") - F.col("kept_joining")).alias("false_negatives"))
