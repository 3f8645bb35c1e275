"""What the operators pass to each other."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class JoinInput:
    """A table, the columns of its join key, and the columns that the query uses beside them."""

    df: DataFrame
    keys: Sequence[str]
    columns: Sequence[str] = ()
    name: str = ""

    def keyed(self) -> DataFrame:
        """(jk, columns...): rows with a null key left out, as they join nothing."""
        from .functions.keys import join_key

        return self.df.select(join_key([self.df[c] for c in self.keys], [self.df.schema[c].dataType for c in self.keys]).alias("jk"), *self.columns).where(F.col("jk").isNotNull())


@dataclass(frozen=True)
class FilterParams:
    """m_bits and h of a Bloom filter; layout: word (h bits in one 64-bit word), classic (h words), counting (counters), scalable (generations)."""

    m_bits: int
    h: int
    seed: int = 42
    layout: str = "word"
    family: str = "xx"

    @property
    def words(self) -> int:
        return max(1, -(-self.m_bits // 64))


@dataclass(frozen=True)
class Budget:
    """A desired latency in seconds, a desired error, or both. error_kind: stratum_mean, total_abs or relative."""

    latency_s: float | None = None
    error: float | None = None
    confidence: float = 0.95
    error_kind: str = "stratum_mean"


@dataclass(frozen=True)
class LatencyModel:
    """Seconds for a number of edges: beta for each, and epsilon."""

    beta: float = 4.16e-9
    epsilon: float = 0.0
    r2: float = 1.0

    def predict(self, edges: float) -> float:
        return self.beta * edges + self.epsilon

    def save(self, spark, path: str) -> None:
        spark.createDataFrame([(self.beta, self.epsilon, self.r2)], "beta double, epsilon double, r2 double").write.mode("overwrite").parquet(path)

    @staticmethod
    def load(spark, path: str) -> LatencyModel:
        return LatencyModel(*spark.read.parquet(path).first())


class InfeasibleError(ValueError):
    """The budget can't be met; ``least`` is the smallest latency that can."""

    def __init__(self, message: str, least: float):
        super().__init__(message)
        self.least = least
