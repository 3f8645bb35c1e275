"""Standard deviations by key that one run leaves for the next."""

from __future__ import annotations

import hashlib
import time

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.utils import AnalysisException


def fingerprint(*parts: object) -> str:
    """A query's name in the store: a digest of what defines it."""
    return hashlib.sha256("|".join(map(str, parts)).encode()).hexdigest()[:32]


class FeedbackStore:
    """Parquet, appended to by each run; a query's keys are read from its latest run. Keys seen only once are not kept, as they have no deviation."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def save(self, name: str, sigma: DataFrame) -> None:
        sigma.where("n > 1").select("jk", "n", "sigma", F.lit(name).alias("query"), F.lit(time.time_ns()).alias("run")).write.mode("append").partitionBy("query").parquet(self.path)

    def load(self, name: str) -> DataFrame | None:
        """(jk, n, sigma) of the latest run, or None."""
        try:
            rows = self.spark.read.parquet(self.path).where(F.col("query") == name)
        except AnalysisException:
            return None
        latest = rows.withColumn("last", F.max("run").over(Window.partitionBy("jk"))).where("run = last").select("jk", "n", "sigma")
        return None if latest.isEmpty() else latest
