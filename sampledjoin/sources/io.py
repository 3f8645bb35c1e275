"""Sources and sinks."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def load(spark: SparkSession, folder: str, name: str, fmt: str = "parquet", schema: T.StructType | str | None = None, **options) -> DataFrame:
    """A table of a folder, or of the catalog; csv and json want a schema, as inferring one reads the data twice."""
    if fmt == "catalog":
        return catalog_table(spark, name)
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(f"{folder}/{name}.{fmt}")


def shared_folder(spark: SparkSession) -> str:
    """The folder that spark.checkpoint.dir names; a folder of this machine only where that is unset and the session is local."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if spark.sparkContext.master.partition("[")[0] != "local":
            raise ValueError("spark.checkpoint.dir has to name a folder that the driver and all executors share")
        base = f"file://{tempfile.gettempdir()}/checkpoints"
    return base.rstrip("/")


def stored(df: DataFrame, tag: str) -> DataFrame:
    """``df`` as a table in the shared folder: computed once, read as often as wanted, and there if executors are lost."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def catalog_table(spark: SparkSession, name: str) -> DataFrame:
    return spark.table(name)


def jdbc(spark: SparkSession, url: str, table: str, key: str, lower: int, upper: int, parts: int) -> DataFrame:
    """Read in ``parts`` ranges of a numeric key."""
    return spark.read.format("jdbc").options(url=url, dbtable=table, partitionColumn=key, lowerBound=lower, upperBound=upper, numPartitions=parts).load()


def kafka(spark: SparkSession, servers: str, topic: str) -> DataFrame:
    return spark.readStream.format("kafka").options(**{"kafka.bootstrap.servers": servers, "subscribe": topic}).load()


def read_grouped_text(spark: SparkSession, path: str) -> DataFrame:
    """(movie, user, rating, date) of files that each begin with a line "id:" and go on with "user,rating,date". Files are read whole: each is one movie."""
    files = spark.read.text(path, wholetext=True)
    lines = files.select(F.regexp_extract("value", r"^\s*(\d+):", 1).cast("bigint").alias("movie"), F.explode(F.split("value", r"\r?\n")).alias("line"))
    part = F.split("line", ",")
    return lines.where(F.col("line").rlike(r"^\d+,")).select("movie", part[0].cast("bigint").alias("user"), part[1].cast("double").alias("rating"), F.to_date(part[2]).alias("date"))


def read_query_list(spark: SparkSession, path: str) -> DataFrame:
    """(movie, user) of files in which a line "id:" heads the lines of users that follow. A file is cut at its headings where it is read, so no window orders its lines."""
    parts = spark.read.text(path, wholetext=True).select(F.explode(F.split("value", r"(?m)^(?=\s*\d+:)")).alias("part"))
    rows = parts.select(F.regexp_extract("part", r"^\s*(\d+):", 1).alias("movie"), F.explode(F.split("part", r"\r?\n")).alias("line")).where(F.col("line").rlike(r"^\d+(,|$)") & (F.col("movie") != ""))
    return rows.select(F.col("movie").cast("bigint").alias("movie"), F.split("line", ",")[0].cast("bigint").alias("user"))


def save(df: DataFrame, path: str | None = None, fmt: str = "parquet", mode: str = "errorifexists", partition_by: list[str] | None = None, bucket_by: tuple[int, list[str]] | None = None, table: str | None = None) -> None:
    """A file sink, partitioned if asked; a bucketed table (co-located for later joins); or noop, which only runs the plan."""
    w = df.write.mode("overwrite" if fmt == "noop" else mode).format(fmt)
    if partition_by:
        w = w.partitionBy(*partition_by)
    if bucket_by:
        w.bucketBy(bucket_by[0], *bucket_by[1]).sortBy(*bucket_by[1]).saveAsTable(table)
    elif table:
        w.saveAsTable(table)
    else:
        w.save(*([path] if path else []))
