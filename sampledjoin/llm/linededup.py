"""Line de-duplication: lines are exploded to keyed hashes, distinct documents counted by hash, lines over the threshold dropped except in the largest document id, and texts reassembled by position.

Defined cases: a null or empty text is one empty line; rows that share a doc_id are one document for counting, and each
row is reassembled by itself; rows with a null doc_id take no part in the counting and keep all
lines; keys are compared by 128 bits of hash. Other columns pass through unchanged, whatever their names; columns named as the results are replaced by them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The stripped characters, the least length of a key and the least documents.
BLANKS = "\x20\x09\x0a\x0b\x0c\x0d"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
LEAST_LENGTH, LEAST_DOCUMENTS = 20, 3


def key(line: Column) -> Column:
    return F.translate(F.btrim(line, F.lit(BLANKS)), UPPER, LOWER)


def key_hash(k: Column) -> Column:
    return F.struct(F.xxhash64(k).alias("a"), F.xxhash64(F.lit(7), k).alias("b"))


def lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def line_places(docs: DataFrame, least_length: int = LEAST_LENGTH) -> DataFrame:
    """(hash, doc_id, text_hash, pos): where the long keys of each row lie. Stripping alone decides the length, as lower case has as many characters."""
    return (
        docs.where("doc_id is not null").select("doc_id", F.xxhash64("text").alias("text_hash"), F.posexplode(lines(F.col("text"))).alias("pos", "line"))
        .where(F.char_length(F.btrim("line", F.lit(BLANKS))) >= least_length)
        .select(key_hash(key(F.col("line"))).alias("hash"), "doc_id", "text_hash", "pos")
    )


def common_lines(places: DataFrame, least_documents: int = LEAST_DOCUMENTS) -> DataFrame:
    """(hash, keeper): keys of enough documents, and the largest id that holds each; from ``line_places``."""
    return places.select("hash", "doc_id").distinct().groupBy("hash").agg(F.count("*").alias("n"), F.max("doc_id").alias("keeper")).where(F.col("n") >= least_documents).select("hash", "keeper")


def lost_lines(places: DataFrame, common: DataFrame) -> DataFrame:
    """(lost_id, lost_text, lost): for rows that lose lines, these lines' positions."""
    return places.join(common, "hash").where("doc_id <> keeper").groupBy(F.col("doc_id").alias("lost_id"), F.col("text_hash").alias("lost_text")).agg(F.collect_list("pos").alias("lost"))


def _reassembled(docs: DataFrame) -> DataFrame:
    """(row, total, dropped, kept): each row of ``docs`` as a struct, so that no name of its columns meets another, its numbers of lines and its text without the lost ones."""
    from .common import materialise

    places = materialise(line_places(docs), "line-places")  # texts are split once for both uses
    common = materialise(common_lines(places), "common-lines")
    rows = docs.select(F.struct(*(docs[c] for c in docs.columns)).alias("row"))
    text = F.col("row.text")
    both = rows.join(lost_lines(places, common), (F.col("row.doc_id") == F.col("lost_id")) & (F.xxhash64(text) == F.col("lost_text")), "left")
    every = lines(text)
    # positions by difference of sets, which takes time in proportion to a text's lines
    left = F.array_except(F.sequence(F.lit(0), F.size(every) - 1), F.col("lost"))
    kept = F.element_at(F.transform(F.array(every), lambda e: F.array_join(F.transform(left, lambda i: F.element_at(e, i + 1)), "\n")), 1)
    loses = F.col("lost").isNotNull()
    return both.select("row", F.size(every).cast("bigint").alias("total"), F.when(loses, F.size(every) - F.size(left)).otherwise(0).cast("bigint").alias("dropped"), F.when(loses, kept).otherwise(F.coalesce(text, F.lit(""))).alias("kept"))


RESULTS = {"line_total": "total", "line_dropped": "dropped", "line_text": "kept"}


def drop_common_lines(docs: DataFrame) -> DataFrame:
    """``docs`` with line_total, line_dropped and line_text (what is left) beside its columns."""
    return _reassembled(docs).select(*(F.col("row")[c].alias(c) for c in docs.columns if c not in RESULTS), *(F.col(c).alias(name) for name, c in RESULTS.items()))


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return drop_common_lines(docs).select("doc_id", F.col("line_total").alias("n_lines"), F.col("line_dropped").alias("n_dropped"), F.sha2("line_text", 256).alias("kept_sha256"))


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents with common lines dropped from their text; n_chars follows the text."""
    new = {"text": F.col("kept"), "n_chars": F.char_length("kept").cast("bigint")}
    return _reassembled(docs).select(*(new.get(c, F.col("row")[c]).alias(c) for c in docs.columns))


SQL9 = """
WITH l AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos
  FROM documents),
k AS (SELECT doc_id, line, pos,
             translate(trim(line, chr(32)||chr(9)||chr(10)||chr(11)||chr(12)||chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
      FROM l),
c AS (SELECT key, max(doc_id) AS keeper FROM k WHERE length(key) >= 20
      GROUP BY key HAVING count(DISTINCT doc_id) >= 3),
j AS (SELECT k.doc_id, k.pos, k.line, (c.key IS NOT NULL AND c.keeper <> k.doc_id) AS gone
      FROM k LEFT JOIN c ON k.key = c.key)
SELECT doc_id, CAST(count(*) AS BIGINT) AS n_lines,
       CAST(count(*) FILTER (WHERE gone) AS BIGINT) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM j GROUP BY doc_id
"""
