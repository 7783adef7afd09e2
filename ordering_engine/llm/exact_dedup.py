"""Exact deduplication: group by a 128-bit content hash, compare bytes inside groups, keep one stable id.

The grouping key is (hash, text): Spark compares the bytes of equal hashes, so two texts that
collide are two groups. The partial aggregation folds the copies of a group inside each task
before anything is shuffled, hence a group with a third of all rows costs one row per task.
Rows find their group again by (hash, SHA-256): only small rows are joined, and the join is
one that adaptive execution splits where a key is hot.

Defined results: a null text counts as empty; a null id is a row of its own whose id loses
against every other; repeated rows (same id, same text) get the same answer; an empty table
gives an empty result; other columns are ignored, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import lower_ascii

NORMALISE = {"ascii_lower": lower_ascii, "none": lambda text: text}


def _keyed(docs: DataFrame, id_col: str, text_col: str, normalise: str, content_hash) -> DataFrame:
    text = NORMALISE[normalise](F.coalesce(F.col(text_col), F.lit("")))
    return docs.select(F.col(id_col).alias("_id"), text.alias("_text")).withColumn("_hash", content_hash(F.col("_text")))


def md5_128(text: Column) -> Column:
    return F.unhex(F.md5(text))


def groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min", normalise: str = "ascii_lower", content_hash=md5_128) -> DataFrame:
    """One row per distinct text: ``_hash``, ``text_sha256``, ``keep_id``, ``group_size``."""
    best = {"min": F.min, "max": F.max}[keep]
    rows = _keyed(docs, id_col, text_col, normalise, content_hash)
    found = rows.groupBy("_hash", "_text").agg(best("_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
    return found.select("_hash", F.sha2("_text", 256).alias("text_sha256"), "keep_id", "group_size")


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min", normalise: str = "ascii_lower", content_hash=md5_128) -> DataFrame:
    """One row per input row: id, ``keep_id``, ``group_size``, ``kept``, ``text_sha256``."""
    rows = _keyed(docs, id_col, text_col, normalise, content_hash).select("_id", "_hash", F.sha2("_text", 256).alias("text_sha256"))
    found = groups(docs, id_col, text_col, keep, normalise, content_hash)
    return rows.join(found, ["_hash", "text_sha256"]).select(
        F.col("_id").alias(id_col), "keep_id", "group_size", F.col("_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256"
    )


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min", normalise: str = "ascii_lower") -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns; a repeated row stays once."""
    # The id as text and a null flag: equal keys on both sides, so the duplicates' check below needs no further exchange.
    identity = lambda c: F.struct(F.coalesce(c.cast("string"), F.lit("")).alias("id"), c.isNull().alias("none"))
    found = groups(docs, id_col, text_col, keep, normalise).select(identity(F.col("keep_id")).alias("_row_id"), F.col("_hash").alias("_row_hash"))
    text = NORMALISE[normalise](F.coalesce(F.col(text_col), F.lit("")))
    rows = docs.select(F.struct("*").alias("_doc"), identity(F.col(id_col)).alias("_row_id"), md5_128(text).alias("_row_hash"))
    kept = rows.join(found, ["_row_id", "_row_hash"], "left_semi").dropDuplicates(["_row_id", "_row_hash"])
    return kept.select("_doc.*")


ORACLE_SQL = """
WITH t AS (
  SELECT doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) AS text_sha256
  FROM documents
), g AS (SELECT text_sha256, max(doc_id) AS keep_id, count(*) AS group_size FROM t GROUP BY text_sha256)
SELECT t.doc_id, g.keep_id, g.group_size, t.doc_id = g.keep_id AS kept, t.text_sha256
FROM t JOIN g USING (text_sha256)
"""
