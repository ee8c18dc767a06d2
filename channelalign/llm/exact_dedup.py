"""Exact duplicates by content hash, with bytes compared inside groups. DataFrame functions only."""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed value: the characters that do not count when texts are compared.
IGNORED = " \t\n\x0b\x0c\r"
_SHIFT = Decimal(10**20)  # above the range of a 64-bit id


def normalised(text: Column) -> Column:
    """The text without the ignored characters; null counts as empty."""
    return F.translate(F.coalesce(text, F.lit("")), IGNORED, "")


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256.

    Rows form a group when their normalised texts are the same bytes: they are grouped by (128-bit hash, text
    itself), so two texts that only share a hash stay apart. Map-side partial aggregation folds the copies within
    a partition before anything moves, so a group that holds a third of all rows reaches a reducer as one row per
    task. Each row then looks its group up by (MD5, SHA-256, length); AQE may split that join where one group is
    hot. In a group the row with the most code points in its original text stays, then the one of the smallest id.
    Null ids never win over others and a repeated row with the winner's id is kept only if it is as long as the
    winner; exact repeats of the winning row (same id, same length) are all marked kept. Empty tables give no rows.
    """
    body = normalised(F.col(text_col))
    keyed = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        F.length(F.coalesce(F.col(text_col), F.lit(""))).cast("long").alias("_n"),
        body.alias("_body"),
    ).withColumns({"_md5": F.md5("_body"), "_sha": F.sha2("_body", 256), "_len": F.octet_length("_body")})
    rank = F.col("_n").cast("decimal(38,0)") * F.lit(_SHIFT) - F.coalesce(F.col("doc_id"), F.lit(2**63 - 1)).cast("decimal(38,0)")
    groups = keyed.groupBy("_md5", "_sha", "_len", "_body").agg(
        F.max(rank.cast("decimal(38,0)")).alias("_best"), F.max("_n").alias("_most"), F.count(F.lit(1)).alias("group_size")
    )
    groups = groups.select(
        "_md5", "_sha", "_len", "group_size", F.col("_most").alias("_keep_n"),
        (F.col("_most").cast("decimal(38,0)") * F.lit(_SHIFT) - F.col("_best")).cast("long").alias("keep_id"),
    )
    found = keyed.drop("_body").join(groups, ["_md5", "_sha", "_len"])
    mine = F.coalesce(F.col("doc_id"), F.lit(2**63 - 1)) == F.col("keep_id")
    return found.select(
        "doc_id",
        F.when(F.col("keep_id") != 2**63 - 1, F.col("keep_id")).alias("keep_id"),
        "group_size",
        (mine & (F.col("_n") == F.col("_keep_n"))).alias("kept"),
        F.col("_sha").alias("text_sha256"),
    )


SQL = r"""
WITH t AS (SELECT doc_id, length(coalesce(text, '')) AS n, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') AS body FROM documents),
g AS (SELECT body, arg_min(doc_id, (-n, doc_id)) AS keep_id, count(*) AS group_size FROM t GROUP BY body)
SELECT t.doc_id, g.keep_id, g.group_size, t.doc_id = g.keep_id AS kept, sha256(t.body) AS text_sha256
FROM t JOIN g ON t.body = g.body
"""
