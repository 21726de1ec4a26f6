"""Exact deduplication by skew-safe combining.

Texts equal after each run of ASCII white space becomes one space form a group; of the rows of the smallest doc_id one
stays.  Stages: (1) within each task, rows are combined by digest and full text;
(2) those local winners meet in groups of digest, salt and full text, so one text held by a third of
all rows is spread over ``salts`` tasks; (3) the salts' winners are combined by digest and full text.
Every stage groups by the text itself, so two texts of one digest are never merged.  Rows find their
group by digest alone where it belongs to one text, and by digest and text where it doesn't; in that join too the rows
of a large group are spread over many tasks.

Null texts count as empty.  Null doc_ids sort after all others.  Of repeated rows, and of several rows of a group that share the smallest
doc_id, one stays: a row number, fixed by writing it down, tells them apart.  An empty table gives an empty result; very long
texts are compared whole; other columns, whatever their names, are not read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import heavy, join_spread, materialise

SALTS = 16


def normalised(text):
    return F.regexp_replace(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+", " ")


def _first_rows(rows: DataFrame, *keys: str) -> DataFrame:
    """keys, keep_row: the number of the row that stays, combined in the map tasks."""
    return rows.groupBy(*keys).agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row")).alias("first")).select(*keys, F.col("first.row").alias("keep_row"))


def group_rows(docs: DataFrame, *, salts: int = SALTS, digest=lambda text: F.sha2(text, 256)) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 of every row of (doc_id, text); doc_id may have any type with an order."""
    rows = docs.select(F.col("`doc_id`"), normalised(F.col("`text`")).alias("norm")).withColumn("digest", digest(F.col("norm")))
    local = rows.withColumn("salt", F.pmod(F.spark_partition_id(), F.lit(salts)))
    salted = local.groupBy("digest", "salt", "norm").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("n"))
    groups = salted.groupBy("digest", "norm").agg(F.min("first").alias("keep_id"), F.sum("n").alias("group_size"))
    # one row a digest: how many texts share it (the texts themselves stay behind)
    table = groups.groupBy("digest").agg(F.count(F.lit(1)).alias("texts"), F.min("keep_id").alias("keep_id"), F.sum("group_size").alias("group_size"))
    table = materialise(table, "dedup-groups")
    ids = materialise(rows.select("doc_id", "digest", F.monotonically_increasing_id().alias("row")), "dedup-rows")
    single = table.filter("texts = 1").drop("texts").join(_first_rows(ids, "digest"), "digest")
    out = join_spread(ids, single, "digest", heavy(table, "digest", "group_size"))
    clashing = table.filter("texts > 1").select("digest")
    if not clashing.isEmpty():
        several = materialise(rows.join(clashing, "digest").withColumn("row", F.monotonically_increasing_id()), "dedup-clashes")
        texts = groups.join(clashing, "digest", "left_semi").join(_first_rows(several, "digest", "norm"), ["digest", "norm"])
        out = out.unionByName(several.join(texts, ["digest", "norm"]).drop("norm"))
    return out.select("doc_id", "keep_id", "group_size", (F.col("row") == F.col("keep_row")).alias("kept"), F.col("digest").alias("text_sha256"))
