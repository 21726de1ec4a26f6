"""The corpus pipeline: quality rules, exact dedup, near-dedup, source mixing, BPE encoding.

Each stage takes (spark, docs, sf_dir), works on all rows that its predecessor kept, and returns a DataFrame; all but the
last return the columns of ``docs``, whatever their names.  Between stages the rows are written as Parquet and read again.

Decisions apply to rows, not to doc_ids: inside a stage a row is known by ``key``, a struct of its doc_id, its file and its place in the
file, and its columns travel as one struct, so no name of theirs can clash.  Of rows that share a doc_id, or that repeat wholly, dedup
keeps one of each text; rows of null doc_id are ordinary rows, after all others.  Null texts fail the quality rules.  An empty table gives
an empty result.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from compatgraph.llm import bpe, exact_dedup, mixing, near_dedup, quality
from compatgraph.llm.common import documents, materialise

#: No SQL: the quality verdict, MinHash and BPE have no SQL form; tests hold run() against a brute-force version.
ORACLE_SQL = None


def _keyed(docs: DataFrame) -> DataFrame:
    """key, row: each row with what tells it from all others, in an order by doc_id (nulls last).

    File and place are the scan's own, the same whenever and wherever a task runs again; what isn't a scan is written down first.
    """
    for tried in (lambda: docs, lambda: materialise(docs, "stage-rows")):
        try:
            rows = tried()
            place = rows.metadataColumn("_metadata")
            names = [F.col(f"`{c}`") for c in rows.columns]
            key = F.struct(F.col("`doc_id`").isNull().alias("none"), F.coalesce(F.col("`doc_id`"), F.lit(0)).alias("id"), F.xxhash64(place["file_path"]).alias("file"), place["row_index"].alias("place"))
            return rows.select(key.alias("key"), F.struct(*names).alias("row"))
        except AnalysisException:
            continue
    raise ValueError("documents need a Parquet scan, or a form that can be written as Parquet")


def _viewed(keyed: DataFrame) -> DataFrame:
    """doc_id, text for the operators, with the key in the doc_id's place."""
    return keyed.select(F.col("key").alias("doc_id"), F.col("row.text").alias("text"))


def _only(keyed: DataFrame, judged: DataFrame) -> DataFrame:
    """The rows that were kept.  Keys grow with the documents, so both sides are shuffled at every size."""
    kept = materialise(judged.filter("kept").select(F.col("doc_id").alias("key")), "kept-rows")
    return keyed.join(kept.hint("merge"), "key", "left_semi").select("row.*")


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep(docs)


def one_of_each_text(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    keyed = _keyed(docs)
    return _only(keyed, exact_dedup.group_rows(_viewed(keyed)))


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    keyed = _keyed(docs)
    return _only(keyed, near_dedup.near_duplicates(_viewed(keyed)))


def mixed_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as many times as the mix takes it."""
    keyed = _keyed(docs)
    mixed = mixing.mix(keyed.select(F.col("row.doc_id").alias("doc_id"), F.col("row.text").alias("text"), F.col("row.source").alias("source"), "key"), key=F.col("key"))
    times = materialise(mixed.filter("copies > 0").select("key", F.col("copies").cast("int").alias("copies")), "mix-copies")
    return keyed.join(times.hint("merge"), "key").select("row", F.explode(F.sequence(F.lit(1), "copies"))).select("row.*")


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.encode(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, with_ids=False)


STAGES = [
    ("quality rules", good_quality),
    ("exact dedup", one_of_each_text),
    ("MinHash near-dedup", one_of_each_group),
    ("mixing sources", mixed_sources),
    ("byte-level BPE", encoded),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = documents(spark, sf_dir)
    for i, (_, stage) in enumerate(STAGES):
        out = stage(spark, out, sf_dir)
        if i < len(STAGES) - 1:
            out = materialise(out, f"pipeline-{i}")
    return out
