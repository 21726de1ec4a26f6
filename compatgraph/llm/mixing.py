"""Mixing sources to target weights with hash-threshold histograms, in DataFrame operations only.

Each document has a 48-bit hash of its doc_id.  A source's budget beyond whole copies is met by a hash
threshold: documents at or below it are taken once more.  The threshold is found by histograms of the
sizes over 12 bits of the hash at a time; only the boundary bucket is looked into at the next 12 bits,
so no source is ever sorted and no task gets a source's rows.  The cell on the boundary is taken
where that brings the source nearer to its target.

Null texts have size 0.  Null sources are one source, the last.  Null doc_ids share one hash.  Repeated
rows are taken or left together.  An empty table gives an empty result; other columns, whatever their names, are not read.  Where
rows meet their source's numbers in a shuffle, those of a large source are spread over many tasks.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import WORD, heavy, join_spread, materialise

LEVELS, BITS = 4, 12
WEIGHTS, SHARE, MOST = (3, 1, 2), 1.5, 2


def sized(docs: DataFrame, key=None) -> DataFrame:
    """doc_id, [key], src (never null), source, size, h of every document; ``key`` is a column that tells rows apart."""
    source = F.col("`source`")
    return docs.select(
        F.col("`doc_id`"), *([] if key is None else [key.alias("key")]), F.when(source.isNull(), "n").otherwise(F.concat(F.lit("s"), source)).alias("src"), source.alias("source"),
        F.coalesce(F.regexp_count(F.col("`text`"), F.lit(WORD)), F.lit(0)).cast("long").alias("size"),
        F.conv(F.substring(F.md5(F.coalesce(F.col("`doc_id`").cast("string"), F.lit("null"))), 1, 12), 16, 10).cast("long").alias("h"),
    )


def targets(rows: DataFrame, *, weights=WEIGHTS, share=SHARE, most=MOST) -> DataFrame:
    """src, docs, source_size, target: budget shared by weight, each source at most ``most`` times its size, the excess shared again.

    Re-sharing until none is above ends where one rate serves all sources below their cap: with the sources
    by cap over weight, the rate is what the budget leaves after the capped ones, over the weights of the rest.
    """
    sums = rows.groupBy("src", "source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("docs"))
    order = W.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int"))
    ranked = sums.withColumn("w", weight).withColumn("cap", F.col("source_size") * float(most)).withColumn("ratio", F.col("cap") / F.col("w"))
    rise = W.orderBy("ratio", "src")
    before, everything = rise.rowsBetween(W.unboundedPreceding, -1), W.partitionBy(F.lit(1))
    rate = (F.sum("source_size").over(everything) * float(share) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / (F.sum("w").over(everything) - F.coalesce(F.sum("w").over(before), F.lit(0.0)))
    # the first source whose cap is above the rate left for it and all later ones sets the rate
    found = ranked.withColumn("rate", F.when(rate <= F.col("ratio"), rate)).withColumn("rate", F.first("rate", True).over(rise.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)))
    return found.select("src", "docs", "source_size", F.when(F.coalesce(F.col("rate") >= F.col("ratio"), F.lit(True)), F.col("cap")).otherwise(F.col("rate") * F.col("w")).alias("target"))


def thresholds(rows: DataFrame, goals: DataFrame, busy: DataFrame) -> DataFrame:
    """src, docs, source_size, target, copies, below, through: whole copies of every document, and one more where h < below or h = through."""
    copies = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0)
    edge = goals.withColumn("copies", copies.cast("long")).withColumn("need", F.col("target") - F.col("copies") * F.col("source_size"))
    edge = edge.select("src", "need", F.lit(0.0).alias("got"), F.lit(0).cast("long").alias("prefix"))
    for level in range(1, LEVELS + 1):
        rest = BITS * (LEVELS - level)
        cell = F.shiftright("h", rest)
        if level == 1:  # summed before the join: at most 4,096 cells a source
            hist = rows.groupBy("src", cell.alias("cell")).agg(F.sum("size").alias("sum")).join(edge, "src")
        else:
            inside = join_spread(rows, edge, "src", busy).filter(F.shiftright("h", rest + BITS) == F.col("prefix"))
            hist = inside.groupBy("src", cell.alias("cell")).agg(F.sum("size").alias("sum"), F.first("need").alias("need"), F.first("got").alias("got"))
        run = W.partitionBy("src").orderBy("cell")
        hist = hist.withColumn("upto", F.col("got") + F.sum("sum").over(run))
        over = hist.filter(F.col("upto") > F.col("need")).groupBy("src").agg(F.min(F.struct("cell", F.col("upto") - F.col("sum"), "upto", "need")).alias("b"))
        edge = over.select("src", F.col("b.need").alias("need"), F.col("b.col2").alias("got"), F.col("b.cell").alias("prefix"), F.col("b.upto").alias("upto"))
    near = F.col("upto") - F.col("need") < F.col("need") - F.col("got")
    last = edge.select("src", F.col("prefix").alias("below"), F.when(near, F.col("prefix")).alias("through"))
    return goals.withColumn("copies", copies.cast("long")).join(last, "src", "left")


def mix(docs: DataFrame, *, weights=WEIGHTS, share=SHARE, most=MOST, key=None) -> DataFrame:
    """doc_id, size, source_size, target, taken, copies, [key] of every document."""
    rows = materialise(sized(docs, key).drop("source"), "mix-sizes")
    goals = materialise(targets(rows.withColumn("source", F.when(F.col("src") != "n", F.expr("substr(src, 2)"))), weights=weights, share=share, most=most), "mix-targets")
    busy = heavy(goals, "src", "docs")
    edges = materialise(thresholds(rows, goals, busy), "mix-edges")
    # no boundary cell: every document is needed for the budget, or nothing is left of it
    more = F.when(F.col("below").isNull(), F.col("target") > F.col("copies") * F.col("source_size")).otherwise((F.col("h") < F.col("below")) | F.coalesce(F.col("h") == F.col("through"), F.lit(False)))
    times = F.col("copies") + more.cast("long")
    return join_spread(rows, edges, "src", busy).select("doc_id", "size", "source_size", "target", (F.col("size") * times).alias("taken"), times.alias("copies"), *([] if key is None else ["key"]))
