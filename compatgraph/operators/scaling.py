"""Degrees, degree scaling, clamping and the echo diagonal.  Row i of a matrix is the set of edges with ``src = i``."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

RAW, ROW, COL, SYM = (0.0, 0.0), (1.0, 0.0), (0.0, 1.0), (0.5, 0.5)


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("src").alias("node")).agg(F.sum("w").alias("deg"))


def scale_edges(edges: DataFrame, alpha: float, beta: float) -> DataFrame:
    """deg_src^-alpha * w * deg_dst^-beta; a side of exponent 0 is not joined."""
    out = edges
    for side, power in (("src", alpha), ("dst", beta)):
        if power:
            deg = degrees(edges).withColumnRenamed("node", side)
            out = out.join(deg, side).withColumn("w", F.col("w") * F.pow("deg", F.lit(-power))).drop("deg")
    return out.select("src", "dst", "w")


def clamp_edges(edges: DataFrame, seeds: DataFrame, gamma: float | None = 1.0) -> DataFrame:
    """Weaken the rows of seeds by ``1 - gamma``; with ``gamma=None`` by each seed's own column ``g``."""
    if gamma == 0:
        return edges
    if gamma == 1:
        return edges.join(seeds.select(F.col("node").alias("src")).distinct(), "src", "left_anti")
    own = seeds.select(F.col("node").alias("src"), (F.col("g") if gamma is None else F.lit(gamma)).alias("g"))
    return edges.join(own, "src", "left").select("src", "dst", (F.col("w") * (1 - F.coalesce("g", F.lit(0.0)))).alias("w"))


def echo_diagonal(edges: DataFrame) -> DataFrame:
    """node, q: sum over neighbours of P_ij * P_ji."""
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("w").alias("v"))
    return edges.join(back, ["src", "dst"]).groupBy(F.col("src").alias("node")).agg(F.sum(F.col("w") * F.col("v")).alias("q"))


def echo_diagonal_closed(edges: DataFrame, seeds: DataFrame, alpha: float, beta: float, gamma: float = 0.0) -> DataFrame:
    """The echo diagonal of a scaled and clamped matrix without joining edges to edges.

    q_i = g_i deg_i^-(alpha+beta) sum_j w_ij^2 g_j deg_j^-(alpha+beta) with g = 1 - gamma on seeds and 1 elsewhere: one factor a node, sent
    along the squared weights of a symmetric graph.
    """
    factor = degrees(edges).join(seeds.select("node", F.lit(1.0 - gamma).alias("g")).distinct(), "node", "left")
    factor = factor.select("node", (F.coalesce("g", F.lit(1.0)) * F.pow("deg", F.lit(-(alpha + beta)))).alias("g"))
    sums = edges.join(factor.withColumnRenamed("node", "dst"), "dst").groupBy(F.col("src").alias("node")).agg(F.sum(F.col("w") * F.col("w") * F.col("g")).alias("q"))
    return sums.join(factor, "node").select("node", (F.col("q") * F.col("g")).alias("q")).filter("q <> 0")
