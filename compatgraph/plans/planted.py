"""Planted graphs: exact class sizes, class-pair budgets and degrees on the keys of a table, wired by one join.

Ranks over a class are two-level (range buckets of a 32-bit number, then rows inside a bucket; a bucket of one number is cut again by its
ties), so no task sorts a whole class.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.compat import edge_budget
from .lineage import cut

#: Buckets by the leading bits of a number, and parts of a bucket that holds one number only.
BITS, PARTS = 12, 1 << 12
#: Rows of two numbers that are broadcast at most.
BROADCAST = 500_000


def hashed(*parts) -> F.Column:
    """32 hash bits of parts joined by colons; the same number in any SQL with md5."""
    bits = F.conv(F.substring(F.md5(F.concat_ws(":", *[F.lit(p) if isinstance(p, (str, int)) else p.cast("string") for p in parts])), 1, 8), 16, 10).cast("long")
    return F.coalesce(bits, F.lit(0).cast("long"))  # never null: joins then need no filter that hashes once more


def ranked(df: DataFrame, keys: list[str], u: str, ties: list[str], name: str, dense: str | None = None) -> DataFrame:
    """``name``: rank from 1 within ``keys`` by the 32-bit column ``u`` and ``ties``.  Bucket counts give each bucket's base.

    ``dense`` names a first tie that numbers the rows of a key from 1: with it, buckets where all rows have one ``u`` are cut into parts.
    """
    own = df.withColumn("_b", F.shiftright(F.col(u), 32 - BITS).cast("int"))
    inside, part = ["_b"], F.lit(0)
    counted = own.groupBy(*keys, "_b").agg(F.count(F.lit(1)).alias("_n"), F.min(u).alias("_low"), F.max(u).alias("_high"), *([F.max(dense).alias("_top")] if dense else []))
    if dense:
        inside = ["_b", "_p"]
        part = F.when(F.col("_low") == F.col("_high"), F.floor(F.col(dense) * PARTS / (F.col("_top") + 1))).otherwise(0).cast("int")
        own = own.join(counted.drop("_n"), [*keys, "_b"]).withColumn("_p", part).drop("_low", "_high", "_top")
        counted = own.groupBy(*keys, "_b", "_p").agg(F.count(F.lit(1)).alias("_n"))
    base = counted.withColumn("_base", F.coalesce(F.sum("_n").over(W.partitionBy(*keys).orderBy(*inside)) - F.col("_n"), F.lit(0))).select(*keys, *inside, "_base")
    # buckets first: a sort compares by its first column, and keys are few; the join then takes the window's order as it is
    order = W.partitionBy(*inside, *keys).orderBy(u, *ties)
    return own.withColumn("_r", F.row_number().over(order)).join(base, [*inside, *keys]).withColumn(name, F.col("_r") + F.col("_base")).drop(*inside, "_r", "_base")


def class_sizes(n: int, alpha) -> list[int]:
    exact = np.asarray(alpha, float) * n
    sizes = np.floor(exact + 1e-9).astype(int)
    for c in sorted(range(len(sizes)), key=lambda c: (-(exact[c] - sizes[c]), c))[: n - sizes.sum()]:
        sizes[c] += 1
    return sizes.tolist()


def cut_by(bounds: list[int], rank: F.Column, values: list[int] | None = None) -> F.Column:
    """Index of the block that a rank from 1 falls into, for blocks of the given sizes, or the block's value."""
    out, upto = None, 0
    for i, size in enumerate(bounds):
        upto += size
        value = F.lit(i if values is None else int(values[i]))
        out = F.when(rank <= upto, value) if out is None else out.when(rank <= upto, value)
    return out


def assign_classes(keys: DataFrame, alpha, seed: int = 1, n: int | None = None) -> DataFrame:
    """node, cls: a random order cut at the class sizes."""
    n = keys.count() if n is None else n
    own = ranked(keys.select("node", hashed(seed, F.col("node")).alias("u"), F.lit(0).alias("g")), ["g"], "u", ["node"], "r")
    return own.select("node", cut_by(class_sizes(n, alpha), F.col("r")).cast("int").alias("cls"))


def assign_degrees(classes: DataFrame, totals: list[int], delta: float = 0.3, seed: int | str = 1) -> DataFrame:
    """node, cls, d: integer degrees in proportion to rank^-delta (0: equal), with the given total of each class."""
    own = cut(ranked(classes.withColumn("u", hashed(f"d{seed}", F.col("node"))), ["cls"], "u", ["node"], "r").withColumn("share", F.pow("r", F.lit(-delta))))
    total = F.coalesce(*[F.when(F.col("cls") == c, F.lit(int(t))) for c, t in enumerate(totals)])
    sums = own.groupBy("cls").agg(F.sum("share").alias("all"))
    own = own.join(sums, "cls").withColumn("exact", F.round(total * F.col("share") / F.col("all"), 9)).withColumn("d", F.floor("exact").cast("long"))
    rest = own.groupBy("cls").agg(F.sum("d").alias("given")).select("cls", (total - F.col("given")).alias("rest"))
    own = own.join(rest, "cls").withColumn("v", F.lit(2**32 - 1) - F.floor((F.col("exact") - F.col("d")) * F.lit(2.0**32)).cast("long"))
    own = ranked(own.withColumn("v", F.greatest("v", F.lit(0))), ["cls"], "v", ["r"], "q", "r")  # equal degrees tie everywhere
    return own.select("node", "cls", (F.col("d") + (F.col("q") <= F.col("rest")).cast("long")).alias("d"))


def spread(df: DataFrame) -> DataFrame:
    """``df`` by node in as many parts as there are cores, or shuffles have: few rows that become many should not be in few parts."""
    spark = df.sparkSession
    return df.repartition(max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions"))), "node")


def wire(out_deg: DataFrame, in_deg: DataFrame, M: np.ndarray, seed: int = 1) -> DataFrame:
    """arcs src, dst, c, d: each class's stubs in random order are cut by the budgets and joined place by place."""
    def stubs(deg: DataFrame, tag: str) -> DataFrame:
        s = deg.filter("d > 0").select(F.col("node"), "cls", F.explode(F.sequence(F.lit(1), F.col("d").cast("int"))).alias("i"))
        return ranked(s.withColumn("u", hashed(f"{tag}{seed}", F.col("node"), F.col("i"))), ["cls"], "u", ["node", "i"], "r")

    # a place of all arcs, class pair after class pair: stubs of sending classes are in its order, those of receiving ones are moved block by
    # block; stubs beyond a budget meet none.  No part of it is null to the planner: a join would test for that first, by working out the whole column once more
    k, rows, flat = len(M), M.sum(1), M.reshape(-1)
    first, own = (np.cumsum(flat) - flat).reshape(M.shape).T, np.cumsum(M.T, 1) - M.T
    by_class = lambda f, none=0: F.coalesce(*[F.when(F.col("cls") == c, f(c)) for c in range(k)], F.lit(none))
    a, b = stubs(out_deg, "o"), stubs(in_deg, "i")
    a = a.select(F.col("node").alias("src"), F.col("cls").alias("c"), by_class(lambda c: cut_by(M[c].tolist(), F.col("r"))).alias("d"), (F.col("r") + by_class(lambda c: cut_by(M[c].tolist(), F.col("r"), [rows[:c].sum()] * k), -(1 << 61))).alias("p"))
    b = b.select(F.col("node").alias("dst"), (F.col("r") + by_class(lambda d: cut_by(M.T[d].tolist(), F.col("r"), (first - own)[d].tolist()), -(1 << 62))).alias("p"))
    return a.join(b, "p").select("src", "dst", "c", "d")


def flaws(arcs: DataFrame) -> DataFrame:
    """``bad``: self-loops, repeated arcs and reversed arcs (but the first of a pair)."""
    u, v = F.least("src", "dst"), F.greatest("src", "dst")
    order = W.partitionBy(u, v).orderBy("src", "dst", "c", "d")
    return arcs.withColumn("bad", (F.col("src") == F.col("dst")) | (F.row_number().over(order) > 1))


def repair(arcs: DataFrame, rounds: int = 40, seed: int = 1) -> tuple[DataFrame, int]:
    """Swap the targets of flawed arcs with others of their class pair until none is flawed; marginals stay.  Also the number left.

    One pass over all arcs finds the flaws.  From there on only flawed arcs, the arcs drawn to swap with them, and what meets these
    is moved: the sound arcs stay where they are, less those whose hash falls under a round's share.  What comes back is a checkpoint.
    """
    all_arcs = flaws(arcs).persist()  # columns in memory: each round reads them all
    sound, bad = all_arcs.filter("not bad").drop("bad"), all_arcs.filter("bad").drop("bad")
    by_pair = lambda df: df.groupBy("c", "d", "bad").agg(F.count(F.lit(1)).alias("n")).collect()  # noqa: E731  twice k x k numbers
    found = by_pair(all_arcs)
    size, flawed = ({(r.c, r.d): r.n for r in found if r.bad == x} for x in (False, True))
    pair = [F.least("src", "dst").alias("x"), F.greatest("src", "dst").alias("y")]
    for i in range(rounds):
        if not flawed:
            break
        share = None
        for (c, d), n in flawed.items():
            most = int(min(2**32, (3 * n + 1) * 2**32 / max(1, size.get((c, d), 0))))
            share = (F.when if share is None else share.when)((F.col("c") == c) & (F.col("d") == d), F.lit(most))
        draw = sound.withColumn("u", hashed(f"s{seed}.{i}", F.col("src"), F.col("dst"))).withColumn("most", F.coalesce(share, F.lit(0)))
        # at most about four arcs a flaw: they and their pairs are broadcast where that is few, and shuffled else
        few = 8 * sum(flawed.values()) <= BROADCAST
        drawn = draw.filter("u < most").drop("most")
        drawn = cut(drawn) if few else drawn
        pool = drawn.unionByName(bad.withColumn("u", hashed(f"b{seed}.{i}", F.col("src"), F.col("dst"))))
        order = W.partitionBy("c", "d").orderBy("u", "src", "dst")
        ring = order.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
        # the last of a block takes the first's target; equal rows of the pool are rows of their own
        moved = flaws(pool.withColumn("dst", F.coalesce(F.lead("dst").over(order), F.first("dst").over(ring))).drop("u")).select("*", *pair).persist()
        # sound arcs are unlike each other, so what was not drawn is told by its ends: no later pass hashes all arcs for this round again
        sound = sound.join(F.broadcast(drawn.select("src", "dst")), ["src", "dst"], "left_anti").select(*sound.columns) if few else draw.filter("u >= most").drop("u", "most")
        near = moved.select("x", "y").distinct()
        met = sound.select(*pair).join(F.broadcast(near) if few else near, ["x", "y"], "left_semi").distinct().withColumn("met", F.lit(True))
        told = cut(moved.join(met, ["x", "y"], "left").select("src", "dst", "c", "d", (F.col("bad") | F.coalesce("met", F.lit(False))).alias("bad")))
        sound, bad = sound.unionByName(told.filter("not bad").drop("bad")), told.filter("bad").drop("bad")
        moved.unpersist()
        before, flawed = flawed, {(r.c, r.d): r.n for r in by_pair(told) if r.bad}
        size = {p: size.get(p, 0) + before.get(p, 0) - flawed.get(p, 0) for p in {*size, *before}}
        if i % 6 == 5:  # each round adds a filter and a union
            sound = cut(sound)
    out = cut(sound.unionByName(bad))
    all_arcs.unpersist()
    return out, sum(flawed.values())


def planted_graph(keys: DataFrame, K: np.ndarray, degree: float, *, alpha=None, delta: float = 0.3, seed: int = 1, directed: bool = False, rounds: int = 40, independent: bool = False) -> tuple[DataFrame, DataFrame, np.ndarray]:
    """edges, labels, budget: an undirected graph (or arcs) over ``keys(node)`` whose class-pair counts are in proportion to K exactly.

    In- and out-degrees of a node are correlated (one order of the nodes for both) or ``independent``.  Raises where no graph without
    loops, repeated and reversed arcs was found within ``rounds``: blocks that are too dense have none.
    """
    k = len(K)
    alpha = alpha if alpha is not None else [1 / k] * k
    n = keys.count()
    labels = cut(assign_classes(keys, alpha, seed, n))
    m = int(round(n * degree / (1 if directed else 2)))
    M = edge_budget(m, K)
    # a row a node, kept: the stubs, their counts and their join would each rank the nodes again
    starts = cut(spread(assign_degrees(labels, M.sum(1).tolist(), delta, seed)))
    same = not independent and M.sum(0).tolist() == M.sum(1).tolist()
    ends = starts if same else cut(spread(assign_degrees(labels, M.sum(0).tolist(), delta, f"{seed}in" if independent else seed)))
    arcs, left = repair(wire(starts, ends, M, seed), rounds, seed)
    if left:
        raise ValueError(f"{left} of {m} arcs are still loops, repeated or reversed after {rounds} rounds: give more rounds or a lower degree")
    edges = arcs.select("src", "dst", F.lit(1.0).alias("w"))
    if not directed:
        edges = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    return edges, labels, M


def planted_check(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """c, d, n: class-pair counts, to hold against the budget."""
    a, b = labels.select(F.col("node").alias("src"), F.col("cls").alias("c")), labels.select(F.col("node").alias("dst"), F.col("cls").alias("d"))
    return edges.join(a, "src").join(b, "dst").groupBy("c", "d").agg(F.count(F.lit(1)).alias("n"))


def block_model(keys: DataFrame, labels: DataFrame, K: np.ndarray, degree: float, seed: int = 1) -> DataFrame:
    """Contrast with expected, not exact, properties: each stub draws the class of its end by K and a node of it at random."""
    k = len(K)
    n = keys.count()
    size = labels.groupBy("cls").agg(F.count(F.lit(1)).alias("n_cls"))
    numbered = ranked(labels.withColumn("u", hashed(f"b{seed}", F.col("node"))), ["cls"], "u", ["node"], "r").select(F.col("node").alias("dst"), F.col("cls").alias("d"), "r")
    stub = labels.select(F.col("node").alias("src"), "cls", F.explode(F.sequence(F.lit(1), F.lit(max(1, round(degree / 2))))).alias("i"))
    u, v = hashed(f"x{seed}", F.col("src"), F.col("i")) / F.lit(2.0**32), hashed(f"y{seed}", F.col("src"), F.col("i")) / F.lit(2.0**32)
    cum = np.cumsum(K / K.sum(1, keepdims=True), 1)
    d = F.coalesce(*[F.when((F.col("cls") == c) & (u < float(cum[c, x]) if x < k - 1 else F.col("cls") == c), F.lit(x)) for c in range(k) for x in range(k)])
    drawn = stub.withColumn("d", d).join(size.withColumnRenamed("cls", "d"), "d").withColumn("r", F.floor(v * F.col("n_cls")).cast("long") + 1)
    return drawn.join(numbered, ["d", "r"]).filter("src <> dst").select("src", "dst", F.lit(1.0).alias("w")).distinct() if n else drawn.select("src", F.col("src").alias("dst"), F.lit(1.0).alias("w"))


def degree_histogram(edges: DataFrame, labels: DataFrame | None = None) -> DataFrame:
    """[cls], deg, n: how many nodes have each degree, by class where labels are given."""
    deg = edges.groupBy(F.col("src").alias("node")).agg(F.count(F.lit(1)).alias("deg"))
    by = [] if labels is None else ["cls"]
    return (deg if labels is None else deg.join(labels, "node")).groupBy(*by, "deg").agg(F.count(F.lit(1)).alias("n"))


def clustered_adjacency(edges: DataFrame, labels: DataFrame, size: int) -> DataFrame:
    """row_bin, col_bin, n: edges between bins of ``size`` nodes, with nodes renumbered by class and hash."""
    counts = labels.groupBy("cls").agg(F.count(F.lit(1)).alias("n"))
    before = counts.withColumn("before", F.sum("n").over(W.orderBy("cls")) - F.col("n")).drop("n")  # one row a class
    own = ranked(labels.withColumn("u", hashed("o", F.col("node"))), ["cls"], "u", ["node"], "r").join(F.broadcast(before), "cls")
    bins = own.select("node", F.floor((F.col("r") - 1 + F.col("before")) / size).cast("int").alias("bin"))
    a, b = bins.toDF("src", "row_bin"), bins.toDF("dst", "col_bin")
    return edges.join(a, "src").join(b, "dst").groupBy("row_bin", "col_bin").agg(F.count(F.lit(1)).alias("n"))


def coloring_conflicts(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """conflicts: edges whose ends share a class.  0 means a proper colouring, which is what fits ``coloring_compat`` exactly."""
    a, b = labels.toDF("src", "c"), labels.toDF("dst", "d")
    return edges.filter("src < dst").join(a, "src").join(b, "dst").agg(F.coalesce(F.sum((F.col("c") == F.col("d")).cast("long")), F.lit(0)).alias("conflicts"))
